"""Table functions."""


class BlocksOf:
    """The spans of the blocks of a bucket of n rows."""

    def eval(self, bucket: int, n: int, b: int):
        for i in range(0, n, b):
            yield bucket, i, min(n, i + b)
