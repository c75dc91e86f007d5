"""Buckets of rows by splitters: the branch-free walk through an implicit tree, and other forms of the same function."""

from __future__ import annotations

import json
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..plans.keys import KeySpec, quoted
from ..plans.sampling import SplitterSet

#: Splitters beyond which range joins take over from expressions; a driver list of them is small either way.
BACKENDS = ("chained", "case", "hof", "arrow", "rangejoin")


_NUMPY = {T.DoubleType(): "float64", T.FloatType(): "float32", T.LongType(): "int64", T.IntegerType(): "int32", T.ShortType(): "int16"}


def literal_array(values: list, kind: T.DataType) -> Column:
    """An array constant; of most types as one node of the plan, so that planning time doesn't grow with it."""
    if kind in _NUMPY and values and all(v is not None for v in values):
        return F.lit(np.array(values, dtype=_NUMPY[kind]))
    if values and (kind in (T.StringType(), T.DateType()) or isinstance(kind, T.DecimalType)):
        text = F.from_json(F.lit(json.dumps([None if v is None else str(v) for v in values])), "array<string>")
        return text if kind == T.StringType() else text.cast(T.ArrayType(kind))
    return F.array(*[F.lit(v).cast(kind) for v in values])


@dataclass(frozen=True)
class SplitterTree:
    """Splitters in the order of a complete binary search tree, and what the columns' types are."""

    keys: KeySpec
    splitters: SplitterSet
    types: tuple[T.DataType, ...]

    @classmethod
    def build(cls, df: DataFrame, keys, splitters: SplitterSet) -> SplitterTree:
        spec = KeySpec.of(keys)
        return cls(spec, splitters, tuple(df.schema[n].dataType for n in spec.names))

    @property
    def buckets(self) -> int:
        return len(self.splitters) + 1

    @property
    def depth(self) -> int:
        return max(0, (self.buckets - 1).bit_length())

    def heap(self) -> list[tuple]:
        """Node i has its children at 2i and 2i + 1; node 0 is unused.  Missing splitters are the largest one again."""
        leaves = 2**self.depth
        full = [*self.splitters.values, *[self.splitters.values[-1]] * (leaves - 1 - len(self.splitters))]
        out: list[tuple] = [full[0]] * leaves
        for level in range(self.depth):
            first, stride = 2**level, leaves >> level
            for j in range(first):
                out[first + j] = full[j * stride + stride // 2 - 1]
        return out

    def _columns(self, rows: list[tuple]) -> list[Column]:
        return [literal_array([r[j] for r in rows], t) for j, t in enumerate(self.types)]

    def _values(self, row: tuple) -> list[Column]:
        return [F.lit(v).cast(t) for v, t in zip(row, self.types)]

    def with_bucket(self, df: DataFrame, out: str = "bucket", method: str = "chained") -> DataFrame:
        """df and the number of splitters that don't come after each row."""
        if not len(self.splitters):
            return df.withColumn(out, F.lit(0))
        return getattr(self, f"_{method}")(df, out)

    def _chained(self, df: DataFrame, out: str) -> DataFrame:
        arrays = self._columns(self.heap())
        nulls = [any(v[j] is None for v in self.splitters.values) for j in range(len(self.types))]
        # one projection a level, all in one call: each step names the one before
        steps = [*[a.alias(f"_tree_{j}") for j, a in enumerate(arrays)], F.lit(1).alias("_walk_0")]
        for level in range(self.depth):
            nodes = [f"get(_tree_{j}, _walk_{level})" for j in range(len(arrays))]
            steps.append(F.expr(f"_walk_{level} * 2 + cast(not {self.keys.before_sql(nodes, nulls)} as int) as _walk_{level + 1}"))
        # padding repeats the largest splitter, so that its rows end in the last leaf
        bucket = F.expr(f"least(_walk_{self.depth} - {2**self.depth}, {self.buckets - 1})").alias(out)
        kept = [quoted(c) for c in df.columns if c != out]
        return df.select(*kept, *steps, bucket).select(*kept, out)

    def _case(self, df: DataFrame, out: str) -> DataFrame:
        values = self.splitters.values

        def node(lo: int, hi: int) -> Column:
            if lo == hi:
                return F.lit(lo)
            mid = (lo + hi) // 2
            return F.when(self.keys.before(self._values(values[mid])), node(lo, mid)).otherwise(node(mid + 1, hi))

        return df.withColumn(out, node(0, len(values)))

    def _hof(self, df: DataFrame, out: str) -> DataFrame:
        rows = F.arrays_zip(*[a.alias(f"s{j}") for j, a in enumerate(self._columns(list(self.splitters.values)))])
        count = F.aggregate(rows, F.lit(0), lambda n, s: n + (~self.keys.before([s[f"s{j}"] for j in range(len(self.types))])).cast("int"))
        return df.withColumn(out, count)

    def _arrow(self, df: DataFrame, out: str) -> DataFrame:
        if len(self.types) != 1 or not self.keys.keys[0].asc:
            raise ValueError("the Arrow form takes one ascending key")
        cuts = np.array([v[0] for v in self.splitters.values])

        @F.pandas_udf("int")
        def place(x: pd.Series) -> pd.Series:
            return pd.Series(np.where(x.isna(), 0, np.searchsorted(cuts, x.to_numpy(), side="right")).astype("int32"))

        return df.withColumn(out, place(F.col(self.keys.names[0])))

    def _rangejoin(self, df: DataFrame, out: str) -> DataFrame:
        """A broadcast table of half-open splitter intervals, at most as many rows as buckets."""
        name, values = self.keys.names[0], [v[0] for v in self.splitters.values]
        if len(self.types) != 1 or not self.keys.keys[0].asc:
            raise ValueError("the range join takes one ascending key")
        rows = list(zip(range(self.buckets), [None, *values], [*values, None]))
        t = df.sparkSession.createDataFrame(rows, T.StructType([T.StructField(out, T.IntegerType()), T.StructField("_lo", self.types[0]), T.StructField("_hi", self.types[0])]))
        c = F.col(name)
        inside = (F.col("_lo").isNull() | (c >= F.col("_lo"))) & (F.col("_hi").isNull() | (c < F.col("_hi")))
        return df.join(F.broadcast(t), inside | (c.isNull() & F.col("_lo").isNull())).drop("_lo", "_hi")

    def inside(self, bucket: int, open_: bool = False) -> Column:
        """Whether a row is in one bucket (open_: and no equal of its lower splitter), by two comparisons that filters push down."""
        values, out = self.splitters.values, F.lit(True)
        if bucket > 0:
            out = ~self.keys.before(self._values(values[bucket - 1]))
            out = out & ~self.keys.same(self._values(values[bucket - 1])) if open_ else out
        return out & self.keys.before(self._values(values[bucket])) if bucket < len(values) else out

    def with_class(self, df: DataFrame, out: str = "cls", bucket: str = "bucket") -> DataFrame:
        """Even classes are open intervals, odd ones hold the rows that equal a splitter; one comparison more."""
        b = quoted(bucket)
        if not len(self.splitters):
            return df.withColumn(out, F.expr(f"{b} * 2"))
        arrays = self._columns(list(self.splitters.values))
        equal = self.keys.same_sql([f"get(_splitter_{j}, {b} - 1)" for j in range(len(arrays))])
        kept = [quoted(c) for c in df.columns if c != out]
        cls = F.expr(f"{b} * 2 - cast({b} > 0 and {equal} as int)").alias(out)
        return df.select(*kept, *[a.alias(f"_splitter_{j}") for j, a in enumerate(arrays)], cls).select(*kept, out)
