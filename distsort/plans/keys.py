"""Sort keys: which columns, in which direction, and where their nulls go."""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass
from functools import total_ordering

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T


_PLAIN = ("double", "float", "long", "integer", "short", "byte", "string", "date", "timestamp", "timestamp_ntz", "decimal", "boolean", "binary")


@total_ordering
class Descending:
    """A value that sorts the other way round."""

    __slots__ = ("value",)

    def __init__(self, value) -> None:
        self.value = value

    def __lt__(self, other) -> bool:
        return other.value < self.value

    def __eq__(self, other) -> bool:
        return self.value == other.value

    def __hash__(self) -> int:
        return hash(self.value)


def quoted(name: str) -> str:
    return "`" + name.replace("`", "``") + "`"


@dataclass(frozen=True)
class SortKey:
    name: str
    asc: bool = True
    nulls_first: bool | None = None  # None: as Spark does, first if ascending

    @property
    def first(self) -> bool:
        return self.asc if self.nulls_first is None else self.nulls_first

    def order(self) -> Column:
        c = F.col(self.name)
        if self.asc:
            return c.asc_nulls_first() if self.first else c.asc_nulls_last()
        return c.desc_nulls_first() if self.first else c.desc_nulls_last()

    def plain(self, v) -> tuple:
        """What Python compares as Spark compares v: nulls by their place, NaN above all numbers."""
        if v is None:
            return (0 if self.first else 2,)
        nan = isinstance(v, float) and v != v
        own = (nan, 0.0 if nan else v) if isinstance(v, float) else v
        return 1, own if self.asc else Descending(own)

    def before(self, v: Column, nullable: bool = True) -> Column:
        """Whether the row sorts strictly before the value v, which may be null only if nullable; never null itself."""
        c = F.col(self.name)
        less = F.coalesce(c < v if self.asc else c > v, F.lit(self.first))
        if not nullable:
            return less
        return F.when(v.isNull(), F.lit(False) if self.first else c.isNotNull()).otherwise(less)


@dataclass(frozen=True)
class KeySpec:
    keys: tuple[SortKey, ...]

    @classmethod
    def of(cls, keys: KeySpec | Iterable[str | SortKey] | str) -> KeySpec:
        """Names, `-name` for descending, or SortKeys."""
        if isinstance(keys, KeySpec):
            return keys
        keys = [keys] if isinstance(keys, (str, SortKey)) else keys
        return cls(tuple(k if isinstance(k, SortKey) else SortKey(k.removeprefix("-"), not k.startswith("-")) for k in keys))

    @property
    def names(self) -> list[str]:
        return [k.name for k in self.keys]

    def order(self) -> list[Column]:
        return [k.order() for k in self.keys]

    def plain(self, row: tuple) -> tuple:
        """A row of key values as Python's sort has to see it."""
        return tuple(k.plain(v) for k, v in zip(self.keys, row))

    def plainly_ordered(self, df: DataFrame) -> bool:
        """Whether Python compares the values of all keys as Spark does: numbers, dates, and strings by code points."""
        return all(df.schema[k.name].dataType.typeName() in _PLAIN and getattr(df.schema[k.name].dataType, "collation", "UTF8_BINARY") == "UTF8_BINARY" for k in self.keys)

    def before(self, values: list[Column], nullable: list[bool] | None = None) -> Column:
        """Lexicographically: whether the row sorts strictly before the tuple of values; nullable: which of them may be null."""
        out = None
        for k, v, n in reversed(list(zip(self.keys, values, nullable or [True] * len(values)))):
            less = k.before(v, n)
            same = F.col(k.name).eqNullSafe(v) if n else F.coalesce(F.col(k.name) == v, F.lit(False))
            out = less if out is None else less | (same & out)
        return out

    def before_sql(self, values: list[str], nullable: list[bool]) -> str:
        """The same as SQL text; one parsed text costs the driver less than its many parts as columns."""
        out = ""
        for k, v, n in reversed(list(zip(self.keys, values, nullable))):
            c = quoted(k.name)
            less = f"coalesce({c} {'<' if k.asc else '>'} {v}, {str(k.first).lower()})"
            if n:
                less = f"case when {v} is null then {'false' if k.first else f'{c} is not null'} else {less} end"
            same = f"{c} <=> {v}" if n else f"coalesce({c} = {v}, false)"
            out = f"({less} or ({same} and {out}))" if out else less
        return out

    def same_sql(self, values: list[str]) -> str:
        return " and ".join(f"{quoted(k.name)} <=> {v}" for k, v in zip(self.keys, values))

    def prefix(self, n: int) -> KeySpec:
        return KeySpec(self.keys[:n])

    def same(self, values: list[Column]) -> Column:
        out = F.lit(True)
        for k, v in zip(self.keys, values):
            out = out & F.col(k.name).eqNullSafe(v)
        return out

    def validate(self, df: DataFrame) -> KeySpec:
        def orderable(t: T.DataType) -> bool:
            if isinstance(t, T.MapType) or t.typeName() == "variant":
                return False
            if isinstance(t, T.ArrayType):
                return orderable(t.elementType)
            return all(orderable(f.dataType) for f in t.fields) if isinstance(t, T.StructType) else True

        if not self.keys:
            raise ValueError("no sort key")
        for k in self.keys:
            if not orderable(df.select(k.name).schema[0].dataType):
                raise TypeError(f"{k.name} can't be ordered")
        return self
