"""Order that is already there."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..plans.keys import KeySpec


def _descents(spec: KeySpec, names: list[str]):
    """Rows in order to one row for each partition: the first and the last key, steps down and up; nothing is kept but a batch and a row."""

    def ranks(table: pa.Table) -> list[np.ndarray]:
        """Each key's order as numbers, for neighbours to be compared by; floats have their NaNs above all else, as a key before them."""
        out = []
        for k, name in zip(spec.keys, names):
            column = table.column(name).combine_chunks()
            parts = [column]
            if pa.types.is_floating(column.type):
                nan = pc.is_nan(column)
                parts = [nan, pc.if_else(nan, 0.0, column)]
            for x in parts:
                order = "ascending" if k.asc else "descending"
                out.append(pc.rank(x, sort_keys=order, null_placement="at_start" if k.first else "at_end", tiebreaker="dense").to_numpy(zero_copy_only=False).astype(np.int64))
        return out

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        first = last = None
        down = up = 0
        for batch in batches:
            if not batch.num_rows:
                continue
            table = pa.Table.from_batches([batch])
            first = table.slice(0, 1) if first is None else first
            seen = table if last is None else pa.concat_tables([last, table])
            last = table.slice(table.num_rows - 1, 1)
            step = np.zeros(seen.num_rows - 1, dtype=np.int64)
            for r in ranks(seen):
                step = np.where(step == 0, np.sign(np.diff(r)), step)
            down, up = down + int((step < 0).sum()), up + int((step > 0).sum())
        if first is not None:
            ends = [t.column(n).combine_chunks() for t in (first, last) for n in names]
            fields = [f"{x}_{i}" for x in ("first", "last") for i in range(len(names))]
            yield pa.RecordBatch.from_arrays([first.column("p").combine_chunks(), pa.array([down], pa.int64()), pa.array([up], pa.int64()), *ends], ["p", "down", "up", *fields])

    return run


def _as_numbers(c: str, kind: T.DataType) -> Column:
    """Types whose order Arrow's ranks don't have, as others of the same order."""
    return F.hex(c) if isinstance(kind, T.BinaryType) else F.col(c)


def _compared(spec: KeySpec, values: list[str], row: list[str]) -> tuple[Column, Column]:
    """Whether a row of columns sorts before the values of other columns, and whether after them."""
    own = KeySpec(tuple(type(k)(n, k.asc, k.nulls_first) for k, n in zip(spec.keys, row)))
    there = [F.col(v) for v in values]
    return own.before(there), ~own.before(there) & ~own.same(there)


def probe_order(df: DataFrame, keys, index: str | None = None, parts: int = 64) -> DataFrame:
    """One row (state, descents): sorted, reversed, constant or unsorted, in the keys' own directions and with their nulls' places.

    With an index column, order means its order: runs of the index are windows of their own, and their edges are compared in a table of
    `parts` rows.  Without, order means that of rows in files, within and across partitions; rows are read where they are and not exchanged."""
    spec = KeySpec.of(keys).validate(df)
    names = [f"k{i}" for i in range(len(spec.keys))]
    kinds = [df.schema[n].dataType for n in spec.names]
    ends = [[f"{x}_{i}" for i in range(len(names))] for x in ("first", "last")]
    if index is None and not any(isinstance(k, (T.ArrayType, T.StructType)) for k in kinds):
        rows = df.select(F.spark_partition_id().alias("p"), *[_as_numbers(c, k).alias(n) for c, k, n in zip(spec.names, kinds, names)])
        fields = [T.StructField("p", T.IntegerType()), T.StructField("down", T.LongType()), T.StructField("up", T.LongType())]
        fields += [T.StructField(e, rows.schema[n].dataType) for x in ends for e, n in zip(x, names)]
        each = rows.mapInArrow(_descents(spec, names), T.StructType(fields))
    else:
        cols = [F.col(c).alias(n) for c, n in zip(spec.names, names)]
        if index is None:
            rows = df.select(*cols, F.monotonically_increasing_id().alias("i"), F.spark_partition_id().alias("p"))
        else:
            lo, hi = df.agg(F.min(index), F.max(index)).first()
            step = max(1, ((hi or 0) - (lo or 0)) // parts + 1)
            rows = df.select(*cols, F.col(index).alias("i"), F.floor((F.col(index) - (lo or 0)) / step).cast("int").alias("p"))
        w = Window.partitionBy("p").orderBy("i")
        seen = rows.withColumns({**{f"was_{n}": F.lag(n).over(w) for n in names}, "has": F.lag(F.lit(True)).over(w).isNotNull()})
        down, up = _compared(spec, [f"was_{n}" for n in names], names)
        firsts = [f.alias(e) for x, f_ in zip(ends, (F.min_by, F.max_by)) for e, f in zip(x, [f_(F.struct(n), "i")[n] for n in names])]
        each = seen.groupBy("p").agg(F.sum((down & F.col("has")).cast("long")).alias("down"), F.sum((up & F.col("has")).cast("long")).alias("up"), *firsts)
    over = Window.orderBy("p")  # one row for each part
    edges = each.withColumns({**{f"was_{i}": F.lag(e).over(over) for i, e in enumerate(ends[1])}, "has": F.lag(F.lit(True)).over(over).isNotNull()})
    down, up = _compared(spec, [f"was_{i}" for i in range(len(names))], ends[0])
    add = lambda c, x: (F.col(c) + (x & F.col("has")).cast("long")).alias(c)
    total = edges.select(add("down", down), add("up", up)).agg(F.coalesce(F.sum("down"), F.lit(0)).alias("down"), F.coalesce(F.sum("up"), F.lit(0)).alias("up"))
    state = F.when((F.col("down") == 0) & (F.col("up") == 0), "constant").when(F.col("down") == 0, "sorted").when(F.col("up") == 0, "reversed").otherwise("unsorted")
    return total.select(state.alias("state"), F.col("down").alias("descents"))
