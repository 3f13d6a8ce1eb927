"""Ordered prefix sums over any number of rows, without a window that gathers a group in one task.

Rows are range-sorted on (group, order), each sorted partition adds up its own rows as a stream,
and the partitions' closing totals (one row a partition) are chained on the driver. A group may
span any number of partitions.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, types as T
from pyspark.sql import functions as F

from kgfeat.plans.state import Workspace

PART, ROW = "_part", "_row"


def _run_name(v: str) -> str:
    return f"_run_{v}"


def prefix_sums(ws: Workspace, df: DataFrame, group: str | None, order: list[str], values: list[str], name: str = "prefix") -> DataFrame:
    """df plus ``before_<v>`` for each value: the sum of v over the earlier rows of the same group.

    group is a non-null string column or None (all rows are one group); order columns must settle
    the order up to rows that are alike. values are non-null longs. Driver memory: one row a partition.
    """
    g = group or "_all"
    src = df if group else df.withColumn(g, F.lit(""))
    keys = ([group] if group else []) + order
    schema = T.StructType([*src.schema.fields, T.StructField(PART, T.IntegerType()), T.StructField(ROW, T.LongType()), *(T.StructField(_run_name(v), T.LongType()) for v in values)])

    def running(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, seen = TaskContext.get().partitionId(), 0
        last, carry = None, dict.fromkeys(values, 0)
        for b in batches:
            n = b.num_rows
            if not n:
                continue
            key = b.column(g)
            new = np.ones(n, bool)
            new[0] = last is None or key[0].as_py() != last
            if n > 1:
                new[1:] = pc.not_equal(key.slice(1), key.slice(0, n - 1)).to_numpy(zero_copy_only=False)
            start = np.maximum.accumulate(np.where(new, np.arange(n), -1))  # -1: the run began in an earlier batch
            runs = []
            for v in values:
                x = b.column(v).to_numpy(zero_copy_only=False).astype(np.int64)
                before = np.concatenate(([0], np.cumsum(x)[:-1]))
                run = before - np.where(start >= 0, before[np.maximum(start, 0)], -carry[v])
                carry[v] = int(run[-1] + x[-1])
                runs.append(pa.array(run))
            last = key[n - 1].as_py()
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(np.full(n, part, np.int32)), pa.array(np.arange(seen, seen + n)), *runs], schema=pa.schema([*b.schema, (PART, pa.int32()), (ROW, pa.int64()), *((_run_name(v), pa.int64()) for v in values)]))
            seen += n

    saved = ws.save(src.repartitionByRange(*keys).sortWithinPartitions(*keys).mapInArrow(running, schema), name)
    closing = F.struct(g, *((F.col(_run_name(v)) + F.col(v)).alias(v) for v in values))
    ends = saved.groupBy(PART).agg(F.min_by(g, ROW).alias("first"), F.max_by(closing, ROW).alias("last")).collect()
    offsets, prev, total = [], None, dict.fromkeys(values, 0)
    for r in sorted(ends, key=lambda r: r[PART]):
        if r["first"] != prev:
            total = dict.fromkeys(values, 0)
        offsets.append((r[PART], r["first"], *(total[v] for v in values)))
        single = r["last"][g] == r["first"]
        total = {v: r["last"][v] + (total[v] if single else 0) for v in values}
        prev = r["last"][g]
    at = ws.spark.createDataFrame(offsets, T.StructType([T.StructField(PART, T.IntegerType()), T.StructField("_first", T.StringType()), *(T.StructField(f"_off_{v}", T.LongType()) for v in values)]))
    out = saved.join(F.broadcast(at), PART)  # one row a partition
    for v in values:
        out = out.withColumn(f"before_{v}", F.col(_run_name(v)) + F.when(F.col(g) == F.col("_first"), F.col(f"_off_{v}")).otherwise(0))
    return out.drop(PART, ROW, "_first", *(_run_name(v) for v in values), *(f"_off_{v}" for v in values), *([] if group else [g]))
