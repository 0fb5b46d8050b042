"""Encoding of row matrices (row_id, x, y) and of feature blocks.

Encoded rows are (worker, enc_row, x, y).  A worker is logical: a value of a column, by which data is laid out so that
an erased worker's data is not read.

Row numbers are whole; numbers from 0 on are data.  Negative ones are rows that must never be erased (those of
`absorb_ridge`): they are left as they are under the worker ALWAYS.  A missing or repeated row_id, a missing x or y and rows of
different lengths are errors, as no sum over them would stand for the data; `numbered` gives any table proper numbers.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from erasureml.operators.codes import Code, assign

ROWS = "worker int, enc_row long, x array<double>, y double"


def stacked(column: pa.Array | pd.Series) -> np.ndarray:
    return np.stack([np.asarray(v, float) for v in column]) if len(column) else np.zeros((0, 0))


ALWAYS = -1


class BadRows(ValueError):
    """Rows that can't be encoded: see the module."""


def numbered(df: DataFrame) -> DataFrame:
    """df with row_id 0, 1, ... without gaps, in the order of its partitions; two passes and no shuffle."""
    marked = df.withColumn("_at", F.monotonically_increasing_id())
    part = F.shiftright("_at", 33)
    sizes = marked.groupBy(part.alias("part")).agg(F.count("*").alias("n")).orderBy("part").collect()  # a row a partition
    ends = np.cumsum([0, *(r["n"] for r in sizes)]).tolist()
    first = F.create_map(*(F.lit(v) for r, at in zip(sizes, ends, strict=False) for v in (r["part"], at))) if sizes else F.create_map(F.lit(0), F.lit(0))
    return marked.withColumn("row_id", first[part] + F.col("_at").bitwiseAND(F.lit((1 << 33) - 1))).drop("_at")


def _columns(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row_id, x and y side by side) of a batch of row_id, x, y."""
    ids, x, y = batch.columns[:3]
    if ids.null_count or x.null_count or y.null_count:
        raise BadRows("a row_id, x or y is missing")
    n, width = len(ids), len(x.flatten())
    p = width // n if n else 0
    if n and (width % n or not (np.diff(x.offsets.to_numpy()) == p).all()):
        raise BadRows("rows differ in length")
    values = x.flatten()
    if values.null_count:
        raise BadRows("a number of x is missing")
    return ids.to_numpy(), np.column_stack([values.to_numpy().reshape(n, p), y.to_numpy()]) if n else np.zeros((0, 1)), np.zeros(0)


def _batch(worker: np.ndarray, enc_row: np.ndarray, z: np.ndarray) -> pa.RecordBatch:
    p = z.shape[1] - 1
    x = pa.ListArray.from_arrays(pa.array(np.arange(len(z) + 1, dtype=np.int32) * p), pa.array(np.ascontiguousarray(z[:, :-1]).ravel()))
    return pa.RecordBatch.from_arrays([pa.array(worker.astype(np.int32)), pa.array(enc_row.astype(np.int64)), x, pa.array(np.ascontiguousarray(z[:, -1]))], ["worker", "enc_row", "x", "y"])


def group_of(row_id: Column, n: int) -> Column:
    """The number of a row's group, whole at any size (no division of floating numbers)."""
    return F.call_function("div", row_id - F.pmod(row_id, F.lit(n).cast("long")), F.lit(n).cast("long"))


def encode_rows(df: DataFrame, code: Code, m: int, *, mode: str = "grouped", how: str = "scatter", seed: int = 1, untouched: bool = True) -> DataFrame:
    """(S x, S y) of rows numbered 0, 1, ...; rows with negative numbers as they are, under the worker ALWAYS.

    grouped: rows are taken in groups of code.n by number; every group is encoded by itself (a fast transform where the
        code has one) and its encoded rows are dealt over all workers in the same pattern.  S is block-diagonal, so
        its spectrum over any set of workers is that of one group.  One shuffle by group; a task encodes all whole
        groups of a batch at once and holds one batch.
    join: the same groups, as a join with the coordinates of S and a sum: for small codes and as a check.
    untouched: also the encoded rows, all zero, that no row of an incomplete group takes part in.
    """
    n = code.n
    data = df.select(F.col("row_id").cast("long").alias("row_id"), "x", F.col("y").cast("double").alias("y"))
    if mode == "join":
        coords = code.to_df(df.sparkSession, m, how, seed)
        kept = data.where("row_id < 0").select(F.lit(ALWAYS).cast("int").alias("worker"), F.col("row_id").alias("enc_row"), "x", "y")
        rows = data.where("row_id >= 0").select(F.pmod("row_id", F.lit(n)).alias("src_row"), group_of(F.col("row_id"), n).alias("group"), F.posexplode(F.concat("x", F.array("y"))).alias("pos", "v"))
        coords = coords.withColumnRenamed("enc_row", "code_row")
        enc_row = F.col("group") * code.N + F.col("code_row")
        terms = coords.join(rows, "src_row").select("worker", enc_row.alias("enc_row"), "pos", (F.col("coef") * F.col("v")).alias("v"))
        # encoded rows of an incomplete group that no row of it touches
        zeros = coords.select("worker", "code_row").distinct().crossJoin(rows.select("group", "pos").distinct()).select("worker", enc_row.alias("enc_row"), "pos", F.lit(0.0).alias("v"))
        sums = (terms.union(zeros) if untouched else terms).groupBy("worker", "enc_row", "pos").agg(F.sum("v").alias("v"))
        whole = sums.groupBy("worker", "enc_row").agg(F.transform(F.sort_array(F.collect_list(F.struct("pos", "v"))), lambda s: s["v"]).alias("all"))
        return whole.select("worker", "enc_row", F.slice("all", F.lit(1), F.size("all") - 1).alias("x"), F.element_at("all", -1).alias("y")).union(kept)
    if mode != "grouped":
        raise ValueError(f"unknown mode {mode}")
    worker = assign(code, m, how, seed)

    def encoded(ids: np.ndarray, values: np.ndarray) -> pa.RecordBatch:
        """Whole groups, side by side."""
        own = ids < 0
        group, at = np.unique(ids[~own] // n, return_inverse=True)
        full = np.zeros((n, len(group), values.shape[1]))
        seen = np.zeros((n, len(group)), np.int64)
        np.add.at(seen, (ids[~own] % n, at), 1)
        if (seen > 1).any() or len(np.unique(ids[own])) < own.sum():
            raise BadRows("a row_id is repeated")
        full[ids[~own] % n, at] = values[~own]
        z = code.apply(full).transpose(1, 0, 2).reshape(len(group) * code.N, values.shape[1])
        rows = (group[:, None] * code.N + np.arange(code.N)).ravel()
        by = np.tile(worker, len(group))
        if not untouched and not seen.all():
            live = code.touched(seen).T.ravel()
            z, rows, by = z[live], rows[live], by[live]
        return _batch(np.concatenate([np.full(int(own.sum()), ALWAYS), by]), np.concatenate([ids[own], rows]), np.concatenate([values[own], z]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, values = np.zeros(0, np.int64), None  # of the group that the next batch may go on with
        for batch in batches:
            new, table, _ = _columns(batch)
            if not len(new):
                continue
            if values is not None and values.shape[1] != table.shape[1]:
                raise BadRows("rows differ in length")
            ids, values = np.concatenate([ids, new]), table if values is None else np.concatenate([values, table])
            cut = int(np.searchsorted(ids, ids[-1] // n * n)) if ids[-1] >= 0 else 0  # sorted by number
            if cut:
                yield encoded(ids[:cut], values[:cut])
                ids, values = ids[cut:], values[cut:]
        if len(ids):
            yield encoded(ids, values)

    # negative numbers are dealt by themselves; a missing one makes its task fail in _columns
    dealt = data.repartition(F.when(F.col("row_id") < 0, F.col("row_id")).otherwise(group_of(F.col("row_id"), n))).sortWithinPartitions("row_id")
    return dealt.mapInArrow(run, ROWS)


def support_rows(df: DataFrame, code: Code, m: int, how: str = "scatter", seed: int = 1) -> DataFrame:
    """(worker, row_id, x, y): the uncoded rows that each worker's part of the code touches, for `online` gradients."""
    pairs = code.to_df(df.sparkSession, m, how, seed).select("worker", "src_row").distinct()
    grouped = df.withColumn("src_row", F.pmod("row_id", F.lit(code.n)))
    return grouped.join(pairs, "src_row").select("worker", "row_id", "x", "y")


def replicate(df: DataFrame, m: int, r: int = 2) -> DataFrame:
    """(worker, part, row_id, x, y): m/r distinct parts, each on r workers."""
    parts = m // r
    copies = df.select((F.col("row_id") % parts).cast("int").alias("part"), "row_id", "x", "y", F.explode(F.sequence(F.lit(0), F.lit(r - 1))).alias("copy"))
    return copies.select((F.col("copy") * parts + F.col("part")).cast("int").alias("worker"), "part", "row_id", "x", "y")


def absorb_ridge(df: DataFrame, lam: float, p: int) -> DataFrame:
    """Rows sqrt(lam) I below the data; they take the numbers -1, -2, ..., which encoding leaves alone (worker ALWAYS)."""
    extra = df.sparkSession.range(p).select(
        (-F.col("id") - 1).alias("row_id"), F.transform(F.sequence(F.lit(0), F.lit(p - 1)), lambda j: F.when(j == F.col("id"), F.lit(lam**0.5)).otherwise(F.lit(0.0))).alias("x"), F.lit(0.0).alias("y")
    )
    return df.select("row_id", "x", "y").unionByName(extra)


def encode_columns(df: DataFrame, code: Code, m: int, how: str = "scatter", seed: int = 1) -> DataFrame:
    """(row_id, worker, xblk): every row's lifted features S x by worker; local to a row, so nothing is shuffled."""
    worker = assign(code, m, how, seed)
    blocks = [np.flatnonzero(worker == i) for i in range(m)]

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            z = code.apply(stacked(frame["x"]).T).T
            yield pd.DataFrame({"row_id": np.repeat(frame["row_id"].to_numpy(), m), "worker": np.tile(np.arange(m, dtype=np.int32), len(frame)), "xblk": [row[b] for row in z for b in blocks]})

    return df.select("row_id", "x").mapInPandas(run, "row_id long, worker int, xblk array<double>")


def write_by_worker(encoded: DataFrame, path: str) -> None:
    """A folder for every worker: a filter on worker prunes whole folders, so an erased worker is never read."""
    encoded.repartition("worker").write.mode("overwrite").partitionBy("worker").parquet(path)


def read_active(spark, path: str, active: list[int]) -> DataFrame:
    """The rows of these workers and those that are never erased."""
    return spark.read.parquet(path).where(F.col("worker").isin([ALWAYS, *(int(i) for i in active)]))
