"""Shares as data: what an owner sends to each proxy, and how results are opened.

An owner turns each value into two numbers whose sum (mod 2**64) or XOR is the value. One is a keyed
pseudo-random number of (record, column), the other the rest; a frame for each proxy holds one of them.
Opening is an equality join of the two frames and wrapping arithmetic in decimals, so it stays
within built-in expressions whatever the session says about overflow.

Defined cases: a null value is split as zero beside its completeness; an empty frame gives empty frames; record ids are
public names and stand in both frames.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

U = np.uint64
TWO64 = 1 << 64


def wrapped(total: Column) -> Column:
    """A decimal as the long that it is mod 2**64."""
    full = F.lit(str(TWO64)).cast("decimal(38,0)")
    rest = total.cast("decimal(38,0)") % full
    rest = F.when(rest < 0, rest + full).otherwise(rest)
    return F.when(rest >= F.lit(str(TWO64 >> 1)).cast("decimal(38,0)"), rest - full).otherwise(rest).cast("long")


def ring_add(a: Column, b: Column) -> Column:
    return wrapped(a.cast("decimal(20,0)") + b.cast("decimal(20,0)"))


def ring_sum(a: Column) -> Column:
    """Aggregate: the sum mod 2**64."""
    return wrapped(F.sum(a.cast("decimal(20,0)")))


def _numbers(key: bytes, column: str, ids: list[int], n: int) -> np.ndarray:
    """One row of n ring elements for each id."""
    prefix = key + column.encode() + b"|"
    return np.frombuffer(b"".join(hashlib.shake_128(prefix + str(i).encode()).digest(8 * n) for i in ids), U).reshape(len(ids), n)


def split(df: DataFrame, columns: list[str], key: str, party: int, by: str = "rec_id", bits: bool = False) -> DataFrame:
    """Frame of one proxy: ``by``, ``party`` and a share of every column; long columns, or with ``bits`` arrays of longs under XOR."""
    secret = hashlib.sha256(key.encode()).digest()
    kind = "array<bigint>" if bits else "bigint"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column(0).to_pylist()
            out = [batch.column(0), pa.array([party] * len(ids), pa.int32())]
            for name, column in zip(columns, batch.columns[1:]):
                if bits:
                    lists = column.to_pylist()
                    n = max((len(v or ()) for v in lists), default=0)
                    held = np.array([list(v or ()) + [0] * (n - len(v or ())) for v in lists], np.int64).reshape(len(ids), n).view(U)
                    r = _numbers(secret, name, ids, n)
                    share = r if party == 0 else held ^ r
                    out.append(pa.ListArray.from_arrays(pa.array(np.arange(len(ids) + 1) * n, pa.int32()), pa.array(share.ravel().view(np.int64))))
                else:
                    held = column.fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64).view(U)
                    r = _numbers(secret, name, ids, 1)[:, 0]
                    share = r if party == 0 else held - r
                    out.append(pa.array(np.ascontiguousarray(share).view(np.int64)))
            yield pa.RecordBatch.from_arrays(out, names=[by, "party", *columns])

    rows = df.select(F.col(by).cast("long").alias(by), *[F.col(c).cast(kind).alias(c) for c in columns])
    return rows.mapInArrow(run, ", ".join([f"{by} bigint", "party int", *[f"{c} {kind}" for c in columns]]))


def both(df: DataFrame, columns: list[str], key: str, **how) -> tuple[DataFrame, DataFrame]:
    return split(df, columns, key, 0, **how), split(df, columns, key, 1, **how)


def opened(p0: DataFrame, p1: DataFrame, columns: list[str], by: str = "rec_id", bits: bool = False) -> DataFrame:
    """The values that two frames of shares stand for."""
    other = p1.select(by, *[F.col(c).alias(f"_{c}") for c in columns])
    xor = lambda a, b: F.zip_with(a, b, lambda x, y: x.bitwiseXOR(y))
    return p0.join(other, by).select(by, *[(xor(F.col(c), F.col(f"_{c}")) if bits else ring_add(F.col(c), F.col(f"_{c}"))).alias(c) for c in columns])


def revealed(p0: DataFrame, p1: DataFrame, columns: list[str], receivers: DataFrame, to: str, by: str = "rec_id") -> DataFrame:
    """Opened only for one receiver: shares of rows that ``receivers`` (by, receiver) does not grant to ``to`` never meet."""
    own = receivers.where(F.col("receiver") == to).select(by)
    return opened(p0.join(own, by, "left_semi"), p1.join(own, by, "left_semi"), columns, by)


def write(p0: DataFrame, p1: DataFrame, path: str) -> None:
    """Both frames as Parquet, a folder for each proxy; a repeated run overwrites its own folders only."""
    p0.unionByName(p1).write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("party").parquet(path)


def shape_only(p0: DataFrame) -> DataFrame:
    """(party, n_rows, n_columns): all that a proxy's frame tells without the other's."""
    return p0.groupBy("party").agg(F.count("*").alias("n_rows")).withColumn("n_columns", F.lit(len(p0.columns) - 2))


def view_uniform(p: DataFrame, column: str) -> DataFrame:
    """(cells, n, chi_square): bytes of a proxy's column over 256 cells; near 255 if nothing shows."""
    raw = F.transform(F.sequence(F.lit(0), F.lit(7)), lambda i: F.call_function("shiftrightunsigned", F.col(column), i * 8).bitwiseAND(F.lit(255)))
    counts = p.select(F.explode(raw).alias("b")).groupBy("b").agg(F.count("*").alias("n"))
    sums = counts.agg(F.count("*").alias("cells"), F.sum("n").alias("n"), F.sum(F.col("n").cast("double") * F.col("n")).alias("sq"))
    return sums.select("cells", "n", F.round(F.col("sq") * 256 / F.col("n") - F.col("n"), 4).alias("chi_square"))
