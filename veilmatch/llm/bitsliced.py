"""Exact top-k search by a bit-sliced index.

Vectors are quantised to whole numbers. A block of rows is stored as bitmaps: slice j of
attribute d has one bit per row, in two's complement. The score of a query is a weighted sum of
attributes, so its slices are made by bitmap addition: bitmaps of equal weight go through carry-save
adders until one is left. Only the upper slices of each attribute are added; what the
lower ones can still add lies in a known interval. The selection walks the summed slices from the
most significant one down and keeps the rows that must be among the best; rows whose
upper bound reaches the last kept lower bound are resolved exactly by integer products.

Scale: queries are the stated tenth or hundredth of the rows and meet all rows in blocks: a
group is one block of rows and one block of queries, both of bounded size; each returns at
most k rows for a query, and a window picks the k best of them. Defined cases: null vectors
and vectors that hold null or non-finite components take no part; vectors of another width than
the query's score over the common width, missing components being zero; rows with the query's own id are no candidates
(repeated ids included) and equal rows with other ids are all candidates; ties go to the smaller id; rows with a
null id take no part; empty tables give no rows; other columns are ignored.
"""

from __future__ import annotations



import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from veilmatch.llm.common import table

ROWS, QUERIES, K = 32_768, 8_192, 10
KEPT_SLICES = 5  # upper slices of each attribute that are added


def quantised(vector: Column, scale: int = 1024) -> Column:
    """floor(scale * x) of every component; null where a vector takes no part."""
    x = vector.cast("array<double>")
    bad = F.exists(x, lambda c: c.isNull() | F.isnan(c) | (F.abs(c) == float("inf")))
    return F.when(vector.isNotNull() & ~F.coalesce(bad, F.lit(False)), F.transform(x, lambda c: F.floor(c * scale)))


class Block:
    """A bit-sliced index of up to ROWS vectors."""

    def __init__(self, ids: np.ndarray, values: np.ndarray, keep: int = KEPT_SLICES):
        self.ids, self.values = ids, values
        n, width = values.shape
        self.n, self.width = n, width
        low, high = (int(values.min()), int(values.max())) if values.size else (0, 0)
        self.bits = max(int(v).bit_length() for v in (high, -low - 1 if low < 0 else low)) + 1  # with sign
        self.drop = max(0, self.bits - keep)
        self.words = -(-n // 64)
        self.slices = np.zeros((width, self.bits - self.drop, self.words), np.uint64)
        for j in range(self.drop, self.bits):
            on = (values >> j & 1).astype(np.uint8).T
            padded = np.zeros((width, self.words * 64), np.uint8)
            padded[:, :n] = on
            self.slices[:, j - self.drop] = np.packbits(padded, axis=1, bitorder="little").view(np.uint64)

    def sums(self, query: np.ndarray) -> tuple[list[np.ndarray], int]:
        """Slices of sum(q_d * upper part of x_d) in units of 2**drop, offset so that none is negative; that offset."""
        upper = self.bits - self.drop
        piles: dict[int, list[np.ndarray]] = {}
        offset = 0
        for d, q in enumerate(query.tolist()):
            if not q:
                continue
            # A negative weight adds the complement: -x = ~x + 1 - 2**bits in the unsigned reading.
            size, part = abs(q), self.slices[d]
            for j in range(upper):
                # The sign slice weighs -2**(upper-1): its complement with the opposite weight, and a constant.
                flip = (q < 0) != (j == upper - 1)
                bitmap = ~part[j] if flip else part[j]
                offset -= (size << j) if flip else 0
                w = size
                shift = j
                while w:
                    if w & 1:
                        piles.setdefault(shift, []).append(bitmap)
                    w >>= 1
                    shift += 1
        out = []
        shift = 0
        while piles:
            pile = piles.pop(shift, [])
            while len(pile) > 1:
                if len(pile) == 2:
                    a, b = pile
                    pile = [a ^ b]
                    piles.setdefault(shift + 1, []).append(a & b)
                else:
                    # One level of a carry-save tree over the whole pile at once.
                    third = len(pile) // 3
                    m = np.array(pile[: 3 * third])
                    a, b, c = m[:third], m[third : 2 * third], m[2 * third :]
                    x = a ^ b
                    carry = (a & b) | (c & x)
                    piles.setdefault(shift + 1, []).extend(carry)
                    pile = [*(x ^ c), *pile[3 * third :]]
            out.append(pile[0] if pile else np.zeros(self.words, np.uint64))
            shift += 1
        return out, offset

    def best(self, query: np.ndarray, own: int, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Ids and scores of the k best rows of this block, ties to the smaller id."""
        query = query[: self.width] if len(query) > self.width else np.pad(query, (0, self.width - len(query)))
        usable = self.ids != own
        alive = np.zeros(self.words * 64, np.uint8)
        alive[: self.n] = usable
        alive = np.packbits(alive, bitorder="little").view(np.uint64)
        rows = np.flatnonzero(usable)
        if len(rows) > k and self.n > 4 * k:
            slices, offset = self.sums(query)
            # The k-th largest sum, slice by slice from the top.
            sure, open_, need, bound = np.zeros(self.words, np.uint64), alive, k, 0
            for s in range(len(slices) - 1, -1, -1):
                ones = open_ & slices[s]
                n = int(np.bitwise_count(ones).sum())
                if n >= need:
                    open_ = ones
                    bound |= 1 << s
                else:
                    sure |= ones
                    need -= n
                    open_ = open_ & ~slices[s]
            # Dropped slices add between min and max below: a row can pass the k-th sum only within that reach.
            low = (1 << self.drop) - 1
            reach = low * int(np.abs(query).sum())
            least = bound - -(-reach >> self.drop) - 1 if self.drop else bound
            passing, equal = np.zeros(self.words, np.uint64), alive
            for s in range(len(slices) - 1, -1, -1) if least > 0 else ():
                if least >> s & 1:
                    equal = equal & slices[s]
                else:
                    passing |= equal & slices[s]
                    equal = equal & ~slices[s]
            chosen = passing | equal if least > 0 else alive
            rows = np.flatnonzero(np.unpackbits(chosen.view(np.uint8), bitorder="little")[: self.n])
        scores = self.values[rows] @ query
        order = np.lexsort((self.ids[rows], -scores))[:k]
        return self.ids[rows][order], scores[order]


def _matrix(column: pa.ChunkedArray) -> np.ndarray:
    lists = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    sizes = np.diff(lists.offsets.to_numpy())
    flat = lists.flatten().to_numpy()
    width = int(sizes.max()) if len(sizes) else 0
    if len(sizes) and (sizes == width).all():
        return flat.reshape(-1, width)
    out = np.zeros((len(sizes), width), np.int64)
    out[np.arange(width) < sizes[:, None]] = flat
    return out


def top_k(rows: DataFrame, queries: DataFrame, k: int = K, block_rows: int = ROWS, block_queries: int = QUERIES) -> DataFrame:
    """rows and queries hold (vec_id, q array<long>); gives query_id, rank, vec_id, score.

    Equal query rows are one query; query rows of one id with other vectors are queries of their own.
    """
    queries = queries.dropDuplicates(["vec_id", "q"]).withColumn("qh", F.xxhash64("q"))
    n_rows, n_queries = rows.count(), queries.count()
    row_blocks, query_blocks = max(1, -(-n_rows // block_rows)), max(1, -(-n_queries // block_queries))
    # Dealt out by position, so that rows with one id do not meet in one block.
    deal = lambda df, n: F.pmod(F.xxhash64(F.monotonically_increasing_id()), F.lit(n)).cast("int")
    left = rows.withColumn("rb", deal(rows, row_blocks)).withColumn("qb", F.explode(F.sequence(F.lit(0), F.lit(query_blocks - 1))))
    right = queries.withColumn("qb", deal(queries, query_blocks)).withColumn("rb", F.explode(F.sequence(F.lit(0), F.lit(row_blocks - 1))))

    def run(some: pa.Table, asked: pa.Table) -> pa.Table:
        ids, hashes, found, scores = [], [], [], []
        if some.num_rows and asked.num_rows:
            block = Block(some["vec_id"].to_numpy(), _matrix(some["q"]))
            own = asked["vec_id"].to_numpy()
            for query, qh, q in zip(own.tolist(), asked["qh"].to_numpy().tolist(), _matrix(asked["q"])):
                got, score = block.best(q, query, k)
                ids.append(np.full(len(got), query))
                hashes.append(np.full(len(got), qh))
                found.append(got)
                scores.append(score)
        join = lambda x: pa.array(np.concatenate(x) if x else np.zeros(0, np.int64), pa.int64())
        return pa.table({"query_id": join(ids), "qh": join(hashes), "vec_id": join(found), "score": join(scores)})

    part = left.groupBy("rb", "qb").cogroup(right.groupBy("rb", "qb")).applyInArrow(run, "query_id long, qh long, vec_id long, score long")
    order = Window.partitionBy("query_id", "qh").orderBy(F.desc("score"), "vec_id")
    return part.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op2_exact_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    given = table(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("long").alias("vec_id"), quantised(F.col("embedding")).alias("q"))
    rows = given.where("vec_id is not null and q is not null")
    return top_k(rows, rows.where("vec_id % 100 = 0"))


OP2_SQL = """
with v as (
  select vec_id, list_transform(embedding, lambda x: floor(1024 * x::double)::bigint) as q from embeddings
  where embedding is not null and vec_id is not null and not list_bool_or(list_transform(embedding, lambda x: x is null or not isfinite(x)))
), s as (
  select a.vec_id as query_id, b.vec_id, list_sum(list_transform(list_zip(a.q, b.q), lambda z: z[1] * z[2]))::bigint as score
  from v a join v b on a.vec_id <> b.vec_id where a.vec_id % 100 = 0
)
select query_id, row_number() over (partition by query_id order by score desc, vec_id)::int as rank, vec_id, score
from s qualify rank <= 10
"""
