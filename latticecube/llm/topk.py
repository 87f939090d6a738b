"""Operator 2, exact top-k inner products over a bit-sliced index.

Rows are cut into blocks of at most ``BLOCK_ROWS``.  A block stores, for every attribute and every binary
digit of its quantised values, one bitmap over the block's rows: the bit slices.  For a query, slices whose
weights are equal powers of two are added as whole bitmaps (three bitmaps into a sum and a carry at a time), which gives
the score of every row as bit slices too.  The best rows are then picked from the most significant slice
downward by intersecting bitmaps.  The lowest digits of the attributes may be left out of the sum; then every row whose
score lies within the error of that of the k-th is a boundary row and gets its exact score.

Negative weights use the complement of a slice, so that all terms are sums of non-negative numbers.

Every pair of a query block and an index block meets once, in one task; a block pair sends on at most k rows of each query.

Edge cases: vectors that are null, empty, or hold null or non-finite components take no part; a query meets only
vectors of its own dimension; a null id is no query and no candidate; rows that repeat an id count as rows of their own, but
none of them answers a query of that id; fewer than k candidates give all of them; ties go to the smaller id.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import common

BLOCK_ROWS = 16_384
QUERY_ROWS = 1_024


def popcount(words: np.ndarray) -> int:
    return int(np.bitwise_count(words).sum())


class SlicedBlock:
    """Bit slices of an integer matrix (rows x attributes)."""

    def __init__(self, values: np.ndarray):
        self.values = values
        self.n = len(values)
        self.low = values.min(axis=0)
        span = values - self.low
        self.digits = max(1, int(span.max()).bit_length())
        words = -(-self.n // 64)
        self.valid = self._pack(np.ones((self.n, 1), np.uint8), words)[0]
        # slices[digit, attribute, word]
        self.slices = np.stack([self._pack(((span >> d) & 1).astype(np.uint8), words) for d in range(self.digits)])

    @staticmethod
    def _pack(bits: np.ndarray, words: int) -> np.ndarray:
        out = np.zeros((bits.shape[1], words * 8), np.uint8)
        packed = np.packbits(bits.T, axis=1, bitorder="little")
        out[:, : packed.shape[1]] = packed
        return out.view(np.uint64)

    def score_slices(self, query: np.ndarray, drop: int = 0) -> list[np.ndarray]:
        """The sum over attributes of |q| * term as bit slices, least significant (2**drop) first.

        The term is value - low for a positive weight, and its complement for a negative one.
        """
        size = np.abs(query)
        heap: dict[int, list[np.ndarray]] = {}
        for bit in range(int(size.max(initial=0)).bit_length()):
            on = (size >> bit) & 1 == 1
            plus, minus = np.flatnonzero(on & (query > 0)), np.flatnonzero(on & (query < 0))
            for digit in range(drop, self.digits):
                of = heap.setdefault(bit + digit, [])
                if len(plus):
                    of.append(self.slices[digit, plus])
                if len(minus):
                    of.append(~self.slices[digit, minus])
        out, power = [], drop
        while heap and power <= max(heap):
            rows = heap.pop(power, [])
            layer = np.concatenate(rows) if len(rows) > 1 else rows[0] if rows else np.zeros((0, len(self.valid)), np.uint64)
            carries = []
            while len(layer) > 2:
                third = len(layer) // 3
                a, b, c = layer[:third], layer[third : 2 * third], layer[2 * third : 3 * third]
                half = a ^ b
                carries.append((a & b) | (half & c))
                layer = np.concatenate([half ^ c, layer[3 * third :]]) if len(layer) % 3 else half ^ c
            if len(layer) == 2:
                carries.append((layer[0] & layer[1])[None])
                layer = (layer[0] ^ layer[1])[None]
            out.append(layer[0] & self.valid if len(layer) else np.zeros_like(self.valid))
            if carries:
                heap.setdefault(power + 1, []).extend(carries)
            power += 1
        return out

    def top(self, query: np.ndarray, k: int, drop: int = 0) -> tuple[np.ndarray, np.ndarray]:
        """Row numbers and exact scores of a set that holds the k best rows (ties to the earlier row)."""
        if self.n <= k:
            rows = np.arange(self.n)
        else:
            sums = self.score_slices(query, drop)
            sure, maybe, kth = np.zeros_like(self.valid), self.valid, 0
            for power in range(len(sums) - 1, -1, -1):
                both = maybe & sums[power]
                if popcount(sure | both) >= k:
                    maybe, kth = both, kth | 1 << power
                else:
                    sure, maybe = sure | both, maybe & ~sums[power]
            picked = sure | maybe
            if drop:
                # kth * 2**drop bounds the k-th exact score from below; what was left out adds at most slack
                slack = ((1 << drop) - 1) * int(np.abs(query).sum())
                least = max(0, kth - (slack >> drop))
                above, equal = np.zeros_like(self.valid), self.valid
                for power in range(len(sums) - 1, -1, -1):
                    if least >> power & 1:
                        equal = equal & sums[power]
                    else:
                        above, equal = above | (equal & sums[power]), equal & ~sums[power]
                picked = above | equal
            rows = np.flatnonzero(np.unpackbits(picked.view(np.uint8), bitorder="little")[: self.n])
        score = self.values[rows] @ query
        best = np.lexsort((rows, -score))[:k]
        return rows[best], score[best]


def _blocks(df: DataFrame, rows: int, label: str) -> DataFrame:
    """Pack vectors into blocks of about ``rows`` rows: ``dim, block, n, ids, values`` (binary, eight bytes each)."""
    sizes = df.groupBy("dim").count()
    parts = sizes.select("dim", F.ceil(F.col("count") / rows).cast("int").alias("parts"))
    # one row for each dimension; salted ids spread a dimension's rows over its blocks
    placed = df.join(common.small_side(parts), "dim").withColumn("block", F.pmod(F.xxhash64("vec_id", "v"), F.col("parts").cast("long")).cast("int"))

    def pack(table: pa.Table) -> pa.Table:
        ids = table.column("vec_id").to_numpy()
        flat = table.column("v").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(len(ids), -1)
        order = np.argsort(ids, kind="stable")
        head = {"dim": [table.column("dim")[0].as_py()], "block": [table.column("block")[0].as_py()], "n": [len(ids)]}
        return pa.table(head | {"ids": [ids[order].astype("<i8").tobytes()], "values": [flat[order].astype("<i8").tobytes()]}, schema=pa.schema([("dim", pa.int32()), ("block", pa.int32()), ("n", pa.int32()), ("ids", pa.binary()), ("values", pa.binary())]))

    return placed.groupBy("dim", "block").applyInArrow(pack, "dim int, block int, n int, ids binary, values binary")


def quantised(vectors: DataFrame, scale: int, key: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """``vec_id, dim, v``: floor(scale * x) of each component; unusable vectors are left out."""
    x = F.transform(F.col(vector), lambda c: F.floor(c.cast("double") * F.lit(float(scale))))
    bad = F.exists(F.col(vector), lambda c: c.isNull() | F.isnan(c.cast("double")) | (F.abs(c.cast("double")) == F.lit(float("inf"))))
    return vectors.select(F.col(key).cast("long").alias("vec_id"), F.col(vector).alias("raw"), F.when(~bad, x).alias("v")).where(F.col("vec_id").isNotNull() & F.col("v").isNotNull() & (F.size("raw") > 0)).select("vec_id", F.size("v").alias("dim"), "v")


def top_k(queries: DataFrame, candidates: DataFrame, k: int, drop: int = 1) -> DataFrame:
    """``query_id, rank, vec_id, score`` from two frames of ``vec_id, dim, v`` (integer components)."""
    q = _blocks(queries, QUERY_ROWS, "q").select("dim", F.col("block").alias("qblock"), F.col("ids").alias("qids"), F.col("values").alias("qvalues"))
    index = _blocks(candidates, BLOCK_ROWS, "i")
    count = q.groupBy("dim").agg((F.max("qblock") + 1).alias("qblocks"))
    copies = index.join(common.small_side(count), "dim").withColumn("qblock", F.explode(F.sequence(F.lit(0), F.col("qblocks") - 1))).drop("qblocks")
    met = copies.join(q, ["dim", "qblock"])

    def search(batches):
        last, block = None, None
        for batch in batches:
            for r in range(batch.num_rows):
                cell = lambda name: batch.column(names[name])[r].as_py()  # noqa: B023, E731
                names = {n: i for i, n in enumerate(batch.schema.names)}
                dim, at = cell("dim"), cell("block")
                if last != (dim, at):
                    last, ids = (dim, at), np.frombuffer(cell("ids"), "<i8")
                    block = SlicedBlock(np.frombuffer(cell("values"), "<i8").reshape(-1, dim))
                    least = min(drop, block.digits - 1)
                qids = np.frombuffer(cell("qids"), "<i8")
                out: tuple[list, list, list] = ([], [], [])
                for qid, query in zip(qids, np.frombuffer(cell("qvalues"), "<i8").reshape(-1, dim), strict=True):
                    lo, hi = np.searchsorted(ids, [qid, qid + 1])  # the query's own rows don't answer it
                    rows, score = block.top(query, k + int(hi - lo), least)
                    keep = np.flatnonzero((rows < lo) | (rows >= hi))[:k]
                    out[0].append(np.full(len(keep), qid))
                    out[1].append(ids[rows[keep]])
                    out[2].append(score[keep])
                yield pa.record_batch([pa.array(np.concatenate(x).astype(np.int64)) for x in out], ["query_id", "vec_id", "score"])

    # a block pair is a unit of work of its own; sorting keeps the pairs of an index block together
    dealt = met.repartition(F.col("dim"), F.col("block"), F.col("qblock")).sortWithinPartitions("dim", "block", "qblock")
    found = dealt.mapInArrow(search, "query_id long, vec_id long, score long")
    place = F.row_number().over(Window.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id"))
    return found.withColumn("rank", place).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
