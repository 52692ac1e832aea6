"""Nearest neighbours by cosine, exact: the rows that are asked for against all rows.

The table is cut into parts by id; a task holds one part, and every query's vector visits
every part. A block of queries meets a block of the part in one matrix product of single
precision. Pairs that reach the query's floor, the k-th best similarity so far less the
product's largest possible error, are computed again in double precision, and each part
gives a query's k best. Nothing is sampled, learned or estimated, so no neighbour is lost;
the work is queries times rows.

The similarity is rounded to six digits, and ranks follow the rounded one; ties go to the
lower id.

Edge cases: null vectors, vectors with null, NaN or infinite parts or of length zero have no
neighbours and are no one's; vectors of another dimension than the most frequent one (the
lower of two as frequent) are left out likewise; null ids are left out; repeated rows of one
id count once (the least vector).

``Codes`` are one-bit codes of rotated vectors with bounds; the search does not need them.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Neighbours of a query; rows of a block of the part and of a block of queries; bytes of vectors of a part.
K, CELL, ASKED, PART_BYTES = 10, 1024, 512, 1 << 26


def rotation(dim: int, seed: int = 7) -> np.ndarray:
    """A random orthogonal matrix of the dimension's next multiple of 64."""
    wide = -(-dim // 64) * 64
    q, r = np.linalg.qr(np.random.default_rng(seed).normal(size=(wide, wide)))
    return (q * np.sign(np.diag(r)))[:, :dim].astype(np.float32)


class Codes:
    """One-bit codes of residuals, with their correction scalars."""

    def __init__(self, residuals: np.ndarray, turn: np.ndarray):
        self.dim = len(turn)
        self.norm = np.linalg.norm(residuals, axis=1)
        direction = residuals / np.maximum(self.norm, 1e-12)[:, None]
        turned = direction @ turn.T
        bits = turned > 0
        self.bits = np.packbits(bits, axis=1, bitorder="little").view(np.uint64)
        self.ones = bits.sum(1).astype(np.float32)
        #: Inner product of a direction with its code vector of +-1/sqrt(dim).
        self.align = np.maximum(np.abs(turned).sum(1) / np.sqrt(self.dim), 1e-6)
        self.error = np.sqrt(np.maximum(1 - self.align**2, 0)) / self.align / np.sqrt(max(1, self.dim - 1))

    def estimate(self, query: np.ndarray, turn: np.ndarray, epsilon: float) -> tuple[np.ndarray, np.ndarray]:
        """Estimated inner products of residuals with queries (queries x vectors), and error bounds."""
        turned = query @ turn.T
        low, high = turned.min(1), turned.max(1)
        step = np.maximum((high - low) / 15, 1e-12).astype(np.float32)
        levels = np.rint((turned - low[:, None]) / step[:, None]).astype(np.uint8)
        # Levels of the query over set bits, counted plane by plane on packed words.
        ahead = np.zeros((len(query), len(self.bits)), np.uint32 if self.dim > 4096 else np.uint16)
        for plane in range(4):
            packed = np.packbits(levels >> plane & 1, axis=1, bitorder="little").view(np.uint64)
            for word in range(packed.shape[1]):
                ahead += np.left_shift(np.bitwise_count(packed[:, word, None] & self.bits[None, :, word]), plane, dtype=ahead.dtype)
        # Twice the sum over set bits less the whole sum is the inner product with the signs.
        root = np.float32(np.sqrt(self.dim))
        guess = ahead.astype(np.float32)
        guess *= (2 * step / root)[:, None]
        guess += np.outer((2 * low / root).astype(np.float32), self.ones)
        guess -= ((levels.sum(1, dtype=np.float64) * step + low * self.dim) / root).astype(np.float32)[:, None]
        scale = (self.norm / self.align).astype(np.float32)
        guess *= scale[None, :]
        bound = np.outer(np.linalg.norm(query, axis=1).astype(np.float32), (epsilon * self.error * self.norm).astype(np.float32))
        bound += np.outer(step / 2, scale)
        return guess, bound


def _scaled(vectors: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(vectors of length one in single precision, their lengths in double)."""
    norm = np.sqrt(np.einsum("ij,ij->i", vectors, vectors, dtype=np.float64))
    return np.divide(vectors, norm[:, None], out=np.empty_like(vectors), casting="same_kind"), norm


class Part:
    """Vectors of a part of the table, searched by brute force."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, cell: int = CELL):
        self.ids, self.vectors, self.cell = ids, vectors, cell
        self.unit, self.norm = _scaled(vectors)
        self.dim = vectors.shape[1]
        # A product errs by at most (dim + 8) / 2**24 for vectors of length one; two of them, and two roundings to six digits.
        self.margin = 2 * (self.dim + 8) / 2**24 + 1.2e-6

    def nearest(self, ids: np.ndarray, vectors: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(place of the query, neighbour id, similarity) of each query's k best, in order."""
        found = [self._block(a, ids[a : a + ASKED], vectors[a : a + ASKED], k) for a in range(0, len(ids), ASKED)]
        return tuple(np.concatenate([f[j] for f in found]) for j in range(3))  # type: ignore[return-value]

    def _block(self, shift: int, ids: np.ndarray, vectors: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        unit, norm = _scaled(vectors)
        floor = np.full(len(ids), -np.inf, np.float32)
        best = (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))
        waiting, count = [best], 0
        room = np.empty((len(ids), min(self.cell, len(self.ids))), np.float32)
        for b in range(0, len(self.ids), self.cell):
            cell = self.unit[b : b + self.cell]
            likeness = np.matmul(unit, cell.T, out=room if len(cell) == room.shape[1] else None)
            if b == 0 and len(cell) > k + 1:
                # The query itself may be among them, so one more than k.
                floor = (np.partition(likeness, -k - 1, axis=1)[:, -k - 1] - self.margin).astype(np.float32)
            # Most queries have no pair that reaches their floor.
            some = np.flatnonzero(likeness.max(1) >= floor)
            row, column = np.divmod(np.flatnonzero(likeness[some] >= floor[some, None]), len(cell))
            row = some[row]
            column += b
            apart = ids[row] != self.ids[column]
            row, column = row[apart], column[apart]
            waiting.append((row, self.ids[column], self._similarity(vectors, norm, row, column)))
            count += len(row)
            if count >= 32 * len(ids) or b + self.cell >= len(self.ids):
                best, floor = self._sift(waiting, floor, k)
                waiting, count = [best], 0
        return best[0] + shift, best[1], best[2]

    def _similarity(self, vectors: np.ndarray, norm: np.ndarray, row: np.ndarray, column: np.ndarray) -> np.ndarray:
        out = np.empty(len(row))
        step = max(1, (1 << 20) // self.dim)
        for a in range(0, len(row), step):
            r, c = row[a : a + step], column[a : a + step]
            out[a : a + step] = np.einsum("ij,ij->i", vectors[r], self.vectors[c], dtype=np.float64) / (norm[r] * self.norm[c])
        return np.round(out, 6) + 0.0

    def _sift(self, waiting: list[tuple[np.ndarray, np.ndarray, np.ndarray]], floor: np.ndarray, k: int) -> tuple[tuple[np.ndarray, np.ndarray, np.ndarray], np.ndarray]:
        """The k best of each row among those that wait, and the floors that follow."""
        row, others, likeness = (np.concatenate([w[j] for w in waiting]) for j in range(3))
        order = np.lexsort((others, -likeness, row))
        row, others, likeness = row[order], others[order], likeness[order]
        first = np.searchsorted(row, np.arange(len(floor) + 1))
        full = np.flatnonzero(np.diff(first) >= k)
        floor = floor.copy()
        floor[full] = np.maximum(floor[full], likeness[first[full] + k - 1] - self.margin)
        good = np.arange(len(row)) - first[row] < k
        return (row[good], others[good], likeness[good]), floor


def _vectors(column: pa.Array, dim: int) -> np.ndarray:
    return np.asarray(column.flatten(), dtype=np.float32).reshape(len(column), dim)


def _searcher(dim: int, k: int, cell: int):
    """Searches a part: its own rows come first (kind 0), then the queries (kind 1)."""

    def run(batches):
        ids, vectors, part = [], [], None
        for batch in batches:
            split = int(np.searchsorted(np.asarray(batch.column("kind")), 1))
            numbers, values = np.asarray(batch.column("vec_id")), _vectors(batch.column("vector"), dim)
            if split:
                ids.append(numbers[:split].copy())
                vectors.append(values[:split].copy())
            if split == batch.num_rows:
                continue
            if part is None:
                if not ids:
                    return
                part = Part(np.concatenate(ids), np.concatenate(vectors), cell)
                ids, vectors = [], []
            row, others, likeness = part.nearest(numbers[split:], values[split:], k)
            ends = np.searchsorted(row, np.arange(batch.num_rows - split + 1)).astype(np.int32)
            best = pa.StructArray.from_arrays([pa.array(-likeness), pa.array(others)], ["far", "neighbour_id"])
            yield pa.RecordBatch.from_arrays([pa.array(numbers[split:]), pa.ListArray.from_arrays(pa.array(ends), best)], ["vec_id", "best"])

    return run


def _usable(embeddings: DataFrame, asked: Column | None = None) -> DataFrame:
    """(vec_id, vector) of the rows that have an id and a direction."""
    rows = embeddings.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<float>").alias("vector")).where("vec_id is not null")
    # Null parts make the sum null; NaN is above infinity.
    square = F.aggregate("vector", F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double"))
    return (rows if asked is None else rows.where(asked)).where((square > 0) & (square < F.lit(float("inf"))))


def neighbours(embeddings: DataFrame, k: int = K, every: int = 1, cell: int = CELL, part_bytes: int = PART_BYTES) -> DataFrame:
    """(vec_id, neighbour_id, rank, similarity): the k nearest of every usable row whose id is divisible by ``every``, by cosine, among all usable rows.

    ``cell`` and ``part_bytes`` bound the rows that are compared at once and the bytes of a
    task's vectors; no result depends on them.
    """
    spark = embeddings.sparkSession
    dims = _usable(embeddings).groupBy(F.size("vector").alias("d")).count().orderBy(F.desc("count"), "d").first()
    if dims is None:
        return spark.createDataFrame([], "vec_id long, neighbour_id long, rank int, similarity double")
    dim, rows = dims["d"], dims["count"]
    parts = max(-(-rows * dim * 4 // part_bytes), min(2 * spark.sparkContext.defaultParallelism, -(-rows // 2048)))

    def single(frame: DataFrame) -> DataFrame:
        return frame.where(F.size("vector") == dim).groupBy("vec_id").agg(F.min("vector").alias("vector"))

    base = single(_usable(embeddings)).select(F.pmod(F.xxhash64("vec_id"), F.lit(parts)).cast("int").alias("part"), F.lit(0).alias("kind"), "vec_id", "vector")
    asked = single(_usable(embeddings, F.col("vec_id") % every == 0)).select(F.explode(F.sequence(F.lit(0), F.lit(parts - 1))).alias("part"), F.lit(1).alias("kind"), "vec_id", "vector")
    placed = base.unionByName(asked).repartitionById(parts, "part").sortWithinPartitions("kind")
    found = placed.select("kind", "vec_id", "vector").mapInArrow(_searcher(dim, k, cell), "vec_id long, best array<struct<far: double, neighbour_id: long>>")
    # Least (far, neighbour_id) first: ties to the lower id.
    best = found.groupBy("vec_id").agg(F.slice(F.array_sort(F.flatten(F.collect_list("best"))), 1, k).alias("best"))
    return best.select("vec_id", F.posexplode("best").alias("at", "b")).select("vec_id", F.col("b.neighbour_id").alias("neighbour_id"), (F.col("at") + 1).alias("rank"), (-F.col("b.far")).alias("similarity"))
