"""Shared pieces of the text operators: scratch tables, Arrow text access, hashing.

Scratch tables are Parquet folders below ``spark.checkpoint.dir``, the folder that
all executors share, so a lost executor never loses an intermediate result.
"""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

U64 = np.uint64
#: Text bytes that one NumPy step works on; bounds a worker's memory whatever the batch holds.
SLICE_BYTES = 1 << 20


def shared_dir(spark: SparkSession) -> str:
    """The cluster's shared scratch folder; a local one only where none is configured and the session is local."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if folder:
        return folder
    context = spark.sparkContext
    if context.getCheckpointDir() is None:
        if not context.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        context.setCheckpointDir(tempfile.mkdtemp(prefix="elimspark-"))
    return context.getCheckpointDir()


#: Folders of the scratch tables that were made and not deleted, in order.
_made: list[str] = []


def delete(spark: SparkSession, where: str) -> None:
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(where)
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


@contextmanager
def released(spark: SparkSession, keep: str = "") -> Iterator[None]:
    """Deletes the scratch tables of all operators called in the block, but those below ``keep``.

    An operator returns a frame that reads its scratch tables, so only a caller that has
    written that frame knows that they are done with.
    """
    before = len(_made)
    yield
    for where in [w for w in _made[before:] if not keep or not w.startswith(keep)]:
        delete(spark, where)
        _made.remove(where)


class Scratch:
    """Named intermediate tables of one operator call, kept in the shared folder."""

    def __init__(self, spark: SparkSession, owner: str):
        self.spark = spark
        self.root = f"{shared_dir(spark).rstrip('/')}/{owner}-{uuid.uuid4().hex}"
        self.made = 0
        _made.append(self.root)

    def keep(self, frame: DataFrame, name: str) -> DataFrame:
        """Write a frame and read it back: its lineage ends here."""
        self.made += 1
        path = f"{self.root}/{self.made:03d}-{name}"
        frame.write.parquet(path)
        back = self.spark.read.schema(frame.schema).parquet(path)
        back._scratch_path = path
        return back

    def drop(self, frame: DataFrame) -> None:
        """Delete a table made by keep(); the caller knows that nothing reads it again."""
        delete(self.spark, frame._scratch_path)


def spread_id(id_column: Column, bits: int = 31) -> Column:
    """A fixed pseudo-random rank of an integer id below 2**31, the same in any SQL engine.

    One step of a linear congruence on the id reduced mod 2**31-1; null ids count as -1.
    """
    base = F.pmod(F.coalesce(id_column.cast("long"), F.lit(-1)), F.lit(2147483647))
    return F.pmod(base * F.lit(1103515245) + F.lit(12345), F.lit(1 << bits))


def text_arrays(batch: pa.RecordBatch, column: str, limit: int = SLICE_BYTES) -> Iterator[tuple[int, int, pa.Array]]:
    """(first row, end row, texts without nulls) in slices of at most ``limit`` bytes, or one text."""
    texts = pc.fill_null(batch.column(column).cast(pa.large_string()), "")
    ends = np.cumsum(np.asarray(pc.binary_length(texts), dtype=np.int64)) if len(texts) else np.zeros(0, np.int64)
    start = 0
    while start < len(texts):
        before = ends[start - 1] if start else 0
        stop = max(start + 1, int(np.searchsorted(ends, before + limit, side="right")))
        yield start, stop, texts.slice(start, stop - start)
        start = stop


def verdicts(judge: Callable[[str], bool], texts: pa.Array) -> pa.Array:
    """judge(text) of each text, nulls as empty ones; Python holds the strings of one slice at a time."""
    batch = pa.RecordBatch.from_arrays([texts], ["text"])
    return pa.array([bool(judge(t)) for _, _, part in text_arrays(batch, "text") for t in part.to_pylist()], pa.bool_())


def keep_where(frame: DataFrame, text: Column, judge_of: Callable[[], Callable[[str], bool]]) -> DataFrame:
    """The rows whose text the judge accepts; ``judge_of`` makes it, once a task.

    Only the text travels to Python and one bit a row back; the rows themselves stay in the JVM.
    """

    @F.arrow_udf("boolean")
    def accepted(arrays: Iterator[pa.Array]) -> Iterator[pa.Array]:
        judge = judge_of()
        for texts in arrays:
            yield verdicts(judge, texts)

    return frame.where(accepted(text.cast("string")))


def mix64(x: np.ndarray) -> np.ndarray:
    """Finalising scrambler of 64-bit integers (splitmix)."""
    x = x.astype(U64, copy=True)
    x ^= x >> U64(30)
    x *= U64(0xBF58476D1CE4E5B9)
    x ^= x >> U64(27)
    x *= U64(0x94D049BB133111EB)
    x ^= x >> U64(31)
    return x


_BASE, _BASE_INVERSE = 0x9E3779B97F4A7C15 | 1, pow(0x9E3779B97F4A7C15 | 1, -1, 1 << 64)
_powers = [np.ones(1, U64), np.ones(1, U64)]


def _power_tables(length: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_powers[0]) < length:
        size = 1 << (length - 1).bit_length()
        for k, base in enumerate((_BASE, _BASE_INVERSE)):
            steps = np.full(size, base, U64)
            steps[0] = 1
            _powers[k] = np.multiply.accumulate(steps)
    return _powers[0][:length], _powers[1][:length]


def byte_class(chars: bytes, high: bool) -> np.ndarray:
    table = np.zeros(256, bool)
    table[list(chars)] = True
    table[128:] = high
    return table


#: ASCII letters and digits, and every byte of a longer UTF-8 sequence.
ALNUM = byte_class(b"abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789", True)
#: Everything but ASCII white space.
NONSPACE = ~byte_class(b" \t\n\r\x0b\x0c", False)


class Words:
    """Words of a slice of texts as arrays: 64-bit hash, document index, byte span."""

    def __init__(self, texts: pa.Array, word_bytes: np.ndarray):
        count = len(texts)
        offsets = np.frombuffer(texts.buffers()[1], np.int64)[texts.offset : texts.offset + count + 1]
        data = texts.buffers()[2]
        raw = np.frombuffer(data, np.uint8)[offsets[0] : offsets[-1]] if data is not None else np.zeros(0, np.uint8)
        offsets = offsets - offsets[0]
        self.count, self.raw, self.offsets = count, raw, offsets
        if not len(raw):
            self.starts = self.ends = self.doc = np.zeros(0, np.int64)
            self.hashes = np.zeros(0, U64)
        else:
            inside = word_bytes[raw]
            before = np.empty_like(inside)
            before[0], before[1:] = False, inside[:-1]
            edges = offsets[:-1][offsets[:-1] < len(raw)]
            before[edges] = False
            after = np.empty_like(inside)
            after[-1], after[:-1] = False, inside[1:]
            tails = offsets[1:][offsets[1:] > 0] - 1
            after[tails] = False
            self.starts = np.flatnonzero(inside & ~before)
            self.ends = np.flatnonzero(inside & ~after) + 1
            power, inverse = _power_tables(len(raw) + 1)
            sums = np.zeros(len(raw) + 1, U64)
            np.cumsum((raw.astype(U64) + U64(1)) * power[:-1], out=sums[1:])
            self.hashes = mix64((sums[self.ends] - sums[self.starts]) * inverse[self.starts])
            self.doc = np.searchsorted(offsets, self.starts, side="right") - 1
        #: Words of each document, and where its first word is.
        self.per_doc = np.bincount(self.doc, minlength=count).astype(np.int64)
        self.first = np.concatenate([[0], np.cumsum(self.per_doc)])


def ngram_hashes(words: Words, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Hash of every run of n words inside one document, and the index of its first word."""
    total = len(words.hashes)
    if total < n:
        return np.zeros(0, U64), np.zeros(0, np.int64)
    out = np.zeros(total - n + 1, U64)
    for k in range(n):
        out += words.hashes[k : total - n + 1 + k] * U64(2 * (0x632BE59BD9B4E019 >> (k % 13)) + 2 * k + 1)
    at = np.flatnonzero(words.doc[: total - n + 1] == words.doc[n - 1 :])
    return mix64(out[at]), at
