"""Language identification by unigram pieces, summed over all segmentations.

The vocabulary is that of a public tokenizer and stays fixed; only the probability of each
piece in each language is learned. The probability of a word is the sum over every way
to cut it into pieces of the product of their probabilities, by the forward recursion; a
text is its runs of letters, and the language with the largest probability wins. Pieces never cross
them, so the score of a text is a sum over its words: each distinct word of a batch
is scored once, all words of one length together.

Learning is expectation maximisation on the words of at most ``TRAIN_DOCS`` labelled
documents per language: expected piece counts over all segmentations by forward and
backward sums. A piece with no count keeps a small share, and any single sign has at least
that share, so every text can be segmented.

Edge cases: null texts and texts without letters have the language ``und`` and score 0; null doc_ids
keep their row; without labelled documents every text is ``und``; rows are independent.
"""

from __future__ import annotations

import os
import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

VOCABULARY = os.environ.get("ELIMSPARK_TOKENIZERS", "/opt/tokenizers") + "/piece_bpe_32k.model"
TRAIN_DOCS, ROUNDS, SMOOTH, MOST_CHOSEN = 150, 4, 1e-9, 200_000
MARK = "▁"
#: Signs of the words that are scored at once; bounds a step's memory (a longer word is a step of its own).
STEP_SIGNS = 1 << 20


def vocabulary(path: str = VOCABULARY) -> list[str]:
    """All pieces, lower case, without control and byte pieces."""
    import sentencepiece

    if not os.path.exists(path):
        raise FileNotFoundError(f"{path}: give the path of a sentencepiece model")
    model = sentencepiece.SentencePieceProcessor(model_file=path)
    pieces = {model.id_to_piece(k).lower() for k in range(model.get_piece_size()) if not (model.is_control(k) or model.is_unknown(k) or model.is_byte(k))}
    return sorted(p for p in pieces if p)


class Lattice:
    """Finds pieces in many words at once by hashes of their signs."""

    BASE = np.uint64(0x9E3779B97F4A7C15 | 1)

    def __init__(self, pieces: list[str]):
        self.pieces = pieces
        self.longest = max((len(p) for p in pieces), default=1)
        self.by_length: dict[int, tuple[np.ndarray, np.ndarray]] = {}
        for n in sorted({len(p) for p in pieces}):
            ids = [k for k, p in enumerate(pieces) if len(p) == n]
            codes = np.array([[ord(c) for c in pieces[k]] for k in ids], np.uint64)
            keys = self.hash_rows(codes)
            order = np.argsort(keys)
            self.by_length[n] = keys[order], np.array(ids)[order]

    def hash_rows(self, codes: np.ndarray) -> np.ndarray:
        out = np.zeros(len(codes), np.uint64)
        for k in range(codes.shape[1]):
            out = (out ^ (codes[:, k] + np.uint64(k + 1))) * self.BASE
            out ^= out >> np.uint64(29)
        return out

    def find(self, codes: np.ndarray, start: int, n: int) -> np.ndarray:
        """Piece of each row's signs start .. start + n, or -1; the hash is 64 bits wide."""
        if n not in self.by_length:
            return np.full(len(codes), -1)
        keys, ids = self.by_length[n]
        want = self.hash_rows(codes[:, start : start + n])
        at = np.minimum(np.searchsorted(keys, want), len(keys) - 1)
        return np.where(keys[at] == want, ids[at], -1)

    def edges(self, codes: np.ndarray) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
        """(start, end, rows, pieces) by rising end; unknown single signs have piece -1."""
        count, length = codes.shape
        if count >= 16:
            for end in range(1, length + 1):
                for n in range(1, min(self.longest, end) + 1):
                    if n in self.by_length or n == 1:
                        found = self.find(codes, end - n, n)
                        rows = np.flatnonzero(found >= 0) if n > 1 else np.arange(count)
                        if len(rows):
                            yield end - n, end, rows, found[rows]
            return
        # Few words, maybe very long ones: all places of one length at once, one word at a time.
        hits: list[list[tuple[int, int, int, int]]] = []
        for row in range(count):
            for n in range(1, min(self.longest, length) + 1):
                if n in self.by_length or n == 1:
                    found = self.find(np.lib.stride_tricks.sliding_window_view(codes[row], n), 0, n)
                    at = np.flatnonzero(found >= 0) if n > 1 else np.arange(len(found))
                    hits.append(np.stack([at + n, np.full(len(at), n), np.full(len(at), row), found[at]], 1))
        flat = np.concatenate(hits) if hits else np.zeros((0, 4), np.int64)
        flat = flat[np.lexsort((flat[:, 2], flat[:, 1], flat[:, 0]))]
        begins = np.flatnonzero(np.concatenate([[True], (flat[1:, :2] != flat[:-1, :2]).any(1)])) if len(flat) else []
        for a, b in zip(begins, [*begins[1:], len(flat)]):
            end, n = int(flat[a, 0]), int(flat[a, 1])
            yield end - n, end, flat[a:b, 2], flat[a:b, 3]


def by_length(words: list[str]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(places, sign codes with the word mark in front) of the words of each length."""
    groups: dict[int, list[int]] = {}
    for k, word in enumerate(words):
        groups.setdefault(len(word), []).append(k)
    steps = ((length, all_places[a : a + max(1, STEP_SIGNS // (length + 1))]) for length, all_places in groups.items() for a in range(0, len(all_places), max(1, STEP_SIGNS // (length + 1))))
    for length, places in steps:
        flat = "".join(MARK + words[k] for k in places).encode("utf-32-le", "surrogatepass")
        yield np.array(places), np.frombuffer(flat, np.uint32).reshape(len(places), length + 1).astype(np.uint64)


class Model:
    """Log probabilities of pieces by language; row -1 is the unknown sign."""

    def __init__(self, pieces: list[str], languages: list[str], probabilities: np.ndarray):
        self.lattice, self.languages = Lattice(pieces), languages
        self.table = np.vstack([probabilities, np.full((1, len(languages)), SMOOTH)])

    def score(self, words: list[str]) -> np.ndarray:
        """Log probability of each word in each language."""
        out = np.zeros((len(words), len(self.languages)))
        for places, codes in by_length(words):
            out[places] = self.forward(codes)[1]
        return out

    def forward(self, codes: np.ndarray) -> tuple[list[np.ndarray | None], np.ndarray]:
        """Scaled forward sums after each sign (those that a piece can still start from), and the log of the last one.

        After each sign the sums that later pieces can still start from are divided by
        the newest one, so no length of word underflows.
        """
        count, length = codes.shape
        sums: list[np.ndarray | None] = [np.ones((count, len(self.languages)))]
        logs = np.zeros((count, len(self.languages)))
        current, at = np.zeros_like(logs), 1

        def close() -> None:
            nonlocal current
            scale = np.maximum(current, 1e-300)
            far = len(sums) - self.lattice.longest
            if far > 0:
                sums[far - 1] = None
            for k in range(max(0, far), len(sums)):
                sums[k] = sums[k] / scale
            sums.append(np.ones_like(current))
            np.add(logs, np.log(scale), out=logs)
            current = np.zeros_like(logs)
        for start, end, rows, pieces in self.lattice.edges(codes):
            if end != at:
                close()
                at = end
            if len(rows) == count:
                current += sums[start] * self.table[pieces]
            else:
                current[rows] += sums[start][rows] * self.table[pieces]
        close()
        return sums, logs


def posteriors(edges: list, length: int, count: int, table: np.ndarray, longest: int) -> Iterator[tuple[np.ndarray, tuple[np.ndarray, np.ndarray]]]:
    """(pieces, (rows, chance that the row's segmentation uses that piece there)) of every edge of words of one length.

    Logs of forward sums, and the chance that a place is a border, which falls out of them
    from the end on: nothing underflows, however long a word is.
    """
    log = np.zeros((length + 1, count))
    at = 0
    ends = [*np.flatnonzero(np.diff([e for _, e, _, _ in edges])) + 1, len(edges)] if edges else []
    for stop in ends:
        end = edges[at][1]
        top = log[max(0, end - longest) : end].max(0)
        total = np.zeros(count)
        for s, _, r, p in edges[at:stop]:
            total[r] += np.exp(log[s, r] - top[r]) * table[p]
        log[end] = np.log(total) + top
        at = stop
    border = np.zeros((length + 1, count))
    border[length] = 1.0
    for s, e, r, p in sorted(edges, key=lambda x: -x[1]):
        share = border[e, r] * np.exp(log[s, r] - log[e, r]) * table[p]
        border[s, r] += share
        yield p, (r, share)


def train(pieces: list[str], counts: dict[str, Counter], rounds: int = ROUNDS) -> Model:
    """Expectation maximisation per language on word counts."""
    languages = sorted(counts)
    columns = []
    for language in languages:
        words = sorted(counts[language])
        weight = np.array([counts[language][w] for w in words], float)
        lattice = Lattice(pieces)
        probability = np.array([1.0 / len(pieces)] * len(pieces))
        groups = [(weight[places], codes.shape[1], len(places), list(lattice.edges(codes))) for places, codes in by_length(words)]
        for _ in range(rounds):
            expected = np.zeros(len(pieces) + 1)
            table = np.append(probability, SMOOTH)
            for mass, length, count, edges in groups:
                for piece, share in posteriors(edges, length, count, table, lattice.longest):
                    expected += np.bincount(piece % len(expected), share[1] * mass[share[0]], minlength=len(expected))
            known = expected[:-1]
            probability = (known + SMOOTH * known.sum()) / (known.sum() * (1 + SMOOTH * len(pieces))) if known.sum() else probability
        columns.append(np.maximum(probability, SMOOTH))
    return Model(pieces, languages, np.array(columns).T.reshape(len(pieces), len(languages)))


_LETTERS = re.compile(r"[^\W\d_]+")


def words_of(text: str) -> list[str]:
    """Lower-case runs of letters, whole ones."""
    return _LETTERS.findall(text.lower())


def fit(documents: DataFrame, path: str = VOCABULARY, limit: int = TRAIN_DOCS) -> Model:
    """Model from at most ``limit`` labelled documents per language, those with the least scrambled doc_id."""
    known = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("lang").cast("string").alias("lang")).where("doc_id is not null and lang is not null and lang <> ''").distinct()
    order = Window.partitionBy("lang").orderBy(F.xxhash64("doc_id"), "doc_id")
    chosen = known.withColumn("n", F.row_number().over(order)).where(F.col("n") <= limit).select("doc_id", "lang").collect()
    few = documents.sparkSession.createDataFrame([tuple(r) for r in chosen], "doc_id long, lang string")
    # At most `limit` rows per language; beyond MOST_CHOSEN of them (very many languages) the join is left to shuffle.
    few = F.broadcast(few) if len(chosen) <= MOST_CHOSEN else few
    rows = documents.select("doc_id", "lang", "text").where("text is not null").join(few, ["doc_id", "lang"], "left_semi").select("lang", "text").toLocalIterator()
    counts: dict[str, Counter] = {}
    for row in rows:
        counts.setdefault(row.lang, Counter()).update(words_of(row.text))
    counts = {k: v for k, v in counts.items() if v}
    return train(vocabulary(path), counts)


def identify(documents: DataFrame, model: Model) -> DataFrame:
    """(doc_id, predicted, log_margin, words) of every row; log_margin is per word, best against second."""
    languages = model.languages

    def run(batches):
        index: dict[str, int] = {}
        scores = np.zeros((0, max(1, len(languages))))
        for batch in batches:
            texts = [Counter(words_of(t)) if t else {} for t in batch.column("text").to_pylist()]
            if len(index) > 2_000_000:
                index, scores = {}, scores[:0]
            fresh = list({w for t in texts for w in t if w not in index})
            if fresh and languages:
                index.update(zip(fresh, range(len(scores), len(scores) + len(fresh))))
                scores = np.concatenate([scores, model.score(fresh)])
            best, margin, sizes = [], [], []
            for text in texts:
                total = sum(text.values())
                sizes.append(total)
                if not total or not languages:
                    best.append("und")
                    margin.append(0.0)
                    continue
                at = np.fromiter((index[w] for w in text), np.int64, len(text))
                sums = np.fromiter(text.values(), float, len(text)) @ scores[at]
                order = np.argsort(-sums, kind="stable")
                best.append(languages[order[0]])
                margin.append(float(sums[order[0]] - sums[order[1]]) / total if len(order) > 1 else 0.0)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id").cast(pa.int64()), pa.array(best, pa.string()), pa.array([round(m, 6) for m in margin], pa.float64()), pa.array(sizes, pa.int64())], ["doc_id", "predicted", "log_margin", "words"])

    return documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id long, predicted string, log_margin double, words long")
