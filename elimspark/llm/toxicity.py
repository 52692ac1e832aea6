"""Toxicity by a weighted lexicon, matched by Aho-Corasick on folded text.

Folding maps look-alike letters, full-width forms, accents and digit substitutions to
one letter each, for the lexicon and the text alike, so no spelling of a term needs an
entry of its own. A substitution sign at the end of a word may be punctuation as well:
the readings are searched, and a word counts once. A match counts where it starts a word; an entry that ends in ``*``
matches any ending, the others must end the word too. Where several entries match in one
word the largest weight counts. Matches inside an exception phrase count nothing.
The score is the sum of weights per 100 words (at least ``MIN_WORDS`` words).

The lexicon is a public seed list plus entries learned from labelled documents: words
and word beginnings whose share of toxic documents exceeds that of clean ones by far,
as many as the sample has, weighted by the logarithm of that ratio. Learning reads at most ``MAX_LABELLED`` labelled
documents of each class; the cut score is the one that best separates a held-out
quarter of them, scored with the lexicon of the rest.

Edge cases: null or empty text scores 0; a null doc_id keeps its row; rows are scored one
by one, so repeated rows give repeated results; an empty table gives no rows; other columns
are not looked at; without labels the seed list is used alone.
"""

from __future__ import annotations

import math
import re
import unicodedata
from collections import Counter
from collections.abc import Iterable

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import keep_where

#: Labelled documents of each class that the lexicon is learned from.
MAX_LABELLED = 4000
MIN_WORDS = 20
#: Learned entries need this many toxic documents and this log ratio.
MIN_DOCS, MIN_WEIGHT = 3, 3.0
STEMS = range(4, 9)
#: Signs that stand for letters, at the end of a word.
TAIL = re.compile(r"[!|$@€£]+(?![\w!|$@€£])")
#: Of these the ones that are punctuation first, behind the others.
MARKS = re.compile(r"[!|]+(?![\w!|$@€£])")

SEED = {
    **dict.fromkeys("idiot idiots moron morons stupid scum trash pathetic worthless disgusting loser losers clown clowns".split(), 6.0),
    **dict.fromkeys("dumbass imbecile imbeciles retard retarded cretin degenerate vermin filth jackass dimwit halfwit".split(), 6.0),
    **dict.fromkeys("asshole bastard bitch bullshit fuck* shit shitty whore slut* dickhead wanker".split(), 6.0),
}
EXCEPTIONS = ("trash can", "trash bin", "trash bag", "clown fish", "circus clown", "shit happens", "pond scum", "soap scum")
#: Cut score when nothing is labelled: one seed word in 250.
DEFAULT_CUT = 2.4

_LOOKALIKE = {
    "а": "a", "в": "b", "е": "e", "ё": "e", "к": "k", "м": "m", "н": "h", "о": "o", "р": "p", "с": "c", "т": "t", "у": "y", "х": "x", "і": "i", "ї": "i", "ј": "j", "ѕ": "s", "ԁ": "d", "ӏ": "i", "ѵ": "v", "ԛ": "q", "ԝ": "w",
    "α": "a", "β": "b", "γ": "y", "ε": "e", "η": "n", "ι": "i", "κ": "k", "ν": "v", "ο": "o", "ρ": "p", "σ": "o", "τ": "t", "υ": "u", "χ": "x", "ω": "w", "ɑ": "a", "ɡ": "g", "ı": "i", "ɩ": "i", "ꞵ": "b", "ß": "s", "ø": "o", "đ": "d", "ł": "i", "æ": "a", "œ": "o",
    "0": "o", "1": "i", "3": "e", "4": "a", "5": "s", "7": "t", "8": "b", "9": "g", "@": "a", "$": "s", "!": "i", "|": "i", "l": "i", "€": "e", "£": "i",
}


class _Fold(dict):
    """Translation table of str.translate, filled as characters are met.

    ``l`` folds to ``i`` as 1, ! and | do, in texts and lexicon alike.
    """

    def __missing__(self, code: int) -> int | str:
        char = chr(code)
        if unicodedata.combining(char) or unicodedata.category(char) == "Cf":
            out: int | str = ""
        else:
            base = unicodedata.normalize("NFKD", char.lower())
            base = next((c for c in base if not unicodedata.combining(c)), " ")
            base = _LOOKALIKE.get(base, base)
            out = base if base.isalnum() else " "
        self[code] = out
        return out


_FOLD = _Fold()


def fold(text: str) -> str:
    """Folded text: letters of one alphabet and spaces; every other sign is a space."""
    return text.translate(_FOLD)


def plain_ends(text: str, signs: re.Pattern = TAIL) -> str:
    """The text with spaces for substitution signs at the ends of words; as long as before."""
    return signs.sub(lambda m: " " * len(m[0]), text)


def bare(text: str) -> str:
    """A lexicon entry in folded form, its spaces single."""
    return " ".join(fold(text).split())


class Matcher:
    """Automaton over folded entries; phrases of EXCEPTIONS cancel what they cover."""

    def __init__(self, lexicon: dict[str, float], exceptions: Iterable[str] = EXCEPTIONS):
        entries: dict[str, list] = {}
        for term, weight in lexicon.items():
            open_end = term.endswith("*")
            if key := bare(term.rstrip("*")):
                slot = entries.setdefault(" " + key, [0.0, 0.0, False])
                slot[open_end] = max(slot[open_end], float(weight))
        for phrase in exceptions:
            if key := bare(phrase):
                entries.setdefault(" " + key, [0.0, 0.0, False])[2] = True
        self.automaton = ahocorasick.Automaton()
        for key, (whole, stem, excuse) in entries.items():
            self.automaton.add_word(key, (len(key), whole, stem, excuse))
        self.empty = not entries
        if not self.empty:
            self.automaton.make_automaton()

    def scan(self, text: str) -> tuple[float, int, int]:
        """(sum of weights, matched words, words) of a text."""
        plain = plain_ends(text)
        folded = fold(plain)
        words = len(folded.split())
        if self.empty or not (words or plain != text):
            return 0.0, 0, words
        best: dict[int, float] = {}
        excused: list[tuple[int, int]] = []
        # All readings fold to the same places: signs differ, not their number.
        readings = {folded} if plain == text else {folded, fold(text), fold(plain_ends(text, MARKS))}
        for reading in readings:
            padded = f" {reading} "
            for end, (length, whole, stem, excuse) in self.automaton.iter(padded):
                closed = padded[end + 1] == " "
                start = end - length + 1
                if excuse and closed:
                    excused.append((start, end))
                weight = max(stem, whole if closed else 0.0)
                if weight > best.get(start, 0.0):
                    best[start] = weight
        for a, b in excused:
            for start in [s for s in best if a <= s < b]:
                del best[start]
        return sum(best.values()), len(best), words


def score_of(weight: float, words: int) -> float:
    return 100.0 * weight / max(words, MIN_WORDS)


def learn(spark: SparkSession, documents: DataFrame, labels: DataFrame | None, limit: int = MAX_LABELLED) -> tuple[dict[str, float], float]:
    """Lexicon and cut score from at most ``limit`` labelled documents of each class."""
    if labels is None:
        return dict(SEED), DEFAULT_CUT
    known = labels.where(F.col("toxic").isin(0, 1) & F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    order = F.xxhash64("doc_id"), F.col("doc_id")
    sample = known.where("toxic = 1").orderBy(*order).limit(limit).unionByName(known.where("toxic = 0").orderBy(*order).limit(limit))
    # A quarter is held out: the cut is chosen on documents that its lexicon hasn't seen.
    part = (F.pmod(F.xxhash64("doc_id", F.lit("part")), F.lit(4)) == 0).alias("held")
    texts = documents.select("doc_id", "text").join(F.broadcast(sample), "doc_id").select("text", "toxic", part)

    def features(batches):
        counts: Counter = Counter()
        for batch in batches:
            for text, toxic, held in zip(*(batch.column(c).to_pylist() for c in ("text", "toxic", "held"))):
                words = set(fold(plain_ends(text or "")).split())
                seen = words | {w[:k] + "*" for w in words for k in STEMS if len(w) >= k}
                counts.update((x, toxic, held) for x in seen)
                counts[("", toxic, held)] += 1
        keys = list(counts)
        yield pa.RecordBatch.from_arrays([pa.array([k[0] for k in keys], pa.string()), pa.array([int(k[1]) for k in keys], pa.int32()), pa.array([k[2] for k in keys], pa.bool_()), pa.array([counts[k] for k in keys], pa.int64())], ["term", "toxic", "held", "docs"])

    terms = texts.mapInArrow(features, "term string, toxic int, held boolean, docs long")
    total = lambda toxic, also=F.lit(True): F.sum(F.when((F.col("toxic") == toxic) & also, F.col("docs")).otherwise(0))
    per = terms.groupBy("term").agg(total(1).alias("bad"), total(0).alias("good"), total(1, ~F.col("held")).alias("bad_seen"), total(0, ~F.col("held")).alias("good_seen"))
    totals = per.where("term = ''").first()
    if totals is None or not totals.bad:
        return dict(SEED), DEFAULT_CUT

    def weight(bad: str, good: str):
        ratio = F.log((F.col(bad) + 0.5) / F.lit(totals[bad] + 1.0)) - F.log((F.col(good) + 0.5) / F.lit(totals[good] + 1.0))
        return F.when((F.col(bad) >= MIN_DOCS) & (ratio >= MIN_WEIGHT), F.round(ratio, 6)).otherwise(0.0)

    weighed = per.where("term <> ''").select("term", weight("bad", "good").alias("final"), weight("bad_seen", "good_seen").alias("trial"))
    rows = weighed.where("final > 0 or trial > 0").collect()

    def lexicon(column: str) -> dict[str, float]:
        return SEED | {r.term: max(SEED.get(r.term, 0.0), r[column]) for r in rows if r[column]}

    trial = lexicon("trial")

    def judge(batches):
        matcher = Matcher(trial)
        for batch in batches:
            found = [matcher.scan(t or "") for t in batch.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array([score_of(w, n) for w, _, n in found], pa.float64()), pa.array(batch.column("toxic").to_pylist(), pa.int32())], ["score", "toxic"])

    scores = texts.where("held").select("text", "toxic").mapInArrow(judge, "score double, toxic int").collect()
    return lexicon("final"), best_cut([r.score for r in scores if r.toxic == 1], [r.score for r in scores if r.toxic == 0])


def best_cut(toxic: list[float], clean: list[float]) -> float:
    """The cut that misjudges the smallest shares of both classes, a clean document counting ten times."""
    if not toxic:
        return DEFAULT_CUT
    a, b = np.sort(np.asarray(toxic)), np.sort(np.asarray(clean))
    cuts = np.unique(np.concatenate([a[a > 0], [DEFAULT_CUT]]))
    missed = np.searchsorted(a, cuts, side="left") / len(a)
    wrong = (len(b) - np.searchsorted(b, cuts, side="left")) / max(1, len(b))
    return float(cuts[np.argmin(missed + 10.0 * wrong)]) * (1 - 1e-9)


def score(documents: DataFrame, lexicon: dict[str, float], cut: float) -> DataFrame:
    """Every row with ``toxic_hits``, ``words``, ``toxic_score`` and ``rejected``; only doc_id is carried."""
    matcher_of = lexicon

    def run(batches):
        matcher = Matcher(matcher_of)
        for batch in batches:
            found = [matcher.scan(t) if t else (0.0, 0, 0) for t in batch.column("text").to_pylist()]
            scores = [round(score_of(w, n), 6) for w, _, n in found]
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id").cast(pa.int64()), pa.array([h for _, h, _ in found], pa.int64()), pa.array([n for _, _, n in found], pa.int64()), pa.array(scores, pa.float64()), pa.array([s >= cut for s in scores], pa.bool_())],
                ["doc_id", "toxic_hits", "words", "toxic_score", "rejected"],
            )

    return documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id long, toxic_hits long, words long, toxic_score double, rejected boolean")


def keep_clean(documents: DataFrame, lexicon: dict[str, float], cut: float) -> DataFrame:
    """The rows whose text is not rejected, all columns unchanged, in one pass without a join."""

    def judge_of():
        matcher = Matcher(lexicon)

        def clean(text):
            weight, _, words = matcher.scan(text) if text else (0.0, 0, 0)
            return round(score_of(weight, words), 6) < cut

        return clean

    return keep_where(documents, F.col("text"), judge_of)


def weight_of_ratio(bad: int, good: int, all_bad: int, all_good: int) -> float:
    """The learned weight, for tests."""
    return math.log((bad + 0.5) / (all_bad + 1.0)) - math.log((good + 0.5) / (all_good + 1.0))
