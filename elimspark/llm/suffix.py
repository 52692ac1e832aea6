"""Repeated passages by suffix sorting: every place where ``LENGTH`` or more words repeat.

A word position is repeated if it lies in a window of LENGTH words (split at white space,
compared exactly) that stands in two places of the corpus, in one document or two. The
result is the maximal runs of repeated positions of each document.

Only windows that can repeat are sorted. Each window has an anchor, the run of ``ANCHOR``
words inside it with the least hash; equal windows have equal anchors at equal places, and
the windows of one anchor follow one another, so a document is cut into few segments, each
the text of one anchor's windows. Segments whose anchor stands nowhere else are done;
segments that are equal as a whole repeat as a whole. The others of an anchor are brought
together and the suffixes at their window starts are sorted deep-shallow: multikey
quicksort on the words to depth ``SHALLOW``, then, for the suffixes that are still equal,
blind tries, which branch on the first differing words only and are read in order. Each
suffix is compared with its neighbours in order: LENGTH common words mean a repeat.
Hashes (64 bits) choose and pre-fold segments, and suffixes whose tails share a 64-bit
stamp are taken as equal without a trie; all others that are sorted are compared by words.

Edge cases: null, empty and short texts have no windows; null doc_ids give rows with a
null doc_id, each text apart; rows that share a doc_id are documents of their own; rows
equal in doc_id and text repeat each other and are reported once; no length of text or
number of copies is cut.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import NONSPACE, U64, Scratch, Words, mix64, ngram_hashes, text_arrays

LENGTH, ANCHOR, SHALLOW = 50, 20, 24


def window_minima(keys: np.ndarray, width: int) -> np.ndarray:
    """Place of the least key (the first of equals) in every run of ``width`` keys: two scans over blocks."""
    n = len(keys)
    blocks = -(-n // width)
    padded = np.full(blocks * width, np.iinfo(np.uint64).max, U64)
    padded[:n] = keys
    grid = padded.reshape(blocks, width)
    place = np.arange(blocks * width).reshape(blocks, width)
    ahead, back = place.copy(), place.copy()
    for k in range(1, width):
        keep = grid[:, k] < padded[ahead[:, k - 1]]
        ahead[:, k] = np.where(keep, place[:, k], ahead[:, k - 1])
        j = width - 1 - k
        keep = grid[:, j] <= padded[back[:, j + 1]]
        back[:, j] = np.where(keep, place[:, j], back[:, j + 1])
    ahead, back = ahead.ravel(), back.ravel()
    starts = np.arange(n - width + 1)
    a, b = back[starts], ahead[starts + width - 1]
    return np.where(padded[b] < padded[a], b, a)


def segments(words: Words, length: int = LENGTH, anchor: int = ANCHOR) -> dict[str, np.ndarray]:
    """Segments of a slice of texts: document, first and last window, anchor hash and whole hash."""
    keys, at = ngram_hashes(words, anchor)
    width = length - anchor + 1
    names = ("doc", "low", "high", "anchor", "offset")
    if len(keys) < width:
        return {n: np.zeros(0, np.int64) for n in (*names, "whole")}
    # Anchors of one document are consecutive, so a window is whole if its first and last anchor start width - 1 words apart.
    best = window_minima(keys, width)
    first = np.arange(len(best))
    good = (at[first + width - 1] - at[first] == width - 1) & (words.doc[at[first + width - 1]] == words.doc[at[first]])
    first, best = first[good], best[good]
    if not len(first):
        return {n: np.zeros(0, np.int64) for n in (*names, "whole")}
    start = at[first]
    new = np.concatenate([[True], (np.diff(best) != 0) | (np.diff(start) != 1)])
    low = start[new]
    high = np.append(start[np.flatnonzero(new)[1:] - 1], start[-1])
    anchors = best[new]
    doc = words.doc[low]
    # A hash of all words of the segment, by prefix sums of words weighted by place.
    power = np.multiply.accumulate(np.full(len(words.hashes) + 1, 0xD1342543DE82EF95, U64))
    inverse = np.multiply.accumulate(np.full(len(words.hashes) + 1, pow(0xD1342543DE82EF95, -1, 1 << 64), U64))
    sums = np.concatenate([np.zeros(1, U64), np.cumsum(words.hashes * power[:-1], dtype=U64)])
    whole = mix64((sums[high + length] - sums[low]) * inverse[low]) ^ mix64((high - low).astype(U64) ^ mix64((at[anchors] - low).astype(U64)))
    return {"doc": doc, "low": low - words.first[doc], "high": high - words.first[doc], "anchor": keys[anchors].view(np.int64), "offset": at[anchors] - low, "whole": whole.view(np.int64), "first": low, "last": high + length - 1}


def _cut(batches):
    for batch in batches:
        for start, stop, texts in text_arrays(batch, "text"):
            words = Words(texts, NONSPACE)
            found = segments(words)
            if not len(found["doc"]):
                continue
            a, b = words.starts[found["first"]], words.ends[found["last"]]
            at = pa.array(found["doc"])
            rows, ids = (batch.column(c).slice(start, stop - start).take(at) for c in ("row", "doc_id"))
            yield pa.RecordBatch.from_arrays(
                [rows, ids, pa.array(found["low"].astype(np.int32)), pa.array(found["high"].astype(np.int32)), pa.array(found["anchor"]), pa.array(found["whole"]), pa.array((a - words.offsets[found["doc"]]).astype(np.int64)), pa.array((b - a).astype(np.int32))],
                ["row", "doc_id", "low", "high", "anchor", "whole", "byte", "bytes"],
            )


class BlindTrie:
    """Patricia trie over suffixes with a long common prefix; edges keep depths and first words only.

    Suffixes are rows of ``text`` (word numbers). A new suffix goes down by branching words
    alone to some leaf, one comparison with that leaf gives the true common depth, and the
    new branch is put at that depth on the way.
    """

    def __init__(self, text: np.ndarray, starts: np.ndarray, depth: int, length: int):
        self.text, self.starts, self.depth, self.length = text, starts, depth, length
        self.root: list | int | None = None

    def insert(self, leaf: int) -> None:
        if self.root is None:
            self.root = leaf
            return
        text, start = self.text, self.starts[leaf]
        node = self.root
        while isinstance(node, list):
            node = node[1].get(int(text[start + node[0]])) if int(text[start + node[0]]) in node[1] else next(iter(node[1].values()))
        other = self.starts[node]
        differ = np.flatnonzero(text[start + self.depth : start + self.length] != text[other + self.depth : other + self.length])
        common = self.depth + int(differ[0]) if len(differ) else self.length
        parent, node = None, self.root
        while isinstance(node, list) and node[0] < common:
            parent, key = node, int(text[start + node[0]])
            if key not in node[1]:
                node[1][key] = leaf
                return
            node = node[1][key]
        if isinstance(node, list) and node[0] == common and common < self.length:
            node[1][int(text[start + common])] = leaf
            return
        if common == self.length:
            raise ValueError("equal suffixes are to be folded before")
        branch = [common, {int(text[other + common]): node, int(text[start + common]): leaf}]
        if parent is None:
            self.root = branch
        else:
            parent[1][key] = branch

    def ordered(self) -> list[tuple[int, int]]:
        """(leaf, common words with the leaf before) in suffix order."""
        out: list[tuple[int, int]] = []
        stack: list[tuple[list | int | None, int]] = [(self.root, self.depth)]
        while stack:
            node, common = stack.pop()
            if isinstance(node, list):
                keys = sorted(node[1])
                stack.extend((node[1][k], node[0]) for k in reversed(keys[1:]))
                stack.append((node[1][keys[0]], common))
            elif node is not None:
                out.append((node, common))
        return out


def deep_shallow(text: np.ndarray, starts: np.ndarray, length: int = LENGTH, shallow: int = SHALLOW) -> tuple[np.ndarray, np.ndarray]:
    """(order, common): suffixes in order of their first ``length`` words, and the words each shares with the one before.

    ``text`` holds word numbers and has ``length`` words after each start.
    """
    n, shallow = len(starts), min(shallow, length - 1)
    order = np.arange(n)
    common = np.zeros(n, np.int64)
    groups = [(0, n)] if n > 1 else []
    live = np.concatenate([np.arange(a, b) for a, b in groups]) if groups else np.zeros(0, np.int64)
    group = np.zeros(len(live), np.int64)
    # Multikey quicksort, all open groups of a depth at a time: equal parts go on to the next word.
    for depth in range(shallow):
        if not len(live):
            break
        word = text[starts[order[live]] + depth]
        by = np.lexsort((word, group))
        order[live] = order[live[by]]
        word, group = word[by], group[by]
        edge = np.concatenate([[True], (np.diff(group) != 0) | (np.diff(word) != 0)])
        split = edge & np.concatenate([[False], np.diff(group) == 0])
        common[live[split]] = depth
        group = np.cumsum(edge) - 1
        sizes = np.bincount(group)
        stay = sizes[group] > 1
        live, group = live[stay], group[stay]
    if not len(live):
        return order, common
    # Deep part: equal suffixes are folded, the distinct ones of a group go through a blind trie.
    begins = np.flatnonzero(np.concatenate([[True], np.diff(group) != 0]))
    power = np.multiply.accumulate(np.full(length, 0x9E3779B97F4A7C15, U64))
    stamp = np.zeros(len(live), U64)
    for k in range(shallow, length):
        stamp += mix64(text[starts[order[live]] + k].astype(U64) + U64(1)) * power[k]
    # A stamp only proposes: tails of one stamp are compared word by word, and told apart if they differ.
    places = starts[order[live]]
    _, first, inverse = np.unique(np.stack([group.astype(U64), stamp]), axis=1, return_index=True, return_inverse=True)
    lead = places[first[inverse.ravel()]]
    if any((text[places + k] != text[lead + k]).any() for k in range(shallow, length)):
        stamp = np.unique(np.stack([text[places + k] for k in range(shallow, length)], 1), axis=0, return_inverse=True)[1].ravel().astype(U64)
    ends = np.append(begins[1:], len(live))
    equal = np.minimum.reduceat(stamp, begins) == np.maximum.reduceat(stamp, begins)
    inner = np.ones(len(live), bool)
    inner[begins] = False
    common[live[inner & np.repeat(equal, ends - begins)]] = length
    for a, b in zip(begins[~equal], ends[~equal]):
        slots = live[a:b]
        members = order[slots]
        values, first, inverse = np.unique(stamp[a:b], return_index=True, return_inverse=True)
        trie = BlindTrie(text, starts[members], shallow, length)
        for leaf in first:
            trie.insert(int(leaf))
        at, by_value = 0, np.argsort(inverse, kind="stable")
        bounds = np.concatenate([[0], np.cumsum(np.bincount(inverse))])
        for leaf, shared in trie.ordered():
            value = inverse[leaf]
            same = by_value[bounds[value] : bounds[value + 1]]
            order[slots[at : at + len(same)]] = members[same]
            if at:
                common[slots[at]] = shared
            common[slots[at + 1 : at + len(same)]] = length
            at += len(same)
    return order, common


def repeated_windows(texts: list[bytes], counts: list[int], windows: list[int], length: int = LENGTH) -> list[np.ndarray]:
    """For the distinct segments of one anchor group (or several): which of their windows repeat.

    ``counts`` tells how often a segment stands in the corpus; ``windows`` how many windows it has.
    """
    numbers: dict[bytes, int] = {}
    parts, starts, owner = [], [], []
    at = 0
    for k, raw in enumerate(texts):
        words = raw.split()
        parts.append(np.fromiter((numbers.setdefault(w, len(numbers)) for w in words), np.int64, len(words)))
        starts.append(np.arange(at, at + windows[k]))
        owner.append(np.full(windows[k], k))
        at += len(words)
    rank = np.empty(len(numbers), np.int64)
    rank[[numbers[w] for w in sorted(numbers)]] = np.arange(len(numbers))
    text, begin, whose = rank[np.concatenate(parts)], np.concatenate(starts), np.concatenate(owner)
    order, common = deep_shallow(text, begin, length)
    hit = common >= length
    flag = np.zeros(len(begin), bool)
    flag[order[hit]] = True
    flag[order[np.flatnonzero(hit) - 1]] = True
    flag |= np.asarray(counts)[whose] > 1
    ends = np.cumsum(windows)
    return [flag[e - w : e] for e, w in zip(ends, windows)]


def _sort(length: int):
    def emit(held: list[pa.RecordBatch]):
        columns = {c: [x for b in held for x in b.column(c).to_pylist()] for c in ("anchor", "whole", "n", "windows", "text")}
        flags = repeated_windows(columns["text"], columns["n"], columns["windows"], length)
        bits = [np.packbits(f, bitorder="little").tobytes() for f in flags]
        return pa.RecordBatch.from_arrays([pa.array(columns["anchor"], pa.int64()), pa.array(columns["whole"], pa.int64()), pa.array(bits, pa.binary())], ["anchor", "whole", "bits"])

    def run(batches):
        held: list[pa.RecordBatch] = []
        size = 0
        for batch in batches:
            if not batch.num_rows:
                continue
            anchors = np.asarray(batch.column("anchor"))
            size += batch.num_rows
            if size >= 20_000 and (anchors != anchors[-1]).any():
                cut = int(np.flatnonzero(anchors != anchors[-1])[-1]) + 1
                yield emit([*held, batch.slice(0, cut)])
                held, size = [batch.slice(cut)], batch.num_rows - cut
            else:
                held.append(batch)
        if held:
            yield emit(held)

    return run


def _spans(length: int):
    def run(batches):
        for batch in batches:
            rows, starts, ends = [], [], []
            for row, lows, highs, bits in zip(batch.column("doc_id").to_pylist(), *(batch.column(c).to_pylist() for c in ("lows", "highs", "bits"))):
                hits = []
                for low, high, b in zip(lows, highs, bits):
                    if b is None:
                        hits.append((low, high))
                    else:
                        on = np.flatnonzero(np.unpackbits(np.frombuffer(b, np.uint8), bitorder="little")[: high - low + 1]) + low
                        hits.extend((int(x), int(x)) for x in on)
                hits.sort()
                now = None
                for low, high in hits:
                    if now is not None and low <= now[1]:
                        now = (now[0], max(now[1], high + length))
                    else:
                        if now is not None:
                            rows.append(row), starts.append(now[0]), ends.append(now[1])
                        now = (low, high + length)
                if now is not None:
                    rows.append(row), starts.append(now[0]), ends.append(now[1])
            yield pa.RecordBatch.from_arrays([pa.array(rows, pa.int64()), pa.array(starts, pa.int64()), pa.array(ends, pa.int64())], ["doc_id", "start_word", "end_word"])

    return run


def repeated_passages(documents: DataFrame) -> DataFrame:
    """(doc_id, start_word, end_word): maximal runs of words that lie in repeated windows; the end is exclusive."""
    spark = documents.sparkSession
    scratch = Scratch(spark, "suffix")
    rows = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).where(F.length("text") >= 2 * LENGTH - 1)
    rows = rows.withColumn("row", F.xxhash64("doc_id", "text"))
    cut = scratch.keep(rows.mapInArrow(_cut, "row long, doc_id long, low int, high int, anchor long, whole long, byte long, bytes int"), "segments")
    anchors = cut.groupBy("anchor").agg(F.count("*").alias("n")).where("n > 1")
    repeated = scratch.keep(cut.join(anchors, "anchor", "left_semi"), "repeated")
    scratch.drop(cut)
    kinds = repeated.groupBy("anchor", "whole").agg(F.count("*").alias("n"), F.min(F.struct("row", "low", "high", "byte", "bytes")).alias("one"))
    kinds = scratch.keep(kinds.withColumn("kinds", F.count("*").over(Window.partitionBy("anchor"))), "kinds")
    plain = kinds.where("kinds = 1").select("anchor", "whole", F.lit(None).cast("binary").alias("bits"))
    mixed = kinds.where("kinds > 1").select("anchor", "whole", "n", "one.*")
    text = F.expr("substring(encode(text, 'UTF-8'), cast(byte + 1 as int), bytes)")
    texts = mixed.join(rows.select("row", "text"), "row").select("anchor", "whole", "n", (F.col("high") - F.col("low") + 1).alias("windows"), text.alias("text"))
    ordered = texts.repartition("anchor").sortWithinPartitions("anchor").mapInArrow(_sort(LENGTH), "anchor long, whole long, bits binary")
    hits = repeated.select("row", "doc_id", "low", "high", "anchor", "whole").join(plain.unionByName(ordered), ["anchor", "whole"])
    per_row = hits.groupBy("row").agg(F.first("doc_id").alias("doc_id"), F.collect_list(F.struct("low", "high", "bits")).alias("hits"))
    lists = per_row.select("doc_id", F.col("hits.low").alias("lows"), F.col("hits.high").alias("highs"), F.col("hits.bits").alias("bits"))
    return lists.mapInArrow(_spans(LENGTH), "doc_id long, start_word long, end_word long")
