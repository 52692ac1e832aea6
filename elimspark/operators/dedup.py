"""Bloom filter for repeated states, vectorised, one filter per task.

A key is new if at least one of its bits was not set. Positions combine two 32-bit hashes
linearly. Each key belongs to one task by hash partitioning, so nothing is set at the same
time by two writers and no locks are needed. A :class:`BloomChain` gives the results of
inserting one key after the other, whatever the batches are.
Errors are one-sided: a new key may be called old, never the reverse.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

U64 = np.uint64


def murmur3(keys: np.ndarray, seed: int) -> np.ndarray:
    """32-bit Murmur3 of sets (words x batch of uint64), the same for every batch."""
    h = np.full(keys.shape[1], seed, np.uint32)
    for word in keys:
        for half in (word & U64(0xFFFFFFFF), word >> U64(32)):
            x = half.astype(np.uint32) * np.uint32(0xCC9E2D51)
            x = (x << np.uint32(15) | x >> np.uint32(17)) * np.uint32(0x1B873593)
            h ^= x
            h = (h << np.uint32(13) | h >> np.uint32(19)) * np.uint32(5) + np.uint32(0xE6546B64)
    h ^= np.uint32(8 * len(keys))
    for shift, factor in ((16, 0x85EBCA6B), (13, 0xC2B2AE35)):
        h = (h ^ h >> np.uint32(shift)) * np.uint32(factor)
    return h ^ h >> np.uint32(16)


class BloomBits:
    def __init__(self, items: int, bits_per_item: int = 24, hashes: int = 17):
        self.size = max(64, items * bits_per_item)
        self.hashes = hashes
        self.words = np.zeros(-(-self.size // 64), U64)

    def spots(self, keys: np.ndarray) -> np.ndarray:
        """Bit positions, hashes x batch."""
        first, second = murmur3(keys, 0).astype(U64), murmur3(keys, 0x9747B28C).astype(U64)
        return (first[None] + np.arange(self.hashes, dtype=U64)[:, None] * second[None]) % U64(self.size)

    def missing(self, keys: np.ndarray) -> np.ndarray:
        """Which keys are certainly not in the filter."""
        spots = self.spots(keys)
        return (self.words[(spots >> U64(6)).astype(np.int64)] >> (spots & U64(63)) & U64(1) == 0).any(0)

    def add(self, keys: np.ndarray) -> np.ndarray:
        """Insert keys together (words x batch); which of them were new before the batch."""
        fresh = self.missing(keys)
        spots = self.spots(keys)
        np.bitwise_or.at(self.words, (spots >> U64(6)).astype(np.int64), U64(1) << (spots & U64(63)))
        return fresh

    def add_each(self, keys: np.ndarray, step: int = 256) -> np.ndarray:
        """Insert keys in steps, so that keys of one call are held against one another as well."""
        parts = [self.add(keys[:, a : a + step]) for a in range(0, keys.shape[1], step)]
        return np.concatenate(parts) if parts else np.zeros(0, bool)


class BloomChain:
    """Filters of one size, one after the other: a full one stays for look-ups and a new one takes what follows."""

    def __init__(self, items: int, bits_per_item: int, hashes: int):
        self.items, self.make = items, lambda: BloomBits(items, bits_per_item, hashes)
        self.filters, self.used = [self.make()], 0

    def sift(self, keys: np.ndarray, step: int = 4096) -> np.ndarray:
        """Which keys (words x batch) are new, as if each were inserted before the next is looked up."""
        out = np.zeros(keys.shape[1], bool)
        at = 0
        while at < keys.shape[1]:
            if self.used >= self.items:
                self.filters.append(self.make())
                self.used = 0
            part = keys[:, at : at + step]
            unseen = np.ones(part.shape[1], bool)
            for old in self.filters[:-1]:
                unseen &= old.missing(part)
            here = np.flatnonzero(unseen)
            current = self.filters[-1]
            spots = current.spots(part[:, here]).T.ravel()
            words, masks = (spots >> U64(6)).astype(np.int64), U64(1) << (spots & U64(63))
            clear = np.flatnonzero(current.words[words] & masks == 0)
            # A key is new if it is the first of all to touch one of its bits.
            _, first = np.unique(spots[clear], return_index=True)
            fresh = np.zeros(len(here), bool)
            fresh[clear[first] // current.hashes] = True
            room = self.items - self.used
            taken, stop = len(here), part.shape[1]
            if fresh.sum() > room:
                taken = int(np.flatnonzero(fresh)[room - 1]) + 1
                stop = int(here[taken - 1]) + 1
            np.bitwise_or.at(current.words, words[: taken * current.hashes], masks[: taken * current.hashes])
            out[at + here[:taken][fresh[:taken]]] = True
            self.used += int(fresh[:taken].sum())
            at += stop
        return out


def sift_rows(batches: Iterable[tuple], items: int, bits_per_item: int, hashes: int) -> Iterator[tuple]:
    """(sets, last, ways, lost) that the filters let through, from batches of (shard, sets, last, ways).

    Rows come sorted by shard, hash, set and last, so equal sets stand side by side. ``lost``
    counts the sets that a filter took for repeats though they are none, beside the row before.
    """
    chain, shard, previous, held = None, None, None, None
    for shards, sets, last, ways in batches:
        if not sets.shape[1]:
            continue
        new = np.ones(sets.shape[1], bool)
        new[1:] = (sets[:, 1:] != sets[:, :-1]).any(0)
        new[0] = previous is None or (sets[:, 0] != previous).any()
        previous = sets[:, -1].copy()
        fresh = np.zeros(sets.shape[1], bool)
        edges = [0, *(np.flatnonzero(shards[1:] != shards[:-1]) + 1), len(shards)]
        for a, b in zip(edges, edges[1:]):
            if shards[a] != shard:
                chain, shard = BloomChain(items, bits_per_item, hashes), shards[a]
            asked = a + np.flatnonzero(new[a:b])
            fresh[asked] = chain.sift(sets[:, asked])
        missed = (new & ~fresh).astype(np.int64)
        begins = np.flatnonzero(fresh)
        lead = begins[0] if len(begins) else len(fresh)
        if held is not None:
            held[2][-1] += ways[:lead].sum()
            held[3][-1] += missed[:lead].sum()
        if len(begins):
            if held is not None:
                yield held
            held = (sets[:, begins], last[begins], np.add.reduceat(ways, begins), np.add.reduceat(missed, begins))
    if held is not None:
        yield held


def bloom_fpr(n: float, m: float, h: int) -> float:
    """Chance that a new key is called old, with n keys in m bits and h hash functions."""
    return (1.0 - np.exp(-h * n / m)) ** h


def bloom_fpr_column(n: Column, m: Column, h: Column) -> Column:
    return F.pow(F.lit(1.0) - F.exp(-h * n / m), h)
