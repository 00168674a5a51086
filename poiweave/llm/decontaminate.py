"""Benchmark decontamination by Wu-Manber multi-pattern search over words.

Every window of a benchmark item (``window`` consecutive words; a shorter item is one window)
is a pattern. Patterns of one length share tables over their words: a shift table
tells for a block of two words how far the search may jump; where it may not, the block's hash names a bucket of the patterns that end with it, of which
those that also begin with the words met are compared with the text, word hashes first and then bytes. Many stretches of
text are searched in lockstep, each with its own position, so the jumps stay and the loop is numpy.

The tables are arrays, built once on the driver from the streamed benchmark, in blocks of at most ``block_patterns`` patterns (about 60 bytes each), and broadcast;
a worker searches all blocks in turn.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .textkit import Words, as_bytes, byte_chunks, hash_words, split_words

WINDOW = 10
BLOCK_PATTERNS = 2_000_000
_STRETCH = 512
_BITS = 20
_PAIR = np.uint64(0xD6E8FEB86659FD93)


def pair_hash(first: np.ndarray, second: np.ndarray | None) -> np.ndarray:
    """A hash of a block of two words, or of one."""
    h = first if second is None else second + first * _PAIR
    h = h * _PAIR
    return h ^ (h >> np.uint64(29))


def fold(hashes: np.ndarray) -> np.ndarray:
    """One hash for each row of word hashes."""
    out = np.zeros(len(hashes), dtype=np.uint64)
    for k in range(hashes.shape[1]):
        out = (out ^ hashes[:, k]) * _PAIR
        out ^= out >> np.uint64(31)
    return out


@dataclass
class Patterns:
    """The patterns of one length in a block's words: ``at`` has each one's first word, in the order of the keys of their buckets and beginnings."""

    length: int
    shift: np.ndarray
    buckets: np.ndarray  #: sorted hashes of last blocks
    keys: np.ndarray  #: sorted hashes of last and first blocks
    at: np.ndarray
    owners: np.ndarray  #: items of all patterns behind each other
    first_owner: np.ndarray

    @staticmethod
    def of(length: int, at: np.ndarray, item: np.ndarray, words: Words, hashes: np.ndarray) -> Patterns:
        """Tables for windows at words ``at`` of items ``item``; equal windows become one pattern with several owners."""
        rows = hashes[at[:, None] + np.arange(length)]
        whole = fold(rows)
        order = np.lexsort((item, whole))
        at, item, whole, rows = at[order], item[order], whole[order], rows[order]
        fresh = np.append(True, whole[1:] != whole[:-1])
        leader = at[np.maximum.accumulate(np.where(fresh, np.arange(len(at)), 0))]
        for k in np.flatnonzero(~fresh).tolist():  # equal hashes: bytes decide
            fresh[k] = said(words, int(at[k]), length) != said(words, int(leader[k]), length)
        one = np.flatnonzero(fresh)
        block = min(2, length)
        last = pair_hash(rows[one, length - block], rows[one, length - 1] if block == 2 else None)
        begin = pair_hash(rows[one, 0], rows[one, 1] if block == 2 else None)
        keys = fold(np.stack([last, begin], axis=1))
        place = np.argsort(keys, kind="stable")
        counts = np.diff(np.append(one, len(at)))[place]
        shift = np.full(1 << _BITS, length - block + 1, dtype=np.uint16)
        for end in range(block, length + 1):
            met = pair_hash(rows[one, end - block], rows[one, end - 1] if block == 2 else None)
            np.minimum.at(shift, slots(met), np.uint16(length - end))
        first_owner = np.append(0, np.cumsum(counts))
        owners = item[np.repeat(one[place] - first_owner[:-1], counts) + np.arange(len(item))]
        return Patterns(length, shift, np.unique(last), keys[place], at[one][place], owners, first_owner)

    def find(self, h: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Candidates (index of the first word, index of the pattern); ``first`` bounds the texts."""
        m, block = self.length, min(2, self.length)
        nothing = np.empty(0, np.int64), np.empty(0, np.int64)
        counts = np.diff(first)
        cuts = np.maximum(0, -(-(counts - m + 1) // _STRETCH))
        text = np.repeat(np.arange(len(counts)), cuts)
        if not len(text):
            return nothing
        nth = np.arange(len(text)) - np.repeat(np.cumsum(cuts) - cuts, cuts)
        at = first[text] + nth * _STRETCH + m - 1  # the last word under the pattern
        stop = np.minimum(at + _STRETCH, first[text + 1])
        ends, lasts = [], []
        while len(at):
            last = pair_hash(h[at - block + 1], h[at] if block == 2 else None)
            jump = self.shift[slots(last)].astype(np.int64)
            met = np.flatnonzero(jump == 0)
            if len(met):
                ends.append(at[met])
                lasts.append(last[met])
            at = at + np.maximum(jump, 1)
            going = at < stop
            at, stop = at[going], stop[going]
        if not ends:
            return nothing
        end, last = np.concatenate(ends), np.concatenate(lasts)
        bucket = np.minimum(np.searchsorted(self.buckets, last), len(self.buckets) - 1)
        in_bucket = self.buckets[bucket] == last
        begin, last = end[in_bucket] - m + 1, last[in_bucket]
        key = fold(np.stack([last, pair_hash(h[begin], h[begin + 1] if block == 2 else None)], axis=1))
        low, high = np.searchsorted(self.keys, key, side="left"), np.searchsorted(self.keys, key, side="right")
        n = high - low
        return np.repeat(begin, n), np.repeat(low - np.append(0, np.cumsum(n))[:-1], n) + np.arange(n.sum())


def slots(block: np.ndarray) -> np.ndarray:
    return (block >> np.uint64(64 - _BITS)).astype(np.int64)


def said(words: Words, at: int, length: int) -> list[bytes]:
    """The words of a window."""
    return [words.low[a:b].tobytes() for a, b in zip(words.starts[at : at + length].tolist(), words.ends[at : at + length].tolist(), strict=True)]


@dataclass
class Block:
    """Some benchmark items: their words and the patterns of every length."""

    words: Words
    hashes: np.ndarray
    patterns: list[Patterns]

    @staticmethod
    def of(items: list[tuple[int, str | None]], window: int) -> Block:
        words = split_words([(text or "").encode() for _, text in items])
        hashes, counts, ids = hash_words(words), words.counts, np.array([i for i, _ in items], np.int64)
        lengths = np.minimum(window, counts)
        windows = np.where(counts > 0, counts - lengths + 1, 0)
        patterns = []
        for m in np.unique(lengths[lengths > 0]).tolist():
            own = np.flatnonzero(lengths == m)
            n = windows[own]
            at = np.repeat(words.first[own] - np.append(0, np.cumsum(n))[:-1], n) + np.arange(n.sum())
            patterns.append(Patterns.of(m, at, np.repeat(ids[own], n), words, hashes))
        return Block(words, hashes, patterns)

    def search(self, w: Words, h: np.ndarray, cover: np.ndarray, items: list[set[int]]) -> None:
        """Add what occurs in the texts of ``w`` to ``cover`` (starts and ends of hits over words) and to their ``items``."""
        for p in self.patterns:
            begin, which = p.find(h, w.first)
            step = np.arange(p.length)
            same = (h[begin[:, None] + step] == self.hashes[p.at[which][:, None] + step]).all(axis=1)
            begin, which = begin[same], which[same]
            doc = np.searchsorted(w.first, begin, side="right") - 1
            for b, k, d in zip(begin.tolist(), which.tolist(), doc.tolist(), strict=True):
                if said(w, b, p.length) == said(self.words, int(p.at[k]), p.length):
                    cover[b] += 1
                    cover[b + p.length] -= 1
                    items[d].update(p.owners[p.first_owner[k] : p.first_owner[k + 1]].tolist())


def search(blocks: list[Block], texts: list[bytes]) -> tuple[np.ndarray, list[np.ndarray], list[set[int]]]:
    """Words, a hit mask and the items that occur, for every text."""
    w = split_words(texts)
    h = hash_words(w)
    cover = np.zeros(len(h) + 1, dtype=np.int32)
    items: list[set[int]] = [set() for _ in texts]
    for block in blocks:
        block.search(w, h, cover, items)
    hit = np.cumsum(cover[:-1]) > 0
    return w.counts, [hit[a:b] for a, b in zip(w.first[:-1].tolist(), w.first[1:].tolist(), strict=True)], items


def benchmark_blocks(benchmark: DataFrame, window: int, most: int) -> list[Block]:
    """Tables of all items (item_id, text), which are streamed through the driver; a block has at most ``most`` patterns, or one item."""
    blocks, held, size = [], [], 0
    for row in benchmark.toLocalIterator():
        n = max(1, len(row[1] or "") // 2 - window)  # no text has more windows
        if held and size + n > most:
            blocks.append(Block.of(held, window))
            held, size = [], 0
        held.append((row[0], row[1]))
        size += n
    return [*blocks, Block.of(held, window)] if held else blocks


def find_contamination(documents: DataFrame, benchmark: DataFrame, window: int = WINDOW, block_patterns: int = BLOCK_PATTERNS, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """Per document: the columns ``keep``, n_words, n_hit, item_ids (array of long, sorted as strings), hit_mask (binary, one bit a word).

    Null and empty texts have no words. Items without words give no pattern; items without an id
    are left out. Repeated items count once by id; repeated documents each get their row.
    Extra columns are ignored unless named in ``keep``; an empty table gives an empty result.
    """
    if window < 1:
        raise ValueError("window must be at least 1")
    text = "text" if "text" in keep else "__text"
    columns = [F.col(k) for k in keep] + [F.col("text").alias(text)] * (text not in keep)
    chosen = benchmark.select(F.col("item_id").cast("long"), F.col("text")).filter("item_id is not null").dropDuplicates()
    blocks = documents.sparkSession.sparkContext.broadcast(benchmark_blocks(chosen, window, block_patterns))
    wanted = [F.lit(0).cast("long").alias("__n"), F.lit(0).cast("long").alias("__hit"), F.lit(None).cast("binary").alias("__mask"), F.array().cast("array<bigint>").alias("__items")]
    rows = documents.select(*columns, *wanted)

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in byte_chunks(whole, text):
                old = {f.name: b.column(i) for i, f in enumerate(b.schema)}
                counts, hits, items = search(blocks.value, as_bytes(old[text]))
                sums = [int(hit.sum()) for hit in hits]
                masks = [np.packbits(hit).tobytes() if n else None for hit, n in zip(hits, sums, strict=True)]
                ids = [sorted(own, key=str) for own in items]
                old |= {"__n": pa.array(counts, pa.int64()), "__hit": pa.array(sums, pa.int64()), "__mask": pa.array(masks, pa.binary()), "__items": pa.array(ids, pa.list_(pa.int64()))}
                yield pa.RecordBatch.from_arrays([old[f.name] for f in b.schema], names=b.schema.names)

    out = rows.mapInArrow(scan, rows.schema)
    return out.select(*keep, F.col("__n").alias("n_words"), F.col("__hit").alias("n_hit"), F.col("__items").alias("item_ids"), F.col("__mask").alias("hit_mask"))


def decontaminate(documents: DataFrame, benchmark: DataFrame, window: int = WINDOW) -> DataFrame:
    """The documents in which no window of any item occurs, with all their columns."""
    names = tuple(documents.columns)
    return find_contamination(documents, benchmark, window, keep=names).filter("n_hit = 0").select(*names)


def digest(found: DataFrame) -> DataFrame:
    """The columns that the query returns."""
    return found.select(
        "doc_id",
        "n_words",
        "n_hit",
        F.size("item_ids").cast("long").alias("n_items"),
        F.sha2(F.array_join(F.transform("item_ids", lambda x: x.cast("string")), ","), 256).alias("items_sha256"),
        (F.col("n_hit") > 0).alias("contaminated"),
    )
