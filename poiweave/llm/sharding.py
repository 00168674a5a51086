"""Histogram sort: shards of near equal bytes by refined splitters and one exchange.

Every row gets a 62-bit key: 32 bits of its text's hash, then 30 bits of its id's, so equal texts lie
side by side. Candidate boundaries (probes) are laid
between the known bounds of each splitter, the exact bytes and rows below each probe are
counted across all partitions, and the bounds close in until a splitter meets the tolerance or no key
is left between them. A key that is too heavy for that (repeated rows) is cut inside, after a counted number of its rows: these are numbered
across partitions by their counts, so no key needs to fit a task. Then rows move once, to slices of the key range, and get slots there.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .session import cut

KEY_TOP = 1 << 62
SLICE_BYTES = 256 << 20
PROBE_BUDGET = 1 << 15


@dataclass(frozen=True)
class Splitters:
    """Cuts of the key range into ``shards * per_shard`` slices. Left of a cut lie the rows with smaller keys, and the first ``within`` rows of its own key."""

    keys: np.ndarray
    within: np.ndarray
    rows_below: np.ndarray
    bytes_below: np.ndarray
    shards: int
    per_shard: int
    rounds: int

    def heavy(self) -> list[int]:
        """Keys with a cut inside."""
        return np.unique(self.keys[self.within > 0]).tolist()

    def slices(self, key: np.ndarray, rank: np.ndarray | None = None) -> np.ndarray:
        """The slice of every row by its key and, for heavy keys, its number among the rows of the key."""
        if rank is None:
            return np.searchsorted(self.keys, key, side="right").astype(np.int64)
        out = np.searchsorted(self.keys, key, side="left").astype(np.int64)
        for k in self.heavy():
            own = key == k
            out[own] += np.searchsorted(self.within[self.keys == k], rank[own], side="right")
        return out


def text_size(text: Column) -> Column:
    """UTF-8 bytes of a text (null: none) plus one."""
    return (F.octet_length(F.coalesce(text, F.lit(""))) + 1).cast("long")


def row_key(doc_id: Column, text: Column) -> Column:
    """The 62-bit key; null ids and texts have keys of their own."""
    high = F.shiftrightunsigned(F.xxhash64(text), 32)
    return F.shiftleft(high, 30).bitwiseOR(F.xxhash64(F.lit(7), doc_id).bitwiseAND(F.lit((1 << 30) - 1)))


def count_below(keyed: DataFrame, probes: np.ndarray) -> tuple[np.ndarray, np.ndarray, int, int]:
    """Exact bytes and rows with keys below each probe, and the totals. Partitions count locally first."""

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        size, rows = np.zeros(len(probes) + 1, np.int64), np.zeros(len(probes) + 1, np.int64)
        for b in batches:
            at = np.searchsorted(probes, b.column(0).to_numpy(), side="right")
            np.add.at(size, at, b.column(1).to_numpy())
            rows += np.bincount(at, minlength=len(rows))
        used = np.flatnonzero(rows)
        yield pa.RecordBatch.from_arrays([pa.array(used), pa.array(size[used]), pa.array(rows[used])], names=["at", "size", "rows"])

    counted = keyed.mapInArrow(local, "at long, size long, rows long").groupBy("at").agg(F.sum("size"), F.sum("rows")).collect()
    size, rows = np.zeros(len(probes) + 1, np.int64), np.zeros(len(probes) + 1, np.int64)
    for at, s, n in counted:
        size[at], rows[at] = s, n
    return np.cumsum(size)[:-1], np.cumsum(rows)[:-1], int(size.sum()), int(rows.sum())


def find_splitters(keyed: DataFrame, shards: int, tolerance: float, slice_bytes: int = SLICE_BYTES) -> Splitters:
    """Splitters of ``keyed`` (key, size): shard cuts within ``tolerance`` of a shard's bytes, slice cuts within a quarter of a slice."""
    _, _, total, rows = count_below(keyed, np.array([KEY_TOP >> 1], np.int64))
    per = max(4, -(-total // (shards * slice_bytes)))
    n = shards * per - 1
    goal = (np.arange(1, n + 1, dtype=object) * total // (n + 1)).astype(np.int64)
    tight = np.arange(1, n + 1) % per == 0
    allowed = np.where(tight, tolerance * total / shards, 0.25 * total / (shards * per))
    low, high = np.zeros(n, np.int64), np.full(n, KEY_TOP, np.int64)
    low_b, high_b = np.zeros(n, np.int64), np.full(n, total, np.int64)
    low_r, high_r = np.zeros(n, np.int64), np.full(n, rows, np.int64)
    rounds = 0
    while True:
        near = np.minimum(goal - low_b, high_b - goal)
        open_ = np.flatnonzero((near > allowed) & (high - low > 1))
        if not len(open_):
            break
        rounds += 1
        steps = max(2, min(255, PROBE_BUDGET // len(open_)))
        width = (high[open_] - low[open_])[:, None]
        share = np.arange(1, steps)[None, :]
        probes = np.unique(low[open_][:, None] + np.maximum(1, width // steps) * np.minimum(share, width - 1))
        below, count, _, _ = count_below(keyed, probes)
        at = np.searchsorted(below, goal, side="right")  # probes[:at] have at most the goal below them
        left, right = at - 1, np.minimum(at, len(probes) - 1)
        up = (left >= 0) & (probes[np.maximum(left, 0)] > low)
        low, low_b, low_r = np.where(up, probes[left], low), np.where(up, below[left], low_b), np.where(up, count[left], low_r)
        down = (at < len(probes)) & (probes[right] < high)
        high, high_b, high_r = np.where(down, probes[right], high), np.where(down, below[right], high_b), np.where(down, count[right], high_r)
    # one key between the bounds, and neither side near enough: the cut goes inside the key (its rows are as long as each other)
    inside = (near > allowed) & (high_r - low_r > 1)
    each = (high_b - low_b) / np.maximum(1, high_r - low_r)
    within = np.where(inside, np.rint((goal - low_b) / np.maximum(each, 1e-9)), 0).astype(np.int64)
    within = np.clip(within, 0, high_r - low_r)
    take_low = inside | (goal - low_b <= high_b - goal)
    keys, b, r = np.where(take_low, low, high), np.where(take_low, low_b, high_b), np.where(take_low, low_r, high_r)
    return Splitters(keys, within, r + within, b + (within * each).astype(np.int64), shards, per, rounds)


def _numbered(rows: DataFrame, key: str, order: list[str]) -> DataFrame:
    """``rows`` of heavy keys plus ``__nth``, their number among the rows of their key: counts by partition, then places inside the partition."""
    held = cut(rows.withColumn("__part", F.spark_partition_id()))
    counts = held.groupBy(key, "__part").agg(F.count(F.lit(1)).alias("__rows"))
    earlier = F.sum("__rows").over(Window.partitionBy(key).orderBy("__part").rowsBetween(Window.unboundedPreceding, -1))
    starts = counts.select(key, "__part", F.coalesce(earlier, F.lit(0)).alias("__start"))
    place = F.row_number().over(Window.partitionBy(key, "__part").orderBy(*order))
    return held.join(starts, [key, "__part"]).withColumn("__nth", F.col("__start") + place - 1).drop("__part", "__start")


def shard_documents(documents: DataFrame, shards: int = 16, tolerance: float = 0.002, key: str = "__key", size: str = "__size", slice_bytes: int = SLICE_BYTES, measured: DataFrame | None = None) -> DataFrame:
    """``documents`` (any columns, with long columns ``key`` and ``size``) plus ``shard`` and gapless ``slot``.

    Earlier columns shard and slot are replaced; ``key`` and ``size`` are dropped. A shard's bytes
    differ from an equal share by at most ``tolerance`` of it or one row. Equal keys lie together
    and are cut only where they are heavier than that; equal rows may swap slots, which cannot be told apart.
    An empty table gives an empty result. ``measured`` may hold key and size alone, so that counting need not read more.
    """
    s = find_splitters((documents if measured is None else measured).select(F.col(key), F.col(size)), shards, tolerance, slice_bytes)
    first_of_shard = np.concatenate(([0], s.rows_below))[:: s.per_shard]
    offset = np.concatenate(([0], s.rows_below)) - np.repeat(first_of_shard, s.per_shard)

    @F.pandas_udf("long")
    def slice_of(k: pd.Series) -> pd.Series:
        return pd.Series(s.slices(k.to_numpy()))

    @F.pandas_udf("long")
    def slice_of_heavy(k: pd.Series, nth: pd.Series) -> pd.Series:
        return pd.Series(s.slices(k.to_numpy(), nth.to_numpy()))

    @F.pandas_udf("long")
    def offset_of(k: pd.Series) -> pd.Series:
        return pd.Series(offset[k.to_numpy()])

    plain = [c for c in documents.columns if c not in ("shard", "slot")]
    order = [c for c in ("doc_id",) if c in plain]
    sliced = documents.select(*plain)
    if s.heavy():
        heavy = F.col(key).isin(s.heavy())
        own = _numbered(sliced.filter(heavy), key, order or [key])
        sliced = sliced.filter(~heavy).select(*plain, slice_of(F.col(key)).alias("__slice")).unionByName(own.select(*plain, slice_of_heavy(F.col(key), F.col("__nth")).alias("__slice")))
    else:
        sliced = sliced.select(*plain, slice_of(F.col(key)).alias("__slice"))
    place = Window.partitionBy("__slice").orderBy(key, *order)
    return sliced.withColumn("__rank", F.row_number().over(place).cast("long") - 1).select(
        *(c for c in plain if c not in (key, size)), F.floor(F.col("__slice") / s.per_shard).cast("int").alias("shard"), (F.col("__rank") + offset_of(F.col("__slice"))).alias("slot")
    )


def shard_digest(documents: DataFrame, shards: int = 16) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard of all rows, under the law ``bytes``.

    Null text: size 1 and the checksum of no bytes. Null ids and repeated rows keep their own slots.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    small = cut(documents.select("doc_id", text_size(F.col("text")).alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), row_key(F.col("doc_id"), F.col("text")).alias("__key")))
    placed = shard_documents(small.withColumn("__size", F.col("size")), shards)
    return placed.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def shard_texts(documents: DataFrame, shards: int = 16) -> DataFrame:
    """All columns of ``documents`` plus ``shard`` and ``slot``: texts are read once for their keys and move whole in the one exchange."""
    keyed = documents.withColumns({"__key": row_key(F.col("doc_id"), F.col("text")), "__size": text_size(F.col("text"))})
    return shard_documents(keyed, shards, measured=cut(keyed.select("__key", "__size")))
