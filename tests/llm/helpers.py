"""Small tables with every awkward case, and brute-force versions."""

from __future__ import annotations

import re

import numpy as np

WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, shard string, slot string, score string, node string, target string, placements string, words string, label string"


def words(text: str | None) -> list[str]:
    return WORD.findall((text or "").translate(LOWER))


def awkward(spark, more=()):
    """Nulls in every column, empty and long texts, copies, repeated rows, columns whose names operators use."""
    base = " ".join(f"w{k} x{k % 7}" for k in range(60))
    rows = [
        (1, base, "en", "a"),
        (2, base, "en", "a"),
        (3, base.replace("w30", "zz"), "en", "b"),
        (4, None, None, None),
        (5, "", "en", "b"),
        (6, "  \n\t ", "de", None),
        (7, "one two", "en", "a"),
        (8, "ONE, two!", "en", "a"),
        (None, base, "en", "a"),
        (None, None, None, None),
        (9, "é漢字 " * 5000, "fr", "c"),
        (10, "repeat me please now and then again", "de", "c"),
        (10, "repeat me please now and then again", "de", "c"),
        (11, "x" * 200_000, "es", "c"),
        (12, "<|im_end|> a@b.co 4111 1111 1111 1111 ++ \u0000 end", "en", "c"),
        *more,
    ]
    return spark.createDataFrame([(*r, None, *("keep",) * 8) for r in rows], SCHEMA)


def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def shingles(text: str | None, k: int = 5) -> frozenset:
    w = words(text)
    return frozenset(tuple(w[i : i + k]) for i in range(len(w) - k + 1)) if len(w) >= k else frozenset([tuple(w)] if w else [])


def brute_classes(rows: list[tuple[int, str | None]]) -> dict[int, tuple[int, int]]:
    """class id and number of links of every document with an id, by comparing all pairs."""
    sets = [shingles(t) for _, t in rows]
    root = list(range(len(rows)))

    def find(i: int) -> int:
        while root[i] != i:
            i = root[i]
        return i

    links = [0] * len(rows)
    for i in range(len(rows)):
        for j in range(i):
            inter = len(sets[i] & sets[j])
            if inter and 5 * inter >= 4 * (len(sets[i]) + len(sets[j]) - inter):
                links[i] += 1
                links[j] += 1
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    groups: dict[int, list[int]] = {}
    for i in range(len(rows)):
        groups.setdefault(find(i), []).append(rows[i][0])
    return {rows[i][0]: (min(groups[find(i)]), links[i]) for i in range(len(rows))}


def brute_nearest(ids: np.ndarray, x: np.ndarray, k: int, every: int) -> dict[int, list[int]]:
    u = x / np.sqrt((x * x).sum(axis=1, keepdims=True))
    out = {}
    for i in np.flatnonzero(ids % every == 0):
        s = u @ u[i]
        order = [j for j in np.lexsort((ids, -np.round(s, 12))) if ids[j] != ids[i]]
        out[int(ids[i])] = [int(ids[j]) for j in order[:k]]
    return out
