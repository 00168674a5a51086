"""Language identification by cross-parsing.

A suffix automaton over a language's sample text accepts exactly its substrings. A text is parsed greedily into
longest phrases found in the sample; the language that needs the fewest phrases, each priced at the logarithm
of the sample's length, wins. The automaton and the restart after a phrase become one table: from state and symbol to next state and
whether a phrase ended. Many stretches of text walk through a language's table in lockstep. As a phrase's end depends only on where it began,
the parse that comes over from the stretch before soon shares a phrase's end with the one that began at the stretch's start; up to there it is
walked again, and where the two never meet, the text is parsed in one go. So the count is that of one parse of the whole text.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .session import bounded_sample, held_out
from .textkit import byte_chunks

#: Bounds of the training sample of a language: rows drawn, characters of a row that can be drawn, characters kept (whole texts, as many as fit); and bytes of all
#: tables, which the languages share.
SAMPLE_ROWS, ROW_CHARS, SAMPLE_CHARS, TABLE_BYTES = 200, 200_000, 40_000, 256 << 20
#: Symbols: 0 a run of what is no letter, then the commonest letters, then pieces of two that spell other letters, last one that is never met.
ALPHABET, PIECES = 96, 32
STRETCH = 256


def suffix_automaton(symbols: list[int]) -> list[dict[int, int]]:
    """Transitions of the automaton of all substrings; state 0 is the start."""
    moves: list[dict[int, int]] = [{}]
    link, length, last = [-1], [0], 0
    for c in symbols:
        new = len(moves)
        moves.append({})
        length.append(length[last] + 1)
        link.append(0)
        p = last
        while p >= 0 and c not in moves[p]:
            moves[p][c] = new
            p = link[p]
        if p >= 0:
            q = moves[p][c]
            if length[q] == length[p] + 1:
                link[new] = q
            else:
                copy = len(moves)
                moves.append(dict(moves[q]))
                length.append(length[p] + 1)
                link.append(link[q])
                while p >= 0 and moves[p].get(c) == q:
                    moves[p][c] = copy
                    p = link[p]
                link[q] = link[new] = copy
        last = new
    return moves


class Parser:
    """Tables of all languages, each with states of its own."""

    def __init__(self, samples: tuple[tuple[str, str], ...]):
        self.languages = [name for name, _ in samples]
        seen = Counter(c for _, text in samples for c in text if c.isalpha())
        own = ALPHABET - PIECES - 2
        known = [c for c, _ in sorted(seen.items(), key=lambda x: (-x[1], x[0]))[:own] if ord(c) < 65536]
        self.symbol = np.array([-1 if chr(c).isalpha() else 0 for c in range(65536)], np.int32)
        for k, c in enumerate(known):
            self.symbol[ord(c)] = k + 1
        self.tables = []
        for _, text in samples:
            moves = suffix_automaton(self.symbols(text)[0].tolist())
            table = np.empty((len(moves) + 1, ALPHABET), np.int64)
            # a phrase ends and the next one starts with this symbol; one that the sample lacks is a phrase by itself, which the last state stands for
            first = np.full(ALPHABET, len(moves), np.int64)
            for c, to in moves[0].items():
                first[c] = to
            table[:] = first * ALPHABET * 2 + 1
            for s, out in enumerate(moves):
                for c, to in out.items():
                    table[s, c] = to * ALPHABET * 2
            self.tables.append(table.ravel().astype(np.int32))
        self.price = np.array([math.log2(max(2, len(text))) for _, text in samples])

    def symbols(self, text: str) -> tuple[np.ndarray, np.ndarray]:
        """Symbols of a text, and for each the position of its character; a rare letter is spelled by two pieces."""
        points = np.frombuffer(text.encode("utf-32-le", "replace"), np.uint32).astype(np.int64)
        out = np.where(points < 65536, self.symbol[np.minimum(points, 65535)], -1)
        for k in np.flatnonzero(points >= 65536).tolist():
            out[k] = -1 if text[k].isalpha() else 0
        rare = np.flatnonzero(out < 0)
        if not len(rare):
            return out, np.arange(len(out))
        mixed = points[rare] * 0x9E3779B1 >> 11
        base = ALPHABET - PIECES - 1
        out[rare] = base + mixed % PIECES
        at = np.repeat(np.arange(len(out)), 1 + np.isin(np.arange(len(out)), rare, assume_unique=True))
        spelled = out[at]
        spelled[np.flatnonzero(at[1:] == at[:-1]) + 1] = base + mixed // PIECES % PIECES
        return spelled, at

    def phrases(self, symbols: np.ndarray, sizes: np.ndarray) -> np.ndarray:
        """Phrases of every text (rows) in every language (columns); ``symbols`` of all texts lie behind each other."""
        cuts = -(-sizes // STRETCH)
        text = np.repeat(np.arange(len(sizes)), cuts)
        out = np.zeros((len(sizes), len(self.tables)))
        if not len(text):
            return out
        offset = (np.arange(len(text)) - np.repeat(np.cumsum(cuts) - cuts, cuts)) * STRETCH
        begin = (np.cumsum(sizes) - sizes)[text] + offset
        long = np.minimum(sizes[text] - offset, STRETCH)
        order = np.argsort(-long, kind="stable")
        live = np.searchsorted(-long[order], -np.arange(STRETCH), side="left")  # stretches longer than each step
        padded = np.zeros((int(long.max()), len(text)), np.int32)
        for t in range(len(padded)):
            padded[t, : live[t]] = symbols[begin[order[: live[t]]] + t]
        place = np.empty(len(order), np.int64)
        place[order] = np.arange(len(order))
        later = np.flatnonzero(offset > 0)
        for k, table in enumerate(self.tables):
            state = np.zeros(len(text), np.int32)
            ended = np.zeros(padded.shape, np.int8)
            for t, n in enumerate(live[: len(padded)].tolist()):
                to = table[state[:n] + padded[t, :n]]
                ended[t, :n] = to & 1
                state[:n] = to >> 1
            # a stretch begins with a phrase, so its first symbol counts as an end before it
            ended[0] = 1
            after = ended[::-1].cumsum(axis=0, dtype=np.int32)[::-1]  # ends from each step on
            count = after[0].astype(np.int64)
            lane, own = place[later], state[place[later - 1]]
            found, apart = np.zeros(len(later), np.int64), np.ones(len(later), bool)
            at = np.arange(len(later))
            for t in range(len(padded)):
                inside = long[later[at]] > t
                at = at[inside]
                if not len(at):
                    break
                to = table[own[at] + padded[t, lane[at]]]
                own[at] = to >> 1
                end = (to & 1).astype(bool)
                met = end & (ended[t, lane[at]] > 0)
                found[at[met]] += after[t, lane[at[met]]]
                apart[at[met]] = False
                found[at[end & ~met]] += 1
                at = at[~met]
            count[lane] = found
            apart &= offset[later] + long[later] < sizes[text[later]]  # a text's last stretch is walked to its end
            np.add.at(out[:, k], text, count[place])
            for i in np.unique(text[later[apart]]).tolist():
                first = int(sizes[:i].sum())
                out[i, k] = self._in_one_go(table, symbols[first : first + int(sizes[i])])
        return out

    @staticmethod
    def _in_one_go(table: np.ndarray, symbols: np.ndarray) -> int:
        state, n = 0, 1
        for c in symbols.tolist():
            to = int(table[state + c])
            n += to & 1
            state = to >> 1
        return n - int(len(symbols) > 0 and (int(table[symbols[0]]) & 1))

    def costs(self, texts: list[str]) -> np.ndarray:
        """Bits of every text (rows) in every language (columns)."""
        symbols, at = self.symbols("".join(texts))
        ends = np.cumsum([0, *map(len, texts)])
        owner = np.searchsorted(ends, at, side="right") - 1
        fresh = (symbols != 0) | np.append(True, (symbols[1:] != symbols[:-1]) | (owner[1:] != owner[:-1]))[: len(symbols)]
        sizes = np.bincount(owner[fresh], minlength=len(texts))[: len(texts)]
        return self.phrases(symbols[fresh].astype(np.int32), sizes) * self.price

    def predict(self, texts: list[str | None]) -> tuple[list[str], list[float]]:
        costs = self.costs([(t or "").lower() for t in texts])
        names, scores = [], []
        for t, row in zip(texts, costs, strict=True):
            if not t or not self.languages or not has_letter(t):
                names.append("und")
                scores.append(0.0)
                continue
            k = int(np.argmin(row))
            names.append(self.languages[k])
            scores.append(float(1 / np.exp2(np.maximum(row[k] - row, -1000.0)).sum()))
        return names, scores


def has_letter(text: str) -> bool:
    """Is any character a letter? Digits, fractions and numerals in other forms are none."""
    return any(map(str.isalpha, text))


def squeeze(text: str) -> str:
    """Lower case, and one space for each run of what is no letter."""
    return " ".join("".join(c if c.isalpha() else " " for c in text.lower()).split())


@lru_cache(maxsize=2)
def _parser(samples: tuple[tuple[str, str], ...]) -> Parser:
    return Parser(samples)


def language_samples(documents: DataFrame, rows: int = SAMPLE_ROWS, chars: int = SAMPLE_CHARS) -> tuple[tuple[str, str], ...]:
    """Sample text of every language, from rows with a language that are not held out; sorted by language.

    Of the rows drawn, whole texts are kept in the order of a hash while they fit into ``chars`` characters, less if many languages
    share ``TABLE_BYTES``; if none fits, the shortest. Texts longer than ``ROW_CHARS`` are not drawn.
    """
    known = documents.select("doc_id", "lang", F.col("text").alias("__text")).filter(F.col("lang").isNotNull() & (F.length("text") > 0) & (F.length("text") <= ROW_CHARS) & ~held_out(F.col("doc_id")))
    chosen = bounded_sample(known, "lang", "doc_id", rows)
    place = F.pmod(F.xxhash64(F.lit(3), "doc_id"), F.lit(1 << 30))
    drawn: dict[str, list[str]] = {}
    for lang, _, text in chosen.select("lang", place.alias("__p"), "__text").dropDuplicates().orderBy("__p", "lang", "__text").toLocalIterator():
        if has_letter(text):
            drawn.setdefault(lang, []).append(squeeze(text))
    share = min(chars, TABLE_BYTES // (max(1, len(drawn)) * ALPHABET * 6))  # three states for two characters, four bytes a cell
    out = []
    for lang in sorted(drawn):
        kept, size = [], 0
        for text in drawn[lang]:
            if size + len(text) <= share:
                kept.append(text)
                size += len(text)
        out.append((lang, " ".join(kept or [min(drawn[lang], key=lambda t: (len(t), t))])))
    return tuple(out)


def identify_language(documents: DataFrame, samples: tuple[tuple[str, str], ...] | None = None) -> DataFrame:
    """doc_id, held_out, lang_pred, score for every row, from its whole text.

    Texts that are null, empty or without a letter are ``und`` with score 0, and so is everything if no row can
    be learned from. Equal costs go to the first language by name. Null ids are held out. Repeated rows get rows like others; extra columns
    are ignored.
    """
    samples = language_samples(documents) if samples is None else samples
    kind = documents.schema["doc_id"].dataType.simpleString()

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parser = _parser(samples)
        for whole in batches:
            for b in byte_chunks(whole, "text"):
                names, scores = parser.predict(b.column(2).to_pylist())
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(names, pa.string()), pa.array(scores, pa.float64())], names=["doc_id", "held_out", "lang_pred", "score"])

    return documents.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "text").mapInArrow(scan, f"doc_id {kind}, held_out boolean, lang_pred string, score double")
