"""Toxicity by weak supervision.

Lexicon and pattern voters look at a document's words. A generative label model estimates, from the votes alone, how often each voter
votes on either class and which voters go together: votes form a tree, each depending on the hidden class and on the voter it is most tied to given
the class. The model's posterior labels, and nothing else, train a linear classifier on the votes and how strongly they are meant. Labels of training rows
choose among words and word beginnings as entries of the learned lexicons and give the share of toxic rows; no model is fitted to them.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .quality import score_digest
from .session import cut, label_share, labelled_sample
from .textkit import Words, _mix, as_bytes, byte_chunks, hash_words, split_words

#: Bound of the labelled sample: rows of each label.
SAMPLE_ROWS = 2_500
CUTOFF = 0.5
#: Insults in four languages, by theme; each line is one lexicon voter.
LEXICONS = (
    "idiot idiots moron morons stupid imbecile fool fools dumb dumbass",
    "scum trash garbage filth vermin parasite worthless useless",
    "loser losers pathetic clown clowns disgusting ugly creep freak",
    "bastard bitch asshole jerk shit fuck fucking crap damn slut whore",
    "idioten dumm dummkopf trottel arschloch scheisse scheiße abschaum versager widerlich hure",
    "connard connasse salaud imbécile crétin ordure déchet raté merde pute minable",
    "idiota imbécil estúpido basura escoria perdedor asqueroso payaso mierda puta cabrón",
)
PREFIXES = (5, 6, 7, 8)
#: Learned voters: whole words of high and of lower odds, and beginnings of each length.
SURE = 4.0
GROUPS = 2 + len(PREFIXES)
VOTES = len(LEXICONS) + GROUPS + 6  #: lexicon voters, then patterns
#: Voters are tied only by more than so much mutual information (in nats) given the class.
LEAST_TIE = 0.002
_MASK = [np.uint64((1 << (8 * n)) - 1) for n in range(8)] + [np.uint64(0xFFFFFFFFFFFFFFFF)]


def word_keys(words: Words) -> list[np.ndarray]:
    """Keys of whole words and, by prefix length in bytes, of word beginnings (0 for words that are shorter)."""
    lanes = np.ndarray((len(words.low) - 7,), dtype="<u8", buffer=words.low.data, strides=(1,))[words.starts]
    size = words.ends - words.starts
    return [hash_words(words), *(np.where(size >= n, _mix((lanes & _MASK[n]) + np.uint64(n)), np.uint64(0)) for n in PREFIXES)]


def key_of(word: str) -> int:
    return int(hash_words(split_words([word.encode()]))[0])


@dataclass
class Lexicon:
    """Sorted keys with a weight and a voter each."""

    keys: np.ndarray
    weights: np.ndarray
    voter: np.ndarray

    def hits(self, keys: list[np.ndarray], doc: np.ndarray, n_docs: int, n_voters: int) -> tuple[np.ndarray, np.ndarray]:
        """Hits of each voter in each document, and each document's summed weights (the strongest key of a word counts)."""
        counts = np.zeros((n_docs, n_voters))
        best = np.zeros(len(doc))
        if not len(self.keys):
            return counts, np.zeros(n_docs)
        for own in keys:
            at = np.minimum(np.searchsorted(self.keys, own), len(self.keys) - 1)
            met = np.flatnonzero(self.keys[at] == own)
            np.add.at(counts, (doc[met], self.voter[at[met]]), 1)
            best[met] = np.where(np.abs(self.weights[at[met]]) > np.abs(best[met]), self.weights[at[met]], best[met])
        return counts, np.bincount(doc, weights=best, minlength=n_docs)


def key_counts(texts: list[bytes]) -> list[tuple[np.ndarray, np.ndarray]]:
    """For words and for beginnings of each length: distinct keys, and how many of the texts hold each."""
    words = split_words(texts)
    doc = np.repeat(np.arange(len(texts)), words.counts)
    found = []
    for keys in word_keys(words):
        own, at = keys[keys != 0], doc[keys != 0]
        order = np.lexsort((at, own))
        own, at = own[order], at[order]
        fresh = np.append(True, (own[1:] != own[:-1]) | (at[1:] != at[:-1]))[: len(own)]
        found.append(np.unique(own[fresh], return_counts=True))
    return found


def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for whole in batches:
        for b in byte_chunks(whole, "__text"):
            part, texts = b.column(1).to_numpy(), as_bytes(b.column(2))
            for own in np.unique(part):
                for kind, (keys, n) in enumerate(key_counts([texts[i] for i in np.flatnonzero(part == own)])):
                    fixed = [pa.array(np.full(len(keys), x, np.int32)) for x in (kind, own)]
                    yield pa.RecordBatch.from_arrays([pa.array(keys.view(np.int64)), *fixed, pa.array(n.astype(np.int64))], names=["key", "kind", "part", "n"])


def learn_lexicons(sample: DataFrame, sizes: list[int], support: float = 0.012, strength: float = 2.5, most: int = 4000) -> list[dict[int, tuple[float, int]]]:
    """Words and word beginnings that toxic training rows hold far more often than others, as key to log-odds and kind: from fold 0, from fold 1, from both.

    ``sizes`` are the rows of each ``__part`` (twice the fold plus the label). Texts stay on the executors; only keys that enter a lexicon are collected.
    """
    counts = sample.mapInArrow(_count, "key long, kind int, part int, n long").groupBy("key", "kind").agg(*(F.sum(F.when(F.col("part") == k, F.col("n")).otherwise(0)).alias(f"c{k}") for k in range(4)))
    wanted, sides = F.lit(False), []
    for folds in ((0,), (1,), (0, 1)):
        n0, n1 = (sum(sizes[2 * f + y] for f in folds) for y in (0, 1))
        c0, c1 = (sum((F.col(f"c{2 * f + y}") for f in folds), F.lit(0)) for y in (0, 1))
        least = max(4, support * n1)
        sides.append((folds, n0, n1, least))
        wanted = wanted | ((c1 >= least) & (F.log((c1 + 0.5) / (n1 + 1)) - F.log((c0 + 0.5) / (n0 + 1)) >= strength - 1e-6))
    rows = counts.filter(wanted).collect()
    out = []
    for folds, n0, n1, least in sides:
        odds = []
        for r in rows:
            c0, c1 = (sum(r[f"c{2 * f + y}"] for f in folds) for y in (0, 1))
            if c1 >= least:
                odds.append((float(np.log((c1 + 0.5) / (n1 + 1)) - np.log((c0 + 0.5) / (n0 + 1))), r["key"] % (1 << 64), r["kind"]))
        out.append({k: (v, kind) for v, k, kind in sorted((x for x in odds if x[0] >= strength), reverse=True)[:most]})
    return out


@dataclass
class LabelModel:
    """Share of the class; for every voter the voter it is tied to (-1: none) and its chance of a vote by class and by that voter's vote."""

    share: float
    parent: np.ndarray
    chance: np.ndarray  #: [class, vote of the parent, voter]

    def log_chance(self, votes: np.ndarray) -> np.ndarray:
        """Log of the chance of each row's votes in either class."""
        tied = np.where(self.parent >= 0, votes[:, self.parent], 0).astype(np.int64)
        out = np.empty((len(votes), 2))
        for c in (0, 1):
            p = np.clip(self.chance[c][tied, np.arange(votes.shape[1])], 1e-4, 1 - 1e-4)
            out[:, c] = np.log(np.where(votes > 0, p, 1 - p)).sum(axis=1)
        return out

    def likelihood(self, votes: np.ndarray) -> float:
        """Mean log of the chance of a row's votes."""
        both = self.log_chance(votes) + np.log([1 - self.share, self.share])
        return float(np.logaddexp(both[:, 0], both[:, 1]).mean())

    def posterior(self, votes: np.ndarray) -> np.ndarray:
        both = self.log_chance(votes)
        logit = np.log(self.share / (1 - self.share)) + both[:, 1] - both[:, 0]
        return 1 / (1 + np.exp(-np.clip(logit, -60, 60)))


def _ties(votes: np.ndarray, q: np.ndarray) -> np.ndarray:
    """The parent of every voter in the forest of greatest mutual information given the class, whose weights are ``q``."""
    k = votes.shape[1]
    tie = np.zeros((k, k))
    for w in (1 - q, q):
        n = w.sum() + 1e-9
        one = (w @ votes + 0.5) / (n + 1)
        joint = [None, None, None, None]
        joint[3] = ((votes * w[:, None]).T @ votes + 0.25) / (n + 1)
        joint[2], joint[1] = one[:, None] - joint[3], one[None, :] - joint[3]
        joint[0] = 1 - joint[1] - joint[2] - joint[3]
        for (a, b), p in zip(((0, 0), (0, 1), (1, 0), (1, 1)), joint, strict=True):
            alone = (one if a else 1 - one)[:, None] * (one if b else 1 - one)[None, :]
            p = np.maximum(p, 1e-9)
            tie += n / len(votes) * p * np.log(p / np.maximum(alone, 1e-9))
    parent, part = np.full(k, -1), np.arange(k)
    links: list[list[int]] = [[] for _ in range(k)]
    for i, j in sorted(((i, j) for i in range(k) for j in range(i + 1, k) if tie[i, j] > LEAST_TIE), key=lambda x: (-tie[x], x)):
        if part[i] != part[j]:
            part[part == part[j]] = part[i]
            links[i].append(j)
            links[j].append(i)
    for root in range(k):  # every part of the forest hangs on its first voter
        if parent[root] == -1 and part[root] != -1:
            stack, own = [root], part[root]
            while stack:
                at = stack.pop()
                part[at] = -1
                for j in links[at]:
                    if part[j] == own:
                        parent[j] = at
                        stack.append(j)
    return parent


def fit_label_model(votes: np.ndarray, share: float, rounds: int = 40) -> LabelModel:
    """EM over votes without labels, from two starts: voters that count alike, and voters that count less the more they resemble others.

    The first would take a block of voters that repeat each other for the class, the second would mistrust good voters that agree; the model under which the votes are likelier wins.
    """
    share = float(np.clip(share, 0.01, 0.99))
    spread = votes.std(axis=0) + 1e-9
    alike = np.abs(np.cov(votes.T, bias=True).reshape(len(spread), -1) / np.outer(spread, spread))
    starts = (np.ones(len(spread)), 1 / np.maximum(1.0, (alike**8).sum(axis=1)))  # eighth powers: only near copies count
    models = [_expectation_maximisation(votes, share, discount, rounds) for discount in starts]
    return max(models, key=lambda m: m.likelihood(votes))


def _expectation_maximisation(votes: np.ndarray, share: float, discount: np.ndarray, rounds: int) -> LabelModel:
    """First as if voters were independent, each counting by its ``discount``; then with the ties that the posteriors show."""
    k, any_vote = votes.shape[1], votes.mean(axis=0)
    rates = np.stack([np.clip(any_vote * 0.3, 0.002, 0.4), np.clip(any_vote * 3, 0.05, 0.9)])
    model = LabelModel(share, np.full(k, -1), np.stack([rates, rates], axis=1))
    for turn in range(rounds):
        if turn < rounds // 2:
            p = np.clip(rates, 1e-4, 1 - 1e-4)
            logit = np.log(share / (1 - share)) + (votes * np.log(p[1] / p[0]) + (1 - votes) * np.log((1 - p[1]) / (1 - p[0]))) @ discount
            q = 1 / (1 + np.exp(-np.clip(logit, -60, 60)))
        else:
            q = model.posterior(votes)
        if turn in (rounds // 2, 3 * rounds // 4):
            model.parent = _ties(votes, q)
        tied = np.where(model.parent >= 0, votes[:, model.parent], 0)
        weights = np.stack([1 - q, q])
        rates = (weights @ votes + np.array([[0.02], [0.5]])) / (weights.sum(axis=1)[:, None] + 2)
        flip = rates[1] < rates[0]
        rates[1, flip] = rates[0, flip]  # a voter may be useless but not turn its meaning
        for v in (0, 1):
            own = (tied == v).astype(float)
            # two further rows vote as the voter does in the class whatever its tie
            model.chance[:, v] = (weights @ (votes * own) + 2 * rates) / (weights @ own + 2)
        if flip.any():
            model.chance[:, :, flip] = any_vote[flip]
    return model


@dataclass
class ToxicityModel:
    """Voters, label model and linear classifier; without ``weights`` it gives a constant."""

    constant: float = 0.5
    lexicon: Lexicon | None = None
    labeller: LabelModel | None = None
    weights: np.ndarray | None = None
    mean: np.ndarray | None = None
    scale: np.ndarray | None = None

    def views(self, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Votes and features of all texts."""
        words = split_words(texts)
        n = words.counts
        doc = np.repeat(np.arange(len(texts)), n)
        hits, strength = self.lexicon.hits(word_keys(words), doc, len(texts), len(LEXICONS) + GROUPS)
        raised = np.array([t.count(b"!") for t in texts]) / np.maximum(n, 1)
        fixed, learned = hits[:, : len(LEXICONS)].sum(axis=1), hits[:, len(LEXICONS) :].sum(axis=1)
        patterns = np.stack([fixed >= 2, learned >= 3, fixed * 100 >= np.maximum(n, 1), (learned * 50 >= np.maximum(n, 1)) & (learned > 0), strength >= 6, (raised > 0.3) & (fixed > 0)], axis=1)
        votes = np.concatenate([hits > 0, patterns], axis=1).astype(float)
        dense = np.stack([np.log1p(fixed), np.log1p(learned), np.log1p(np.maximum(strength, 0)), fixed * 20 / np.maximum(n, 20), learned * 10 / np.maximum(n, 20), strength * 5 / np.maximum(n, 20), np.log1p(n) / 5, raised], axis=1)
        return votes, np.concatenate([votes, dense, np.minimum(hits, 3) / 3, np.ones((len(texts), 1))], axis=1)

    def scores(self, texts: list[bytes]) -> np.ndarray:
        if self.weights is None:
            return np.full(len(texts), self.constant)
        _, x = self.views(texts)
        return 1 / (1 + np.exp(-np.clip((x - self.mean) / self.scale @ self.weights, -60, 60)))


def logistic(x: np.ndarray, y: np.ndarray, weight: np.ndarray, penalty: float, rounds: int = 30) -> np.ndarray:
    """Newton's method for logistic regression on soft labels."""
    w = np.zeros(x.shape[1])
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        g = x.T @ (weight * (p - y)) + penalty * w
        h = (x * (weight * p * (1 - p) + 1e-9)[:, None]).T @ x + penalty * np.eye(len(w))
        step = np.linalg.solve(h, g)
        w -= step
        if np.abs(step).max() < 1e-6:
            break
    return w


def _features(models: list[ToxicityModel]):
    """Features of each training row under the model whose lexicon comes from the other fold, so that its votes are honest."""

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in byte_chunks(whole, "__text"):
                part, texts = b.column(1).to_numpy(), as_bytes(b.column(2))
                for fold in (0, 1):
                    at = np.flatnonzero(part // 2 == fold)
                    if len(at):
                        _, x = models[1 - fold].views([texts[i] for i in at])
                        yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(at)), pa.array(part[at], pa.int32()), pa.array([v.tobytes() for v in x], pa.binary())], names=["doc_id", "part", "x"])

    return scan


def train(sample: DataFrame, share: float | None = None) -> ToxicityModel:
    """Model from labelled training rows (doc_id, __label, __text); ``share`` is the share of toxic rows before sampling."""
    kind = sample.schema["doc_id"].dataType.simpleString()
    fold = F.conv(F.substring(F.sha2(F.col("__text").cast("binary"), 256), 2, 1), 16, 10).cast("int") % 2
    sample = cut(sample.select("doc_id", (fold * 2 + F.col("__label")).alias("__part"), "__text"))
    met = dict(sample.groupBy("__part").count().collect())
    sizes = [met.get(k, 0) for k in range(4)]
    toxic, n = sizes[1] + sizes[3], sum(sizes)
    if toxic in (0, n):
        return ToxicityModel(constant=toxic / n if n else 0.5)
    # lexicons from one half, so that votes on the other half are honest; then lexicons from all for use
    *halves, whole = (_lexicon(x) for x in learn_lexicons(sample, sizes))
    rows = sample.mapInArrow(_features([ToxicityModel(lexicon=x) for x in halves]), f"doc_id {kind}, part int, x binary").collect()
    rows.sort(key=lambda r: (r["part"] // 2, r["doc_id"]))
    x = np.stack([np.frombuffer(r["x"]) for r in rows])
    drawn = toxic / n
    labeller = fit_label_model(x[:, :VOTES], drawn)
    posterior = labeller.posterior(x[:, :VOTES])
    mean, scale = x.mean(axis=0), x.std(axis=0) + 0.05
    mean[-1], scale[-1] = 0.0, 1.0
    weights = logistic((x - mean) / scale, posterior, np.ones(len(x)), penalty=2.0)
    if share is not None and 0 < share < 1:  # the sample has both labels about equally often
        weights[-1] += np.log(share / (1 - share)) - np.log(drawn / (1 - drawn))
    return ToxicityModel(lexicon=whole, labeller=labeller, weights=weights, mean=mean, scale=scale)


def _lexicon(learned: dict[int, tuple[float, int]]) -> Lexicon:
    entries = {k: (v, len(LEXICONS) + (kind + 1 if kind else int(v < SURE))) for k, (v, kind) in learned.items()}
    for voter, line in enumerate(LEXICONS):
        for word in line.split():
            entries[key_of(word)] = (max(3.0, learned.get(key_of(word), (0.0, 0))[0]), voter)
    keys = np.array(sorted(entries), np.uint64)
    return Lexicon(keys, np.array([entries[int(k)][0] for k in keys]), np.array([entries[int(k)][1] for k in keys]))


def fit_toxicity(documents: DataFrame, labels: DataFrame) -> ToxicityModel:
    return train(labelled_sample(documents, labels, "toxic", SAMPLE_ROWS), label_share(labels, "toxic"))


def score_toxicity(documents: DataFrame, labels: DataFrame) -> DataFrame:
    """Toxicity of every document. Without labels of both kinds the score is the share of label 1, or 0.5; empty texts score like texts without votes."""
    return score_digest(documents, fit_toxicity(documents, labels), CUTOFF)
