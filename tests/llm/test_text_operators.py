from __future__ import annotations

import hashlib
import random
import re

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from poiweave.llm import chat, decontaminate, language, pii, quality, similarity, textkit, toxicity
from poiweave.llm.op1 import op1_decontaminate
from poiweave.llm.op2 import op2_ngram_jaccard
from poiweave.llm.op9 import FORGED, op9_format_chat
from poiweave.llm.session import table

from .helpers import awkward, brute_classes, empty, shingles, words


def test_words_and_hashes_match_the_pattern():
    texts = ["A b-C9 é漢字x", "", "...", "abcdefgh abcdefghi abcdefghijklmnopq", "\u0000a\u007fb"]
    w = textkit.split_words([t.encode() for t in texts])
    found = [w.low[a:b].tobytes().decode() for a, b in zip(w.starts, w.ends, strict=True)]
    assert found == [x for t in texts for x in words(t)]
    assert w.counts.tolist() == [len(words(t)) for t in texts]
    h = textkit.hash_words(w)
    assert len(set(h.tolist())) == len(set(found))


def _brute_hits(text, items, window=10):
    w = words(text)
    hit, own = set(), set()
    for item, t in items:
        v = words(t)
        m = min(window, len(v))
        for i in range(len(v) - m + 1 if m else 0):
            for p in range(len(w) - m + 1):
                if w[p : p + m] == v[i : i + m]:
                    hit.update(range(p, p + m))
                    own.add(item)
    return len(w), len(hit), own


def test_decontamination_against_brute_force(spark):
    r = random.Random(1)
    items = [(k, " ".join(r.choice("abcde") * r.randint(1, 2) for _ in range(r.choice([0, 1, 2, 9, 10, 14])))) for k in range(25)] + [(25, None)]
    docs = [(k, " ".join(r.choice("abcde") * r.randint(1, 2) for _ in range(r.randint(0, 700)))) for k in range(40)]
    docs += [(50 + k, "Start, " + t.upper().replace(" ", "; ") + " end") for k, t in items if t] + [(99, None)]
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = decontaminate.digest(decontaminate.find_contamination(spark.createDataFrame(docs, "doc_id long, text string"), bench))
    blocks = decontaminate.digest(decontaminate.find_contamination(spark.createDataFrame(docs, "doc_id long, text string"), bench, block_patterns=12))
    assert sorted(got.collect()) == sorted(blocks.collect())
    for row in got.collect():
        n, hits, own = _brute_hits(dict(docs)[row.doc_id], items)
        assert (row.n_words, row.n_hit, row.n_items) == (n, hits, len(own)), row
        assert row.items_sha256 == hashlib.sha256(",".join(sorted(map(str, own))).encode()).hexdigest()
        assert row.contaminated == (hits > 0)


def test_decontamination_edge_cases(spark):
    bench = spark.createDataFrame([(1, "w1 x1 w2 x2"), (None, "one two"), (2, ""), (2, None)], "item_id long, text string")
    out = decontaminate.decontaminate(awkward(spark), bench)
    assert out.columns == awkward(spark).columns
    assert {r.doc_id for r in out.collect()} == {4, 5, 6, 7, 8, None, 9, 10, 11, 12}
    assert decontaminate.decontaminate(empty(spark), bench).count() == 0
    assert decontaminate.decontaminate(awkward(spark), bench.limit(0)).count() == 15
    assert op1_decontaminate(spark, "/root/testdata/sf0.001").count() == 200


def test_near_duplicates_against_brute_force(spark, sf):
    d = table(spark, sf, "documents")
    rows = [(r.doc_id, r.text) for r in d.select("doc_id", "text").collect()]
    got = {r.doc_id: (r.class_id, r.n_links) for r in op2_ngram_jaccard(spark, sf).collect()}
    assert got == brute_classes(rows)


def test_near_duplicates_of_one_large_group_in_small_blocks(spark):
    r = random.Random(2)
    base = [f"w{k}" for k in range(80)]
    rows = []
    for k in range(60):
        w = list(base)
        for _ in range(r.randint(0, 2)):
            w[r.randrange(80)] = f"v{r.randrange(5)}"
        rows.append((k, " ".join(w)))
    rows += [(100 + k, f"other text number {k} with its own words {k * 7} and {k * 11} more") for k in range(10)]
    got = similarity.link_documents(spark.createDataFrame(rows, "doc_id long, text string"), block=16)
    assert {x.doc_id: (x.class_id, x.n_links) for x in got.collect()} == brute_classes(rows)


def test_near_duplicate_edge_cases(spark):
    got = {r.doc_id: (r.class_id, r.n_links) for r in similarity.link_documents(awkward(spark)).filter("doc_id is not null").collect()}
    assert got[1] == got[2] and got[1][0] == 1 and got[3] == (1, 2)
    assert got[4] == (4, 0) and got[5] == (5, 0) and got[7] == (7, 1) and got[8] == (7, 1) and got[10] == (10, 1)
    assert all(r.class_id is None and r.n_links == 0 for r in similarity.link_documents(awkward(spark)).filter("doc_id is null").collect())
    kept = similarity.keep_first(awkward(spark))
    assert kept.columns == awkward(spark).columns
    assert sorted(r.doc_id for r in kept.collect() if r.doc_id is not None) == [1, 4, 5, 6, 7, 9, 10, 11, 12]
    assert similarity.link_documents(empty(spark)).count() == 0


def test_prefixes_are_shorter_where_the_tries_are_thin():
    gain, need = similarity.GAIN, -np.log(1 - similarity.RECALL)
    dense = np.array([[900, 500, 250, 120, 60, 30]] * 24)
    thin = np.ones((24, 6), int)
    both = similarity.choose_lengths(np.concatenate([dense, thin]), np.array([24, 24]))
    assert (both[24:] == similarity.SHORTEST).all() and np.median(both[:24]) > similarity.SHORTEST + 1
    mixed = similarity.choose_lengths(np.concatenate([dense[:10], thin[:4]]), np.array([14]))  # ten crowded trees, four thin ones, ten not listed
    assert mixed[:10].min() >= 7 and (mixed[10:] == similarity.SHORTEST).all()
    for lengths, listed in ((both[:24], 24), (both[24:], 24), (mixed, 14)):
        assert gain[lengths - similarity.SHORTEST].sum() + (24 - listed) * gain[0] >= need - 1e-9


def test_signatures_meet_as_often_as_they_should():
    r = np.random.default_rng(3)
    met, shared, far = 0, [], []
    for k in range(200):
        common = r.integers(0, 1 << 62, 800 if k < 150 else 400, dtype=np.uint64)
        a, b = (similarity.labels(similarity.minima(np.unique(np.concatenate([common, r.integers(0, 1 << 62, 100 if k < 150 else 200, dtype=np.uint64)])))) for _ in range(2))
        if k < 150:
            met += bool((a[0] == b[0]).any())
        (shared if k < 150 else far).append(int((a[2] == b[2]).sum()))
    assert met == 150 and min(shared) >= similarity.LEAST_SHARED and max(far) < similarity.LEAST_SHARED
    assert len(shingles("a b c")) == 1


def test_rows_that_share_an_id_are_judged_by_their_texts(spark):
    """An id may name several texts: none is lost, and none joins the others' classes."""
    words_of = lambda k: " ".join(f"t{k}w{j}" for j in range(40))
    rows = [(1, words_of(1)), (1, words_of(2)), (1, words_of(1)), (2, words_of(2)), (3, words_of(3)), (3, words_of(3) + " more"), (4, words_of(4)), (4, None), (None, words_of(4))]
    d = spark.createDataFrame(rows, "doc_id long, text string")
    kept = sorted((r.doc_id or 0, r.text or "") for r in similarity.keep_first(d).collect())
    # classes: {1, 1}, {1, 2}, {3, 3}, {4}; the row without words and the one without an id stay
    assert [i for i, _ in kept] == [0, 1, 1, 3, 4, 4] and {t for i, t in kept if i == 1} == {words_of(1), words_of(2)}
    got = sorted((r.doc_id, r.class_id, r.n_links) for r in similarity.link_documents(d).filter("doc_id is not null").collect())
    assert got == [(1, 1, 1), (1, 1, 1), (1, 1, 1), (2, 1, 1), (3, 3, 1), (3, 3, 1), (4, 4, 0), (4, 4, 0)]


def test_branches_link_all_that_alike_pairs_join():
    """Groups of any size against all pairs: large ones are not compared pair by pair."""
    r = np.random.default_rng(6)
    base = r.integers(0, 256, (3, similarity.SKETCH)).astype(np.uint8)
    n = 60
    sketch = np.stack([np.where(r.random(similarity.SKETCH) < 0.17, r.integers(0, 256, similarity.SKETCH), base[min(2, k // 25)]) for k in range(n)]).astype(np.uint8)
    rest, length = r.integers(0, 3, n) << 48, r.integers(4, 7, n)
    own = similarity.Branches(np.sort(rest), length, sketch)

    def parts(links):
        root = list(range(n))
        for a, b in links:
            a, b = root[a], root[b]
            root = [min(a, b) if x == max(a, b) else x for x in root]
        return root

    i, j = np.triu_indices(n, 1)
    at = own.alike(i, j)
    assert parts(zip(i[at].tolist(), j[at].tolist(), strict=True)) == parts(own.large_group(0, n, None))
    side = np.arange(n) % 2
    mixed = parts([(a, b) for a, b in zip(i[at].tolist(), j[at].tolist(), strict=True) if side[a] != side[b]])
    got = parts(own.large_group(0, n, side))
    assert all(got[a] == got[b] for a in range(n) for b in range(n) if mixed[a] == mixed[b])


_E = re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
_I = re.compile(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")
_C = re.compile(r"[0-9]([\x20-]?[0-9])+")
_P = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")


def _brute_pii(t):
    out = [("email", *m.span()) for m in _E.finditer(t)] + [("ip", *m.span()) for m in _I.finditer(t) if all(int(p) <= 255 for p in m[0].split("."))]
    out += [("card", *m.span()) for m in _C.finditer(t) if 14 <= len(d := re.sub("[ -]", "", m[0])) <= 19 and pii.luhn(d)]
    out += [("phone", *m.span()) for m in _P.finditer(t) if 10 <= len(re.sub(r"\D", "", m[0])) <= 15]
    return sorted(out, key=lambda s: (s[1], pii.KINDS.index(s[0])))


def test_plain_spans_against_the_patterns():
    r = random.Random(4)
    for _ in range(20_000):
        t = "".join(r.choice("a@.1 25-+()é0") for _ in range(r.randint(0, 40)))
        assert pii.plain_spans(t) == _brute_pii(t), t


@pytest.mark.parametrize(
    ("text", "kind", "source"),
    [
        ("mail john.doe [at] example [dot] com now", "email", "john.doe [at] example [dot] com"),
        ("john(at)mail(dot)example(dot)org", "email", "john(at)mail(dot)example(dot)org"),
        ("jane at example dot com", "email", "jane at example dot com"),
        ("іnfo@exаmple.com", "email", "іnfo@exаmple.com"),
        ("x​@y.com", "email", "x​@y.com"),
        ("ip １９２.168.0.1 end", "ip", "１９２.168.0.1"),
        ("one nine two dot one six eight dot zero dot one", "ip", "one nine two dot one six eight dot zero dot one"),
        ("jane.doe at example.ch", "email", "jane.doe at example.ch"),
        ("write to j_doe at mail.example.co.uk please", "email", "j_doe at mail.example.co.uk"),
        ("email jane at mail.example.com today", "email", "jane at mail.example.com"),
        ("jane [at] example.museum", "email", "jane [at] example.museum"),
        ("+1 555 zero 123 4567", "phone", "+1 555 zero 123 4567"),
        ("call plus four nine one five one two three four five six seven now", "phone", "plus four nine one five one two three four five six seven"),
        ("four one one one one one one one one one one one one one one one", "card", "four one one one one one one one one one one one one one one one"),
    ],
)
def test_disguises_map_back_to_the_source(text, kind, source):
    plain, every = pii.find_spans(text)
    assert [(k, text[a:b]) for k, a, b in every if (k, a, b) not in plain] == [(kind, source)]


@pytest.mark.parametrize("text", ["we met at noon dot com", "look at google.com for help", "I looked at example dot com", "they were at home dot org said so", "open at nine dot the end", "stay at hotel.example tonight", "one two three", "at 9 dot 30 one of us"])
def test_prose_is_no_disguise(text):
    assert pii.find_spans(text) == ([], [])


def test_clean_texts_have_no_disguises(spark, sf):
    for r in table(spark, sf, "documents").select("text").collect():
        plain, every = pii.find_spans(r.text)
        assert plain == _brute_pii(r.text) and len(every) == len(plain)
    assert pii.find_spans("He was at home. The dot at the end, at noon.") == ([], [])


def test_pii_edge_cases(spark):
    got = {r.doc_id: r for r in pii.find_pii(awkward(spark)).collect()}
    assert got[12].n_email == 1 and got[12].n_card == 1 and got[4].spans == "" and got[5].base_sha256 == hashlib.sha256(b"").hexdigest()
    assert pii.find_pii(awkward(spark)).count() == 15 and pii.find_pii(empty(spark)).count() == 0


def test_suffix_automaton_knows_all_substrings():
    text = [1, 2, 1, 3, 2, 1, 2]
    moves = language.suffix_automaton(text)

    def known(s):
        at = 0
        for c in s:
            if c not in moves[at]:
                return False
            at = moves[at][c]
        return True

    subs = {tuple(text[i:j]) for i in range(len(text)) for j in range(i, len(text) + 1)}
    r = random.Random(5)
    for _ in range(500):
        s = tuple(r.choice([1, 2, 3]) for _ in range(r.randint(0, 5)))
        assert known(s) == (s in subs)


def test_parse_costs_against_a_plain_parse():
    """Also over stretches that join late or never, and with letters that are spelled by pieces."""
    r = random.Random(1)
    samples = (("a", "the cat sat on the mat " + " ".join("".join(r.choice("abcdefgh ") for _ in range(6)) for _ in range(200))), ("b", "xx xxx der hund und die katze 漢字仮名"))
    p = language.Parser(samples)

    def plain(text, sample):
        known = "".join(chr(200 + c) for c in p.symbols(sample)[0].tolist())
        own = p.symbols(text)[0]
        own = own[(own != 0) | np.append(True, own[1:] != own[:-1])[: len(own)]]
        said, n, i = "".join(chr(200 + c) for c in own.tolist()), 0, 0
        while i < len(said):
            j = i + 1
            while j <= len(said) and said[i:j] in known:
                j += 1
            n, i = n + 1, max(i + 1, j - 1)
        return n

    for k in range(60):
        t = "x" * r.choice([255, 256, 600, 1111]) if k % 10 == 0 else "".join(r.choice("abcdefgh x漢字é") for _ in range(r.choice([0, 1, 5, 255, 256, 257, 512, 900, 1500])))
        got = np.rint(p.costs([t, "the cat", t]) / p.price)
        for c, (_, sample) in enumerate(samples):
            assert got[0, c] == got[2, c] == plain(t, sample) and got[1, c] == plain("the cat", sample)


def test_no_letters_no_language_and_many_languages(spark):
    p = language.Parser((("de", "der hund und die katze"), ("ja", "漢字仮名交じり文")))
    assert p.predict(["½", "Ⅷ ①②", "12 ²", "", None])[0] == ["und"] * 5
    assert p.predict(["仮名交じり", "die katze"])[0] == ["ja", "de"]
    r = random.Random(2)
    alphabet = {f"l{k:03d}": [chr(0x4E00 + 40 * k + j) for j in range(40)] for k in range(300)}
    rows = [(k * 1000 + j, " ".join("".join(r.choice(a) for _ in range(4)) for _ in range(30)), lang) for k, (lang, a) in enumerate(alphabet.items()) for j in range(4)]
    d = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    samples = language.language_samples(d)
    assert sum(len(t) for _, t in samples) * language.ALPHABET * 6 <= language.TABLE_BYTES + 300 * 200 * language.ALPHABET * 6
    got = language.identify_language(d, samples).join(d.select("doc_id", "lang"), "doc_id").filter("held_out")
    known = {lang for lang, _ in samples}
    assert got.count() > 100 and len(known) > 250
    seen = got.filter(F.col("lang").isin(sorted(known)))
    assert seen.filter("lang_pred = lang").count() / seen.count() >= 0.95


def test_language_held_out_accuracy_and_edge_cases(spark):
    sf = "/root/testdata/sf0.01"
    d = table(spark, sf, "documents")
    got = language.identify_language(d).join(d.select("doc_id", "lang"), "doc_id").filter("held_out")
    assert got.filter("lang_pred = lang").count() / got.count() >= 0.97
    samples = language.language_samples(d)
    out = {r.doc_id: r for r in language.identify_language(awkward(spark), samples).collect()}
    assert out[4].lang_pred == out[5].lang_pred == out[6].lang_pred == "und" and out[4].score == 0
    assert all(0 <= r.score <= 1 for r in out.values())
    assert {r.lang_pred for r in language.identify_language(awkward(spark), ()).collect()} == {"und"}
    assert language.identify_language(empty(spark)).count() == 0


@pytest.mark.parametrize(("name", "module", "least"), [("quality", quality, 0.97), ("toxic", toxicity, 0.9)])
def test_classifiers_on_held_out_rows(spark, name, module, least):
    sf = "/root/testdata/sf0.1" if name == "toxic" else "/root/testdata/sf0.01"
    d, y = table(spark, sf, "documents"), table(spark, sf, "labels")
    score = quality.score_quality if name == "quality" else toxicity.score_toxicity
    got = score(d, y).join(y, "doc_id").filter("held_out")
    assert got.filter(F.col("predicted") == F.col(name)).count() / got.count() >= least
    assert score(empty(spark), y).count() == 0
    none = score(awkward(spark), y.limit(0))
    assert none.count() == 15 and {r.score for r in none.collect()} == {0.5}
    some = score(awkward(spark), y)
    assert all(0 <= r.score <= 1 for r in some.collect())
    assert module.CUTOFF in (0.3, 0.5)


def test_attention_gradients():
    r = np.random.default_rng(0)
    texts = ["abc def " * int(n) for n in r.integers(1, 200, 6)]
    x, first = quality.passages([t.encode() for t in texts])
    sizes = {"E": (quality.N_FEATURES, 4), "e": (4,), "V": (4, 3), "U": (4, 3), "w": (3,), "c": (4,), "b": ()}
    m = quality.Model(p={k: np.asarray(r.normal(0, 0.3, s)) for k, s in sizes.items()})
    x = x.astype(float)
    y = np.array([0, 1, 0, 1, 1, 0.0])

    def loss():
        z = m.forward(x, first)["y"]
        return float((np.log1p(np.exp(z)) - y * z).mean())

    s = m.forward(x, first)
    grads = m.gradients(s, first, (1 / (1 + np.exp(-s["y"])) - y) / len(y))
    for k in sizes:
        at = tuple(0 for _ in m.p[k].shape)
        keep = m.p[k].copy()
        m.p[k] = keep.copy()
        m.p[k][at] += 1e-6
        up = loss()
        m.p[k] = keep.copy()
        m.p[k][at] -= 1e-6
        down = loss()
        m.p[k] = keep
        assert abs((up - down) / 2e-6 - grads[k][at]) < 1e-5


def _planted_votes(n):
    r = np.random.default_rng(1)
    y = r.random(n) < 0.3
    votes = np.stack([np.where(y, r.random(n) < a, r.random(n) < b) for a, b in ((0.9, 0.02), (0.7, 0.05), (0.6, 0.1), (0.8, 0.03))], axis=1)
    # voters that nearly repeat a weak one, false votes included
    copies = [np.where(r.random(n) < 0.95, votes[:, 2], r.random(n) < 0.3) for _ in range(3)]
    return y, np.column_stack([votes, *copies]).astype(float)


def test_label_model_finds_rates_and_ties_without_labels():
    y, votes = _planted_votes(6000)
    m = toxicity.fit_label_model(votes, 0.3)
    group = {2, 4, 5, 6}
    tied = {(k, int(p)) for k, p in enumerate(m.parent) if p >= 0}
    assert len([1 for a, b in tied if a in group and b in group]) == 3  # the repeating voters hang together in a tree
    for voter, (a, b) in enumerate(((0.9, 0.02), (0.7, 0.05))):
        assert abs(((m.posterior(votes) > 0.5) & (votes[:, voter] > 0)).sum() / (m.posterior(votes) > 0.5).sum() - a) < 0.08
    alone = toxicity.LabelModel(m.share, np.full(votes.shape[1], -1), np.repeat(np.stack([votes[~y].mean(axis=0), votes[y].mean(axis=0)])[:, None, :], 2, axis=1))
    right = lambda model: ((model.posterior(votes) > 0.5) == y).mean()
    assert right(m) >= right(alone) - 0.002 and right(m) > 0.96
    # independent voters at their true rates are too sure of what the repeating voters say alone
    only = (votes[:, sorted(group)].min(axis=1) > 0) & (votes[:, [0, 1, 3]].max(axis=1) == 0)
    truth = y[only].mean()
    assert abs(m.posterior(votes)[only].mean() - truth) < abs(alone.posterior(votes)[only].mean() - truth)


def test_posterior_against_enumeration():
    r = np.random.default_rng(4)
    parent, chance = np.array([-1, 0, 0, 1]), r.uniform(0.05, 0.95, (2, 2, 4))
    m = toxicity.LabelModel(0.2, parent, chance)

    def joint(c, v):
        p = m.share if c else 1 - m.share
        for k in range(4):
            q = chance[c][v[parent[k]] if parent[k] >= 0 else 0][k]
            p *= q if v[k] else 1 - q
        return p

    every = [[(k >> j) & 1 for j in range(4)] for k in range(16)]
    assert abs(sum(joint(c, v) for c in (0, 1) for v in every) - 1) < 1e-9
    got = m.posterior(np.array(every, float))
    assert np.allclose(got, [joint(1, v) / (joint(0, v) + joint(1, v)) for v in every])


def test_quality_scores_against_plain_loops():
    """The vectorised attention over bags equals a document at a time, a passage at a time."""
    r = np.random.default_rng(5)
    texts = [b"", b"a", *(" ".join(r.choice(["ab", "cde", "f", "12", "!!"], int(n))).encode() for n in r.integers(1, 900, 8))]
    sizes = {"E": (quality.N_FEATURES, 5), "e": (5,), "V": (5, 3), "U": (5, 3), "w": (3,), "c": (5,), "b": ()}
    p = {k: np.asarray(r.normal(0, 0.5, s)) for k, s in sizes.items()}
    m = quality.Model(mean=np.full(quality.N_FEATURES, 0.1), scale=np.full(quality.N_FEATURES, 0.7), p=p)
    for t, got in zip(texts, m.scores(texts), strict=True):
        bag, _ = quality.passages([t])
        hidden = [np.tanh(((x - 0.1) / 0.7) @ p["E"] + p["e"]) for x in bag.astype(float)]
        raw = [float((np.tanh(h @ p["V"]) / (1 + np.exp(-(h @ p["U"])))) @ p["w"]) for h in hidden]
        share = [np.exp(a - max(raw)) for a in raw]
        z = sum(a * h for a, h in zip(share, hidden, strict=True)) / sum(share)
        assert len(bag) == max(1, -(-len(t) // quality.PASSAGE_BYTES)) and abs(got - 1 / (1 + np.exp(-(z @ p["c"] + p["b"])))) < 1e-4


def test_chat_round_trip_and_forged_turns(spark, sf):
    got = {r.conv_id: r for r in op9_format_chat(spark, sf).collect()}
    want = hashlib.sha256(f"user\n{FORGED}\nassistant\n{FORGED}\n".encode()).hexdigest()
    assert got[-1].turns_sha256 == want and got[-1].n_turns == 2 and got[-1].loss_chars == len(FORGED)


def test_chat_edge_cases(spark, monkeypatch):
    rows = [(1, k, "assistant" if k % 2 else "user", "é<|im_end|>\\<\\|x" * k) for k in range(60)]
    rows += [(None, 0, None, None), (2, None, "a\nb\\n", "<"), (2, None, "a\nb\\n", "<"), (2, 1, "assistant", "")]
    d = spark.createDataFrame([(*r, "x") for r in rows], "conv_id long, turn long, role string, text string, piece string")
    got = {r.conv_id: r for r in chat.digest_formatted(chat.format_conversations(d)).collect()}
    for c in (1, 2, None):
        own = sorted((r for r in rows if r[0] == c), key=lambda r: (r[1] is not None, r[1] or 0, r[2] or "", r[3] or ""))
        loss = "".join(r[3] for r in own if r[2] == "assistant")
        assert got[c].turns_sha256 == hashlib.sha256("".join(f"{r[2] or ''}\n{r[3] or ''}\n" for r in own).encode()).hexdigest()
        assert (got[c].n_turns, got[c].loss_chars, got[c].loss_sha256) == (len(own), len(loss), hashlib.sha256(loss.encode()).hexdigest())
    assert chat.digest_formatted(chat.format_conversations(d.limit(0))).count() == 0


def test_chat_pieces_of_a_long_conversation(monkeypatch):
    monkeypatch.setattr(chat, "PIECE_BYTES", 2000)
    rows = [(7, "user" if k % 2 else "assistant", "text <| " * 20) for k in range(200)] + [(8, "user", "end")]
    batch = pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows]), pa.array([r[2] for r in rows])], names=["conv_id", "role", "text"])
    monkeypatch.setattr(chat, "byte_chunks", lambda b, _: (b.slice(k, 30) for k in range(0, b.num_rows, 30)))
    pieces = list(chat._format(iter([batch])))
    formatted = [x for p in pieces for x in p.to_pylist()]
    assert len(formatted) > 3 and [x["piece"] for x in formatted if x["conv_id"] == 7] == list(range(len(formatted) - 1))
    out = [x for p in chat._digest(iter(pieces)) for x in p.to_pylist()]
    assert [(x["conv_id"], x["n_turns"]) for x in out] == [(7, 200), (8, 1)]
    assert out[0]["turns_sha256"] == hashlib.sha256("".join(f"{r}\n{t}\n" for c, r, t in rows if c == 7).encode()).hexdigest()


def test_classifiers_learn_from_the_ends_of_long_texts(spark):
    r = random.Random(3)
    prose = lambda n: " ".join(r.choice(["river", "stone", "garden", "morning", "letter", "window"]) for _ in range(n))
    rows = [(k, prose(2000) + " " + ("zorblax @@## {{}} " * 60 if k % 2 else prose(150))) for k in range(120)]
    assert min(t.find("zorblax") for _, t in rows if "zorblax" in t) > 12_000
    d = spark.createDataFrame(rows, "doc_id long, text string")
    y = spark.createDataFrame([(k, 1 - k % 2, k % 2) for k, _ in rows], "doc_id long, quality int, toxic int")
    assert toxicity.key_of("zorblax") in toxicity.fit_toxicity(d, y).lexicon.keys.tolist()
    scores = quality.fit_quality(d, y).scores([rows[k][1].encode() for k in (0, 1, 2, 3)])
    assert min(scores[0], scores[2]) > 0.7 and max(scores[1], scores[3]) < 0.3
    kept = [t for k, t in rows if k in {x.doc_id for x in y.join(d, "doc_id").filter(~quality.held_out(F.col("doc_id"))).collect()}]
    assert [len(b) for b in quality.training_bags(d, y)[0]] == [-(-len(t.encode()) // quality.PASSAGE_BYTES) for t in kept]
