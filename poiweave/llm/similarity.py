"""Near-duplicate join on word shingles with a MinHash LSH forest.

Texts with the same set of shingles form one node. A node has a signature in every tree, and a tree's sorted signatures
are a prefix trie: how many nodes share a prefix of each length is read off neighbouring rows. A node starts with its
longest prefixes and shortens them tree by tree, first where that adds the fewest companions, until a pair at the threshold
would meet in some tree with the target recall; so prefixes stay long in dense parts of a trie and get short in thin ones.
Nodes that meet are compared by a sketch of 128 minimum hashes, which tells pairs far below the threshold; what passes forms
candidate components, and inside each every pair is verified exactly on its shingle sets by counting shared shingles with
matrix products. Branches and components of any size are compared in pairs of bounded blocks, and only counts and spanning
links leave a task, never all pairs.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..operators.components import connected_components
from .session import cut
from .textkit import as_bytes, byte_chunks, hash_windows, hash_words, split_words

SHINGLE, THRESHOLD_PARTS = 5, (4, 5)
#: Trees; lengths that a prefix may have; chance that a pair at the threshold meets in some tree.
TREES, SHORTEST, LONGEST, RECALL = 24, 4, 9, 0.9997
#: Bits of a signature's value below the shortest prefix.
BITS = 12
#: Values of a sketch, and how many a pair must share: a pair at the threshold shares fewer with chance 0.000006.
SKETCH, LEAST_SHARED = 128, 83
#: Nodes of a trie's branch that are compared in one go, and nodes of a verified block: a task holds two of either.
BRANCH, BLOCK = 1024, 128
_COLUMNS, _PAIRS, _FEW = 4096, 1 << 17, 8

_R = np.random.default_rng(2)
_MUL = (_R.integers(0, 1 << 31, TREES * LONGEST, dtype=np.uint32) * np.uint32(2)) | np.uint32(1)
_ADD = _R.integers(0, 1 << 32, TREES * LONGEST, dtype=np.uint32)
_FOLD = np.uint64(0x9E3779B97F4A7C15)
_SIMILARITY = THRESHOLD_PARTS[0] / THRESHOLD_PARTS[1]
#: What a tree adds to the log of the chance of missing a pair at the threshold, by prefix length.
GAIN = -np.log(1 - _SIMILARITY ** np.arange(SHORTEST, LONGEST + 1))


def shingle_sets(texts: list[bytes]) -> list[np.ndarray]:
    """Sorted distinct shingle hashes of each text: five words, or all words of a text with fewer; none without words."""
    w = split_words(texts)
    h = hash_words(w)
    whole = hash_windows(h, SHINGLE)
    out = []
    for a, b in zip(w.first[:-1].tolist(), w.first[1:].tolist(), strict=True):
        if b - a >= SHINGLE:
            out.append(np.unique(whole[a : b - SHINGLE + 1]))
        elif b > a:
            out.append(hash_windows(h[a:b], b - a) + np.uint64(b - a))
        else:
            out.append(np.empty(0, np.uint64))
    return out


def minima(shingles: np.ndarray) -> np.ndarray:
    """The minimum hashes of a set, ``LONGEST`` for each tree."""
    x = (shingles >> np.uint64(32)).astype(np.uint32) ^ shingles.astype(np.uint32)
    low = np.full(len(_MUL), 0xFFFFFFFF, np.uint32)
    for k in range(0, len(x), 2048):
        low = np.minimum(low, (x[k : k + 2048, None] * _MUL + _ADD).min(axis=0))
    return low


def labels(low: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For each tree the key of the shortest prefix and, as one sortable number, the values after it; and the sketch."""
    by_tree = low.reshape(TREES, LONGEST)
    key = np.arange(TREES, dtype=np.uint64)
    for k in range(SHORTEST):
        key = (key ^ by_tree[:, k]) * _FOLD
        key ^= key >> np.uint64(29)
    rest = np.zeros(TREES, np.int64)
    for k in range(SHORTEST, LONGEST):
        rest = (rest << BITS) | ((by_tree[:, k] * np.uint32(0x9E3779B1)) >> np.uint32(32 - BITS)).astype(np.int64)
    return key.view(np.int64), rest, ((low[:SKETCH] * np.uint32(0x85EBCA6B)) >> np.uint32(24)).astype(np.uint8)


def set_id(shingles: np.ndarray) -> int:
    """A 64-bit identity of a shingle set, never 0."""
    k = np.arange(1, len(shingles) + 1, dtype=np.uint64)
    h = ((shingles ^ (shingles >> np.uint64(31))) * _FOLD * (2 * k + np.uint64(1))).sum(dtype=np.uint64)
    h = ((int(h) ^ (int(h) >> 32)) * int(_FOLD) ^ len(shingles)) & 0xFFFFFFFFFFFFFFFF
    return (h - (1 << 64) if h >> 63 else h) or 1


def _signatures(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """doc_id and node of every row; keys, rests and sketch once for each node of a partition."""
    seen: set[int] = set()
    for whole in batches:
        for b in byte_chunks(whole, "text"):
            nodes, made = [], []
            for s in shingle_sets(as_bytes(b.column(1))):
                node = set_id(s) if len(s) else None
                nodes.append(node)
                made.append(labels(minima(s)) if node is not None and node not in seen else None)
                if node is not None:
                    seen.add(node)
            own = [m for m in made if m is not None]
            mask = np.array([m is None for m in made], bool)
            ends = np.append(0, np.cumsum(~mask) * TREES).astype(np.int32)
            tries = [pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate([m[k] for m in own]) if own else np.empty(0, np.int64)), mask=pa.array(mask)) for k in (0, 1)]
            sketch = pa.array([None if m is None else m[2].tobytes() for m in made], pa.binary())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(nodes, pa.int64()), *tries, sketch], names=["doc_id", "node", "keys", "rests", "sketch"])


def _shingles(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Shingles of each node, once for all rows of a partition."""
    seen: set[int] = set()
    for whole in batches:
        for b in byte_chunks(whole, "text"):
            fresh: dict[int, bytes] = {}
            for s in shingle_sets(as_bytes(b.column(0))):
                node = set_id(s) if len(s) else None
                if node is not None and node not in seen:
                    fresh[node] = s.tobytes()
            seen.update(fresh)
            yield pa.RecordBatch.from_arrays([pa.array(fresh.keys(), pa.int64()), pa.array(fresh.values(), pa.binary())], names=["node", "shingles"])


def _whole_groups(batches: Iterator[pa.RecordBatch], by: int) -> Iterator[tuple[pa.Table, np.ndarray]]:
    """Tables that end with a group (rows with equal first ``by`` columns, which are sorted), and where groups begin and end."""
    held = None
    for b in batches:
        t = pa.Table.from_batches([b])
        t = (t if held is None else pa.concat_tables([held, t])).combine_chunks()
        if not t.num_rows:
            continue
        turn = np.zeros(t.num_rows - 1, bool)
        for k in range(by):
            c = t.column(k).to_numpy()
            turn |= c[1:] != c[:-1]
        at = np.flatnonzero(turn) + 1
        held = t.slice(int(at[-1])) if len(at) else t
        if len(at):
            yield t.slice(0, int(at[-1])), np.append(0, at)
    if held is not None and held.num_rows:
        yield held, np.array([0, held.num_rows])


def _prefix_sizes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """How many nodes share a node's prefix of each length: neighbouring rows (key, branch, rest, node, m), sorted, are compared."""
    for t, ends in _whole_groups(batches, 2):
        rest, m = t.column("rest").to_numpy(), t.column("m").to_numpy()
        opens = np.zeros(len(rest), bool)
        opens[ends[:-1]] = True
        sizes = np.empty((len(rest), len(GAIN)), np.int64)
        for k in range(len(GAIN)):
            top = rest >> (BITS * (LONGEST - SHORTEST - k))
            fresh = opens.copy()
            fresh[1:] |= top[1:] != top[:-1]
            at = np.append(np.flatnonzero(fresh), len(rest))
            sizes[:, k] = np.repeat(np.diff(at), np.diff(at))
        sizes *= -(-m // BRANCH)[:, None]  # a branch dealt in parts holds about as many in each
        lists = pa.ListArray.from_arrays(pa.array(np.arange(len(rest) + 1, dtype=np.int32) * len(GAIN)), pa.array(sizes.ravel()))
        columns = [t.column(c).combine_chunks() for c in ("node", "key", "rest", "m")]
        yield pa.RecordBatch.from_arrays([*columns, lists], names=["node", "key", "rest", "m", "sizes"])


def choose_lengths(sizes: np.ndarray, counts: np.ndarray, recall: float = RECALL) -> np.ndarray:
    """Prefix length of every row of ``sizes`` (a node's tree: nodes that share each length); ``counts`` are the rows of each node.

    Starting from the lengths with the fewest companions, a price on recall is raised, which shortens prefixes where that adds few
    companions for what it gains. Once a node's trees reach the recall, the trees that are no longer needed for it go back one step. Trees
    that are not listed have no companions and are shortened for nothing.
    """
    starts = np.append(0, np.cumsum(counts))[:-1]
    owner = np.repeat(np.arange(len(counts)), counts)
    need = -np.log(1 - recall) - (TREES - counts) * GAIN[0]
    out, waits, last = np.zeros(len(sizes), np.int64), np.ones(len(counts), bool), None
    for price in (0.0, *(1.5**k for k in range(-4, 90))):
        pick = np.argmin((sizes - 1) - price * GAIN, axis=1)
        enough = waits & (np.add.reduceat(GAIN[pick], starts) >= need)
        rows = enough[owner]
        if last is None:
            out[rows] = pick[rows]
        else:
            more = GAIN[pick] - GAIN[last]
            before = np.cumsum(more) - more
            lacks = need - np.add.reduceat(GAIN[last], starts)
            out[rows] = np.where(before - before[starts][owner] < lacks[owner], pick, last)[rows]
        waits &= ~enough
        if not waits.any():
            break
        last = pick
    return out + SHORTEST


def _lengths(recall: float):
    def choose(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            twigs = b.column(1)
            counts = pa.compute.list_value_length(twigs).to_numpy().astype(np.int64)
            flat = twigs.flatten()
            own = np.repeat(np.arange(b.num_rows), counts)
            flat = flat.take(pa.array(np.lexsort((flat.field("key").to_numpy(), own))))  # the same choice in every run
            sizes = flat.field("sizes").flatten().to_numpy().reshape(len(flat), len(GAIN))
            own = pa.array(own)
            columns = [flat.field("key"), flat.field("rest"), b.column(0).take(own), flat.field("m"), pa.array(choose_lengths(sizes, counts, recall).astype(np.int32)), b.column(2).take(own)]
            yield pa.RecordBatch.from_arrays(columns, names=["key", "rest", "node", "m", "length", "sketch"])

    return choose


class Branches:
    """Nodes of one or more branches: do two of them meet, and does their sketch let them pass?"""

    def __init__(self, rest: np.ndarray, length: np.ndarray, sketch: np.ndarray):
        self.rest, self.length, self.sketch = rest, length, sketch

    def meet(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """For pairs of positions: is the common prefix as long as the shorter of both lengths?"""
        shift = BITS * (LONGEST - np.minimum(self.length[a], self.length[b]))
        return ((self.rest[a] ^ self.rest[b]) >> shift) == 0

    def alike(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        out = np.flatnonzero(self.meet(a, b))
        passed = [(self.sketch[a[k]] == self.sketch[b[k]]).sum(axis=1) >= LEAST_SHARED for k in (out[i : i + _PAIRS] for i in range(0, len(out), _PAIRS))]
        return out[np.concatenate(passed)] if passed else out

    def small_groups(self, starts: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
        """Alike pairs in all groups of one small size."""
        i, j = np.triu_indices(size, 1)
        a, b = (starts[:, None] + i).ravel(), (starts[:, None] + j).ravel()
        at = self.alike(a, b)
        return a[at], b[at]

    def large_group(self, begin: int, end: int, side: np.ndarray | None) -> list[tuple[int, int]]:
        """Links that join all that alike pairs join. ``side`` tells the two blocks apart of which only mixed pairs are asked for.

        What is alike a pivot is one part at once; only nodes outside the largest such part are compared with all others.
        """
        n = end - begin
        every = np.arange(begin, end)
        best, pivot = np.empty(0, np.int64), begin
        for p in {begin, begin + n // 2, end - 1}:
            near = self.alike(np.full(n, p), every)
            if len(near) > len(best):
                best, pivot = near, p
        part = np.arange(n)
        part[best] = part[pivot - begin]
        links = [(pivot, begin + int(k)) for k in best if begin + k != pivot]
        for u in np.flatnonzero(part != part[pivot - begin]).tolist():
            others = every if side is None else every[side != side[u]]
            near = others[self.alike(np.full(len(others), begin + u), others)] - begin
            own, first = np.unique(part[near], return_index=True)
            for p, v in zip(own.tolist(), near[first].tolist(), strict=True):
                if p != part[u]:
                    links.append((begin + u, begin + v))
                    part[part == p] = part[u]
        return links


def _meetings(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Candidate links (a, b) from rows (key, i, j, block, rest, node, length, sketch) sorted by task (key, i, j)."""
    for t, ends in _whole_groups(batches, 3):
        node, block = t.column("node").to_numpy(), t.column("block").to_numpy()
        sketch = np.frombuffer(b"".join(t.column("sketch").to_pylist()), np.uint8).reshape(-1, SKETCH)
        own = Branches(t.column("rest").to_numpy(), t.column("length").to_numpy().astype(np.int64), sketch)
        sizes, links = np.diff(ends), []
        for n in range(2, _FEW + 1):
            a, b = own.small_groups(ends[:-1][sizes == n], n)
            links.append(np.stack([node[a], node[b]]))
        for g in np.flatnonzero(sizes > _FEW).tolist():
            begin, end = int(ends[g]), int(ends[g + 1])
            side = block[begin:end] if block[begin:end].min() < block[begin:end].max() else None
            found = own.large_group(begin, end, side)
            if found:
                links.append(node[np.array(found).T])
        a, b = np.concatenate(links, axis=1)
        yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], names=["a", "b"])


def candidate_links(nodes: DataFrame, recall: float = RECALL, branch: int = BRANCH) -> DataFrame:
    """(a, b): links that join all nodes which the forest and their sketches hold to be alike. ``nodes`` has node, keys, rests, sketch."""
    twigs = nodes.select("node", F.explode(F.arrays_zip("keys", "rests")).alias("x")).select("node", F.col("x.keys").alias("key"), F.col("x.rests").alias("rest"))
    shared = twigs.groupBy("key").agg(F.count(F.lit(1)).alias("m")).filter("m > 1")
    live = twigs.join(shared, "key")
    blocks = F.ceil(F.col("m") / branch).cast("int")
    block = F.pmod(F.xxhash64(F.lit(4), "node"), blocks).cast("int")
    sized = live.withColumn("branch", block).select("key", "branch", "rest", "node", "m").repartition("key", "branch").sortWithinPartitions("key", "branch", "rest", "node")
    sized = sized.mapInArrow(_prefix_sizes, "node bigint, key bigint, rest bigint, m bigint, sizes array<bigint>")
    of_node = sized.groupBy("node").agg(F.collect_list(F.struct("key", "rest", "m", "sizes")).alias("twigs"))  # at most one for each tree
    chosen = of_node.join(nodes.select("node", "sketch"), "node").select("node", "twigs", "sketch")
    chosen = chosen.mapInArrow(_lengths(recall), "key bigint, rest bigint, node bigint, m bigint, length int, sketch binary")
    dealt = chosen.withColumns({"block": block, "other": F.explode(F.sequence(F.lit(0), blocks - 1))})
    dealt = dealt.select("key", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "block", "rest", "node", "length", "sketch")
    return dealt.repartition("key", "i", "j").sortWithinPartitions("key", "i", "j").mapInArrow(_meetings, "a bigint, b bigint")


def count_links(sets_a: list[np.ndarray], sets_b: list[np.ndarray]) -> np.ndarray:
    """Matrix of pairs whose similarity reaches the threshold, exactly, in integers."""
    both = np.concatenate([*sets_a, *sets_b])
    owner = np.repeat(np.arange(len(sets_a) + len(sets_b)), [len(s) for s in (*sets_a, *sets_b)])
    value, column, times = np.unique(both, return_inverse=True, return_counts=True)
    shared = times > 1
    renamed = np.cumsum(shared) - 1
    keep = shared[column]
    column, owner = renamed[column[keep]], owner[keep]
    order = np.argsort(column, kind="stable")
    column, owner = column[order], owner[order]
    width = int(shared.sum())
    inter = np.zeros((len(sets_a), len(sets_b)), np.float32)
    for begin in range(0, width, _COLUMNS):
        lo, hi = np.searchsorted(column, (begin, begin + _COLUMNS))
        m = np.zeros((len(sets_a) + len(sets_b), min(_COLUMNS, width - begin)), np.float32)
        m[owner[lo:hi], column[lo:hi] - begin] = 1
        inter += m[: len(sets_a)] @ m[len(sets_a) :].T
    shared_n = np.rint(inter).astype(np.int64)
    union = np.array([len(s) for s in sets_a])[:, None] + np.array([len(s) for s in sets_b])[None, :] - shared_n
    part, of = THRESHOLD_PARTS
    return (shared_n * of >= part * union) & (shared_n > 0)


Name = tuple[int, int]


def _verify(rows: list[tuple[int, Name, int, bytes]], first: int, second: int) -> list[tuple[int, int, int, int, int]]:
    """(least id, node, linked documents, least id and node of the root) of one pair of blocks. rows: (block, name, documents, shingles)."""
    sides = []
    for block in (first, second):
        own = sorted({r[1]: r for r in rows if r[0] == block}.values(), key=lambda r: r[1])
        sides.append(([r[1] for r in own], np.array([r[2] for r in own], np.int64), [np.frombuffer(r[3], np.uint64) for r in own]))
    (names_a, docs_a, sets_a), (names_b, docs_b, sets_b) = sides
    if not names_a or not names_b:
        return []
    links = count_links(sets_a, sets_b)
    if first == second:
        np.fill_diagonal(links, False)
    parent = {n: n for n in (*names_a, *names_b)}

    def root(n: Name) -> Name:
        while parent[n] != n:
            parent[n] = parent[parent[n]]
            n = parent[n]
        return n

    for i, row in enumerate(links):
        for j in np.flatnonzero(row).tolist():
            a, b = root(names_a[i]), root(names_b[j])
            if a != b:
                parent[max(a, b)] = min(a, b)
    out = [(*n, int(c), *root(n)) for n, c in zip(names_a, links @ docs_b, strict=True)]
    if first != second:
        out += [(*n, int(c), *root(n)) for n, c in zip(names_b, docs_a @ links, strict=True)]
    return out


def _verify_groups(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows arrive sorted by task (component, first, second); one task is held at a time."""
    names = ["id", "node", "linked", "root_id", "root_node"]

    def out(made: list[tuple[int, int, int, int, int]]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array([m[k] for m in made], pa.int64()) for k in range(5)], names=names)

    task, rows = None, []
    for b in batches:
        made = []
        columns = [c.to_pylist() for c in b.columns]
        for comp, i, j, block, least, node, docs, shingles in zip(*columns, strict=True):
            if (comp, i, j) != task:
                if task:
                    made += _verify(rows, task[1], task[2])
                task, rows = (comp, i, j), []
            rows.append((block, (least, node), docs, shingles))
        yield out(made)
    if task:
        yield out(_verify(rows, task[1], task[2]))


def _classes(documents: DataFrame, recall: float, block: int) -> tuple[DataFrame, DataFrame]:
    """doc_id and node of every row; and for every node id (its least document), class_id, class_node, n_links.

    A node's name is (least id, node), so names order like ids, nodes that share an id stay apart, and a class's least name is its root.
    """
    kind = documents.schema["doc_id"].dataType.simpleString()
    own = cut(documents.select("doc_id", "text").mapInArrow(_signatures, f"doc_id {kind}, node bigint, keys array<bigint>, rests array<bigint>, sketch binary"))
    part = own.filter("doc_id is not null and node is not null")
    # the first copy in a partition has the signature, which a copy without an id may be
    signed = own.filter("keys is not null").select("node", "keys", "rests", "sketch")
    sums = part.groupBy("node").agg(F.min("doc_id").cast("long").alias("id"), F.count(F.lit(1)).alias("docs"))
    nodes = cut(sums.join(signed.groupBy("node").agg(*(F.first(c).alias(c) for c in ("keys", "rests", "sketch"))), "node"))
    candidates = cut(connected_components(candidate_links(nodes, recall)))

    # shingles of one document of each candidate node, read again from the texts
    chosen = cut(candidates.join(nodes.select("node", "id", "docs"), "node").select("node", "root", "id", "docs"))
    wanted = documents.select(F.col("doc_id"), "text").join(chosen.select(F.col("id").cast(kind).alias("doc_id")).distinct(), "doc_id", "left_semi")
    sets = wanted.select("text").mapInArrow(_shingles, "node bigint, shingles binary")
    sizes = chosen.groupBy("root").agg(F.ceil(F.count(F.lit(1)) / block).cast("int").alias("blocks"))
    dealt = chosen.join(sets, "node").join(sizes, "root").withColumn("block", F.pmod(F.xxhash64(F.lit(4), "node"), F.col("blocks")).cast("int"))
    dealt = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    dealt = dealt.select("root", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "block", "id", "node", "docs", "shingles")
    tasks = dealt.repartition("root", "i", "j").sortWithinPartitions("root", "i", "j", "block", "id", "node")
    verified = cut(tasks.mapInArrow(_verify_groups, "id bigint, node bigint, linked bigint, root_id bigint, root_node bigint"))

    linked = verified.groupBy("node").agg(F.sum("linked").alias("linked"))
    name = lambda i, n: F.struct(F.col(i).alias("id"), F.col(n).alias("node"))
    roots = connected_components(verified.select(name("id", "node").alias("a"), name("root_id", "root_node").alias("b")))
    roots = roots.select(F.col("node.node").alias("node"), F.col("root.id").alias("root_id"), F.col("root.node").alias("root_node"))
    joined = nodes.select("node", "id", "docs").join(linked, "node", "left").join(roots, "node", "left")
    classes = joined.select("node", "id", F.coalesce("root_id", "id").alias("class_id"), F.coalesce("root_node", "node").alias("class_node"), (F.coalesce("linked", F.lit(0)) + F.col("docs") - 1).alias("n_links"))
    return own.select("doc_id", "node"), cut(classes)


def link_documents(documents: DataFrame, recall: float = RECALL, block: int = BLOCK) -> DataFrame:
    """doc_id, class_id, n_links for every row: near-duplicate classes at similarity 0.8 of five-word shingles.

    ``class_id`` is the smallest id of the documents connected by verified links; ``n_links`` counts the other rows whose
    similarity reaches the threshold, equal ones included. A text without words (null, empty) has no links and is a class of its
    own; rows without an id get class null and no links, and take no part. Ids are integers; rows that share an id but hold
    different texts are judged by their texts, each in its own class, and repeated rows are copies of each other. Extra columns
    are ignored; an empty table gives an empty result.
    """
    own, classes = _classes(documents, recall, block)
    kind = documents.schema["doc_id"].dataType.simpleString()
    of_node = classes.select(F.col("node").alias("__node"), F.col("class_id").cast(kind).alias("class_id"), "n_links")
    alone = F.when(F.col("doc_id").isNotNull(), F.coalesce("class_id", "doc_id"))
    key = F.when(F.col("doc_id").isNotNull(), F.col("node"))
    return own.join(of_node, key == F.col("__node"), "left").select("doc_id", alone.alias("class_id"), F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"))


def _with_node(text: str):
    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in byte_chunks(whole, text):
                nodes = [set_id(s) if len(s) else None for s in shingle_sets(as_bytes(b.column(b.schema.get_field_index(text))))]
                yield pa.RecordBatch.from_arrays([pa.array(nodes, pa.int64()) if f.name == "__node" else b.column(i) for i, f in enumerate(b.schema)], names=b.schema.names)

    return scan


def keep_first(documents: DataFrame, recall: float = RECALL, block: int = BLOCK) -> DataFrame:
    """One row of each class, with all its columns: a document with the class's smallest id, or one that has the same shingles.

    Classes are of texts, so rows that share an id and differ in text do not stand for each other. Rows without an id or without words stay.
    """
    _, classes = _classes(documents.select("doc_id", "text"), recall, block)
    firsts = classes.filter("node = class_node").select(F.col("id").alias("__id"), F.col("node").alias("__first"))
    marked = documents.withColumn("__node", F.lit(None).cast("bigint"))
    marked = marked.mapInArrow(_with_node("text"), marked.schema)
    judged = F.col("doc_id").isNotNull() & F.col("__node").isNotNull()
    copies = marked.filter(judged).join(firsts, (F.col("__node") == F.col("__first")) & (F.col("doc_id") == F.col("__id")), "left_semi")
    one = copies.withColumn("__n", F.row_number().over(Window.partitionBy("__node", "doc_id").orderBy(F.xxhash64("text")))).filter("__n = 1")
    return one.select(*documents.columns).unionByName(marked.filter(~judged).select(*documents.columns))
