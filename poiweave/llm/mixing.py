"""Mixing sources to target weights with DataFrame functions only.

A source's rows fall into permuted blocks by a hash of their id. A source whose target is ``r`` times its
size and a bit contributes every block ``r`` times and, in permuted order, further blocks up to the
rest of the target; the block at the edge is cut inside, first by sub-blocks, then by rows. The block
counts of all sources are then split between output shards down a binary tree: at each node
the left half's count of every source is drawn from the multivariate hypergeometric law
(one conditional draw per source, by inverting the exact cumulative law), so that quotas
stay exact. Each shard draws its quota of disjoint blocks from the sources' permuted blocks and is
shuffled by a hash of id and repetition.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .session import cut

#: Fixed values of the mix: weights of the sources in order, repeating; most repeats of a source.
WEIGHTS = (5, 2, 1)
MOST = 3
BLOCKS = 1024
#: Sources in one chain of conditional draws.
FAN = 256
#: Rows that may be added or left out to close the gap at a source's edge: the largest that fit, the smallest, the next larger.
FITTING, SMALLEST, LARGER = 32, 64, 4
#: Beyond so many rows a block table is joined by a shuffle instead of a broadcast.
BROADCAST_ROWS = 100_000


@dataclass(frozen=True)
class MixPlan:
    """Per source: words, target and block counts; per block: where its copies go."""

    sources: DataFrame  #: src, source_size, target, whole, extra
    quotas: DataFrame  #: shard, src, quota
    blocks: DataFrame  #: src, block, placements array<struct<rep, shard>>, edge struct<rep, shard> or null
    edges: DataFrame  #: src, block, sub, rest: inside the block at the edge, words left for sub-block ``sub``
    fill: DataFrame  #: src, u, id, words, copies, delta, spot: rows with more or fewer copies, which close the gap between what the edge took and the target


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def _draw(*parts: Column) -> Column:
    """A number in [0, 1) fixed by its parts."""
    return F.pmod(F.xxhash64(*parts), F.lit(1 << 40)) / F.lit(float(1 << 40))


def _row_hash(doc_id: Column, seed: int) -> Column:
    return F.pmod(F.xxhash64(F.lit(seed), doc_id), F.lit(1 << 40))


def _small(df: DataFrame, rows: int) -> DataFrame:
    return F.broadcast(df) if rows <= BROADCAST_ROWS else df


def numbered(rows: DataFrame, *order: str | Column) -> DataFrame:
    """``rows`` plus ``nth``, their number from 0 in a total order: sorted ranges are numbered each for itself, after the counts of the ranges before."""
    held = cut(rows.repartitionByRange(*order).withColumn("__part", F.spark_partition_id()))
    counts = held.groupBy("__part").agg(F.count(F.lit(1)).alias("__rows"))  # a row for each partition
    starts = counts.select("__part", F.coalesce(F.sum("__rows").over(Window.orderBy("__part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("__start"))
    place = F.row_number().over(Window.partitionBy("__part").orderBy(*order))
    return held.join(F.broadcast(starts), "__part").withColumn("nth", F.col("__start") + place - 1).drop("__part", "__start")


def targets(sizes: DataFrame) -> DataFrame:
    """``sizes`` (src, source_size) plus nth, weight and target: shares by weight, none above MOST times its size.

    Sources are weighed in code point order, null last. The excess of the sources above their cap is reshared by weight over the others, again and again
    until no further one is above: each round is one aggregation.
    """
    weight = F.element_at(F.array(*map(F.lit, WEIGHTS)), (F.col("nth") % len(WEIGHTS) + 1).cast("int"))
    rows = cut(numbered(sizes, F.col("src").isNull(), "src").withColumn("weight", weight).withColumn("cap", F.lit(float(MOST)) * F.col("source_size")))
    total, weights = rows.agg(F.coalesce(F.sum("source_size"), F.lit(0)), F.coalesce(F.sum("weight"), F.lit(0))).first()
    level, capped = total / max(1, weights), -1
    while True:
        over = F.lit(float(level)) * F.col("weight") > F.col("cap")
        n, given, taken = rows.filter(over).agg(F.count(F.lit(1)), F.coalesce(F.sum("weight"), F.lit(0)), F.coalesce(F.sum("cap"), F.lit(0.0))).first()
        if n == capped or given == weights:
            break
        level, capped = (total - taken) / (weights - given), n
    return rows.withColumn("target", F.least("cap", F.lit(float(level)) * F.col("weight"))).select("src", "nth", "source_size", "weight", "target")


def _let(value: Column, body) -> Column:
    """``body`` of a value that is computed once."""
    return F.transform(F.array(value), body)[0]


def hypergeometric(population: Column, marked: Column, drawn: Column, u: Column) -> Column:
    """How many of ``drawn`` from ``population`` are ``marked``: the law inverted at ``u``.

    Points further than twelve standard deviations (and two) from the mean, whose mass is below the
    precision of doubles, are left out.
    """
    least, most = F.greatest(F.lit(0).cast("long"), drawn - population + marked), F.least(marked, drawn)
    mean = drawn * marked / F.greatest(population, F.lit(1))
    wide = 12 * F.sqrt(F.greatest(mean * (1 - marked / F.greatest(population, F.lit(1))), F.lit(0.0))) + 2

    def law(points: Column) -> Column:
        def step(x: Column) -> Column:  # log p(x) - log p(x - 1); 0 at the first point
            up = (marked - x + 1) * (drawn - x + 1)
            down = x * (population - marked - drawn + x)
            return F.when(x == points[0], F.lit(0.0)).otherwise(F.log(up.cast("double")) - F.log(down.cast("double")))

        logs = F.struct(F.lit(0.0).alias("log"), F.lit(0.0).alias("top"))
        top = F.aggregate(points, logs, lambda a, x: _let(a["log"] + step(x), lambda v: F.struct(v.alias("log"), F.greatest(a["top"], v).alias("top"))), lambda a: a["top"])

        def mass(t: Column) -> Column:
            sums = F.struct(F.lit(0.0).alias("log"), F.lit(0.0).alias("sum"))
            return F.aggregate(points, sums, lambda a, x: _let(a["log"] + step(x), lambda v: F.struct(v.alias("log"), (a["sum"] + F.exp(v - t)).alias("sum"))), lambda a: a["sum"])

        def invert(t: Column, total: Column) -> Column:
            start = F.struct(F.lit(0.0).alias("log"), F.lit(0.0).alias("sum"), points[0].alias("at"))
            walk = lambda a, x: _let(a["log"] + step(x), lambda v: F.struct(v.alias("log"), (a["sum"] + F.exp(v - t)).alias("sum"), F.when(a["sum"] <= u * total, x).otherwise(a["at"]).alias("at")))
            return F.aggregate(points, start, walk, lambda a: a["at"])

        return _let(top, lambda t: _let(mass(t), lambda total: invert(t, total)))

    low = F.greatest(least, F.floor(mean - wide).cast("long"))
    high = F.least(most, F.ceil(mean + wide).cast("long"))
    return _let(F.sequence(low, high), law)


def _draw_left(split: DataFrame, levels: int, seed: int) -> DataFrame:
    """``split`` (low, high, src, nth, n) plus got: how many of each source's blocks the left half of its node draws.

    One draw for each source, conditional on those before it, would be one long chain. So sources form groups of ``FAN``, groups of
    groups and so on, ``levels`` high: the draws of a node are split over its groups, a group's over its members, each chain in a row of its own.
    """
    node = ["low", "high"]
    sums = [split.select(*node, F.col("nth").alias("id"), "n", "src")]
    for _ in range(levels - 1):
        sums.append(sums[-1].groupBy(*node, F.floor(F.col("id") / FAN).alias("id")).agg(F.sum("n").alias("n")).withColumn("src", F.lit(None).cast("string")))
    middle, draws = F.floor((F.col("low") + F.col("high")) / 2), None
    for level in reversed(range(levels)):
        groups = sums[level].groupBy(*node, F.floor(F.col("id") / FAN).alias("up")).agg(F.array_sort(F.collect_list(F.struct("id", "n", "src"))).alias("own"), F.sum("n").alias("all"))
        if draws is None:  # one group a node
            groups = groups.withColumn("draws", F.round(F.col("all") * (middle - F.col("low")) / (F.col("high") - F.col("low"))).cast("long"))
        else:
            groups = groups.join(draws.select(*node, F.col("nth").alias("up"), F.col("got").alias("draws")), [*node, "up"])
        place = [F.lit(seed), F.lit(level), F.col("low"), F.col("high")]

        def merge(a: Column, x: Column) -> Column:
            k = hypergeometric(a["left"], x["n"], a["draws"], _draw(*place, x["id"]))
            return F.struct((a["left"] - x["n"]).alias("left"), (a["draws"] - k).alias("draws"), F.concat(a["got"], F.array(k)).alias("got"))

        begin = F.struct(F.col("all").alias("left"), F.col("draws"), F.array().cast("array<bigint>").alias("got"))
        drawn = groups.withColumn("got", F.aggregate("own", begin, merge, lambda a: a["got"]))
        draws = drawn.select(*node, F.explode(F.arrays_zip("own", "got")).alias("x")).select(*node, F.col("x.own.src").alias("src"), F.col("x.own.id").alias("nth"), F.col("x.own.n").alias("n"), F.col("x.got").alias("got"))
    return draws


def split_quotas(counts: DataFrame, shards: int, seed: int) -> DataFrame:
    """Rows (shard, src, quota): block counts (src, nth, n) split down the tree; quotas of a source add up to its n. ``nth`` numbers the sources from 0."""
    levels, n = 1, counts.count()
    while FAN**levels < n:
        levels += 1
    tree = counts.select(F.lit(0).alias("low"), F.lit(shards).alias("high"), "src", "nth", F.col("n").cast("long").alias("n"))
    for _ in range(max(0, (shards - 1).bit_length())):
        both = _draw_left(tree.filter("high - low > 1"), levels, seed).withColumn("mid", F.floor((F.col("low") + F.col("high")) / 2).cast("int"))
        left = both.select("low", F.col("mid").alias("high"), "src", "nth", F.col("got").alias("n"))
        right = both.select(F.col("mid").alias("low"), "high", "src", "nth", (F.col("n") - F.col("got")).alias("n"))
        tree = cut(tree.filter("high - low <= 1").unionByName(left).unionByName(right))
    return tree.select(F.col("low").alias("shard"), "src", F.col("n").alias("quota"))


def plan_mix(rows: DataFrame, shards: int, seed: int) -> MixPlan:
    """The plan for ``rows`` (src, id, words, u)."""
    block, sub = F.shiftright("u", 30).alias("block"), F.shiftright("u", 20).bitwiseAND(F.lit(BLOCKS - 1)).alias("sub")
    blocks = cut(rows.groupBy("src", block).agg(F.sum("words").alias("words")))
    sizes = targets(blocks.groupBy("src").agg(F.sum("words").alias("source_size")))
    share = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    sources = cut(sizes.withColumn("whole", F.least(F.floor(share + 1e-12), F.lit(MOST)).cast("int")).withColumn("extra", F.when(F.col("whole") >= MOST, 0.0).otherwise(F.greatest(F.lit(0.0), F.col("target") - F.col("whole") * F.col("source_size")))))
    n = sources.count()
    few = _small(sources, n)
    order = Window.partitionBy("src").orderBy("block")
    run = F.sum("words").over(order)
    marked = blocks.withColumn("run", run).join(few, blocks["src"].eqNullSafe(few["src"])).select(blocks["src"], "nth", "block", "words", "run", "whole", "extra")
    marked = marked.withColumn("full", (F.col("run") <= F.col("extra")) & (F.col("extra") > 0)).withColumn("edge", (F.col("run") > F.col("extra")) & (F.col("run") - F.col("words") < F.col("extra")))
    copies = F.col("whole") + F.when(F.col("full") | F.col("edge"), 1).otherwise(0)
    marked = cut(marked.withColumn("copies", copies))
    quotas = split_quotas(cut(marked.groupBy("src", "nth").agg(F.sum("copies").alias("n"))), shards, seed)
    to = Window.partitionBy("src").orderBy("shard")
    spans = quotas.withColumn("end", F.sum("quota").over(to)).withColumn("begin", F.col("end") - F.col("quota")).filter("quota > 0")
    spans = spans.groupBy("src").agg(F.array_sort(F.collect_list(F.struct("begin", "end", "shard"))).alias("spans"))
    drawn = marked.filter("copies > 0").withColumn("rep", F.explode(F.sequence(F.lit(0), F.col("copies") - 1)))
    permuted = Window.partitionBy("src").orderBy(F.xxhash64(F.lit(seed), "src", "block", "rep"), "block", "rep")
    drawn = drawn.withColumn("at", F.row_number().over(permuted) - 1)
    drawn = drawn.join(_small(spans, n), drawn["src"].eqNullSafe(spans["src"])).select(drawn["src"], "block", "rep", "whole", "edge", F.filter("spans", lambda s: (s["begin"] <= F.col("at")) & (F.col("at") < s["end"]))[0]["shard"].alias("shard"))
    is_edge = F.col("edge") & (F.col("rep") == F.col("whole"))
    spot = F.struct("rep", "shard")
    placed = cut(drawn.groupBy("src", "block").agg(F.array_sort(F.collect_list(F.when(~is_edge, spot))).alias("placements"), F.max(F.when(is_edge, spot)).alias("edge")))
    rest = marked.filter("edge").select(F.col("src").alias("e_src"), F.col("block").alias("e_block"), (F.col("extra") - F.col("run") + F.col("words")).alias("rest"))
    subs = rows.select("src", block, sub, "words").join(_small(rest, n), F.col("src").eqNullSafe(F.col("e_src")) & (F.col("block") == F.col("e_block")))
    subs = subs.groupBy("src", "block", "sub").agg(F.sum("words").alias("words"), F.max("rest").alias("rest"))
    inner = F.sum("words").over(Window.partitionBy("src", "block").orderBy("sub"))
    subs = subs.withColumn("run", inner).filter((F.col("run") > F.col("rest")) & (F.col("run") - F.col("words") < F.col("rest")))
    edges = cut(subs.select("src", "block", "sub", (F.col("rest") - F.col("run") + F.col("words")).alias("rest")))
    at_edge = edges.select(F.col("src").alias("e_src"), F.col("block").alias("e_block"), F.col("sub").alias("e_sub"), "rest")
    cell = rows.select("src", block, sub, "words", "u", "id").join(_small(at_edge, n), F.col("src").eqNullSafe(F.col("e_src")) & (F.col("block") == F.col("e_block")) & (F.col("sub") == F.col("e_sub")))
    cell = cut(cell.withColumn("in", F.sum("words").over(_in_cell("src", "u", "id")) <= F.col("rest")).select("src", "u", "id", "words", "in", "rest", "e_sub"))
    gaps = cell.groupBy("src").agg((F.max("rest") - F.coalesce(F.sum(F.when(F.col("in"), F.col("words"))), F.lit(0))).alias("gap"), F.max("e_sub").alias("e_sub"))
    spots = placed.filter("edge is not null").select(F.col("src").alias("e_src"), F.col("block").alias("e_block"), F.col("edge").alias("spot"))
    gaps = gaps.join(spots, F.col("src").eqNullSafe(F.col("e_src"))).join(few.select(F.col("src").alias("f_src"), "whole"), F.col("src").eqNullSafe(F.col("f_src"))).select("e_src", "e_block", "e_sub", "gap", "spot", "whole").filter("gap > 0")
    fill = fill_gaps(rows.select("src", block, sub, "words", "u", "id"), cell.select("src", "u", "id", "words", "in"), gaps, n)
    return MixPlan(sources, quotas, placed, edges, cut(fill))


def fill_gaps(rows: DataFrame, cell: DataFrame, gaps: DataFrame, n: int) -> DataFrame:
    """src, u, id, words, copies, delta, spot: how many copies more (or fewer) some rows of a source get, so that its words come near the target.

    Equal rows with equally many copies can't be told apart and count as one item. Either items are added, from the largest that fits to the smallest, each as often as it fits and MOST allows; or
    the next larger item is added and copies of small ones are left out likewise; what misses the target by less is done.
    """
    source = F.col("src").eqNullSafe(F.col("e_src"))
    before = (F.col("block") < F.col("e_block")) | ((F.col("block") == F.col("e_block")) & (F.col("sub") < F.col("e_sub")))
    outside = (F.col("block") != F.col("e_block")) | (F.col("sub") != F.col("e_sub"))
    facts = ["gap", "spot", "whole"]
    far = rows.join(_small(gaps, n), source).filter(outside).select("src", "u", "id", "words", before.alias("in"), *facts)
    near = cell.join(_small(gaps, n), source).select("src", "u", "id", "words", "in", *facts)
    items = far.unionByName(near).filter("words > 0").groupBy("src", "u", "id", "words", "in", *facts).agg((F.col("words") * F.count(F.lit(1))).alias("size"))
    items = items.withColumn("copies", F.col("whole") + F.col("in").cast("int")).withColumn("room", MOST - F.col("copies"))
    by = Window.partitionBy("src")
    tie = ["u", "id", "words", F.col("in")]
    fits = items.filter("size <= gap").withColumn("rn", F.row_number().over(by.orderBy(F.desc("size"), *tie))).filter(F.col("rn") <= FITTING)
    small = items.filter("size <= gap").withColumn("rn", F.row_number().over(by.orderBy("size", *tie))).filter(F.col("rn") <= SMALLEST)
    larger = items.filter("size > gap and room > 0").withColumn("rn", F.row_number().over(by.orderBy("size", *tie))).filter(F.col("rn") <= LARGER)
    pool = fits.unionByName(small).unionByName(larger).drop("rn").distinct()
    item = F.struct("size", "u", "id", "words", "copies", "room")
    pool = pool.groupBy("src", "gap", "spot").agg(F.sort_array(F.collect_list(item), asc=False).alias("own"))

    def deal(amount: Column, most: str) -> Column:
        """Copies of each item, largest first, as many as fit into what is left of ``amount``."""
        begin = F.struct(amount.alias("left"), F.array().cast("array<bigint>").alias("got"))

        def step(a: Column, x: Column) -> Column:
            return _let(F.least(x[most].cast("long"), F.floor(a["left"] / x["size"]).cast("long")), lambda k: F.struct((a["left"] - k * x["size"]).alias("left"), F.concat(a["got"], F.array(k)).alias("got")))

        return F.aggregate("own", begin, step)

    # of the items larger than the gap the smallest comes last in the descending array
    over = F.element_at(F.filter("own", lambda x: x["size"] > F.col("gap")), -1)
    pool = pool.withColumn("added", deal(F.col("gap"), "room")).withColumn("over", F.when(F.size(F.filter("own", lambda x: x["size"] > F.col("gap"))) > 0, over))
    pool = pool.withColumn("dropped", deal(F.coalesce(F.col("over.size") - F.col("gap"), F.lit(0).cast("long")), "copies"))
    exceed = F.col("over").isNotNull() & (F.col("dropped.left") < F.col("added.left"))
    # the added item itself is larger than what it exceeds the gap by only if that is less than its size, so it is never dropped again
    delta = F.when(exceed, F.zip_with("own", F.col("dropped.got"), lambda x, k: F.when(x == F.col("over"), F.lit(1).cast("long")).otherwise(-k))).otherwise(F.col("added.got"))
    out = pool.select("src", "spot", F.explode(F.arrays_zip("own", delta.alias("delta"))).alias("x"))
    return out.select("src", F.col("x.own.u").alias("u"), F.col("x.own.id").alias("id"), F.col("x.own.words").alias("words"), F.col("x.own.copies").alias("copies"), F.col("x.delta").cast("int").alias("delta"), "spot").filter("delta <> 0")


def _in_cell(source: str, u: str, row_id: str):
    return Window.partitionBy(source).orderBy(u, row_id).rowsBetween(Window.unboundedPreceding, 0)


def mix(documents: DataFrame, shards: int = 16, seed: int = 8, small: DataFrame | None = None, words: str | None = None) -> DataFrame:
    """``documents`` plus source_size, target and ``placements`` (array of rep and shard; empty: not taken).

    Needs doc_id, source and text (or a long column ``words`` with the sizes). Null text and empty text: size 0. A null
    source is a source of its own, the last one. Null ids share one block. Repeated rows are rows like others.
    The rows at a source's edge are taken while they fit; a few rows with copies more or fewer close the gap (:func:`fill_gaps`).
    Empty tables give empty results. Columns with the new names are replaced.
    """
    size = F.col(words) if words else word_count(F.col("text"))
    keyed = documents.withColumn("__u", _row_hash(F.col("doc_id"), seed))
    if small is None:
        small = cut(keyed.select(F.col("source").alias("src"), F.col("doc_id").alias("id"), size.alias("words"), F.col("__u").alias("u")))
    plan = plan_mix(small, shards, seed)
    block, sub = F.shiftright("__u", 30), F.shiftright("__u", 20).bitwiseAND(F.lit(BLOCKS - 1))
    n_blocks, n_sources = plan.blocks.count(), plan.sources.count()
    of_source = _small(plan.sources.select(F.col("src").alias("__src1"), "source_size", "target"), n_sources)
    of_block = _small(plan.blocks.select(F.col("src").alias("__src2"), F.col("block").alias("__block"), "placements", F.col("edge").alias("__edge")), n_blocks)
    of_edge = _small(plan.edges.select(F.col("src").alias("__src3"), F.col("block").alias("__block3"), F.col("sub").alias("__sub"), F.col("rest").alias("__rest")), n_sources)
    plain = [c for c in documents.columns if c not in ("source_size", "target", "placements")]
    out = keyed.select(*plain, "__u").join(of_source, F.col("source").eqNullSafe(F.col("__src1")), "left")
    out = out.join(of_block, F.col("source").eqNullSafe(F.col("__src2")) & (block == F.col("__block")), "left")
    out = out.join(of_edge, F.col("source").eqNullSafe(F.col("__src3")) & (block == F.col("__block3")), "left")
    out = out.withColumn("placements", F.coalesce("placements", F.array().cast("array<struct<rep:int,shard:int>>")))
    whole = out.filter(F.col("__edge").isNull() | F.col("__sub").isNull() | (sub != F.col("__sub")))
    whole = whole.withColumn("__in", F.col("__edge").isNotNull() & (F.col("__sub").isNull() | (sub < F.col("__sub"))))
    cell = out.filter(F.col("__edge").isNotNull() & (sub == F.col("__sub"))).withColumn("__w", size)
    cell = cell.withColumn("__in", F.sum("__w").over(_in_cell("source", "__u", "doc_id")) <= F.col("__rest")).drop("__w")
    n_fill = plan.fill.count()
    fill = plan.fill.select(F.col("src").alias("__src4"), F.col("u").alias("__u4"), F.col("id").alias("__id4"), F.col("words").alias("__words4"), F.col("copies").alias("__copies4"), F.col("delta").alias("__delta"), F.col("spot").alias("__spot"))
    out = whole.unionByName(cell).withColumn("placements", F.when(F.col("__in"), F.concat("placements", F.array("__edge"))).otherwise(F.col("placements")))
    same = F.col("source").eqNullSafe(F.col("__src4")) & (F.col("__u") == F.col("__u4")) & F.col("doc_id").eqNullSafe(F.col("__id4")) & (F.size("placements") == F.col("__copies4"))
    same = same & (F.abs(size - F.col("__words4")) < 1)  # no join key: words are counted for rows that meet the others only
    out = out.join(_small(fill, n_fill), same, "left")
    more = F.transform(F.sequence(F.lit(1), F.col("__delta")), lambda k: F.struct((F.size("placements") + k - 1).cast("int").alias("rep"), F.col("__spot.shard").cast("int").alias("shard")))
    placements = F.when(F.col("__delta") > 0, F.concat("placements", more)).when(F.col("__delta") < 0, F.slice("placements", F.lit(1), F.size("placements") + F.col("__delta"))).otherwise(F.col("placements"))
    return out.select(*plain, "source_size", "target", placements.alias("placements"))


def mix_digest(documents: DataFrame, shards: int = 16, seed: int = 8) -> DataFrame:
    """doc_id, size, source_size, target, taken of all rows."""
    rows = cut(documents.select("doc_id", "source", word_count(F.col("text")).alias("size")))
    out = mix(rows, shards, seed, words="size")
    return out.select("doc_id", "size", "source_size", "target", (F.col("size") * F.size("placements")).cast("long").alias("taken"))


def mixed_texts(documents: DataFrame, shards: int = 16, seed: int = 8) -> DataFrame:
    """The mix: the columns of ``documents``, a row for every copy, dealt to shards and shuffled inside them.

    Shards follow each other in the range-partitioned output; a shard may span as many partitions as its bytes need.
    """
    names = documents.columns
    own = {c: f"__own_{c}" for c in names if c in ("source_size", "target", "placements")}  # columns that happen to have our names
    out = mix(documents.withColumnsRenamed(own), shards, seed).select(*(own.get(c, c) for c in names), F.explode("placements").alias("__to"))
    dealt = out.repartitionByRange(F.col("__to.shard"), F.xxhash64(F.lit(seed), "doc_id", F.col("__to.rep")))
    dealt = dealt.sortWithinPartitions(F.col("__to.shard"), F.xxhash64(F.lit(seed), "doc_id", F.col("__to.rep")))
    return dealt.select(*(F.col(own.get(c, c)).alias(c) for c in names))
