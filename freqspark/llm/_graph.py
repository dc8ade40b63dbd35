"""Connected components, and a search of similar pairs in buckets that makes no pair within a group."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ._blocks import bounded, cut, stored

#: Facts about nodes that are broadcast to a join at most; more are joined by a shuffle.
BROADCAST_ROWS = 300_000
#: Edges at most whose rounds run in one task, so many before lineage is cut; more are dealt over all tasks.
FEW_EDGES, FEW_ROUNDS = 200_000, 3
#: Partners of a node in another component that are checked before all others.
LIKELY = 4
#: Rounds across components: first a look at one partner in so many, which joins most of what can be joined; the last takes all.
SHARES = (8, 1)
#: Nodes of a bucket at most of which all pairs are looked at; nodes of a larger one that all others are paired with first.
SMALL, PICKED = 8, 4


def _print(edges: DataFrame) -> tuple[int, int]:
    """A fingerprint of a set of edges."""
    row = edges.agg(F.count("*"), F.coalesce(F.bit_xor(F.xxhash64("u", "v")), F.lit(0))).first()
    return row[0], row[1]


def _rounds_of_few(own: DataFrame) -> DataFrame:
    """Rounds of components() over edges in one partition: windows instead of joins, so that they stay there."""
    least = lambda: F.min("v").over(Window.partitionBy("u"))
    ways = lambda *ends: F.explode(F.array(*(F.struct(F.col(x).alias("u"), F.col(y).alias("v")) for x, y in ends))).alias("e")
    own = own.coalesce(1)
    for _ in range(FEW_ROUNDS):
        both = own.select(ways("uv", "vu")).select("e.*")
        large = both.withColumn("m", F.least("u", least())).where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        own = large.withColumn("m", least()).select(ways("vm", "um")).select("e.*").where("u <> v").distinct()
    return cut(own, release=False)


def _round_of_many(own: DataFrame) -> DataFrame:
    """A round of components() over edges that are dealt over all tasks; its shuffle files are let go before the next."""
    both = own.unionByName(own.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("k"), F.least("u", "m").alias("m"))
    large = both.where("v > u").join(least, F.col("u") == F.col("k")).select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
    low = large.groupBy("u").agg(F.min("v").alias("m")).withColumnRenamed("u", "k")
    pairs = large.join(low, F.col("u") == F.col("k")).select("u", "v", "m")
    small = pairs.select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(pairs.select("u", F.col("m").alias("v"))).where("u <> v").distinct()
    return cut(small)


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """node, root for each node that has an edge and is not the smallest of its component: root is the smallest.

    Rounds of two steps over edges alone: each node sends its larger neighbours to its smallest one, then its
    smaller ones likewise, until every edge leads to the smallest node. The rounds grow with the
    logarithm of a component's length; lineage is cut after each. A few edges stay in one task: dealt over
    many, the rounds would be thousands of tasks and shuffle files of next to no rows.
    """
    own = edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where("u <> v").distinct()
    own = cut(own, release=False)
    was = _print(own)
    while was[0]:
        own = _rounds_of_few(own) if was[0] <= FEW_EDGES else _round_of_many(own)
        now = _print(own)
        if now == was:
            break
        was = now
    return own.select(F.col("u").alias("node"), F.col("v").alias("root"))


def similar_groups(members: DataFrame, verify: Callable[[DataFrame], DataFrame], sizes: DataFrame | None = None, percent: int = 0, tags: DataFrame | None = None, near: str = "true", shares: tuple[int, ...] = SHARES) -> DataFrame:
    """Components of the similarity graph over nodes that share buckets: node, root (nodes with a smaller partner only).

    members: bucket, node, info = 8 * place + need. A pair is a candidate when it shares at least the lesser
    need of the two in buckets. With sizes (node, n), nodes are sets, buckets their members in one order
    for all sets, place a member's number in its own (from 0), and similar sets have a Jaccard similarity of
    `percent` hundredths: then a pair must overlap in `least` of its members, so it shares one that stands in
    neither set too late for that, and those before its last shared one that it does not share are misses.
    tags: node, tag, a value that `near`, a condition on x_tag and tag, compares before a pair is made.
    verify: pairs (a, b), each two nodes once, to those that are similar.

    First each node is checked against one partner. Each bucket has a centre, the node that shares most
    buckets of its own with others: of a group of changed copies that is the one nearest to all. A node's
    partner is the centre that it meets most often, so groups of copies are joined by one pair a node. Then
    only pairs across the components found so far can add anything: in each bucket the nodes outside
    its commonest component are paired with the others, in rounds over ever more partners. The last round
    takes all, which is exact, as two nodes of one component need no further link.
    """
    # Members are dealt by bucket once, for both sides; the second side reads the same columns, so that the exchange is used again.
    dealt = members.repartition("bucket")
    shared = dealt.groupBy("bucket").agg(F.min("node").alias("low"), F.max("node").alias("high"), F.max("info").alias("top")).where("low <> high and top >= 0").select(F.col("bucket").alias("own"))
    held = cut(dealt.join(shared.hint("merge"), F.col("bucket") == F.col("own")).select("bucket", "node", "info").distinct())
    # Nothing that stands before a set's first bucket of several nodes is shared.
    of = held.groupBy("node").agg(F.count("*").alias("degree"), F.shiftright(F.min("info"), 3).alias("start"))
    of = of.join(sizes.select(F.col("node").alias("t"), "n"), F.col("node") == F.col("t")).drop("t") if sizes is not None else of.withColumn("n", F.lit(1))
    of = of.join(tags.select(F.col("node").alias("t"), "tag"), F.col("node") == F.col("t")).drop("t") if tags is not None else of.withColumn("tag", F.lit(0))
    few_of = bounded(cut(of).withColumnRenamed("node", "s"), BROADCAST_ROWS)
    ranked = held.join(few_of, F.col("node") == F.col("s")).select("bucket", "node", "n", F.struct("degree", (-F.col("node")).alias("minus"), "n").alias("rank"))
    centres = ranked.groupBy("bucket").agg(F.max("rank").alias("top")).select("bucket", (-F.col("top.minus")).alias("centre"), F.col("top.n").alias("m"))
    met = ranked.join(centres, "bucket").where(f"node <> centre and 100 * least(n, m) >= {percent} * greatest(n, m)").groupBy("node", "centre").agg(F.count("*").alias("c"))
    most = met.groupBy("node").agg(F.max_by("centre", F.struct("c", -F.col("centre"))).alias("centre"))
    # The centre stands first, as the one of many pairs; two nodes that are each other's centre make one.
    once = most.groupBy(F.least("node", "centre").alias("low"), F.greatest("node", "centre").alias("high")).agg(F.min("centre").alias("a"))
    first = cut(verify(once.select("a", F.col("low").bitwiseXOR(F.col("high")).bitwiseXOR(F.col("a")).alias("b"))))
    known = components(first)
    for share in shares:
        links = _across(held, few_of, known, verify, sizes is not None, percent, near, share)
        known = components(known.select(F.col("root").alias("a"), F.col("node").alias("b")).unionByName(links))
    return known


def _across(held: DataFrame, of: DataFrame, known: DataFrame, verify: Callable[[DataFrame], DataFrame], sized: bool, percent: int, near: str, share: int) -> DataFrame:
    """Links across the known components: with share 1 all that can join any two; else likely ones, found among one partner in `share`."""
    # Small sides are broadcast, so that the rows stay where their buckets are.
    named = held.join(bounded(known.withColumnRenamed("node", "k"), BROADCAST_ROWS), F.col("node") == F.col("k"), "left").select("bucket", "node", "info", F.coalesce("root", "node").alias("root"))
    counted = named.groupBy("bucket", "root").agg(F.count("*").alias("c"))
    mixed = counted.groupBy("bucket").agg(F.max_by("root", F.struct("c", "root")).alias("main"), F.count("*").alias("k")).where("k > 1").select(F.col("bucket").alias("own"), "main")
    open_ = named.join(mixed, F.col("bucket") == F.col("own"))
    open_ = cut(open_.join(of, F.col("node") == F.col("s")).select("bucket", "node", F.shiftright("info", 3).alias("place"), (F.col("info") % 8).alias("need"), "root", "main", "n", "start", "tag"))
    few = open_.where("root <> main").select("bucket", *(F.col(c).alias(f"x_{c}") for c in ("node", "place", "need", "root", "n", "start", "tag")))
    apart = f"root <> x_root and (root = main or node > x_node) and ({near})"
    least = f"(({percent} * (x_n + n) + {99 + percent}) div {100 + percent})"
    # The last round asks for one shared member, standing as early as it must; the misses before the last one decide nothing there.
    enough, more = ("c >= l", "least(x_need, need) - 1") if share > 1 or not sized else ("c >= 1", "0")
    if sized:
        apart += f" and x_start <= x_n - {least} and start <= n - {least}"
        apart += f" and 100 * least(x_n, n) >= {percent} * greatest(x_n, n) and x_place <= x_n - {least} + {more} and place <= n - {least} + {more}"
        enough += f" and x_n - (x_last + 1 - c) >= {least} and n - (last + 1 - c) >= {least}"
    partners = open_.where(F.pmod(F.xxhash64("node"), F.lit(share)) == 0)
    met = few.join(partners, "bucket").where(apart).groupBy("x_node", "node")
    counts = met.agg(F.count("*").alias("c"), F.min(F.least("x_need", "need")).alias("l"), F.max("root").alias("other"), F.max("x_n").alias("x_n"), F.max("n").alias("n"), F.max("x_place").alias("x_last"), F.max("place").alias("last")).where(enough)
    pairs = cut(counts.select(F.least("x_node", "node").alias("a"), F.greatest("x_node", "node").alias("b"), F.col("x_node").alias("x"), "c", "other").dropDuplicates(["a", "b"]))
    # The likeliest partners of each node in each other component first: what they join needs no more checks.
    place = F.row_number().over(Window.partitionBy("x", "other").orderBy(F.desc("c"), "a", "b"))
    likely = pairs.withColumn("place", place).where(F.col("place") <= LIKELY).select("a", "b")
    links = cut(verify(likely))
    if share > 1:
        return links
    now = components(known.select(F.col("root").alias("a"), F.col("node").alias("b")).unionByName(links))
    root = lambda side: now.select(F.col("node").alias(side), F.col("root").alias(f"{side}_root"))
    rest = pairs.select("a", "b").join(root("a"), "a", "left").join(root("b"), "b", "left").where("coalesce(a_root, a) <> coalesce(b_root, b)").select("a", "b")
    others = rest.join(likely.select(F.col("a").alias("la"), F.col("b").alias("lb")), (F.col("a") == F.col("la")) & (F.col("b") == F.col("lb")), "left_anti")
    return links.unionByName(cut(verify(others)))


def near_groups(members: DataFrame, facts: DataFrame, near: str, verify: Callable[[DataFrame], DataFrame], firsts: DataFrame) -> DataFrame:
    """Components of the similarity graph over nodes that share a bucket: node, root (nodes with a smaller partner only).

    members: bucket, node (once a bucket). facts: node and what is known of it; `near` is a condition on the
    facts of two nodes (those of one with x_ before them) that all similar ones meet. verify: pairs
    (a < b) to those that are similar. firsts: node, firsts: a few of the smallest buckets of each node.

    In small buckets all near pairs are verified. In a large one each node is first paired with a few,
    which joins groups of copies by few pairs a node. Only pairs across the components found so far can
    add anything then: where a bucket still holds several, the nodes outside the commonest are paired with
    near ones of others, in rounds over ever more partners. The first joins what has many similar partners by
    few pairs; the last takes all, which is exact, as two nodes of one component need no further link. Two nodes
    that share a bucket of their first ones are left to it in all larger buckets.
    """
    # Members are dealt by bucket once: they are counted where they lie, as most have a bucket to themselves.
    shared = members.withColumn("c", F.count("*").over(Window.partitionBy("bucket"))).where("c > 1")
    known_of = facts.withColumnRenamed("node", "k")
    held, drop = stored(shared.join(known_of, F.col("node") == F.col("k")).drop("k"))
    columns = [c for c in facts.columns if c != "node"]

    def pairs(x: DataFrame, y: DataFrame, *more: str, apart: str, last: str = "") -> DataFrame:
        """a, b of the near pairs of rows of both that share a bucket; x and y of one kind are shuffled once."""
        both = x.alias("l").join(y.alias("r"), F.col("l.bucket") == F.col("r.bucket"))
        named = both.select(*(F.col(f"l.{c}").alias(f"x_{c}") for c in ("node", *more, *columns)), *(f"r.{c}" for c in ("node", *more, *columns)))
        return named.where(f"{apart} and {near}{last}").select(F.least("x_node", "node").alias("a"), F.greatest("x_node", "node").alias("b"))

    small, large = held.where(F.col("c") <= SMALL).drop("c"), held.where(F.col("c") > SMALL).drop("c")
    every = pairs(small, small, apart="x_node < node")
    # The least nodes of a bucket in a few orders, which an exclusive or with a constant makes and undoes.
    salts = [F.lit((0x9E3779B97F4A7C15 * i) % (1 << 63)) for i in range(PICKED)]
    least = F.array_distinct(F.array(*(F.min(F.col("node").bitwiseXOR(salt)).bitwiseXOR(salt) for salt in salts)))
    picked = large.groupBy("bucket").agg(least.alias("nodes")).select("bucket", F.explode("nodes").alias("node"))
    first = pairs(large.join(picked, ["bucket", "node"], "left_semi"), large, apart="x_node <> node")
    known = components(verify(every.unionByName(first).distinct()))

    def opened(rows: DataFrame) -> DataFrame:
        """The rows of buckets that hold several components, with each row's and the bucket's commonest."""
        rooted = rows.join(bounded(known.withColumnRenamed("node", "k"), BROADCAST_ROWS), F.col("node") == F.col("k"), "left").select(*rows.columns, F.coalesce("root", "node").alias("root"))
        counted = rooted.groupBy("bucket", "root").agg(F.count("*").alias("c")).groupBy("bucket").agg(F.max_by("root", F.struct("c", "root")).alias("main"), F.count("*").alias("k"))
        return rooted.join(counted.where("k > 1").select(F.col("bucket").alias("own"), "main"), F.col("bucket") == F.col("own")).drop("own")

    # A pair that shares a smaller bucket was verified there if it is small, is made there if it is large, and has one root if all there have.
    before = F.filter("firsts", lambda b: b < F.col("bucket")).alias("before")
    open_ = opened(large).join(firsts.withColumnRenamed("node", "k"), F.col("node") == F.col("k")).select("bucket", "node", *columns, "root", "main", before)
    for share in SHARES:
        open_ = cut(open_ if share == SHARES[0] else opened(open_.drop("root", "main")))
        partners = open_.where(F.pmod(F.xxhash64("node"), F.lit(share)) == 0)
        links = verify(pairs(open_.where("root <> main"), partners, "root", "main", "before", apart="x_root <> root and (root = main or x_node < node)", last=" and not arrays_overlap(x_before, before)").distinct())
        known = components(known.select(F.col("root").alias("a"), F.col("node").alias("b")).unionByName(links))
    drop()
    return known
