"""Operator 9: an exact Jaccard self-join of shingle sets by token combinations.

Documents with one set become one node, so groups of copies cost one row. The sorted
hashes of a set are its global order. Two sets of Jaccard similarity t share a hash
within their first ``(1-t)n + 1`` hashes. If a hash shared there is rare, that single
hash is the signature. A set with a frequent hash there extends its prefix to
``(1-t)n + (k-1)((1-t)n/t + 1) + 1`` hashes and is indexed by combinations instead: each k
neighbours of the order. That long a prefix has so many more shared hashes than the two sets
have differences that k shared ones follow each other in both, and the pair
meets in that combination; a set has as many combinations as hashes, not their power.
Two neighbours come first. A set with a frequent pair is indexed once more by runs of up to ``DEEPEST``,
as many as its size allows, so that a passage that many different texts share makes small buckets.
Below ``COMBINED_FROM`` percent the set may cap its prefix before that holds; there
the plain prefix is indexed by single hashes alone, frequent ones included.

Links are gathered as a spanning set. First every member of a bucket is compared with
the least member, its hub; the links found are closed to components. Then only members
of different components are compared: in buckets of at most ``crowd`` pair by pair, in
larger ones by their differences from the hub, inside the join's condition, and what that finds is told as links
of components. Candidates are first tested on their prefixes, then on their whole sets,
rebuilt from the texts. Components come from rounds of hooking and shortcutting.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import kernels as K
from .arrow_rows import exploded_by_arrow
from .storage import Scratch, table, written

#: Ids that are sent to all executors to pick or leave out texts; beyond that rows are shuffled.
BROADCAST_IDS = 1_000_000
#: The least percentage at which combinations of neighbours lose no pair.
COMBINED_FROM = 67
#: The most hashes of a combination.
DEEPEST = 5
WORDS = K.byte_table(K.SPACED, lower=True)

MEMBERS = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("n_shingles", T.LongType()), T.StructField("digest", T.BinaryType())])
SKETCHES = T.StructType([*MEMBERS.fields, T.StructField("lead", T.ArrayType(T.LongType(), False))])
DEEP = T.StructType([T.StructField(c, T.LongType()) for c in ("node", "n", "sig")])
SETS = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("hashes", T.ArrayType(T.LongType(), False))])


def shingle_sets(data: np.ndarray, offsets: np.ndarray, width: int) -> Iterator[np.ndarray]:
    """The sorted distinct shingle hashes of every document of a piece."""
    _, _, hashes, bounds = K.words(data, offsets, WORDS)
    runs = K.grams(hashes, width).view(np.int64)
    for a, b in zip(bounds[:-1], bounds[1:]):
        if b - a >= width:
            yield np.unique(runs[a : b - width + 1])
        else:
            yield K.grams(hashes[a:b], int(b - a)).view(np.int64)[: int(b > a)]


def prefix_size(n: int, percent: int, k: int) -> int:
    """Length of the prefix in which sets of n hashes and any similar one have k shared neighbours (one for k = 1)."""
    lost = n * (100 - percent) // 100
    apart = n * (100 - percent) // percent
    return lost + (k - 1) * (apart + 1) + 1


@lru_cache(100_000)
def depth(n: int, percent: int) -> int:
    """The most neighbours, two at least, for which the prefix fits into a set of n hashes."""
    return max([2, *(k for k in range(3, DEEPEST + 1) if prefix_size(n, percent, k) <= n)])


@lru_cache(100_000)
def depths(n: int, percent: int) -> tuple[int, ...]:
    """The depths of all sets that are not larger than n and can be similar: a pair meets at that of the smaller set."""
    return tuple(sorted({depth(m, percent) for m in range(-(-n * percent // 100), n + 1)}))


def combinations(found: np.ndarray, percent: int) -> np.ndarray:
    """Hashes of the runs of neighbours by which a set is indexed when its pairs are frequent."""
    n = len(found)
    runs = [K.grams(found[: min(n, prefix_size(n, percent, k))].view(np.uint64), k) for k in depths(n, percent)]
    return np.unique(np.concatenate(runs)).view(np.int64)


def sketches(docs: DataFrame, width: int, percent: int, with_lead: bool) -> DataFrame:
    """Set size, digest of the set and, on request, extended prefix of every document."""

    def kernel(batch: pa.RecordBatch) -> Iterator[list[pa.Array]]:
        data, offsets, _ = K.text_column(batch.column(1))
        for row, end, raw, cuts in K.pieces(data, offsets):
            sizes, digests, leads = [], [], []
            for found in shingle_sets(raw, cuts, width):
                sizes.append(len(found))
                digests.append(xxhash.xxh3_128_digest(found.tobytes()))
                leads.append(found[: min(len(found), prefix_size(len(found), percent, 2))])
            flat = np.concatenate(leads)
            lead = [K.lists(flat, np.fromiter(map(len, leads), np.int64), pa.int64())] if with_lead else []
            yield [batch.column(0).slice(row, end - row), pa.array(sizes, pa.int64()), pa.array(digests, pa.binary()), *lead]

    return exploded_by_arrow(docs, SKETCHES if with_lead else MEMBERS, kernel)


def deep_combinations(docs: DataFrame, width: int, percent: int) -> DataFrame:
    def kernel(batch: pa.RecordBatch) -> Iterator[list[pa.Array]]:
        ids = np.asarray(batch.column(0))
        data, offsets, _ = K.text_column(batch.column(1))
        for row, end, raw, cuts in K.pieces(data, offsets):
            sets = list(shingle_sets(raw, cuts, width))
            found = [combinations(x, percent) for x in sets]
            lengths = np.fromiter(map(len, found), np.int64)
            sizes = np.fromiter(map(len, sets), np.int64)
            yield [pa.array(np.repeat(ids[row:end], lengths)), pa.array(np.repeat(sizes, lengths)), pa.array(np.concatenate(found))]

    return exploded_by_arrow(docs, DEEP, kernel)


def whole_sets(docs: DataFrame, width: int) -> DataFrame:
    def kernel(batch: pa.RecordBatch) -> Iterator[list[pa.Array]]:
        data, offsets, _ = K.text_column(batch.column(1))
        for row, end, raw, cuts in K.pieces(data, offsets):
            found = list(shingle_sets(raw, cuts, width))
            yield [batch.column(0).slice(row, end - row), K.lists(np.concatenate(found), np.fromiter(map(len, found), np.int64), pa.int64())]

    return exploded_by_arrow(docs, SETS, kernel)


def least_shared(n_a: Column, n_b: Column, percent: int) -> Column:
    """The smallest intersection at which two sets of these sizes are similar enough."""
    return F.ceil((n_a + n_b) * percent / F.lit(100.0 + percent) - 1e-9)


def similar(shared: Column, n_a: Column, n_b: Column, percent: int) -> Column:
    return 100 * shared >= percent * (n_a + n_b - shared)


def sizes_fit(n_a: Column, n_b: Column, percent: int) -> Column:
    return (100 * F.least(n_a, n_b) >= percent * F.greatest(n_a, n_b))


def brief(lead: Column, n: Column) -> tuple[Column, Column]:
    """The distinct upper 16 bits of a prefix, and the value below which they are those of the whole set."""
    cut = F.transform(lead, lambda h: F.shiftright(h, 48).cast("short"))
    return F.array_distinct(cut), F.when(F.size(lead) < n, F.get(cut, F.size(lead) - 1).cast("int")).otherwise(F.lit(1 << 15))


def leads_fit(a: Column, end_a: Column, n_a: Column, b: Column, end_b: Column, n_b: Column, percent: int) -> Column:
    """Whether the prefixes leave the pair possible: differences up to the nearer end of the two.

    Below the end of the shorter reach both prefixes are complete, so what one
    has there that the other lacks stands for one true difference at least, whatever hashes
    share their upper bits; similar sets have few.
    """
    within = lambda x: F.filter(x, lambda h: h < F.least(end_a, end_b))
    differences = F.size(within(a)) + F.size(within(b)) - 2 * F.size(F.array_intersect(within(a), within(b)))
    return differences <= n_a + n_b - 2 * least_shared(n_a, n_b, percent)


def components(links: DataFrame) -> DataFrame:
    """``a, b`` -> ``node, component``: the least node that links reach, for every node of a link.

    Rounds of large-star and small-star steps on a written table of edges, until a round
    changes nothing; the driver sees two numbers a round. The first step ties the lower
    neighbours of a node to the least of them, which leaves about one edge a node.
    """
    scratch = Scratch(links.sparkSession)
    given = links.select(F.greatest("a", "b").alias("hi"), F.least("a", "b").alias("lo")).where("hi <> lo").distinct()
    given = given.withColumn("least", F.min("lo").over(Window.partitionBy("hi")))
    tied = given.select("hi", F.col("least").alias("lo")).union(given.select(F.col("lo").alias("hi"), F.col("least").alias("lo"))).where("hi <> lo").distinct()
    edges = scratch.keep(tied, "edges-0")
    seen, turn = None, 0
    while True:
        both = edges.union(edges.select(F.col("lo").alias("hi"), F.col("hi").alias("lo")))
        least = both.groupBy("hi").agg(F.least(F.min("lo"), F.col("hi")).alias("least")).withColumnRenamed("hi", "node")
        # Large star: every greater neighbour of a node is tied to the least of its neighbourhood.
        large = both.select(F.col("hi").alias("node"), F.col("lo").alias("far")).where("far > node").join(least, "node").select(F.col("far").alias("hi"), F.col("least").alias("lo")).distinct()
        # Small star: what a node is tied to is tied to the least of them.
        lower = large.groupBy("hi").agg(F.min("lo").alias("least"))
        small = large.join(lower, "hi").select(F.explode(F.array(F.struct(F.col("hi").alias("hi"), F.col("least").alias("lo")), F.struct(F.col("lo").alias("hi"), F.col("least").alias("lo")))).alias("e")).select("e.*").where("hi <> lo").distinct()
        edges, turn = scratch.keep(small, f"edges-{turn + 1}"), turn + 1
        scratch.drop(f"edges-{turn - 1}")
        state = tuple(edges.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.xxhash64("hi", "lo").cast("decimal(38,0)")), F.lit(0))).first())
        if state == seen:
            break
        seen = state
    out = edges.groupBy("hi").agg(F.min("lo").alias("component"))
    roots = edges.select(F.col("lo").alias("node")).distinct().join(out.withColumnRenamed("hi", "node"), "node", "left_anti")
    return out.withColumnRenamed("hi", "node").unionByName(roots.withColumn("component", F.col("node")))


def ids_repeat(docs: DataFrame) -> bool:
    """Whether rows share an id that is not null."""
    return not docs.where("doc_id IS NOT NULL").groupBy("doc_id").agg(F.count(F.lit(1)).alias("c")).where("c > 1").isEmpty()


def numbered(docs: DataFrame, number: str) -> DataFrame:
    """The rows, written with distinct numbers that rise with (id, text)."""
    order = [F.col("doc_id"), F.col("text")]
    return written(docs.repartitionByRange(*order).sortWithinPartitions(*order).withColumn(number, F.monotonically_increasing_id()), "numbered")


def jaccard_components(docs: DataFrame, width: int = 5, percent: int = 80, rare: int = 8, crowd: int = 32) -> DataFrame:
    """``doc_id, text`` -> ``doc_id, n_shingles, node, component_id``, one row per input row.

    Two documents link when ``100 * |A and B| >= percent * |A or B|`` over their sets of
    ``width``-word shingles, A-Z lowered. A text of fewer words is one shingle of all of them.
    Null, empty or blank texts have no shingle, link with nothing and are their own
    component. A row with a null id keeps its size, links nothing and has a null component.
    Rows that share an id are told apart by number: each links by its own text. ``node`` is
    the least id with the same set. Empty input gives no rows; other columns are ignored.
    """
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    if ids_repeat(texts):
        rows = numbered(texts.where("doc_id IS NOT NULL"), "number")
        by_number = rows.select(F.col("number").alias("doc_id"), "text").unionByName(texts.where("doc_id IS NULL"))
        groups = jaccard_components(by_number, width, percent, rare, crowd)
        for c in ("doc_id", "node", "component_id"):
            ids = rows.select(F.col("number").alias(c), F.col("doc_id").alias("id"))
            groups = groups.join(ids, c, "left").drop(c).withColumnRenamed("id", c)
        return groups.select("doc_id", "n_shingles", "node", "component_id")
    scratch = Scratch(docs.sparkSession)
    found = scratch.keep(sketches(texts, width, percent, False), "members")
    reps = scratch.keep(found.where("n_shingles > 0 AND doc_id IS NOT NULL").groupBy("digest").agg(F.min("doc_id").alias("node")), "reps")
    named = texts.where("doc_id IS NOT NULL")
    nodes = distinct_sets(named, found, reps, width, percent, scratch)
    joined = _Join(named, nodes, width, percent, crowd, scratch)
    buckets = joined.buckets(rare)
    star, differences, links = joined.hub_links(buckets)
    first = scratch.keep(components(links), "first")
    more = joined.pair_links(buckets, star, first).unionByName(joined.hub_rest(differences, first))
    second = components(scratch.keep(more.distinct(), "more"))
    groups = first.join(second.select(F.col("node").alias("component"), F.col("component").alias("further")), "component", "left")
    groups = groups.select("node", F.coalesce("further", "component").alias("component"))
    alone = second.join(first, "node", "left_anti")  # nodes whose first links came last
    groups = scratch.keep(groups.unionByName(alone), "groups")
    scratch.drop(*(set(scratch.paths) - {"members", "reps", "groups"}))
    members = found.join(reps, "digest", "left")
    members = members.select("doc_id", "n_shingles", F.when((F.col("n_shingles") > 0) & F.col("doc_id").isNotNull(), F.col("node")).otherwise(F.col("doc_id")).alias("node"))
    return members.join(groups, "node", "left").select("doc_id", "n_shingles", "node", F.coalesce("component", "node").alias("component_id"))


def distinct_sets(named: DataFrame, found: DataFrame, reps: DataFrame, width: int, percent: int, scratch: Scratch) -> DataFrame:
    """``node, n, lead``: one row for each different set, with its extended prefix."""
    copies = scratch.keep(found.join(reps, "digest").where("doc_id <> node").select("doc_id"), "copies")
    if copies.count() <= BROADCAST_IDS:  # copies are left out on the way, and prefixes need no shuffle
        nodes = sketches(named.join(F.broadcast(copies), "doc_id", "left_anti"), width, percent, True).where("n_shingles > 0")
        nodes = nodes.select(F.col("doc_id").alias("node"), F.col("n_shingles").alias("n"), "lead")
    else:
        nodes = sketches(named, width, percent, True).where("n_shingles > 0").groupBy("digest")
        nodes = nodes.agg(F.min("doc_id").alias("node"), F.any_value("n_shingles").alias("n"), F.any_value("lead").alias("lead")).drop("digest")
    nodes = scratch.keep(nodes, "nodes")
    scratch.drop("copies")
    return nodes


class _Join:
    """The steps from sets to links; each result is written, and counts by a key are written before they are joined,
    so that a key with very many rows can be split."""

    def __init__(self, named: DataFrame, nodes: DataFrame, width: int, percent: int, crowd: int, scratch: Scratch):
        self.named, self.nodes, self.width, self.percent, self.crowd, self.scratch = named, nodes, width, percent, crowd, scratch

    def counted(self, rows: DataFrame, tag: str) -> DataFrame:
        """``sig, node, n`` of signatures of two sets and more, with their number ``c`` and least member ``hub``."""
        sizes = rows.groupBy("sig").agg(F.count(F.lit(1)).alias("c"), F.min("node").alias("hub")).where("c > 1")
        sizes = self.scratch.keep(sizes, f"{tag}-sizes")
        self.scratch.free()
        out = self.scratch.keep(rows.join(sizes, "sig"), tag)
        self.scratch.drop(f"{tag}-sizes")
        self.scratch.free()
        return out

    def picked(self, rows: DataFrame, key: str, ids: DataFrame) -> DataFrame:
        """The rows whose key is among the ids, which are sent to all executors if they are few."""
        return rows.join(F.broadcast(ids) if ids.count() <= BROADCAST_IDS else ids, key, "left_semi")

    def buckets(self, rare: int) -> DataFrame:
        nodes, percent = self.nodes, self.percent
        short = F.expr(f"least(n, n * {100 - percent} div 100 + 1)").cast("int")
        plain = nodes.select("node", "n", F.explode(F.slice("lead", F.lit(1), short)).alias("sig"))
        shared = self.counted(plain, "singles")
        if percent < COMBINED_FROM:
            return shared
        common = self.scratch.keep(shared.where(F.col("c") > rare).select("node").distinct(), "common")
        ahead = F.slice("lead", F.lit(2), F.greatest(F.size("lead") - 1, F.lit(1)))
        pairs_of = F.zip_with(F.slice("lead", F.lit(1), F.size("lead") - 1), ahead, lambda x, y: F.xxhash64(x, y))
        combined = self.picked(nodes, "node", common).where("size(lead) > 1").select("node", "n", F.explode(pairs_of).alias("sig"))
        met = self.counted(combined, "combined")
        crowded = self.scratch.keep(met.where(F.col("c") > self.crowd).select(F.col("node").alias("doc_id")).distinct(), "crowded")
        deep = self.scratch.keep(deep_combinations(self.picked(self.named, "doc_id", crowded), self.width, percent), "deep-rows")
        deep = self.counted(deep, "deep")
        self.scratch.drop("deep-rows", "common", "crowded")
        return shared.where(F.col("c") <= rare).unionByName(met.where(F.col("c") <= self.crowd)).unionByName(deep)

    def near(self, pairs: DataFrame, tag: str) -> DataFrame:
        """The pairs ``a, b`` that their sizes and then their prefixes leave possible."""
        size_of = lambda x: self.nodes.select(F.col("node").alias(x), F.col("n").alias(f"n_{x}"))
        fit = pairs.join(size_of("a"), "a").join(size_of("b"), "b").where(sizes_fit(F.col("n_a"), F.col("n_b"), self.percent))
        fit = self.scratch.keep(fit, f"{tag}-fit")
        ids = self.scratch.keep(fit.select(F.col("a").alias("node")).union(fit.select("b")).distinct(), f"{tag}-ids")
        lead, end = brief(F.col("lead"), F.col("n"))
        held = self.picked(self.nodes, "node", ids).select("node", lead.alias("lead"), end.alias("end"))
        of = lambda x: held.select(F.col("node").alias(x), F.col("lead").alias(f"lead_{x}"), F.col("end").alias(f"end_{x}"))
        both = fit.join(of("a"), "a").join(of("b"), "b")
        fits = leads_fit(*[F.col(f"{c}_{x}") for x in "ab" for c in ("lead", "end", "n")], self.percent)
        return both.where(fits).select("a", "b")

    def judged(self, asked: DataFrame, tag: str) -> DataFrame:
        """``a, b, hub`` -> the pairs with ``linked`` by their whole sets and, for hubs, ``n`` of b and the ``difference``."""
        asked = self.scratch.keep(asked, f"{tag}-asked")
        self.scratch.free()
        ids = self.scratch.keep(asked.select(F.col("a").alias("doc_id")).union(asked.select("b")).distinct(), f"{tag}-wanted")
        sets = self.scratch.keep(whole_sets(self.picked(self.named, "doc_id", ids), self.width), f"{tag}-sets")
        whole = lambda x: sets.select(F.col("doc_id").alias(x), F.col("hashes").alias(f"set_{x}"))
        both = asked.join(whole("a"), "a").join(whole("b"), "b")
        only = lambda x, y: F.array_except(f"set_{x}", f"set_{y}")
        linked = similar(F.size(F.array_intersect("set_a", "set_b")), F.size("set_a"), F.size("set_b"), self.percent)
        difference = F.when(F.col("hub"), F.concat(only("a", "b"), only("b", "a")))
        out = self.scratch.keep(both.select("a", "b", "hub", linked.alias("linked"), F.size("set_b").cast("long").alias("n"), difference.alias("difference")), tag)
        self.scratch.drop(f"{tag}-asked", f"{tag}-wanted", f"{tag}-sets", f"{tag}-ids", f"{tag}-fit")
        self.scratch.free()
        return out

    def hub_links(self, buckets: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
        """All pairs of a hub and a member, the differences in large buckets, and the links found."""
        large = F.col("c") > self.crowd
        star = self.scratch.keep(buckets.where("hub <> node").groupBy(F.col("hub").alias("a"), F.col("node").alias("b")).agg(F.max(large).alias("hub")), "star")
        asked = self.near(star.where("NOT hub").select("a", "b"), "judged").withColumn("hub", F.lit(False)).unionByName(star.where("hub"))
        judged = self.judged(asked, "judged")
        return star, judged.where("hub"), judged.where("linked").select("a", "b")

    def pair_links(self, buckets: DataFrame, star: DataFrame, first: DataFrame) -> DataFrame:
        """Links of components between members of small buckets that no hub has tied together."""
        rows = buckets.where(F.col("c").between(3, self.crowd)).join(first, "node", "left")
        rows = rows.select("sig", "node", "n", F.coalesce("component", "node").alias("component"))
        a, b = (rows.select("sig", *[F.col(c).alias(f"{c}_{x}") for c in ("node", "n", "component")]) for x in "ab")
        fits = (F.col("node_a") < F.col("node_b")) & (F.col("component_a") != F.col("component_b")) & sizes_fit(F.col("n_a"), F.col("n_b"), self.percent)
        pairs = a.join(b, "sig").where(fits).select(F.col("node_a").alias("a"), F.col("node_b").alias("b")).distinct()
        pairs = self.scratch.keep(pairs.join(star.select("a", "b"), ["a", "b"], "left_anti"), "pairs")
        judged = self.judged(self.near(pairs, "paired").withColumn("hub", F.lit(False)), "paired").where("linked").select("a", "b")
        return contracted(judged, first)

    def hub_rest(self, differences: DataFrame, first: DataFrame) -> DataFrame:
        """Links of components between members of large buckets, by what they do not share with their hub.

        One of the two is outside the hub's component; buckets that lie within one are not looked at."""
        percent = self.percent
        star = differences.select(F.col("a").alias("center"), F.col("b").alias("node"), "n", "difference").join(first, "node", "left")
        own = first.select(F.col("node").alias("center"), F.col("component").alias("hub_component"))
        star = star.join(own, "center", "left").withColumn("component", F.coalesce("component", "node"))
        star = self.scratch.keep(star.withColumn("outside", F.col("component") != F.coalesce("hub_component", "center")), "stars")
        x, y = (star.select("center", *[F.col(c).alias(f"{c}_{s}") for c in ("node", "n", "outside", "difference", "component")]) for s in "xy")
        x = x.where("outside_x")
        y = self.picked(y, "center", self.scratch.keep(x.select("center").distinct(), "centers"))
        apart = F.size("difference_x") + F.size("difference_y")
        # |X or Y| - |X and Y| is what the two differences from the hub do not share.
        differ = apart - 2 * F.size(F.array_intersect("difference_x", "difference_y"))
        total = F.col("n_x") + F.col("n_y")
        room = total - 2 * least_shared(F.col("n_x"), F.col("n_y"), percent)
        once = ~F.col("outside_y") | (F.col("node_x") < F.col("node_y"))
        possible = F.abs(F.size("difference_x") - F.size("difference_y")) <= room
        others = (F.col("component_x") != F.col("component_y")) & once & sizes_fit(F.col("n_x"), F.col("n_y"), percent) & possible & (differ <= room)
        rest = x.join(y, "center").where(others)
        return rest.select(F.col("component_x").alias("a"), F.col("component_y").alias("b"))


def contracted(links: DataFrame, groups: DataFrame) -> DataFrame:
    """Links between nodes as links between their components."""
    of = lambda x: groups.select(F.col("node").alias(x), F.col("component").alias(f"component_{x}"))
    both = links.join(of("a"), "a", "left").join(of("b"), "b", "left")
    return both.select(F.coalesce("component_a", "a").alias("a"), F.coalesce("component_b", "b").alias("b"))


def op9_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return jaccard_components(docs, width=3, percent=90).select("doc_id", "n_shingles", "component_id")
