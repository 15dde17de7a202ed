"""From knowledge graphs to samples of sub-profiles."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from gleaner.operators.components import components

PROFILE = "item long, subj array<string>, pred string, obj array<string>, weight long"


def toy_profile(spark) -> DataFrame:
    """The worked example's four triples of label sets."""
    rows = [(1, ["C1", "C2"], "P1", ["C3"], 22), (2, ["C1", "C3"], "P2", ["C4"], 12), (3, ["C3"], "P3", ["e1", "e3"], 25), (4, ["C1"], "P3", ["e1", "e2"], 34)]
    return spark.createDataFrame(rows, PROFILE)


def build_profile(triples: DataFrame, types: DataFrame) -> DataFrame:
    """Instance links (s, p, o) grouped by their ends' sets of classes; a node without a class stands for itself."""
    kinds = types.groupBy("node").agg(F.array_sort(F.collect_set("type")).alias("labels"))
    at = lambda df, end: df.join(kinds.select(F.col("node").alias(end), F.col("labels").alias(f"{end}_l")), end, "left").withColumn(f"{end}_l", F.coalesce(f"{end}_l", F.array(end)))
    full = at(at(triples, "s"), "o")
    rows = full.groupBy(F.col("s_l").alias("subj"), F.col("p").alias("pred"), F.col("o_l").alias("obj")).agg(F.count("*").alias("weight"))
    return rows.select(F.xxhash64("subj", "pred", "obj").alias("item"), "subj", "pred", "obj", "weight")


def merge_nodes(profile: DataFrame) -> DataFrame:
    """(label, node): label sets that share a label are one node, named after its smallest label."""
    sets = profile.select(F.col("subj").alias("labels")).unionByName(profile.select(F.col("obj").alias("labels"))).distinct()
    edges = sets.select(F.element_at("labels", 1).alias("a"), F.explode("labels").alias("b"))
    linked = components(edges.where("a <> b"))
    return edges.select(F.col("b").alias("label")).distinct().join(linked, F.col("label") == F.col("node"), "left").select("label", F.coalesce("component", "label").alias("node"))


def placed(profile: DataFrame, nodes: DataFrame | None = None) -> DataFrame:
    """``profile`` with the merged nodes of its ends, src and dst."""
    nodes = merge_nodes(profile) if nodes is None else nodes
    src = nodes.select(F.col("label").alias("_s"), F.col("node").alias("src"))
    dst = nodes.select(F.col("label").alias("_d"), F.col("node").alias("dst"))
    return profile.join(src, F.element_at("subj", 1) == F.col("_s")).join(dst, F.element_at("obj", 1) == F.col("_d")).drop("_s", "_d")


def to_qdb(profile: DataFrame, direction: str = "both") -> DataFrame:
    """(tid, item, qty, pred): a transaction for each node and direction, its items the triples that leave (or enter) it."""
    full = placed(profile)
    out = full.select(F.concat(F.lit("out|"), "src").alias("tid"), "item", F.col("weight").alias("qty"), "pred")
    into = full.select(F.concat(F.lit("in|"), "dst").alias("tid"), "item", F.col("weight").alias("qty"), "pred")
    return {"out": out, "in": into, "both": out.unionByName(into)}[direction]


def simple_profile(triples: DataFrame) -> DataFrame:
    """Class-level triples (subj, pred, obj, weight) as a profile of one-label sets."""
    return triples.select(F.xxhash64("subj", "pred", "obj").alias("item"), F.array("subj").alias("subj"), "pred", F.array("obj").alias("obj"), F.col("weight").cast("long"))


def priced(qdb: DataFrame, prices: DataFrame | None = None) -> DataFrame:
    """(tid, item, qty, pred, w): ``prices``: (pred, price), 1 where there is none. The sampler can change them later."""
    if prices is None:
        return qdb.withColumn("w", F.col("qty"))
    named = prices.select(F.col(prices.columns[0]).alias("pred"), F.col(prices.columns[1]).alias("_price"))
    return qdb.join(named, "pred", "left").withColumn("w", F.col("qty") * F.coalesce("_price", F.lit(1))).drop("_price").select("tid", "item", "qty", "pred", "w")


def sub_profile(drawn: DataFrame, profile: DataFrame, by: str = "draw_id") -> tuple[DataFrame, DataFrame]:
    """(nodes, edges) of each group of patterns: their triples, with ends merged that share a label *within the group*."""
    rows = drawn.select(F.col(by).alias("g"), F.explode("pattern").alias("item")).distinct().join(profile, "item")
    ends = rows.select("g", F.col("subj").alias("labels")).unionByName(rows.select("g", F.col("obj").alias("labels"))).distinct()
    key = lambda label: F.concat_ws("\x01", F.col("g").cast("string"), label)
    pairs = ends.select(key(F.element_at("labels", 1)).alias("a"), F.explode("labels").alias("label"), "g").select("g", "label", "a", key(F.col("label")).alias("b"))
    linked = components(pairs.where("a <> b").select("a", "b"))
    names = pairs.select("g", "label", "b").distinct().join(linked, F.col("b") == F.col("node"), "left").select("g", "label", F.coalesce("component", "b").alias("node"))
    nodes = names.groupBy("g", "node").agg(F.array_sort(F.collect_set("label")).alias("labels"))
    one = names.groupBy("g", "label").agg(F.first("node").alias("node"))
    src = one.select("g", F.col("label").alias("_s"), F.col("node").alias("src"))
    dst = one.select("g", F.col("label").alias("_d"), F.col("node").alias("dst"))
    first = rows.withColumn("_s", F.element_at("subj", 1)).withColumn("_d", F.element_at("obj", 1))
    return nodes, first.join(src, ["g", "_s"]).join(dst, ["g", "_d"]).select("g", "src", "pred", "dst", "weight", "item")


def isolated(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """Nodes that touch no edge: there should be none."""
    touched = edges.select("g", F.col("src").alias("node")).unionByName(edges.select("g", F.col("dst").alias("node"))).distinct()
    return nodes.join(touched, ["g", "node"], "left_anti")


def shape(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """(g, nodes, links, top_share): size of each sub-profile, and the largest share of link ends at one node."""
    ends = edges.select("g", F.col("src").alias("node")).unionByName(edges.select("g", F.col("dst").alias("node")))
    degree = ends.groupBy("g", "node").agg(F.count("*").alias("d"))
    top = degree.groupBy("g").agg((F.max("d") / F.sum("d")).alias("top_share"))
    return nodes.groupBy("g").agg(F.count("*").alias("nodes")).join(edges.groupBy("g").agg(F.count("*").alias("links")), "g").join(top, "g")


def stats(profile: DataFrame) -> DataFrame:
    """(triples, links, nodes): kinds of triples, linked pairs of nodes, nodes."""
    full = placed(profile)
    nodes = full.select(F.col("src").alias("x")).unionByName(full.select(F.col("dst").alias("x"))).agg(F.countDistinct("x").alias("nodes"))
    return full.agg(F.count("*").alias("triples"), F.countDistinct("src", "dst").alias("links")).crossJoin(F.broadcast(nodes))  # one row


def export(nodes: DataFrame, edges: DataFrame, how: str = "json") -> DataFrame:
    """(g, value): one JSON graph, or one DOT text, for each sub-profile (at most some dozens of triples each)."""
    if how == "dot":
        plain = lambda c: F.regexp_replace(F.element_at(F.split(c, "\x01"), -1), r'(["\\])', r"\\$1")
        said = F.format_string('  "%s" -> "%s" [label="%s (%d)"];', plain("src"), plain("dst"), plain("pred"), "weight")
        return edges.withColumn("l", said).groupBy("g").agg(F.concat(F.lit("digraph {\n"), F.array_join(F.array_sort(F.collect_list("l")), "\n"), F.lit("\n}")).alias("value"))
    n = nodes.groupBy("g").agg(F.array_sort(F.collect_list(F.struct("node", "labels"))).alias("nodes"))
    e = edges.groupBy("g").agg(F.array_sort(F.collect_list(F.struct("src", "pred", "dst", "weight"))).alias("edges"))
    return n.join(e, "g").select("g", F.to_json(F.struct("nodes", "edges")).alias("value"))


def top_nodes(edges: DataFrame, k: int = 3) -> DataFrame:
    """The k nodes of most links in each sub-profile."""
    ends = edges.select("g", F.col("src").alias("node")).unionByName(edges.select("g", F.col("dst").alias("node")))
    degree = ends.groupBy("g", "node").agg(F.count("*").alias("d"))
    return degree.withColumn("r", F.row_number().over(Window.partitionBy("g").orderBy(F.desc("d"), "node"))).where(F.col("r") <= k)
