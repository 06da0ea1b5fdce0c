"""Graph views on the given tables.

A graph is a table of nodes (``id``) and one of arcs (``src``, ``dst``), both directions, distinct, no loops.  Nodes come
from the tables that list them, never from the arcs: isolated nodes send noise too.  Ids are key * 8 + kind.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .nearest import nearest_pairs
from .scratch import pin

# The kinds of nodes in ids.
PART, SUPPLIER, CUSTOMER, NATION, REGION, USER, DOCUMENT = 1, 2, 3, 4, 5, 6, 7
TURNS = 1 << 20  # more than any conversation has


@dataclass
class Graph:
    nodes: DataFrame
    arcs: DataFrame
    name: str = ""
    _kept: dict[str, DataFrame] = field(default_factory=dict, repr=False)

    @staticmethod
    def from_pairs(nodes: DataFrame, pairs: DataFrame, name: str = "") -> Graph:
        """From any pairs ``a``, ``b``: loops and nulls dropped, both directions, distinct."""
        p = pairs.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
        arcs = p.select(F.explode(F.array(F.struct(F.col("a").alias("src"), F.col("b").alias("dst")), F.struct(F.col("b").alias("src"), F.col("a").alias("dst")))).alias("x")).select("x.src", "x.dst")
        return Graph(nodes.select("id"), arcs, name)

    def pinned(self) -> Graph:
        """The same graph from written tables; several rounds read it.

        They are dealt to all cores: rows are few bytes but are drawn for in every run, so splits by size would be too few.
        """
        if self._kept:
            return self
        parts = 2 * self.nodes.sparkSession.sparkContext.defaultParallelism
        kept = {"nodes": pin(self.nodes.repartition(parts), "nodes"), "arcs": pin(self.arcs.repartition(parts), "arcs")}
        return Graph(kept["nodes"], kept["arcs"], self.name, kept)

    def degrees(self) -> DataFrame:
        """``id``, ``degree`` of every node, isolated ones included."""
        d = self.arcs.groupBy(F.col("dst").alias("id")).agg(F.count("*").alias("degree"))
        return self.nodes.join(d, "id", "left").select("id", F.coalesce("degree", F.lit(0)).cast("long").alias("degree"))

    def stats(self) -> DataFrame:
        d = self.degrees()
        return d.agg(
            F.count("*").alias("n_nodes"), (F.sum("degree") / 2).cast("long").alias("n_edges"), F.max("degree").alias("max_degree"),
            F.round(F.sum("degree") / F.count("*"), 6).alias("avg_degree"), F.count(F.when(F.col("degree") == 0, 1)).alias("isolated"),
        )

    def induced(self, ids: DataFrame) -> Graph:
        """The graph on the nodes in ``ids``."""
        arcs = self.arcs.join(ids.select(F.col("id").alias("src")), "src", "left_semi").join(ids.select(F.col("id").alias("dst")), "dst", "left_semi")
        return Graph(self.nodes.join(ids, "id", "left_semi"), arcs.select("src", "dst"), self.name)

    def without_edges(self, pairs: DataFrame) -> Graph:
        """Without the edges ``a``, ``b``: a neighbouring graph, for one pair."""
        p = pairs.select(F.col("a").alias("src"), F.col("b").alias("dst")).union(pairs.select(F.col("b").alias("src"), F.col("a").alias("dst")))
        return Graph(self.nodes, self.arcs.join(p, ["src", "dst"], "left_anti"), self.name)

    def validate(self) -> Graph:
        """Raise unless the arcs are distinct, symmetric, without loops, and between nodes."""
        bad = self.arcs.where("src = dst or src is null or dst is null").limit(1).count()
        if bad:
            raise ValueError("the arcs have a loop or a null")
        if self.arcs.groupBy("src", "dst").count().where("count > 1").limit(1).count():
            raise ValueError("an arc is there twice")
        if self.arcs.join(self.arcs.select(F.col("dst").alias("src"), F.col("src").alias("dst")), ["src", "dst"], "left_anti").limit(1).count():
            raise ValueError("an arc lacks its reverse")
        if self.arcs.join(self.nodes, self.arcs["src"] == self.nodes["id"], "left_anti").limit(1).count():
            raise ValueError("an arc leaves the nodes")
        return self


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def encode(key: str | Column, kind: int) -> Column:
    return (F.col(key) if isinstance(key, str) else key).cast("long") * 8 + kind


def text_id(kind: str, text: Column) -> Column:
    """A node id for a text: 52 bits of md5."""
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{kind}:"), text)), 1, 13), 16, 10).cast("long")


def _nodes(df: DataFrame, key: str, kind: int) -> DataFrame:
    return df.select(encode(key, kind).alias("id"))


def copurchase(spark: SparkSession, d: str) -> Graph:
    """Parts bought together: two lines of one order, each of at least 40."""
    li = table(spark, d, "lineitem").where("l_quantity >= 40").select("l_orderkey", "l_partkey").distinct()
    pairs = li.alias("x").join(li.alias("y"), "l_orderkey").where("x.l_partkey < y.l_partkey").select(encode(F.col("x.l_partkey"), PART).alias("a"), encode(F.col("y.l_partkey"), PART).alias("b"))
    return Graph.from_pairs(_nodes(table(spark, d, "part"), "p_partkey", PART), pairs, "copurchase")


def _trade(spark: SparkSession, d: str, least: int, name: str) -> Graph:
    li = table(spark, d, "lineitem").where(F.col("l_quantity") >= least).select("l_orderkey", "l_partkey")
    pairs = li.join(table(spark, d, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey")).select(encode("o_custkey", CUSTOMER).alias("a"), encode("l_partkey", PART).alias("b"))
    nodes = _nodes(table(spark, d, "customer"), "c_custkey", CUSTOMER).union(_nodes(table(spark, d, "part"), "p_partkey", PART))
    return Graph.from_pairs(nodes, pairs, name)


def trade(spark: SparkSession, d: str) -> Graph:
    """Customers and the parts they bought."""
    return _trade(spark, d, 0, "trade")


def trade_sparse(spark: SparkSession, d: str) -> Graph:
    """Customers and the parts they bought at least 48 of."""
    return _trade(spark, d, 48, "trade_sparse")


def _supply(spark: SparkSession, d: str, least: int, name: str) -> Graph:
    pairs = table(spark, d, "lineitem").where(F.col("l_quantity") >= least).select(encode("l_partkey", PART).alias("a"), encode("l_suppkey", SUPPLIER).alias("b"))
    nodes = _nodes(table(spark, d, "part"), "p_partkey", PART).union(_nodes(table(spark, d, "supplier"), "s_suppkey", SUPPLIER))
    return Graph.from_pairs(nodes, pairs, name)


def supply(spark: SparkSession, d: str) -> Graph:
    """Parts and their suppliers: few suppliers, large degrees."""
    return _supply(spark, d, 0, "supply")


def supply_sparse(spark: SparkSession, d: str) -> Graph:
    """Parts and suppliers on lines of at least 48."""
    return _supply(spark, d, 48, "supply_sparse")


def handoff(spark: SparkSession, d: str) -> Graph:
    """Users whose purchases follow one another in time.

    The successor in time is found by hour: within an hour by a window, across hours from each one's first and last
    purchase, so that no task orders all events.
    """
    e = table(spark, d, "events")
    buys = e.where("event_type = 'purchase'").select("ts", "event_id", "user_id", F.date_trunc("hour", "ts").alias("hour"))
    order = Window.partitionBy("hour").orderBy("ts", "event_id")
    within = buys.withColumn("next", F.lead("user_id").over(order)).where("next is not null").select("user_id", "next")
    ends = buys.groupBy("hour").agg(F.min_by("user_id", F.struct("ts", "event_id")).alias("first"), F.max_by("user_id", F.struct("ts", "event_id")).alias("last"))
    hours = ends.withColumn("next", F.lead("first").over(Window.orderBy("hour"))).where("next is not null").select(F.col("last").alias("user_id"), "next")  # a row per hour
    pairs = within.union(hours).select(encode("user_id", USER).alias("a"), encode("next", USER).alias("b"))
    return Graph.from_pairs(e.select(encode("user_id", USER).alias("id")).distinct(), pairs, "handoff")


def geo_forest(spark: SparkSession, d: str) -> Graph:
    """The foreign keys among regions, nations, customers and suppliers: a forest."""
    nation, customer, supplier = (table(spark, d, t) for t in ("nation", "customer", "supplier"))
    pairs = nation.select(encode("n_nationkey", NATION).alias("a"), encode("n_regionkey", REGION).alias("b"))
    pairs = pairs.union(customer.select(encode("c_custkey", CUSTOMER), encode("c_nationkey", NATION))).union(supplier.select(encode("s_suppkey", SUPPLIER), encode("s_nationkey", NATION)))
    nodes = _nodes(table(spark, d, "region"), "r_regionkey", REGION).union(_nodes(nation, "n_nationkey", NATION)).union(_nodes(customer, "c_custkey", CUSTOMER)).union(_nodes(supplier, "s_suppkey", SUPPLIER))
    return Graph.from_pairs(nodes, pairs, "geo_forest")


def nation_region(spark: SparkSession, d: str) -> Graph:
    """Nations and regions: 30 nodes."""
    nation = table(spark, d, "nation")
    nodes = _nodes(table(spark, d, "region"), "r_regionkey", REGION).union(_nodes(nation, "n_nationkey", NATION))
    return Graph.from_pairs(nodes, nation.select(encode("n_nationkey", NATION).alias("a"), encode("n_regionkey", REGION).alias("b")), "nation_region")


def near_vectors(spark: SparkSession, d: str, nearest: int = 3) -> Graph:
    """Each vector and its nearest by cosine, ties by id.

    All pairs are scored, block by block; its scoring is quadratic.  The pairs are written, since a graph reads them more
    than once.
    """
    e = table(spark, d, "embeddings").select("vec_id", "embedding")
    pairs = pin(nearest_pairs(e, nearest), "near")
    return Graph.from_pairs(e.select(F.col("vec_id").alias("id")), pairs, "near_vectors")


def page_links(spark: SparkSession, d: str) -> Graph:
    """Pages and the targets of their links."""
    pages = table(spark, d, "pages").select("page_id", F.explode(F.array_distinct(F.regexp_extract_all("html", F.lit('href="([^"]+)"'), 1))).alias("target"))
    pairs = pages.select((F.col("page_id") * 8).alias("a"), text_id("href", F.col("target")).alias("b")).select("a", (F.col("b") * 8 + 1).alias("b"))
    nodes = table(spark, d, "pages").select((F.col("page_id") * 8).alias("id")).union(pairs.select("b").distinct())
    return Graph.from_pairs(nodes, pairs, "page_links")


def doc_facets(spark: SparkSession, d: str) -> Graph:
    """Sources and languages of documents."""
    docs = table(spark, d, "documents").select("source", "lang").distinct()
    pairs = docs.select(text_id("source", F.col("source")).alias("a"), text_id("lang", F.col("lang")).alias("b"))
    return Graph.from_pairs(pairs.select(F.col("a").alias("id")).union(pairs.select("b")).distinct(), pairs, "doc_facets")


def turns(spark: SparkSession, d: str) -> Graph:
    """Each turn of a conversation and the next: disjoint paths."""
    c = table(spark, d, "conversations").select((F.col("conv_id") * TURNS + F.col("turn")).alias("id"), "conv_id", "turn")
    after = Window.partitionBy("conv_id").orderBy("turn")
    pairs = c.select(F.col("id").alias("a"), F.when(F.lead("turn").over(after) == F.col("turn") + 1, F.lead("id").over(after)).alias("b")).where("b is not null")
    return Graph.from_pairs(c.select("id"), pairs, "turns")


VIEWS: dict[str, Callable[[SparkSession, str], Graph]] = {f.__name__: f for f in (copurchase, trade, trade_sparse, supply, supply_sparse, handoff, geo_forest, nation_region, near_vectors, page_links, doc_facets, turns)}


def view(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    return VIEWS[name](spark, sf_dir)
