"""Graphs over the given tables; ids are namespaced by arithmetic."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from subgraph_engine.functions.ranking import global_rank
from subgraph_engine.model import EDGE, GraphSpec
from subgraph_engine.prepare import prepare
from subgraph_engine.storage import written_table
from subgraph_engine.tables import load

#: Similarity is compared after rounding to this many places, ties by id.
KNN = 5
KNN_PLACES = 6
KNN_BLOCK = 1024
SESSION_GAP_HOURS = 6
LONG_LINE = 60


def _ends(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("src").alias("vid")).unionByName(edges.select(F.col("dst").alias("vid"))).distinct()


def _graph(name: str, edges: DataFrame, directed: bool = False, weighted: bool = False, vertices: DataFrame | None = None, **how) -> GraphSpec:
    return prepare(name, edges, directed=directed, weighted=weighted, vertices=vertices, **how)


def even(c: str) -> Column:
    return F.col(c).cast("long") * 2


def odd(c: str) -> Column:
    return F.col(c).cast("long") * 2 + 1


def basket(spark: SparkSession, sf_dir: str) -> GraphSpec:
    """Orders and the parts on them."""
    lines = load(spark, sf_dir, "lineitem")
    return _graph("basket", lines.select(even("l_orderkey").alias("src"), odd("l_partkey").alias("dst")))


def supply(spark: SparkSession, sf_dir: str) -> GraphSpec:
    """Parts and their suppliers: few vertices, many edges."""
    lines = load(spark, sf_dir, "lineitem")
    return _graph("supply", lines.select(even("l_partkey").alias("src"), odd("l_suppkey").alias("dst")))


def _sales(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = load(spark, sf_dir, "lineitem").select(
        "l_orderkey", "l_suppkey", (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("weight")
    )
    orders = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    return lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey"))


def patron(spark: SparkSession, sf_dir: str) -> GraphSpec:
    """Customers to the suppliers they bought from, by revenue."""
    sales = _sales(spark, sf_dir).select(even("o_custkey").alias("src"), odd("l_suppkey").alias("dst"), "weight")
    return _graph("patron", sales, directed=True, weighted=True)


def nation_trade(spark: SparkSession, sf_dir: str) -> GraphSpec:
    """Customer nations to supplier nations, by revenue."""
    customers = load(spark, sf_dir, "customer").select("c_custkey", F.col("c_nationkey").cast("long").alias("src"))
    suppliers = load(spark, sf_dir, "supplier").select("s_suppkey", F.col("s_nationkey").cast("long").alias("dst"))
    sales = _sales(spark, sf_dir).join(customers, F.col("o_custkey") == F.col("c_custkey"))
    sales = sales.join(suppliers, F.col("l_suppkey") == F.col("s_suppkey"))
    return _graph("nation_trade", sales.select("src", "dst", "weight"), directed=True, weighted=True)


def _copurchase(name: str, lines: DataFrame) -> GraphSpec:
    on = lines.select("l_orderkey", F.col("l_partkey").cast("long").alias("part")).distinct()
    pairs = on.withColumnRenamed("part", "src").join(on.withColumnRenamed("part", "dst"), "l_orderkey").filter("src < dst")
    return _graph(name, pairs.select("src", "dst"))


def copurchase(spark: SparkSession, sf_dir: str) -> GraphSpec:
    """Parts that were on one order (an order has few lines, which bounds its pairs)."""
    return _copurchase("copurchase", load(spark, sf_dir, "lineitem"))


def copurchase_sparse(spark: SparkSession, sf_dir: str) -> GraphSpec:
    """The same for large quantities only: sparse, with long paths."""
    return _copurchase("copurchase_sparse", load(spark, sf_dir, "lineitem").filter("l_quantity > 45"))


def accounts(spark: SparkSession, sf_dir: str) -> GraphSpec:
    """Customers and their orders; customers without orders are vertices too."""
    orders = load(spark, sf_dir, "orders").select(even("o_custkey").alias("src"), odd("o_orderkey").alias("dst"))
    customers = load(spark, sf_dir, "customer").select(even("c_custkey").alias("vid"))
    return _graph("accounts", orders, vertices=customers.unionByName(orders.select(F.col("dst").alias("vid"))))


def _in_order(spark: SparkSession, sf_dir: str, by: str) -> tuple[DataFrame, Window]:
    events = load(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type")
    return events, Window.partitionBy(by).orderBy("ts", "event_id")


def event_chain(spark: SparkSession, sf_dir: str) -> GraphSpec:
    """Each event to the next event of its user: the longest paths."""
    events, order = _in_order(spark, sf_dir, "user_id")
    steps = events.select(F.col("event_id").alias("src"), F.lead("event_id").over(order).alias("dst"))
    return _graph("event_chain", steps.filter("dst is not null"), directed=True, vertices=events.select(F.col("event_id").alias("vid")))


def event_session(spark: SparkSession, sf_dir: str) -> GraphSpec:
    """The same where less than six hours lie between; every event is a vertex."""
    events, order = _in_order(spark, sf_dir, "user_id")
    steps = events.select(
        F.col("event_id").alias("src"),
        F.lead("event_id").over(order).alias("dst"),
        (F.lead("ts").over(order) < F.col("ts") + F.expr(f"interval {SESSION_GAP_HOURS} hours")).alias("near"),
    )
    return _graph("event_session", steps.filter("near").select("src", "dst"), directed=True, vertices=events.select(F.col("event_id").alias("vid")))


def event_flow(spark: SparkSession, sf_dir: str) -> GraphSpec:
    """Event types to the type that follows for a user, by count; ids in order of name."""
    events, order = _in_order(spark, sf_dir, "user_id")
    kinds = events.select("event_type").distinct()
    named = kinds.select("event_type", (F.row_number().over(Window.orderBy("event_type")) - 1).cast("long").alias("id"))  # a handful
    steps = events.select("event_type", F.lead("event_type").over(order).alias("next")).filter("next is not null")
    steps = steps.groupBy("event_type", "next").agg(F.count(F.lit(1)).cast("double").alias("weight"))
    left = named.select("event_type", F.col("id").alias("src"))
    right = named.select(F.col("event_type").alias("next"), F.col("id").alias("dst"))
    return _graph("event_flow", steps.join(left, "event_type").join(right, "next").select("src", "dst", "weight"), directed=True, weighted=True)


def user_relay(spark: SparkSession, sf_dir: str) -> GraphSpec:
    """A user to the next other user with the same type of event.

    Event types are few, so their sequences are long: they are cut at months, and
    the first event of a month follows nothing.
    """
    events = load(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type", F.date_trunc("month", "ts").alias("month"))
    order = Window.partitionBy("event_type", "month").orderBy("ts", "event_id")
    steps = events.select(F.col("user_id").alias("src"), F.lead("user_id").over(order).alias("dst"))
    return _graph("user_relay", steps.filter("dst is not null and src <> dst"), directed=True)


def page_links(spark: SparkSession, sf_dir: str) -> GraphSpec:
    """Pages and the targets of their links: a few targets are hubs."""
    pages = load(spark, sf_dir, "pages")
    links = pages.select(even("page_id").alias("src"), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("href"))
    links = links.distinct()
    targets = global_rank(spark, links.select("href").distinct(), [F.col("href")], "rank", "href-rank")
    edges = links.join(targets, "href").select("src", odd("rank").alias("dst"))
    return _graph("page_links", edges)


def knn(spark: SparkSession, sf_dir: str) -> GraphSpec:
    """Vectors to their five nearest by cosine; all pairs, in tiles of two blocks, a matrix product each.

    A tile keeps every vector's five best of its block, so what leaves it is narrow.
    """
    rows = load(spark, sf_dir, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("v"))
    blocks = max(1, rows.count() // KNN_BLOCK)
    # an int on both sides: equal numbers of different types are dealt to different tasks
    rows = rows.withColumn("block", F.pmod(F.col("vec_id"), F.lit(blocks)).cast("int"))
    all_blocks = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    left = rows.select("vec_id", "v", F.col("block").alias("i"), all_blocks.alias("j"))
    right = rows.select("vec_id", "v", all_blocks.alias("i"), F.col("block").alias("j"))

    def nearest(a: pa.Table, b: pa.Table) -> pa.Table:
        out: tuple[list, list, list] = ([], [], [])
        if a.num_rows and b.num_rows:
            src, dst = a.column("vec_id").to_numpy(), b.column("vec_id").to_numpy()
            x, y = (np.array(t.column("v").to_pylist(), float) for t in (a, b))
            near = np.round((x @ y.T) / np.sqrt((x * x).sum(axis=1))[:, None] / np.sqrt((y * y).sum(axis=1))[None, :], KNN_PLACES)
            near[src[:, None] == dst[None, :]] = -np.inf
            for k, row in enumerate(near):
                best = np.lexsort((dst, -row))[:KNN]
                best = best[row[best] > -np.inf]
                out[0].extend([src[k]] * len(best))
                out[1].extend(dst[best])
                out[2].extend(row[best])
        return pa.table({"src": pa.array(out[0], pa.int64()), "dst": pa.array(out[1], pa.int64()), "weight": pa.array(out[2], pa.float64())})

    near = left.groupBy("i", "j").cogroup(right.groupBy("i", "j")).applyInArrow(nearest, "src long, dst long, weight double")
    best = Window.partitionBy("src").orderBy(F.col("weight").desc(), "dst")  # five rows of each block
    near = near.select("src", "dst", "weight", F.row_number().over(best).alias("rank")).filter(F.col("rank") <= KNN)
    # written once: jobs read edges several times, and all pairs are dear
    near = written_table(spark, near.select("src", "dst", "weight"), "knn-edges")
    return _graph("knn", near, directed=True, weighted=True)


def doc_dup(spark: SparkSession, sf_dir: str) -> GraphSpec:
    """Documents with an equal text, or with a long line in common.

    Every such group is a star around its smallest document, so copies do not
    make pairs.
    """
    docs = load(spark, sf_dir, "documents").select("doc_id", "text").filter("text is not null")
    whole = docs.select("doc_id", F.sha2("text", 256).alias("key"))
    lines = docs.select("doc_id", F.explode(F.split("text", "\n")).alias("line")).filter(F.length("line") > LONG_LINE)
    lines = lines.select("doc_id", F.sha2("line", 256).alias("key")).distinct()

    def stars(rows: DataFrame) -> DataFrame:
        groups = rows.groupBy("key").agg(F.min("doc_id").alias("dst"), F.count(F.lit(1)).alias("n")).filter("n > 1")
        return rows.join(groups, "key").filter("doc_id <> dst").select(F.col("doc_id").alias("src"), "dst")

    return _graph("doc_dup", stars(whole).unionByName(stars(lines)))


def dialog(spark: SparkSession, sf_dir: str) -> GraphSpec:
    """Turns of a conversation in a row."""
    turns = load(spark, sf_dir, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("vid"))
    steps = turns.select(F.col("vid").alias("src"), (F.col("vid") + 1).alias("dst"))
    steps = steps.join(turns.select(F.col("vid").alias("dst")), "dst", "left_semi").select("src", "dst")
    return _graph("dialog", steps, directed=True, vertices=turns)


def geo(spark: SparkSession, sf_dir: str) -> GraphSpec:
    """Regions, nations, and the customers and suppliers in them: a tree for each region."""
    place = lambda c, k: (F.col(c).cast("long") * 4 + k)
    nation = load(spark, sf_dir, "nation").select(place("n_nationkey", 1).alias("src"), place("n_regionkey", 0).alias("dst"))
    customer = load(spark, sf_dir, "customer").select(place("c_custkey", 2).alias("src"), place("c_nationkey", 1).alias("dst"))
    supplier = load(spark, sf_dir, "supplier").select(place("s_suppkey", 3).alias("src"), place("s_nationkey", 1).alias("dst"))
    return _graph("geo", nation.unionByName(customer).unionByName(supplier))


def toy5(spark: SparkSession, sf_dir: str | None = None) -> GraphSpec:
    """Five vertices over two partitions, each side joined to all of the other."""
    edges = spark.createDataFrame([(a, b) for a in (0, 1) for b in (2, 3, 4)], EDGE)
    return _graph("toy5", edges)


def kron(spark: SparkSession, scale: int, edge_factor: int = 16, seed: int = 1) -> GraphSpec:
    """A power-law graph from integer arithmetic alone: every bit of both ends is drawn by a hash."""
    rows = spark.range((1 << scale) * edge_factor)
    src, dst = F.lit(0).cast("long"), F.lit(0).cast("long")
    for level in range(scale):
        draw = F.pmod(F.xxhash64(F.lit(seed), F.lit(level), F.col("id")), F.lit(100))
        # quadrant shares of 57, 19, 19 and 5 in a hundred, as the public graph benchmark draws
        src = src * 2 + F.when(draw >= 76, 1).otherwise(0)
        dst = dst * 2 + F.when((draw >= 57) & (draw < 76) | (draw >= 95), 1).otherwise(0)
    edges = rows.select(src.alias("src"), dst.alias("dst")).filter("src <> dst")
    return _graph("kron", edges.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")))


BUILDERS: dict[str, Callable[[SparkSession, str], GraphSpec]] = {
    f.__name__: f
    for f in (
        basket, supply, patron, nation_trade, copurchase, copurchase_sparse, accounts, event_chain, event_session,
        event_flow, user_relay, page_links, knn, doc_dup, dialog, geo,
    )
}
