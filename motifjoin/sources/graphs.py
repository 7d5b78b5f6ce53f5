"""Graphs and relations derived from the given tables; edges are distinct ``(src, dst)`` longs without loops."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from motifjoin.operators import pairs

#: Lines beyond which the pairs of baskets are made in packed form.
LARGE = 2_000_000
EDGE = T.StructType([T.StructField("src", T.LongType()), T.StructField("dst", T.LongType())])


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def as_edges(df: DataFrame, src: str, dst: str, loops: bool = False) -> DataFrame:
    """Two columns as an edge relation."""
    rows = df.select(F.col(src).cast("long").alias("src"), F.col(dst).cast("long").alias("dst")).na.drop()
    return (rows if loops else rows.filter("src <> dst")).dropDuplicates()


def complete_dag(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All ascending pairs of region keys."""
    r = table(spark, sf_dir, "region").select(F.col("r_regionkey").cast("long").alias("k"))
    return r.select(F.col("k").alias("src")).join(r.select(F.col("k").alias("dst")), F.col("src") < F.col("dst"))


def basket_edges(spark: SparkSession, sf_dir: str, filtered: bool = True) -> DataFrame:
    """Two parts bought in one order, from the smaller to the larger key."""
    orders = table(spark, sf_dir, "orders")
    if filtered:
        orders = orders.filter(F.col("o_orderpriority").startswith("1-") & (F.col("o_orderstatus") == "F"))
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").join(orders.select(F.col("o_orderkey").alias("l_orderkey")), "l_orderkey", "left_semi").dropDuplicates()
    # the parts of an order as one sorted array, so that pairs are made without a second shuffle
    baskets = lines.groupBy("l_orderkey").agg(F.array_sort(F.collect_list("l_partkey")).alias("ps")).filter(F.size("ps") > 1)
    if (n := table(spark, sf_dir, "lineitem").count()) > LARGE:
        # many pairs are sorted and made distinct in their tasks and move as differences
        parts = -(-n // 500_000)
        sent = baskets.select("ps").mapInArrow(lambda it: pairs.blobs(pairs.pairs_within(it), pairs.by_class(parts)), pairs.BLOBS)
        return pairs.distinct_pairs(sent, parts).toDF("src", "dst")
    each = baskets.select(F.posexplode("ps").alias("i", "src"), "ps")
    return each.select("src", F.explode(F.expr("slice(ps, i + 2, size(ps))")).alias("dst")).dropDuplicates()


def whole_basket_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two parts bought in any one order."""
    return basket_edges(spark, sf_dir, filtered=False)


def wheel_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A hub (-1) linked with every customer both ways, and a path through the customers."""
    c = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("k"))
    top = c.agg(F.max("k")).first()[0]
    hub = F.lit(-1).cast("long")
    out = c.select(F.explode(F.array(F.struct(hub.alias("src"), F.col("k").alias("dst")), F.struct(F.col("k").alias("src"), hub.alias("dst")), F.struct(F.col("k").alias("src"), (F.col("k") + 1).alias("dst")))).alias("e")).select("e.*")
    return out.filter(F.col("dst") <= (top if top is not None else -1))


def hub_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers and their nations (as negative numbers), both ways."""
    c = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("k"), (-1 - F.col("c_nationkey")).cast("long").alias("h"))
    return c.select(F.explode(F.array(F.struct(F.col("k").alias("src"), F.col("h").alias("dst")), F.struct(F.col("h").alias("src"), F.col("k").alias("dst")))).alias("e")).select("e.*")


def event_pairs(events: DataFrame) -> DataFrame:
    """Events as ``(ts, event_id, event_type, src, dst)``: user to the number in the properties."""
    k = F.expr("try_cast(get_json_object(props, '$.k') as bigint)")
    return events.select(F.col("ts").cast("timestamp").alias("ts"), "event_id", "event_type", F.col("user_id").alias("src"), k.alias("dst")).filter("src is not null and dst is not null and src <> dst")


def event_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edges of purchases."""
    return event_pairs(table(spark, sf_dir, "events")).filter("event_type = 'purchase'").select("src", "dst").dropDuplicates()


def event_updates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Daily net operations ``(day, src, dst, w)``: purchases insert, errors delete, the last one of a day counts."""
    ops = event_pairs(table(spark, sf_dir, "events")).filter("event_type in ('purchase', 'error')")
    w = F.when(F.col("event_type") == "purchase", 1).otherwise(-1)
    return ops.groupBy(F.to_date("ts").alias("day"), "src", "dst").agg(F.max_by(w, F.struct("ts", "event_id")).cast("int").alias("w"))


def page_links(spark: SparkSession, sf_dir: str, shared: int = 3) -> DataFrame:
    """Pages, ascending, that share ``shared`` or more distinct link targets."""
    pages = table(spark, sf_dir, "pages").select("page_id", F.explode(F.array_distinct(F.regexp_extract_all("html", F.lit('href="/([^"]*)"'), 1))).alias("token"))
    left, right = pages.select(F.col("page_id").alias("src"), "token"), pages.select(F.col("page_id").alias("dst"), "token")
    return left.join(right, "token").filter("src < dst").groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") >= shared).select("src", "dst")


def label_band(spark: SparkSession, sf_dir: str, width: int = 40) -> DataFrame:
    """Vectors of one label whose numbers lie at most ``width`` apart: a band join on blocks of numbers."""
    v = table(spark, sf_dir, "embeddings").select("vec_id", "label", F.floor(F.col("vec_id") / width).alias("block"))
    a = v.select(F.col("vec_id").alias("src"), "label", F.explode(F.array("block", F.col("block") + 1)).alias("block"))
    b = v.select(F.col("vec_id").alias("dst"), "label", "block")
    return a.join(b, ["label", "block"]).filter((F.col("dst") > F.col("src")) & (F.col("dst") - F.col("src") <= width)).select("src", "dst")


def turn_path(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each turn of a conversation to the next one; vertices are numbered by conversation and turn, past the last turn of any."""
    c = table(spark, sf_dir, "conversations").select("conv_id", "turn").dropDuplicates()
    width = (c.agg(F.max("turn")).first()[0] or 0) + 1
    a = c.select("conv_id", "turn", (F.col("conv_id") * width + F.col("turn")).alias("src"))
    b = c.select("conv_id", (F.col("turn") - 1).alias("turn"), (F.col("conv_id") * width + F.col("turn")).alias("dst"))
    return a.join(b, ["conv_id", "turn"]).select("src", "dst")


def cycle_relations(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    """Customer, order, supplier and nation relations that close a cycle."""
    t = lambda n: table(spark, sf_dir, n)
    return {
        "C": t("customer").select("c_custkey", "c_nationkey"),
        "O": t("orders").select("o_orderkey", "o_custkey"),
        "L": t("lineitem").select("l_orderkey", "l_suppkey"),
        "S": t("supplier").select("s_suppkey", "s_nationkey"),
    }


def parts_relations(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    """Thirds of (order, part, supplier) by pairs, and the ternary relation itself."""
    ops = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey")
    return {
        "OP": ops.filter("l_suppkey % 3 = 0").select("l_orderkey", "l_partkey"),
        "OS": ops.filter("l_partkey % 3 = 0").select("l_orderkey", "l_suppkey"),
        "PS": ops.filter("l_orderkey % 3 = 0").select("l_partkey", "l_suppkey"),
        "OPS": ops,
    }


def whole_parts_relations(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    """All pairs of order, part and supplier, and the ternary relation itself."""
    ops = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey")
    return {"OP": ops.select("l_orderkey", "l_partkey"), "OS": ops.select("l_orderkey", "l_suppkey"), "PS": ops.select("l_partkey", "l_suppkey"), "OPS": ops}


def mixed_batch(edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """``(old graph, changes with w)``: a tenth inserted, a tenth deleted."""
    digit = (F.col("src") + F.col("dst")) % 10
    changes = edges.filter(digit <= 1).withColumn("w", F.when(digit == 0, 1).otherwise(-1).cast("int"))
    return edges.filter(digit != 0), changes


def batch_sequence(edges: DataFrame, n: int = 20, deletes: bool = True) -> tuple[DataFrame, DataFrame]:
    """``(preloaded graph, changes (ver, src, dst, w))``: half preloaded, the rest in ``n`` batches."""
    g = (F.col("src") * 31 + F.col("dst") * 17) % (2 * n)
    ins = edges.filter(g < n).select((g + 1).alias("ver"), "src", "dst", F.lit(1).alias("w"))
    gone = edges.filter((g >= n) & ((F.col("src") + F.col("dst")) % 3 == 0)).select((g - n + 1).alias("ver"), "src", "dst", F.lit(-1).alias("w"))
    return edges.filter(g >= n), ins.unionByName(gone) if deletes else ins


def fraction(edges: DataFrame, sixteenths: int) -> DataFrame:
    """A share of the edges, by their ends."""
    return edges.filter((F.col("src") + F.col("dst")) % 16 < sixteenths)


def symmetric(edges: DataFrame) -> DataFrame:
    """Every edge in both directions."""
    return edges.select("src", "dst").union(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).dropDuplicates()
