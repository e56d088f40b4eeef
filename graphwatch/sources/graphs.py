"""Typed edge streams made of the given tables. Edges: eid, src, dst, etype, ts; eid is the arrival order.

A vertex id is a type code in the high bits and the table's key in the low ones; categories get the
rank of their value among the distinct ones.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graphwatch.functions.ranking import range_rank, stored_rank

#: Type codes of the vertex ids.
CODES = {n: i for i, n in enumerate("host order part supplier customer nation region segment brand ptype document source lang quality toxic page site conversation turn object priority status".split())}
BITS = 48
#: Cut points of the seven value bands of host edges.
BANDS = (60, 120, 180, 240, 300, 360)


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def vid(kind: str, key: Column | str) -> Column:
    return (F.lit(CODES[kind] << BITS) + (F.col(key) if isinstance(key, str) else key)).cast("long")


def band_kind(value: Column, cuts: tuple = BANDS, name: str = "k") -> Column:
    out = F.lit(f"{name}{len(cuts)}")
    for i in reversed(range(len(cuts))):
        out = F.when(value < cuts[i], f"{name}{i}").otherwise(out)
    return out


def community_kind() -> Column:
    """Noise above 250; else one kind for edges inside a class of hosts; else three bands."""
    inside = F.col("src") % 7 == F.col("dst") % 7
    rest = F.when(F.col("value") < 60, "x0").when(F.col("value") < 120, "x1").otherwise("x2")
    noise = F.concat(F.lit("c"), (F.col("event_id") % 7).cast("string"))
    return F.when(F.col("value") >= 250, noise).when(inside, F.concat(F.lit("c"), (F.col("src") % 7).cast("string"))).otherwise(rest)


def hash_kind(columns: list[str], buckets: int) -> Column:
    return F.concat(F.lit("h"), F.pmod(F.xxhash64(*columns), F.lit(buckets)).cast("string"))


def composite_kind(columns: list[str | Column]) -> Column:
    return F.concat_ws("_", *columns)


def assign_eid(raw: DataFrame, order: list[str]) -> DataFrame:
    """raw with eid, the rank in ``order``; ranges are sorted apart and their sizes added up. Stored, as a query reads its edges many times."""
    return stored_rank(raw, [F.col(c) for c in order], "eid", "edges")


def _edges(df: DataFrame, src: Column, dst: Column, etype: Column | str, ts: str | None) -> DataFrame:
    when = F.col(ts) if ts else F.lit("1970-01-01 00:00:00")
    return df.select(src.alias("src"), dst.alias("dst"), (F.lit(etype) if isinstance(etype, str) else etype).alias("etype"), when.cast("timestamp_ntz").alias("ts"))


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def facet_graph(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Articles (orders) with their facets: part, supplier, customer, nation."""
    orders, lines, customers = (load(spark, sf_dir, n) for n in ("orders", "lineitem", "customer"))
    # Lines meet their orders once for both kinds, and each order's facets are made distinct where they met.
    facets = [F.struct(F.lit(k).alias("etype"), vid(k, c).alias("dst")) for k, c in (("part", "l_partkey"), ("supplier", "l_suppkey"))]
    dated = lines.join(orders.select(F.col("o_orderkey").alias("l_orderkey"), "o_orderdate"), "l_orderkey")
    each = dated.select("l_orderkey", "o_orderdate", F.explode(F.array(*facets)).alias("f")).select("l_orderkey", "o_orderdate", "f.*").distinct()
    bought = orders.join(customers, orders["o_custkey"] == customers["c_custkey"])
    whose = [F.struct(F.lit(k).alias("etype"), vid(k, c).alias("dst")) for k, c in (("customer", "o_custkey"), ("nation", "c_nationkey"))]
    owned = bought.select("o_orderkey", "o_orderdate", F.explode(F.array(*whose)).alias("f")).select("o_orderkey", "o_orderdate", "f.*")
    parts = [_edges(rows, vid("order", key), F.col("dst"), F.col("etype"), "o_orderdate") for rows, key in ((each, "l_orderkey"), (owned, "o_orderkey"))]
    return assign_eid(_union(parts), ["ts", "src", "etype", "dst"])


def host_graph(spark: SparkSession, sf_dir: str, kinds: str = "bands") -> DataFrame:
    """Hosts of one type; kinds by value band, by community or by event type."""
    events = load(spark, sf_dir, "events").select("event_id", F.col("user_id").alias("src"), F.get_json_object("props", "$.k").cast("long").alias("dst"), "value", "event_type", F.col("ts").cast("timestamp_ntz").alias("ts"))
    kind = {"bands": band_kind(F.col("value")), "community": community_kind(), "uniform": F.col("event_type")}[kinds]
    rows = events.filter("src <> dst").select("event_id", "src", "dst", kind.alias("etype"), "ts")
    return assign_eid(rows, ["event_id"]).drop("event_id")


def trade_graph(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Suppliers to customers, one edge for each line of an order; parallel edges are common."""
    orders, lines = load(spark, sf_dir, "orders"), load(spark, sf_dir, "lineitem")
    rows = lines.join(orders.select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey"), "l_orderkey")
    kind = composite_kind(["l_returnflag", "l_linestatus"])
    order = ["l_shipdate", "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"]
    rows = rows.select(*order, vid("supplier", "l_suppkey").alias("src"), vid("customer", "o_custkey").alias("dst"), kind.alias("etype"), F.col("l_shipdate").cast("timestamp_ntz").alias("ts"))
    return assign_eid(rows, order).drop(*order)


def _ranked(df: DataFrame, value: Column, many: bool = False) -> DataFrame:
    """df with ``_k``, the rank of value among its distinct values. many: their number grows with the data; else one row for each category meets in a window."""
    valued = df.withColumn("_v", value)
    each = valued.select("_v").distinct()
    if many:
        ranks = range_rank(each, [F.col("_v")], "_k")
    else:
        ranks = each.withColumn("_k", F.row_number().over(Window.partitionBy(F.lit(0)).orderBy("_v")) - 1)
    return valued.join(ranks, "_v")


def social_graph(spark: SparkSession, sf_dir: str) -> DataFrame:
    """34 kinds of edges: master data first, then activity in time order."""
    t = {n: load(spark, sf_dir, n) for n in "orders lineitem customer supplier part nation documents labels pages conversations events".split()}
    flags = F.concat(F.col("l_returnflag"), F.col("l_linestatus"))
    category = lambda table, kind, key, value, target, name, ts=None, many=False: _edges(_ranked(t[table], value, many), vid(kind, key), vid(target, "_k"), name, ts)
    parts = [
        _edges(t["customer"], vid("customer", "c_custkey"), vid("nation", "c_nationkey"), "in_nation", None),
        _edges(t["supplier"], vid("supplier", "s_suppkey"), vid("nation", "s_nationkey"), "from_nation", None),
        _edges(t["nation"], vid("nation", "n_nationkey"), vid("region", "n_regionkey"), "in_region", None),
        category("customer", "customer", "c_custkey", F.col("c_mktsegment"), "segment", "segment"),
        category("part", "part", "p_partkey", F.col("p_brand"), "brand", "brand"),
        category("part", "part", "p_partkey", F.col("p_type"), "ptype", "ptype"),
        category("documents", "document", "doc_id", F.col("source"), "source", "source"),
        category("documents", "document", "doc_id", F.col("lang"), "lang", "lang"),
        _edges(t["labels"], vid("document", "doc_id"), vid("quality", "quality"), "quality", None),
        _edges(t["labels"], vid("document", "doc_id"), vid("toxic", "toxic"), "toxic", None),
        category("pages", "page", "page_id", F.regexp_extract("url", r"://([^/?#]*)", 1), "site", "site", many=True),
        _edges(t["conversations"], vid("conversation", "conv_id"), vid("turn", F.col("conv_id") * 65536 + F.col("turn")), F.concat(F.lit("turn_"), F.col("role")), None),
        _edges(t["orders"], vid("customer", "o_custkey"), vid("order", "o_orderkey"), "places", "o_orderdate"),
        category("orders", "order", "o_orderkey", F.col("o_orderpriority"), "priority", "prio", "o_orderdate"),
        category("orders", "order", "o_orderkey", F.col("o_orderstatus"), "status", "status", "o_orderdate"),
        _edges(t["lineitem"], vid("order", "l_orderkey"), vid("part", "l_partkey"), F.concat(F.lit("has_"), flags), "l_shipdate"),
        _edges(t["lineitem"], vid("supplier", "l_suppkey"), vid("order", "l_orderkey"), F.concat(F.lit("ships_"), flags), "l_shipdate"),
        _edges(t["events"], vid("customer", "user_id"), vid("object", F.get_json_object("props", "$.k").cast("long")), F.col("event_type"), "ts"),
    ]
    return assign_eid(_union(parts), ["ts", "etype", "src", "dst"])


def social_vertices(spark: SparkSession, sf_dir: str) -> DataFrame:
    """vid, vtype, label of the vertices that have a name in the tables."""
    names = {"customer": ("c_custkey", "c_mktsegment"), "supplier": ("s_suppkey", "s_name"), "part": ("p_partkey", "p_type"), "nation": ("n_nationkey", "n_name"), "region": ("r_regionkey", "r_name")}
    return _union([load(spark, sf_dir, t).select(vid(t, k).alias("vid"), F.lit(t).alias("vtype"), F.col(v).alias("label")) for t, (k, v) in names.items()])


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    """An edge list in parquet, csv, json or as text triples ``<src> <etype> <dst> .``; text has no time, so eid is the place in the order of its columns."""
    schema = "eid long, src long, dst long, etype string, ts timestamp_ntz"
    if fmt != "triples":
        return spark.read.schema(schema).format(fmt).load(path)
    line = F.col("value")
    rows = spark.read.text(path).select(*[F.regexp_extract(line, r"^<([^>]*)> <([^>]*)> <([^>]*)> \.", i).alias(n) for i, n in ((1, "s"), (2, "etype"), (3, "o"))]).filter("s <> ''")
    rows = rows.select(F.col("s").cast("long").alias("src"), F.col("o").cast("long").alias("dst"), "etype", F.lit(None).cast("timestamp_ntz").alias("ts"))
    return assign_eid(rows, ["src", "etype", "dst"])


def drop_vertices(edges: DataFrame, predicate: str) -> DataFrame:
    """edges without those that touch a vertex for which the SQL predicate over vid holds."""
    held = edges
    for c in ("src", "dst"):
        held = held.withColumn("vid", F.col(c)).filter(~F.coalesce(F.expr(predicate), F.lit(False))).drop("vid")
    return held


def hub_vertices(edges: DataFrame, k: int) -> DataFrame:
    """vid, degree of the k vertices of highest degree (ties: smaller vid)."""
    ends = edges.select(F.explode(F.array("src", "dst")).alias("vid"))
    return ends.groupBy("vid").agg(F.count("*").alias("degree")).orderBy(F.desc("degree"), "vid").limit(k)
