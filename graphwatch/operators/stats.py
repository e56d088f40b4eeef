"""Statistics of an edge stream: kinds, typed two-edge paths, selectivities, stability."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def with_kind(edges: DataFrame, kind: Column) -> DataFrame:
    return edges.withColumn("etype", kind)


def sample_prefix(edges: DataFrame, n: int) -> DataFrame:
    """The first n edges of the stream; a filter, so that it reaches the scan."""
    return edges.filter(F.col("eid") < n)


def edge_histogram(edges: DataFrame) -> DataFrame:
    return edges.groupBy("etype").agg(F.count("*").alias("freq"))


def incidence(edges: DataFrame) -> DataFrame:
    """(v, sig): both ends of every edge, with direction and kind."""
    ends = F.array(F.struct(F.col("src").alias("v"), F.concat(F.lit("o:"), "etype").alias("sig")), F.struct(F.col("dst").alias("v"), F.concat(F.lit("i:"), "etype").alias("sig")))
    return edges.select(F.inline(ends))


def incidence_counts(edges: DataFrame) -> DataFrame:
    return incidence(edges).groupBy("v", "sig").agg(F.count("*").alias("n"))


def _pairs(counts: DataFrame) -> DataFrame:
    """Per vertex: equal signatures n(n-1)/2, different ones once, by name. A vertex has as many rows as signatures, whatever its degree."""
    per = counts.groupBy("v").agg(F.array_sort(F.collect_list(F.struct("sig", "n"))).alias("s"))
    each = per.select(F.posexplode("s").alias("i", "a"), "s").select("a", F.explode(F.slice("s", F.col("i") + 1, F.size("s"))).alias("b"))
    n = F.when(F.col("a.sig") == F.col("b.sig"), F.expr("a.n * (a.n - 1) div 2")).otherwise(F.col("a.n") * F.col("b.n"))
    return each.select(F.col("a.sig").alias("sig1"), F.col("b.sig").alias("sig2"), n.cast("long").alias("cnt"))


def _summed(pairs: DataFrame) -> DataFrame:
    return pairs.groupBy("sig1", "sig2").agg(F.sum("cnt").cast("long").alias("cnt")).filter("cnt > 0")


def two_edge_paths(edges: DataFrame, mode: str = "printed") -> DataFrame:
    """sig1, sig2, cnt of all pairs of edges that meet in a vertex, without making the pairs.

    printed counts all; strict leaves out pairs that share both ends and self loops, so that what is
    left are paths of three vertices.
    """
    if mode == "printed":
        return _summed(_pairs(incidence_counts(edges)))
    plain = edges.filter("src <> dst")
    at = incidence(plain).groupBy("v", "sig").agg(F.count("*").alias("n"))
    both = F.array(
        F.struct(F.col("src").alias("v"), F.col("dst").alias("u"), F.concat(F.lit("o:"), "etype").alias("sig")),
        F.struct(F.col("dst").alias("v"), F.col("src").alias("u"), F.concat(F.lit("i:"), "etype").alias("sig")),
    )
    same = plain.select(F.inline(both)).groupBy("v", "u", "sig").agg(F.count("*").alias("n"))
    parallel = same.select(F.struct("v", "u").alias("v"), "sig", "n")
    less = _pairs(parallel).withColumn("cnt", -F.col("cnt"))
    return _summed(_pairs(at).unionByName(less))


class PathCounters:
    """Two-edge path counts kept up to date by increments of the per-vertex counts."""

    def __init__(self):
        self.counts: DataFrame | None = None
        self.paths: DataFrame | None = None

    def update(self, delta: DataFrame) -> DataFrame:
        from graphwatch.functions.storage import table

        new = incidence_counts(delta)
        if self.counts is None:
            self.counts = table(new, "incidence")
            self.paths = table(_summed(_pairs(self.counts)), "paths")
            return self.paths
        touched = self.counts.join(new.select("v").distinct(), "v", "left_semi")
        now = touched.unionByName(new).groupBy("v", "sig").agg(F.sum("n").alias("n"))
        change = _pairs(now).unionByName(_pairs(touched).withColumn("cnt", -F.col("cnt")))
        self.paths = table(_summed(self.paths.unionByName(change)), "paths")
        self.counts = table(self.counts.unionByName(new).groupBy("v", "sig").agg(F.sum("n").alias("n")), "incidence")
        return self.paths


def selectivity(freqs: DataFrame, freq: str) -> DataFrame:
    """freqs with ``total``, the sum of freq; the ratio of the two is the selectivity."""
    total = freqs.agg(F.sum(freq).cast("long").alias("total"))
    return freqs.join(F.broadcast(total))  # one row


def selectivity_distribution(freqs: DataFrame, freq: str, names: list[str]) -> DataFrame:
    """Ascending by frequency, then by name; the table has one row for each kind or pair of kinds."""
    order = Window.partitionBy(F.lit(0)).orderBy(freq, *names)
    return selectivity(freqs, freq).withColumn("rank", F.row_number().over(order).cast("long"))


def interval_counts(edges: DataFrame, interval: int) -> DataFrame:
    return edges.groupBy(F.floor(F.col("eid") / interval).cast("long").alias("slot"), "etype").agg(F.count("*").alias("n"))


def _inversions(counts: DataFrame, names: list[str]) -> DataFrame:
    """counts (slot, names, n) -> slot, pairs, inverted: pairs that change their order (by n, then names) from the slot before to this one."""
    slots, things = counts.select("slot").distinct(), counts.select(*names).distinct()
    # Slots times kinds (or pairs of kinds): a small table, whatever the number of edges.
    full = slots.join(F.broadcast(things)).join(counts, ["slot", *names], "left").fillna(0, ["n"])
    ranked = full.withColumn("r", F.row_number().over(Window.partitionBy("slot").orderBy("n", *names)))
    before = ranked.select((F.col("slot") + 1).alias("slot"), *names, F.col("r").alias("p"))
    both = ranked.join(before, ["slot", *names]).select("slot", F.struct(*names).alias("t1"), F.col("r").alias("r"), "p")
    other = both.select("slot", F.col("t1").alias("t2"), F.col("r").alias("r2"), F.col("p").alias("p2"))
    pairs = both.join(other, "slot").filter("t1 < t2")
    return pairs.groupBy("slot").agg(F.count("*").alias("pairs"), F.sum(F.when((F.col("r") < F.col("r2")) != (F.col("p") < F.col("p2")), 1).otherwise(0)).cast("long").alias("inverted"))


def order_stability(edges: DataFrame, interval: int, what: str = "edge") -> DataFrame:
    """slot, pairs, inverted: pairs of kinds (what="edge") or of two-edge paths (what="pair") that change their order between intervals."""
    if what == "edge":
        return _inversions(interval_counts(edges, interval), ["etype"])
    return _inversions(interval_paths(edges, interval).withColumnRenamed("cnt", "n"), ["sig1", "sig2"])


def interval_paths(edges: DataFrame, interval: int) -> DataFrame:
    """slot, sig1, sig2, cnt: two-edge paths within each interval of the stream, counted like those of the whole."""
    slot = F.floor(F.col("eid") / interval).cast("long")
    ends = F.array(*[F.struct(F.struct(slot.alias("slot"), F.col(c).alias("v")).alias("v"), F.concat(F.lit(d), "etype").alias("sig")) for c, d in (("src", "o:"), ("dst", "i:"))])
    counts = edges.select(F.inline(ends)).groupBy("v", "sig").agg(F.count("*").alias("n"))
    per = counts.groupBy("v").agg(F.array_sort(F.collect_list(F.struct("sig", "n"))).alias("s"))
    each = per.select(F.col("v.slot").alias("slot"), F.posexplode("s").alias("i", "a"), "s").select("slot", "a", F.explode(F.slice("s", F.col("i") + 1, F.size("s"))).alias("b"))
    n = F.when(F.col("a.sig") == F.col("b.sig"), F.expr("a.n * (a.n - 1) div 2")).otherwise(F.col("a.n") * F.col("b.n"))
    return each.groupBy("slot", F.col("a.sig").alias("sig1"), F.col("b.sig").alias("sig2")).agg(F.sum(n).cast("long").alias("cnt")).filter("cnt > 0")


def degree_percentiles(edges: DataFrame, shares: tuple[float, ...] = (0.5, 0.9, 0.99)) -> DataFrame:
    """sig and exact percentiles of the number of edges with that signature at a vertex, rounded."""
    return incidence_counts(edges).groupBy("sig").agg(*[F.round(F.percentile("n", F.lit(q)), 6).alias(f"p{round(100 * q)}") for q in shares])


def vertex_estimate(edges: DataFrame) -> DataFrame:
    """Distinct vertices by a HyperLogLog sketch that can be merged with those of other batches, and exactly."""
    v = edges.select(F.explode(F.array("src", "dst")).alias("v"))
    return v.agg(F.hll_sketch_estimate(F.hll_sketch_agg("v", F.lit(14))).alias("estimate"), F.count_distinct("v").alias("vertices"))


def stratified_sample(edges: DataFrame, shares: dict[str, float], seed: int = 1) -> DataFrame:
    """A hashed share of the edges of each kind; kinds that are not named are left out. Reruns agree."""
    share = F.create_map(*[F.lit(x) for kv in shares.items() for x in kv])[F.col("etype")]
    return edges.filter(F.pmod(F.xxhash64(F.lit(seed), "eid"), F.lit(1 << 20)) < F.coalesce(share, F.lit(0.0)) * (1 << 20))


def triangle_counts(edges: DataFrame) -> DataFrame:
    """Undirected triangles by their sorted kinds. Each edge points from its end of lower degree, so a hub's edges are few."""
    plain = edges.filter("src <> dst").select(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b"), "etype").distinct()
    degree = plain.select(F.explode(F.array("a", "b")).alias("v")).groupBy("v").agg(F.count("*").alias("d"))
    e = plain.join(degree.select(F.col("v").alias("a"), F.col("d").alias("da")), "a").join(degree.select(F.col("v").alias("b"), F.col("d").alias("db")), "b")
    up = (F.col("da") < F.col("db")) | ((F.col("da") == F.col("db")) & (F.col("a") < F.col("b")))
    e = e.select(F.when(up, F.col("a")).otherwise(F.col("b")).alias("lo"), F.when(up, F.col("b")).otherwise(F.col("a")).alias("hi"), "etype")
    one, two = e.select("lo", F.col("hi").alias("x"), F.col("etype").alias("t1")), e.select("lo", F.col("hi").alias("y"), F.col("etype").alias("t2"))
    wedge = one.join(two, "lo").filter("x <> y")
    close = e.select(F.col("lo").alias("x"), F.col("hi").alias("y"), F.col("etype").alias("t3"))
    kinds = F.array_join(F.array_sort(F.array("t1", "t2", "t3")), ",")
    return wedge.join(close, ["x", "y"]).groupBy(kinds.alias("kinds")).agg(F.count("*").alias("n"))


def triangle_estimate(edges: DataFrame, p: float, seed: int = 1) -> DataFrame:
    """Triangles on a hashed sample of the edges, divided by p cubed."""
    share = F.pmod(F.xxhash64(F.lit(seed), "eid"), F.lit(1 << 20)) < int(p * (1 << 20))
    return triangle_counts(edges.filter(share)).withColumn("estimate", F.col("n") / p**3)


def mean_degree(edges: DataFrame) -> DataFrame:
    """Per signature: edges, vertices that have one, and their ratio in integers."""
    return incidence_counts(edges).groupBy("sig").agg(F.sum("n").cast("long").alias("edges"), F.count("*").alias("vertices"))


def signature_summary(edges: DataFrame) -> DataFrame:
    paths = two_edge_paths(edges)
    return edges.agg(F.count_distinct("etype").alias("kinds"), F.count("*").alias("edges")).join(F.broadcast(paths.agg(F.count("*").alias("signatures"), F.coalesce(F.sum("cnt"), F.lit(0)).cast("long").alias("total"))))
