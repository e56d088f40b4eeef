"""Mixing sources to target weights.

A source's words are cut into blocks of consecutive words of its documents, and its blocks are put
in a permuted order. A source's quota is a number of draws: as many whole passes over its blocks as the
target allows, and the first blocks of one more pass, so that the words come nearest to the target.
A splitting tree divides the quotas among the shards: a node halves its shards and splits its vector of
per-source draws by a multivariate hypergeometric draw, down to single shards, which gives every shard
exact quotas. Draws are then made by the shards: shard s takes, of each source, the next blocks of the
permuted order, as many as its quota says; a block that no quota reaches is not in the mix. So draws are
disjoint, no document is taken more than ``max_copies`` times, and within a shard draws are ordered by a
hash. Everything is SQL functions; randomness is hashing, so reruns agree.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from graphwatch.functions.ranking import range_rank, range_sums
from graphwatch.functions.storage import cut
from graphwatch.llm.text import count_words

WEIGHTS, SHARE, MAX_COPIES, BLOCK_WORDS, SHARDS, SEED = (5, 2, 1), 1.5, 2, 128, 8, 20


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: float = SHARE, max_copies: int = MAX_COPIES) -> DataFrame:
    """source, size -> source, si (its place by code point, null last), source_size, target.

    Sources share ``share`` of all words by weight; what exceeds max_copies times a source's size
    is shared again by the weights of the others. Only sums over all sources come to the driver.
    """
    per = sizes.groupBy("source").agg(F.sum("size").cast("long").alias("source_size"))
    ranked = range_rank(per, [F.col("source").asc_nulls_last()], "si")
    weight = F.get(F.array(*[F.lit(float(w)) for w in weights]), (F.col("si") % len(weights)).cast("int"))
    ranked = cut(ranked.withColumn("w", weight).withColumn("cap", (max_copies * F.col("source_size")).cast("double")))
    total = float(ranked.agg(F.sum("source_size")).first()[0] or 0) * share
    rate = 0.0
    while True:
        # rate: words for each unit of weight; sources that it would fill stop at their cap.
        free = F.col("cap") > rate * F.col("w")
        full, rest = ranked.agg(F.sum(F.when(~free, F.col("cap")).otherwise(0.0)), F.sum(F.when(free, F.col("w")).otherwise(0.0))).first()
        now = (total - full) / rest if rest else rate
        if not rest or now <= rate:
            break
        rate = now
    return ranked.select("source", "si", "source_size", F.least("cap", F.lit(rate) * F.col("w")).alias("target"))


def _let(value: Column, use: Callable[[Column], Column]) -> Column:
    """use(value), with value computed once and named, so that expressions stay small."""
    return F.get(F.transform(F.array(value), use), F.lit(0))


def _ln_factorial(n: Column) -> Column:
    """Stirling's series after a shift by eight; n is a double."""

    def series(x: Column) -> Column:
        product = x + 1.0
        for i in range(2, 9):
            product = product * (x + float(i))
        z = x + 9.0
        return (z - 0.5) * F.log(z) - z + 0.9189385332046727 + 1 / (12 * z) - 1 / (360 * z * z * z) + 1 / (1260 * z * z * z * z * z) - F.log(product)

    return _let(n, series)


def hypergeometric(white: Column, black: Column, draws: Column, u: Column) -> Column:
    """How many of ``draws`` from white + black are white: the inverse of the distribution at u, taken from the mode outwards.

    The steps end 40 deviations from the mode, beyond what a double can show.
    """

    def bounds(a: Column) -> Column:
        low, high = F.greatest(F.lit(0.0), a["k"] - a["b"]), F.least(a["k"], a["w"])
        mode = F.floor((a["k"] + 1) * (a["w"] + 1) / (a["w"] + a["b"] + 2)).cast("double")
        every = a["w"] + a["b"]
        spread = F.sqrt(a["k"] * a["w"] * a["b"] * (every - a["k"]) / F.greatest(every * every * (every - 1), F.lit(1.0)))
        return F.struct(a["w"].alias("w"), a["b"].alias("b"), a["k"].alias("k"), a["u"].alias("u"), low.alias("low"), high.alias("high"), F.greatest(low, F.least(high, mode)).alias("mode"), F.coalesce(spread, F.lit(0.0)).alias("spread"))

    def drawn(a: Column) -> Column:
        choose = lambda n, k: _ln_factorial(n) - _ln_factorial(k) - _ln_factorial(n - k)
        top = F.exp(choose(a["w"], a["mode"]) + choose(a["b"], a["k"] - a["mode"]) - choose(a["w"] + a["b"], a["k"]))

        def walk(p: Column) -> Column:
            start = F.struct((a["u"] - p).alias("u"), a["mode"].alias("up"), p.alias("pu"), a["mode"].alias("down"), p.alias("pd"), F.when(a["u"] < p, a["mode"]).alias("got"))

            def step(s: Column, _: Column) -> Column:
                more = F.when(s["up"] < a["high"], s["pu"] * (a["w"] - s["up"]) * (a["k"] - s["up"]) / ((s["up"] + 1) * (a["b"] - a["k"] + s["up"] + 1))).otherwise(0.0)
                less = F.when(s["down"] > a["low"], s["pd"] * s["down"] * (a["b"] - a["k"] + s["down"]) / ((a["w"] - s["down"] + 1) * (a["k"] - s["down"] + 1))).otherwise(0.0)

                def after(m: Column) -> Column:
                    got = F.when(s["got"].isNotNull(), s["got"]).when(s["u"] < m["more"], s["up"] + 1).when(s["u"] < m["more"] + m["less"], s["down"] - 1)
                    return F.struct((s["u"] - m["more"] - m["less"]).alias("u"), (s["up"] + 1).alias("up"), m["more"].alias("pu"), (s["down"] - 1).alias("down"), m["less"].alias("pd"), got.alias("got"))

                return _let(F.struct(more.alias("more"), less.alias("less")), after)

            steps = F.least(a["high"] - a["low"], 40 * a["spread"] + 60).cast("long")
            return F.aggregate(F.sequence(F.lit(1).cast("long"), F.greatest(steps, F.lit(1).cast("long"))), start, step, lambda s: F.coalesce(s["got"], a["mode"]))

        return F.when(a["low"] >= a["high"], a["low"]).otherwise(_let(top, walk)).cast("long")

    d = lambda c: c.cast("double")
    return _let(F.struct(d(white).alias("w"), d(black).alias("b"), d(draws).alias("k"), u.alias("u")), lambda a: _let(bounds(a), drawn))


def shard_quotas(draws: DataFrame, shards: int = SHARDS, seed: int = SEED) -> DataFrame:
    """si, draws -> si, shard, ``until`` (draws of the source in this shard and those before it).

    One row holds the vector of a tree node, with as many entries as there are sources.
    """
    node = draws.groupBy().agg(F.array_sort(F.collect_list(F.struct("si", "draws"))).alias("v"))
    node = node.select(F.lit(0).alias("first"), F.lit(shards).alias("width"), F.col("v.si").alias("si"), F.col("v.draws").alias("n"))
    while shards > 1:
        total = F.aggregate("n", F.lit(0).cast("long"), lambda a, x: a + x)
        half = F.floor(F.col("width") / 2).cast("int")
        u_of = lambda i: F.pmod(F.xxhash64(F.lit(seed), F.col("first"), F.col("width"), i), F.lit(1 << 53)).cast("double") / float(1 << 53)
        start = F.struct(F.col("_total").alias("left"), F.col("_take").alias("take"), F.array().cast("array<bigint>").alias("out"))

        def split(s: Column, x: Column) -> Column:
            got = hypergeometric(x["n"], s["left"] - x["n"], s["take"], u_of(x["i"]))
            return _let(got, lambda g: F.struct((s["left"] - x["n"]).alias("left"), (s["take"] - g).alias("take"), F.concat(s["out"], F.array(g)).alias("out")))

        node = node.withColumn("_half", half).withColumn("_total", total).withColumn("_take", F.floor(F.col("_total") * F.col("_half") / F.col("width")).cast("long"))
        halved = F.aggregate(F.transform("n", lambda x, i: F.struct(x.alias("n"), i.alias("i"))), start, split, lambda s: s["out"])
        # One level's plan at a time: the table has one row for each node.
        node = cut(node.withColumn("_left", F.when(F.col("width") > 1, halved).otherwise(F.col("n"))))
        node = node.withColumn("_right", F.zip_with("n", "_left", lambda a, b: a - b))
        one = F.struct(F.col("first"), F.greatest(F.col("_half"), F.lit(1)).alias("width"), F.col("_left").alias("n"))
        two = F.struct((F.col("first") + F.col("_half")).alias("first"), (F.col("width") - F.col("_half")).alias("width"), F.col("_right").alias("n"))
        node = node.select("si", F.explode(F.when(F.col("width") > 1, F.array(one, two)).otherwise(F.array(one))).alias("c")).select("si", "c.*")
        shards = (shards + 1) // 2
    each = node.select(F.col("first").alias("shard"), F.explode(F.arrays_zip("si", "n")).alias("q")).select("shard", "q.si", "q.n")
    upto = Window.partitionBy("si").orderBy("shard").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return each.withColumn("until", F.sum("n").over(upto)).select("si", "shard", "until")


def mix(docs: DataFrame, text: str = "text", source: str = "source", doc_id: str = "doc_id", weights: tuple[int, ...] = WEIGHTS, share: float = SHARE, max_copies: int = MAX_COPIES, block_words: int | None = BLOCK_WORDS, shards: int = SHARDS, seed: int = SEED) -> tuple[DataFrame, DataFrame]:
    """(rows, draws). rows: doc_id, source, size, row, source_size, target, one for each row of docs.
    draws: shard, slot, si, doc_id, source, size, row, block, first_word, n_words, copy.

    A null source is a source of its own, the last; a null text has no words and is never drawn. Rows
    that agree in doc_id, source and size are told apart by ``row``. block_words None: a document
    is one block, so that a mix of whole documents comes out.
    """
    sizes = docs.select(docs[doc_id].alias("doc_id"), docs[source].alias("source"), count_words(docs[text]).alias("size")).groupBy("doc_id", "source", "size").count()
    sizes = cut(sizes)
    targets = cut(source_targets(sizes.select("source", (F.col("size") * F.col("count")).alias("size")), weights, share, max_copies))
    t = targets.withColumnRenamed("source", "_source")
    rows = sizes.select("doc_id", "source", "size", F.explode(F.sequence(F.lit(1).cast("long"), F.col("count"))).alias("row"))
    rows = rows.join(t, rows["source"].eqNullSafe(t["_source"])).drop("_source")
    per = F.lit(block_words).cast("long") if block_words else F.greatest("size", F.lit(1).cast("long"))
    blocks = rows.filter("size > 0").withColumn("_b", per).withColumn("block", F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("size") - 1) / F.col("_b")).cast("long"))))
    blocks = blocks.withColumn("n_words", F.least("_b", F.col("size") - F.col("block") * F.col("_b"))).withColumn("first_word", F.col("block") * F.col("_b")).drop("_b")
    blocks = blocks.withColumn("_key", F.xxhash64(F.lit(seed), "doc_id", "source", "size", "row", "block"))
    placed = range_sums(blocks, [F.col(c) for c in ("si", "_key", "doc_id", "size", "row", "block")], {"_words": F.col("n_words"), "_rank": F.lit(1)}, "si")
    base = F.floor(F.col("target") / F.col("source_size")).cast("long")
    # The rest of the target is a first part of the order; its last block is taken if that comes nearer.
    extra = F.col("_words") + F.col("n_words") / 2 < F.col("target") - base * F.col("source_size")
    quotas = cut(placed.groupBy("si").agg(F.sum(base + F.when(extra, 1).otherwise(0)).cast("long").alias("draws"), F.count("*").alias("_blocks")))
    until = shard_quotas(quotas.select("si", "draws"), shards, seed).groupBy("si").agg(F.array_sort(F.collect_list("until")).alias("_until"))
    per_source = cut(quotas.join(until, "si").select(F.col("si").alias("_si"), "_blocks", "_until"))
    # Draw number k of a source is block k of its order, counted on over further passes; the shards' quotas say which numbers are drawn, and by whom.
    made = placed.join(per_source, F.col("si") == F.col("_si"))
    passes = F.array_max("_until") - F.col("_rank")
    made = made.withColumn("_at", F.explode(F.when(passes > 0, F.sequence(F.col("_rank"), F.array_max("_until") - 1, F.col("_blocks")))))
    drawn = made.withColumn("shard", F.size(F.filter("_until", lambda x: x <= F.col("_at")))).withColumn("copy", F.floor(F.col("_at") / F.col("_blocks")).cast("long"))
    slot = F.xxhash64(F.lit(seed + 1), "shard", "si", "_at")
    return rows, drawn.select("shard", slot.alias("slot"), "si", "doc_id", "source", "size", "row", "block", "first_word", "n_words", "copy")


def taken_words(rows: DataFrame, draws: DataFrame) -> DataFrame:
    """rows with ``taken``, the words that the draws take of each, ``n_draws`` and ``n_shards``, from how many draws and by how many shards."""
    key = ["doc_id", "source", "size", "row"]
    sums = draws.groupBy(*key, "shard").agg(F.sum("n_words").alias("w"), F.count("*").alias("n"))
    sums = sums.groupBy(*key).agg(F.sum("w").alias("taken"), F.sum("n").alias("n_draws"), F.count("*").alias("n_shards")).withColumnsRenamed({k: f"_{k}" for k in key})
    on = [rows[k].eqNullSafe(sums[f"_{k}"]) for k in key]
    counts = {c: F.coalesce(c, F.lit(0).cast("long")) for c in ("taken", "n_draws", "n_shards")}
    return rows.join(sums, on, "left").withColumns(counts).drop(*[f"_{k}" for k in key])


def mixed_documents(docs: DataFrame, text: str = "text", source: str = "source", doc_id: str = "doc_id", **settings) -> DataFrame:
    """The mix as documents: a row of docs for each time that it is drawn whole, with the columns that docs has."""
    rows, draws = mix(docs, text, source, doc_id, **(settings | {"block_words": None}))
    times = draws.groupBy("doc_id", "source", "size", "row").count()
    # Rows that agree in doc_id, source and size share their number of draws as evenly as whole numbers allow; the first take what is left over.
    share = times.groupBy("doc_id", "source", "size").agg(F.sum("count").alias("_n")).withColumnsRenamed({k: f"_{k}" for k in ("doc_id", "source", "size")})
    all_rows = rows.groupBy("doc_id", "source", "size").agg(F.count("*").alias("_m")).withColumnsRenamed({k: f"_{k}" for k in ("doc_id", "source", "size")})
    plan = all_rows.alias("a").join(share.alias("b"), F.col("a._doc_id").eqNullSafe(F.col("b._doc_id")) & F.col("a._source").eqNullSafe(F.col("b._source")) & (F.col("a._size") == F.col("b._size")))
    plan = plan.select("a._doc_id", "a._source", "a._size", F.floor(F.col("_n") / F.col("_m")).cast("int").alias("_each"), (F.col("_n") % F.col("_m")).alias("_over"))
    whole = docs.select(F.struct("*").alias("_doc"), docs[doc_id].alias("_i"), docs[source].alias("_s"), count_words(docs[text]).alias("_z"))
    whole = whole.join(plan, F.col("_i").eqNullSafe(F.col("_doc_id")) & F.col("_s").eqNullSafe(F.col("_source")) & (F.col("_z") == F.col("_size")))
    even = whole.filter("_each > 0").select("_doc", F.explode(F.sequence(F.lit(1), F.col("_each")))).select("_doc.*")
    # Only rows of groups with something left over are ordered; which of equal rows is first makes no difference.
    order = Window.partitionBy("_i", "_s", "_z").orderBy(F.xxhash64("_t"), "_t")
    over = whole.filter("_over > 0").withColumn("_t", F.col("_doc").getField(text)).withColumn("_place", F.row_number().over(order))
    return even.unionByName(over.filter("_place <= _over").select("_doc.*"))


def op6_query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "source")
    return taken_words(*mix(docs)).select("doc_id", "size", "source_size", "target", "taken", "n_draws", "n_shards")
