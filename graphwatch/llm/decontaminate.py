"""Benchmark decontamination by spaced seeds, in SQL functions alone.

A mask picks some of the words of a short span and ignores the others. The hashes of the picked
words are looked up at every place of every text, so a substituted word hides a passage only from
the masks that pick it. All hits of a text and an item on one diagonal are one candidate, and text and
item are compared word by word along the whole of it; the best stretch with at least ``similarity``
equal words decides. Items too short for the masks are looked up whole.

Inside the projection, words and hashes are tested against bitmaps of fixed size, which let through
all true hits and few others; only those become rows and are joined with the test hashes.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphwatch.functions.storage import table
from graphwatch.llm.text import once, text_or_empty, words

#: Places that each mask picks; five words each.
MASKS = ((0, 1, 2, 4, 5), (0, 1, 3, 5, 6), (0, 2, 3, 6, 7))
#: An overlap is a stretch with this share of equal words, of which there are as many as half of the item, but at
#: least 8 (or the whole item, if it is shorter), and never more than 64: a passage of that length is one in any item.
MIN_WORDS, LONG_WORDS, SIMILARITY, SHARE = 8, 64, 0.8, 0.5
#: Texts with candidates that are broadcast at most, for their second reading.
BROADCAST_TEXTS = 200_000
#: A test set of at most so many words is broadcast; a larger one is joined by shuffling.
BROADCAST_WORDS = 300_000
#: Bytes of the bitmap of test hashes, and longs of that of test words, at least and at most.
BITMAP_BYTES = (1 << 13, 1 << 20)
WORD_LONGS = (1 << 8, 1 << 12)
_EDGE = ".,;:!?\"'()[]{}*#"


def word_hashes(text: Column) -> Column:
    """Hashes of the words of a text, lower-cased, without punctuation at their ends."""
    return F.transform(words(F.lower(text)), lambda w: F.xxhash64(F.btrim(w, F.lit(_EDGE))))


def _seed(h: str, at: Column, mask: tuple[int, ...]) -> Column:
    return F.xxhash64(F.lit(",".join(map(str, mask))), *[F.get(F.col(h), at + p if p else at) for p in mask])


def _places(h: str, mask: tuple[int, ...]) -> Column:
    last = F.size(h) - (mask[-1] + 1)
    return F.when(last >= 0, F.sequence(F.lit(0), last)).otherwise(F.array().cast("array<int>"))


def masks_for(lengths: list[int]) -> list[tuple[int, ...]]:
    """The masks, and for each number of words of an item that is too short to be found by all of them, or to lose a word, all its words."""
    return [*MASKS, *(tuple(range(n)) for n in sorted(set(lengths)) if 0 < n < MIN_WORDS)]


def test_seeds(benchmark: DataFrame, text: str = "text", item_id: str = "item_id") -> tuple[DataFrame, DataFrame, list[tuple[int, ...]]]:
    """(items: item_id, item; seeds: seed, item_id, q, n; masks). Items without words match nothing."""
    items = benchmark.select(benchmark[item_id].alias("item_id"), word_hashes(text_or_empty(benchmark[text])).alias("item")).filter("item_id is not null").dropDuplicates(["item_id", "item"])
    items = table(items, "bench-items")
    short = items.filter(F.size("item") < MIN_WORDS).select(F.size("item").alias("n")).distinct().collect()
    masks, seeds = masks_for([r.n for r in short]), None
    for m in masks:
        whole = len(m) < MIN_WORDS and m == tuple(range(len(m)))
        rows = items.filter(F.size("item") == len(m) if whole else F.size("item") >= MIN_WORDS)
        own = rows.select("item_id", F.size("item").alias("n"), "item", F.explode(_places("item", m)).alias("q")).select(_seed("item", F.col("q"), m).alias("seed"), "item_id", "q", "n")
        seeds = own if seeds is None else seeds.unionByName(own)
    return items, table(seeds, "bench-seeds"), masks


def _byte_and_bit(seed: Column, size: int) -> tuple[Column, Column]:
    return seed.bitwiseAND(size - 1).cast("int"), F.call_function("shiftrightunsigned", seed, F.lit(33)).bitwiseAND((1 << 30) - 1) % 7


def _bitmap(seeds: DataFrame, size: int) -> Column:
    """A binary literal in which each seed has set one bit, seven to a byte; its size is bounded, whatever the test set's is."""
    byte, bit = _byte_and_bit(F.col("seed"), size)
    rows = seeds.select(byte.alias("i"), F.call_function("shiftleft", F.lit(1), bit.cast("int")).alias("b")).groupBy("i").agg(F.bit_or("b").alias("b")).collect()
    made = bytearray(size)
    for r in rows:
        made[r.i] = r.b
    return F.lit(bytes(made))


def _in_bitmap(bitmap: Column, seed: Column, size: int) -> Column:
    byte, bit = _byte_and_bit(seed, size)
    have = F.ascii(F.call_function("substring", bitmap, byte + 1, F.lit(1)).cast("string"))
    return F.call_function("shiftright", have, bit.cast("int")).bitwiseAND(1) == 1


def _known_words(items: DataFrame, longs: int) -> Column:
    """A literal array of longs in which each word of the test set has set one bit."""
    word = items.select(F.explode("item").alias("w"))
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), F.col("w").bitwiseAND(63).cast("int"))
    rows = word.select(F.call_function("shiftrightunsigned", "w", F.lit(6)).bitwiseAND(longs - 1).alias("i"), bit.alias("b")).groupBy("i").agg(F.bit_or("b").alias("b")).collect()
    have = {r.i: r.b for r in rows}
    # Parsed once, by the optimizer: as an array of literals, each would be a node of the plan.
    return F.from_json(F.lit("[" + ",".join(str(have.get(i, 0)) for i in range(longs)) + "]"), "array<bigint>")


def _if_known(bits: Column, w: Column, longs: int) -> Column:
    """The hash, or 0 for a word that the test set does not have."""
    long = F.get(bits, F.call_function("shiftrightunsigned", w, F.lit(6)).bitwiseAND(longs - 1).cast("int"))
    return F.when(F.call_function("shiftrightunsigned", long, w.bitwiseAND(63).cast("int")).bitwiseAND(1) == 1, w).otherwise(F.lit(0).cast("long"))


def contamination(docs: DataFrame, benchmark: DataFrame, text: str = "text", doc_id: str = "doc_id", bench_text: str = "text", item_id: str = "item_id") -> DataFrame:
    """doc_id, item_id, item_words, matched_words, first_word: one row for each document and item that overlap.

    matched_words: most equal words of one stretch; first_word: where the item would begin in that
    text, the first such place of those with most. Null texts have no words; rows with a null doc_id or item_id are left out, since a pair
    could not name them; rows that share a doc_id are one document. Empty tables give an empty result.
    """
    items, seeds, masks = test_seeds(benchmark, bench_text, item_id)
    n_words = items.agg(F.coalesce(F.sum(F.size("item")), F.lit(0))).first()[0]
    sized = F.broadcast if n_words <= BROADCAST_WORDS else (lambda df: df)
    size = BITMAP_BYTES[0]
    while size < BITMAP_BYTES[1] and size < 2 * n_words * len(masks):
        size *= 2
    bitmap = _bitmap(seeds, size)
    longs = WORD_LONGS[0]
    while longs < WORD_LONGS[1] and 2 * longs < n_words:
        longs *= 2
    known = _known_words(items, longs)
    hashed = docs.filter(docs[doc_id].isNotNull()).select(docs[doc_id].alias("doc_id"), once(word_hashes(text_or_empty(docs[text]))).alias("h"))
    rows = hashed.select("doc_id", once(F.transform("h", lambda w: _if_known(known, w, longs))).alias("h"))

    def found(mask: tuple[int, ...]) -> Column:
        def may(i: Column) -> Column:
            """All picked words are words of the test set, and so is their hash one of its hashes."""
            words_known = [F.get("h", i + p if p else i) != 0 for p in mask]
            return reduce(lambda a, b: a & b, words_known) & _in_bitmap(bitmap, _seed("h", i, mask), size)

        return F.transform(F.filter(_places("h", mask), may), lambda i: F.struct(_seed("h", i, mask).alias("seed"), i.alias("p")))

    hits = rows.select("doc_id", F.explode(once(F.concat(*map(found, masks)))).alias("x")).select("doc_id", "x.*")
    # One candidate for each diagonal, however many hits it has; then one row for each text that has any.
    lines = hits.join(sized(seeds), "seed").select("doc_id", "item_id", "n", (F.col("p") - F.col("q")).alias("begin")).distinct()
    texts = table(lines.groupBy("doc_id").agg(F.collect_list(F.struct("item_id", "n", "begin")).alias("lines")), "bench-candidates")
    few = F.broadcast if texts.count() <= BROADCAST_TEXTS else (lambda df: df)
    again = hashed.join(few(texts.withColumnRenamed("doc_id", "_id")), F.col("doc_id") == F.col("_id"))
    # A candidate carries the words that lie along the item, not the text.
    along = F.transform("lines", lambda x: F.struct(x["item_id"].alias("item_id"), x["begin"].alias("begin"), F.slice("h", F.greatest(x["begin"], F.lit(0)) + 1, F.greatest(x["n"] + F.least(x["begin"], F.lit(0)), F.lit(0))).alias("w")))
    pairs = again.select("doc_id", F.explode(along).alias("x")).select("doc_id", "x.*").join(sized(items), "item_id")
    skipped = F.greatest(-F.col("begin"), F.lit(0))  # words of the item before the text's first
    equal = F.zip_with(F.slice("item", skipped + 1, F.size("w")), "w", lambda a, b: F.coalesce(a == b, F.lit(False)))
    # Best stretch: an equal word adds 1, another takes off so much that the stretch stays similar enough.
    off = int(round(SIMILARITY / (1 - SIMILARITY)))
    start = F.struct(*[F.lit(0).alias(c) for c in ("score", "same", "best", "matched")])

    def step(s: Column, e: Column) -> Column:
        fresh = s["score"] <= 0
        score = F.when(e, F.greatest(s["score"], F.lit(0)) + 1).otherwise(s["score"] - off)
        same = F.when(fresh, F.lit(0)).otherwise(s["same"]) + F.when(e, 1).otherwise(0)
        better = score > s["best"]
        return F.struct(score.alias("score"), same.alias("same"), F.when(better, score).otherwise(s["best"]).alias("best"), F.when(better, same).otherwise(s["matched"]).alias("matched"))

    matched = F.aggregate(equal, start, step, lambda s: s["matched"])
    pairs = pairs.select("doc_id", "item_id", F.size("item").cast("long").alias("item_words"), F.col("begin").cast("long").alias("first_word"), matched.cast("long").alias("matched_words"))
    needed = F.least(F.greatest(F.lit(MIN_WORDS), F.ceil(F.col("item_words") * SHARE)), F.lit(LONG_WORDS), F.col("item_words"))
    pairs = pairs.filter(F.col("matched_words") >= needed)
    best = F.max(F.struct("matched_words", (-F.col("first_word")).alias("b"), "item_words")).alias("m")
    return pairs.groupBy("doc_id", "item_id").agg(best).select("doc_id", "item_id", "m.item_words", "m.matched_words", (-F.col("m.b")).alias("first_word"))


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """docs without the documents that overlap with an item; columns as they were."""
    gone = contamination(docs, benchmark, text, doc_id).select(F.col("doc_id").alias("_gone")).distinct()
    rows = docs.select(F.struct("*").alias("_doc"), docs[doc_id].alias("_id"))
    return rows.join(gone, F.col("_id") == F.col("_gone"), "left_anti").select("_doc.*")


def op3_query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return contamination(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet").select("item_id", "text"))
