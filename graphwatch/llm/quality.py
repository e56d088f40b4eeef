"""Quality rules: a table of thresholds compiled into one projection of built-in functions."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphwatch.llm.text import once, strip, text_or_empty, words


@dataclass(frozen=True)
class Rule:
    """A document passes if low <= measure <= high; None leaves that side open."""

    measure: str
    low: float | None = None
    high: float | None = None


#: Length, symbol, stop-word and line rules. Each can be left out or replaced.
RULES = (
    Rule("n_words", 50, None),
    Rule("repeat_ratio", None, 0.5),
    Rule("mean_word_chars", 2.5, 12.0),
    Rule("symbols_per_word", None, 0.1),
    Rule("stop_words", 2, None),
    Rule("dup_line_ratio", None, 0.5),
)
#: Frequent function words of the languages that the rules know.
STOP_WORDS = (
    "the and of to in that is with for be was it on as by from this are or an"
    " le la les de des et un une que qui dans pour est en du"
    " der die das und ein eine ist von mit zu den auf nicht"
    " el los las y con no se por para una del"
).split()


def _measures(docs: DataFrame, text: str) -> DataFrame:
    """All columns of docs as a struct ``_doc`` and the measures; each step is one projection that uses the last one's arrays."""
    n = F.size("_words")
    lines = F.filter(F.split("_text", "\n"), lambda x: strip(x) != "")
    base = docs.select(F.struct("*").alias("_doc"), text_or_empty(docs[text]).alias("_text"))
    base = base.select("_doc", "_text", words(F.col("_text")).alias("_words"), lines.alias("_lines"))
    # A window's hash and its place share one long, so that sorting longs brings equal windows together.
    window_at = lambda i: F.xxhash64(F.get("_words", i), F.get("_words", i + 1), F.get("_words", i + 2))
    shift = F.ceil(F.log2(n + 1)).cast("int")
    base = base.select(
        "_doc",
        "_words",
        n.cast("long").alias("n_words"),
        F.aggregate("_words", F.lit(0).cast("long"), lambda a, w: a + F.char_length(w)).alias("word_chars"),
        F.regexp_count("_text", F.lit(r"[#*$%&|<>]")).cast("long").alias("n_symbols"),
        F.size("_lines").cast("long").alias("n_lines"),
        (F.size("_lines") - F.size(F.array_distinct("_lines"))).cast("long").alias("n_dup_lines"),
        F.size(F.array_intersect(F.transform("_words", F.lower), F.array(*map(F.lit, STOP_WORDS)))).cast("long").alias("stop_words"),
        shift.alias("_shift"),
        F.when(n >= 3, F.sort_array(F.transform(F.sequence(F.lit(0), n - 3), lambda i: F.call_function("shiftleft", window_at(i), shift).bitwiseOR(i.cast("long"))))).alias("_keys"),
    )
    place = lambda k: k.bitwiseAND(F.call_function("shiftleft", F.lit(1).cast("long"), F.col("_shift")) - 1).cast("int")
    hashed = lambda k: F.call_function("shiftrightunsigned", k, F.col("_shift"))

    def same(k: Column, other: Column) -> Column:
        """The hashes agree and so do the words."""
        i, j = place(k), place(other)
        return (hashed(k) == hashed(other)) & (F.get("_words", i) == F.get("_words", j)) & (F.get("_words", i + 1) == F.get("_words", j + 1)) & (F.get("_words", i + 2) == F.get("_words", j + 2))

    near = lambda k, other: F.call_function("shiftrightunsigned", k.bitwiseXOR(other), F.col("_shift")) == 0
    base = base.withColumn("_keys", F.filter("_keys", lambda k, j: near(k, F.get("_keys", j + 1)) | near(k, F.get("_keys", j - 1))))
    twice = F.filter("_keys", lambda k, j: F.coalesce(same(k, F.get("_keys", j + 1)), F.lit(False)) | F.coalesce(same(k, F.get("_keys", j - 1)), F.lit(False)))
    base = base.withColumn("_places", F.sort_array(F.transform(twice, place)))
    # A repeated window covers three words, less those that the next one covers too.
    covered = F.aggregate(F.transform("_places", lambda p, j: F.coalesce(F.least(F.get("_places", j + 1) - p, F.lit(3)), F.lit(3))), F.lit(0).cast("long"), lambda a, x: a + x)
    base = base.withColumn("n_repeat_words", F.coalesce(covered, F.lit(0)).cast("long"))
    per = lambda x, y: F.when(F.col(y) > 0, F.col(x) / F.col(y)).otherwise(F.lit(0.0))
    return base.select(
        "_doc",
        *"n_words word_chars n_symbols n_dup_lines n_repeat_words n_lines stop_words".split(),
        per("n_repeat_words", "n_words").alias("repeat_ratio"),
        per("word_chars", "n_words").alias("mean_word_chars"),
        per("n_symbols", "n_words").alias("symbols_per_word"),
        per("n_dup_lines", "n_lines").alias("dup_line_ratio"),
    )


def compiled(rules: tuple[Rule, ...]) -> list[tuple[str, Column]]:
    """(name, does the document break the rule) for each threshold."""
    out = []
    for r in rules:
        if r.low is not None:
            out.append((f"{r.measure}<{r.low:g}", F.col(r.measure) < F.lit(r.low)))
        if r.high is not None:
            out.append((f"{r.measure}>{r.high:g}", F.col(r.measure) > F.lit(r.high)))
    return out


def judge(docs: DataFrame, text: str = "text", rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """``_doc`` (all columns of docs, so that none can clash), the measures, base_failed, ``broken`` (names of the broken rules) and kept.

    A null or blank text has no words and fails. Rows are judged one by one: repeated rows get
    the same verdict each, an empty table gives an empty result. There is no shuffle.
    """
    seen = _measures(docs, text)
    broken = F.filter(F.array(*[F.when(c, F.lit(n)) for n, c in compiled(rules)]), lambda x: x.isNotNull())
    # Whole numbers decide, so that no rounding does.
    failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    seen = seen.withColumn("base_failed", failed).withColumn("broken", broken)
    return seen.withColumn("kept", ~F.col("base_failed") & (F.size("broken") == 0))


def keep_good(docs: DataFrame, text: str = "text", rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """The documents that break no rule, with the columns they had."""
    # The filter must stay above the projection: below it, the arrays would be computed again for each use.
    return judge(docs, text, rules).select("_doc", once(F.col("kept")).alias("_kept")).filter("_kept").select("_doc.*")


def op10_query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    names = "n_words word_chars n_symbols n_dup_lines n_repeat_words base_failed kept".split()
    return judge(docs.select("doc_id", "text")).select("_doc.doc_id", *names)
