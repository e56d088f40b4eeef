"""Line dedup on levelled sorted runs of line hashes.

Documents come in batches from the largest doc_ids to the smallest. A batch is merge-anti-joined with
the runs: a key that no run has is new, and the largest doc_id of the batch that holds it keeps its
lines; a key that a run has is kept by an earlier, larger doc_id. The batch then adds its own run to
level 0: for each key, sorted, its number of documents and, for new keys, that doc_id. As soon as a
level has ``fanout`` runs they are merged into one run of the next level, so a key is rewritten once a
level. When all batches are in, the runs say which keys stand in enough documents.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from graphwatch.functions.storage import table
from graphwatch.llm.text import ascii_lower, strip, text_or_empty

MIN_CHARS, MIN_DOCS, FANOUT, BATCHES = 20, 3, 4, 6
#: Keys in more than one of so many (key, document) pairs are broadcast: there are at most so many of them.
HOT_KEYS = 10_000
_H = ["h1", "h2"]


def line_key(line: Column) -> Column:
    return ascii_lower(strip(line))


def hashed_lines(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", min_chars: int = MIN_CHARS) -> DataFrame:
    """doc_id, ``th`` (hash of the text), ``at`` (place of the line) and the 128-bit hash of its key, for lines with a long enough key."""
    body = text_or_empty(docs[text])
    lines = docs.select(docs[doc_id].alias("doc_id"), F.xxhash64(body).alias("th"), F.posexplode(F.split(body, "\n")).alias("at", "line"))
    keyed = lines.select("doc_id", "th", "at", line_key(F.col("line")).alias("key")).filter(F.char_length("key") >= min_chars)
    return keyed.select("doc_id", "th", "at", F.xxhash64("key").alias("h1"), F.xxhash64(F.lit(7), "key").alias("h2"))


def _merged(runs: list[DataFrame]) -> DataFrame:
    both = runs[0]
    for r in runs[1:]:
        both = both.unionByName(r)
    return both.groupBy(*_H).agg(F.sum("n_docs").alias("n_docs"), F.max("last_doc").alias("last_doc"))


class LineRuns:
    """Levelled runs in the shared folder: h1, h2, n_docs, last_doc (null but in the run that had the key first).

    Batches must come in falling order of doc_id and not share a document.
    """

    def __init__(self, spark: SparkSession, fanout: int = FANOUT):
        self.spark, self.fanout, self.levels, self.compactions = spark, fanout, [[]], 0

    def _write(self, run: DataFrame) -> DataFrame:
        return table(run.sortWithinPartitions(*_H), "line-run")

    def add(self, lines: DataFrame) -> None:
        """Anti-join the lines of one batch (doc_id, h1, h2) with the runs, add them as a run, and compact full levels."""
        # A key counts once for each document: first the documents of a key, then their number.
        each = lines.filter("doc_id is not null").groupBy(*_H, "doc_id").agg(F.lit(1))
        batch = each.groupBy(*_H).agg(F.count("doc_id").alias("n_docs"), F.max("doc_id").alias("largest"))
        seen = self.merged()
        if seen is None:
            run = batch.select(*_H, "n_docs", F.col("largest").alias("last_doc"))
        else:
            # One merge join gives both sides of the anti-join: keys that no run has, and the others.
            seen = seen.select(F.col("h1").alias("_h1"), F.col("h2").alias("_h2")).hint("merge")
            run = batch.join(seen, (F.col("h1") == F.col("_h1")) & (F.col("h2") == F.col("_h2")), "left")
            run = run.select(*_H, "n_docs", F.when(F.col("_h1").isNull(), F.col("largest")).alias("last_doc"))
        self.levels[0].append(self._write(run))
        level = 0
        while len(self.levels[level]) >= self.fanout:
            if level + 1 == len(self.levels):
                self.levels.append([])
            self.levels[level + 1].append(self._write(_merged(self.levels[level])))
            self.levels[level] = []
            self.compactions += 1
            level += 1

    def merged(self) -> DataFrame | None:
        """All runs as one table: h1, h2, n_docs, last_doc."""
        runs = [r for level in self.levels for r in level]
        return _merged(runs) if runs else None

    def new_lines(self, lines: DataFrame) -> DataFrame:
        """The lines of a batch whose key no run has yet."""
        seen = self.merged()
        return lines if seen is None else lines.join(seen.select(*_H), _H, "left_anti")


def batch_bounds(docs: DataFrame, batches: int) -> list[tuple[int | None, int | None]]:
    """(above, up to) of batches - 1 cuts in doc_id, from the largest doc_ids down; batches of about equal size."""
    shares = [i / batches for i in range(1, batches)]
    cuts = docs.agg(F.percentile_approx("doc_id", shares, 10_000)).first()[0] if shares else []
    cuts = sorted(set(cuts or []), reverse=True)
    return list(zip([*cuts, None], [None, *cuts], strict=True))


def _hits(lines: DataFrame, often: DataFrame) -> DataFrame:
    """The lines whose key is in ``often`` and whose document does not keep them.

    A key of a share of more than 1 / HOT_KEYS of all pairs is hot; by that, there are less than
    HOT_KEYS of them, and they are broadcast, so that no task gets all lines of such a key. The other
    keys are joined by shuffling.
    """
    pairs = often.agg(F.coalesce(F.sum("n_docs"), F.lit(0))).first()[0]
    is_hot = F.col("n_docs") * HOT_KEYS > pairs
    loses = ~F.col("doc_id").eqNullSafe(F.col("last_doc"))
    hot, rest = often.filter(is_hot).select(*_H, "last_doc"), often.filter(~is_hot).select(*_H, "last_doc")
    here = lines.join(F.broadcast(hot), _H).filter(loses).select("doc_id", "th", "at")
    others = lines.join(F.broadcast(hot.select(*_H)), _H, "left_anti").join(rest, _H).filter(loses)
    return here.unionByName(others.select("doc_id", "th", "at"))


def drop_repeated(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", min_chars: int = MIN_CHARS, min_docs: int = MIN_DOCS, batches: int = BATCHES, fanout: int = FANOUT, runs: LineRuns | None = None) -> DataFrame:
    """``_doc`` (all columns of docs), n_lines, n_dropped and ``kept_text``.

    A key of at least min_chars code points that stands in at least min_docs documents keeps its
    lines in the largest doc_id only. A null or empty text is one empty line. A null doc_id counts
    as no document and never is the largest. Rows that share a doc_id are one document. The drops
    of a document are a list of line numbers, so a document is rebuilt without looking lines up.
    ``runs``: where the levels are kept; empty at first.
    """
    runs = runs or LineRuns(docs.sparkSession, fanout)
    lines = table(hashed_lines(docs, text, doc_id, min_chars), "line-hashes")
    for above, upto in batch_bounds(docs.select(docs[doc_id].alias("doc_id")), batches):
        batch = lines
        if above is not None:
            batch = batch.filter(F.col("doc_id") > above)
        if upto is not None:
            batch = batch.filter(F.col("doc_id") <= upto)
        runs.add(batch)
    often = table(runs.merged().filter(F.col("n_docs") >= min_docs), "line-drops")
    drops = _hits(lines, often).groupBy("doc_id", "th").agg(F.collect_set("at").alias("_drops")).withColumnsRenamed({"doc_id": "_id", "th": "_th"})
    body = text_or_empty(docs[text])
    rows = docs.select(F.struct("*").alias("_doc"), docs[doc_id].alias("_own"), body.alias("_text"), F.xxhash64(body).alias("_own_th"))
    rows = rows.join(drops, F.col("_own").eqNullSafe(F.col("_id")) & (F.col("_own_th") == F.col("_th")), "left")
    rows = rows.select("_doc", F.split("_text", "\n").alias("_lines"), "_drops")
    kept = F.when(F.col("_drops").isNull(), F.col("_lines")).otherwise(F.transform(F.array_except(F.sequence(F.lit(0), F.size("_lines") - 1), F.col("_drops")), lambda i: F.get("_lines", i)))
    rows = rows.select("_doc", F.size("_lines").cast("long").alias("n_lines"), kept.alias("_kept"))
    return rows.select("_doc", "n_lines", (F.col("n_lines") - F.size("_kept")).alias("n_dropped"), F.array_join("_kept", "\n").alias("kept_text"))


def op8_query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return drop_repeated(docs).select("_doc.doc_id", "n_lines", "n_dropped", F.sha2(F.col("kept_text").cast("binary"), 256).alias("kept_sha256"))
