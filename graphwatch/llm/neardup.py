"""Near-duplicate documents: banded MinHash, verified by odd sketches and then on full shingle sets.

* A document's MinHash samples are folded into a parity bitmap (odd sketch): the XOR of two bitmaps
  has few ones exactly if the samples agree in most places, so its population count estimates a
  high similarity. A second parity bitmap of the whole set bounds the symmetric difference from
  below and so rejects, without error, pairs whose difference is too large.
* Documents with equal shingle sets form one class; only its smallest doc_id goes on.
* Classes that share a band are candidates. First every class is compared with the smallest one of
  its buckets: that joins large groups without making their pairs. Then, in buckets that still hold
  more than one component, all pairs across components are compared inside the join, which keeps
  only those that both bitmaps let through. Large buckets are dealt to several tasks; no bucket or
  number of partners is capped.
* Both kinds of pairs are confirmed on full sets, and components of the confirmed links follow.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphwatch.functions.storage import table
from graphwatch.llm.components import connected_components
from graphwatch.llm.workers import trimmed

#: A similarity of 0.85 shares one of 26 bands of 6 samples but for 5 in a million.
BANDS, BAND_ROWS, SEED = 26, 6, 11
#: Longs of the odd sketch and of the set's parity bitmap.
SKETCH_LONGS, PARITY_LONGS = 8, 16
#: The estimate has a standard deviation of 0.03 there; five of them below the threshold are let through.
SLACK = 0.15
#: Words whose hash a worker keeps; then it starts anew. Only speed depends on it.
CACHE_WORDS = 150_000
#: Members of a bucket that one task compares with others; a larger bucket is split.
BUCKET_ROWS = 2000
_SCHEMA = "doc_id long, n_shingles long, k1 long, k2 long, bands array<long>, odd array<long>, parity array<long>"
_M1, _M2, _M3 = (np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0xFF51AFD7ED558CCD))


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * _M3
    x = (x ^ (x >> np.uint64(29))) * _M1
    return x ^ (x >> np.uint64(32))


class WordHash(dict):
    def __missing__(self, word: bytes) -> int:
        import xxhash

        if len(self) >= CACHE_WORDS:
            self.clear()
        got = self[word] = xxhash.xxh64_intdigest(word)
        return got


def shingle_set(hashes: WordHash, text: str | None, width: int) -> np.ndarray:
    """Sorted distinct 64-bit hashes of a text's shingles; a shorter text is one shingle; no words, no shingles."""
    words = text.encode().lower().split() if text else []
    if not words:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(hashes.__getitem__, words), np.uint64, len(words))
    n = max(1, len(words) - width + 1)
    # The number of words goes in, so that a short text does not look like a shingle of a long one.
    out = np.full(n, min(len(words), width), np.uint64)
    for i in range(min(len(words), width)):
        out = _mix(out + h[i : i + n] * _M2)
    return np.unique(out)


def _chunks(batches: Iterator[pa.RecordBatch], width: int) -> Iterator[tuple[list, list[np.ndarray]]]:
    """doc_ids and shingle sets, about half a million shingles at a time."""
    hashes, ids, sets, size = WordHash(), [], [], 0
    for batch in batches:
        for name, body in zip(batch.column(0), batch.column(1), strict=True):
            got = shingle_set(hashes, body.as_py(), width)
            ids.append(name.as_py()), sets.append(got)
            size += len(got)
            if size > 500_000:
                yield ids, sets
                ids, sets, size = [], [], 0
    if ids:
        yield ids, sets


def _lists(rows: np.ndarray) -> pa.Array:
    offsets = np.arange(rows.shape[0] + 1, dtype=np.int32) * rows.shape[1]
    return pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.ascontiguousarray(rows).view(np.int64).ravel()))


def signatures(docs: DataFrame, width: int = 3, bands: int = BANDS, band_rows: int = BAND_ROWS, seed: int = SEED) -> DataFrame:
    """One row for each (doc_id, text) row: set size, 128-bit key of the set, band hashes, odd sketch and the set's parity bitmap."""

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        draw = np.random.default_rng(seed)
        k = bands * band_rows
        odd = draw.integers(0, 2**63, k, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
        xor = draw.integers(0, 2**63, k, dtype=np.uint64)
        place = _mix(np.arange(k, dtype=np.uint64) + np.uint64(1))
        for ids, sets in _chunks(batches, width):
            sizes = np.array([len(s) for s in sets], np.int64)
            some = np.flatnonzero(sizes)
            n = len(ids)
            keys = np.zeros((n, 2), np.uint64)
            band = np.zeros((n, bands), np.uint64)
            sketch = np.zeros((n, SKETCH_LONGS), np.uint64)
            parity = np.zeros((n, PARITY_LONGS), np.uint64)
            if len(some):
                flat = np.concatenate(sets)
                starts = np.concatenate([[0], np.cumsum(sizes[some])[:-1]])
                keys[some, 0] = np.add.reduceat(_mix(flat), starts)
                keys[some, 1] = np.bitwise_xor.reduceat(_mix(flat * _M2), starts)
                low = np.empty((len(some), k), np.uint64)
                for i in range(k):
                    low[:, i] = np.minimum.reduceat((flat ^ xor[i]) * odd[i], starts)
                low = _mix(low)
                h = np.zeros((len(some), bands), np.uint64)
                for r in range(band_rows):
                    h = _mix(h * _M2 + low[:, r::band_rows][:, :bands])
                band[some] = h
                sketch[some] = _parity(_mix(low + place), SKETCH_LONGS)
                owner = np.repeat(np.arange(len(some)), sizes[some])
                parity[some] = _set_parity(flat, owner, len(some), PARITY_LONGS)
            yield pa.RecordBatch.from_arrays(
                [pa.array(ids, pa.int64()), pa.array(sizes), pa.array(keys[:, 0].view(np.int64)), pa.array(keys[:, 1].view(np.int64)), _lists(band), _lists(sketch), _lists(parity)],
                ["doc_id", "n_shingles", "k1", "k2", "bands", "odd", "parity"],
            )

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(trimmed(sign), _SCHEMA)


def _parity(values: np.ndarray, longs: int) -> np.ndarray:
    """A row of values to a bitmap of 64 * longs bits, each value flipping one bit."""
    owner = np.repeat(np.arange(values.shape[0]), values.shape[1])
    return _set_parity(values.ravel(), owner, values.shape[0], longs)


def _set_parity(values: np.ndarray, owner: np.ndarray, n: int, longs: int) -> np.ndarray:
    out = np.empty((n, longs), np.uint64)
    step = max(1, (8 << 20) // (64 * longs))
    bit = (_mix(values) >> np.uint64(20)) % np.uint64(64 * longs)
    cuts = np.searchsorted(owner, np.arange(0, n + step, step))
    for i, (a, b) in enumerate(zip(cuts[:-1], cuts[1:], strict=True)):
        rows = min(step, n - i * step)
        if rows <= 0:
            break
        flips = np.bincount((owner[a:b] - i * step) * (64 * longs) + bit[a:b].astype(np.int64), minlength=rows * 64 * longs) & 1
        out[i * step : i * step + rows] = np.packbits(flips.astype(np.uint8).reshape(rows, -1), axis=1, bitorder="little").view(np.uint64)
    return out


def _ones(a: str, b: str, longs: int) -> Column:
    """Ones in the XOR of two bitmaps."""
    out = F.lit(0)
    for i in range(longs):
        out = out + F.bit_count(F.get(F.col(a), F.lit(i)).bitwiseXOR(F.get(F.col(b), F.lit(i))))
    return out


def similarity_estimate(ones: Column, samples: int, longs: int = SKETCH_LONGS) -> Column:
    """Similarity from the ones in the XOR of two odd sketches: k samples that differ in a share 1 - J flip 2k(1 - J) bits."""
    bits = 64.0 * longs
    return 1 + bits / (4.0 * samples) * F.log(F.greatest(1 - 2.0 * ones / bits, F.lit(1e-9)))


def _close(low: float, samples: int) -> Column:
    """May the pair (columns a_ and b_) reach a similarity of low? Never false for one that does, but for the sampling error of five deviations."""
    small, large = F.least("a_n", "b_n"), F.greatest("a_n", "b_n")
    both = F.col("a_n") + F.col("b_n")
    apart = both * ((1 - low) / (1 + low)) + 1e-6  # at most so many shingles are in only one of two sets
    return (small >= large * low - 1e-6) & (_ones("a_parity", "b_parity", PARITY_LONGS) <= apart) & (similarity_estimate(_ones("a_odd", "b_odd", SKETCH_LONGS), samples) >= low - SLACK)


def _sided(df: DataFrame, side: str) -> DataFrame:
    return df.select(*[F.col(c).alias(f"{side}_{c}") for c in df.columns])


def _keys(s: np.ndarray) -> tuple[int, int]:
    """The 128-bit key of a set."""
    if not len(s):
        return 0, 0
    return tuple(int(x.astype(np.int64)) for x in (np.add.reduce(_mix(s)), np.bitwise_xor.reduce(_mix(s * _M2))))


def confirmed(docs: DataFrame, classes: DataFrame, pairs: DataFrame, percent: int, width: int) -> DataFrame:
    """The pairs (a, b) of ids of classes (k1, k2, id) with 100 * intersection >= percent * union of their full sets."""

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for ids, found in _chunks(batches, width):
            offsets = np.concatenate([[0], np.cumsum([len(s) for s in found])]).astype(np.int32)
            keys = [_keys(s) for s in found]
            arrays = [pa.array(ids, pa.int64()), pa.array([k[0] for k in keys], pa.int64()), pa.array([k[1] for k in keys], pa.int64()), pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate(found).view(np.int64)))]
            yield pa.RecordBatch.from_arrays(arrays, ["id", "k1", "k2", "set"])

    ids = pairs.select(F.explode(F.array("a", "b")).alias("_id")).distinct()
    wanted = classes.join(ids, classes["id"] == ids["_id"]).select("_id", F.col("k1").alias("_k1"), F.col("k2").alias("_k2"))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    full = table(rows.join(ids, rows["doc_id"] == ids["_id"], "left_semi").mapInArrow(trimmed(sets), "id long, k1 long, k2 long, set array<long>"), "dup-sets")
    # Of rows that share an id, those with the set that stands for it.
    full = full.join(wanted, (F.col("id") == F.col("_id")) & (F.col("k1") == F.col("_k1")) & (F.col("k2") == F.col("_k2")), "left_semi").dropDuplicates(["id"])
    full = table(full.select("id", "set"), "dup-full")
    one, two = full.select(F.col("id").alias("a"), F.col("set").alias("s")), full.select(F.col("id").alias("b"), F.col("set").alias("t"))
    both = F.size(F.array_intersect("s", "t")).cast("long")
    either = F.size("s").cast("long") + F.size("t") - both
    return pairs.join(one, "a").join(two, "b").filter(100 * both >= percent * either).select("a", "b")


def near_duplicates(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", percent: int = 85, width: int = 3, bands: int = BANDS, band_rows: int = BAND_ROWS) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for each row of docs.

    A document without words is linked with nothing. A row with a null doc_id cannot be named: its
    component_id is null and it is kept. Rows that share a doc_id are one document, with the
    set of the least key among theirs: they get the same result, and all of them are kept or none.
    """
    rows = docs.select(docs[doc_id].cast("long").alias("doc_id"), docs[text].cast("string").alias("text"))
    signed = table(signatures(rows, width, bands, band_rows), "dup-signatures")
    samples, low = bands * band_rows, percent / 100
    one_each = signed.filter("doc_id is not null").groupBy("doc_id").agg(F.min(F.struct("k1", "k2", "n_shingles")).alias("s"), F.count("*").alias("rows"))
    one_each = table(one_each.select("doc_id", "s.*", "rows"), "dup-documents")
    classes = table(one_each.filter("n_shingles > 0").groupBy("k1", "k2").agg(F.min("doc_id").alias("id")), "dup-classes")
    own = classes.select("id", F.col("k1").alias("_k1"), F.col("k2").alias("_k2"))
    firsts = signed.join(own, (F.col("doc_id") == F.col("id")) & (F.col("k1") == F.col("_k1")) & (F.col("k2") == F.col("_k2")), "left_semi")
    firsts = firsts.select(F.col("doc_id").alias("id"), F.col("n_shingles").alias("n"), "bands", "odd", "parity").dropDuplicates(["id"])
    firsts = table(firsts, "dup-firsts")
    sketch = firsts.select("id", "n", "odd", "parity")
    buckets = firsts.select("id", F.posexplode("bands").alias("band", "h")).select("id", F.xxhash64("band", "h").alias("bucket"))
    heads = table(buckets.groupBy("bucket").agg(F.min("id").alias("head"), F.count("*").alias("n")).filter("n > 1").select("bucket", "head"), "dup-heads")
    full = table(buckets.join(heads, "bucket").select("bucket", "id", "head"), "dup-buckets")
    stars = full.filter("id <> head").select(F.col("head").alias("a"), F.col("id").alias("b")).distinct()
    stars = stars.join(_sided(sketch, "a"), F.col("a") == F.col("a_id")).join(_sided(sketch, "b"), F.col("b") == F.col("b_id"))
    stars = table(stars.filter(_close(low, samples)).select("a", "b"), "dup-stars")
    links = table(confirmed(rows, classes, stars, percent, width), "dup-links")
    parts = table(connected_components(links), "dup-parts")
    # Buckets that hold more than one component yet: their members, with what the comparison needs.
    placed = table(full.join(parts.withColumnRenamed("id", "_i"), F.col("id") == F.col("_i"), "left").select("bucket", "id", F.coalesce("component", "id").alias("part")), "dup-placed")
    mixed = table(placed.groupBy("bucket").agg(F.min("part").alias("x"), F.max("part").alias("y"), F.count("*").alias("n")).filter("x <> y").select("bucket", F.ceil(F.col("n") / BUCKET_ROWS).cast("int").alias("salts")), "dup-mixed")
    open_ = placed.join(mixed, "bucket").join(sketch.withColumnRenamed("id", "_i"), F.col("id") == F.col("_i")).drop("_i")
    open_ = table(open_, "dup-open")
    # A large bucket is dealt to several tasks: one side by a hash, the other side to all of them.
    one = _sided(open_.withColumn("salt", F.explode(F.sequence(F.lit(0), F.col("salts") - 1))), "a")
    two = _sided(open_.withColumn("salt", F.pmod(F.xxhash64("id"), F.col("salts")).cast("int")), "b")
    across = one.join(two, (F.col("a_bucket") == F.col("b_bucket")) & (F.col("a_salt") == F.col("b_salt")) & (F.col("a_id") < F.col("b_id")) & (F.col("a_part") != F.col("b_part")) & _close(low, samples))
    across = table(across.select(F.col("a_id").alias("a"), F.col("b_id").alias("b")).distinct(), "dup-across")
    late = confirmed(rows, classes, across, percent, width)
    parts = table(connected_components(links.unionByName(late)), "dup-components")
    # From class representatives to all members, by the key of their set.
    named_parts = classes.join(parts.withColumnRenamed("id", "_i"), F.col("id") == F.col("_i"), "left").select(F.col("k1").alias("_k1"), F.col("k2").alias("_k2"), F.coalesce("component", "id").alias("c"))
    out = one_each.withColumn("_k", F.when(F.col("n_shingles") > 0, F.col("k1"))).join(table(named_parts, "dup-members"), (F.col("_k") == F.col("_k1")) & (F.col("k2") == F.col("_k2")), "left")
    out = out.select("doc_id", "n_shingles", F.coalesce("c", "doc_id").alias("component_id"), F.explode(F.sequence(F.lit(1).cast("long"), F.col("rows"))).alias("_r"))
    out = out.select("doc_id", "n_shingles", "component_id", (F.col("doc_id") == F.col("component_id")).alias("kept"))
    unnamed = signed.filter("doc_id is null").select("doc_id", "n_shingles", F.lit(None).cast("long").alias("component_id"), F.lit(True).alias("kept"))
    return out.unionByName(unnamed)


def drop_near_duplicates(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", **settings) -> DataFrame:
    """docs without the documents that are not the first of their component; columns as they were."""
    gone = near_duplicates(docs, text, doc_id, **settings).filter(~F.col("kept")).select(F.col("doc_id").alias("_gone")).distinct()
    rows = docs.select(F.struct("*").alias("_doc"), docs[doc_id].cast("long").alias("_id"))
    return rows.join(gone, F.col("_id") == F.col("_gone"), "left_anti").select("_doc.*")


def op1_query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return near_duplicates(docs)
