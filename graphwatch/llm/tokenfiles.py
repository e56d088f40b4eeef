"""Token ids as Parquet list columns, in ascending doc_id order.

The columns are shard, doc_id, n_tokens, local_start (ids of the shard before the document) and
tokens (list of int). Token ids are dictionary encoded and fall back to delta encoding, the other
columns are delta encoded; row groups and pages are bounded and carry page indexes, so that a
reader can take the metadata alone or the tokens of a range of documents. Spark's own writer makes
the files, so any store works and a lost task is done again.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graphwatch.functions.storage import scratch_path

END_ID = 1
#: Parquet writer settings: rows sorted by doc_id, row groups of 32 MB, pages of 64 KB.
WRITER = {
    "compression": "zstd",
    "parquet.writer.version": "v2",
    "parquet.block.size": str(32 << 20),
    "parquet.page.size": str(64 << 10),
    "parquet.page.row.count.limit": "2000",
    "parquet.enable.dictionary": "true",
    "parquet.enable.dictionary#doc_id": "false",
    "parquet.enable.dictionary#local_start": "false",
}
_SCHEMA = "shard int, doc_id long, n_tokens int, local_start long, tokens array<int>"
#: Distinct words of which a worker keeps the ids; then it starts anew. Only speed depends on it.
CACHE_WORDS = 600_000
#: Letters and marks on which all Unicode versions agree, so that a word of these alone is normalised here.
_PLAIN = re.compile(r"[!-~À-ÖØ-öø-ÿ]+")
#: Marks that often end a word.
_ENDS = frozenset(b".,;:!?")
_PIECE = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[^\W\d_]+|[0-9]|(?:[^\s\w]|_)+")


@lru_cache(1)
def _byte_chars() -> list[str]:
    """The printable stand-in that byte-level models have for each byte."""
    shown = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
    hidden = [b for b in range(256) if b not in set(shown)]
    table = {b: chr(b) for b in shown} | {b: chr(256 + i) for i, b in enumerate(hidden)}
    return [table[b] for b in range(256)]


class _Packed(dict):
    """Id -> little-endian unsigned 32-bit integer."""

    def __missing__(self, i: int) -> bytes:
        got = self[i] = i.to_bytes(4, "little")
        return got


class WordIds(dict):
    """Word (bytes without white space) -> its ids as little-endian unsigned 32-bit integers.

    The tokenizer drops white space and never looks across it, so a text's ids are those of its
    words, one after the other; a word is encoded once.
    """

    def __init__(self, path: str):
        super().__init__()
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.model = self.tokenizer.model
        self.pieces: dict[str, bytes] = {}
        #: Each id as bytes, and the printable stand-ins by byte.
        self.packed = _Packed()
        self.shown = dict(enumerate(_byte_chars()))
        # The short way is taken only with the normaliser and splitter that it stands for.
        import json

        made = json.loads(self.tokenizer.to_str())
        self.short = (
            [x.get("type") for x in (made.get("normalizer") or {}).get("normalizers", [])] == ["NFC", "Replace", "Lowercase"]
            and [x.get("type") for x in (made.get("pre_tokenizer") or {}).get("pretokenizers", [])] == ["Split", "ByteLevel"]
        )
        self.special = [x["content"] for x in made.get("added_tokens", [])]

    def _whole(self, word: str) -> bytes:
        return np.array(self.tokenizer.encode(word, add_special_tokens=False).ids, "<u4").tobytes()

    def _piece(self, piece: str) -> bytes:
        got = self.pieces.get(piece)
        if got is None:
            mapped = piece if piece.isascii() else piece.encode().decode("latin-1").translate(self.shown)
            got = self.pieces[piece] = b"".join([self.packed[t.id] for t in self.model.tokenize(mapped)])
        return got

    def __missing__(self, word: bytes) -> bytes:
        if self.short and word.isalpha():
            # Most words: letters, and perhaps one mark at the end; nothing to normalise or to split. For bytes, isalpha holds for ASCII letters alone.
            got = self._piece(word.lower().decode())
        elif self.short and word[:-1].isalpha() and word[-1] in _ENDS:
            got = self._piece(word[:-1].lower().decode()) + self._piece(chr(word[-1]))
        else:
            text = word.decode()
            # The letters of _PLAIN are composed, so that NFC leaves them as they are.
            if self.short and _PLAIN.fullmatch(text) and not ("<" in text and any(s in text for s in self.special)):
                got = b"".join(map(self._piece, _PIECE.findall(text.lower())))
            else:
                got = self._whole(text)
        if len(self) >= CACHE_WORDS:
            self.clear()
        if len(self.pieces) >= CACHE_WORDS:
            self.pieces.clear()
        self[word] = got
        return got


@lru_cache(1)
def word_ids(path: str) -> WordIds:
    """One for each worker process, which runs many tasks."""
    return WordIds(path)


def encode_text(ids: WordIds, text: str | None) -> bytes:
    """All ids of a text, without the end id. Null is empty."""
    return b"".join(map(ids.__getitem__, text.encode().split())) if text else b""


def encode_documents(docs: DataFrame, tokenizer: str, text: str = "text", doc_id: str = "doc_id", end_id: int = END_ID) -> DataFrame:
    """The rows of the file format: documents range-partitioned and sorted by doc_id, then encoded in that order.

    Null doc_ids come first; rows that share a doc_id follow one another by text. Texts are dealt
    before they are encoded, so the sampling of the ranges encodes nothing.
    """

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, end, start, shard = word_ids(tokenizer), np.array([end_id], "<u4").tobytes(), 0, TaskContext.get().partitionId()
        names, starts, parts, size = [], [], [], 0

        def made():
            flat = np.frombuffer(b"".join(parts), "<i4")
            lengths = np.array([len(p) // 4 for p in parts], np.int32)
            offsets = np.concatenate([[0], np.cumsum(lengths)]).astype(np.int32)
            arrays = [pa.array(np.full(len(parts), shard, np.int32)), pa.array(names, pa.int64()), pa.array(lengths), pa.array(starts, pa.int64()), pa.ListArray.from_arrays(pa.array(offsets), pa.array(flat))]
            return pa.RecordBatch.from_arrays(arrays, ["shard", "doc_id", "n_tokens", "local_start", "tokens"])

        for batch in batches:
            for name, body in zip(batch.column(0), batch.column(1), strict=True):
                got = encode_text(ids, body.as_py()) + end
                names.append(name.as_py()), starts.append(start), parts.append(got)
                start += len(got) // 4
                size += len(got)
                if size > 8 << 20:
                    yield made()
                    names, starts, parts, size = [], [], [], 0
        if parts:
            yield made()

    rows = docs.select(docs[doc_id].alias("doc_id"), docs[text].alias("text"))
    return rows.repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text").mapInArrow(encode, _SCHEMA)


def write_tokens(docs: DataFrame, path: str, tokenizer: str, **names) -> None:
    encode_documents(docs, tokenizer, **names).write.options(**WRITER).parquet(path)


def read_tokens(spark: SparkSession, path: str) -> DataFrame:
    """The files; select columns and filter doc_id to read only those pages."""
    return spark.read.schema(_SCHEMA).parquet(path)


def token_digest(tokens: DataFrame) -> DataFrame:
    """doc_id, start (ids of all documents before it), n_tokens, ids_crc32, from the rows of the files."""

    def digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lists = batch.column(4)
            flat, offsets = np.asarray(lists.values).astype("<u4"), np.asarray(lists.offsets)
            sums = [zlib.crc32(flat[a:b]) for a, b in zip(offsets[:-1], offsets[1:], strict=True)]
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(4)), pa.array(sums, pa.int64())], ["shard", "doc_id", "n_tokens", "local_start", "ids_crc32"])

    each = tokens.mapInArrow(digest, "shard int, doc_id long, n_tokens int, local_start long, ids_crc32 long")
    # One row for each shard: the window sees as many rows as there are files.
    shards = tokens.groupBy("shard").agg(F.sum("n_tokens").alias("_n"))
    before = Window.partitionBy(F.lit(0)).orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    shards = shards.select("shard", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_before"))
    return each.join(shards, "shard").select("doc_id", (F.col("_before") + F.col("local_start")).alias("start"), F.col("n_tokens").cast("long").alias("n_tokens"), "ids_crc32")


def op4_query(spark, sf_dir: str) -> DataFrame:
    import public_tokenizers

    path = scratch_path(spark, "tokens")
    write_tokens(spark.read.parquet(f"{sf_dir}/documents.parquet"), path, public_tokenizers.path("word_bpe_49k.json"))
    return token_digest(read_tokens(spark, path))
