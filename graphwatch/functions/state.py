"""State that survives its driver: tables that grow by parts, and a commit for each batch."""

from __future__ import annotations

import json
import uuid

from pyspark.sql import DataFrame, SparkSession


class StateStore:
    """A folder with parts of named tables and ``commits``, one small file for each batch that ended.

    A batch writes its parts under new names; they count once its commit is there. So a batch that died
    half way leaves nothing behind that is read, and a batch that is sent again after its commit is
    known. A commit names all parts, so old ones can be merged and deleted. Any store that Spark writes to will do.
    """

    def __init__(self, spark: SparkSession, path: str, fanout: int = 8):
        self.spark, self.path, self.fanout = spark, path.rstrip("/"), fanout
        self.last = -1
        self.leaving: list[str] = []
        self.parts: dict[str, list[str]] = {}
        self.schemas: dict[str, str] = {}
        self.dropped: list[str] = []
        self.result: list[str] | None = None  # table and part that hold what the last batch gave
        self._fs = spark._jvm.org.apache.hadoop.fs.Path(self.path).getFileSystem(spark._jsc.hadoopConfiguration())
        commits = self._path("commits")
        if self._fs.exists(commits):
            done = [int(x.getPath().getName()) for x in self._fs.listStatus(commits) if x.getPath().getName().isdigit()]
            if done:
                self._load(max(done))

    def _path(self, name: str):
        return self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{name}")

    def _load(self, batch: int) -> None:
        stream = self._fs.open(self._path(f"commits/{batch}"))
        try:
            text = self.spark._jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8")
        finally:
            stream.close()
        made = json.loads(text)
        self.last, self.parts, self.schemas, self.leaving, self.result = batch, made["parts"], made["schemas"], made["leaving"], made["result"]

    def read(self, name: str) -> DataFrame | None:
        """All parts of a table; None if it has none."""
        if not self.parts.get(name):
            return None
        return self.spark.read.schema(self.schemas[name]).parquet(*[f"{self.path}/{p}" for p in self.parts[name]])

    def write(self, name: str, rows: DataFrame) -> DataFrame:
        """Write rows as a further part, which counts from the next commit on, and read it back."""
        part = f"{name}/{uuid.uuid4().hex}"
        rows.write.parquet(f"{self.path}/{part}")
        self.schemas[name] = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields)
        self.parts.setdefault(name, []).append(part)
        return self.spark.read.schema(rows.schema).parquet(f"{self.path}/{part}")

    def keep_result(self, name: str) -> None:
        """What was last written to a table is what this batch gives."""
        self.result = [name, self.parts[name][-1]]

    def read_result(self) -> DataFrame:
        name, part = self.result
        return self.spark.read.schema(self.schemas[name]).parquet(f"{self.path}/{part}")

    def replace(self, name: str, rows: DataFrame) -> None:
        """Put one part in the place of all parts of a table. rows may be made of them."""
        old = list(self.parts.get(name, []))
        self.write(name, rows)
        self.parts[name] = self.parts[name][len(old) :]
        self.dropped += old

    def full(self, name: str) -> bool:
        return len(self.parts.get(name, [])) >= self.fanout

    def commit(self, batch: int) -> None:
        """From here on the batch counts. Parts are deleted one commit after the one that replaced them, so that what a batch gave can be read until the next one ends."""
        stream = self._fs.create(self._path(f"commits/{batch}.tmp"), True)
        try:
            stream.write(bytearray(json.dumps({"parts": self.parts, "schemas": self.schemas, "leaving": self.dropped, "result": self.result}).encode()))
        finally:
            stream.close()
        self._fs.rename(self._path(f"commits/{batch}.tmp"), self._path(f"commits/{batch}"))
        if self.last >= 0 and self.last != batch:
            self._fs.delete(self._path(f"commits/{self.last}"), False)
        self.last = batch
        for part in self.leaving:
            self._fs.delete(self._path(part), True)
        self.leaving, self.dropped = self.dropped, []
