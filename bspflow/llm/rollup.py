"""Token counts by source, language and tokenizer version, kept up by signed deltas with idempotent commits.

A batch is a table of signed changes: an insert adds a document's count, a delete takes it off, a revision takes the old
count off and adds the new one.  Totals are sums, so a batch folds to one row a group before it is kept, and the order
of batches doesn't matter.  A batch is written to a folder of its own and then entered under its name by an exclusive
create, which one of several writers wins; a name that the ledger has is done and is not applied again, so a batch may be
retried or replayed at will.  An entry that names no folder is of a writer that died in between, and may be taken over.
``compact`` folds committed batches into one base, and lists which it holds.

Defined cases: null source or language is a group of its own; a null count is 0 tokens and still a document; a batch
without rows commits and changes nothing; groups whose documents and tokens are all taken off leave the totals; extra
columns are ignored.
"""

from __future__ import annotations

import uuid

from py4j.protocol import Py4JJavaError
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import exists, remove

GROUP = ("source", "lang", "tokenizer")
_FOLDED = "source string, lang string, tokenizer string, docs long, tokens long"


def signed_changes(before: DataFrame | None, after: DataFrame | None) -> DataFrame:
    """Changes that lead from the counts ``before`` to ``after``; each has doc_id, source, lang, tokenizer, tokens.

    A document that only ``after`` has is an insert, one that only ``before`` has a delete, one whose row differs a
    revision.  Rows that are in both cancel when the batch folds.
    """
    sides = []
    for df, sign in ((before, -1), (after, 1)):
        if df is not None:
            sides.append(df.select(*GROUP, "tokens", F.lit(sign).alias("sign")))
    out = sides[0]
    for more in sides[1:]:
        out = out.unionByName(more)
    return out


def _fold(rows: DataFrame, docs, tokens) -> DataFrame:
    folded = rows.groupBy(*GROUP).agg(F.sum(docs).cast("long").alias("docs"), F.sum(tokens).cast("long").alias("tokens"))
    return folded.where("docs <> 0 OR tokens <> 0")


class Ledger:
    """Committed batches and their totals under ``path``."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")
        hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs
        self._path = hadoop.Path
        self._fs = hadoop.Path(self.path).getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())

    def _names(self, folder: str) -> list[str]:
        where = self._path(f"{self.path}/{folder}")
        return sorted(x.getPath().getName() for x in self._fs.listStatus(where)) if self._fs.exists(where) else []

    def _base(self) -> tuple[str | None, set[str]]:
        """The newest base and the batches it holds."""
        names = self._names("base")
        if not names:
            return None, set()
        base = f"{self.path}/base/{names[-1]}"
        return base, {r.batch for r in self.spark.read.schema("batch string").parquet(f"{base}/batches").collect()}

    def committed(self) -> set[str]:
        """Names of all committed batches."""
        return set(self._entries()) | self._base()[1]

    def commit(self, batch: str, changes: DataFrame) -> bool:
        """Apply a batch of signed changes once; False if it was committed before."""
        if batch in self.committed():
            return False
        tokens = F.coalesce(F.col("tokens"), F.lit(0)) * F.col("sign")
        folder = f"{self.path}/data/{uuid.uuid4().hex}"
        _fold(changes, F.col("sign"), tokens).repartition(1).write.parquet(folder)
        if self._enter(batch, folder):
            return True
        remove(self.spark, folder)
        return False

    def _enter(self, batch: str, folder: str) -> bool:
        """Enter a batch's folder under its name; False if another writer has."""
        entry = self._path(f"{self.path}/batches/{batch}")
        try:
            out = self._fs.create(entry, self._fs.exists(entry) and self._folder(batch) is None)
        except Py4JJavaError as error:
            if "AlreadyExists" in str(error.java_exception):
                return False
            raise
        out.write(bytearray(folder.rsplit("/", 1)[1].encode()))
        out.close()
        return True

    def _folder(self, batch: str) -> str | None:
        """The folder that an entry names."""
        stream = self._fs.open(self._path(f"{self.path}/batches/{batch}"))
        try:
            name = bytes(stream.readAllBytes()).decode()
        finally:
            stream.close()
        return f"{self.path}/data/{name}" if len(name) == 32 else None

    def _entries(self) -> dict[str, str]:
        """Folders of the entered batches."""
        found = {b: self._folder(b) for b in self._names("batches")}
        return {b: folder for b, folder in found.items() if folder}

    def _kept(self) -> DataFrame:
        base, held = self._base()
        paths = [folder for b, folder in self._entries().items() if b not in held]
        paths += [f"{base}/totals"] if base else []
        return self.spark.read.schema(_FOLDED).parquet(*paths) if paths else self.spark.createDataFrame([], _FOLDED)

    def totals(self) -> DataFrame:
        """source, lang, tokenizer, docs, tokens over all committed batches."""
        return _fold(self._kept(), F.col("docs"), F.col("tokens"))

    def compact(self) -> None:
        """Fold what is committed into a new base; old batch folders go once the base is in place."""
        entries, (old, held) = self._entries(), self._base()
        batches = sorted(held | set(entries))
        number = len(self._names("base")) and int(self._names("base")[-1]) + 1
        staged = f"{self.path}/staged/base"
        if exists(self.spark, staged):
            remove(self.spark, staged)
        kept = [folder for b, folder in entries.items() if b not in held] + ([f"{old}/totals"] if old else [])
        rows = self.spark.read.schema(_FOLDED).parquet(*kept) if kept else self.spark.createDataFrame([], _FOLDED)
        _fold(rows, F.col("docs"), F.col("tokens")).repartition(1).write.parquet(f"{staged}/totals")
        self.spark.createDataFrame([(b,) for b in batches], "batch string").coalesce(1).write.parquet(f"{staged}/batches")
        self._fs.mkdirs(self._path(f"{self.path}/base"))
        if not self._fs.rename(self._path(staged), self._path(f"{self.path}/base/{number:08d}")):
            raise RuntimeError("the base could not be committed")
        for b, folder in entries.items():
            remove(self.spark, f"{self.path}/batches/{b}")
            remove(self.spark, folder)
        if old:
            remove(self.spark, old)
