"""Token counts as delta-maintained rollups.

Tokens are counted by the vocabulary files of public tokenizers, whose names are the versions. A change is
signed: an insert adds a document and its tokens, a delete takes them away, a revision takes away the old
count and adds the new one. A batch of changes is aggregated before it is stored, so what is kept grows with
groups, not documents. Totals by source, language and tokenizer version are the sum over the committed batches.

A commit writes the folder of its batch id anew, so a batch applied twice (or again
after a lost driver) counts once; half-written folders carry no success mark and are not
read. ``compact`` folds the batches it found at its start into one snapshot that names what it holds;
batches that commit meanwhile stay apart.

Null source, language or version form groups of their own; null texts and counts are 0 tokens. Groups
whose documents and tokens both return to 0 are left out of the totals. Repeated changes in one
batch count as often as they occur. An empty batch commits nothing but its id. Extra columns are ignored.
"""

from __future__ import annotations

import base64
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphcc.session import exists, remove

KEYS = ["source", "lang", "tokenizer"]
_SCHEMA = "source string, lang string, tokenizer string, documents long, tokens long"


#: Texts are cut near this many characters, at a space between letters, where no token lies across.
_LONG = 1 << 20
_CUT = re.compile(r"(?<=[a-z]) (?=[A-Za-z])")
_COUNTERS: dict = {}


def vocabulary_path(version: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(f"{version}.tiktoken")


def _counter(path: str):
    """Tokens of a text by the ranks in a vocabulary file; loaded once a worker."""
    if path not in _COUNTERS:
        import public_tokenizers
        import tiktoken

        with open(path, "rb") as f:
            ranks = {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, f)}
        encoding = tiktoken.Encoding(path, pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})

        def count(text: str) -> int:
            n, a = 0, 0
            while len(text) - a > _LONG and (cut := _CUT.search(text, a + _LONG)):
                n += len(encoding.encode_ordinary(text[a : cut.start()]))
                a = cut.start()
            return n + len(encoding.encode_ordinary(text[a:] if a else text))

        _COUNTERS[path] = count
    return _COUNTERS[path]


def _counted(path: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        count = _counter(path)
        for b in batches:
            n = pa.array([count(t.as_py()) if t.is_valid else 0 for t in b.column("text")], pa.int64())
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in ("doc_id", "source", "lang")), n], ["doc_id", "source", "lang", "n_tokens"])

    return run


def count_tokens(docs: DataFrame, version: str, path: str | None = None) -> DataFrame:
    """``(doc_id, source, lang, tokenizer, n_tokens)`` of every row of ``docs``, by the vocabulary file of ``version`` (or at ``path``)."""
    counted = docs.select("doc_id", "source", "lang", "text").mapInArrow(_counted(path or vocabulary_path(version)), "doc_id long, source string, lang string, n_tokens long")
    return counted.withColumn("tokenizer", F.lit(version))


def _summed(df: DataFrame) -> DataFrame:
    return df.groupBy(*KEYS).agg(F.sum("documents").alias("documents"), F.sum("tokens").alias("tokens")).where("documents <> 0 OR tokens <> 0")


def signed(counted: DataFrame, sign: int) -> DataFrame:
    """Changes from ``(source, lang, tokenizer, n_tokens)``: +1 inserts the rows, -1 deletes them."""
    return counted.select(*KEYS, F.lit(sign).cast("long").alias("documents"), (F.coalesce(F.col("n_tokens"), F.lit(0)) * sign).cast("long").alias("tokens"))


def revised(before: DataFrame, after: DataFrame) -> DataFrame:
    """Changes that replace the counts of ``before`` by those of ``after``."""
    return signed(before, -1).unionByName(signed(after, 1))


class TokenRollup:
    """Totals kept below ``path``, a folder all executors share."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")

    def _folders(self, kind: str) -> list[str]:
        jvm = self.spark.sparkContext._jvm
        top = jvm.org.apache.hadoop.fs.Path(f"{self.path}/{kind}")
        fs = top.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration())
        names = [s.getPath().getName() for s in fs.listStatus(top)] if fs.exists(top) else []
        return sorted(n for n in names if not n.endswith(("-holds", ".tmp")) and exists(self.spark, f"{self.path}/{kind}/{n}/_SUCCESS"))

    def _snapshot(self) -> str | None:
        """The newest snapshot's folder."""
        done = self._folders("snapshots")
        return f"{self.path}/snapshots/{done[-1]}" if done else None

    def _held(self, snapshot: str | None) -> DataFrame:
        """Ids of the batches folded into a snapshot."""
        return self.spark.read.schema("batch string").parquet(f"{snapshot}-holds") if snapshot else self.spark.createDataFrame([], "batch string")

    def _parts(self) -> tuple[str | None, list[str]]:
        """The newest snapshot, and the batches it does not hold: only folders that are still there are looked up in it."""
        at, names = self._snapshot(), self._folders("batches")
        held = {r.batch for r in self._held(at).where(F.col("batch").isin(names)).collect()} if at and names else set()
        return at, [b for b in names if b not in held]

    def batches(self) -> set[str]:
        """Ids of all committed batches."""
        at, fresh = self._parts()
        return {r.batch for r in self._held(at).collect()} | set(fresh)

    def committed(self, batch_id: str) -> bool:
        at = self._snapshot()
        return exists(self.spark, f"{self.path}/batches/{batch_id}/_SUCCESS") or not self._held(at).where(F.col("batch") == batch_id).isEmpty()

    def commit(self, batch_id: str, changes: DataFrame) -> bool:
        """Apply a batch once; False if it had been committed before."""
        if self.committed(batch_id):
            return False
        _summed(changes).write.mode("overwrite").parquet(f"{self.path}/batches/{batch_id}")
        return True

    def _sum_of(self, snapshot: str | None, fresh: list[str]) -> DataFrame:
        parts = ([snapshot] if snapshot else []) + [f"{self.path}/batches/{b}" for b in fresh]
        return _summed(self.spark.read.schema(_SCHEMA).parquet(*parts) if parts else self.spark.createDataFrame([], _SCHEMA))

    def totals(self) -> DataFrame:
        """``(source, lang, tokenizer, documents, tokens)`` over the committed batches."""
        return self._sum_of(*self._parts())

    def compact(self) -> None:
        """Fold the batches committed by now into a new snapshot, then drop what it replaces."""
        at, fresh = self._parts()
        if not fresh:
            return
        name = f"{int(at.rpartition('/')[2]) + 1 if at else 0:08d}"
        # The list of held batches is written first: a snapshot counts from its own success mark on.
        held = self._held(at).union(self.spark.createDataFrame([(b,) for b in fresh], "batch string"))
        held.coalesce(1).write.mode("overwrite").parquet(f"{self.path}/snapshots/{name}-holds.tmp")
        self._rename(f"{self.path}/snapshots/{name}-holds.tmp", f"{self.path}/snapshots/{name}-holds")
        self._sum_of(at, fresh).write.mode("overwrite").parquet(f"{self.path}/snapshots/{name}")
        for p in [f"{self.path}/batches/{b}" for b in fresh] + ([at, f"{at}-holds"] if at else []):
            remove(self.spark, p)

    def _rename(self, a: str, b: str) -> None:
        path = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path
        fs = path(a).getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration())
        remove(self.spark, b)
        fs.rename(path(a), path(b))
