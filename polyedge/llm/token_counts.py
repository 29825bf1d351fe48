"""Token counts: additive rollups by source, language and tokenizer version, kept by signed deltas.

A change of the corpus is a batch of signed rows: an insert adds a document's counts, a delete
subtracts them, a revised count subtracts the old and adds the new ones.  Tokens are counted by the
tokenizer that the version names.  A batch is summed per group before it is written, so a hot source
is one row per task in the shuffle.  It is written to a folder of its own and committed by renaming
that folder to the batch id, which fails where the id is taken: of several writers of one id, also at
one time, a single one commits and the others change nothing.  (The rename is atomic in file systems
where it is, as HDFS or a local one.)  Totals are sums over the committed batches; ``compact`` folds
them into one.

Defined results: null sources, languages and texts are groups and empty texts of their own; rows of
one id are counted each; a null id joins no list of ids; groups whose counts all return to zero leave
the totals; an empty batch commits and changes nothing.
"""

from __future__ import annotations

import uuid
from functools import partial

from py4j.protocol import Py4JJavaError
from pyspark.sql import DataFrame, SparkSession, functions as F, types as T

from polyedge.llm import bpe, common, packing

KEYS = ["source", "lang", "tokenizer_version"]
SUMS = ["n_docs", "n_tokens", "n_chars"]


def _lengths(texts: list[str], path: str, pattern: str | None) -> list[list[int]]:
    encode = packing.encoder(path) if pattern is None else bpe.vocabulary(path, pattern).encode_batch
    out = []
    for at in range(0, len(texts), 512):
        out += [len(x) // 4 for x in encode(texts[at : at + 512])]
    return [out]


def counted(docs: DataFrame, version: str, path: str, pattern: str | None = None) -> DataFrame:
    """(doc_id, source, lang, tokenizer_version, n_tokens, n_chars) of every row.

    ``path`` is a tokenizer file (json), or with ``pattern`` a file of ranks.
    """
    n_chars = F.coalesce(F.char_length(F.col("text").cast("string")), F.lit(0)).cast("long").alias("__chars")
    rows = docs.select("doc_id", "source", "lang", n_chars, "text")
    rows = common.with_text_columns(rows, "text", partial(_lengths, path=path, pattern=pattern), [("n_tokens", T.LongType())], keep=["doc_id", "source", "lang", "__chars"])
    return rows.select("doc_id", "source", "lang", F.lit(version).alias("tokenizer_version"), "n_tokens", F.col("__chars").alias("n_chars"))


def recounted(docs: DataFrame, ids: DataFrame, version: str, path: str, pattern: str | None = None) -> DataFrame:
    """``counted`` for the documents whose id is among ``ids`` (unique rows of doc_id).

    A bitmap of the ids chooses before counting and the join after it decides, so no text is shuffled,
    however many ids there are.
    """
    ids = ids.select(F.col("doc_id").cast(docs.schema["doc_id"].dataType).alias("doc_id"))
    near = common.may_hold(docs, "doc_id", ids).where("__hit")
    return counted(near, version, path, pattern).join(ids, "doc_id", "left_semi")


def signed(rows: DataFrame, sign: int) -> DataFrame:
    """Counted rows as deltas: ``sign`` +1 inserts, -1 deletes."""
    return rows.select(*KEYS, F.lit(sign).cast("long").alias("n_docs"), (sign * F.col("n_tokens")).alias("n_tokens"), (sign * F.col("n_chars")).alias("n_chars"))


def revised(old: DataFrame, new: DataFrame) -> DataFrame:
    return signed(old, -1).unionByName(signed(new, 1))


def summed(deltas: DataFrame) -> DataFrame:
    return deltas.groupBy(*KEYS).agg(*[F.sum(c).alias(c) for c in SUMS])


class Rollup:
    """Committed batches of deltas below one folder."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")

    def _path(self, path: str):
        return self.spark._jvm.org.apache.hadoop.fs.Path(path)

    def _system(self):
        return self._path(self.path).getFileSystem(self.spark._jsc.hadoopConfiguration())

    def _folder(self, batch_id: str) -> str:
        if not batch_id or not all(c.isalnum() or c in "-_" for c in batch_id):
            raise ValueError("a batch id is letters, digits, - and _")
        return f"{self.path}/batch={batch_id}"

    def committed(self, batch_id: str) -> bool:
        return self._system().exists(self._path(self._folder(batch_id)))

    def _rename(self, source: str, target: str) -> bool:
        """False if the target exists."""
        fs, jvm = self.spark._jvm.org.apache.hadoop.fs, self.spark._jvm
        kind = getattr(fs, "Options$Rename")
        options = self.spark.sparkContext._gateway.new_array(kind, 1)
        options[0] = kind.NONE
        src = self._system().makeQualified(self._path(source))
        try:
            jvm.org.apache.hadoop.fs.FileContext.getFileContext(src.toUri(), self.spark._jsc.hadoopConfiguration()).rename(src, self._system().makeQualified(self._path(target)), options)
        except Py4JJavaError as e:
            if "FileAlreadyExistsException" in str(e.java_exception):
                return False
            raise
        return True

    def commit(self, batch_id: str, deltas: DataFrame) -> bool:
        """True if this call committed the batch, False if it had been or was meanwhile by another."""
        if self.committed(batch_id):
            return False
        attempt = f"{self.path}/_attempt-{batch_id}-{uuid.uuid4().hex}"
        summed(deltas).write.parquet(attempt)
        done = self._rename(attempt, self._folder(batch_id))
        if not done:
            self._system().delete(self._path(attempt), True)
        return done

    def batches(self) -> list[str]:
        if not self._system().exists(self._path(self.path)):
            return []
        names = [s.getPath().getName() for s in self._system().listStatus(self._path(self.path))]
        return sorted(n.removeprefix("batch=") for n in names if n.startswith("batch="))

    def totals(self) -> DataFrame:
        ids = self.batches()
        if not ids:
            return self.spark.createDataFrame([], "source string, lang string, tokenizer_version string, n_docs long, n_tokens long, n_chars long")
        rows = self.spark.read.parquet(*[self._folder(i) for i in ids])
        return summed(rows).where(" OR ".join(f"{c} <> 0" for c in SUMS)).select(*KEYS, *SUMS)

    def compact(self, target: Rollup, batch_id: str) -> bool:
        """Fold all committed batches into one batch of another rollup."""
        return target.commit(batch_id, self.totals())
