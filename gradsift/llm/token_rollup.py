"""Delta-maintained token counts by source, language and tokenizer version.

Totals are sums of signed rows: an insert adds a document and its tokens, a delete takes both off,
a revision takes the old count off and adds the new one.  A batch is aggregated, written to the
ledger's folder, and committed by renaming its finished marker to the batch's name, which succeeds
once only; a repeated or concurrent commit of the same batch finds the marker and changes nothing.
Data without a marker (of a writer that died) are never read, and a marker without content (of a
store that could not rename at once) counts as none and is replaced.

Defined results: null source or language is a group of its own; a null count is 0; a null text has
no tokens; a text of any length is counted whole; repeated rows count each; an empty batch commits
and adds nothing; further columns are ignored.  Markers are handled by Hadoop's file system through
the driver's JVM, so the ledger needs a session that has one.
"""

from __future__ import annotations

import json
import uuid

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gradsift.llm.bpe import byte_encoder, text_blocks, word_encoder
from gradsift.llm.common import fresh_path, materialise, table
from gradsift.llm.packing import tokenizer_path

KEYS = ["source", "lang", "version"]
TOTALS = "source string, lang string, version string, n_docs long, n_tokens long"


def inserted(counts: DataFrame) -> DataFrame:
    return counts.select(*KEYS, F.lit(1).cast("long").alias("n_docs"), F.coalesce("n_tokens", F.lit(0)).cast("long").alias("n_tokens"))


def deleted(counts: DataFrame) -> DataFrame:
    return counts.select(*KEYS, F.lit(-1).cast("long").alias("n_docs"), (-F.coalesce("n_tokens", F.lit(0))).cast("long").alias("n_tokens"))


def revised(counts: DataFrame, old: str = "old_tokens", new: str = "n_tokens") -> DataFrame:
    change = F.coalesce(new, F.lit(0)) - F.coalesce(old, F.lit(0))
    return counts.select(*KEYS, F.lit(0).cast("long").alias("n_docs"), change.cast("long").alias("n_tokens"))


class TokenLedger:
    """Committed batches below a folder that driver and executors share."""

    def __init__(self, spark: SparkSession, root: str):
        self.spark, self.root = spark, root.rstrip("/")
        self.path = spark._jvm.org.apache.hadoop.fs.Path
        self.fs = self.path(self.root).getFileSystem(spark._jsc.hadoopConfiguration())

    def _marker(self, batch: str) -> str | None:
        """Data folder that the batch's marker names, if it is there and whole."""
        at = self.path(f"{self.root}/commits/{batch}")
        if not self.fs.exists(at):
            return None
        data = self.fs.open(at)
        raw = bytes(data.readAllBytes())
        data.close()
        return json.loads(raw)["data"] if raw else None

    def committed(self, batch: str) -> bool:
        return self._marker(batch) is not None

    def commit(self, batch: str, deltas: DataFrame) -> bool:
        """Adds the batch once; False if it is there already."""
        if not batch or "/" in batch or batch[0] in "._":
            raise ValueError("a batch needs a name without slash that starts with neither dot nor underscore")
        if self.committed(batch):
            return False
        data = f"data/{batch}-{uuid.uuid4().hex}"
        rows = deltas.groupBy(*KEYS).agg(F.sum("n_docs").cast("long").alias("n_docs"), F.sum("n_tokens").cast("long").alias("n_tokens"))
        rows.where("n_docs <> 0 or n_tokens <> 0").write.parquet(f"{self.root}/{data}")
        return self._mark(batch, data)

    def _mark(self, batch: str, data: str) -> bool:
        ready, at = self.path(f"{self.root}/commits/.{batch}-{uuid.uuid4().hex}"), self.path(f"{self.root}/commits/{batch}")
        out = self.fs.create(ready, False)
        out.write(bytearray(json.dumps({"data": data}).encode()))
        out.close()
        if self.fs.exists(at) and not self.committed(batch):
            self.fs.delete(at, False)
        jvm = self.spark._jvm
        kind = getattr(jvm.org.apache.hadoop.fs, "Options$Rename")
        try:  # refuses a name that is taken
            jvm.org.apache.hadoop.fs.FileContext.getFileContext(self.fs.getUri(), self.spark._jsc.hadoopConfiguration()).rename(ready, at, self.spark.sparkContext._gateway.new_array(kind, 0))
        except Exception:
            self.fs.delete(ready, False)
            if self.committed(batch):
                return False
            raise
        return True

    def batches(self) -> dict[str, str]:
        """Committed batch names and their data; one entry per batch, not per document."""
        folder = self.path(f"{self.root}/commits")
        if not self.fs.exists(folder):
            return {}
        names = [f.getPath().getName() for f in self.fs.listStatus(folder)]
        found = {n: self._marker(n) for n in names if not n.startswith(".")}
        return {n: data for n, data in found.items() if data}

    def totals(self) -> DataFrame:
        paths = [f"{self.root}/{p}" for p in self.batches().values()]
        if not paths:
            return self.spark.createDataFrame([], TOTALS)
        rows = self.spark.read.schema(TOTALS).parquet(*paths).groupBy(*KEYS)
        return rows.agg(F.sum("n_docs").alias("n_docs"), F.sum("n_tokens").alias("n_tokens")).where("n_docs <> 0 or n_tokens <> 0")


def token_counts(docs: DataFrame, word_path: str, byte_path: str) -> DataFrame:
    """doc_id, source, lang, version, n_tokens and old_tokens (an estimate from the bytes)."""

    def run(batches):
        for b in batches:
            texts = [t or "" for t in b.column("text").to_pylist()]
            for version, encoder in (("word_bpe_49k", word_encoder(word_path)), ("byte_bpe_50k", byte_encoder(byte_path))):
                n = [x for i, j in text_blocks(texts) for x in encoder.lengths(texts[i:j])]
                yield pa.RecordBatch.from_arrays(
                    [*(b.column(c) for c in ("doc_id", "source", "lang")), pa.array([version] * len(n), pa.string()), pa.array(n, pa.int64()), b.column("old_tokens")],
                    ["doc_id", "source", "lang", "version", "n_tokens", "old_tokens"],
                )

    old = F.floor(F.coalesce(F.octet_length(F.col("text").cast("string")), F.lit(0)) / 4).cast("long").alias("old_tokens")
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), *(F.col(c).cast("string").alias(c) for c in ("source", "lang", "text")), old)
    return docs.mapInArrow(run, "doc_id long, source string, lang string, version string, n_tokens long, old_tokens long")


def op6_delta_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Totals of all documents for two tokenizers: estimates inserted, then revised, a third of the documents deleted and inserted again, each batch sent twice."""
    counts = materialise(token_counts(table(spark, sf_dir, "documents"), tokenizer_path("word_bpe_49k.json"), tokenizer_path("byte_bpe_50k.json")), "token-counts")
    ledger = TokenLedger(spark, fresh_path(spark, "token-ledger"))
    for _ in range(2):
        ledger.commit("estimates", inserted(counts.select(*KEYS, F.col("old_tokens").alias("n_tokens"))))
        ledger.commit("exact", revised(counts))
        ledger.commit("removed", deleted(counts.where("doc_id % 3 = 0")))
        ledger.commit("restored", inserted(counts.where("doc_id % 3 = 0")))
    return ledger.totals()
