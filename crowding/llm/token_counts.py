"""Token counts kept as signed additive deltas.

A count is a row (doc_id, source, lang, tokenizer, tokens). Changes carry a sign: an insert is +1, a
delete -1, a revised count is its old image with -1 beside its new image with +1. Every batch is summed to
one row per (source, lang, tokenizer) before it is stored, so the store grows with batches and keys and
never with documents, and totals are a sum over it.

The store is data folders plus numbered manifests, each naming the folders in force and the batch ids in them.
A manifest is created only if its number is free, so of several writers one wins and the others read again;
what a crash leaves behind is a folder that no manifest names.

Edge cases: null source or lang is a group of its own; null or empty text counts 0 tokens and is still a
document; repeated rows count as often as they occur; an empty change set commits an empty batch; columns
other than those named are ignored. A batch id that is committed already is skipped, whatever it holds.
"""

from __future__ import annotations

import json
import os
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Tokenizer version -> pattern whose matches are its tokens.
TOKENIZERS = {
    "words-1": r"[^\x20\x09-\x0D]+",
    "pieces-2": r"[A-Za-z0-9]+|[^\x20\x09-\x0DA-Za-z0-9]",
}
KEYS = ["source", "lang", "tokenizer"]
SUMS = ("n_docs", "n_tokens", "n_chars")
SCHEMA = "source string, lang string, tokenizer string, n_docs long, n_tokens long, n_chars long"


def count_tokens(docs: DataFrame, tokenizers: dict[str, str] = TOKENIZERS) -> DataFrame:
    """doc_id, source, lang, n_chars, text_md5 and one column tokens_<i> per tokenizer, in their order."""
    text = F.coalesce(F.col("text"), F.lit(""))
    return docs.select(
        "doc_id", "source", "lang", F.char_length(text).cast("long").alias("n_chars"), F.md5(text).alias("text_md5"),
        *[F.regexp_count(text, F.lit(p)).cast("long").alias(f"tokens_{i}") for i, p in enumerate(tokenizers.values())],
    )


def change(rows: DataFrame, sign: int, tokenizer: str, tokens: str) -> DataFrame:
    """Signed change rows of counted documents under one tokenizer version."""
    return rows.select(
        "source", "lang", F.lit(tokenizer).alias("tokenizer"), F.lit(sign).cast("long").alias("n_docs"),
        (F.lit(sign) * F.col(tokens)).cast("long").alias("n_tokens"), (F.lit(sign) * F.col("n_chars")).cast("long").alias("n_chars"),
    )


class TokenRollup:
    """A store of committed batches below one path of any Hadoop filesystem.

    apply() and fold() first write a data folder, then the next manifest; that is the commit. Creating a file
    only if it is absent is atomic on HDFS (rename without overwriting) and on local and network disks (a hard
    link); on other stores use one writer. A manifest holds every batch id in force, about 30 bytes each.
    """

    def __init__(self, spark: SparkSession, root: str):
        self.spark, self.root = spark, root.rstrip("/")
        self._jvm = spark.sparkContext._jvm
        self._path = self._jvm.org.apache.hadoop.fs.Path
        self._conf = spark.sparkContext._jsc.hadoopConfiguration()
        self._fs = self._path(self.root).getFileSystem(self._conf)
        for folder in ("manifest", "data", "staging"):
            self._fs.mkdirs(self._path(f"{self.root}/{folder}"))

    def _version(self) -> int:
        names = [s.getPath().getName() for s in self._fs.listStatus(self._path(f"{self.root}/manifest"))]
        return max((int(n) for n in names if n.isdigit()), default=0)

    def _manifest(self, version: int) -> list[dict]:
        """The folders in force: [{"path": ..., "ids": [...]}]."""
        if not version:
            return []
        f = self._fs.open(self._path(f"{self.root}/manifest/{version:012d}"))
        try:
            return json.loads(self._jvm.org.apache.commons.io.IOUtils.toString(f, "UTF-8"))
        finally:
            f.close()

    def _create(self, version: int, parts: list[dict]) -> bool:
        """Write a manifest; False if its number is taken."""
        stage, final = (self._path(f"{self.root}/{x}") for x in (f"staging/{uuid.uuid4().hex}", f"manifest/{version:012d}"))
        f = self._fs.create(stage, True)
        f.write(json.dumps(parts).encode())
        f.close()
        try:
            if self._fs.getScheme() == "file":
                os.link(stage.toUri().getPath(), final.toUri().getPath())
            else:
                none = self._jvm.org.apache.hadoop.fs.Options.Rename.NONE
                options = self.spark.sparkContext._gateway.new_array(self._jvm.org.apache.hadoop.fs.Options.Rename, 1)
                options[0] = none
                self._jvm.org.apache.hadoop.fs.FileContext.getFileContext(final.toUri(), self._conf).rename(self._path(self._fs.makeQualified(stage).toString()), self._path(self._fs.makeQualified(final).toString()), options)
        except FileExistsError:
            return False
        except Exception as e:
            if "FileAlreadyExistsException" in str(e):
                return False
            raise
        finally:
            self._fs.delete(stage, True)
        return True

    def _write(self, changes: DataFrame) -> str:
        path = f"data/{uuid.uuid4().hex}"
        changes.groupBy(*KEYS).agg(*[F.sum(c).cast("long").alias(c) for c in SUMS]).write.parquet(f"{self.root}/{path}")
        return path

    def committed(self) -> list[str]:
        """Ids of the batches in force, those folded included."""
        return sorted(i for part in self._manifest(self._version()) for i in part["ids"])

    def apply(self, batch_id: str, changes: DataFrame) -> bool:
        """Commit signed changes under an id; False, and nothing added, if that id is in force already."""
        if not batch_id.replace("-", "").replace("_", "").isalnum():
            raise ValueError(f"batch id {batch_id!r} has other characters than letters, digits, - and _")
        path = None
        while True:
            version = self._version()
            parts = self._manifest(version)
            if any(batch_id in part["ids"] for part in parts):
                if path is not None:
                    self._fs.delete(self._path(f"{self.root}/{path}"), True)
                return False
            path = path or self._write(changes)
            if self._create(version + 1, [*parts, {"path": path, "ids": [batch_id]}]):
                return True

    def _read(self, parts: list[dict]) -> DataFrame:
        if not parts:
            return self.spark.createDataFrame([], SCHEMA)
        return self.spark.read.schema(SCHEMA).parquet(*[f"{self.root}/{p['path']}" for p in parts])

    def totals(self) -> DataFrame:
        """Current totals; keys whose documents have all been taken back are left out."""
        return self._read(self._manifest(self._version())).groupBy(*KEYS).agg(*[F.sum(c).cast("long").alias(c) for c in SUMS]).filter("n_docs <> 0")

    def fold(self) -> bool:
        """Replace the committed batches by one folder; their ids stay in force. What it replaced stays until vacuum()."""
        old = self._manifest(self._version())
        if len(old) < 2:
            return False
        one = {"path": self._write(self._read(old)), "ids": sorted(i for part in old for i in part["ids"])}
        while True:
            version = self._version()
            now = self._manifest(version)
            if any(part not in now for part in old):  # another fold was first
                self._fs.delete(self._path(f"{self.root}/{one['path']}"), True)
                return False
            if self._create(version + 1, [one, *[part for part in now if part not in old]]):
                return True

    def vacuum(self, older_than_s: float = 86_400) -> int:
        """Delete data folders that the newest manifest does not name, and manifests before it, if they are that old
        (long enough for readers of an older manifest, and for writers between folder and manifest); how many."""
        version = self._version()
        keep = {p["path"].rsplit("/", 1)[1] for p in self._manifest(version)} | {f"{version:012d}"}
        limit, gone = self._jvm.java.lang.System.currentTimeMillis() - older_than_s * 1000, 0
        for folder in ("data", "manifest", "staging"):
            for s in self._fs.listStatus(self._path(f"{self.root}/{folder}")):
                if s.getPath().getName() not in keep and s.getModificationTime() <= limit:
                    gone += bool(self._fs.delete(s.getPath(), True))
        return gone


#: Groups of copies of so many rows, if they are a 20,000th of all rows as well, have their smallest id broadcast.
HEAVY = 200


def later_copies(counts: DataFrame) -> DataFrame:
    """Rows whose text already stands under a smaller doc_id; a null doc_id is never one."""
    from crowding.llm.common import join_counted, settle

    first = settle(counts.groupBy("text_md5").agg(F.min("doc_id").alias("first_id"), F.count(F.lit(1)).alias("n")).filter("n > 1"), "token-first")
    total = first.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    return join_counted(counts, first, "text_md5", total, HEAVY).filter("doc_id > first_id").select(*counts.columns)


def maintain(docs: DataFrame, rollup: TokenRollup) -> DataFrame:
    """The production run: load a crawl, take back later copies, move languages other than English to the
    newer tokenizer, replay a batch as a restarted job would, and return the totals."""
    from crowding.llm.common import settle

    old, new = TOKENIZERS
    counts = settle(count_tokens(docs), "token-counts")
    copies = settle(later_copies(counts), "token-copies")
    rollup.apply("crawl", change(counts, 1, old, "tokens_0"))
    rollup.apply("copies", change(copies, -1, old, "tokens_0"))
    other = F.coalesce(F.col("lang") != "en", F.lit(True))
    moved = [change(x.filter(other), s, t, c) for x, sign in ((counts, 1), (copies, -1)) for s, t, c in ((-sign, old, "tokens_0"), (sign, new, "tokens_1"))]
    revised = moved[0]
    for m in moved[1:]:
        revised = revised.unionByName(m)
    rollup.apply("retokenized", revised)
    rollup.apply("copies", change(copies, -1, old, "tokens_0"))
    return rollup.totals()


def op1_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Totals by source, language and tokenizer version after the batches of maintain()."""
    from crowding.llm.common import scratch, table

    return maintain(table(spark, sf_dir, "documents"), TokenRollup(spark, scratch(spark, "token-rollup")))


SQL = r"""
WITH c AS (
  SELECT doc_id, source, lang, length(coalesce(text, '')) AS n_chars,
         doc_id > min(doc_id) OVER (PARTITION BY coalesce(text, '')) AS copy,
         len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS t0,
         len(regexp_extract_all(coalesce(text, ''), '[A-Za-z0-9]+|[^\x20\x09-\x0DA-Za-z0-9]')) AS t1
  FROM documents)
SELECT source, lang, CASE WHEN lang = 'en' THEN 'words-1' ELSE 'pieces-2' END AS tokenizer,
       count(*) AS n_docs, CAST(sum(CASE WHEN lang = 'en' THEN t0 ELSE t1 END) AS BIGINT) AS n_tokens,
       CAST(sum(n_chars) AS BIGINT) AS n_chars
FROM c WHERE copy IS NOT TRUE GROUP BY 1, 2, 3
"""
