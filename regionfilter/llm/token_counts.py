"""Token counts behind a digest cache.

A cache is a Parquet table (digest, n_tokens) below a folder, one subfolder for each tokenizer version, which is
the SHA-256 of the tokenizer's file. Counting joins the digests of all texts to the stored counts, encodes only
the distinct texts that have none, appends their counts and joins once more. Counts depend on every code point,
so the content is digested as it is, with null as empty. Cached rows of two writers may repeat; readers take one.

Defined results: null and empty texts count 0; equal texts are encoded once; an empty table gives no rows; other
columns are ignored; the limit is exceeded by strictly more tokens.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bpe import TOKENIZER, encoder, tokenizer_digest
from .common import digest_of, distinct_texts, shared_folder, table, whole_text

STORED = "digest binary, n_tokens long"


def encoded_counts(texts: DataFrame, tokenizer: str = TOKENIZER) -> DataFrame:
    """(digest, n_tokens) of (digest, text)."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(tokenizer)
        for b in batches:
            n = [len(ids) // 4 for ids in enc.encode_many(b.column("text").to_pylist())]
            yield pa.RecordBatch.from_arrays([b.column("digest"), pa.array(n, pa.int64())], ["digest", "n_tokens"])

    return texts.mapInArrow(count, STORED)


class CountCache:
    """Counts stored by content digest and tokenizer version."""

    def __init__(self, spark, folder: str, tokenizer: str = TOKENIZER):
        self.spark, self.tokenizer = spark, tokenizer
        self.at = f"{folder}/tokenizer={tokenizer_digest(tokenizer)}"
        path = spark._jvm.org.apache.hadoop.fs.Path(self.at)
        self._has_files = lambda: path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(path)

    def stored(self) -> DataFrame | None:
        return self.spark.read.schema(STORED).parquet(self.at).dropDuplicates(["digest"]) if self._has_files() else None

    def add_misses(self, docs: DataFrame) -> None:
        """Encode what the cache lacks of the texts of docs, and append it."""
        texts, stored = distinct_texts(docs), self.stored()
        if stored is not None:
            texts = texts.join(stored, "digest", "left_anti")
        encoded_counts(texts, self.tokenizer).write.mode("append").parquet(self.at)

    def counts(self, docs: DataFrame, limit: int) -> DataFrame:
        """(doc_id, n_bytes, n_tokens, over_limit) for every row of docs."""
        self.add_misses(docs)
        text = whole_text()
        rows = docs.select("doc_id", F.octet_length(text).cast("long").alias("n_bytes"), digest_of(text).alias("digest"))
        # the many copies of one text are one row of the cache: adaptive execution splits the hot side of this join
        return rows.join(self.spark.read.schema(STORED).parquet(self.at) if not self._shared else self.stored(), "digest").select(
            "doc_id", "n_bytes", "n_tokens", (F.col("n_tokens") > limit).alias("over_limit")
        )

    #: whether others may have written the same digests
    _shared = True


def token_counts(docs: DataFrame, limit: int = 1024, cache_folder: str | None = None, tokenizer: str = TOKENIZER) -> DataFrame:
    """Counts of every text; without a cache folder the cache is a new one for this call."""
    spark = docs.sparkSession
    cache = CountCache(spark, cache_folder or shared_folder(spark, "token-cache"), tokenizer)
    cache._shared = cache_folder is not None
    return cache.counts(docs, limit)


def op4_token_counts(spark, sf_dir: str) -> DataFrame:
    return token_counts(table(spark, sf_dir, "documents"))
