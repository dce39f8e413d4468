"""BPE encoding and decoding of whole texts (the tree encoder of ``bpe``), with digests of both directions.

Texts are encoded and decoded where they stand, in one narrow pass; a worker remembers the digests of the texts it met
last, so that copies cost it a look-up.
Defined results: null is the empty text (no ids, the digests of nothing); special strings inside a text become
their special id, as the library's default does; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bpe import TOKENIZER, encoder
from .common import Remembered, table, whole_text


def encode_texts(texts: DataFrame, tokenizer: str = TOKENIZER) -> DataFrame:
    """(digest, ids array<int>) of (digest, text): the operator's real output."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(tokenizer)
        for b in batches:
            ids = [np.frombuffer(x, dtype="<i4") for x, _ in enc.encode_trees(b.column("text").to_pylist())]
            yield pa.RecordBatch.from_arrays([b.column("digest"), pa.array(ids, pa.list_(pa.int32()))], ["digest", "ids"])

    return texts.mapInArrow(run, "digest binary, ids array<int>")


def decode_ids(rows: DataFrame, tokenizer: str = TOKENIZER) -> DataFrame:
    """(digest, text) of (digest, ids array<int>)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(tokenizer)
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column("digest"), pa.array([enc.decode(x) for x in b.column("ids").to_pylist()], pa.string())], ["digest", "text"])

    return rows.mapInArrow(run, "digest binary, text string")


def roundtrip_digests(docs: DataFrame, tokenizer: str = TOKENIZER) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256, n_joins (how many joins the text's tree made). Ids and decoded text stay in the worker; only digests leave it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(tokenizer)

        def digests(texts: list[str]) -> list[tuple]:
            out = []
            for packed, joins in enc.encode_trees(texts):
                ids = np.frombuffer(packed, dtype="<u4").tolist()
                said = hashlib.sha256(",".join(map(enc.decimal_of.__getitem__, ids)).encode()).hexdigest()
                out.append((len(ids), said, hashlib.sha256(enc.decode(ids).encode()).hexdigest(), joins))
            return out

        known = Remembered(digests)
        for whole in batches:
            for at in range(0, whole.num_rows, 500):
                b = whole.slice(at, 500)
                out = list(zip(*known(b.column("text").to_pylist())))
                yield pa.RecordBatch.from_arrays([b.column("doc_id"), *(pa.array(c, k) for c, k in zip(out, (pa.int64(), pa.string(), pa.string(), pa.int64())))], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256", "n_joins"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), whole_text().alias("text"))
    return rows.mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string, n_joins long")


def op7_bpe_roundtrip(spark, sf_dir: str) -> DataFrame:
    return roundtrip_digests(table(spark, sf_dir, "documents"))
