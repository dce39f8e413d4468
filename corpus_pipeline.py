"""A corpus pipeline of four stages: reject poor documents, drop exact copies, drop near copies, pack into windows.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame that is written as Parquet and read again as the
next stage's docs. All but the last return the columns of documents.

Defined results of every stage: null text is the empty text and is carried as null; a null doc_id is carried and comes
after all others where ids decide; rows that repeat a doc_id with other texts are judged by their own text; fully equal
rows (doc_id and text) are one after the second stage; texts of any length are taken whole; an empty table stays empty;
columns beside doc_id and text are carried through the first three stages, whatever their names.
"""

from __future__ import annotations

from regionfilter.llm.common import shared_folder, table
from regionfilter.llm.exact_dedup import deduplicate
from regionfilter.llm.near import drop_near_copies
from regionfilter.llm.packing import pack
from regionfilter.llm.quality import keep_good


def quality(spark, docs, sf_dir: str):
    """Documents that the pairwise-ranking classifier does not reject: those that score 0.5 or more, all of them where the
    labels hold no good or no bad document. Equal texts get the same verdict."""
    return keep_good(docs, table(spark, sf_dir, "labels"))


def exact(spark, docs, sf_dir: str):
    """Of equal texts, the row with the largest doc_id; one of rows that repeat it."""
    return deduplicate(docs)


def near(spark, docs, sf_dir: str):
    """Of each group of near copies (5-word shingles, Jaccard of at least 0.8), the row with the smallest doc_id and then
    the smallest text digest. Candidates come from SimHash fingerprints of 256 bits alone, by multi-index hashing over their
    blocks; the whole sets of shingles decide on each."""
    return drop_near_copies(docs)


def packing(spark, docs, sf_dir: str):
    """The pieces of what is left, placed in windows of 1024 tokens; an empty text is its end id."""
    return pack(docs)


STAGES = [("quality classifier", quality), ("exact dedup", exact), ("simhash near-dedup", near), ("packing", packing)]

#: a trained classifier, near-copy components and token ids are beyond SQL; tests hold run() against brute force
ORACLE_SQL = None


def run(spark, sf_dir: str):
    """The stages applied to documents, one after the other."""
    docs, at = table(spark, sf_dir, "documents"), shared_folder(spark, "pipeline")
    for k, (_, stage) in enumerate(STAGES):
        stage(spark, docs, sf_dir).write.parquet(f"{at}/{k}")
        docs = spark.read.parquet(f"{at}/{k}")
    return docs
