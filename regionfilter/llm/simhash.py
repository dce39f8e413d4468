"""SimHash near-dedup by multi-index hashing.

A fingerprint has 64 bits. Two that differ in at most ``2`` bits either differ in at most one bit of the upper
half, or agree in the whole lower half. So each distinct fingerprint is listed under its upper half and under
its lower half, looked up under its lower half as it is and under every upper half of the Hamming ball of radius
one, and each match is verified on all 64 bits. As distance is symmetric, a flip is only tried where it sets a
bit, and equal halves are listed once.

Halves are shared far too often where a group holds very many near copies. A half with more than ``crowded``
fingerprints is therefore not paired up: its fingerprints are looked up by full 64-bit values, all those within
two bits of each, which costs a fixed number of look-ups for each fingerprint and makes exactly the true links.

Equal fingerprints (copies) are one row of every table here. Components come from hash-to-minimum rounds over
fingerprints; neighbour lists are never gathered: each round takes minima by partial aggregation and joins them
back, with both tables in the shared folder.

Defined results: null text is the empty text; no words give the fingerprint zero, linked like any other; fewer
words than a shingle give one shingle of all of them; rows that repeat a doc_id are members like others; a null
doc_id comes after all others, so its row gets its component's smallest doc_id, which is null only if no row of the
component has one; an empty table gives no rows; other columns are ignored.

The look-ups within two bits cost 2080 rows for each fingerprint in a crowded half, whatever their number.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import staged, table, whole_text

SHINGLE, BITS, SEED = 3, 2, 42
LOW = 0xFFFFFFFF


def shingle_hashes(text: str, shingle: int = SHINGLE) -> np.ndarray:
    """The hash of each shingle of a text, in order; none without words."""
    words = text.encode("utf-8", "surrogatepass").lower().split()  # bytes: A-Z only, and the six ASCII spaces
    if not words:
        return np.empty(0, dtype="<u8")
    joined = b" ".join(words)
    if len(words) <= shingle:
        return np.array([xxhash.xxh64_intdigest(joined, SEED)], dtype="<u8")
    ends = np.cumsum([len(w) + 1 for w in words])
    starts = [0, *ends[:-1].tolist()]
    digest = xxhash.xxh64_intdigest
    return np.fromiter((digest(joined[a:b], SEED) for a, b in zip(starts, (ends[shingle - 1 :] - 1).tolist())), dtype="<u8")


def fingerprint(text: str, shingle: int = SHINGLE) -> int:
    """64-bit SimHash of a text: a bit is set if more than half of the shingles' hashes have it."""
    return fingerprint_of(shingle_hashes(text, shingle))


def fingerprint_of(hashes: np.ndarray) -> int:
    """The same of shingle hashes."""
    if not len(hashes):
        return 0
    ones = np.zeros(64, dtype=np.int64)
    for i in range(0, len(hashes), 65536):
        ones += np.unpackbits(hashes[i : i + 65536].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(hashes), bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, shingle: int = SHINGLE) -> DataFrame:
    """(doc_id, fp long): the fingerprint's 64 bits as a signed number."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fps = np.array([fingerprint(t, shingle) for t in b.column("text").to_pylist()], dtype=np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(fps, pa.int64())], ["doc_id", "fp"])

    return docs.select(F.col("doc_id").cast("long"), whole_text().alias("text")).mapInArrow(run, "doc_id long, fp long")


def _bit(at) -> Column:
    return F.call_function("shiftleft", F.lit(1).cast("long"), at)


def links(nodes: DataFrame, crowded: int = 64) -> DataFrame:
    """(a, b) with a < b for all pairs of the distinct fingerprints in ``nodes`` (fp) that differ in 1 or 2 bits."""
    upper, lower = F.shiftrightunsigned("fp", 32), F.col("fp").bitwiseAND(F.lit(LOW))
    listed = nodes.select("fp", F.explode(F.array(F.struct(F.lit(0).alias("half"), upper.alias("value")), F.struct(F.lit(1).alias("half"), lower.alias("value")))).alias("k")).select("fp", "k.half", "k.value")
    sizes = listed.groupBy("half", "value").agg(F.count("*").alias("n")).where("n > 1")
    big = staged(sizes.where(F.col("n") > crowded).select("half", "value"), "crowded-halves")
    # every way one bit of the upper half may be set, and the half itself
    ball = F.concat(F.array(upper), F.filter(F.transform(F.sequence(F.lit(0), F.lit(31)), lambda i: upper.bitwiseOR(_bit(i))), lambda v: v != upper))
    probes = nodes.select("fp", F.explode(ball).alias("value")).select(F.col("fp").alias("a"), F.lit(0).alias("half"), "value").unionByName(nodes.select(F.col("fp").alias("a"), F.lit(1).alias("half"), lower.alias("value")))
    few = listed.join(big, ["half", "value"], "left_anti")
    pairs = probes.join(few, ["half", "value"]).where((F.bit_count(F.col("a").bitwiseXOR(F.col("fp"))) <= BITS) & (F.col("a") != F.col("fp")))
    pairs = pairs.select(F.least("a", "fp").alias("a"), F.greatest("a", "fp").alias("b"))
    # crowded halves: who probes or fills one is looked up by whole values within two bits
    crowd = probes.join(big, ["half", "value"], "left_semi").select(F.col("a").alias("fp")).distinct()
    bits = F.sequence(F.lit(0), F.lit(63))
    masks = F.flatten(F.transform(bits, lambda i: F.transform(F.filter(bits, lambda j: j >= i), lambda j: _bit(i).bitwiseOR(_bit(j)))))
    near = crowd.select(F.col("fp").alias("a"), F.explode(masks).alias("mask")).select("a", F.col("a").bitwiseXOR(F.col("mask")).alias("fp"))
    exact = near.join(nodes, "fp").select(F.least("a", "fp").alias("a"), F.greatest("a", "fp").alias("b"))
    return pairs.unionByName(exact).distinct()


def _label(id_, at) -> Column:
    """What orders the documents of a component: known ids by size, then fingerprints without one."""
    return F.struct(F.col(id_).isNull().alias("none"), F.col(id_).alias("id"), F.col(at).alias("at"))


def components(edges: DataFrame, ids: DataFrame) -> DataFrame:
    """(fp, component, head): the least ``id`` of (fp, id) that can be reached over edges (a, b), and the fp that has
    it; only fps with edges. A null id comes after all others.

    Each round every fp takes the least label of itself, its neighbours, and its neighbours' own labels' owners
    (pointer jumping over labels), so a chain of length n ends after about log n rounds."""
    both = staged(edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))), "edges")
    # labels are (id, fp) of the least document known so far; the fp lets a label be followed
    own = ids.join(both.select(F.col("a").alias("fp")).distinct(), "fp", "left_semi")
    state = staged(own.select("fp", _label("id", "fp").alias("label")), "labels")
    while True:
        seen = both.join(state, F.col("b") == F.col("fp")).groupBy("a").agg(F.min("label").alias("near"))
        least = state.join(seen, F.col("fp") == F.col("a")).select("fp", "label", F.least("label", "near").alias("new"))
        least = staged(least, "least")
        # what a label's old owner has learned holds for all that carry the label, and the other way round
        told = least.groupBy(F.col("label.at").alias("at")).agg(F.min("new").alias("told"))
        hop = least.select(F.col("fp").alias("at"), F.col("new").alias("hop"))
        step = least.join(told, F.col("label.at") == F.col("at")).select("fp", "label", F.least("new", "told").alias("new"))
        step = step.join(hop, F.col("new.at") == F.col("at"), "left").select("fp", "label", F.least("new", F.coalesce("hop", "new")).alias("new"))
        state = staged(step, "labels")
        changed = state.where(F.col("label.at") != F.col("new.at")).limit(1).count()
        state = state.select("fp", F.col("new").alias("label"))
        if not changed:
            return state.select("fp", F.col("label.id").alias("component"), F.col("label.at").alias("head"))


def _grouped(docs: DataFrame, shingle: int) -> DataFrame:
    """(doc_id, fp, component_id, head) of every row; head is the fingerprint of the component's first document."""
    rows = staged(fingerprints(docs, shingle), "fingerprints")
    ids = staged(rows.groupBy("fp").agg(F.min("doc_id").alias("id")), "distinct-fingerprints")
    joined = staged(components(links(ids.select("fp")), ids), "components")
    final = ids.join(joined, "fp", "left").select("fp", F.when(F.col("head").isNull(), F.col("id")).otherwise(F.col("component")).alias("component_id"), F.coalesce("head", "fp").alias("head"))
    return rows.join(staged(final, "fingerprint-components"), "fp")


def near_groups(docs: DataFrame, shingle: int = SHINGLE) -> DataFrame:
    """(doc_id, fingerprint, component_id), one row for each row of docs."""
    return _grouped(docs, shingle).select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op10_simhash(spark, sf_dir: str) -> DataFrame:
    return near_groups(table(spark, sf_dir, "documents"))
