"""Near-dedup by SimHash: links are pairs whose sets of 5-word shingles reach Jaccard 0.8.

A set has a fingerprint of 256 bits: each bit is 1 if set in over half the hashes of its shingles. Two sets at 0.8 differ
in about 39 of them (48 where they have four and five shingles), in over ``FAR`` with a probability of about 1e-9, two
unrelated ones in 128. Multi-index hashing finds the pairs: the bits lie in 42 blocks of six, and fingerprints that
differ in at most 41 bits agree in a block by the pigeonhole principle; with more differences a block without any is
all but certain, and about 15 are to be expected. Each fingerprint is moved once for each block, to the others that
agree in it. A group of those is searched in memory by further indexes over some of the other bits, as many as the
number of nodes asks for (``_indexes``), so that unrelated fingerprints hardly meet, and by more of them for sets of at
most ``SMALL`` shingles, whose fingerprints differ more. All of them together may still miss a pair close to 0.8, very
rarely (README). A pair that meets goes on if its
set sizes allow 0.8 and its fingerprints differ in at most ``FAR`` bits. Every pair that goes on is counted out on the
whole sets, so no link is wrong, and nothing but fingerprints proposes pairs.

Texts of equal sets are one node. Sets of so few shingles that no other set can reach 0.8 are not searched. The search
takes turns. In each, a node chooses among those of other components that it may link to: the first in the turn's order
of those within ``CLOSE`` bits, and the closest. Choices travel packed, and the best of all groups are counted out, so a
turn brings at most two pairs a node, however large its group is. A last search then lists what is still of different components: all
pairs where an index brings at most ``crowded`` nodes together, else a crowded bucket, of which only nodes outside its
largest component come out, and two inside. Nodes that meet more than ``crowded`` others in a group are such a bucket too.
The nodes that come out are an explicit set of queries: in groups of a bounded size they are held against the whole sets
of all nodes whose component a bucket has, each task taking its own, and only links that join two components come out:
first those among the queries of a group, then at most one for each component that a task meets. So every pair that an
index brings together is decided or already in one component, and no step lists the pairs of a large group. What is left
costs its number times the crowd's; the turns keep it small where groups hang together.

Defined results: null text is the empty text; texts without words are near copies of one another only; fewer words
than a shingle give one shingle of all of them; rows that repeat a doc_id are members like others; a null doc_id
comes after all others, and a component without any has null as its id; of each component exactly one row stays, that
of its least doc_id and then least text digest; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import functools
import itertools
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import keep_rows, staged, whole_text
from .simhash import components, fingerprint_of, shingle_hashes  # noqa: F401

SHINGLE, LEAST = 5, 0.8
WORDS, BLOCK, FAR, SMALL = 4, 6, 86, 5
#: bits that likely links differ in at most, and nodes whose choices meet in a task
CLOSE, PART = 48, 1 << 14
BLOCKS = 64 * WORDS // BLOCK
#: nodes of a bucket that are paired up, turns of choices, and how many nodes (and bytes of their sets) a group of queries has
CROWDED, TURNS, LEFT, LEFT_BYTES = 16, 4, 2048, 1 << 23
_ODD = np.random.default_rng(42).integers(0, 1 << 63, (2, WORDS), dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_FP = [f"f{i}" for i in range(WORDS)]
#: a fingerprint as it is moved
_MOVED = np.dtype([("node", "<i8"), ("label", "<i8"), ("n", "<i4"), ("f", "<u8", (WORDS,))])
#: a node's choice as it is moved
_PICK = np.dtype([("node", "<i8"), ("other", "<i8"), ("kind", "<i4"), ("by", "<u8")])


def shingle_set(text: str, shingle: int = SHINGLE) -> np.ndarray:
    """The distinct shingle hashes of a text, in order."""
    return np.unique(shingle_hashes(text, shingle))


def wide_fingerprint(grams: np.ndarray) -> np.ndarray:
    """The 64 * WORDS bits of a set's fingerprint: a bit is 1 if set in over half of the shingles' hashes. The first
    word's hashes are those of the set, the others are mixed from them."""
    ones = np.zeros(64 * WORDS, dtype=np.int64)
    for i in range(0, len(grams), 255):  # so many bits are counted in a byte, eight bytes at a time
        h = grams[i : i + 255, None] * _ODD[0]
        h = (h ^ (h >> np.uint64(32))) * _ODD[1]
        h ^= h >> np.uint64(29)
        h[:, 0] = grams[i : i + 255]
        bits = np.unpackbits(h.astype("<u8", copy=False).view(np.uint8), bitorder="little").view("<u8")
        ones += bits.reshape(-1, 8 * WORDS).sum(axis=0).view(np.uint8)
    return np.packbits(2 * ones > len(grams), bitorder="little").view("<u8")


def signed(df: DataFrame, shingle: int = SHINGLE) -> DataFrame:
    """(doc_id, sha, node, n, f0, f1, f2, f3) of every row of df; the fs are the fingerprint."""
    schema = "doc_id long, sha string, node long, n int, " + ", ".join(f"{f} long" for f in _FP)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 250):
                b = whole.slice(at, 250)
                sets = [shingle_set(t, shingle) for t in b.column("text").to_pylist()]
                prints = np.array([wide_fingerprint(g) for g in sets], dtype=np.uint64).reshape(-1, WORDS).view(np.int64)
                nodes = np.array([xxhash.xxh3_64_intdigest(g.tobytes()) for g in sets], dtype=np.uint64).view(np.int64)
                yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("sha"), pa.array(nodes), pa.array([len(g) for g in sets], pa.int32()), *(pa.array(prints[:, i].copy()) for i in range(WORDS))], ["doc_id", "sha", "node", "n", *_FP])

    return df.select(F.col("doc_id").cast("long").alias("doc_id"), F.sha2(whole_text(), 256).alias("sha"), whole_text().alias("text")).mapInArrow(run, schema)


@functools.lru_cache(64)
def _indexes(n: int, block: int) -> np.ndarray:
    """The masks of the indexes that are searched among n nodes, for those that agree in a block: each takes so many of
    the other bits that 16 times the nodes have values of their own. A pair at 0.8 agrees in one more bit with a
    probability of about 0.85, so that each bit asks for so many more indexes."""
    bits = max(8, math.ceil(math.log2(max(n, 1))) + 4 - BLOCK)
    random, out = np.random.default_rng([42, block]), []
    others = np.setdiff1d(np.arange(64 * WORDS), np.arange(block * BLOCK, (block + 1) * BLOCK))
    for _ in range(max(32, math.ceil(96 * 0.8485 ** (15 - bits)))):
        mask = np.zeros(64 * WORDS, dtype=np.uint8)
        mask[random.choice(others, bits, replace=False)] = 1
        out.append(np.packbits(mask, bitorder="little").view("<u8"))
    return np.array(out)


def _moved(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(block, value, prints): the fingerprints of a batch once for each block, those that agree in it in one row."""
    for t in batches:
        rows = np.empty(t.num_rows, dtype=_MOVED)
        rows["node"], rows["n"] = t.column("node").to_numpy(), t.column("n").to_numpy()
        rows["label"] = t.column("label").to_numpy() if "label" in t.schema.names else rows["node"]
        for i, f in enumerate(_FP):
            rows["f"][:, i] = t.column(f).to_numpy().view(np.uint64)
        bits = np.unpackbits(rows["f"].astype("<u8").view(np.uint8), axis=1, bitorder="little")[:, : BLOCKS * BLOCK].reshape(-1, BLOCKS, BLOCK)
        values = np.packbits(bits, axis=2, bitorder="little")[:, :, 0]
        blocks, of, prints = [], [], []
        for k in range(BLOCKS):
            order = np.argsort(values[:, k], kind="stable")
            some, first = np.unique(values[order, k], return_index=True)
            blocks += [k] * len(some)
            of += some.tolist()
            prints += [x.tobytes() for x in np.split(rows[order], first[1:])] if len(some) else []
        yield pa.RecordBatch.from_arrays([pa.array(blocks, pa.int32()), pa.array(of, pa.int32()), pa.array(prints, pa.binary())], ["block", "value", "prints"])


def _met(prints: np.ndarray, masks: np.ndarray, crowded: int) -> Iterator[tuple[np.ndarray, int]]:
    """(places, length) of fingerprints (one row a word) that have equal values in an index: runs of one length end to end
    where they are not crowded, one by one where they are; each run in order."""
    m = prints.shape[1]
    if m < 2:
        return
    shift = np.uint64(max(1, (m - 1).bit_length()))
    low = (np.uint64(1) << shift) - np.uint64(1)
    key = np.zeros((len(masks), m), dtype=np.uint64)
    for f, bits, odd in zip(prints, masks.T, _ODD[1]):
        key += (f & bits[:, None]) * odd
    key &= ~low
    key |= np.arange(m, dtype=np.uint64)
    key.sort(axis=1)
    same = np.zeros(key.shape, dtype=bool)  # as the one before
    np.equal(key[:, 1:] >> shift, key[:, :-1] >> shift, out=same[:, 1:])
    hits = np.flatnonzero(same)
    if not len(hits):
        return
    first = np.flatnonzero(np.concatenate([[True], np.diff(hits) > 1]))
    starts, lengths = hits[first] - 1, np.diff(np.append(first, len(hits))) + 1
    flat = key.ravel()
    for length in np.unique(lengths).tolist():
        of = starts[lengths == length]
        for part in of[:, None] if length > crowded else of[None]:
            yield (flat[part[:, None] + np.arange(length)] & low).astype(np.int64).ravel(), length


def _group(t: pa.Table, turn: int = 0) -> np.ndarray:
    """The fingerprints of a group in an order by their nodes' hashes, the same in each group of a turn."""
    rows = np.concatenate([np.frombuffer(x.as_py(), dtype=_MOVED) for x in t.column("prints")])
    return rows[np.argsort(_mixed(rows["node"], turn))]


def _mixed(nodes: np.ndarray, turn: int = 0) -> np.ndarray:
    mixed = (nodes.view(np.uint64) ^ np.uint64(turn)) * _ODD[turn % 2, turn % WORDS]
    return mixed ^ (mixed >> np.uint64(31))


def _runs(rows: np.ndarray, block: int, n: int, small: int | None, crowded: int) -> Iterator[np.ndarray]:
    """Places of fingerprints that an index brings together: a row for each run of one length, one row if crowded."""
    prints, few = np.ascontiguousarray(rows["f"].T), np.flatnonzero(rows["n"] <= SMALL)
    for some, masks in ((np.arange(len(rows)), _indexes(n, block)), (few, _indexes(len(few) << BLOCK if small is None else small, block))):
        of = prints[:, some]
        for at in range(0, len(masks), step := max(1, 65536 // max(1, len(some)))):
            for where, length in _met(of, masks[at : at + step], crowded):
                yield some[where].reshape(-1, length)


def _compared(rows: np.ndarray, where: np.ndarray, least: float, crowded: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(i, j, bits that differ) of the places in a run that may link: all pairs of it, or of a crowded run each place with
    the first, the last and the next."""
    length = where.shape[1]
    if length > crowded:
        run = where[0]
        some = [(np.full(length - 1, run[0]), run[1:]), (run[1:-1], np.full(length - 2, run[-1])), (run[1:-1], run[2:])]
    else:
        some = [(where[:, x], where[:, y]) for x, y in itertools.combinations(range(length), 2)]
    sizes = rows["n"]
    for i, j in some:
        apart = np.bitwise_count(rows["f"][i] ^ rows["f"][j]).sum(axis=1, dtype=np.int64)
        may = (apart <= FAR) & (np.minimum(sizes[i], sizes[j]) >= least * np.maximum(sizes[i], sizes[j]) - 1e-9)
        yield i[may], j[may], apart[may]


def _packed(picks: np.ndarray, parts: int) -> pa.Table:
    """(part, picks): those of a node are in one part."""
    part = (_mixed(picks["node"]) >> np.uint64(7)) % np.uint64(parts)
    held = np.unique(part)
    return pa.table({"part": pa.array(held.astype(np.int32)), "picks": pa.array([picks[part == k].tobytes() for k in held], pa.binary())})


def _chosen(n: int, small: int, least: float, crowded: int, parts: int, turn: int = 0):
    """A function of a group of fingerprints that agree in a block, which yields (part, picks): for each node, of the close
    ones with another label that it may link to, the first in the turn's order, and the closest (turns after the first: with some
    bits of chance); and itself if a crowded run left it without any."""

    def run(t: pa.Table) -> pa.Table:
        rows = _group(t, turn)
        m, every, labels = len(rows), np.iinfo(np.int64).max, rows["label"]
        hub, close, alone = np.full(m, every), np.full(m, every), np.zeros(m, dtype=bool)
        for where in _runs(rows, t.column("block")[0].as_py(), n, small, crowded):
            if where.shape[1] > crowded:
                alone[where[0]] = True
            where = where[(labels[where] != labels[where[:, :1]]).any(axis=1)]
            for i, j, apart in _compared(rows, where, least, crowded) if len(where) else ():
                other = labels[i] != labels[j]
                i, j, apart = i[other], j[other], apart[other]
                near = apart <= CLOSE
                if turn:
                    apart = apart + ((i * 31 + j * 17 + turn) % 13)
                for x, y in ((i, j), (j, i)):
                    np.minimum.at(close, x, apart * m + y)
                    np.minimum.at(hub, x[near], y[near])
        x, y, z = (np.flatnonzero(of) for of in (hub < every, close < every, alone & (close == every)))
        nodes, order = rows["node"], _mixed(rows["node"], turn)
        picks = np.empty(len(x) + len(y) + len(z), dtype=_PICK)
        picks["node"] = nodes[np.concatenate([x, y, z])]
        picks["other"] = nodes[np.concatenate([hub[x], close[y] % m, z])]
        picks["kind"] = np.repeat(np.array([0, 1, 2]), [len(x), len(y), len(z)])
        picks["by"] = np.concatenate([order[hub[x]], (close[y] // m).astype(np.uint64), np.zeros(len(z), dtype=np.uint64)])
        return _packed(picks, parts)

    return run


def _best(t: pa.Table) -> pa.Table:
    """(a, b): the best of all groups' choices of each node and kind; both are the node where it has only itself."""
    picks = np.concatenate([np.frombuffer(x.as_py(), dtype=_PICK) for x in t.column("picks")])
    picks = picks[np.lexsort((picks["other"], picks["by"], picks["kind"], picks["node"]))]
    new = np.ones(len(picks), dtype=bool)
    new[1:] = (picks["node"][1:] != picks["node"][:-1]) | (picks["kind"][1:] != picks["kind"][:-1])
    a, b = picks["node"][new], picks["other"][new]
    return pa.table({"a": np.minimum(a, b), "b": np.maximum(a, b)})


def _searched(n: int, least: float, crowded: int, small: int | None = None):
    """A function of a group of labelled fingerprints that agree in a block, which yields (a, b, first, null) for pairs of
    different labels that may link (first: b is the first or the closest for a, or a for b) and (node, null, first, bucket)
    for the nodes of crowded buckets outside the most frequent label, and for two (first) of those that have it. Nodes that
    meet more than ``crowded`` others in the group make a bucket with them."""

    def run(t: pa.Table) -> pa.Table:
        block, value = t.column("block")[0].as_py(), t.column("value")[0].as_py()
        rows = _group(t)
        nodes, labels, m = rows["node"], rows["label"], len(rows)
        codes, held, bucket_of, buckets = np.empty(0, dtype=np.int64), [], np.full(m, -1, dtype=np.int64), []
        for where in _runs(rows, block, n, small, crowded):
            several = (labels[where] != labels[where[:, :1]]).any(axis=1)
            if not several.any():
                continue
            if where.shape[1] > crowded:
                _join_bucket(where[0], bucket_of, buckets)
            for i, j, apart in _compared(rows, where[several], least, crowded):
                other = labels[i] != labels[j]
                held.append((apart * m + np.minimum(i, j))[other] * m + np.maximum(i, j)[other])
            if sum(map(len, held)) > 1 << 20:
                codes, held = np.unique(np.concatenate([codes, *held])), []
        codes = np.unique(np.concatenate([codes, *held]))  # the closest come first
        i, j = codes // m % m, codes % m
        first = np.zeros(len(codes), dtype=bool)
        for order in (np.arange(len(codes)), np.lexsort((j, i)), np.lexsort((i, j))):
            for end in (i, j):
                first[order[np.unique(end[order], return_index=True)[1]]] = True
        degree = np.bincount(i, minlength=m) + np.bincount(j, minlength=m)
        if len(hot := np.flatnonzero(degree > crowded)):
            both = np.concatenate([np.stack([i, j], 1), np.stack([j, i], 1)])
            both = both[np.argsort(both[:, 0], kind="stable")]
            ends = np.searchsorted(both[:, 0], [hot, hot + 1])
            for h, low, high in zip(hot.tolist(), *ends.tolist()):
                _join_bucket(np.append(both[low:high, 1], h), bucket_of, buckets)
            stay = first | (degree[i] <= crowded) & (degree[j] <= crowded)
            i, j, first = i[stay], j[stay], first[stay]
        crowd, top, of = [np.empty(0, dtype=np.int64)], [np.empty(0, dtype=bool)], [np.empty(0, dtype=np.int64)]
        for k, b in enumerate(buckets):
            some = np.unique(np.concatenate(b))
            names, count = np.unique(labels[some], return_counts=True)
            most = labels[some] == names[count.argmax()]
            crowd += [some[most][:2], some[~most]]
            top += [np.ones(len(crowd[-2]), dtype=bool), np.zeros(len(crowd[-1]), dtype=bool)]
            of.append(np.full(len(crowd[-2]) + len(crowd[-1]), xxhash.xxh3_64_intdigest(f"{block} {value} {k}") >> 1, dtype=np.int64))
        crowd, top, of = map(np.concatenate, (crowd, top, of))
        a = np.concatenate([np.minimum(nodes[i], nodes[j]), nodes[crowd]])
        b = [pa.array(np.maximum(nodes[i], nodes[j])), pa.nulls(len(crowd), pa.int64())]
        return pa.table({"a": a, "b": pa.chunked_array(b), "first": np.concatenate([first, top]), "bucket": pa.chunked_array([pa.nulls(len(i), pa.int64()), pa.array(of)])})

    return run


def _open(n: int, small: int, least: float, crowded: int, parts: int):
    """A function of a group that yields what ``_searched`` does, packed in parts: a pair as (a, b, first), a node of a
    crowded bucket with itself."""
    search = _searched(n, least, crowded, small)

    def run(t: pa.Table) -> pa.Table:
        found = search(t).combine_chunks()
        picks = np.zeros(len(found), dtype=_PICK)
        picks["node"] = found.column("a").to_numpy()
        picks["other"] = found.column("b").combine_chunks().fill_null(0).to_numpy()
        alone = found.column("b").combine_chunks().is_null().to_numpy(zero_copy_only=False)
        picks["other"][alone] = picks["node"][alone]
        picks["kind"] = found.column("first").to_numpy()
        return _packed(picks, parts)

    return run


def _distinct(t: pa.Table) -> pa.Table:
    """(a, b, first), each once, of all groups' picks; of a pair first is true if any has it so."""
    picks = np.concatenate([np.frombuffer(x.as_py(), dtype=_PICK) for x in t.column("picks")])
    picks = picks[np.lexsort((-picks["kind"], picks["other"], picks["node"]))]
    new = np.ones(len(picks), dtype=bool)
    same = (picks["node"][1:] == picks["node"][:-1]) & (picks["other"][1:] == picks["other"][:-1])
    alone = picks["node"][1:] == picks["other"][1:]
    new[1:] = ~same | alone & (picks["kind"][1:] != picks["kind"][:-1])
    picks = picks[new]
    return pa.table({"a": picks["node"].copy(), "b": picks["other"].copy(), "first": picks["kind"] == 1})


def _join_bucket(some: np.ndarray, bucket_of: np.ndarray, buckets: list[list[np.ndarray]]) -> None:
    """Adds nodes that an index brought together to the bucket that most of those known are in, if these are an eighth of
    them at least, or makes them a new one."""
    known = bucket_of[some]
    known = known[known >= 0]
    most = int(np.bincount(known).argmax()) if len(known) else -1
    if most < 0 or 8 * np.count_nonzero(known == most) < len(some):
        most = len(buckets)
        buckets.append([])
    new = some[bucket_of[some] != most]
    if len(new):
        buckets[most].append(new)
        bucket_of[new[bucket_of[new] < 0]] = most


def _in_blocks(prints: DataFrame):
    """Labelled or plain fingerprints, grouped by blocks and values in them."""
    return prints.mapInArrow(_moved, "block int, value int, prints binary").groupBy("block", "value")


def _sets(docs: DataFrame, nodes: DataFrame, ids: DataFrame, shingle: int) -> DataFrame:
    """(node, grams) of nodes, from the text of the documents they stand for. At most 2^20 residues of doc_ids are
    broadcast, so that other texts mostly stay where they are."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 250):
                grams = [shingle_set(t, shingle).tobytes() for t in whole.column("text").slice(at, 250).to_pylist()]
                nodes = np.array([xxhash.xxh3_64_intdigest(g) for g in grams], dtype=np.uint64).view(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(nodes), pa.array(grams, pa.binary())], ["node", "grams"])

    some = nodes.join(ids, F.col("node") == F.col("fp")).select(F.pmod(F.coalesce("id", F.lit(-1)), F.lit(1 << 20)).alias("__some")).distinct()
    asked = docs.join(F.broadcast(some), F.pmod(F.coalesce(F.col("doc_id").cast("long"), F.lit(-1)), F.lit(1 << 20)) == F.col("__some"), "left_semi")
    sets = asked.select(whole_text().alias("text")).mapInArrow(run, "node long, grams binary")
    return staged(sets.join(nodes, "node", "left_semi").dropDuplicates(["node"]), "near-sets")


def verified(pairs: DataFrame, docs: DataFrame, ids: DataFrame, shingle: int, least: float) -> DataFrame:
    """The pairs (a, b) of nodes whose sets reach ``least``."""
    pairs = staged(pairs.distinct(), "near-pairs")
    nodes = pairs.select(F.col("a").alias("node")).unionByName(pairs.select(F.col("b").alias("node"))).distinct()
    sets = _sets(docs, staged(nodes, "near-nodes"), ids, shingle)
    both = pairs.join(sets.select(F.col("node").alias("a"), F.col("grams").alias("x")), "a").join(sets.select(F.col("node").alias("b"), F.col("grams").alias("y")), "b")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in batches:
            keep = []
            for x, y in zip(t.column("x"), t.column("y")):
                u, v = np.frombuffer(x.as_py(), dtype="<u8"), np.frombuffer(y.as_py(), dtype="<u8")
                k = len(np.intersect1d(u, v, assume_unique=True))
                keep.append(k >= least * (len(u) + len(v) - k) - 1e-9)
            yield t.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return staged(both.select("a", "b", "x", "y").mapInArrow(run, "a long, b long"), "near-links")


def _labels(nodes: DataFrame, joined: DataFrame) -> DataFrame:
    """nodes (node, ...) with the label of their component, or themselves."""
    return nodes.join(joined.select(F.col("fp").alias("__fp"), "head"), F.col("node") == F.col("__fp"), "left").withColumn("label", F.coalesce("head", "node")).drop("__fp", "head")


def _stars(sets: DataFrame, queries: DataFrame, least: float) -> DataFrame:
    """(a, b): links of a bounded number of queries with all sets (node, label, grams), no more than join their components."""
    got, up = queries.toArrow(), {}
    own = pa.Table.from_batches(_against(got, least, up)(iter(got.to_batches())), pa.schema([("a", pa.int64()), ("b", pa.int64())]))
    return sets.mapInArrow(_against(got, least, up), "a long, b long").unionByName(sets.sparkSession.createDataFrame(own)).distinct()


def _links_of_the_rest(crowd: DataFrame, labels: DataFrame, docs: DataFrame, ids: DataFrame, shingle: int, least: float) -> DataFrame:
    """(a, b): links of the nodes of crowded buckets that are not ``first`` with all of (node, label) whose label some node
    of a bucket has."""
    own = labels.join(crowd.groupBy("node").agg(F.bool_or(~F.col("first")).alias("left")), "node")
    own = staged(own, "near-crowd")
    data = labels.join(own.select("label").distinct(), "label", "left_semi").join(own.where("left").select("node", "left"), "node", "left")
    data = staged(data.select("node", "label", F.coalesce("left", F.lit(False)).alias("left")), "near-crowd")
    sets = staged(_sets(docs, data.select("node"), ids, shingle).join(data, "node"), "near-crowd-sets")
    rest = sets.where("left")
    n, size = rest.agg(F.count("*"), F.coalesce(F.sum(F.length("grams")), F.lit(0))).first()
    groups, found = max(1, -(-n // LEFT), -(-size // LEFT_BYTES)), None
    for g in range(groups):  # of about LEFT rows
        some = staged(_stars(sets, rest.where(F.pmod(F.xxhash64("node"), F.lit(groups)) == g).select("node", "label", "grams"), least), "near-late")
        found = some if found is None else found.unionByName(some)
    return found


def _root(up: dict[int, int], x: int) -> int:
    while (y := up.get(x, x)) != x:
        up[x] = x = up.get(y, y)
    return x


def _against(queries: pa.Table, least: float, up: dict[int, int]):
    """A function of batches (node, label, grams) that yields links with the queries: of those between two components one,
    and none where earlier ones lead from one to the other. ``up`` has what is known of that, and learns it."""
    own, labels = queries.column("node").to_numpy(), queries.column("label").to_numpy()
    sets = [np.frombuffer(x.as_py(), dtype="<u8") for x in queries.column("grams")]
    sizes = np.array([len(x) for x in sets], dtype=np.int64)
    grams, owner = np.concatenate([*sets, np.empty(0, "<u8")]), np.repeat(np.arange(len(sets)), sizes)
    order = np.argsort(grams, kind="stable")
    grams, owner = grams[order], owner[order]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in batches:
            a, b = [], []
            for node, label, x in zip(t.column("node").to_pylist(), t.column("label").to_pylist(), t.column("grams")):
                mine = np.frombuffer(x.as_py(), dtype="<u8")
                low, high = np.searchsorted(grams, mine, "left"), np.searchsorted(grams, mine, "right")
                n = high - low
                found = np.flatnonzero(n)
                if not len(found):
                    continue
                n = n[found]
                at = np.repeat(low[found] - np.concatenate([[0], np.cumsum(n)[:-1]]), n) + np.arange(n.sum())  # all places of all shared grams
                both = np.bincount(owner[at], minlength=len(own))
                hit = (both >= least * (sizes + len(mine) - both) - 1e-9) & (both > 0) & (labels != label)
                for other, theirs in zip(own[hit].tolist(), labels[hit].tolist()):
                    if (x := _root(up, label)) != (y := _root(up, theirs)):
                        up[x] = y
                        a.append(min(other, node))
                        b.append(max(other, node))
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])

    return run


def _grouped(docs: DataFrame, shingle: int, least: float, crowded: int = CROWDED) -> DataFrame:
    """(doc_id, sha, component_id, head) for each row of docs; head is the node of the component's first document."""
    rows = staged(signed(docs, shingle), "near-signatures")
    ids = staged(rows.groupBy("node").agg(F.min("doc_id").alias("id")).withColumnRenamed("node", "fp"), "near-ids")
    per_node = staged(rows.groupBy("node").agg(*(F.first(c).alias(c) for c in ("n", *_FP))), "near-nodes")
    asked = per_node.where(F.col("n") >= least * (F.col("n") + 1) - 1e-9).select("node", "n", *_FP)  # others have no other set at least
    n, small = asked.agg(F.count("*"), F.count_if(F.col("n") <= SMALL)).first()
    parts, edges, joined, met = -(-n // PART) or 1, None, None, asked
    for turn in range(TURNS):
        picks = _in_blocks(met).applyInArrow(_chosen(n, small, least, crowded, parts, turn), "part int, picks binary")
        picks = staged(picks.groupBy("part").applyInArrow(_best, "a long, b long"), "near-picks")
        new = verified(picks.where("a <> b"), docs, ids, shingle, least)
        if turn == 0:
            some = picks.select(F.col("a").alias("node")).unionByName(picks.select(F.col("b").alias("node"))).distinct()
            asked = staged(asked.join(some, "node"), "near-asked")  # others meet none that they may link to
        if turn == 0 or (many := new.count()):
            edges = staged(new if turn == 0 else edges.unionByName(new).distinct(), "near-edges")
            joined = staged(components(edges, ids), "near-components")
            met = staged(_labels(asked, joined), "near-asked")
        if turn and many < met.count() / 100:  # what is left hardly hangs together
            break
    found = _in_blocks(met).applyInArrow(_open(n, small, least, crowded, parts), "part int, picks binary")
    found = staged(found.groupBy("part").applyInArrow(_distinct, "a long, b long, first boolean"), "near-candidates")
    pairs, crowd = found.where("a <> b"), found.where("a = b").select(F.col("a").alias("node"), "first")
    for of in ("first", "not first"):
        some = pairs.where(of).select(F.col("a").alias("node"), "b")
        some = _labels(some, joined).select(F.col("node").alias("a"), F.col("label").alias("x"), F.col("b").alias("node"))
        new = verified(_labels(some, joined).where("x <> label").select("a", F.col("node").alias("b")), docs, ids, shingle, least)
        if new.limit(1).count():
            edges = staged(edges.unionByName(new).distinct(), "near-edges")
            joined = staged(components(edges, ids), "near-components")
    if crowd.limit(1).count():
        late = _links_of_the_rest(crowd, _labels(asked.select("node"), joined), docs, ids, shingle, least)
        if late.limit(1).count():
            joined = staged(components(edges.unionByName(late), ids), "near-components")
    own = ids.join(joined, "fp", "left")
    final = own.select(F.col("fp").alias("node"), F.when(F.col("head").isNull(), F.col("id")).otherwise(F.col("component")).alias("component_id"), F.coalesce("head", "fp").alias("head"))
    return rows.select("doc_id", "sha", "node").join(staged(final, "near-node-components"), "node").select("doc_id", "sha", "component_id", "head")


def near_components(docs: DataFrame, shingle: int = SHINGLE, least: float = LEAST, crowded: int = CROWDED) -> DataFrame:
    """(doc_id, component_id) for each row of docs; component_id is the least doc_id that links lead to."""
    return _grouped(docs, shingle, least, crowded).select("doc_id", "component_id")


def drop_near_copies(docs: DataFrame, shingle: int = SHINGLE, least: float = LEAST) -> DataFrame:
    """One row of docs for each group, with their columns as they are."""
    first = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "sha")
    per_row = staged(_grouped(docs, shingle, least).groupBy("head", "doc_id", "sha").agg(F.count("*").alias("n")), "near-rows")
    stay = per_row.groupBy("head").agg(F.min(F.struct(first.alias("first"), "n")).alias("m"))
    return keep_rows(docs, staged(stay.select("m.first.doc_id", "m.first.sha", (F.col("m.n") > 1).alias("again")), "near-stay"))
