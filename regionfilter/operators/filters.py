"""Building and probing filters.

A filter is a table of set words (region, word, bits), 32 bits a word, made by one partial and one final bit_or:
the shuffle carries at most as many rows as there are words, keyed by (region, word), so a region that holds most
keys is spread like any other. Regions with rate 1 store nothing and always answer yes; regions without keys
answer no; neither is looked up.

Probing has four ways. ``array`` makes a constant of all words of a filter of a checked size and tests bits with
expressions. ``broadcast`` joins chunks of 512 bits of a filter of a checked size once for each position; ``scatter``
answers the same at any size, by a shuffle of positions to their chunks. ``shuffle`` uses the blocked layout, in which
all bits of an element lie in one block: a single equi-join on (region, block), whatever the filter's size. ``auto``
picks by layout and size.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.formulas import seg_of
from ..functions.hashing import bases, positions
from ..plans.planner import Plan
from ..schemas import require
from ..sources.io import staged

WORD = 32
BLOCK_BITS = 512
#: bits of a long in a chunk, and of a built-in bitmap
LONG, BITMAP_BITS = 64, 32768
#: most bits of a filter whose words are a constant of the plan, and that travel as broadcast chunks (2^19 rows, about
#: 64 MB as a hashed table)
ARRAY_BITS, BROADCAST_BITS = 1 << 22, 1 << 28


def with_region(df: DataFrame, plan: Plan) -> DataFrame:
    """df with region 1..k of its seg, by literals; a plan of one region needs no seg."""
    if plan.k > 1:
        require(df, "seg")
    region = F.lit(plan.k)
    for r in range(plan.k - 1, 0, -1):
        region = F.when(F.col("seg") < plan.cuts[r], F.lit(r)).otherwise(region)
    return df.withColumn("region", region)


def _of_region(values: list[int], kind: str = "bigint") -> Column:
    return F.element_at(F.array(*(F.lit(v).cast(kind) for v in values)), F.col("region"))


def _sizes(plan: Plan, sizing: str) -> tuple[list[int], list[int]]:
    built = [plan.built(r, sizing) for r in range(plan.k)]
    return [m for m, _ in built], [h for _, h in built]


def _positions(df: DataFrame, plan: Plan, family: str, sizing: str) -> DataFrame:
    m, h = _sizes(plan, sizing)
    return df.withColumn("positions", positions(F.col("elem"), F.greatest(F.lit(1), _of_region(h, "int")), F.greatest(F.lit(1).cast("bigint"), _of_region(m)), family))


def _words(rows: DataFrame, *by: str) -> DataFrame:
    bit = rows.select(*by, F.explode("positions").alias("p"))
    word = F.floor(F.col("p") / WORD).cast("bigint")
    one = F.call_function("shiftleft", F.lit(1).cast("bigint"), F.pmod("p", F.lit(WORD)).cast("int"))
    return bit.select(*by, word.alias("word"), one.alias("bit")).groupBy(*by, "word").agg(F.bit_or("bit").alias("bits"))


def build(keys: DataFrame, plan: Plan, family: str = "md5", sizing: str = "formula") -> DataFrame:
    """(region, word, bits): a separate array for each region."""
    m, _ = _sizes(plan, sizing)
    rows = with_region(keys.where("elem is not null"), plan)
    return _words(_positions(rows.where(_of_region(m) > 0), plan, family, sizing), "region")


def _shared_positions(keys: DataFrame, plan: Plan, m: int, family: str) -> DataFrame:
    _, h = _sizes(plan, "formula")
    rows = with_region(keys.where("elem is not null"), plan).where(_of_region(h, "int") > 0)
    return rows.withColumn("positions", positions(F.col("elem"), F.greatest(F.lit(1), _of_region(h, "int")), m, family))


def build_shared(keys: DataFrame, plan: Plan, m: int, family: str = "md5") -> DataFrame:
    """(word, bits): one array of m bits for all regions; only the number of hashes depends on the region."""
    return _words(_shared_positions(keys, plan, m, family))


def _chunks(rows: DataFrame, *by: str) -> DataFrame:
    """(by..., chunk, longs): the bits of positions, 512 of them in a row. A task's partial rows take little more room than
    the bits themselves."""
    bit = rows.select(*by, F.explode("positions").alias("p"))
    bit = bit.select(*by, F.shiftright("p", 9).alias("chunk"), F.shiftright("p", 6).bitwiseAND(F.lit(7)).alias("at"), _one("p", LONG).alias("bit"))
    every = [F.coalesce(F.bit_or(F.when(F.col("at") == i, F.col("bit"))), F.lit(0).cast("bigint")) for i in range(BLOCK_BITS // LONG)]
    return bit.groupBy(*by, "chunk").agg(F.array(*every).alias("longs"))


def _chunks_of(words: DataFrame, *by: str) -> DataFrame:
    """The same from (by..., word, bits)."""
    bits = F.call_function("shiftleft", F.col("bits"), (F.col("word").bitwiseAND(F.lit(1)) * WORD).cast("int"))
    part = words.select(*by, F.shiftright("word", 4).alias("chunk"), F.shiftright("word", 1).bitwiseAND(F.lit(7)).alias("at"), bits.alias("bits"))
    every = [F.coalesce(F.bit_or(F.when(F.col("at") == i, F.col("bits"))), F.lit(0).cast("bigint")) for i in range(BLOCK_BITS // LONG)]
    return part.groupBy(*by, "chunk").agg(F.array(*every).alias("longs"))


def _one(p, size: int) -> Column:
    """The bit of a position in its word or long."""
    return F.call_function("shiftleft", F.lit(1).cast("bigint"), F.pmod(p, F.lit(size)).cast("int"))


def build_chunks(keys: DataFrame, plan: Plan, family: str = "md5", sizing: str = "formula") -> DataFrame:
    """(region, chunk, longs): the bits of ``build``, 512 in a row."""
    m, _ = _sizes(plan, sizing)
    rows = with_region(keys.where("elem is not null"), plan)
    return _chunks(_positions(rows.where(_of_region(m) > 0), plan, family, sizing), "region")


def build_shared_chunks(keys: DataFrame, plan: Plan, m: int, family: str = "md5") -> DataFrame:
    """(chunk, longs): the bits of ``build_shared``, 512 in a row."""
    return _chunks(_shared_positions(keys, plan, m, family))


def _block_offsets(df: DataFrame, plan: Plan, family: str, sizing: str) -> DataFrame:
    """block of each element, and where its bits there begin and how far they are apart."""
    m, _ = _sizes(plan, sizing)
    blocks = [-(-x // BLOCK_BITS) for x in m]
    h1, h2 = bases(F.col("elem"), family)
    n = F.greatest(F.lit(1).cast("bigint"), _of_region(blocks))
    inner = F.call_function("div", h1, n)  # in whole numbers: a quotient of doubles would lose bits
    step = F.pmod(h2, F.lit(BLOCK_BITS)).bitwiseOR(F.lit(1).cast("bigint"))
    return df.withColumn("block", F.pmod(h1, n)).withColumn("__at", F.pmod(inner, F.lit(BLOCK_BITS)).cast("int")).withColumn("__step", step.cast("int"))


def _block_positions(df: DataFrame, plan: Plan, family: str, sizing: str) -> DataFrame:
    """block of each element, and the positions of its bits there."""
    return _positions_in_block(_block_offsets(df, plan, family, sizing), plan, sizing)


def _positions_in_block(df: DataFrame, plan: Plan, sizing: str) -> DataFrame:
    _, h = _sizes(plan, sizing)
    at = F.transform(F.sequence(F.lit(0), F.greatest(F.lit(1), _of_region(h, "int")) - 1), lambda i: F.pmod(F.col("__at") + i * F.col("__step"), F.lit(BLOCK_BITS)))
    return df.withColumn("positions", at).drop("__at", "__step")


def build_blocked(keys: DataFrame, plan: Plan, family: str = "xx", sizing: str = "formula") -> DataFrame:
    """(region, block, words array<bigint>): one row for each block of 512 bits that holds a key."""
    m, _ = _sizes(plan, sizing)
    rows = _block_positions(with_region(keys.where("elem is not null"), plan).where(_of_region(m) > 0), plan, family, sizing)
    words = _words(rows, "region", "block")
    every = [F.coalesce(F.bit_or(F.when(F.col("word") == w, F.col("bits"))), F.lit(0).cast("bigint")) for w in range(BLOCK_BITS // WORD)]
    return words.groupBy("region", "block").agg(F.array(*every).alias("words"))


def build_any(keys: DataFrame, plan: Plan, family: str = "auto", sizing: str = "formula") -> DataFrame:
    """The layout that ``probe`` can read by 'auto' at the plan's size: blocks above BROADCAST_BITS, else as ``build_plain``."""
    if sum(_sizes(plan, sizing)[0]) > BROADCAST_BITS:
        return build_blocked(keys, plan, "xx" if family == "auto" else family, sizing)
    return build_plain(keys, plan, "md5" if family == "auto" else family, sizing)


def build_plain(keys: DataFrame, plan: Plan, family: str = "md5", sizing: str = "formula") -> DataFrame:
    """The bits of ``build`` at any size: words, and chunks where these are too many for a constant."""
    return (build_chunks if sum(_sizes(plan, sizing)[0]) > ARRAY_BITS else build)(keys, plan, family, sizing)


def build_bitmap(keys: DataFrame, plan: Plan, family: str = "xx") -> DataFrame:
    """(region, bucket, bitmap): built-in bitmaps of 32768 bits."""
    m, _ = _sizes(plan, "formula")
    rows = _positions(with_region(keys.where("elem is not null"), plan).where(_of_region(m) > 0), plan, family, "formula")
    bits = rows.select("region", F.explode("positions").alias("p")).withColumn("p", F.col("p") + 1)  # bitmaps count from one
    return bits.groupBy("region", F.bitmap_bucket_number("p").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("p")).alias("bitmap"))


def build_fingerprints(keys: DataFrame, plan: Plan, family: str = "xx") -> DataFrame:
    """(region, bucket, prints array): short fingerprints in buckets of about four keys, an exact-match filter kind.
    A probe is one look-up; its rate is about 2 ** -bits times the bucket's fill."""
    rows = with_region(keys.where("elem is not null"), plan)
    rows = rows.where(_of_region([n if 0 < n and x < 1 else 0 for n, x in zip(plan.n_keys, plan.rates)]) > 0)
    return _prints(rows, plan, family).groupBy("region", "bucket").agg(F.collect_set("print").alias("prints"))


def _prints(rows: DataFrame, plan: Plan, family: str) -> DataFrame:
    import math

    bits = [min(50, max(1, math.ceil(math.log2(1 / x)) + 2)) if 0 < x < 1 else 1 for x in plan.rates]
    h1, h2 = bases(F.col("elem"), family)
    return rows.withColumn("bucket", F.pmod(h1, F.greatest(F.lit(1).cast("bigint"), _of_region([-(-n // 4) for n in plan.n_keys])))).withColumn("print", F.pmod(h2, _of_region([1 << b for b in bits])))


def merge(*filters: DataFrame) -> DataFrame:
    """The filter of all keys of filters with one plan: bits only ever rise."""
    out = filters[0]
    for f in filters[1:]:
        out = out.unionByName(f)
    by = [c for c in out.columns if c != "bits"]
    return out.groupBy(*by).agg(F.bit_or("bits").alias("bits"))


def _without_lookup(plan: Plan) -> Column:
    """True, false, or null where a look-up decides."""
    fixed = [False if n == 0 else True if x >= 1 else None for n, x in zip(plan.n_keys, plan.rates)]
    return F.element_at(F.array(*(F.lit(v).cast("boolean") for v in fixed)), F.col("region"))


def packed(filt: DataFrame, plan: Plan, sizing: str = "formula") -> tuple[Column, list[int]]:
    """All words of a filter of a checked size as one constant array, and where each region's begin. A constant is
    referred to, not copied into rows as a joined column would be."""
    m, _ = _sizes(plan, sizing)
    if sum(m) > ARRAY_BITS:
        raise ValueError(f"{sum(m)} bits are too many for a constant; probe with strategy 'broadcast' or 'shuffle'")
    begins, at = [], 0
    for x in m:
        begins.append(at)
        at += -(-x // WORD)
    words = [0] * max(1, at)
    for r in filt.select("region", "word", "bits").collect():  # at most ARRAY_BITS / WORD rows
        words[begins[r["region"] - 1] + r["word"]] = r["bits"]
    return F.split(F.lit(",".join(map(str, words))), ",").cast("array<bigint>"), begins


def probe(df: DataFrame, filt: DataFrame, plan: Plan, strategy: str = "auto", family: str = "auto", sizing: str = "formula") -> DataFrame:
    """df (elem, seg, ...) with region and maybe. ``filt`` is from ``build`` or ``build_chunks``, or from ``build_blocked`` for
    'shuffle'; the family of hashes is the builder's, by default that of either. A filter too large for 'broadcast' is
    probed by 'scatter', with the same answers."""
    require(df, "elem")
    m, _ = _sizes(plan, sizing)
    if strategy == "auto":
        strategy = "shuffle" if "block" in filt.columns else "array" if sum(m) <= ARRAY_BITS and "word" in filt.columns else "broadcast"
    if strategy == "broadcast" and sum(m) > BROADCAST_BITS:
        strategy = "scatter"
    family = ("xx" if strategy == "shuffle" else "md5") if family == "auto" else family
    rows = with_region(df, plan)
    fixed = F.when(F.col("elem").isNull(), F.lit(False)).otherwise(_without_lookup(plan))
    if strategy == "array":
        words, begins = packed(filt, plan, sizing)
        _, h = _sizes(plan, sizing)
        h1, h2 = bases(F.col("elem"), family)
        size = F.greatest(F.lit(1).cast("bigint"), _of_region(m))
        asked = rows.withColumn("__m", size).withColumn("__begin", _of_region(begins, "int")).withColumn("__h", _of_region(h, "int"))
        asked = asked.withColumn("__at", F.pmod(h1, F.col("__m"))).withColumn("__step", F.pmod(h2.bitwiseOR(F.lit(1).cast("bigint")), F.col("__m")))
        hit = F.lit(True)
        for i in range(max(h)):  # written out, so that the constant is folded once and tests stop at the first miss
            p = F.pmod(F.col("__at") + i * F.col("__step"), F.col("__m"))
            bit = F.call_function("shiftleft", F.lit(1).cast("bigint"), F.pmod(p, F.lit(WORD)).cast("int"))
            hit = hit & ((F.col("__h") <= i) | (F.get(words, F.col("__begin") + F.floor(p / WORD).cast("int")).bitwiseAND(bit) != 0))
        return asked.withColumn("maybe", F.coalesce(fixed, hit, F.lit(False))).drop("__m", "__begin", "__h", "__at", "__step")
    if strategy in ("broadcast", "scatter"):
        _, h = _sizes(plan, sizing)
        chunks = filt if "chunk" in filt.columns else _chunks_of(filt, "region")
        size, hashes = F.greatest(F.lit(1).cast("bigint"), _of_region(m)), _of_region(h, "int")
        return _found(rows, chunks, size, hashes, max(h), fixed, family, strategy == "scatter")
    if strategy == "shuffle":
        asked = rows.withColumn("__fixed", fixed)
        known = asked.where(F.col("__fixed").isNotNull()).withColumn("maybe", F.col("__fixed")).drop("__fixed")
        open_ = _block_offsets(asked.where(F.col("__fixed").isNull()).drop("__fixed"), plan, family, sizing)  # two numbers travel, not all positions
        joined = _positions_in_block(open_.join(filt.select("region", "block", "words"), ["region", "block"], "left"), plan, sizing)
        hit = F.forall("positions", lambda p: F.get("words", F.floor(p / WORD).cast("int")).bitwiseAND(F.call_function("shiftleft", F.lit(1).cast("bigint"), F.pmod(p, F.lit(WORD)).cast("int"))) != 0)
        return joined.withColumn("maybe", F.coalesce(hit, F.lit(False))).drop("block", "positions", "words").unionByName(known)
    raise ValueError(strategy)


def _chunk_key(p: Column, by_region: bool) -> Column:
    return (F.col("region").cast("bigint") * F.lit(1 << 40) if by_region else F.lit(0).cast("bigint")) + F.shiftright(p, 9)


def _is_set(longs: str, p: Column) -> Column:
    return F.coalesce(F.get(longs, F.shiftright(p, 6).bitwiseAND(F.lit(7)).cast("int")).bitwiseAND(_one(p, LONG)) != 0, F.lit(False))


def _found(rows: DataFrame, chunks: DataFrame, m: Column, h: Column, most: int, fixed: Column, family: str, scatter: bool) -> DataFrame:
    """rows with maybe: fixed where it is not null, else whether all h positions of elem below m are set in the chunks."""
    by_region = "region" in chunks.columns
    keyed = chunks.select(((F.col("region").cast("bigint") * F.lit(1 << 40) if by_region else F.lit(0).cast("bigint")) + F.col("chunk")).alias("__k"), F.col("longs").alias("__longs"))
    if scatter:
        at = rows.withColumn("__fixed", fixed).where("__fixed is null").select("elem", "region", m.alias("__m"), h.alias("__h")).distinct()
        at = at.select("elem", "region", F.explode(positions(F.col("elem"), F.greatest(F.lit(1), F.col("__h")), F.col("__m"), family)).alias("__p"))
        at = at.join(keyed, _chunk_key(F.col("__p"), by_region) == F.col("__k"), "left")
        said = at.groupBy("elem", "region").agg(F.bool_and(_is_set("__longs", F.col("__p"))).alias("__hit"))
        return rows.join(said, ["elem", "region"], "left").withColumn("maybe", F.coalesce(fixed, F.col("__hit"), F.lit(False))).drop("__hit")
    h1, h2 = bases(F.col("elem"), family)
    asked = rows.withColumn("__fixed", fixed).withColumn("__m", m).withColumn("__h", h)
    asked = asked.withColumn("__at", F.pmod(h1, F.col("__m"))).withColumn("__step", F.pmod(h2.bitwiseOR(F.lit(1).cast("bigint")), F.col("__m"))).withColumn("__hit", F.col("__fixed").isNull())
    for i in range(most):  # one broadcast join for each position, no row is multiplied; a miss needs no further look-up
        p, look = F.pmod(F.col("__at") + i * F.col("__step"), F.col("__m")), F.col("__hit") & (F.col("__h") > i)
        asked = asked.join(F.broadcast(keyed), F.when(look, _chunk_key(p, by_region)) == F.col("__k"), "left")
        asked = asked.withColumn("__hit", F.col("__hit") & ((F.col("__h") <= i) | _is_set("__longs", p))).drop("__k", "__longs")
    return asked.withColumn("maybe", F.coalesce("__fixed", "__hit", F.lit(False))).drop("__fixed", "__m", "__h", "__at", "__step", "__hit")


def probe_shared(df: DataFrame, filt: DataFrame, plan: Plan, m: int, family: str = "md5") -> DataFrame:
    """maybe for the one-array layout, in words or chunks: a region's own number of hashes decides."""
    _, h = _sizes(plan, "formula")
    fixed = F.when(F.col("elem").isNull(), F.lit(False)).otherwise(F.element_at(F.array(*(F.lit(True if x == 0 else None).cast("boolean") for x in h)), F.col("region")))
    chunks = filt if "chunk" in filt.columns else _chunks_of(filt)
    return _found(with_region(df, plan), chunks, F.lit(m).cast("bigint"), _of_region(h, "int"), max(h), fixed, family, m > BROADCAST_BITS)


def _chunks_of_bitmaps(bitmaps: DataFrame) -> DataFrame:
    """(region, chunk, longs) from built-in bitmaps, whose bits lie in bytes from the lowest up."""
    one = bitmaps.select("region", F.col("bucket").alias("__bucket"), F.hex("bitmap").alias("__hex"), F.explode(F.sequence(F.lit(0), F.lit(BITMAP_BITS // BLOCK_BITS - 1))).alias("__i"))
    # sixteen hex digits are a long with its lowest byte first
    digits = F.substring("__hex", F.col("__i") * (BLOCK_BITS // 4) + 1, F.lit(BLOCK_BITS // 4))

    def long_of(k: int) -> Column:
        byte = lambda b: F.conv(F.substring("__part", F.lit(16 * k + 2 * b + 1), F.lit(2)), 16, 10).cast("bigint")
        out = byte(0)
        for b in range(1, 8):
            out = out.bitwiseOR(F.call_function("shiftleft", byte(b), F.lit(8 * b)))
        return out

    parts = one.withColumn("__part", digits).where(F.ltrim("__part", F.lit("0")) != "")
    # buckets are counted from one
    return parts.select("region", ((F.col("__bucket") - 1) * (BITMAP_BITS // BLOCK_BITS) + F.col("__i")).alias("chunk"), F.array(*map(long_of, range(BLOCK_BITS // LONG))).alias("longs"))


def probe_bitmap(df: DataFrame, filt: DataFrame, plan: Plan, family: str = "xx") -> DataFrame:
    """maybe for the layout of built-in bitmaps, whatever their number: they are cut into chunks, which are broadcast up to
    BROADCAST_BITS and met by a shuffle of positions beyond."""
    m, h = _sizes(plan, "formula")
    fixed = F.when(F.col("elem").isNull(), F.lit(False)).otherwise(_without_lookup(plan))
    size, hashes = F.greatest(F.lit(1).cast("bigint"), _of_region(m)), _of_region(h, "int")
    return _found(with_region(df, plan), staged(_chunks_of_bitmaps(filt), "bitmap-chunks"), size, hashes, max(h), fixed, family, sum(m) > BROADCAST_BITS)


def probe_fingerprints(df: DataFrame, filt: DataFrame, plan: Plan, family: str = "xx") -> DataFrame:
    rows = _prints(with_region(df, plan), plan, family)
    joined = rows.join(filt, ["region", "bucket"], "left")
    fixed = F.when(F.col("elem").isNull(), F.lit(False)).otherwise(_without_lookup(plan))
    return joined.withColumn("maybe", F.coalesce(fixed, F.array_contains("prints", F.col("print")), F.lit(False))).drop("bucket", "print", "prints")


@dataclass(frozen=True)
class OneRegion:
    """Plans of a single array, for the plain filter and for the parts of two-stage designs."""

    @staticmethod
    def plan(n: int, rate: float, size: int) -> Plan:
        return Plan((0, size), (1.0,), (1.0,), (rate,), (n,), rate, "standard")


def probe_sandwich(df: DataFrame, front: DataFrame, front_plan: Plan, score, cut: int, n_segments: int, back: DataFrame, back_plan: Plan, family: str = "auto", sizing: str = "formula") -> DataFrame:
    """Front filter first; only its survivors are scored (``score``: DataFrame -> DataFrame with score); from the cut
    on they are accepted, below it the backup filter decides. Columns as df's, with seg and maybe."""
    asked = staged(probe(df.withColumn("seg", F.lit(0)), front, front_plan, family=family, sizing=sizing).drop("region"), "front")  # so that the front is asked once
    alive = score(asked.where("maybe").drop("maybe", "seg")).withColumn("seg", seg_of(F.col("score"), n_segments))
    back_says = probe(alive, back, back_plan, family=family, sizing=sizing).drop("region")
    kept = back_says.withColumn("maybe", (F.col("seg") >= cut) | F.col("maybe"))
    columns = [*df.columns, "seg", "maybe"]
    return asked.where(~F.col("maybe")).select(columns).unionByName(kept.select(columns))


def fill(filt: DataFrame, plan: Plan, sizing: str = "formula") -> DataFrame:
    """(region, m, set_bits, fill) of every array that was built."""
    m, _ = _sizes(plan, sizing)
    sizes = filt.sparkSession.createDataFrame([(r + 1, x) for r, x in enumerate(m) if x] or [(0, 1)], "region int, m bigint")
    return filt.groupBy("region").agg(F.sum(F.bit_count("bits")).cast("bigint").alias("set_bits")).join(F.broadcast(sizes), "region").select("region", "m", "set_bits", (F.col("set_bits") / F.col("m")).alias("fill"))


def exact(df: DataFrame, keys: DataFrame) -> DataFrame:
    """The true answer, by a semi-join."""
    return df.join(keys.select("elem").distinct(), "elem", "left_semi")

