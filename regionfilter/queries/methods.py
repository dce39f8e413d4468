"""Queries of the methods, competing designs, measures and experiments."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import workloads as W
from ..functions.formulas import LOG2E, kl_term, plain_bits, standard_rate
from ..operators import filters, measure, prune, scorers, segments
from ..plans import baselines, kinds, planner
from ..plans import rates as R
from ..plans import thresholds as T
from ..plans.thresholds import Histogram
from ..sources.io import scratch, staged, table
from ..functions.hashing import u60_sql
from . import oracle as O

N, CUTS = O.N, [0, 5, 12, 20]
QUERIES: dict = {}
ORACLES: dict = {}


def add(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return keep


def dec(c, places: int = 6):
    """c rounded to so many places, the same double in both engines."""
    return (F.col(c) if isinstance(c, str) else c).cast("double").cast(f"decimal(18,{places})").cast("double")


def scored(spark, sf_dir, name, n: int = N):
    if name == "zipf":
        from ..operators.elements import split

        return W.Scored(split(W.zipf(spark, sf_dir, n)), scorers.Scorer("given", ()), n)
    return W.scored(spark, sf_dir, name, n)


def zipf_histogram(spark, sf_dir, n: int = 1000, z: float = 1.0) -> Histogram:
    """Orders by segments that are drawn from the synthetic masses."""
    from ..operators.elements import split

    return Histogram.of(segments.histogram(split(W.zipf(spark, sf_dir, n, z)), n), 0.05)


def histogram(spark, sf_dir, name, n: int = N, alpha: float = 0.5) -> Histogram:
    return Histogram.of(scored(spark, sf_dir, name, n).hist(), alpha)


def plan_rows(spark, p: planner.Plan) -> DataFrame:
    return p.frame(spark).select("region", "seg_lo", "seg_hi", "n_keys", dec("a").alias("a"), dec("b").alias("b"), dec("rate", 9).alias("rate"))


def rows(spark, values, schema: str) -> DataFrame:
    return spark.createDataFrame(values, schema)


def _per_workload(name: str):
    @add(f"split_counts_{name}", O.query(O.scored(name)[:2], "SELECT part, count(*) AS n FROM p GROUP BY part") if name != "zipf" else None)
    def counts(spark, sf_dir):
        return W.split(spark, sf_dir, name).groupBy("part").agg(F.count("*").alias("n"))

    @add(f"cell_scores_{name}", O.query(O.scored(name)[:3], f"SELECT c1, c2, {O.dec('cell_rate')} AS cell_rate FROM cells"))
    def cells(spark, sf_dir):
        return scored(spark, sf_dir, name).scorer.cells.select("c1", "c2", dec("cell_rate").alias("cell_rate"))


for _name in ("line", "url", "docs", "toxic", "turns"):
    _per_workload(_name)
for _name in ("line", "url", "docs", "toxic", "turns", "zipf"):
    add(f"seg_hist_{_name}", O.query(O.scored(_name), "SELECT seg, kc, qc FROM hist"))(lambda spark, sf_dir, name=_name: scored(spark, sf_dir, name).hist())

LINE = O.scored("line")


@add("cum_gh_line", O.query(LINE, f"SELECT seg, kc, qc, {O.dec('sum(kc) OVER (ORDER BY seg)::DOUBLE / sum(kc) OVER ()')} AS g, {O.dec('sum(qc) OVER (ORDER BY seg)::DOUBLE / sum(qc) OVER ()')} AS h FROM hist"))
def cum_gh_line(spark, sf_dir):
    return segments.cumulate(scored(spark, sf_dir, "line").hist()).select("seg", "kc", "qc", dec("g").alias("g"), dec("h").alias("h"))


FIXED = O.regions_of(f"SELECT 0 AS pid, {CUTS} AS cuts")


@add("region_shares_line", O.query([*LINE, *FIXED], f"SELECT region, seg_lo, seg_hi, n_keys, {O.dec('a')} AS a, {O.dec('b')} AS b FROM r"))
def region_shares_line(spark, sf_dir):
    return segments.roll_up(scored(spark, sf_dir, "line").hist(), CUTS, 0.5).select("region", "seg_lo", "seg_hi", "n_keys", dec("a").alias("a"), dec("b").alias("b"))


@add("divergence_terms_line", O.query([*LINE, *FIXED], f"SELECT region, {O.dec('CASE WHEN a > 0 THEN a * log2(a / b) ELSE 0 END')} AS term FROM r"))
def divergence_terms_line(spark, sf_dir):
    return segments.roll_up(scored(spark, sf_dir, "line").hist(), CUTS, 0.5).select("region", dec(kl_term(F.col("a"), F.col("b"))).alias("term"))


@add("divergence_line", O.query([*LINE, *FIXED], f"SELECT {O.dec('sum(CASE WHEN a > 0 THEN a * log2(a / b) ELSE 0 END)')} AS divergence, false AS unbounded FROM r"))
def divergence_line(spark, sf_dir):
    return segments.divergence(segments.roll_up(scored(spark, sf_dir, "line").hist(), CUTS, 0.5)).select(dec("divergence").alias("divergence"), "unbounded")


@add("relaxed_rates_line", O.query([*LINE, *FIXED], f"SELECT region, {O.dec('0.001::DOUBLE * a / b', 9)} AS rate FROM r"))
def relaxed_rates_line(spark, sf_dir):
    return segments.roll_up(scored(spark, sf_dir, "line").hist(), CUTS, 0.5).select("region", dec(F.lit(0.001) * F.col("a") / F.col("b"), 9).alias("rate"))


@add("relaxed_size_identity", O.query([*LINE, *FIXED], f"SELECT {O.dec('sum(-a * log2(0.001::DOUBLE * a / b))')} AS direct, {O.dec('log2(1000::DOUBLE) - sum(a * log2(a / b))')} AS identity FROM r WHERE a > 0"))
def relaxed_size_identity(spark, sf_dir):
    """Bits for each key summed over regions, and by the divergence."""
    a, b = histogram(spark, sf_dir, "line").shares(CUTS)
    direct = R.size_per_key(a, R.relaxed(a, b, 0.001))
    return rows(spark, [(direct, measure.relaxed_bits(1, 1.0, 0.001, T.divergence(a, b)))], "direct double, identity double").select(dec("direct").alias("direct"), dec("identity").alias("identity"))


CAPPED = O.query([*LINE, *FIXED, *O.capped("0.3")], f"SELECT region, {O.dec('rate', 9)} AS rate FROM c")


@add("capped_rates_line_t30", CAPPED)
def capped_rates_line_t30(spark, sf_dir):
    """In closed form, by window functions."""
    shares = segments.roll_up(scored(spark, sf_dir, "line").hist(), CUTS, 0.5).withColumn("target", F.lit(0.3))
    return R.capped_sql(shares).select("region", dec("rate", 9).alias("rate"))


@add("capped_iterative_line_t30", CAPPED)
def capped_iterative_line_t30(spark, sf_dir):
    rates = R.capped(*histogram(spark, sf_dir, "line").shares(CUTS), 0.3)
    return rows(spark, [(i + 1, float(x)) for i, x in enumerate(rates)], "region int, rate double").select("region", dec("rate", 9).alias("rate"))


DP_TABLE = O.query([*LINE, *O.dp(4)], " UNION ALL ".join(f"SELECT e, {j} AS j, {O.dec('best')} AS best, last FROM l{j}" for j in range(1, 5)))


@add("dp_table_line_n20_k4", DP_TABLE)
def dp_table_line(spark, sf_dir):
    t = T.dp_table(histogram(spark, sf_dir, "line"), 4)
    return rows(spark, [(e, j, float(t.best[j][e]), int(t.last[j][e])) for j in range(1, 5) for e in range(j, N + 1)], "e int, j int, best double, last int").select("e", "j", dec("best").alias("best"), "last")


@add("dp_table_dataframe_line", DP_TABLE)
def dp_table_dataframe_line(spark, sf_dir):
    return T.dp_table_sql(staged(scored(spark, sf_dir, "line").hist(), "hist"), 4).select("e", "j", dec("best").alias("best"), "last")


def _best_cuts(k: int):
    @add(f"best_cuts_line_k{k}", O.query([*LINE, *O.dp(k)], f"SELECT array_to_string(cuts, ',') AS cuts, {O.dec('best')} AS divergence FROM l{k} WHERE e = {N}"))
    def q(spark, sf_dir):
        cuts, d = T.best_cuts(histogram(spark, sf_dir, "line"), k)
        return rows(spark, [(",".join(map(str, cuts)), d)], "cuts string, divergence double").select("cuts", dec("divergence").alias("divergence"))


for _k in (2, 3, 4, 5):
    _best_cuts(_k)


def _plans(name: str, target: float):
    ctes = O.scored(name)

    @add(f"plan_relaxed_{name}", O.query([*ctes, *O.dp(4), *O.regions_of(f"SELECT 0 AS pid, cuts FROM l4 WHERE e = {N}")], f"SELECT region, seg_lo, seg_hi, n_keys, {O.dec('a')} AS a, {O.dec('b')} AS b, {O.dec(f'{target}::DOUBLE * a / b', 9)} AS rate FROM r"))
    def relaxed(spark, sf_dir):
        return plan_rows(spark, planner.relaxed(histogram(spark, sf_dir, name), 4, target))

    @add(f"plan_relaxcap_{name}", O.query([*ctes, *O.relax_cap(4, str(target))], O.PLAN_ROWS))
    def relax_cap(spark, sf_dir):
        return plan_rows(spark, planner.relaxed_then_cap(histogram(spark, sf_dir, name), 4, target))

    @add(f"plan_topboundary_{name}", O.query([*ctes, *O.top_boundary(4, str(target))], O.PLAN_ROWS))
    def top(spark, sf_dir):
        return plan_rows(spark, planner.top_boundary(histogram(spark, sf_dir, name), 4, target))


for _name, _t in (("line", 0.01), ("url", 0.001), ("docs", 0.05), ("toxic", 0.05), ("turns", 0.05), ("zipf", 0.01)):
    _plans(_name, _t)


@add("plan_exhaustive_k3", O.query([*LINE, *O.regions_of(f"SELECT x.i * 100 + y.i AS pid, [0, x.i, y.i, {N}] AS cuts FROM range(1, {N}) x(i) JOIN range(1, {N}) y(i) ON x.i < y.i"), *O.capped("0.1"), O.SIZES, "best AS (SELECT pid FROM z ORDER BY round(size, 9), pid LIMIT 1)"], O.PLAN_ROWS))
def plan_exhaustive_k3(spark, sf_dir):
    return plan_rows(spark, planner.exhaustive(histogram(spark, sf_dir, "line"), 3, 0.1))


BUDGET = [  # the region pinned at rate 1 are a prefix in the order of a / b, as under a target
    "bo AS (SELECT *, a / b AS ratio, 1 - coalesce(sum(a) OVER w, 0) AS a_free, sum(a * log2(b / a)) OVER v AS s_free FROM r WHERE a > 0 WINDOW w AS (PARTITION BY pid ORDER BY a / b DESC, region DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), v AS (PARTITION BY pid ORDER BY a / b DESC, region DESC ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING))",
    "bf AS (SELECT *, pow(2::DOUBLE, (s_free - 4.0::DOUBLE) / a_free) AS scale FROM bo)",
    "bm AS (SELECT pid, max(ratio) FILTER (WHERE scale * ratio <= 1 + 1e-12) AS first_free, arg_max(scale, ratio) FILTER (WHERE scale * ratio <= 1 + 1e-12) AS lam FROM bf GROUP BY pid)",
    "c AS (SELECT r.pid, r.region, r.seg_lo, r.seg_hi, r.n_keys, r.a, r.b, CASE WHEN r.a <= 0 THEN 0 WHEN first_free IS NULL OR r.a / r.b > first_free THEN 1 ELSE least(1, lam * (r.a / r.b)) END AS rate FROM r JOIN bm USING (pid))",
    "z AS (SELECT pid, sum(b * rate) AS rate FROM c GROUP BY pid)",
    "best AS (SELECT pid FROM z WHERE rate <= (SELECT min(rate) FROM z) * (1 + 1e-9) ORDER BY pid LIMIT 1)",
]


@add("plan_budget_line", O.query([*LINE, *O.dp(4), *O.regions_of(f"SELECT -1 AS pid, cuts FROM l4 WHERE e = {N} UNION ALL SELECT e AS pid, list_append(cuts, {N}) AS cuts FROM l3 WHERE e < {N}"), *BUDGET], O.PLAN_ROWS))
def plan_budget_line(spark, sf_dir):
    """Least rate in four bits a key."""
    h = histogram(spark, sf_dir, "line")
    return plan_rows(spark, planner.for_budget(h, 4, 4.0 * h.n))


@add("plan_per_flag")
def plan_per_flag(spark, sf_dir):
    """A plan for each return flag of the line items, planned where the histograms are."""
    t = table(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_returnflag")
    flag = t.select(F.concat_ws("-", "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber").alias("elem"), "l_returnflag")
    r = scored(spark, sf_dir, "line").rows.join(flag, "elem")
    counts = r.groupBy("l_returnflag", "seg").agg(F.count_if(F.col("part") == "key").alias("kc"), F.count_if(F.col("part") == "train").alias("qc"))
    every = counts.select("l_returnflag").distinct().withColumn("seg", F.explode(F.sequence(F.lit(0), F.lit(N - 1))))
    hists = every.join(counts, ["l_returnflag", "seg"], "left").fillna(0)
    return planner.plan_groups(hists, "l_returnflag", 4, 0.01)


MONOTONE = """SELECT count(*) FILTER (WHERE kc * before_qc < before_kc * qc) = 0 AS monotone, count(*) FILTER (WHERE kc * before_qc < before_kc * qc)::INT AS falls FROM
 (SELECT kc, qc, lag(kc) OVER (ORDER BY seg) AS before_kc, lag(qc) OVER (ORDER BY seg) AS before_qc FROM hist WHERE kc + qc > 0)"""


@add("monotone_ratio_line", O.query(LINE, MONOTONE))
def monotone_ratio_line(spark, sf_dir):
    ok, falls = planner.ratio_is_monotone(histogram(spark, sf_dir, "line"))
    return rows(spark, [(ok, falls)], "monotone boolean, falls int")


@add("relaxation_tight", O.query([*LINE, *O.dp(4), *O.regions_of(f"SELECT 0 AS pid, cuts FROM l4 WHERE e = {N}")], "SELECT t AS target, bool_and(t::DOUBLE * a / b <= 1 + 1e-12) AS tight FROM r, (VALUES ('0.001'), ('0.1'), ('0.5')) v(t) GROUP BY t"))
def relaxation_tight(spark, sf_dir):
    h = histogram(spark, sf_dir, "line")
    return rows(spark, [(t, planner.relaxation_is_tight(planner.relaxed(h, 4, float(t)))) for t in ("0.001", "0.1", "0.5")], "target string, tight boolean")


# ---- filters
TARGET = 0.01
BUILT = [*LINE, *O.fixed(CUTS, str(TARGET))]
STANDARD = [*LINE, f"c AS (SELECT 1 AS region, 0 AS seg_lo, {N} AS seg_hi, sum(kc)::BIGINT AS n_keys, {TARGET}::DOUBLE AS rate FROM hist)", O.built("c")]


def _fixed_plan(spark, sf_dir, target: float = TARGET):
    s = scored(spark, sf_dir, "line")
    g = staged(s.rows.select("elem", "is_key", "part", "score", "seg"), "scored")
    h = Histogram.of(segments.histogram(g, N))
    return g, h, planner.plan_of(h, CUTS, R.capped(*h.shares(CUTS), target), target, "region")


def _standard_plan(h: Histogram, target: float = TARGET) -> planner.Plan:
    return filters.OneRegion.plan(h.n, target, h.size)


def _answers(probed, *by):
    a = measure.answers(probed, *by)
    return a.withColumn("rate", dec("rate"))


@add("bloom_words_regions", O.query([*BUILT, *O.words()], "SELECT region, word, bits FROM w"))
def bloom_words_regions(spark, sf_dir):
    g, _, p = _fixed_plan(spark, sf_dir)
    return filters.build(g.where("part = 'key'"), p)


@add("bloom_words_standard", O.query([*STANDARD, *O.words()], "SELECT region, word, bits FROM w"))
def bloom_words_standard(spark, sf_dir):
    g, h, _ = _fixed_plan(spark, sf_dir)
    return filters.build(g.where("part = 'key'"), _standard_plan(h))


_SHARED = f"built AS (SELECT *, greatest(32, ceil(round({LOG2E!r}::DOUBLE * sum(n_keys * h) OVER (), 6)))::BIGINT AS m FROM (SELECT region, seg_lo, seg_hi, n_keys, rate, CASE WHEN n_keys = 0 OR rate >= 1 THEN 0 ELSE greatest(1, round(log2(1 / rate)))::INT END AS h FROM c))"


def shared_bits(p: planner.Plan) -> int:
    """Bits of one array for all regions, by how many it is set to hold."""
    return max(32, math.ceil(round(LOG2E * sum(n * p.built(r)[1] for r, n in enumerate(p.n_keys)), 6)))


@add("bloom_words_shared", O.query([*BUILT[:-1], _SHARED, *O.words()], "SELECT word, bit_or(bits) AS bits FROM w GROUP BY word"))
def bloom_words_shared(spark, sf_dir):
    g, _, p = _fixed_plan(spark, sf_dir)
    return filters.build_shared(g.where("part = 'key'"), p, shared_bits(p))


@add("probe_counts_region", O.query([*BUILT, *O.words(), *O.probed()], f"SELECT region, {O.ANSWERS} FROM a GROUP BY region"))
def probe_counts_region(spark, sf_dir):
    g, _, p = _fixed_plan(spark, sf_dir)
    f = staged(filters.build_plain(g.where("part = 'key'"), p), "words")
    return _answers(filters.probe(g, f, p), "region")


@add("probe_counts_region_broadcast", ORACLES["probe_counts_region"])
def probe_counts_region_broadcast(spark, sf_dir):
    g, _, p = _fixed_plan(spark, sf_dir)
    f = staged(filters.build_chunks(g.where("part = 'key'"), p), "words")
    return _answers(filters.probe(g, f, p, "broadcast"), "region")


def _blocked(which: str) -> str:
    """SQL of (elem, part, region, block, pos) in blocks of 512 bits."""
    n = "((m + 511) // 512)"
    return f"SELECT elem, part, region, {u60_sql('elem')} % {n} AS block, ({u60_sql('elem')} // {n} % 512 + i * ({u60_sql("elem || '#2'")} % 512 | 1)) % 512 AS pos FROM g JOIN built ON seg >= seg_lo AND seg < seg_hi AND m > 0, range(40) x(i) WHERE i < h{which}"


@add("probe_counts_blocked", O.query([*BUILT, f"kb AS (SELECT DISTINCT region, block, pos FROM ({_blocked(" AND part = 'key'")}))", f"pa AS (SELECT elem, bool_and(kb.pos IS NOT NULL) AS hit FROM ({_blocked('')}) x LEFT JOIN kb USING (region, block, pos) GROUP BY elem)", O.probed()[2]], f"SELECT region, {O.ANSWERS} FROM a GROUP BY region"))
def probe_counts_blocked(spark, sf_dir):
    """One equi-join on (region, block): the way for filters of any size."""
    g, _, p = _fixed_plan(spark, sf_dir)
    f = filters.build_blocked(g.where("part = 'key'"), p, "md5")
    return _answers(filters.probe(g, f, p, "shuffle", "md5"), "region")


@add("probe_counts_bitmap", ORACLES["probe_counts_region"])
def probe_counts_bitmap(spark, sf_dir):
    """The layout of built-in bitmaps, probed by size."""
    g, _, p = _fixed_plan(spark, sf_dir)
    return _answers(filters.probe_bitmap(g, filters.build_bitmap(g.where("part = 'key'"), p, "md5"), p, "md5"), "region")


@add("probe_counts_fingerprint")
def probe_counts_fingerprint(spark, sf_dir):
    g, _, p = _fixed_plan(spark, sf_dir)
    return _answers(filters.probe_fingerprints(g, filters.build_fingerprints(g.where("part = 'key'"), p), p), "region")


@add("probe_counts_standard", O.query([*STANDARD, *O.words(), *O.probed()], f"SELECT {O.ANSWERS} FROM a"))
def probe_counts_standard(spark, sf_dir):
    g, h, _ = _fixed_plan(spark, sf_dir)
    p = _standard_plan(h)
    return _answers(filters.probe(g, staged(filters.build_plain(g.where("part = 'key'"), p), "words"), p))


@add("probe_counts_shared", O.query([*BUILT[:-1], _SHARED, *O.words()[:1], "w AS (SELECT pos // 32 AS word, bit_or(1::BIGINT << (pos % 32)::INT) AS bits FROM (SELECT (first + i * step) % m AS pos FROM kp) GROUP BY ALL)", *[x.replace("ON w.region = x.region AND w.word", "ON w.word") for x in O.probed()[:2]], "a AS (SELECT g.elem, g.part, CASE WHEN h = 0 THEN true ELSE coalesce(hit, false) END AS maybe FROM g JOIN built ON seg >= seg_lo AND seg < seg_hi LEFT JOIN (SELECT * FROM pa) USING (elem))"], f"SELECT {O.ANSWERS} FROM a"))
def probe_counts_shared(spark, sf_dir):
    g, _, p = _fixed_plan(spark, sf_dir)
    f = staged(filters.build_shared(g.where("part = 'key'"), p, shared_bits(p)), "words")
    return _answers(filters.probe_shared(g, f, p, shared_bits(p)))


def _two_stages(spark, sf_dir, design):
    """Rows with maybe of a front filter, a cut and a backup filter that were planned on the line items."""
    g, h, _ = _fixed_plan(spark, sf_dir)
    p = design(h, 0.3)
    low = int(sum(h.kc[: p.cut]))
    front_plan, back_plan = filters.OneRegion.plan(h.n, p.front, N), filters.OneRegion.plan(low, p.backup if low else 1.0, N)
    keys = g.where("part = 'key'")
    front, back = filters.build_any(keys, front_plan), filters.build_any(keys.where(F.col("seg") < p.cut), back_plan)
    return filters.probe_sandwich(g.drop("seg"), front, front_plan, lambda d: d, p.cut, N, back, back_plan)


@add("probe_counts_sandwich")
def probe_counts_sandwich(spark, sf_dir):
    return _answers(_two_stages(spark, sf_dir, baselines.sandwich))


@add("probe_counts_single")
def probe_counts_single(spark, sf_dir):
    return _answers(_two_stages(spark, sf_dir, baselines.single))


@add("fill_fraction", O.query([*BUILT, *O.words()], f"SELECT region, m, sum(bit_count(bits))::BIGINT AS set_bits, {O.dec('sum(bit_count(bits))::DOUBLE / m')} AS fill FROM w JOIN built USING (region) GROUP BY region, m"))
def fill_fraction(spark, sf_dir):
    g, _, p = _fixed_plan(spark, sf_dir)
    return filters.fill(filters.build(g.where("part = 'key'"), p), p).withColumn("fill", dec("fill"))


def built_answers(g: DataFrame, h: Histogram, k: int, target: float) -> DataFrame:
    """(method, target, expected_rate, bits_set_aside, n_queries, false_positives, rate, n_keys, false_negatives): every
    design that meets the target, built from the keys of g and probed with all its rows. One design at a time: what it
    wrote and shuffled goes before the next begins."""
    keys, out, same = g.where("part = 'key'"), [], {}
    for name, p in {**designs(h, k, target), "standard": _standard_plan(h, target)}.items():
        if p is not None and name != "ideal":
            what = (p.cut, p.front, p.backup) if isinstance(p, baselines.TwoStage) else (name == "geometric_shared", p.cuts, p.rates)
            same.setdefault(what, (p, []))[1].append(name)
    for p, names in same.values():  # designs that come to the same filter are built once
        name = names[0]
        with scratch(g.sparkSession):
            if isinstance(p, baselines.TwoStage):
                low = int(sum(h.kc[: p.cut]))
                front, back = filters.OneRegion.plan(h.n, p.front, h.size), filters.OneRegion.plan(low, p.backup if low else 1.0, h.size)
                words = [staged(filters.build_any(keys, front, "xx", "exact"), "front-words"), staged(filters.build_any(keys.where(F.col("seg") < p.cut), back, "xx", "exact"), "back-words")]
                probed = filters.probe_sandwich(g.drop("seg", "is_key"), words[0], front, lambda d: d, p.cut, h.size, words[1], back, "xx", "exact")
                bits = front.built(0, "exact")[0] + back.built(0, "exact")[0]
            elif name == "geometric_shared":
                bits = shared_bits(p)
                build = filters.build_shared_chunks if bits > filters.ARRAY_BITS else filters.build_shared
                probed = filters.probe_shared(g, staged(build(keys, p, bits, "xx"), "words"), p, bits, "xx")
            else:
                bits = sum(p.built(r, "exact")[0] for r in range(p.k))
                probed = filters.probe(g, staged(filters.build_any(keys, p, "xx", "exact"), "words"), p, family="xx", sizing="exact")
            expected = float(target if name == "standard" else p.expected_rate)
            got = measure.answers(probed).select(F.explode(F.array(*map(F.lit, names))).alias("method"), F.lit(target).alias("target"), F.lit(expected).alias("expected_rate"), F.lit(bits).cast("bigint").alias("array_bits"), "*")
            out += got.collect()  # a row for each name
    return g.sparkSession.createDataFrame(out, got.schema)


def _measured(name: str, target: float):
    @add(f"actual_rate_{name}")
    def measured(spark, sf_dir):
        """Expected and measured rate on held-out non-keys, and false negatives, of built filters of every design."""
        with scratch(spark) as kept:
            with scratch(spark) as made:  # only the scored rows outlive it
                s = scored(spark, sf_dir, "line" if name == "all" else name, 100)
                g = staged(s.rows.select("elem", "is_key", "part", "score", "seg"), "scored")
                kept.append(made.pop())
            return built_answers(g, Histogram.of(segments.histogram(g, 100)), 5, target)


_measured("all", TARGET)
_measured("url", 0.001)


@add("false_negatives_all", O.query([*BUILT, *O.words(), *O.probed()], "SELECT count(*) FILTER (WHERE part = 'key' AND NOT maybe) AS false_negatives FROM a"))
def false_negatives_all(spark, sf_dir):
    """Keys that any built design misses, region filters in every layout included: there are none. All are built from the
    same staged rows, one after the other."""
    from ..functions.formulas import seg_of

    missed = 0
    with scratch(spark) as kept:
        with scratch(spark) as made:  # only the scored rows outlive it
            g, _, p = _fixed_plan(spark, sf_dir)
            kept.append(made.pop())
        keys = g.where("part = 'key'")
        for probed in (
            lambda: filters.probe(g, staged(filters.build_plain(keys, p), "words"), p),
            lambda: filters.probe(g, staged(filters.build_blocked(keys, p, "md5"), "blocks"), p, "shuffle", "md5"),
            lambda: filters.probe_fingerprints(g, filters.build_fingerprints(keys, p), p),
            lambda: filters.probe_bitmap(g, staged(filters.build_bitmap(keys, p, "md5"), "bitmaps"), p, "md5"),
        ):
            with scratch(spark):
                missed += measure.answers(probed()).first()["false_negatives"]
        fine = g.withColumn("seg", seg_of(F.col("score"), 100))
        missed += sum(r["false_negatives"] for r in built_answers(fine, Histogram.of(segments.histogram(fine, 100)), 5, TARGET).collect())
    return rows(spark, [(missed,)], "false_negatives bigint")


# ---- competing designs
CUTS_SQL = ["pre2 AS (SELECT seg + 1 AS t, sum(kc) OVER (ORDER BY seg)::DOUBLE / sum(kc) OVER () AS a_low, sum(qc + 0.5::DOUBLE) OVER (ORDER BY seg) / sum(qc + 0.5::DOUBLE) OVER () AS b_low FROM hist)", f"tl AS (SELECT * FROM pre2 WHERE t < {N})"]


@add("single_best_threshold", O.query([*LINE, *CUTS_SQL], f"SELECT t::INT AS cut, {O.dec('backup')} AS backup, {O.dec('size')} AS bits_per_key FROM (SELECT t, least(1, (0.3::DOUBLE - (1 - b_low)) / b_low) AS backup, -a_low * log2(least(1, (0.3::DOUBLE - (1 - b_low)) / b_low)) AS size FROM tl WHERE a_low > 0 AND 0.3::DOUBLE - (1 - b_low) > 0) ORDER BY round(size, 9), t LIMIT 1"))
def single_best_threshold(spark, sf_dir):
    p = baselines.single(histogram(spark, sf_dir, "line"), 0.3)
    return rows(spark, [(p.cut, p.backup, p.bits_per_key)] if p else [], "cut int, backup double, bits_per_key double").select("cut", dec("backup").alias("backup"), dec("bits_per_key").alias("bits_per_key"))


SANDWICH = """SELECT t, a_low, b_low, CASE WHEN free >= 1 THEN {t}::DOUBLE WHEN front > 1 THEN 1 ELSE front END AS front,
 CASE WHEN free >= 1 THEN 1 WHEN front > 1 THEN least(1, ({t}::DOUBLE - (1 - b_low)) / b_low) ELSE free END AS backup, free < 1 AND front > 1 AND {t}::DOUBLE - (1 - b_low) <= 0 AS broken FROM
 (SELECT *, a_low * (1 - b_low) / (b_low * (1 - a_low)) AS free, {t}::DOUBLE * (1 - a_low) / (1 - b_low) AS front FROM tl WHERE a_low > 0 AND a_low < 1)"""


def _sandwich_sql(target: str) -> list[str]:
    return [f"sw AS (SELECT t, front, backup, -log2(front) - a_low * log2(backup) AS size FROM ({SANDWICH.format(t=target)}) WHERE NOT broken)"]


@add("sandwich_best_threshold", O.query([*LINE, *CUTS_SQL, *_sandwich_sql("0.01")], f"SELECT t::INT AS cut, {O.dec('front', 9)} AS front, {O.dec('backup', 9)} AS backup, {O.dec('size')} AS bits_per_key FROM sw ORDER BY round(size, 9), t LIMIT 1"))
def sandwich_best_threshold(spark, sf_dir):
    p = baselines.sandwich(histogram(spark, sf_dir, "line"), 0.01)
    return rows(spark, [(p.cut, p.front, p.backup, p.bits_per_key)], "cut int, front double, backup double, bits_per_key double").select("cut", dec("front", 9).alias("front"), dec("backup", 9).alias("backup"), dec("bits_per_key").alias("bits_per_key"))


@add("sandwich_equals_two_regions", O.query([*LINE, *CUTS_SQL, *_sandwich_sql("0.01"), *O.dp(1), *O.regions_of(f"SELECT e AS pid, [0, e, {N}] AS cuts FROM l1 WHERE e < {N}"), *O.capped("0.01"), O.SIZES], f"SELECT {O.dec('min(sw.size)')} AS sandwich, {O.dec('min(z.size)')} AS two_regions FROM sw FULL JOIN z ON z.pid = sw.t"))
def sandwich_equals_two_regions(spark, sf_dir):
    h = histogram(spark, sf_dir, "line")
    return rows(spark, [(baselines.sandwich(h, 0.01).bits_per_key, planner.top_boundary(h, 2, 0.01).bits_per_key)], "s double, r double").select(dec("s").alias("sandwich"), dec("r").alias("two_regions"))


@add("sandwich_for_budget_line")
def sandwich_for_budget_line(spark, sf_dir):
    h = histogram(spark, sf_dir, "line")
    got = [(bits, p.cut, p.front, p.backup, p.expected_rate) for bits in (2.0, 4.0, 6.0, 8.0) if (p := baselines.sandwich_for_budget(h, bits * h.n))]
    return rows(spark, got, "bits_per_key double, cut int, front double, backup double, expected_rate double").select("bits_per_key", "cut", *(dec(c, 9).alias(c) for c in ("front", "backup", "expected_rate")))


def _geometric_sql(k: int, gammas) -> str:
    """Plans (pid = number of gamma) with geometric cuts of k = 3 regions."""
    assert k == 3
    g = ", ".join(f"({i}, {x}::DOUBLE)" for i, x in enumerate(gammas))
    reach = [f"round(({'gamma * gamma' if r == 1 else 'gamma * gamma + gamma'}) / (gamma * gamma + gamma + 1), 12)" for r in (1, 2)]
    at = [f"(SELECT min(t) FROM pre2 WHERE round(b_low, 12) >= {x})" for x in reach]
    first = f"least(greatest({at[0]}, 1), {N - 2})"
    return f"SELECT pid, [0, c1, least(greatest(c2, c1 + 1), {N - 1}), {N}] AS cuts FROM (SELECT pid, {first} AS c1, {at[1]} AS c2 FROM (VALUES {g}) v(pid, gamma))"


GRID = baselines.GAMMAS
EQUAL_MASS = [  # pins regions in the order of b, the smallest first
    "eo AS (SELECT *, coalesce(sum(b) OVER w, 0) AS b_before, count(*) OVER w AS n_before, count(*) OVER (PARTITION BY pid) AS k FROM r WINDOW w AS (PARTITION BY pid ORDER BY b, region ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING))",
    "ef AS (SELECT *, (0.01::DOUBLE - b_before) / (k - n_before) AS mass FROM eo)",
    "em AS (SELECT pid, min(b) FILTER (WHERE mass / b <= 1 + 1e-12) AS free_b, arg_min(mass, b) FILTER (WHERE mass / b <= 1 + 1e-12) AS mass FROM ef GROUP BY pid)",
    "c AS (SELECT pid, region, seg_lo, seg_hi, n_keys, a, b, CASE WHEN b < free_b THEN 1 ELSE least(1, em.mass / b) END AS rate FROM ef JOIN em USING (pid))",
]


@add("geometric_separate_grid", O.query([*LINE, *CUTS_SQL, *O.regions_of(_geometric_sql(3, GRID)), *EQUAL_MASS, O.SIZES, "best AS (SELECT pid FROM z ORDER BY round(size, 9), pid LIMIT 1)"], O.PLAN_ROWS))
def geometric_separate_grid(spark, sf_dir):
    return plan_rows(spark, baselines.geometric_separate(histogram(spark, sf_dir, "line"), 3, 0.01, GRID))


@add("geometric_shared_grid", O.query([*LINE, *CUTS_SQL, *O.regions_of(_geometric_sql(3, GRID)), "hs AS (SELECT r.*, top, CASE WHEN region = 1 THEN top WHEN region = 3 THEN 0 ELSE CASE WHEN top % 2 = 0 THEN top // 2 WHEN (top // 2) % 2 = 0 THEN top // 2 ELSE top // 2 + 1 END END AS h FROM r, range(1, 41) x(top))", "ok AS (SELECT pid, min(top) AS top FROM (SELECT pid, top, sum(b * pow(2::DOUBLE, -h)) AS rate FROM hs GROUP BY ALL) WHERE rate <= 0.01::DOUBLE * (1 + 1e-12) GROUP BY pid)", "c AS (SELECT pid, region, seg_lo, seg_hi, n_keys, a, b, pow(2::DOUBLE, -h) AS rate FROM hs JOIN ok USING (pid, top))", O.SIZES, "best AS (SELECT pid FROM z ORDER BY round(size, 9), pid LIMIT 1)"], O.PLAN_ROWS))
def geometric_shared_grid(spark, sf_dir):
    p = baselines.geometric_shared(histogram(spark, sf_dir, "line"), 3, 0.01, GRID)
    return plan_rows(spark, p) if p else rows(spark, [], "region int, seg_lo int, seg_hi int, n_keys bigint, a double, b double, rate double")


@add("uniform_rates_line", O.query([*LINE, *O.dp(4), *O.regions_of(f"SELECT 0 AS pid, cuts FROM l4 WHERE e = {N}"), "c AS (SELECT *, 0.01::DOUBLE AS rate FROM r)", "best AS (SELECT 0 AS pid)"], O.PLAN_ROWS))
def uniform_rates_line(spark, sf_dir):
    return plan_rows(spark, baselines.uniform_rates(histogram(spark, sf_dir, "line"), 4, 0.01))


@add("equal_width_cuts_line", O.query([*LINE, *O.regions_of("SELECT 0 AS pid, [0, 5, 10, 15, 20] AS cuts"), *O.capped("0.01"), "best AS (SELECT 0 AS pid)"], O.PLAN_ROWS))
def equal_width_cuts_line(spark, sf_dir):
    return plan_rows(spark, baselines.equal_cuts(histogram(spark, sf_dir, "line"), 4, 0.01, "width"))


@add("equal_key_cuts_line")
def equal_key_cuts_line(spark, sf_dir):
    return plan_rows(spark, baselines.equal_cuts(histogram(spark, sf_dir, "line"), 4, 0.01, "key"))


@add("exact_answer_line", O.query(O.scored("line")[:2], "SELECT part, count(*) AS n FROM p WHERE elem IN (SELECT elem FROM p WHERE is_key = 1) GROUP BY part"))
def exact_answer_line(spark, sf_dir):
    g = W.split(spark, sf_dir, "line")
    return filters.exact(g, g.where("is_key = 1")).groupBy("part").agg(F.count("*").alias("n"))


# ---- experiments
TARGETS = (0.1, 0.03, 0.01, 0.003, 0.001, 0.0003, 0.0001)


def designs(h: Histogram, k: int, target: float, tables: tuple | None = None) -> dict:
    """Every design at a target; None where it cannot meet it. ``tables``: best cuts of k - 1 and of k regions, which
    hold for all targets."""
    lower, whole = tables or dp_tables(h, k)
    return {
        "ideal": filters.OneRegion.plan(h.n, target, h.size),
        "single": baselines.single(h, target),
        "sandwich": baselines.sandwich(h, target),
        "geometric_shared": baselines.geometric_shared(h, k, target),
        "geometric_separate": baselines.geometric_separate(h, k, target),
        "relax_cap": planner.relaxed_then_cap(h, k, target, whole),
        "region": planner.top_boundary(h, k, target, lower),
    }


def dp_tables(h: Histogram, k: int) -> tuple:
    """The table of k regions serves k - 1 as well."""
    table_ = T.dp_table(h, k)
    return table_, table_


CURVE = "method string, k int, target double, backup_bits double, model_bits double, total_bits double, expected_rate double"
LEARNED = ("single", "sandwich", "geometric_shared", "geometric_separate", "relax_cap", "region")


def curve(spark, h: Histogram, k: int = 5, targets=TARGETS, model_bits: float = 0.0) -> DataFrame:
    """Bits and expected rates of all designs; whatever asks the scorer pays for it."""
    got, tables = [], dp_tables(h, k)
    for t in targets:
        for m, p in designs(h, k, t, tables).items():
            if p:
                backup, model = float(p.bits_per_key * h.n), float(model_bits if m in LEARNED else 0.0)
                got.append((m, k, t, backup, model, backup + model, float(t if m == "ideal" else p.expected_rate)))
    return rows(spark, got, CURVE)


#: bits for each key that are compared at equal space; 4.83 and 7.5 are the published budgets over the published keys
BUDGETS = (2.0, 4.0, 4.83, 6.0, 7.5, 8.0)


def equal_space_rows(h: Histogram, model_bits: float, budgets=BUDGETS) -> list[tuple]:
    """(bits_per_key, method, expected_rate, ratio to the region design's) with the scorer inside the budget; a design
    that cannot pay for the scorer is left out."""
    got = []
    for per_key in budgets:
        left = per_key * h.n - model_bits
        found = {"ideal": 2.0**-per_key}
        if left > 0:
            found["region"] = planner.for_budget(h, 5, left).expected_rate
            if p := baselines.sandwich_for_budget(h, left):
                found["sandwich"] = p.expected_rate
            found["geometric_separate"] = baselines.geometric_separate_for_budget(h, 5, left)
            if (x := baselines.geometric_shared_for_budget(h, 5, left)) is not None:
                found["geometric_shared"] = x
        got += [(per_key, m, float(x), float(x / found["region"]) if "region" in found else None) for m, x in found.items()]
    return got


def _experiment(name: str, n: int = 1000):
    def hist(spark, sf_dir):
        """Histogram and the scorer's bits."""
        if name == "zipf":
            return zipf_histogram(spark, sf_dir, n), 0.0
        if name == "zipf99":
            return zipf_histogram(spark, sf_dir, n, sharp_exponent(n)), 0.0
        if name == "forest_url":
            r, s = ml_scored(spark, sf_dir, "forest", "url", URL_FEATURES, n)
            return Histogram.of(segments.histogram(r, n)), float(s.model_bits())
        if name == "forest_line":
            r, s = ml_scored(spark, sf_dir, "forest", "line", LINE_FEATURES, n)
            return Histogram.of(segments.histogram(r, n)), float(s.model_bits())
        # many segments beside few sampled queries: the added half query a segment would weigh too much
        s = scored(spark, sf_dir, name, n)
        return Histogram.of(s.hist(), 0.5 if name in ("line", "url") else 0.05), float(s.scorer.model_bits())

    @add(f"curve_{name}")
    def curve_(spark, sf_dir):
        """Rate against space, all designs with their scorer, N = 1000, five regions."""
        h, model = hist(spark, sf_dir)
        return curve(spark, h, model_bits=model)

    @add(f"saved_vs_k_{name}")
    def saved(spark, sf_dir):
        """Bits saved for each number of regions at .001, the scorer paid, with 25 as the line of saturation."""
        h, model = hist(spark, sf_dir)
        plain = math.log2(1 / 0.001)
        return rows(spark, [(p.k, p.divergence, float((plain - p.bits_per_key) * h.n - model)) for p in planner.sweep_k(h, [*range(1, 11), 25], 0.001)], "k int, divergence double, saved_bits double")

    @add(f"equal_space_{name}")
    def equal_space(spark, sf_dir):
        """Rates of the designs in the same number of bits, the scorer's included, over the region design's."""
        return rows(spark, equal_space_rows(*hist(spark, sf_dir)), "bits_per_key double, method string, expected_rate double, ratio double")


def zipf_f1(n: int, z: float) -> float:
    """F1 of the synthetic scores at .5, with as many non-keys as keys."""
    k, q = (np.array(x, dtype=float) for x in W.zipf_weights(n, z))
    hit, wrong = k[n // 2 :].sum() / k.sum(), q[n // 2 :].sum() / q.sum()
    return float(2 * hit / (hit + wrong + 1))


def sharp_exponent(n: int = 1000, f1: float = 0.99) -> float:
    """The exponent of the synthetic scores at which F1 is the published one."""
    low, high = 0.1, 4.0
    for _ in range(40):
        mid = (low + high) / 2
        low, high = (mid, high) if zipf_f1(n, mid) < f1 else (low, mid)
    return round(high, 6)


for _name in ("zipf", "zipf99", "url", "line", "docs", "forest_url", "forest_line"):
    _experiment(_name)


@add("sizes_all_methods_t001")
def sizes_all_methods_t001(spark, sf_dir):
    """Bits of every design at .001 on the line items, ideal filters and real arrays, with the scorer's bits."""
    s = scored(spark, sf_dir, "line", 1000)
    h, model = Histogram.of(s.hist()), float(s.scorer.model_bits())
    got = [(m, float(p.bits_per_key * h.n), float(p.bits_per_key * h.n * kinds.CONSTANTS["standard"]), model if m in LEARNED else 0.0) for m, p in designs(h, 5, 0.001).items() if p]
    return rows(spark, got, "method string, ideal_bits double, array_bits double, model_bits double").withColumn("total_bits", F.col("ideal_bits") + F.col("model_bits"))


@add("space_ratio_t001")
def space_ratio_t001(spark, sf_dir):
    """Bits of every design, scorers included, over the region design's at .001; the synthetic scores both at exponent 1
    and at the published F1."""
    out = None
    for name in ("zipf", "zipf99", "url", "line"):
        if name.startswith("zipf"):
            h, model = W.zipf_hist(1000, 1.0 if name == "zipf" else sharp_exponent()), 0.0
        else:
            s = scored(spark, sf_dir, name, 1000)
            h, model = Histogram.of(s.hist()), float(s.scorer.model_bits())
        r = measure.space_ratio(curve(spark, h, 5, (0.001,), model)).select(F.lit(name).alias("workload"), "*")
        out = r if out is None else out.unionByName(r)
    return out


@add("space_ratio_by_exponent")
def space_ratio_by_exponent(spark, sf_dir):
    """Synthetic scores of several exponents, that of the published F1 among them: the sharper, the larger the ratio."""
    got = []
    for z in (0.5, 1.0, 1.2, 1.5, sharp_exponent(), 2.0):
        d = designs(W.zipf_hist(1000, z), 5, 0.001)
        got += [(z, zipf_f1(1000, z), m, p.bits_per_key, p.bits_per_key / d["region"].bits_per_key) for m, p in d.items() if p]
    return rows(spark, got, "exponent double, f1 double, method string, bits_per_key double, ratio double")


@add("pareto_line")
def pareto_line(spark, sf_dir):
    """How many points of each design's curve another design beats."""
    s = scored(spark, sf_dir, "line", 1000)
    c = staged(curve(spark, Histogram.of(s.hist()), model_bits=float(s.scorer.model_bits())), "curve")
    return c.join(measure.dominated(c).select("method", "target", F.lit(1).alias("beaten")), ["method", "target"], "left").groupBy("method").agg(F.count("*").alias("points"), F.count("beaten").alias("beaten"))


@add("knee_line")
def knee_line(spark, sf_dir):
    h = histogram(spark, sf_dir, "line", 200)
    return rows(spark, [(planner.pick_k(h, 0.001, 25),)], "k int")


@add("plateau_zipf")
def plateau_zipf(spark, sf_dir):
    """Bits saved against the ideal filter as the target falls: they rise, then stay."""
    h = zipf_histogram(spark, sf_dir)
    got = [(t, math.log2(1 / t), planner.top_boundary(h, 5, t).bits_per_key) for t in TARGETS]
    return measure.plateau(rows(spark, got, "target double, ideal_bits double, backup_bits double"))


@add("plan_cost_by_n")
def plan_cost_by_n(spark, sf_dir):
    """Planning cost over the number of segments and of regions: runs of segments weighed, seconds, and the divergence
    that the plan reaches."""
    import time

    full, got = zipf_histogram(spark, sf_dir), []
    for n in (10, 20, 50, 100, 200, 500, 1000):
        fold = lambda x: tuple(int(v) for v in np.array(x, dtype=np.int64).reshape(n, 1000 // n).sum(axis=1))  # noqa: E731, B023
        h = Histogram(fold(full.kc), fold(full.qc), full.alpha)
        for k in (2, 5, 10):
            began = time.perf_counter()
            t = T.dp_table(h, k)
            got.append((n, k, int(t.steps), time.perf_counter() - began, float(t.best[k, n])))
    return rows(spark, got, "n int, k int, steps bigint, seconds double, divergence double")


@add("plan_cost_steps", "SELECT n, k, (n + (k - 1) * n * (n + 1) // 2 - (SELECT sum((j - 1) * n - (j - 1) * (j - 2) // 2) FROM range(2, 11) r(j) WHERE j <= k))::BIGINT AS steps FROM (VALUES (10), (20), (50), (100)) v(n), (VALUES (2), (5), (10)) w(k)")
def plan_cost_steps(spark, sf_dir):
    """Runs of segments that the dynamic programme weighs: in proportion to k and to the square of N."""
    got = [(n, k, int(T.dp_table(h, k).steps)) for n in (10, 20, 50, 100) for h in [zipf_histogram(spark, sf_dir, n)] for k in (2, 5, 10)]
    return rows(spark, got, "n int, k int, steps bigint")


def _scored_rows(spark, sf_dir, name: str, n: int = 100):
    """Staged rows with score and seg, and the smoothing that fits the workload's number of queries."""
    g = staged(scored(spark, sf_dir, name, n).rows.select("elem", "is_key", "part", "score", "seg"), "scored")
    return g, 0.5 if name in ("line", "url") else 0.05


def _against_standard(name: str):
    @add(f"quality_sweep_{name}")
    def quality_sweep(spark, sf_dir):
        """F1, divergence and bits as ever more scores are replaced by noise."""
        from ..functions.formulas import seg_of
        from ..functions.hashing import bucket

        (g, alpha), got = _scored_rows(spark, sf_dir, name), []
        for noise in (0, 10, 20, 30, 40):
            drawn = bucket(F.col("elem"), "worse", 1000) / F.lit(1000.0)
            worse = g.withColumn("score", F.when(bucket(F.col("elem"), "pick") < noise, drawn).otherwise(F.col("score"))).withColumn("seg", seg_of(F.col("score"), 100))
            p = planner.top_boundary(Histogram.of(segments.histogram(worse, 100), alpha), 5, 0.001)
            got.append((noise, float(measure.f1(worse).first()["f1"] or 0.0), p.divergence, p.bits_per_key))
        return rows(spark, got, "noise int, f1 double, divergence double, bits_per_key double")

    @add("standard_vs_region_arrays" if name == "line" else f"standard_vs_region_arrays_{name}")
    def arrays(spark, sf_dir):
        """Real arrays: bits and fill of the plain filter and of the regions' at the same target."""
        g, alpha = _scored_rows(spark, sf_dir, name)
        h = Histogram.of(segments.histogram(g, 100), alpha)
        keys, out = g.where("part = 'key'"), []
        for method, p in (("region", planner.top_boundary(h, 5, TARGET)), ("standard", _standard_plan(h))):
            out.append(filters.fill(filters.build(keys, p, "xx"), p).select(F.lit(method).alias("method"), "region", "m", "set_bits", "fill"))
        return out[0].unionByName(out[1])


for _name in ("line", "url", "docs"):
    _against_standard(_name)


@add("advisor_all")
def advisor_all(spark, sf_dir):
    """Whether regions with the scorer's bits beat a plain filter, workload by workload."""
    got = []
    for name in ("line", "url", "docs", "toxic", "vectors"):
        if name == "vectors":  # no signal: to be refused
            r, scorer = ml_scored(spark, sf_dir, "logit", name, VECTOR_FEATURES, 100)
            hist = Histogram.of(segments.histogram(r, 100), 0.05)
        else:
            s = scored(spark, sf_dir, name, 100)
            hist, scorer = Histogram.of(s.hist(), 0.05), s.scorer
        p = planner.top_boundary(hist, 5, 0.001)
        p = planner.Plan(**{**p.__dict__, "model_bits": float(scorer.model_bits())})
        got.append((name, p.divergence, p.total_bits, p.n * math.log2(1000), planner.worthwhile(p)))
    return rows(spark, got, "workload string, divergence double, total_bits double, plain_bits double, worthwhile boolean")


@add("standard_rate_formula", f"SELECT m, h, n, {O.dec('pow(1 - pow(1 - 1 / m::DOUBLE, h * n), h)')} AS rate FROM (VALUES (1000, 3, 100), (10000, 7, 1000), (14427, 10, 1000), (100, 1, 500)) v(m, h, n)")
def standard_rate_formula(spark, sf_dir):
    d = rows(spark, [(1000, 3, 100), (10000, 7, 1000), (14427, 10, 1000), (100, 1, 500)], "m int, h int, n int")
    return d.select("m", "h", "n", dec(standard_rate(F.col("m").cast("double"), F.col("h"), F.col("n"))).alias("rate"))


@add("plain_bits_by_kind", f"SELECT kind, {O.dec('c::DOUBLE * n * log2(1000::DOUBLE)')} AS bits FROM (VALUES ('ideal', 1.0), ('standard', 1.4426950408889634), ('xor', 1.23)) v(kind, c), (SELECT count(DISTINCT l_partkey) AS n FROM lineitem)")
def plain_bits_by_kind(spark, sf_dir):
    """Bits of a filter of the parts that were sold, at .001, by kind."""
    n = table(spark, sf_dir, "lineitem", "l_partkey").agg(F.count_distinct("l_partkey").alias("n"))
    d = rows(spark, list(kinds.CONSTANTS.items()), "kind string, c double").crossJoin(F.broadcast(n))  # one row
    return d.select("kind", dec(F.col("c") * plain_bits(F.col("n"), F.lit(0.001))).alias("bits"))


@add("f1_cells", O.query(LINE, "SELECT tp, fp, fn, " + ", ".join(f"{O.dec(x)} AS {n}" for x, n in (("tp::DOUBLE / (tp + fp)", "precision"), ("tp::DOUBLE / (tp + fn)", "recall"), ("2.0::DOUBLE * tp / (2 * tp + fp + fn)", "f1"))) + " FROM (SELECT count(*) FILTER (WHERE score >= 0.5 AND is_key = 1) AS tp, count(*) FILTER (WHERE score >= 0.5 AND is_key = 0) AS fp, count(*) FILTER (WHERE score < 0.5 AND is_key = 1) AS fn FROM g)"))
def f1_cells(spark, sf_dir):
    f = measure.f1(scored(spark, sf_dir, "line").rows)
    return f.select("tp", "fp", "fn", dec("precision").alias("precision"), dec("recall").alias("recall"), dec("f1").alias("f1"))


@add("drift_line", O.query([*LINE, "q2 AS (SELECT i::INT AS seg, count(elem) AS n FROM range(20) r(i) LEFT JOIN g ON g.seg = i AND part = 'eval' GROUP BY i)"], f"SELECT {O.dec('sum(abs(p1 - p2)) / 2')} AS variation, {O.dec('sum(s2 * log2(s2 / s1))')} AS kl FROM (SELECT qc::DOUBLE / sum(qc) OVER () AS p1, n::DOUBLE / sum(n) OVER () AS p2, (qc + 0.5::DOUBLE) / sum(qc + 0.5::DOUBLE) OVER () AS s1, (n + 0.5::DOUBLE) / sum(n + 0.5::DOUBLE) OVER () AS s2 FROM hist JOIN q2 USING (seg))"))
def drift_line(spark, sf_dir):
    """Training non-keys against the held-out ones."""
    s = scored(spark, sf_dir, "line")
    d = segments.drift(s.hist(), segments.histogram(s.rows, N, queries="part = 'eval'"))
    return d.select(dec("variation").alias("variation"), dec("kl").alias("kl"))


URGENT = "o_orderpriority = '1-URGENT' AND o_orderdate < TIMESTAMP '1995-01-01'"


@add("semijoin_reduce_orders", f"SELECT l_orderkey, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE {URGENT} GROUP BY l_orderkey")
def semijoin_reduce_orders(spark, sf_dir):
    """Line items of urgent early orders: a filter of the orders' keys is probed before the shuffle join."""
    dim = table(spark, sf_dir, "orders", "o_orderkey", "o_orderpriority", "o_orderdate").where(URGENT).select(F.col("o_orderkey").cast("string").alias("elem"))
    fact = table(spark, sf_dir, "lineitem", "l_orderkey").select("l_orderkey", F.col("l_orderkey").cast("string").alias("elem"), F.lit(0).alias("seg"))
    plan = filters.OneRegion.plan(dim.count(), 0.01, 1)
    out = prune.reduce_join(fact, dim, filters.build(dim, plan, "xx"), plan, family="xx")
    return out.groupBy("l_orderkey").agg(F.count("*").alias("n"))


CONTAM = """WITH words AS (SELECT item_id AS id, 1 AS is_item, list_filter(regexp_split_to_array(lower(coalesce(text, '')), '\\s+'), lambda w: w <> '') AS w FROM benchmark
 UNION ALL SELECT doc_id, 0, list_filter(regexp_split_to_array(lower(coalesce(text, '')), '\\s+'), lambda w: w <> '') FROM documents),
s AS (SELECT id, is_item, array_to_string(w[i:i + 7], ' ') AS shingle FROM (SELECT id, is_item, w, unnest(range(1, len(w) - 6)) AS i FROM words WHERE len(w) >= 8))
SELECT id AS doc_id, count(DISTINCT shingle) AS shared FROM s WHERE is_item = 0 AND shingle IN (SELECT shingle FROM s WHERE is_item = 1) GROUP BY id"""


@add("contam_candidates", CONTAM)
def contam_candidates(spark, sf_dir):
    """Documents that share word 8-grams with benchmark items. Words are hashed once and 8-grams are hashes of eight of
    them; a filter of the items' 8-grams is probed on all of the documents', and only documents with a hit have their
    8-grams spelled out for the exact join."""
    from ..functions.formulas import shingle_hashes, shingles

    items, docs = table(spark, sf_dir, "benchmark", "text"), table(spark, sf_dir, "documents", "doc_id", "text")
    keys = items.select(F.explode(shingle_hashes(F.col("text"), 8)).alias("elem")).distinct()
    asked = docs.select("doc_id", F.explode(shingle_hashes(F.col("text"), 8)).alias("elem"), F.lit(0).alias("seg"))
    plan = filters.OneRegion.plan(keys.count(), 0.001, 1)
    hits = filters.probe(asked, filters.build_any(keys, plan, "xx"), plan, family="xx").where("maybe").select("doc_id").distinct()
    spelled = docs.join(hits, "doc_id", "left_semi").select("doc_id", F.explode(shingles(F.col("text"), 8)).alias("gram"))
    exact = items.select(F.explode(shingles(F.col("text"), 8)).alias("gram")).distinct()
    return spelled.join(exact, "gram", "left_semi").groupBy("doc_id").agg(F.count_distinct("gram").alias("shared"))


@add("weighted_hist_orders", f"WITH k AS (SELECT o_orderkey FROM orders WHERE o_orderpriority = '1-URGENT'), q AS (SELECT l_orderkey, count(*) AS w FROM lineitem GROUP BY 1), x AS (SELECT o_orderkey, 1 AS is_key, 0 AS w FROM k UNION ALL SELECT l_orderkey, 0, w FROM q WHERE l_orderkey NOT IN (SELECT o_orderkey FROM k)) SELECT i::INT AS seg, coalesce(sum(is_key), 0)::BIGINT AS kc, coalesce(sum(w), 0)::BIGINT AS qc FROM range(20) r(i) LEFT JOIN x ON {O.u60_sql("o_orderkey::VARCHAR || '#w'")} % 20 = i GROUP BY i")
def weighted_hist_orders(spark, sf_dir):
    """Queries weighted by how often each non-key is asked."""
    from ..functions.hashing import bucket
    from ..operators.elements import from_keys

    keys = table(spark, sf_dir, "orders", "o_orderkey", "o_orderpriority").where("o_orderpriority = '1-URGENT'").select(F.col("o_orderkey").cast("string").alias("elem"))
    asked = table(spark, sf_dir, "lineitem", "l_orderkey").select(F.col("l_orderkey").cast("string").alias("elem"))
    rows_ = from_keys(keys, asked).withColumn("seg", bucket(F.col("elem"), "w", 20))
    return segments.histogram(rows_, 20, F.col("weight"), "is_key = 1", "is_key = 0")


# ---- MLlib scorers: no SQL can repeat them
URL_FEATURES = tuple(f"f_{x}" for x in "length host path digits question hash slash dot dash equals amp https sub tld depth html utm".split())
LINE_FEATURES = ("price", "discount", "tax")
VECTOR_FEATURES = tuple(f"e{i}" for i in range(W.VECTOR))


def ml_scored(spark, sf_dir, kind: str, name: str, features, n: int = 100, **options):
    """Rows with score and seg, and the scorer, of a workload with an MLlib scorer."""
    from ..functions.formulas import seg_of
    from ..operators import elements

    u = W.vectors(spark, sf_dir) if name == "vectors" else W.line(spark, sf_dir) if name == "line" else W.url_features(W.url(spark, sf_dir))
    g = staged(elements.split(elements.universe(u, *features)), "universe")
    s = scorers.fit(g.where("part <> 'eval'"), kind, features, **options)
    return staged(s.score(g).withColumn("seg", seg_of(F.col("score"), n)).select("elem", "is_key", "part", "score", "seg"), "scored"), s


def _ml(kind: str, name: str, features):
    @add(f"{kind}_{name}_rows")
    def q(spark, sf_dir):
        r, s = ml_scored(spark, sf_dir, kind, name, features)
        p = planner.top_boundary(Histogram.of(segments.histogram(r, 100)), 5, 0.001)
        f = measure.f1(r).first()["f1"]
        return rows(spark, [(kind, name, float(f or 0.0), p.divergence, p.bits_per_key, s.model_bits())], "scorer string, workload string, f1 double, divergence double, bits_per_key double, model_bits bigint")


for _kind in ("forest", "logit", "gbt"):
    _ml(_kind, "line", LINE_FEATURES)
_ml("forest", "url", URL_FEATURES)
_ml("logit", "vectors", VECTOR_FEATURES)


@add("actual_rate_forest_url")
def actual_rate_forest_url(spark, sf_dir):
    """As actual_rate_url, with the forest as the scorer."""
    r, _ = ml_scored(spark, sf_dir, "forest", "url", URL_FEATURES)
    return built_answers(r, Histogram.of(segments.histogram(r, 100)), 5, 0.001)


@add("score_distributions")
def score_distributions(spark, sf_dir):
    """Keys and non-keys by score, for each scorer and workload: (workload, scorer, seg, keys, non_keys) in 20 slices."""
    out = None
    for name, kind in (("line", "cells"), ("url", "cells"), ("line", "forest"), ("url", "forest"), ("vectors", "logit")):
        features = {"line": LINE_FEATURES, "url": URL_FEATURES, "vectors": VECTOR_FEATURES}[name]
        r = scored(spark, sf_dir, name).rows if kind == "cells" else ml_scored(spark, sf_dir, kind, name, features, N)[0]
        d = r.groupBy("seg").agg(F.count_if(F.col("is_key") == 1).alias("keys"), F.count_if(F.col("is_key") == 0).alias("non_keys")).select(F.lit(name).alias("workload"), F.lit(kind).alias("scorer"), "seg", "keys", "non_keys")
        out = d if out is None else out.unionByName(d)
    return out


@add("training_loss_line")
def training_loss_line(spark, sf_dir):
    """The same logistic scorer trained by squared error and by the divergence of its scores: what the choice is worth."""
    got = []
    for loss in scorers.LOSSES:
        r, s = ml_scored(spark, sf_dir, "steps", "line", LINE_FEATURES, 100, loss=loss)
        p = planner.top_boundary(Histogram.of(segments.histogram(r, 100)), 5, 0.001)
        got.append((loss, float(measure.f1(r).first()["f1"] or 0.0), p.divergence, p.bits_per_key, s.model_bits()))
    return rows(spark, got, "loss string, f1 double, divergence double, bits_per_key double, model_bits bigint")


@add("quantile_segments_line")
def quantile_segments_line(spark, sf_dir):
    """Equal slices of the axis against slices at score quantiles, planned alike: divergence and bits by number."""
    g = staged(scored(spark, sf_dir, "line", 100).rows.select("elem", "is_key", "part", "score"), "scored")
    from ..functions.formulas import seg_of

    got = []
    for n in (10, 20, 50, 100):
        edges = segments.quantile_edges(g, n)
        for how, seg, size in (("equal", seg_of(F.col("score"), n), n), ("quantile", segments.seg_between(F.col("score"), edges), len(edges) + 1)):
            h = Histogram.of(segments.histogram(g.withColumn("seg", seg), size))
            p = planner.top_boundary(h, min(5, size), 0.001)
            got.append((how, n, size, p.divergence, p.bits_per_key))
    return rows(spark, got, "slices string, asked int, segments int, divergence double, bits_per_key double")


BLOCKLIST = "regexp_matches(url, '^[a-z]+://([^/?#]*\\.)?(spam-farm|cheap-pills)[^/?#]*')"


@add("blocklist_hosts", f"SELECT count(DISTINCT url) AS urls, count(DISTINCT url) FILTER (WHERE {BLOCKLIST}) AS keys, count(DISTINCT url) FILTER (WHERE {BLOCKLIST}) AS found, 0::BIGINT AS missed FROM pages")
def blocklist_hosts(spark, sf_dir):
    """Pages on blocked hosts, as they are: few keys or none. A filter of them is built and asked for every page, and what
    it says yes to meets the exact list."""
    pages = table(spark, sf_dir, "pages", "url").where("url is not null").select(F.col("url").alias("elem")).distinct()
    keys = pages.where(F.col("elem").rlike(r"^[a-z]+://([^/?#]*\.)?(spam-farm|cheap-pills)[^/?#]*"))
    plan = filters.OneRegion.plan(keys.count(), 0.001, 1)
    said = staged(filters.probe(pages.withColumn("seg", F.lit(0)), filters.build_any(keys, plan, "xx"), plan, family="xx").select("elem", "maybe"), "said")
    asked = said.join(keys.select("elem", F.lit(True).alias("is_key")), "elem", "left")
    key = F.coalesce("is_key", F.lit(False))
    return asked.agg(F.count("*").alias("urls"), F.count_if(key).alias("keys"), F.count_if(key & F.col("maybe")).alias("found"), F.count_if(key & ~F.col("maybe")).alias("missed"))


# ---- SQL for what is defined above the pieces it needs
ORACLES["equal_key_cuts_line"] = O.query([*LINE, *CUTS_SQL, "qc1 AS (SELECT " + ", ".join(f"(SELECT min(t) FROM pre2 WHERE a_low >= {r}::DOUBLE / 4 - 1e-12) AS q{r}" for r in (1, 2, 3)) + ")", f"sp AS (SELECT c1, c2, least(greatest(q3, c2 + 1), {N - 1}) AS c3 FROM (SELECT c1, least(greatest(q2, c1 + 1), {N - 2}) AS c2, q3 FROM (SELECT least(greatest(q1, 1), {N - 3}) AS c1, q2, q3 FROM qc1)))", *O.regions_of(f"SELECT 0 AS pid, [0, c1, c2, c3, {N}] AS cuts FROM sp"), *O.capped("0.01"), "best AS (SELECT 0 AS pid)"], O.PLAN_ROWS)
ORACLES["sandwich_for_budget_line"] = O.query([*LINE, *CUTS_SQL, f"sb AS (SELECT x.bits, t, a_low, b_low, least(1, a_low * (1 - b_low) / (b_low * (1 - a_low))) AS free FROM tl, (VALUES (2.0::DOUBLE), (4.0::DOUBLE), (6.0::DOUBLE), (8.0::DOUBLE)) x(bits) WHERE a_low > 0 AND b_low > 0 AND a_low < 1)", "sr AS (SELECT *, CASE WHEN bits + a_low * log2(free) >= 0 THEN pow(2::DOUBLE, -(bits + a_low * log2(free))) ELSE 1 END AS front, CASE WHEN bits + a_low * log2(free) >= 0 THEN free ELSE pow(2::DOUBLE, -bits / a_low) END AS backup FROM sb)", "se AS (SELECT *, front * (1 - b_low + b_low * backup) AS rate FROM sr)", "sx AS (SELECT *, row_number() OVER (PARTITION BY bits ORDER BY round(rate, 12), t) AS nth FROM se)"], f"SELECT bits AS bits_per_key, t::INT AS cut, {O.dec('front', 9)} AS front, {O.dec('backup', 9)} AS backup, {O.dec('rate', 9)} AS expected_rate FROM sx WHERE nth = 1")
SAVED_KS = (2, 3, 4, 5, 6)
ORACLES["saved_vs_k_line_n20"] = " UNION ALL ".join(f"SELECT * FROM ({O.query([*LINE, *O.top_boundary(k, '0.001')], f"SELECT {k} AS k, {O.dec('log2(1000::DOUBLE) - min(size)')} AS saved_per_key FROM z")})" for k in SAVED_KS)


@add("saved_vs_k_line_n20", ORACLES["saved_vs_k_line_n20"])
def saved_vs_k_line_n20(spark, sf_dir):
    """Bits saved a key for each number of regions, on twenty segments."""
    got = [(p.k, math.log2(1000) - p.bits_per_key) for p in planner.sweep_k(histogram(spark, sf_dir, "line"), SAVED_KS, 0.001)]
    return rows(spark, got, "k int, saved_per_key double").select("k", dec("saved_per_key").alias("saved_per_key"))


def _single_array(name: str, rate: str, keys: str) -> list[str]:
    """SQL of an array with the keys that ``keys`` selects at a rate: sizes, set bits, and (elem, hit) of all rows."""
    h1, h2 = u60_sql("elem"), u60_sql("elem || '#2'")
    size = f"SELECT count(*) AS n, any_value({rate}) AS rate FROM g, tw WHERE part = 'key' AND {keys}"
    return [
        f"{name}_m AS (SELECT n, rate, CASE WHEN n = 0 OR rate >= 1 THEN 0 ELSE greatest(32, ceil(round({LOG2E!r}::DOUBLE * n * log2(1 / rate), 6)))::BIGINT END AS m, CASE WHEN n = 0 OR rate >= 1 THEN 0 ELSE greatest(1, round(log2(1 / rate)))::INT END AS h FROM ({size}))",
        f"{name}_k AS (SELECT DISTINCT ({h1} % m + i * (({h2} | 1) % m)) % m AS pos FROM g, tw, {name}_m, range(60) x(i) WHERE part = 'key' AND {keys} AND m > 0 AND i < h)",
        f"{name}_a AS (SELECT elem, CASE WHEN any_value(n) = 0 THEN false WHEN any_value(rate) >= 1 THEN true ELSE bool_and({name}_k.pos IS NOT NULL) END AS hit FROM (SELECT elem, n, rate, m, CASE WHEN m > 0 THEN ({h1} % m + i * (({h2} | 1) % m)) % m END AS pos FROM g, {name}_m, range(60) x(i) WHERE i < greatest(1, h)) y LEFT JOIN {name}_k USING (pos) GROUP BY elem)",
    ]


def _two_stage_sql(plan: str) -> str:
    tw = f"tw AS ({plan})"
    arrays = [*_single_array("f", "front", "true"), *_single_array("b", "backup", "seg < t")]
    a = "a AS (SELECT g.elem, part, f_a.hit AND (seg >= t OR b_a.hit) AS maybe FROM g JOIN f_a USING (elem) JOIN b_a USING (elem), tw)"
    return O.query([*LINE, *CUTS_SQL, *_sandwich_sql("0.3"), tw, *arrays, a], f"SELECT {O.ANSWERS} FROM a")


ORACLES["probe_counts_sandwich"] = _two_stage_sql("SELECT t, front, backup FROM sw ORDER BY round(size, 9), t LIMIT 1")
ORACLES["probe_counts_single"] = _two_stage_sql("SELECT t, 1::DOUBLE AS front, least(1, (0.3::DOUBLE - (1 - b_low)) / b_low) AS backup FROM tl WHERE a_low > 0 AND 0.3::DOUBLE - (1 - b_low) > 0 ORDER BY round(-a_low * log2(least(1, (0.3::DOUBLE - (1 - b_low)) / b_low)), 9), t LIMIT 1")
