"""Pieces of DuckDB SQL from which the oracles are put together. Every piece is a list of common table expressions."""

from __future__ import annotations

from ..functions.formulas import LOG2E
from ..functions.hashing import u60_sql
from ..workloads import SQL, zipf_sql

N = 20


def dec(x: str, places: int = 6) -> str:
    """x rounded to so many places, the same double in both engines."""
    return f"CAST(CAST({x} AS DECIMAL(18, {places})) AS DOUBLE)"


def scored(name: str, n: int = N) -> list[str]:
    """u, p (split), cells, g (score and seg), hist."""
    if name == "zipf":
        rows = [f"g AS (SELECT *, CASE WHEN is_key = 1 THEN 'key' WHEN {u60_sql("elem || '#split'")} % 100 < 40 THEN 'train' ELSE 'eval' END AS part FROM ({zipf_sql(n)}))"]
    else:
        rows = [
            f"u AS ({SQL[name]})",
            f"p AS (SELECT *, CASE WHEN is_key = 1 THEN 'key' WHEN {u60_sql("elem || '#split'")} % 100 < 40 THEN 'train' ELSE 'eval' END AS part FROM (SELECT elem, max(is_key) AS is_key, min(c1) AS c1, min(c2) AS c2 FROM u GROUP BY elem))",
            "cells AS (SELECT c1, c2, (sum(is_key)::DOUBLE + 0.5::DOUBLE) / (count(*) + 1) AS cell_rate FROM p WHERE part <> 'eval' GROUP BY c1, c2)",
            "prior AS (SELECT (sum(is_key)::DOUBLE + 0.5::DOUBLE) / (count(*) + 1) AS prior FROM p WHERE part <> 'eval')",
            "s AS (SELECT p.*, coalesce(cell_rate, prior) AS score FROM p LEFT JOIN cells USING (c1, c2) CROSS JOIN prior)",
            f"g AS (SELECT *, least({n - 1}, greatest(0, floor(round(score, 9) * {n})))::INT AS seg FROM s)",
        ]
    return [*rows, f"hist AS (SELECT i::INT AS seg, count(*) FILTER (WHERE part = 'key') AS kc, count(*) FILTER (WHERE part = 'train') AS qc FROM range({n}) r(i) LEFT JOIN g ON g.seg = i GROUP BY i)"]


def dp(k: int, alpha: float = 0.5) -> list[str]:
    """l1..lk: for every prefix e the best sum, where the last region begins, and all cuts."""
    out = [
        f"pre AS (SELECT 0 AS at, 0::DOUBLE AS k, 0::DOUBLE AS q UNION ALL SELECT seg + 1, sum(kc) OVER (ORDER BY seg)::DOUBLE, sum(qc + {alpha}::DOUBLE) OVER (ORDER BY seg) FROM hist)",
        "pairs AS (SELECT b, e, a_share, b_share, CASE WHEN a_share <= 0 THEN 0 ELSE a_share * log2(a_share / b_share) END AS term FROM (SELECT x.at AS b, y.at AS e, (y.k - x.k) / tk AS a_share, (y.q - x.q) / tq AS b_share FROM pre x JOIN pre y ON x.at < y.at CROSS JOIN (SELECT max(k) AS tk, max(q) AS tq FROM pre)))",
        "l1 AS (SELECT e, term AS best, 0 AS last, [0, e] AS cuts FROM pairs WHERE b = 0)",
    ]
    for j in range(2, k + 1):
        out.append(f"l{j} AS (SELECT e, best, b AS last, list_append(before, e) AS cuts FROM (SELECT pairs.e, pairs.b, l.best + term AS best, l.cuts AS before, row_number() OVER (PARTITION BY pairs.e ORDER BY round(l.best + term, 9) DESC, pairs.b) AS nth FROM l{j - 1} l JOIN pairs ON pairs.b = l.e) WHERE nth = 1)")
    return out


def regions_of(plans: str, alpha: float = 0.5) -> list[str]:
    """r: regions of every plan in the rows (pid, cuts) that ``plans`` selects."""
    return [
        f"plans AS ({plans})",
        "ri AS (SELECT pid, i::INT AS region, cuts[i]::INT AS seg_lo, cuts[i + 1]::INT AS seg_hi FROM (SELECT pid, cuts, unnest(range(1, len(cuts))) AS i FROM plans))",
        f"rs AS (SELECT pid, region, seg_lo, seg_hi, sum(kc)::BIGINT AS n_keys, sum(qc + {alpha}::DOUBLE) AS q FROM ri JOIN hist ON seg >= seg_lo AND seg < seg_hi GROUP BY ALL)",
        "r AS (SELECT pid, region, seg_lo, seg_hi, n_keys, n_keys::DOUBLE / sum(n_keys) OVER (PARTITION BY pid) AS a, q / sum(q) OVER (PARTITION BY pid) AS b FROM rs)",
    ]


def capped(target: str = "0.001") -> list[str]:
    """c: r with the best rates of at most 1, in closed form."""
    return [
        "o AS (SELECT *, a / b AS ratio, coalesce(sum(a) OVER w, 0) AS a_before, coalesce(sum(b) OVER w, 0) AS b_before FROM r WINDOW w AS (PARTITION BY pid ORDER BY a / b DESC, region DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING))",
        f"f AS (SELECT *, CASE WHEN 1 - a_before > 1e-15 THEN greatest(0, {target}::DOUBLE - b_before) / (1 - a_before) ELSE 0 END AS scale FROM o)",
        "m AS (SELECT pid, max(ratio) FILTER (WHERE scale * ratio <= 1 + 1e-12) AS first_free, arg_max(scale, ratio) FILTER (WHERE scale * ratio <= 1 + 1e-12) AS lam FROM f GROUP BY pid)",
        "c AS (SELECT pid, region, seg_lo, seg_hi, n_keys, a, b, CASE WHEN a <= 0 THEN 0 WHEN first_free IS NULL OR ratio > first_free THEN 1 ELSE least(1, lam * ratio) END AS rate FROM f JOIN m USING (pid))",
    ]


#: bits for each key of every plan in c
SIZES = "z AS (SELECT pid, sum(CASE WHEN a > 0 THEN -a * log2(rate) ELSE 0 END) AS size FROM c GROUP BY pid)"


def top_boundary(k: int, target: str, n: int = N) -> list[str]:
    """Through best: the pid of the smallest plan over all starts of the top region."""
    return [*dp(k - 1), *regions_of(f"SELECT e AS pid, list_append(cuts, {n}) AS cuts FROM l{k - 1} WHERE e < {n}"), *capped(target), SIZES, "best AS (SELECT pid FROM z ORDER BY round(size, 9), pid LIMIT 1)"]


def relax_cap(k: int, target: str, n: int = N) -> list[str]:
    return [*dp(k), *regions_of(f"SELECT 0 AS pid, cuts FROM l{k} WHERE e = {n}"), *capped(target), SIZES, "best AS (SELECT 0 AS pid)"]


PLAN_ROWS = f"SELECT region, seg_lo, seg_hi, n_keys, {dec('a')} AS a, {dec('b')} AS b, {dec('rate', 9)} AS rate FROM c WHERE pid = (SELECT pid FROM best)"


def fixed(cuts: list[int], target: str) -> list[str]:
    """A plan of given cuts with capped rates, array sizes m and hashes h."""
    return [*regions_of(f"SELECT 0 AS pid, {cuts} AS cuts"), *capped(target), built("c")]


def built(source: str) -> str:
    return f"built AS (SELECT region, seg_lo, seg_hi, n_keys, rate, CASE WHEN n_keys = 0 OR rate >= 1 THEN 0 ELSE greatest(32, ceil(round({LOG2E!r}::DOUBLE * n_keys * log2(1 / rate), 6)))::BIGINT END AS m, CASE WHEN n_keys = 0 OR rate >= 1 THEN 0 ELSE greatest(1, round(log2(1 / rate)))::INT END AS h FROM {source})"


def words() -> list[str]:
    """w: the filter's words, from g and built."""
    return [
        f"kp AS (SELECT region, m, {u60_sql('elem')} % m AS first, ({u60_sql("elem || '#2'")} | 1) % m AS step, unnest(range(h)) AS i FROM g JOIN built ON seg >= seg_lo AND seg < seg_hi WHERE part = 'key' AND m > 0)",
        "w AS (SELECT region, pos // 32 AS word, bit_or(1::BIGINT << (pos % 32)::INT) AS bits FROM (SELECT region, (first + i * step) % m AS pos FROM kp) GROUP BY ALL)",
    ]


def probed() -> list[str]:
    """a: g with maybe, from w and built."""
    return [
        f"pp AS (SELECT elem, part, region, m, {u60_sql('elem')} % m AS first, ({u60_sql("elem || '#2'")} | 1) % m AS step, unnest(range(h)) AS i FROM g JOIN built ON seg >= seg_lo AND seg < seg_hi WHERE m > 0)",
        "pa AS (SELECT elem, bool_and(coalesce(bits, 0) & (1::BIGINT << (pos % 32)::INT) <> 0) AS hit FROM (SELECT elem, region, (first + i * step) % m AS pos FROM pp) x LEFT JOIN w ON w.region = x.region AND w.word = pos // 32 GROUP BY elem)",
        "a AS (SELECT g.elem, g.part, built.region, CASE WHEN n_keys = 0 THEN false WHEN rate >= 1 THEN true ELSE coalesce(hit, false) END AS maybe FROM g JOIN built ON seg >= seg_lo AND seg < seg_hi LEFT JOIN pa USING (elem))",
    ]


ANSWERS = f"""count(*) FILTER (WHERE part = 'eval') AS n_queries, count(*) FILTER (WHERE part = 'eval' AND maybe) AS false_positives,
 {dec("count(*) FILTER (WHERE part = 'eval' AND maybe)::DOUBLE / count(*) FILTER (WHERE part = 'eval')")} AS rate,
 count(*) FILTER (WHERE part = 'key') AS n_keys, count(*) FILTER (WHERE part = 'key' AND NOT maybe) AS false_negatives"""


def query(ctes: list[str], select: str) -> str:
    return "WITH " + ",\n".join(ctes) + "\n" + select
