"""What queries on large tables keep on disk while they run."""

import os

from regionfilter import workloads
from regionfilter.operators import filters
from regionfilter.queries import methods


def _folders_while(spark, monkeypatch, run, name="build_any"):
    """Names of the staged folders that are there each time a filter is built."""
    seen, build = [], getattr(filters, name)

    def noted(*args, **kw):
        root = spark.conf.get("spark.checkpoint.dir").removeprefix("file://")
        seen.append({d for d in os.listdir(root) if d not in before})
        return build(*args, **kw)

    workloads.staged(spark.range(1), "first")  # so that there is a root
    before = set(os.listdir(spark.conf.get("spark.checkpoint.dir").removeprefix("file://")))
    monkeypatch.setattr(filters, name, noted)
    run()
    return [{d.rsplit("-", 5)[0].split("-")[0] for d in x} for x in seen]


def test_the_universe_goes_before_filters_are_built(spark, sf, monkeypatch):
    seen = _folders_while(spark, monkeypatch, lambda: methods.QUERIES["actual_rate_all"](spark, sf).collect())
    assert seen and all("scored" in x and "universe" not in x for x in seen)


def test_rows_meet_their_cells_without_a_shuffle(spark, sf):
    rows = workloads.scored(spark, sf, "line").rows
    assert "Exchange hashpartitioning" not in rows._jdf.queryExecution().executedPlan().toString()


def test_probes_shuffle_no_row_for_each_position(spark, sf):
    """Bitmaps of a broadcast size meet the rows where they are; blocks meet a row's two offsets, not its positions."""
    g, _, p = methods._fixed_plan(spark, sf)
    keys = g.where("part = 'key'")
    plan = filters.probe_bitmap(g, filters.build_bitmap(keys, p, "md5"), p, "md5")._jdf.queryExecution().executedPlan().toString()
    assert "Exchange hashpartitioning" not in plan and "Generate" not in plan
    blocks = workloads.staged(filters.build_blocked(keys, p, "md5"), "blocks").hint("merge")
    plan = filters.probe(g, blocks, p, "shuffle", "md5")._jdf.queryExecution().optimizedPlan().toString()
    assert "transform(" not in plan[plan.index("Join"):]
