"""Worked examples, measures and invariants of the methods."""

import collections
import os
import pathlib
import shutil
import subprocess
import sys

import numpy as np
import pytest
from pyspark.sql import functions as F

from tilestar import runtime
from tilestar.functions import layout
from tilestar.operators import lu, multiply, tiles
from tilestar.plans import execute, onepass, schedulers, select
from tilestar.runtime import Scratch, bucketed
from tilestar.sources import platforms


def test_sides_are_exact(spark):
    ms = [1, 2, 3, 4, 5, 20, 21, 22, 2**53 + 1, (10**9) ** 2 - 1, (10**9) ** 2]
    rows = layout.sides(spark.createDataFrame([(m,) for m in ms], "m bigint")).collect()
    for r in rows:
        for name, need in (("g_single", lambda g: 1 + g + g * g), ("g_overlap", lambda g: g * g + 4 * g), ("g_plain", lambda g: g * g + 2 * g), ("g_third", lambda g: 3 * g * g), ("g_fifth", lambda g: 5 * g * g)):
            g = r[name]
            assert (g == 0 or need(g) <= r["m"]) and need(g + 1) > r["m"], (name, r["m"], g)


def test_toy_winners():
    assert onepass.min_min(2, 4, 7, 3, 3)[0] == 49 < onepass.thrifty(2, 4, 7, 3, 3)[0] == 50
    assert onepass.thrifty(2, 8, 9, 6, 3)[0] == 132 < onepass.min_min(2, 8, 9, 6, 3)[0] == 139


@pytest.mark.parametrize(("case", "best"), [((4, 7, 3, 3), 71), ((8, 9, 6, 3), 178), ((4, 1, 5, 2), 30), ((3, 2, 4, 4), 40), ((5, 1, 6, 3), 48)])
def test_alternation_is_optimal(case, best):
    c, w, r, s = case
    assert onepass.one_worker(onepass.alternating(r, s), c, w) == onepass.exhaustive(r, s, c, w) == best


def test_selection_trace(spark):
    rows = select.as_rows(platforms.literal(spark, platforms.THREE))
    one = select.fold(rows, 15, "global").first()
    assert one["picks"] == [2, 1, 3, 1, 3, 1, 3, 1, 3, 1, 3, 1, 3, 2, 1]
    assert one["ends"] == [108, 132, 232, 256, 356, 380, 480, 504, 604, 628, 728, 752, 852, 1080, 1104]
    two = select.fold(rows, 15, "local").first()
    assert two["picks"] == [2, 1, 3, 1, 3, 1, 3, 1, 3, 1, 3, 1, 3, 1, 2] and two["ends"][-3:] == [852, 876, 1080]


@pytest.mark.parametrize(("rule", "ratio"), [("global", 1.173), ("local", 1.210), ("global2", 1.276), ("global2_receding", 1.307)])
def test_long_run_ratio(spark, rule, ratio):
    got = select.asymptotic_ratio(select.fold(select.as_rows(platforms.literal(spark, platforms.THREE)), 3000, rule)).first()["ratio"]
    assert got == pytest.approx(ratio, abs=0.003)


def test_slow_worker_is_never_picked(spark):
    for rule in ("global", "local"):
        assert set(select.fold(select.as_rows(platforms.literal(spark, platforms.FAST_SLOW)), 50, rule).first()["picks"]) == {1}


def test_makespans_of_the_experiment_sets():
    expected = {
        (100, 100, 800, 10485): (32_020_000, 32_000_000, 71_200_000, 32_000_000, 32_000_000, 46_000_000, 58_000_000),
        (200, 200, 800, 2703): (160_240_000, 160_000_000, 255_065_000, 160_000_000, 160_000_000, 252_000_000, 316_000_000),
    }
    for (r, t, s, m), want in expected.items():
        got = []
        for policy in schedulers.POLICIES:
            run = schedulers.play(policy, r, t, s, [(100, 7, m)] * 8)
            assert run.updates == r * t * s
            got.append(max(max(x[7], x[9]) for x in run.rows))
        assert tuple(got) == want


def test_workers_enrolled_by_memory():
    used = lambda policy, m: len({x[1] for x in schedulers.play(policy, 200, 200, 800, [(100, 7, m)] * 8).rows})
    assert used("rr_selected", 2703) == 2 and used("rr_selected", 10485) == 4 and used("demand_plain", 10485) == 8 and used("minmin_overlap", 10485) == 2


def test_no_buffers_is_an_error():
    with pytest.raises(ValueError):
        schedulers.play("demand_overlap", 2, 2, 2, [(1, 1, 4)])


def test_kernels_on_ragged_and_empty(spark):
    rng = np.random.default_rng(1)
    a, b = rng.integers(-3, 4, (7, 5)), rng.integers(-3, 4, (5, 11))
    cells = lambda x, names: spark.createDataFrame([(int(i), int(j), int(v)) for (i, j), v in np.ndenumerate(x) if v], ", ".join(f"{n} bigint" for n in names))
    da, db = cells(a, "ikv"), cells(b, "kju")
    want = {(i, j): v for (i, j), v in np.ndenumerate(a @ b) if v}
    kernels = {
        "chunked": multiply.chunked(da, db, multiply.Cut.squares(7, 11, 3)),
        "pruned": multiply.chunked(da, db, multiply.Cut.squares(7, 11, 20), prune=True),
        "salted": multiply.inner_join(da, db, salt=3),
        "broadcast": multiply.broadcast(da, db),
        "not broadcast": multiply.broadcast(da, db, most=0),
        "slabs": multiply.slabs(da, db, 7, [3, 1, 1]),
        "weighted": multiply.weighted_grid(da, db, 7, 11, [2, 1], [1, 1, 3]),
        "shifted": multiply.shifted(da, db, 7, 5, 11, 2),
        "rectangles": multiply.rectangles(da, db, 7, 11, [4, 2, 1, 1, 1]),
        "inner_split": multiply.inner_split(da, db, 3),
    }
    for name, got in kernels.items():
        assert {(r["i"], r["j"]): r["c"] for r in got.collect() if r["c"]} == want, name
    assert multiply.chunked(da.limit(0), db, multiply.Cut.squares(7, 11, 3)).count() == 0
    tiled = lambda d, q: tiles.to_tiles(d.toDF("row", "col", "val"), q)
    for q in (1, 2, 4):
        out = tiles.to_cells(tiles.resident_multiply(tiled(da, q), tiled(db, q), -(-7 // q), -(-11 // q), 2, q, tiled(kernels["chunked"].limit(0), q)), q)
        assert {(r["row"], r["col"]): round(r["val"]) for r in out.collect()} == want


def test_rectangles_cover_the_result_once():
    seen = np.zeros((13, 17), int)
    for i0, i1, j0, j1 in multiply.packed_rectangles(13, 17, [5, 4, 3, 2, 1, 1]):
        seen[i0:i1, j0:j1] += 1
    assert (seen == 1).all()


def test_messages_equal_the_formula(spark):
    a = spark.range(6 * 4).select((F.col("id") % 6).alias("i"), F.floor(F.col("id") / 6).alias("k"), F.lit(1).alias("v"))
    b = spark.range(4 * 10).select((F.col("id") % 4).alias("k"), F.floor(F.col("id") / 4).alias("j"), F.lit(1).alias("u"))
    got = {r["kind"]: r["tiles"] for r in multiply.messages(a, b, 6, 10, multiply.Cut.squares(6, 10, 4)).collect()}
    assert sum(got.values()) == 2 * 60 + 6 * 4 * 3 + 4 * 10 * 2


def test_lu_zero_pivot_and_factors(spark):
    with pytest.raises(ZeroDivisionError):
        lu.eliminate(np.array([[0.0, 1.0], [1.0, 0.0]]))
    rng = np.random.default_rng(0)
    m = rng.normal(size=(8, 8)) + 20 * np.eye(8)
    cells = spark.createDataFrame([(int(i), int(j), float(v)) for (i, j), v in np.ndenumerate(m)], "row bigint, col bigint, val double")
    low, up = lu.factor(tiles.to_tiles(cells, 2), 4, 2, Scratch(spark, "test"))
    back = np.zeros((8, 8))
    for r in tiles.to_cells(tiles.resident_multiply(low, up, 4, 4, 4, 2), 2).collect():
        back[r["row"], r["col"]] = r["val"]
    assert np.allclose(back, m)


def test_chain_order():
    assert tiles.chain_order([10, 100, 5, 50]) == (7500, "((M1M2)M3)")


def test_package_works_without_the_text_operators(tmp_path):
    """A copy without the optional parts still hands out the other queries."""
    root = pathlib.Path(__file__).parent.parent
    copy = tmp_path / "repo"
    shutil.copytree(root, copy, ignore=shutil.ignore_patterns(".git", "__pycache__", "spark-warehouse"))
    for part in ("tilestar/llm", "tests/llm"):
        shutil.rmtree(copy / part, ignore_errors=True)
    (copy / "corpus_pipeline.py").unlink(missing_ok=True)
    code = "import __spark_entry__ as e; q, o = e.queries(), e.oracle_sql(); assert set(o) <= set(q) and len(q) > 140 and 'pipeline' not in q and not any(n.startswith('op') and n[2].isdigit() for n in q)"
    env = {k: v for k, v in os.environ.items() if k != "PYTHONPATH"}
    assert subprocess.run([sys.executable, "-c", code], cwd=copy, env=env).returncode == 0


def _exchanges(df):
    """Hash or direct exchanges of a plan, and the plan."""
    text = df._jdf.queryExecution().executedPlan().toString()
    return text.count("Exchange "), text


def test_the_resident_product_has_one_exchange(spark):
    a = spark.range(40).selectExpr("id % 8 as i", "id % 5 as k", "id as v")
    b = spark.range(40).selectExpr("id % 5 as k", "id % 8 as j", "id as u")
    for c in (None, a.selectExpr("i", "k as j", "v as c")):
        n, plan = _exchanges(multiply.chunked(a, b, multiply.Cut.squares(8, 8, 4), c))
        assert n == 1, plan
    assert _exchanges(multiply.split(a, b, 8, 8, 48, 3))[0] == 1
    assert _exchanges(multiply.shifted(a, b, 8, 5, 8, 2))[0] == 1


def test_bucketed_operands_join_without_an_exchange(spark):
    a = spark.range(40).selectExpr("id % 8 as i", "id % 5 as k", "id as v")
    b = spark.range(40).selectExpr("id % 5 as k", "id % 8 as j", "id as u")
    stored = [bucketed(x, ["k"], 4) for x in (a, b)]
    joined = stored[0].hint("merge").join(stored[1], "k")
    assert _exchanges(joined)[0] == 0
    rows = lambda df: sorted(map(tuple, df.select("i", "j", "c").collect()))
    assert rows(multiply.inner_join(*stored)) == rows(multiply.inner_join(a, b)) == rows(multiply.inner_join_heavy(a, b, heavy=3, salt=3))


def test_observed_messages_equal_the_formula(spark):
    a = spark.range(64).selectExpr("id div 8 as i", "id % 8 as k", "id as v")
    b = spark.range(128).selectExpr("id div 16 as k", "id % 16 as j", "id as u")
    got = {r["kind"]: r["tiles"] for r in multiply.messages(a, b, 8, 16, multiply.Cut.squares(8, 16, 4)).collect()}
    assert got == {"A": 8 * 8 * 4, "B": 8 * 16 * 2, "C_in": 128, "C_out": 128}
    assert sum(got.values()) == 2 * 8 * 16 + 8 * 8 * -(-16 // 4) + 8 * 16 * -(-8 // 4)


def test_large_sides_are_not_broadcast(spark, monkeypatch):
    scratch = Scratch(spark, "test")
    df = scratch.save(spark.range(1000).selectExpr("id", "repeat('x', 100) as t"), "t")
    size = runtime.in_memory(df)
    assert 1000 * 100 < size < 1000 * 300
    hint = lambda d: "ResolvedHint" in d._jdf.queryExecution().logical().toString() or "UnresolvedHint" in d._jdf.queryExecution().logical().toString()
    assert hint(scratch.small(df, "t"))
    monkeypatch.setattr(runtime, "BROADCAST_MEMORY", size - 1)
    assert not hint(scratch.small(df, "t"))


def test_execution_keeps_the_order_and_the_columns(spark):
    platform = platforms.literal(spark, platforms.THREE)
    trace = select.trace(select.fold(select.as_rows(platform), select.until_owned(20, 4, 60), "global", charge_c=4))
    sent = execute.messages(trace, platform, 20, 4, 60).collect()
    picks = {r["step"]: r["worker_id"] for r in trace.collect()}
    assert all(picks[r["step"]] == r["worker_id"] for r in sent)
    owner = {}
    for r in sent:
        for j in range(r["j0"], r["j1"]):
            assert owner.setdefault(j, r["worker_id"]) == r["worker_id"]
    assert sorted(owner) == list(range(60))
    cells = collections.Counter((i, j, r["k"]) for r in sent for i in range(r["i0"], r["i1"]) for j in range(r["j0"], r["j1"]))
    assert len(cells) == 20 * 60 * 4 and set(cells.values()) == {1}


def test_blocked_factors_and_residual(spark):
    rng = np.random.default_rng(0)
    m = rng.normal(size=(10, 10)) + 20 * np.eye(10)
    cells = spark.createDataFrame([(int(i), int(j), float(v)) for (i, j), v in np.ndenumerate(m)], "row bigint, col bigint, val double")
    low, up = lu.factor(tiles.to_tiles(cells, 2), 5, 2, Scratch(spark, "test"), g=2)
    back = lu.residual(cells, low, up, 5, 2).first()
    assert back["largest"] < 1e-9 and back["relative"] < 1e-12
    assert not low.filter("bj > bi").select(F.explode("tile").alias("x")).filter("abs(x) > 1e-12").count()
    tri = np.tril(m)
    assert np.allclose(lu.forward(tri, m), np.linalg.solve(tri, m))
