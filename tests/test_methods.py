"""Bounds, covers, noise, composition, responses and constraints against brute force and worked examples."""

import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from dpchangelog.functions import noise
from dpchangelog.functions.intervals import DAY, IntervalGrid, interval_span
from dpchangelog.operators import changelog, constraints, hierarchy, linear, metrics, release, responses, sliding
from dpchangelog.operators.sliding import SlidingSpec
from dpchangelog.plans import accounting as A
from dpchangelog.plans.ledger import Busy, Ledger, Overspent
from dpchangelog.plans.planner import choose_sliding_plan, cover, fanout_sweep, worst_cover

SCHEMA = "entry long, ts long, seq long, kind string, before string, after string"


def log(spark, rows):
    return spark.createDataFrame([(e, t, 0, "update", b, a) for e, t, b, a in rows], SCHEMA)


def touched_by_window(endpoints, b):
    """Brute force over windows [s, s + b] at endpoints: intervals met, over grids without end."""
    return interval_span(endpoints, b)


@pytest.mark.parametrize(("endpoints", "b", "span"), [([1, 2, 3], 100, 3), ([0, 10, 11, 12, 13], 5, 4), (list(range(0, 50, 5)), 12, 4), ([0, 1, 2, 3], 0, 1), ([], 3, 0)])
def test_span_cases(endpoints, b, span):
    assert interval_span(endpoints, b) == span


@given(st.integers(1, 20), st.integers(0, 60))
def test_span_of_regular_grid_is_the_closed_form(w, b):
    assert interval_span([i * w for i in range(200)], b) == A.folds_disjoint_b_regular(b, w)


@given(st.integers(1, 30), st.integers(1, 30), st.integers(0, 40))
@settings(max_examples=60)
def test_sliding_folds_bound_what_a_window_touches(w, p, b):
    most = max(sum(1 for i in range(-80, 80) if i * p - w < s + b and s <= i * p) for s in range(p * 3))
    assert most <= max(A.folds_sliding_b(b, w, p), math.ceil((b + w) / p) + 1)


@pytest.mark.parametrize("c", [2, 3, 4, 5, 10])
def test_covers_are_exact_and_within_the_bound(c):
    h = A.height_for(120, c)
    for l in range(0, 40):
        for r in range(l + 1, l + 60):
            nodes = cover(l, r, c, h)
            base = sorted(i for j, k in nodes for i in range(k * c**j, (k + 1) * c**j))
            assert base == list(range(l, r))
            assert len(nodes) <= A.cover_bound(r - l, c)


def test_cover_worked_example():
    assert len(cover(0, 99, 10, 2)) == 18


@pytest.mark.parametrize(("c", "worst"), [(2, [2, 3, 4, 6, 8]), (10, [10])])
def test_worst_covers(c, worst):
    for h, most in enumerate(worst[1:] if c == 2 else worst, 2 if c == 2 else 1):
        assert max(worst_cover(n, c, h) for n in range(1, c**h + 1)) >= most - 1


@pytest.mark.parametrize(("c", "h"), [(2, 3), (2, 8), (3, 4), (4, 3), (7, 2), (10, 2)])
def test_worst_covers_over_all_offsets(c, h):
    for n in range(1, 2 * c**h):
        assert worst_cover(n, c, h) == max(len(cover(l, l + n, c, h)) for l in range(c ** (h - 1)))


def test_planner_looks_at_trees_for_long_windows():
    best = choose_sliding_plan(14 * 24 * 60, 1, 1.0, k=1)  # 14 days, every minute
    assert best.kind == "tree" and best.worst_variance < 2 * 1404 + 1
    assert choose_sliding_plan(10**9, 1, 1.0, k=1).kind == "tree"


def test_tree_folds_safe_and_published():
    assert A.folds_tree_b(3, 2, 1, 1) == 6
    assert A.folds_tree_b(3, 2, 1, 1, "published") == pytest.approx(4.75)


@pytest.mark.parametrize(("c", "fails"), [(2, {3, 4, 5, 6, 7, 9, 10, 11}), (3, {2, 4, 5, 10}), (4, {2, 5, 6}), (16, {2, 3, 4, 5})])
def test_crossover(c, fails):
    assert {r for r in range(2, 400) if not A.prefer_tree_k(r, 1, c)[2]} == fails


def test_crossover_with_b():
    assert A.prefer_tree_b(14, 1, 1, 4)[0] == pytest.approx(126.8, abs=0.1)
    assert A.prefer_tree_b(14, 1, 1, 4, "safe")[0] == 192
    assert A.prefer_tree_b(28, 1, 1, 2, "published")[2] and not A.prefer_tree_b(28, 1, 1, 2, "safe")[2]


def test_matched_ratio():
    assert metrics.matched_ratio(14, 1, 2)["tree_bound"] == pytest.approx(0.653, abs=1e-3)
    assert metrics.matched_ratio(14, 1, 2)["flat"] == pytest.approx(1 / 14)


def test_planner_prefers_flat_then_trees():
    assert choose_sliding_plan(14, 1, 1.0, k=1).kind == "flat"
    best = choose_sliding_plan(90, 1, 1.0, k=1)
    assert (best.kind, best.c, best.h) == ("tree", 7, 2)
    assert best.worst_variance / (2 * 90**2) == pytest.approx(0.0089, abs=1e-4)


def test_composition():
    b = A.Budget(0.1)
    assert A.compose_basic([b, [b, [b]]]) == A.compose_basic([b, b, b])
    assert A.compose_advanced(b, 512, 1e-6).eps < A.fold(512, b).eps
    best = min(x.eps for x in A.compose_optimal(b, 64) if x.delta <= 1e-6)
    assert best <= A.compose_advanced(b, 64, 1e-6).eps
    assert A.compose_optimal(b, 8)[0].delta == pytest.approx(0)
    with pytest.raises(ValueError):
        A.compose_optimal(b, 8, adaptive=True)
    assert A.compose_renyi(lambda a: A.renyi_gaussian(a, 5.0), 10, 1e-6) < 20
    assert A.hybrid_bound([A.Budget(1, 0), A.Budget(0.5, 1e-6)]) == A.Budget(1, 1e-6)
    assert A.split_budget(A.Budget(1.0), 4).eps == 0.25
    assert A.split_budget(A.Budget(1.0), 400, "best", 1e-6).eps > 1 / 400


def test_gaussian_calibrations():
    s = noise.sigma_analytic(1, 0.5, 1e-5)
    assert noise.gaussian_delta(1, s, 0.5) <= 1e-5 and s < noise.sigma_classic(1, 0.5, 1e-5)


@pytest.mark.parametrize("kind", ["laplace", "geometric", "gaussian"])
def test_noise_has_its_variance_and_repeats(spark, kind):
    n = noise.Noise(kind, 0.5, 1e-6)
    k = noise.Key("test", "v" + kind, public=True)
    df = spark.range(20000).select(n.draw(1, 1, k, "0", F.col("id")).alias("x"))
    a = np.array([r.x for r in df.collect()])
    assert a.var() == pytest.approx(n.variance(1, 1), rel=0.1) and abs(a.mean()) < 4 * math.sqrt(n.variance(1, 1) / 20000)
    assert a.tolist() == [r.x for r in df.collect()]


def test_secret_noise_differs_from_the_public_key(spark):
    k = noise.Key("test", "s", b"secret")
    a = spark.range(5).select(noise.laplace(1.0, k, F.col("id")).alias("x")).collect()
    b = spark.range(5).select(noise.laplace(1.0, noise.Key("test", "s", public=True), F.col("id")).alias("x")).collect()
    assert a != b


def test_keys_are_secret_or_said_to_be_public():
    with pytest.raises(ValueError):
        noise.Key("test", "s")
    with pytest.raises(ValueError):
        noise.Key("test", "s", b"secret", public=True)


def test_secret_draws_are_hmac(spark):
    import hashlib
    import hmac

    k = noise.Key("name", "rel", b"a secret that is longer than one block of the hash function, which is sixty-four bytes")
    own = hmac.new(k.secret, b"name|rel", hashlib.sha256).digest()
    for r in spark.range(20).select("id", noise.uniform(k, "0", F.col("id")).alias("u")).collect():
        digest = hmac.new(own, f"name|rel|0|{r.id}|".encode(), hashlib.sha256).hexdigest()
        assert r.u == (int(digest[:13], 16) + 0.5) / 2**52


def test_boundaries_belong_to_the_interval_they_end(spark):
    g = IntervalGrid.regular(0, 10, 3)
    out = g.assign(spark.createDataFrame([(t,) for t in (0, 1, 10, 11, 30, 31)], "ts long"))
    assert [(r.ts, r.idx) for r in out.orderBy("ts").collect()] == [(1, 0), (10, 0), (11, 1), (30, 2)]
    e = IntervalGrid.explicit(range(0, 1000, 7))
    out = e.assign(spark.range(0, 1100).select(F.col("id").alias("ts")))
    assert all(r.idx * 7 < r.ts <= r.idx * 7 + 7 for r in out.collect()) and out.count() == 7 * e.n


def test_empty_changelog_still_answers(spark):
    empty = spark.createDataFrame([], SCHEMA)
    g, q = IntervalGrid.regular(0, 10, 4), linear.count_if(lambda v: v == "a")
    assert release.disjoint(empty, g, q, noise.OFF, noise.Key("t", "r", public=True)).count() == 4
    assert hierarchy.hierarchy(empty, g, 2, 3, q, noise.OFF, noise.Key("t", "r", public=True)).count() == 7
    assert sliding.direct(empty, SlidingSpec(10, 10, 5, 3), q, noise.OFF, noise.Key("t", "r", public=True)).count() == 3


def test_all_sliding_plans_agree_without_noise(spark):
    rows = [(i % 5, 7 * i + 1, "a" if i % 2 else None, "a" if not i % 2 else "b") for i in range(60)]
    cl, q = log(spark, rows), linear.count_if(lambda v: v == "a")
    for w, p in ((14, 1), (36, 24), (6, 12), (20, 20)):
        s = SlidingSpec(w, w, p, 8)
        direct = {r.idx: r.exact for r in sliding.direct_exact(cl, s, q).collect()}
        want = {i: sum((a == "a") - (b == "a") for _, t, b, a in rows if i * p < t <= i * p + w) for i in range(8)}
        assert direct == want
        assert {r.idx: r.estimate for r in sliding.from_hierarchy(cl, s, q, noise.OFF, noise.Key("t", "r", public=True), 2).collect()} == want
        assert {r.idx: r.estimate for r in sliding.from_flat(cl, s, q, noise.OFF, noise.Key("t", "r", public=True)).collect()} == want


def test_consistency_makes_parents_sums_of_children(spark):
    cl = log(spark, [(i, i + 1, None, "a") for i in range(16)])
    nodes = hierarchy.hierarchy(cl, IntervalGrid.regular(0, 1, 16), 2, 5, linear.count_if(lambda v: v == "a"), noise.Noise("laplace", 0.2), noise.Key("test", "c", public=True))
    u = {(r.layer, r.idx): r.consistent for r in hierarchy.make_consistent(nodes, 16, 2, 5).collect()}
    assert len(u) == 31
    assert all(u[j, i] == pytest.approx(u[j - 1, 2 * i] + u[j - 1, 2 * i + 1]) for j, i in u if j)
    # The same by least squares.
    raw = {(r.layer, r.idx): r.noisy for r in nodes.collect()}
    a = np.array([[1.0 if i // 2**j == k else 0.0 for i in range(16)] for j, k in raw])
    leaf = np.linalg.lstsq(a, np.array(list(raw.values())), rcond=None)[0]
    assert np.allclose(leaf, [u[0, i] for i in range(16)])


def test_state_graphs():
    roles = [(None, "system"), (None, "user"), ("system", "user"), ("user", "assistant"), ("assistant", "user")]
    assert constraints.mutation_bound(roles)[0] == 2
    assert constraints.mutation_bound([(None, 1), (1, 2), (2, 3)])[0] == 3
    assert constraints.mutation_bound([(None, "a"), ("a", "b"), ("b", "a")])[0] == 1


def test_enforced_constraints_hold(spark):
    cl = log(spark, [(e, t * DAY, None if t == 0 else "a", "a") for e in range(4) for t in range(12)])
    assert constraints.violators(constraints.enforce_k(cl, 5), k=5).count() == 0
    assert constraints.violators(constraints.enforce_b(cl, 3 * DAY), b=3 * DAY).count() == 0


def test_value_change_round_trip_and_snapshots(spark):
    cl = log(spark, [(1, 1, None, "a"), (1, 5, "a", "b"), (1, 9, "b", None), (2, 2, None, "c")])
    back = changelog.to_value_change(changelog.to_new_value(cl))
    assert sorted((r.entry, r.ts, r.before, r.after) for r in back.collect()) == sorted((r.entry, r.ts, r.before, r.after) for r in cl.collect())
    assert {(r.entry, r.value) for r in changelog.snapshot_at(cl, 5).collect()} == {(1, "b"), (2, "c")}
    assert {(r.entry, r.value) for r in changelog.snapshot_at(cl, 9).collect()} == {(2, "c")}
    assert changelog.chain_violations(cl).count() == 0


@pytest.mark.parametrize("compact", [False, True])
def test_response_estimates_two_ways(compact):
    z, eps = 4, 1.3
    size = responses.pair_size(z, compact)
    counts = np.random.default_rng(3).integers(0, 50, size)
    p, q = responses.optimal_matrix(size, eps)
    closed = responses.change_matrix(z, compact) @ counts / (p - q)
    assert np.allclose(closed, responses.estimate_change_by_matrix(counts, z, eps, compact))


def test_response_matrix():
    m = responses.ResponseMatrix.optimal(4, 1.0)
    assert m.epsilon() == pytest.approx(1.0) and m.delta(1.0) == pytest.approx(0) and m.delta(0.5) > 0
    with pytest.raises(ValueError):
        responses.ResponseMatrix([[1, 0], [1, 1]])
    with pytest.raises(ValueError):
        responses.ResponseMatrix(np.full((3, 3), 1 / 3)).estimate([1, 2, 3])


def test_exact_variance_values():
    assert metrics.change_variance(1, 0, 2, 1.0) == pytest.approx(14.52, abs=0.01)
    assert metrics.change_variance(1, 0, 5, 1.0) == pytest.approx(127.75, abs=0.01)
    assert metrics.change_variance(1, 0, 5, 1.0, compact=True) == pytest.approx(110.82, abs=0.01)
    assert metrics.change_variance(1, 0, 2, 1.0, compact=True) == pytest.approx(11.81, abs=0.01)


def test_estimates_are_unbiased_and_have_that_variance():
    z, eps, n, runs = 2, 1.0, 400, 800
    size = responses.pair_size(z)
    p, q = responses.optimal_matrix(size, eps)
    est = np.array([responses.change_matrix(z) @ responses.simulate_null_reports(n, size, eps, s) / (p - q) for s in range(runs)])
    var = metrics.change_variance(n, 0, z, eps)
    assert np.abs(est.mean(0)).max() < 5 * math.sqrt(var / runs)
    assert est.var(0) == pytest.approx([var] * z, rel=0.2)
    cov = metrics.change_covariance(responses.simulate_null_reports(n, size, eps, 1), z, eps)
    assert cov.shape == (z, z) and np.diag(cov) == pytest.approx([var] * z, rel=0.3)


def test_ledger(spark, tmp_path):
    book = Ledger(spark, str(tmp_path / "book"), A.Budget(1.0))
    book.charge("one", 2, A.Budget(0.25))
    with pytest.raises(Exception):
        book.charge("one", 1, A.Budget(0.1))
    with pytest.raises(Overspent):
        book.charge("two", 3, A.Budget(0.25))
    assert book.remaining().eps == pytest.approx(0.5)
    # One writer at a time: a second one is refused while the lock is there.
    (tmp_path / "book/_lock").touch()
    with pytest.raises(Busy):
        book.charge("three", 1, A.Budget(0.1))
    book.unlock()
    cl = log(spark, [(1, 5, None, "a")])
    q = linear.count_if(lambda v: v == "a")
    out = book.release("four", 1, noise.Noise("laplace", 0.5), lambda n: release.disjoint(cl, IntervalGrid.regular(0, 10, 2), q, n, noise.Key("t", "four", b"x")), str(tmp_path / "out"))
    assert out.count() == 2 and book.remaining().eps == pytest.approx(0)
    with pytest.raises(Overspent):
        book.release("five", 1, noise.Noise("laplace", 0.1), lambda n: 1 / 0, str(tmp_path / "out"))


def test_sql_functions_and_tables(spark):
    from dpchangelog.functions import sql

    sql.register(spark)
    assert spark.sql("select interval_idx(10, 0, 10) a, interval_idx(11, 0, 10) b, interval_idx(0, 0, 10) c").first() == (0, 1, -1)
    assert sorted(map(tuple, spark.sql("select layer, idx from cover_nodes(5, 17, 2, 5)").collect())) == sorted(cover(5, 17, 2, 5))
    assert spark.sql("select * from tree_nodes(5, 2, 3)").count() == 5 + 3 + 2
    want = spark.range(1).select(noise.laplace(2.0, noise.Key("test", "q", public=True), F.lit(3)).alias("x")).first().x
    assert spark.sql("select lap_noise(concat_ws('|', 'test', 'q', 3, ''), 2.0D) as x").first().x == pytest.approx(want)


def test_change_feed_source_and_sinks(spark, tmp_path):
    import json

    from dpchangelog.sources import tables
    from dpchangelog.sources.change_feed import ChangeFeed

    (tmp_path / "feed").mkdir()
    rows = [{"entry": 1, "ts": 5, "kind": "insert", "after": "a"}, {"entry": 1, "ts": 9, "seq": 2, "kind": "update", "before": "a", "after": "b"}]
    (tmp_path / "feed/1.jsonl").write_text("\n".join(map(json.dumps, rows)))
    spark.dataSource.register(ChangeFeed)
    cl = spark.read.format("change_feed").option("path", str(tmp_path / "feed")).load()
    assert [tuple(r) for r in cl.orderBy("ts").collect()] == [(1, 5, 0, "insert", None, "a"), (1, 9, 2, "update", "a", "b")]
    tables.write_changelog(cl, str(tmp_path / "log"))
    assert tables.read(spark, str(tmp_path / "log")).count() == 2
    r = release.disjoint(cl, IntervalGrid.regular(0, 10, 2), linear.count_if(lambda v: v == "b"), noise.OFF, noise.Key("t", "r", public=True))
    tables.write_release(r, str(tmp_path / "out"), release_id="one")
    with pytest.raises(Exception):
        tables.write_release(r, str(tmp_path / "out"), release_id="one")
    series = tables.snapshot_series(spark, {1: str(tmp_path / "out/release=one")})
    assert series[0][1].count() == 2


def test_release_spec():
    from dpchangelog.plans.planner import ReleaseSpec, best_fanout, explain_release

    assert ReleaseSpec("r", 30).budget(A.Budget(0.1), None).eps == pytest.approx(3)
    assert ReleaseSpec("r").budget(A.Budget(0.1), 4).eps == pytest.approx(0.4)
    with pytest.raises(ValueError):
        ReleaseSpec("r").budget(A.Budget(0.1), None)
    with pytest.raises(ValueError):
        ReleaseSpec("r", adaptive=True).budget(A.Budget(0.1), 8, "optimal", 1e-6)
    assert best_fanout(720) in range(2, 65)
    assert "4 folds" in explain_release("r", 4, A.Budget(0.1), 2.0)


def test_neighbours_and_separating_queries(spark):
    from dpchangelog.operators import local

    cl = log(spark, [(1, 5, None, "a"), (2, 5, None, "a"), (2, 15, "a", "b"), (3, 25, None, "c")])
    assert changelog.without_entry(cl, 2).count() == 2 and changelog.with_entry(changelog.without_entry(cl, 2), cl.where("entry = 2")).count() == 4
    g = IntervalGrid.regular(0, 10, 3)
    assert [r.idx for r in local.separating_queries(cl, g, 1, 2).collect()] == [1]
    assert sorted(r.idx for r in local.separating_queries(cl, g, 1, 3).collect()) == [0, 2]


def test_wider_searches_never_give_more_variance():
    for w in (90, 4096, 4097, 8760, 20160):
        found = [choose_sliding_plan(w, 1, 1.0, k=1, fanouts=range(2, c)).worst_variance for c in (3, 9, 33, 65)]
        assert found == sorted(found, reverse=True)
    assert choose_sliding_plan(8760, 1, 1.0, k=1).worst_variance / 2 <= 1280
    assert choose_sliding_plan(4097, 1, 1.0, k=1).kind == "tree"


def test_sweep_counts_prefix_covers():
    for c, h, nodes, _ in fanout_sweep(50, range(2, 8)):
        assert nodes == max(len(cover(0, r, c, h)) for r in range(1, 51))


@pytest.mark.parametrize("grid", [IntervalGrid.regular(0, 10, 5), IntervalGrid.explicit([3, 4, 20, 50])])
def test_states_at_interval_ends(spark, grid):
    rows = [(1, -5, None, "a"), (1, 10, "a", "b"), (1, 11, "b", "c"), (1, 44, "c", None), (2, 7, None, "x"), (2, 7, "x", "y"), (3, 99, None, "z")]
    cl = spark.createDataFrame([(e, t, n, "update", b, a) for n, (e, t, b, a) in enumerate(rows)], SCHEMA)
    got = {(r.entry, r.idx): r.value for r in changelog.states_at(cl, grid).collect()}
    want = {(e, i): next((a for x, t, _, a in reversed(rows) if x == e and t <= grid.end(i)), None) for e in (1, 2, 3) for i in range(grid.n)}
    assert got == want


def test_null_entries_and_long_vectors(spark):
    cl = spark.createDataFrame([(1, 5, 0, "insert", None, "a"), (None, 6, 0, "insert", None, "b")], SCHEMA)
    assert changelog.without_entry(cl, 1).count() == 1 and changelog.without_entry(cl, 2).count() == 2 and changelog.without_entry(cl, None).count() == 1
    v = spark.createDataFrame([(1, None, [1.0, 2.0, 3.0])], "idx long, before array<double>, after array<double>")
    assert linear.vector_change(v, 3, 1.0).count() == 3
    with pytest.raises(Exception, match="longer than 2"):
        linear.vector_change(v, 2, 1.0).collect()


def test_values_outside_the_alphabet_answer(spark):
    k, symbols = noise.Key("t", "foreign", public=True), ["a", "b"]
    df = spark.range(20000).select("id", F.when(F.col("id") % 2 == 0, "zzz").alias("v"))  # foreign, or null
    n = {r.out_code: r.n for r in responses.static_counts(df, "id", "v", symbols, 1.0, k).collect()}
    assert sum(n.values()) == 20000 and abs(n[0] - 10000) < 400
    m = responses.ResponseMatrix([[0.6, 0.2], [0.4, 0.8]])
    got = df.select(m.respond(responses.code_of("v", symbols), k, F.col("id")).alias("c")).groupBy("c").count().collect()
    assert sum(r["count"] for r in got) == 20000 and abs({r.c: r["count"] for r in got}[0] / 20000 - 0.4) < 0.02


def test_first_interval_holds_the_state_before_the_grid(spark):
    cl = log(spark, [(i, i, None, "a") for i in range(20)] + [(3, 25, "a", "b")])
    grid, q, k = IntervalGrid.regular(10, 10, 4), linear.count_if(lambda v: v == "a"), noise.Key("t", "r", public=True)
    nodes = hierarchy.hierarchy(cl, grid, 2, 3, q, noise.OFF, k, from_beginning=True)
    assert {r.idx: r.estimate for r in hierarchy.prefix_series(nodes, 4, 2, 3).collect()} == {0: 20, 1: 19, 2: 19, 3: 19}
    symbols = spark.createDataFrame([("a",), ("b",)], "symbol string")
    nodes = hierarchy.hierarchy_histogram(cl, grid, 2, 3, symbols, noise.OFF, k, from_beginning=True)
    assert {(r.idx, r.symbol): r.estimate for r in hierarchy.prefix_series(nodes, 4, 2, 3).collect()}[3, "b"] == 1


def test_filters():
    from dpchangelog.plans.filters import Filter, are_disjoint, are_parallel, by_group, filtered_budget

    early, late = Filter.time(0, 10), Filter.time(10, 20)
    assert are_disjoint(early, late) and not are_parallel(early, late) and not are_disjoint(early, Filter.time(9, None))
    a, b = (Filter.among("region", [x], fixed=True) for x in "ab")
    assert are_disjoint(a, b) and are_parallel(a, b) and are_parallel(a.and_(early), b) and not are_disjoint(a, a.and_(late))
    loose = Filter.among("status", ["x"]), Filter.among("status", ["y"])
    assert are_disjoint(*loose) and not are_parallel(*loose)
    one = A.Budget(0.5, 1e-6)
    assert filtered_budget([(a, one), (b, one)]) == one and filtered_budget([(early, one), (late, one)]).eps == 1
    assert filtered_budget([(a, one), (b, A.Budget(0.7)), (early, one)]) == A.Budget(1.2, 2e-6)
    assert by_group("region", "ab", one) == one and by_group("region", "ab", one, fixed=False).eps == 1
    with pytest.raises(ValueError):
        Filter.time(5, 5)


def test_filter_columns(spark):
    from dpchangelog.plans.filters import Filter

    cl = log(spark, [(1, 5, None, "a"), (2, 15, "a", None), (3, 25, None, "c")])
    assert [r.entry for r in Filter.time(5, 25).apply(cl).orderBy("entry").collect()] == [2, 3]
    assert [r.entry for r in Filter.among("after", ["a", None]).apply(cl).orderBy("entry").collect()] == [1, 2]
    assert Filter.among("after", []).apply(cl).count() == 0


def test_local_releases_without_noise(spark):
    from dpchangelog.operators import local

    cl = log(spark, [(1, 5, None, "a"), (2, 5, None, "a"), (2, 15, "a", "b"), (3, 25, None, "a")])
    entries, q, k = spark.range(1, 6).withColumnRenamed("id", "entry"), linear.count_if(lambda v: v == "a"), noise.Key("t", "l", public=True)
    plain = local.Randomizer(lambda exact, key, *parts: exact.cast("double"), 1.0)
    g = IntervalGrid.regular(0, 10, 4)
    assert [(r.idx, r.estimate, r.var) for r in local.linear_change(cl, entries, g, q, 1.0, k, plain).orderBy("idx").collect()] == [(0, 2, 5), (1, -1, 5), (2, 1, 5), (3, 0, 5)]
    nodes = local.tree(cl, entries, g, 2, 2, q, 1.0, k, plain)
    assert {(r.layer, r.idx): r.noisy for r in nodes.collect()} == {(0, 0): 2, (0, 1): -1, (0, 2): 1, (0, 3): 0, (1, 0): 1, (1, 1): 1}
    s = SlidingSpec(20, 20, 5, 4)
    want = {r.idx: r.exact for r in sliding.direct_exact(cl, s, q).collect()}
    assert {r.idx: r.estimate for r in local.sliding(cl, entries, s, q, 1.0, k, plain).collect()} == want


def test_one_bit_reports_are_unbiased(spark):
    from dpchangelog.operators import local

    q = linear.count_if(lambda v: v == "a")
    how = local.sign_reports(q, 1.0)
    r = spark.range(40000).select(how.report(F.lit(1), noise.Key("t", "bit", public=True), F.col("id")).alias("x")).agg(F.avg("x")).first()[0]
    assert r == pytest.approx(1, abs=4 * math.sqrt(how.variance / 40000))


def test_matched_budgets_on_data(spark):
    from conftest import SF

    from dpchangelog import catalog

    rows = catalog.load()[0]["sliding_matched_budget"](spark, SF).toPandas()
    by = rows.groupby("plan").agg(var=("var", "mean"), measured=("measured", "mean"))
    assert (abs(by.measured / by["var"] - 1) < 0.15).all()  # 17 windows of 100 keys each
    assert by["var"]["flat"] < by["var"]["tree"] < by["var"]["direct"] and by.measured["tree"] < by.measured["direct"]
    assert (rows.bias.abs() < 5 * (rows["var"] / 100) ** 0.5).all()


def test_response_estimates_are_unbiased_on_data(spark):
    from conftest import SF

    from dpchangelog import catalog

    for r in catalog.load()[0]["rr_bias_over_keys"](spark, SF).collect():
        assert abs(r.bias) < 4 * r.standard_error and r.n == 600
    assert all(r.within for r in catalog.load()[0]["neighbour_output_ratio"](spark, SF).collect())


def test_ordered_changelogs(spark):
    cl = log(spark, [(e, (e * 7919 + t * 104729) % 1000, None, "a") for e in range(20) for t in range(30)])
    got = [(r.ts, r.entry) for r in changelog.ordered(cl).collect()]
    assert got == sorted(got) and len(got) == 600


def test_bucketed_changelogs_need_no_shuffle(spark, tmp_path):
    from dpchangelog.sources import tables

    cl = log(spark, [(e % 40, e, None, "a") for e in range(400)])
    spark.sql("drop table if exists bucketed_log")
    tables.save_bucketed(cl, "bucketed_log", 4)
    held = spark.table("bucketed_log")
    text = constraints.enforce_b(held, 50)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in text and constraints.enforce_b(held, 50).count() == constraints.enforce_b(cl, 50).count()
    spark.sql("drop table bucketed_log")


def test_restarted_batches_publish_once(spark, tmp_path):
    from dpchangelog.streaming import streams

    g, q = IntervalGrid.regular(0, 10, 3), linear.count_if(lambda v: v == "a")
    write = streams.release_sink("r", str(tmp_path / "out"), lambda b: release.disjoint(b, g, q, noise.Noise("laplace", 0.5), noise.Key("t", "r", b"s")))
    log(spark, [(1, 5, None, "a"), (2, 15, None, "b")]).write.parquet(str(tmp_path / "in"))
    rows = spark.readStream.schema(SCHEMA).parquet(str(tmp_path / "in"))
    rows.writeStream.foreachBatch(write).option("checkpointLocation", str(tmp_path / "cp")).trigger(availableNow=True).start().awaitTermination()
    first = sorted(map(tuple, spark.read.parquet(str(tmp_path / "out")).collect()))
    write(spark.read.schema(SCHEMA).parquet(str(tmp_path / "in")), 0)  # the same batch again
    assert sorted(map(tuple, spark.read.parquet(str(tmp_path / "out")).collect())) == first and len(first) == 3


def test_release_specs_are_charged(spark, tmp_path):
    from dpchangelog.plans.planner import ReleaseSpec

    book = Ledger(spark, str(tmp_path / "book"), A.Budget(2.0))
    assert book.charge_spec(ReleaseSpec("endless"), A.Budget(0.1), 5).eps == pytest.approx(0.5)
    assert book.charge_spec(ReleaseSpec("finite", 10), A.Budget(0.1), None).eps == pytest.approx(1.0)
    with pytest.raises(ValueError):
        book.charge_spec(ReleaseSpec("no limit"), A.Budget(0.1), None)
    with pytest.raises(ValueError):
        book.charge_spec(ReleaseSpec("adaptive", adaptive=True), A.Budget(0.1), 4, "optimal", 1e-6)
    with pytest.raises(Overspent):
        book.charge_spec(ReleaseSpec("more", 6), A.Budget(0.1), None)
    assert book.remaining().eps == pytest.approx(0.5)


def test_costs_of_a_release(spark):
    from conftest import SF

    from dpchangelog import catalog

    found = metrics.cost(catalog.load()[0]["disjoint_noisy_laplace"](spark, SF))
    assert found["rows"] == 30 and found["scanned_bytes"] > 0 and 0 < found["shuffled_bytes"] and found["seconds"] > 0
