"""Plans that the design relies on."""

import re

import pytest
from conftest import SF

from dpchangelog import catalog

QUERIES, _ = catalog.load()


def plan(df) -> str:
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


def test_time_ranges_reach_the_scan(spark):
    text = plan(QUERIES["filter_time_range"](spark, SF))
    assert re.search(r"PushedFilters: .*GreaterThan\(ts", text) and "props" not in re.search(r"ReadSchema: (.*)", text)[1]


@pytest.mark.parametrize("name", ["changelog_event_state", "disjoint_noisy_laplace", "tree_nodes_noisy", "sliding_direct_noisy", "rr_mutation_counts"])
def test_columns_are_pruned(spark, name):
    schema = re.search(r"ReadSchema: (.*)", plan(QUERIES[name](spark, SF)))[1]
    assert "props" not in schema and "value" not in schema


def test_first_k_is_limited_before_the_shuffle(spark):
    text = plan(QUERIES["enforce_k"](spark, SF))
    assert "WindowGroupLimit" in text


@pytest.mark.parametrize("name", ["disjoint_noisy_laplace", "tree_nodes_noisy", "range_from_tree", "sliding_direct_noisy", "sliding_from_tree_noisy", "histogram_release_daily"])
def test_one_scan_and_no_python(spark, name):
    text = plan(QUERIES[name](spark, SF))
    assert len(re.findall(r"\(\d+\) Scan parquet", text)) == 1
    assert not re.search("EvalPython|InPandas|InArrow|CartesianProduct", text)
    assert "partial_sum" in text


def test_noise_stays_in_the_jvm(spark):
    df = QUERIES["disjoint_noisy_laplace"](spark, SF)
    secret = QUERIES["disjoint_noisy_secret"](spark, SF)
    assert "sha2" in secret._jdf.queryExecution().optimizedPlan().toString() and not re.search("Python|InArrow|InPandas", plan(secret))
    assert "md5" in df._jdf.queryExecution().optimizedPlan().toString() and "EvalPython" not in plan(df)


def test_cover_slack_has_every_length(spark):
    n = {(r.c, r.h): r["count"] for r in QUERIES["cover_slack"](spark, SF).groupBy("c", "h").count().collect()}
    assert n == {(2, 8): 255, (3, 5): 242, (10, 2): 99}


@pytest.fixture(scope="module")
def stored(spark, tmp_path_factory):
    from dpchangelog.catalog.base import event_state
    from dpchangelog.sources import tables

    at = f"file://{tmp_path_factory.mktemp('log')}/log"
    tables.write_changelog(event_state(spark, SF), at)
    return tables.read(spark, at)


def _releases():
    from dpchangelog.catalog.base import EVENT_TYPES, T0
    from dpchangelog.functions.intervals import DAY, HOUR, IntervalGrid
    from dpchangelog.functions.noise import Key, Noise
    from dpchangelog.operators import hierarchy, linear, release, responses, sliding

    grid, q, n, k = IntervalGrid.regular(T0 + 5 * DAY, HOUR, 48), linear.count_if(lambda v: v == "error"), Noise("laplace", 0.5), Key("t", "p", public=True)
    return {
        "disjoint": lambda cl: release.disjoint(cl, grid, q, n, k),
        "tree": lambda cl: hierarchy.hierarchy(cl, grid, 2, 4, q, n, k),
        "sliding": lambda cl: sliding.from_hierarchy(cl, sliding.SlidingSpec(T0 + 6 * DAY, DAY, HOUR, 24), q, n, k, 2),
        "histogram": lambda cl: release.histogram(cl, grid, cl.sparkSession.createDataFrame([(s,) for s in EVENT_TYPES], "symbol string"), n, k),
        "responses": lambda cl: responses.mutation_counts(cl, cl.select("entry").distinct(), grid, EVENT_TYPES, 1.0, k),
    }


@pytest.mark.parametrize("name", list(_releases()))
def test_releases_read_only_their_days(spark, stored, name):
    text = plan(_releases()[name](stored))
    assert re.search(r"PushedFilters: \[[^\]]*GreaterThan\(ts,[0-9]+\), LessThanOrEqual\(ts,", text)
    assert re.search(r"PartitionFilters: \[[^\]]*ts_day#\d+\w* >= 19728.*ts_day#\d+\w* <= (19729|19730)", text)


def test_pruned_releases_are_the_same(spark, stored):
    from dpchangelog.catalog.base import event_state

    for f in _releases().values():
        a, b = (sorted(map(tuple, f(cl).collect())) for cl in (stored, event_state(spark, SF)))
        assert a == b


@pytest.mark.parametrize("name", ["rr_mutation_counts", "local_linear_change_daily", "base_local_vote", "rr_tree_nodes", "local_tree_daily"])
def test_reports_are_not_shuffled(spark, name):
    """Entries times intervals are laid out after the join, so no exchange has them: a Generate stands above the join."""
    text = plan(QUERIES[name](spark, SF))
    assert not re.search("CartesianProduct|NestedLoop", text)
    tree = text.split("\n\n")[0]
    assert re.search(r"Generate[\s\S]*Join", tree), tree


def test_response_tree_scans_the_changelog_once(spark):
    text = plan(QUERIES["rr_tree_nodes"](spark, SF))
    assert len(re.findall(r"\(\d+\) Scan parquet", text)) == 2  # the changelog, and the entries


def test_order_ship_shuffles_each_table_once(spark):
    text = plan(QUERIES["changelog_order_ship"](spark, SF)).split("\n\n")[0]
    assert len(re.findall(r"\bExchange\b", text)) + len(re.findall("BroadcastExchange", text)) <= 2 + len(re.findall("BroadcastExchange", text))
    assert len(re.findall(r"Scan parquet", text)) == 2


def test_first_mutations_share_the_shuffle(spark):
    text = plan(QUERIES["enforce_b"](spark, SF)).split("\n\n")[0]
    assert len(re.findall(r"\bExchange\b", text)) == 1 and len(re.findall(r"Scan parquet", text)) == 1


READS = [
    "cover_slack",
    "filtered_budgets",
    "composition_table",
    "base_fanout_sweep",
    "base_running_sum_variance",
    "cover_worked_example",
    "cover_nodes_ranges",
    "matched_epsilon",
    "crossover_grid_b",
    "crossover_grid_k",
    "local_folds_table",
    "folds_table",
]


@pytest.mark.parametrize("name", READS)
def test_spark_reads_a_table(spark, name):
    assert re.search(r"\(\d+\) Scan parquet", plan(QUERIES[name](spark, SF)))


def test_crossovers_of_columns_equal_those_of_numbers(spark):
    from pyspark.sql import functions as F

    from dpchangelog.plans import accounting as A

    pairs = [(w, 1) for w in (1, 2, 3, 4, 8, 9, 16, 27, 81, 256, 257, 400, 2**40)] + [(w, p) for w in range(2, 16) for p in range(1, w + 1)]
    df = spark.createDataFrame(pairs, "w long, p long")
    for c in (2, 3, 16):
        left, right, wins = A.prefer_tree_k(F.col("w"), F.col("p"), c)
        got = {(r.w, r.p): (r.l, r.r, r.x) for r in df.select("w", "p", left.alias("l"), right.alias("r"), wins.alias("x")).collect()}
        assert got == {(w, p): A.prefer_tree_k(w, p, c) for w, p in pairs}
        for b in (1, 7, 30):
            for formula in ("safe", "published"):
                left, right, wins = A.prefer_tree_b(F.col("w"), F.col("p"), b, c, formula)
                got = {(r.w, r.p): (pytest.approx(r.l), pytest.approx(r.r), r.x) for r in df.select("w", "p", left.alias("l"), right.alias("r"), wins.alias("x")).collect()}
                assert {(w, p): A.prefer_tree_b(w, p, b, c, formula) for w, p in pairs} == got


def test_compositions_of_columns_equal_those_of_numbers(spark):
    from dpchangelog.plans import accounting as A

    rows = QUERIES["composition_table"](spark, SF).collect()
    assert len({r.k for r in rows}) > 1
    for r in rows:
        b = A.Budget(r.eps)
        best = min(x.eps for x in A.compose_optimal(b, r.k) if x.delta <= 1e-6)
        want = (r.k * r.eps, A.compose_advanced(b, r.k, 1e-6).eps, best, A.zcdp_epsilon(r.eps**2 / 2, r.k, 1e-6), A.compose_renyi(lambda a, e=r.eps: A.renyi_laplace(a, 1 / e), r.k, 1e-6))
        assert (r.basic, r.advanced, r.optimal, r.zcdp, r.renyi) == pytest.approx(want, abs=2e-6)


def test_no_entry_pays_more_than_the_filters_say(spark):
    rows = QUERIES["filtered_budgets"](spark, SF).collect()
    assert len(rows) == 4 and all(0 < r.paid <= r.eps and r.entries > 0 for r in rows)
