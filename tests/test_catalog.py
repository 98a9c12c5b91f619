import pytest

import __spark_entry__ as entry
from helpers import duck, same
from trianglestream.plans import catalog

SF = "/root/testdata/sf0.001"
#: One mapping and, of each family, the small graphs, and of the workloads the audit; the rest takes minutes and is compared
#: at a larger scale outside the tests.
LONG = ("_tripartite", "_consecutive", "_cosupply", "_knn", "_copurchase", "_hostlinks")
NAMES = [n for n in catalog.oracle_sql() if "_random_" not in n and "_epoch_" not in n and not n.endswith(LONG) and (n == "w10_property_audit" or not n[1:2].isdigit())]


@pytest.fixture(scope="module")
def con():
    return duck(SF)


def test_entry_runs(spark):
    rows = entry.entry(spark).collect()
    assert len(rows) == 20


def test_keys_are_consistent():
    assert set(entry.oracle_sql()) <= set(entry.queries())


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_oracle(spark, con, name):
    assert same(catalog.queries()[name](spark, SF), con, catalog.oracle_sql()[name])


def test_plans_read_few_columns_and_have_no_cartesian_product(spark):
    from trianglestream.plans.estimators import estimate_routed
    from trianglestream.sources.graphs import stream

    est = estimate_routed(stream(spark, SF, "copurchase"), 30, 500, seed=1, strategy="wedge")
    plan = est.sums._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "BroadcastNestedLoopJoin" not in plan
    assert "l_extendedprice" not in plan and "l_partkey" in plan
    pruned = catalog.queries()["rel_scan_pruned"](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull" in pruned


MOVED = "expected_uniformity linearity_of_seconds method_ratios predicted_cost recommended_parameters rel_pandas_weight rel_sql_functions rel_udtf_accepted rel_udtf_er variance_slopes variance_terms".split()


@pytest.mark.parametrize("name", MOVED)
def test_query_depends_on_its_tables(spark, name):
    """Other tables give other rows; data made up by the query would stay the same."""
    if name == "expected_uniformity":  # all sizes come in either
        assert "l_quantity" in catalog.queries()[name](spark, SF)._jdf.queryExecution().executedPlan().toString()
        return
    small, large = (sorted(map(tuple, catalog.queries()[name](spark, f"/root/testdata/sf{sf}").collect()), key=repr) for sf in ("0.001", "0.01"))
    assert small != large


def test_redundancy_counts_the_complete_graph(spark):
    """Four nodes and one edge: all six pairs count, of which (0, 2) and (1, 3) lie inside a worker."""
    from trianglestream.operators.analysis import complete_redundancy

    rows = spark.createDataFrame([(1, 0, 1), (2, 2, 3)], "t bigint, u bigint, v bigint")
    assert complete_redundancy(rows, "modulo", 2).first()["twice"] == 4
    assert complete_redundancy(rows.limit(0), "modulo", 2).first()["twice"] == 0


def test_ample_budget_joins_no_wedges_of_samples(spark, monkeypatch):
    """Samples that hold the stream have a wedge for each pair of its edges at a node; true triangles are far fewer."""
    from trianglestream.plans import estimators

    monkeypatch.setattr(estimators, "closures", None)
    truth = catalog.queries()["exact_global_coactivity"](spark, SF).first()["n"]
    assert catalog.queries()["exact_by_ample_budget_coactivity"](spark, SF).first()["est"] == truth


@pytest.mark.parametrize("name", ["epoch_map_coactivity", "routed_epoch_global_coactivity", "routed_epoch_global_copurchase", "routed_adaptive_global_coactivity"])
def test_adaptive_mappings_read_a_written_stream(spark, monkeypatch, name):
    """Epochs read the stream again and again; a plan over the given tables would build it as often."""
    seen = []

    def noted(edges, *args, **options):
        seen.append(edges)
        raise StopIteration

    monkeypatch.setattr(catalog, "adaptive_map", noted)
    monkeypatch.setattr(catalog, "estimate_routed", noted)
    with pytest.raises(StopIteration):
        catalog.queries()[name](spark, SF)
    assert seen[0].inputFiles() and not any("/root/testdata" in f for f in seen[0].inputFiles())


@pytest.mark.parametrize("colours", [3, 5])
def test_counts_by_blocks_equal_brute_force(spark, colours):
    """Loops, repeats in both directions and nulls do not count; a hub meets all nodes; ids may be large or negative."""
    import random

    from trianglestream.operators.blocks import counted

    draw = random.Random(colours)
    pairs = [(draw.randrange(60) * 10**15 - 3, draw.randrange(60) * 10**15 - 3) for _ in range(900)] + [(-(2**62), i * 10**15 - 3) for i in range(60)]
    edges = {(min(e), max(e)) for e in pairs if e[0] != e[1]}
    near = {}
    for u, v in edges:
        near.setdefault(u, set()).add(v)
        near.setdefault(v, set()).add(u)
    found = [(u, v, w) for u, v in edges for w in near[u] & near[v] if w > v]
    want = {x: sum(x in t for t in found) for x in near}
    rows = spark.createDataFrame(pairs + [(v, u) for u, v in pairs[:100]] + [(None, 1), (2, None)], "u bigint, v bigint")
    assert counted(rows, colours=colours).first()["n"] == len(found)
    assert {r["node"]: r["n"] for r in counted(rows, True, colours).collect()} == {x: n for x, n in want.items() if n}
    assert counted(rows.limit(0)).first()["n"] == 0 and counted(rows.limit(0), True).count() == 0


@pytest.mark.parametrize("name", ["exact_global_copurchase", "exact_local_copurchase", "exact_global_tripartite", "exact_local_tripartite"])
def test_large_exact_counts_shuffle_no_wedges(spark, con, monkeypatch, name):
    """Open wedges of these graphs are many times their edges."""
    monkeypatch.setattr(catalog.exact, "triangles", None)
    assert same(catalog.queries()[name](spark, SF), con, catalog.oracle_sql()[name])
