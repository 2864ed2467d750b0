"""Physical plans: scans read keys and features only, and nothing is crossed."""

import re

from pathlift.operators import augment, edge_stats, quality
from pathlift.sources.repository import EDGES, Repository, path_of


def plan_of(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_augmentation_reads_two_keys_and_a_feature(spark, data):
    repo = Repository(spark, data)
    plan = plan_of(augment.augment(repo, repo.table("orders").select("o_orderkey", "o_custkey"), path_of("e1", "e2"), "n_name"))
    schemas = re.findall(r"ReadSchema: struct<([^>]*)>", plan)
    assert sorted(len(s.split(",")) for s in schemas) == [2, 2, 2] and "CartesianProduct" not in plan and "Python" not in plan


def test_quality_is_semi_joins_on_keys(spark, data):
    repo = Repository(spark, data)
    plan = plan_of(quality.reachable_keys(repo, path_of("e5r", "e7")))
    assert "LeftSemi" in plan and all(len(s.split(",")) <= 2 for s in re.findall(r"ReadSchema: struct<([^>]*)>", plan))


def test_bridge_filters_reach_the_scan(spark, data):
    plan = plan_of(quality.reachable_keys(Repository(spark, data), path_of("e14")))
    assert re.search(r"PushedFilters: \[[^\]]*o_orderpriority", plan)


def test_edge_statistics_stay_in_the_jvm(spark, data):
    plan = plan_of(edge_stats.edge_statistics(Repository(spark, data), EDGES[:4]))
    assert "Python" not in plan and "Arrow" not in plan and "CartesianProduct" not in plan


def test_rows_meet_their_key_once(spark, data):
    """Cells of a far table are folded where its rows met by key: nothing is dealt by cell."""
    repo = Repository(spark, data)
    ways = [edge_stats.Leaving(path_of(e).edges[0], c) for e in ("e5r", "e6r") for c in ("l_quantity", "l_returnflag")]
    plan = plan_of(edge_stats.leaving_statistics(repo, ways))
    dealt = re.findall(r"hashpartitioning\(([^()]*(?:\([^()]*\)[^()]*)*), \d+\)", plan)
    assert dealt and not any("key#" in d and ("bin#" in d or "_groupingexpression#" in d) for d in dealt), dealt


def test_rows_meet_the_near_side_before_their_cells_are_taken_apart(spark, data):
    """The join by key sees a row of the far table once, not once a cell, and no cells folded beforehand."""
    repo = Repository(spark, data)
    ways = [edge_stats.Leaving(path_of("e5r").edges[0], c) for c in ("l_quantity", "l_returnflag")]
    lines = plan_of(edge_stats.leaving_statistics(repo, ways)).splitlines()
    depth = [len(re.match(r"[\s:+*()\d-]*", x)[0]) for x in lines]
    joins = [i for i, x in enumerate(lines) if "Join" in x and "key#" in x]
    assert joins
    for i in joins:
        below = next((j for j in range(i + 1, len(lines)) if depth[j] <= depth[i]), len(lines))
        assert not any("Generate" in x or "bin#" in x for x in lines[i + 1 : below])
