"""Every query runs on the smallest tables; those with SQL agree with DuckDB (a sample of the catalogue, each kind once)."""

import duckdb
import pytest

import __spark_entry__ as entry
from modspark.queries import all_queries

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
PICK = [
    "prep_geo_tree", "prep_embedding_knn", "modularity_by_nation", "map_equation", "nmi_four_norms", "move_gain_all", "best_cluster_fixed", "single_pass_assigned", "single_pass_all", "quotient_edges",
    "quotient_incremental_equals_batch", "restream_fixpoint", "edge_stream_capped_n", "connected_components", "overlay_two", "replacement_choice", "paper_table_geomeans", "performance_profile_max", "join_asof", "join_range_interval",
    "metis_roundtrip", "stream_session", "stream_stateful_degree", "sort_total",
]


def canon(rows, names):
    order = sorted(range(len(names)), key=names.__getitem__)
    value = lambda x: round(float(x), 6) if isinstance(x, float) or hasattr(x, "as_tuple") else x
    return sorted((tuple(value(r[i]) for i in order) for r in rows), key=repr), sorted(names)


@pytest.fixture(scope="module")
def duck(sf):
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", PICK)
def test_against_sql(spark, sf, duck, name):
    df = all_queries.QUERIES[name](spark, sf)
    r = duck.execute(all_queries.ORACLES[name])
    assert canon([tuple(x) for x in df.collect()], df.columns) == canon(r.fetchall(), [x[0] for x in r.description])


def test_entry(spark):
    assert entry.entry(spark).count() > 0


def test_sql_belongs_to_queries():
    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert len(all_queries.QUERIES) > 140


def test_experiments_run_whole_workloads(monkeypatch):
    from modspark.config import MemeticConfig
    from modspark.plans import experiments

    asked = []
    for name in ("compare", "edge_order", "memetic_budget", "restream_ablation"):
        monkeypatch.setattr(experiments, name, lambda spark, sf_dir, names, *more, _n=name: asked.append((_n, set(names), more)) or _Frame())
    for name in ("quality_table", "mode_profiles"):
        monkeypatch.setattr(experiments, name, lambda scores: scores)
    every = {f"G{i}" for i in range(1, 11)} | {f"S{i}" for i in range(1, 7)}
    want = {"rq_quality_table": every, "rq_mode_profiles": every, "mode_comparison": every, "rq_ground_truth": {"G3", "G5", "G8", "G1", "G6", "G7", "S1", "S2"},
            "rq_edge_order": {"S2", "G9"}, "rq_memetic_budget": {"G1", "G6"}, "rq_restream_ablation": {"G5", "G9", "S2"}}
    for name, graphs in want.items():
        all_queries.QUERIES[name](None, "")
        fn, names, more = asked.pop()
        assert names == graphs, name
        assert fn != "compare" or more[0].memetic == MemeticConfig()
        assert name != "rq_memetic_budget" or more == ((0, 5, 20, 80),)


class _Frame:
    def where(self, _):
        return self
