"""What the second round's findings were about, small: each of these failed before."""

import re

import numpy as np
import pytest
from cellstream.functions.schedule import SplitSchedule
from cellstream.operators import tree
from cellstream.plans.catalog import CATALOG
from compare import compare

TINY = "/root/testdata/sf0.001"


def plan(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def test_parent_and_child_meet_by_their_cell(spark):
    run, sql = CATALOG["join_parent_child"]
    joins = re.findall(r"(?:SortMergeJoin|ShuffledHashJoin|BroadcastHashJoin) \[(.*?)\], \[", plan(run(spark, TINY)))
    assert any(len(re.findall(r"\bc[012]#", keys)) == 3 for keys in joins)
    assert compare(spark, run, sql, TINY) is None


def test_refine_needs_no_tree_and_few_terms(spark):
    run, sql = CATALOG["roi_refine_events"]
    text = run(spark, TINY)._jdf.queryExecution().analyzed().toString()
    assert "explode" not in text and text.count("shiftleft") < 600
    assert compare(spark, run, sql, TINY) is None


def test_symbols_are_numbered_from_one_run(spark):
    points = spark.range(3000).selectExpr("id * 7919 % 512 AS a0", "id * 104729 % 512 AS a1")
    sch = SplitSchedule.round_robin((9, 9))
    symbols = tree.symbol_stream(tree.count_tree(points, sch), sch.q)
    # The range exchange must have run once, before rows and sizes of its partitions are read.
    assert "rangepartitioning" not in plan(symbols)
    ords = sorted(r[0] for r in symbols.select("ord").collect())
    assert ords == list(range(1, len(ords) + 1))


def _leaves(spark):
    rng = np.random.default_rng(5)
    points = spark.createDataFrame([tuple(int(x) for x in rng.integers(0, 64, 2)) for _ in range(400)] * 2, "a0 long, a1 long")
    sch = SplitSchedule.round_robin((6, 6))
    return points, sch, tree.leaf_multiset(points, sch)


def test_leaves_give_the_payloads_of_the_tree(spark):
    from cellstream.operators import stream_codec

    points, sch, leaves = _leaves(spark)
    nodes = tree.count_tree(points, sch)
    for t in (0, 3, 12):
        for models in ([0] * 12, [1] * 12):
            a, b = (x.orderBy("stage", "tile", "wave").collect() for x in (stream_codec.encode_tiles(nodes, sch, t, models), stream_codec.encode_leaves(leaves, sch, t, models)))
            assert [r[:-1] for r in a] == [r[:-1] for r in b]
    assert stream_codec.choose_models(nodes, sch, 3) == stream_codec.choose_models(leaves, sch, 3)
    assert [stream_codec.choose_tile_bits(nodes, 12, cap) for cap in (0, 5, 60, 10**6)] == [stream_codec.leaf_tile_bits(leaves, 12, cap) for cap in (0, 5, 60, 10**6)]


def test_summary_needs_no_row_a_node(spark):
    from cellstream.operators import codelen

    points, sch, _ = _leaves(spark)
    assert codelen.summary_of(points, sch).collect() == codelen.summary(tree.count_tree(points, sch), sch.q).collect()


@pytest.fixture(scope="module")
def odd(tmp_path_factory):
    """Events with values and times past the lattice and below zero, nulls, and a type of no code."""
    import duckdb

    place = tmp_path_factory.mktemp("odd")
    value = "CASE WHEN event_id % 13 = 3 THEN NULL ELSE value * (1 + event_id % 6) - 20 END AS value"
    kind = "CASE WHEN event_id % 10 = 3 THEN NULL WHEN event_id % 10 = 4 THEN 'other' ELSE event_type END AS event_type"
    ts = "CASE WHEN event_id % 17 = 3 THEN NULL ELSE ts + to_days(CAST(30 * (event_id % 6) AS INT)) - to_days(CAST(event_id % 2 AS INT)) END AS ts"
    duckdb.connect().execute(f"COPY (SELECT event_id, {ts}, user_id, {kind}, {value}, props FROM '{TINY}/events.parquet') TO '{place}/events.parquet'")
    for t in "region nation customer supplier part orders lineitem documents embeddings pages benchmark labels conversations".split():
        (place / f"{t}.parquet").symlink_to(f"{TINY}/{t}.parquet")
    return str(place)


@pytest.mark.parametrize("name", ["decode_3d_events", "progressive_level_6", "progressive_level_14", "progressive_level_24", "progressive_level_36", "roundtrip_events", "tumbling_trees", "sliding_trees", "session_trees"])
def test_points_outside_the_lattice(spark, odd, name):
    run, sql = CATALOG[name]
    assert compare(spark, run, sql, odd) is None


@pytest.mark.parametrize("name", ["uniform_points", "tree_uniform", "empty_cells_uniform", "wave_bound_check_uniform", "grid_mesh_triangles"])
def test_the_plan_reads_a_table(spark, name):
    assert "FileScan parquet" in plan(CATALOG[name][0](spark, TINY))


def test_schedule_and_theory_are_of_the_tables(spark, tmp_path):
    from cellstream.sources.workloads import LATTICES

    assert {r["n"] for r in CATALOG["theory_table"][0](spark, TINY).collect()} >= {LATTICES[k].points(spark, TINY).count() for k in ("events", "lineitem")}
    spark.read.parquet(f"{TINY}/lineitem.parquet").where("l_quantity < 8").write.parquet(str(tmp_path / "lineitem.parquet"))
    rows = CATALOG["schedule_table"][0](spark, str(tmp_path)).collect()
    assert sum(r["axis"] == 2 for r in rows) == 3


@pytest.fixture(scope="module")
def repeated(tmp_path_factory):
    """Events six times over, each time with later keys and 30 days later: past the lattice's 48 days, as larger tables are."""
    import duckdb

    place = tmp_path_factory.mktemp("repeated")
    duckdb.connect().execute(f"COPY (SELECT * REPLACE (event_id + 1000 * r AS event_id, ts + to_days(CAST(30 * r AS INT)) AS ts) FROM '{TINY}/events.parquet', range(6) x(r)) TO '{place}/events.parquet'")
    for t in "region nation customer supplier part orders lineitem documents embeddings pages benchmark labels conversations".split():
        (place / f"{t}.parquet").symlink_to(f"{TINY}/{t}.parquet")
    return str(place)


def test_level_24_of_a_repeated_table(spark, repeated):
    run, sql = CATALOG["progressive_level_24"]
    assert compare(spark, run, sql, repeated) is None


def test_level_36_of_a_repeated_table(spark, repeated):
    run, sql = CATALOG["progressive_level_36"]
    assert compare(spark, run, sql, repeated) is None


@pytest.mark.parametrize("name", ["progressive_level_24", "progressive_level_36", "decode_3d_events"])
def test_points_far_outside_the_lattice(spark, tmp_path, name):
    """A few values and times so far out that bits for all cells between would not fit a key."""
    import duckdb

    value = "CASE event_id % 100 WHEN 7 THEN 1e12 + event_id WHEN 8 THEN -3e13 WHEN 9 THEN NULL ELSE value END AS value"
    ts = "CASE event_id % 100 WHEN 11 THEN TIMESTAMP '2290-01-01' WHEN 12 THEN TIMESTAMP '1700-01-01' WHEN 13 THEN NULL ELSE ts END AS ts"
    duckdb.connect().execute(f"COPY (SELECT * REPLACE ({value}, {ts}) FROM '{TINY}/events.parquet') TO '{tmp_path}/events.parquet'")
    for t in "region nation customer supplier part orders lineitem documents embeddings pages benchmark labels conversations".split():
        (tmp_path / f"{t}.parquet").symlink_to(f"{TINY}/{t}.parquet")
    run, sql = CATALOG[name]
    assert compare(spark, run, sql, str(tmp_path)) is None


def test_the_mesh_is_that_of_the_table_read_once(spark, tmp_path):
    run, sql = CATALOG["grid_mesh_triangles"]
    spark.read.parquet(f"{TINY}/lineitem.parquet").where("l_extendedprice < 50000 or l_shipdate < '1998-01-01'").write.parquet(str(tmp_path / "some"))
    (tmp_path / "lineitem.parquet").write_bytes(next((tmp_path / "some").glob("part-*.parquet")).read_bytes())
    for t in "region nation customer supplier part orders events documents embeddings pages benchmark labels conversations".split():
        (tmp_path / f"{t}.parquet").symlink_to(f"{TINY}/{t}.parquet")
    mesh = run(spark, str(tmp_path))
    assert 0 < mesh.count() < run(spark, TINY).count() < 7200
    # The grid is what the corners read.
    assert "l_shipdate" not in plan(mesh)
    assert compare(spark, run, sql, str(tmp_path)) is None


@pytest.mark.parametrize("rows", ["true", "l_quantity < 8", "false"])
def test_an_axis_below_zero_has_no_halvings(spark, tmp_path, rows):
    """Ship dates before the axis begins, its largest coordinate below zero; fewer bits on another axis; no rows."""
    import duckdb

    duckdb.connect().execute(f"COPY (SELECT * REPLACE (l_shipdate - to_days(5000) AS l_shipdate) FROM '{TINY}/lineitem.parquet' WHERE {rows}) TO '{tmp_path}/lineitem.parquet'")
    for t in "region nation customer supplier part orders events documents embeddings pages benchmark labels conversations".split():
        (tmp_path / f"{t}.parquet").symlink_to(f"{TINY}/{t}.parquet")
    run, sql = CATALOG["schedule_table"]
    assert all(r["axis"] != 0 for r in run(spark, str(tmp_path)).collect())
    assert compare(spark, run, sql, str(tmp_path)) is None


def test_closed_forms_of_few_and_no_points(spark, tmp_path):
    """One order, no part and events without a time: numbers of points are those of the tables, and forms of none those of the SQL."""
    import duckdb

    for t, rows in (("orders", "* FROM '{}' LIMIT 1"), ("part", "* FROM '{}' WHERE false"), ("events", "* REPLACE (CASE WHEN event_id % 3 = 0 THEN ts END AS ts) FROM '{}'"), ("lineitem", "* FROM '{}'")):
        duckdb.connect().execute(f"COPY (SELECT {rows.format(f'{TINY}/{t}.parquet')}) TO '{tmp_path}/{t}.parquet'")
    for t in "region nation customer supplier documents embeddings pages benchmark labels conversations".split():
        (tmp_path / f"{t}.parquet").symlink_to(f"{TINY}/{t}.parquet")
    run, sql = CATALOG["theory_table"]
    con = duckdb.connect()
    for t in ("orders", "part", "events", "lineitem"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{tmp_path}/{t}.parquet'")
    # As text, since not-a-number equals nothing.
    got, want = (sorted(repr(tuple(r)) for r in rows) for rows in (run(spark, str(tmp_path)).collect(), con.sql(sql).fetchall()))
    assert got == want and got[0].startswith("(0,")


@pytest.fixture(scope="module")
def odd_keys(tmp_path_factory):
    """Orders with keys below zero, keys near the largest long and none."""
    import duckdb

    place = tmp_path_factory.mktemp("keys")
    key = "CASE o_orderkey % 10 WHEN 1 THEN -o_orderkey WHEN 2 THEN 9223372036854775807 - o_orderkey WHEN 3 THEN NULL ELSE o_orderkey END AS o_orderkey"
    duckdb.connect().execute(f"COPY (SELECT * REPLACE ({key}) FROM '{TINY}/orders.parquet') TO '{place}/orders.parquet'")
    for t in "region nation customer supplier part lineitem events documents embeddings pages benchmark labels conversations".split():
        (place / f"{t}.parquet").symlink_to(f"{TINY}/{t}.parquet")
    return str(place)


def test_every_order_gives_a_point_of_the_square(spark, odd_keys):
    run, sql = CATALOG["uniform_points"]
    assert all(0 <= x < 1024 for r in run(spark, odd_keys).collect() for x in r)
    assert compare(spark, run, sql, odd_keys) is None
    # The draws of the given keys are those of the plain text.
    plain = "SELECT CAST((o_orderkey * 48271 + 11) % 65521 % 1024 AS BIGINT) AS a0, CAST((o_orderkey * 16807 + 7) % 65519 % 1024 AS BIGINT) AS a1 FROM orders"
    assert compare(spark, run, plain, TINY) is None


@pytest.mark.parametrize("name", ["tree_uniform", "empty_cells_uniform", "wave_bound_check_uniform"])
def test_the_uniform_tree_of_any_keys(spark, odd_keys, name):
    run, sql = CATALOG[name]
    assert compare(spark, run, sql, odd_keys) is None
    rows = run(spark, odd_keys).where("level = 0").collect()
    assert len(rows) == 1 and (name != "tree_uniform" or rows[0]["cnt"] == spark.read.parquet(f"{odd_keys}/orders.parquet").count())
