"""Unit tests: worked example, theory, coder, schedules, predictor, topology, properties."""

import datetime
import random
from itertools import combinations

import numpy as np
import pytest
from cellstream.functions import keys, theory
from cellstream.functions.lattice import AxisSpec, LatticeSpec, from_lattice, infer_lattice, to_lattice
from cellstream.functions.schedule import SplitSchedule
from cellstream.operators import arith, cell_order, codelen, predict, progressive, stream_codec, topology, tree
from cellstream.operators.stream_codec import Codestream
from compare import compare
from pyspark.sql import functions as F

F0 = [(0, 0), (0, 1), (1, 1), (2, 5), (3, 5), (3, 5), (6, 1), (7, 7), (7, 6)]
BREADTH = [6, 3, 1, 3, 0, 0, 0, 3, 3, 1, 0, 2, 1, 1, 0, 1, 0, 0, 0, 0, 1]


def frame(spark, points):
    d = len(points[0]) if points else 2
    return spark.createDataFrame(points, ", ".join(f"a{i} long" for i in range(d)))


@pytest.mark.parametrize("path", ["explode", "cascade", "sweep"])
def test_worked_example(spark, path):
    sch = SplitSchedule.round_robin((3, 3))
    nodes = tree.count_tree(frame(spark, F0), sch, path)
    symbols = tree.symbol_stream(nodes, 6).orderBy("ord").collect()
    assert [r["left_cnt"] for r in symbols] == BREADTH and [r["ord"] for r in symbols] == list(range(1, 22))
    row = codelen.summary(nodes, 6).first()
    assert row["ideal_bits"] == 35.639 and row["integer_bits"] == 39 and row["touches"] == 54


SETS = [(F0, (3, 3)), ([(0, 0)], (3, 3)), ([(5, 5)] * 7, (3, 3)), ([(0, 0), (7, 7)], (3, 3)), ([(x, y) for x in range(4) for y in range(4)], (2, 2)), ([(1, 0)], (1, 0)), ([], (3, 3))]


@pytest.mark.parametrize("model,points,bits", [*[(0, *x) for x in SETS], (1, *SETS[0]), ("choose", *SETS[0]), ("choose", *SETS[6])])
def test_codestream_round_trip(spark, tmp_path, model, points, bits):
    sch = SplitSchedule.round_robin(bits)
    stream = Codestream.encode(frame(spark, points), sch, model, tile_bits=min(2, sum(bits)))
    stream.write(str(tmp_path / "s"))
    back = tree.with_coordinates(Codestream.read(spark, str(tmp_path / "s")).cells(), sch).collect()
    assert sorted((r["c0"], r["c1"]) for r in back for _ in range(r["cnt"])) == sorted(points)


def test_wrong_split_order_decodes_differently(spark):
    stream = Codestream.encode(frame(spark, F0), SplitSchedule.round_robin((3, 3)), tile_bits=0)
    right = {tuple(r) for r in stream.cells().collect()}
    stream.header["axes"] = stream.header["axes"][::-1]
    wrong = SplitSchedule.explicit((3, 3), stream.header["axes"])
    assert {tuple(r) for r in tree.with_coordinates(stream.cells(), wrong).collect()} != {tuple(r) for r in tree.with_coordinates(stream.df.sparkSession.createDataFrame(list(right), "level int, prefix long, cnt long"), SplitSchedule.round_robin((3, 3))).collect()}


def test_data_source(spark, tmp_path):
    from cellstream.sources.datasource import register

    register(spark)
    sch = SplitSchedule.round_robin((3, 3))
    Codestream.encode(frame(spark, F0), sch, tile_bits=2).write(str(tmp_path / "s"))
    read = lambda **o: spark.read.format("cellstream").options(path=str(tmp_path / "s"), **o).load()
    for level in (1, 4, 6):
        for slices in (1, 3, 64):
            want = {tuple(r) for r in tree.cells_at(frame(spark, F0), sch, level).collect()}
            assert sorted(map(tuple, read(level=level, slices=slices).collect())) == sorted(want)
    got = tree.with_coordinates(read(box="0:2,1:5"), sch).collect()
    assert sorted((r["c0"], r["c1"]) for r in got if r["c0"] <= 2 and 1 <= r["c1"] <= 5 for _ in range(r["cnt"])) == [(0, 1), (1, 1), (2, 5)]


def test_stages_and_laws(spark, tmp_path):
    """Tiles far below the root stand in stages; a region is decoded alone; the header's law places the points."""
    rng = np.random.default_rng(5)
    points = [(int(x), int(y)) for x, y in rng.integers(0, 1 << 20, (300, 2))] + [(7, 7)] * 40
    sch = SplitSchedule.round_robin((20, 20))
    stream = Codestream.encode(frame(spark, points), sch, "choose", tile_bits=34, law="choose")
    stream.write(str(tmp_path / "s"))
    stream = Codestream.read(spark, str(tmp_path / "s"))
    assert stream_codec.cuts(34) == [0, 16, 32, 34] and stream.header["law"] in ("centre", "gaussian", "grid", "regular", "uniform")
    for level in (3, 16, 20, 33, 36, 40):
        assert {tuple(r) for r in stream.cells(level).collect()} == {tuple(r) for r in tree.cells_at(frame(spark, points), sch, level).collect()}
    box = stream_codec.Box([(0, 1 << 18), (5, 1 << 19)])
    got = tree.with_coordinates(stream.cells(boxes=[box]), sch).where(box.holds(["c0", "c1"]))
    assert sorted((r["c0"], r["c1"]) for r in got.collect() for _ in range(r["cnt"])) == sorted(p for p in points if p[0] <= 1 << 18 and 5 <= p[1] <= 1 << 19)
    made = stream.points(20)
    assert {tuple(r) for r in tree.cells_at(made, sch, 20).collect()} == {tuple(r) for r in stream.cells(20).collect()}
    codec = stream_codec.PointCodec(None, sch)
    assert codec.encode(frame(spark, points)).cells().agg(F.sum("cnt")).first()[0] == 340 and codec.cost(frame(spark, points)).first()["n"] == 340


def test_payloads_are_near_the_ideal(spark):
    """Payload bytes within 2 % of the ideal bits plus four bytes a tile, and the predicted cost is what the coder pays."""
    rng = np.random.default_rng(6)
    points = [tuple(map(int, p)) for p in np.clip(rng.normal(500, 90, (4000, 2)), 0, 1023)]
    sch = SplitSchedule.round_robin((10, 10))
    nodes = tree.count_tree(frame(spark, points), sch)
    for t in (0, 4):
        tiles = nodes.where(f"level = {t}").count() + (t > 0)
        for model, cost in ((0, "uniform_bits"), (1, "predicted_bits"), ("choose", None)):
            row = Codestream.encode(frame(spark, points), sch, model, tile_bits=t).coded().first()
            costs = stream_codec.wave_costs(nodes, sch, t).collect()
            ideal = sum(min(r["uniform_bits"], r["predicted_bits"]) if cost is None else r[cost] for r in costs)
            assert ideal <= 8 * row["payload_bytes"] <= 1.02 * ideal + 32 * tiles, (t, model)


def test_cascade_has_few_exchanges(spark):
    sch = SplitSchedule.round_robin((16, 16))
    plan = tree.count_tree(frame(spark, F0), sch, "cascade")._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") <= 8


def test_theory_reproduces_the_published_columns():
    for n, q, factor, size in ((120_998, 43, 1.51, 650_365), (908_907, 43, 1.68, 4_885_376), (3_721, 26, 1.57, 12_094)):
        assert round(theory.factor(n, q), 2) == factor and theory.source_bytes(n, q) == size
    assert theory.total_bits(1024, 20) == pytest.approx(1024 * (20 - 10 + 2.402))


def test_predictor_example(spark):
    mu = spark.range(1).select(predict.predicted_left(F.lit(11), F.lit(3), F.lit(9)).alias("m")).first()["m"]
    assert round(mu, 3) == 7.071 and round(mu) == 7 and 9 - round(mu) == 2


def test_range_coder():
    rng = random.Random(3)
    symbols = [(p, rng.randint(0, p)) for p in [0, 1, 2, 9, 2**31, 2**32 - 1, 2**32, 2**40 + 5] * 300]
    enc = arith.Encoder()
    for p, x in symbols:
        enc.put_uniform(x, p + 1)
    data = enc.finish()
    dec = arith.Decoder(data)
    assert [dec.get_uniform(p + 1) for p, _ in symbols] == [x for _, x in symbols]
    ideal = sum(np.log2(p + 1) for p, _ in symbols)
    assert len(data) * 8 <= ideal * 1.001 + 80


def test_cut_payload_is_an_error():
    enc = arith.Encoder()
    rng = random.Random(1)
    for _ in range(2000):
        enc.put_uniform(rng.randint(0, 1000), 1001)
    dec = arith.Decoder(enc.finish()[:200])
    with pytest.raises(ValueError):
        for _ in range(2000):
            dec.get_uniform(1001)


def test_bell_table_is_whole_and_positive():
    for p, a, b in ((2, 0, 1), (9, 11, 3), (400, 7, 900), (4096, 1, 1), (70_000, 12, 9)):
        table = arith.bell_table(p, a, b)
        assert len(table) == p + 1 and min(table) > 0
        root, mean = next(r for r in range(1 << 20) if r * r >= 64 * p), p * (((a + 16) << 20) // (a + b + 32)) >> 16
        top = max(table)
        assert max(abs(v - mean / 16) for v, w in enumerate(table) if w == top) <= max(1.0, root / 128)
    for p in (1 << 20, (1 << 42) - 1):
        edges, weights = arith.bell_bins(np.array([p]), np.array([1 << 41]), np.array([3]))
        assert edges[0, -1] == p + 1 and (np.diff(edges[0]) >= 0).all() and 0 < weights.sum() < 1 << 32 and ((weights[0] > 0) == (np.diff(edges[0]) > 0)).all()


def test_mixed_radix_digits():
    rng = np.random.default_rng(0)
    sizes = np.where(rng.random(5000) < 0.9, rng.integers(2, 20, 5000), rng.integers(2, 1 << 40, 5000))
    values = (rng.random(5000) * sizes).astype(np.int64)
    coder = arith.Encoder()
    arith.put_digits(coder, values, sizes)
    data = coder.finish()
    assert len(arith.radix_groups(sizes)) < 2500 and 8 * len(data) <= np.log2(sizes).sum() + 64
    for tail in (b"", b"\xff" * 40):
        assert (arith.get_digits(arith.Decoder(data + tail), sizes) == values).all()


def test_schedules():
    for bits in ((10, 10, 6), (3, 0, 5), (1,), (8,) * 16):
        for make in (SplitSchedule.round_robin, SplitSchedule.axis_major, SplitSchedule.align_low, SplitSchedule.longest_side):
            s = make(bits)
            assert s.q == sum(bits) and s.used(s.q) == bits
    s = SplitSchedule.round_robin((10, 10, 6))
    assert [s.level_of_precision(r) for r in (6, 7, 10)] == [18, 20, 26]


def test_box_ranges_cover(spark):
    sch = SplitSchedule.round_robin((3, 3))
    box = [(1, 5), (2, 6)]
    ranges = keys.box_to_ranges(sch, box, 1000)
    cells = frame(spark, [(x, y) for x in range(8) for y in range(8)]).select("a0", "a1", keys.cell_key(sch).alias("k")).collect()
    for r in cells:
        assert any(a <= r["k"] <= b for a, b in ranges) == (1 <= r["a0"] <= 5 and 2 <= r["a1"] <= 6)
    rough = keys.box_to_ranges(sch, box, 3)
    assert len(rough) <= 3 and all(any(a <= r["k"] <= b for a, b in rough) for r in cells if 1 <= r["a0"] <= 5 and 2 <= r["a1"] <= 6)


def test_lattice_round_trip(spark):
    df = spark.sql("SELECT * FROM VALUES (1, -999.85D, timestamp_ntz'2024-01-05 10:00:00', 'x', true, 1.5D), (7, 12.30D, timestamp_ntz'2024-03-01 00:00:01', 'y', false, -2.25D) AS t(i, m, t, s, b, f)")
    axes = [AxisSpec("i", "i"), AxisSpec("m", "m", "decimal", step=2), AxisSpec("t", "t", "tick", step=1_000_000), AxisSpec("s", "s", "dict", values=("x", "y")), AxisSpec("b", "b", "bool"), AxisSpec("f", "f", "ieee")]
    spec = infer_lattice(df, axes)
    assert LatticeSpec.from_json(spec.to_json()) == spec
    lattice = to_lattice(df, spec)
    assert all(0 <= r[k] < 1 << spec.bits[k] for r in lattice.collect() for k in range(spec.d))
    back = {tuple(r) for r in from_lattice(lattice, spec).select("i", "m", "s", "b", "f").collect()}
    assert back == {(1, -999.85, "x", True, 1.5), (7, 12.3, "y", False, -2.25)}


def test_lattice_nulls(spark):
    df = spark.createDataFrame([(1,), (None,)], "i long")
    spec = lambda how: LatticeSpec((AxisSpec("i", "i", bits=3, on_null=how),))
    assert to_lattice(df, spec("drop")).count() == 1 and to_lattice(df, spec("flag")).columns == ["a0", "a1"]
    with pytest.raises(Exception, match="null in axis"):
        to_lattice(df, spec("error")).collect()


def test_values_outside_an_axis_are_an_error(spark):
    df = spark.createDataFrame([("x", 5), ("q", -1)], "s string, i long")
    for axis in (AxisSpec("s", "s", "dict", bits=1, values=("x", "y")), AxisSpec("i", "i", bits=3, lo=0, hi=7)):
        with pytest.raises(Exception, match="outside axis"):
            to_lattice(df, LatticeSpec((axis,))).collect()


@pytest.mark.parametrize("seed", range(3))
def test_wave_bound_holds_for_any_multiset(spark, seed):
    rng = np.random.default_rng(seed)
    points = [tuple(map(int, p)) for p in np.clip(rng.normal(30, 4 + 8 * seed, (200, 2)), 0, 63)]
    sch = SplitSchedule.round_robin((6, 6))
    nodes = tree.count_tree(frame(spark, points), sch)
    assert all(r["holds"] for r in codelen.wave_bounds(nodes).collect())
    shuffled = tree.count_tree(frame(spark, points[::-1]).repartition(3), sch, "sweep")
    assert {tuple(r) for r in nodes.collect()} == {tuple(r) for r in shuffled.collect()}


def test_delaunay_circles_and_euler():
    rng = random.Random(4)
    pts = list({(rng.randint(0, 60), rng.randint(0, 60)) for _ in range(60)})
    triangles, _ = topology.delaunay(pts)
    for t in triangles:
        assert not any(topology.in_circle(*(pts[k] for k in t), p) for p in pts)
    edges = {frozenset(e) for t in triangles for e in combinations(t, 2)}
    assert len(pts) - len(edges) + len(triangles) == 1


def test_tiled_delaunay_is_the_global_one(spark):
    rng = random.Random(9)
    pts = list({(rng.randint(0, 90), rng.randint(0, 70)) for _ in range(220)}) + [(x, y) for x in range(100, 116, 4) for y in range(0, 40, 4)]
    corners = lambda r: tuple(v for p in sorted(zip(r[::2], r[1::2], strict=True)) for v in p)
    want = sorted(tuple(v for k in sorted(t, key=lambda k: pts[k]) for v in pts[k]) for t in topology.delaunay(pts)[0])
    for side, halo in ((16, 4), (50, 10), (16, 40)):
        assert sorted(corners(tuple(r)) for r in topology.delaunay_tiles(frame(spark, pts), side, halo=halo).collect()) == want
    # Any order of insertion gives the same triangles, points on one circle included.
    again = pts[:]
    rng.shuffle(again)
    steps = [topology.delaunay(order)[1] for order in (sorted(pts), again)]
    assert sorted(tuple(v for k in sorted(t, key=lambda k: again[k]) for v in again[k]) for t in topology.delaunay(again)[0]) == want and steps[0] < steps[1]
    assert topology.delaunay_tiles(frame(spark, []), 8).count() == 0


def test_ordered_lags_cross_partitions(spark):
    from cellstream.operators import baselines

    rows = [(int(k), int(k) * 7 % 11) for k in np.random.default_rng(1).permutation(100)]
    got = baselines.ordered_lags(spark.createDataFrame(rows, "k long, v long").repartition(7), ["k"], ["v"], 3).collect()
    value = dict(rows)
    for r in got:
        assert [r[f"lag_{j}_v"] for j in (1, 2, 3)] == [value.get(r["k"] - j) for j in (1, 2, 3)]


def test_huffman_lengths_are_optimal():
    from cellstream.operators import baselines

    assert baselines.huffman_lengths([]) == [] and baselines.huffman_lengths([5]) == [0] and sorted(baselines.huffman_lengths([8, 4, 2, 1, 1])) == [1, 2, 3, 4, 4]
    rng = random.Random(2)
    counts = [rng.randint(1, 1000) for _ in range(400)]
    lengths = baselines.huffman_lengths(counts)
    total = sum(counts)
    entropy = sum(c * np.log2(total / c) for c in counts)
    assert sum(2.0**-n for n in lengths) == 1 and entropy <= sum(a * b for a, b in zip(counts, lengths, strict=True)) <= entropy + total


def test_greedy_order_against_brute_force(spark):
    from cellstream.plans.catalog import greedy_axes

    rng = np.random.default_rng(8)
    points, bits = [(int(a), int(b)) for a, b in zip(rng.integers(0, 8, 60), rng.integers(0, 2, 60), strict=True)], (3, 3)
    left, want = list(bits), []
    while any(left):
        costs = []
        for i in (0, 1):
            if left[i]:
                cells = {}
                for p in points:
                    c = tuple(v >> (b - (k == i)) for k, (v, b) in enumerate(zip(p, left, strict=True)))
                    cells[c] = cells.get(c, 0) + 1
                costs.append((round(sum(np.log2(n + 1) for n in cells.values()), 6), i))
        want.append(min(costs)[1])
        left[want[-1]] -= 1
    assert greedy_axes(frame(spark, points), bits) == want
    assert sorted(greedy_axes(frame(spark, points), bits, most=20)) == [0, 0, 0, 1, 1, 1]


def test_neighbours_of_one_axis_without_a_window(spark):
    sch = SplitSchedule.round_robin((5,))
    nodes = tree.count_tree(frame(spark, [(v * v % 29,) for v in range(40)]), sch)
    got = predict.neighbour_counts(nodes, sch, order=2)
    assert "Window" not in got._jdf.queryExecution().executedPlan().toString()
    cells = {(r["level"], r["prefix"]): r["cnt"] for r in nodes.collect()}
    for r in got.collect():
        at = lambda k, r=r: cells.get((r["level"], r["prefix"] + k), 0)
        assert (r["nb_left"], r["nb_right"]) == (at(-1) + at(-2) / 2, at(1) + at(2) / 2)


def test_wide_codestream(spark):
    sch = SplitSchedule.round_robin((40, 40, 50))
    rng = np.random.default_rng(4)
    points = [tuple(int(v) for v in rng.integers(0, 1 << 39, 3)) for _ in range(30)] + [(1, 2, 3)] * 5
    want = {(tuple(r["key"]), r["cnt"]) for r in frame(spark, points).groupBy(keys.wide_key(sch).alias("key")).agg(F.count(F.lit(1)).alias("cnt")).collect()}
    back = stream_codec.decode_wide(stream_codec.encode_wide(frame(spark, points), sch), len(points), sch)
    assert {(tuple(r["key"]), r["cnt"]) for r in back.collect()} == want


def test_sql_codestreams(spark):
    from cellstream.functions.sql import register

    sch = SplitSchedule.round_robin((3, 3))
    register(spark, sch)
    frame(spark, F0).withColumn("key", keys.cell_key(sch)).createOrReplaceTempView("f0")
    spark.sql("SELECT n, payload FROM (SELECT count(*) AS n FROM f0) CROSS JOIN (SELECT count_tree_agg(key) AS payload FROM f0)").createOrReplaceTempView("coded")
    got = spark.sql("SELECT * FROM tile_decode(TABLE(coded))").collect()
    assert {(r["prefix"], r["cnt"]) for r in got} == {(r["key"], r["n"]) for r in spark.sql("SELECT key, count(*) AS n FROM f0 GROUP BY key").collect()}


def test_laws_stay_in_their_cells(spark):
    sch = SplitSchedule.round_robin((3, 3))
    cells = tree.cells_at(frame(spark, F0), sch, 3)
    for law in ("uniform", "regular", "gaussian", "grid", "linear"):
        made = progressive.synthesise(cells, sch, law, grid=1)
        again = tree.cells_at(made, sch, 3)
        assert {tuple(r) for r in cells.collect()} == {tuple(r) for r in again.collect()}


def test_linear_law_leans_to_the_dense_side(spark):
    sch = SplitSchedule.round_robin((10,))
    cells = spark.createDataFrame([(2, 0, 1), (2, 1, 400), (2, 2, 900)], "level int, prefix long, cnt long")
    near = {r["prefix"]: (r["lo0"], r["hi0"]) for r in progressive.beside(cells, sch).collect()}
    assert near == {0: (0, 400), 1: (1, 900), 2: (400, 0)}
    mean = {law: progressive.synthesise(cells, sch, law).where("a0 >= 256 AND a0 < 512").agg(F.avg("a0")).first()[0] for law in ("uniform", "linear")}
    assert abs(mean["uniform"] - 384) < 12 and abs(mean["linear"] - (256 + 256 * 2 / 3)) < 12


def test_text_and_files(spark, tmp_path):
    from cellstream.sources.textio import read_points, read_vertices, write_points

    pts = frame(spark, F0)
    for form in ("csv", "json", "orc"):
        write_points(pts, str(tmp_path / form), form)
        assert read_points(spark, str(tmp_path / form), form, "a0 long, a1 long").count() == 9
    write_points(pts, str(tmp_path / "text"), "text")
    assert sorted(map(tuple, read_vertices(spark, str(tmp_path / "text"), 2).collect())) == sorted(F0)


def test_sql_functions(spark):
    from cellstream.functions.sql import register

    register(spark)
    assert round(spark.sql("SELECT gaussian_bits(9L, 6L, 7.0D, 1.5D) AS b").first()["b"], 2) > 0
    assert spark.sql("SELECT huffman_bits(c) AS b FROM VALUES (1L), (1L), (2L) AS t(c)").first()["b"] == 6
    assert spark.sql("SELECT * FROM decode_cells(TABLE(SELECT 0 AS level, 0L AS prefix, 9L AS cnt, 6L AS left_cnt))").count() == 2
    assert spark.sql("SELECT count_bits(3L) AS b").first()["b"] == 2.0


def test_stream_equals_batch_and_late_rows_drop(spark, tmp_path):
    from cellstream.streaming import trees

    rows = [("2024-01-01 01:00:00", 1), ("2024-01-01 02:00:00", 5), ("2024-01-02 03:00:00", 2), ("2024-01-04 00:00:00", 3)]
    sch, schema = SplitSchedule.round_robin((3,)), "ts timestamp_ntz, a0 long"
    for k, (t, v) in enumerate([*rows, ("2024-01-01 03:00:00", 7), ("2024-01-09 00:00:00", 0)]):
        spark.sql(f"SELECT timestamp_ntz'{t}' AS ts, {v}L AS a0").coalesce(1).write.mode("append").parquet(str(tmp_path / "in" / f"{k}"))
    import shutil
    import time
    from pathlib import Path

    flat = tmp_path / "flat"
    flat.mkdir()
    for k in range(6):
        for f in Path(tmp_path / "in" / f"{k}").glob("*.parquet"):
            shutil.copy(f, flat / f"{k}.parquet")
        time.sleep(0.05)
    points = trees.stream_points(spark, str(flat), schema)
    streamed = trees.windowed_tree(points, sch, trees.window_of("tumbling"), keys.cell_key(sch), 3)
    got = trees.run_to_memory(streamed, "windowed", str(tmp_path / "ck"))
    batch = trees.with_time(spark.createDataFrame([], schema).unionByName(spark.sql(" UNION ALL ".join(f"SELECT timestamp_ntz'{t}' AS ts, {v}L AS a0" for t, v in rows))))
    want = trees.windowed_tree(batch, sch, trees.window_of("tumbling"), keys.cell_key(sch), 3)
    assert {tuple(r) for r in got.collect()} == {tuple(r) for r in want.collect()}


def _feed(spark, folder, batches, schema):
    """One file a batch, in this order."""
    import os
    import shutil
    import time

    folder.mkdir(exist_ok=True)
    for k, rows in enumerate(batches):
        number = len(list(folder.glob("*.parquet")))
        spark.createDataFrame(rows, schema).coalesce(1).write.parquet(str(folder.parent / f"{folder.name}-{number}"))
        part = next((folder.parent / f"{folder.name}-{number}").glob("*.parquet"))
        shutil.copy(part, folder / f"{number}.parquet")
        os.utime(folder / f"{number}.parquet", (time.time() + k, time.time() + k))


def _at(text):
    return datetime.datetime.fromisoformat(text)


def test_closed_windows_are_coded_and_survive_a_restart(spark, tmp_path):
    from cellstream.streaming import trees

    sch, schema = SplitSchedule.round_robin((3, 3)), "ts timestamp_ntz, a0 long, a1 long"
    first = [(_at(f"2024-01-01 0{k}:00:00"), *p) for k, p in enumerate(F0)]
    second = [(_at("2024-01-02 05:00:00"), 1, 2), (_at("2024-01-02 05:00:00"), 1, 2)]
    src, out, ck = tmp_path / "src", str(tmp_path / "out"), str(tmp_path / "ck")
    run = lambda: trees.encode_closed_windows(trees.stream_points(spark, str(src), schema), sch, out, ck, tile_bits=1)

    def coded(day):
        start = int(datetime.datetime(2024, 1, day, tzinfo=datetime.UTC).timestamp())
        cells = tree.with_coordinates(Codestream.read(spark, f"{out}/start={start}").cells(), sch)
        return sorted((r["c0"], r["c1"]) for r in cells.collect() for _ in range(r["cnt"]))

    _feed(spark, src, [first, second], schema)
    run()
    assert coded(1) == sorted(F0) and len(list((tmp_path / "out").iterdir())) == 1
    _feed(spark, src, [[(_at("2024-01-05 00:00:00"), 0, 0)]], schema)
    run()
    assert coded(2) == [(1, 2), (1, 2)] and len(list((tmp_path / "out").iterdir())) == 2


def test_stream_joins_and_deduplication(spark, tmp_path):
    from cellstream.streaming import trees

    sch, schema = SplitSchedule.round_robin((3, 3)), "ts timestamp_ntz, a0 long, a1 long"
    _feed(spark, tmp_path / "p", [[(_at("2024-01-01 00:00:00"), *p) for p in F0]], schema)
    points = trees.stream_points(spark, str(tmp_path / "p"), schema)
    got = trees.run_to_memory(trees.distinct_points(points, ["a0", "a1"]), "distinct_points", str(tmp_path / "c1"))
    assert sorted((r["a0"], r["a1"]) for r in got.collect()) == sorted(set(F0))
    frontier = spark.createDataFrame([(0,), (3,), (3,)], "prefix long")
    got = trees.run_to_memory(trees.in_frontier(points, sch, frontier, 2), "frontier_points", str(tmp_path / "c2"))
    assert sorted((r["a0"], r["a1"]) for r in got.collect()) == sorted(p for p in F0 if (p[0] >> 2) == (p[1] >> 2))

    _feed(spark, tmp_path / "a", [[(_at(f"2024-01-01 00:0{w}:00"), t, w) for w in range(4) for t in (1, 2)]], "ts timestamp_ntz, tile long, wave int")
    _feed(spark, tmp_path / "r", [[(_at("2024-01-01 00:01:30"), 1, 2), (_at("2024-01-01 00:03:00"), 2, 9)]], "ts timestamp_ntz, tile long, to_wave int")
    arrivals = trees.stream_points(spark, str(tmp_path / "a"), "ts timestamp_ntz, tile long, wave int").withColumnRenamed("ts", "at")
    requests = trees.stream_points(spark, str(tmp_path / "r"), "ts timestamp_ntz, tile long, to_wave int").withColumnRenamed("ts", "asked")
    got = trees.run_to_memory(trees.requested_waves(arrivals, requests), "requested", str(tmp_path / "c3"))
    assert sorted((r["tile"], r["wave"]) for r in got.collect()) == [(1, 1), (2, 2), (2, 3)]


QUERIES = ["law_choice", "context_policies", "scope_ablation", "exp_progressive", "wave_symbol_arrays", "lattice_documents", "rate_curve_events", "symbols_breadth", "anytime_frontier", "stream_roundtrip_predicted", "neighbours_moore2d", "roi_stream_events", "session_trees", "baseline_crease", "sql_cte_tree"]


@pytest.mark.parametrize("name", QUERIES)
def test_queries_against_sql(spark, name):
    from cellstream.plans.catalog import CATALOG

    run, sql = CATALOG[name]
    assert compare(spark, run, sql, "/root/testdata/sf0.001") is None


def _by_recursion(points, left, axis, last, again, level, out):
    """Nodes of the cell-by-cell split order, one cell at a time."""
    if not any(left) or not points:
        return
    d = len(left)
    axis = last if again and left[last] else next(a % d for a in range(last + 1, last + 1 + d) if left[a % d])
    rest = tuple(b - (i == axis) for i, b in enumerate(left))
    halves = [[p for p in points if p[axis] >> rest[axis] & 1 == h] for h in (0, 1)]
    out.append((level, len(points), len(halves[0])))
    for h in halves:
        _by_recursion(h, rest, axis, axis, not halves[0] or not halves[1], level + 1, out)


@pytest.mark.parametrize("tile_points", [1, 7, 1000])
def test_cell_order_against_recursion(spark, tile_points):
    rng = np.random.default_rng(3)
    bits, sch = (4, 3, 2), SplitSchedule.round_robin((4, 3, 2))
    points = [tuple(int(rng.integers(0, 1 << b)) for b in bits) for _ in range(30)] * 2 + [(3, 1, 2)] * 9
    df = frame(spark, points)
    top = cell_order.tile_level(df, sch, tile_points)
    want = []
    for tile in {tuple(p[i] >> b - u for i, (b, u) in enumerate(zip(bits, sch.used(top), strict=True))) for p in points}:
        own = [p for p in points if all(p[i] >> bits[i] - sch.used(top)[i] == tile[i] for i in range(3))]
        _by_recursion(own, tuple(b - u for b, u in zip(bits, sch.used(top), strict=True)), 0, sch.steps[top - 1][0] if top else -1, False, top, want)
    got = {r["level"]: r for r in cell_order.cell_order_cost(df, sch, tile_points).collect()}
    for level in range(top, sch.q):
        mine = [(c, low) for lv, c, low in want if lv == level]
        assert (got[level]["nodes"], got[level]["points"], got[level]["empty"]) == (len(mine), len(points), sum(low in (0, c) for c, low in mine))
        assert abs(got[level]["bits"] - sum(np.log2(c + 1) for c, _ in mine)) < 1e-2
    assert set(got) == set(range(sch.q))
    assert cell_order.cell_order_cost(df.limit(0), sch, tile_points).count() == 0


def test_law_errors_are_the_expected_distances(spark):
    rng = np.random.default_rng(4)
    points = [(int(rng.integers(0, 64)), int(rng.integers(0, 64))) for _ in range(50)]
    sch, level = SplitSchedule.round_robin((6, 6)), 4
    got = {r["law"]: r for r in progressive.law_errors(frame(spark, points), sch, level).collect()}
    places = np.arange(16)
    centre = sum((p[i] % 16 - 7.5) ** 2 for p in points for i in (0, 1)) / 50
    uniform = sum(((p[i] % 16 - places) ** 2).mean() for p in points for i in (0, 1)) / 50
    assert abs(got["centre"]["rmse"] - centre**0.5) < 1e-3 and abs(got["uniform"]["rmse"] - uniform**0.5) < 1e-3
    assert [n for n, r in got.items() if r["chosen"]] == [min(got, key=lambda n: (got[n]["rmse"], n))]
    assert progressive.choose_law(frame(spark, points).limit(0), sch, level) is None
