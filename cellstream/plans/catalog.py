"""Every registered query with its DuckDB twin (None where SQL cannot express it)."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import keys, theory
from ..functions.outside import framed, inner, outer_cell
from ..functions.schedule import SplitSchedule
from ..operators import baselines, cell_order, codelen, predict, progressive, stream_codec, topology, tree
from ..operators.stream_codec import Codestream
from ..sources.shared import written
from ..sources.workloads import LATTICES, OBJECTS, TERRAIN, Lattice
from ..streaming import trees
from . import oracles as sql

Query = Callable[[SparkSession, str], DataFrame]
CATALOG: dict[str, tuple[Query, str | None]] = {}


def add(name: str, run: Query, duck: str | None) -> None:
    if name in CATALOG:
        raise ValueError(f"query {name} is registered twice")
    CATALOG[name] = (run, duck)


def nodes_of(lat: Lattice, path: str = "explode", sch: SplitSchedule | None = None):
    return lambda spark, sf: tree.count_tree(lat.points(spark, sf), sch or lat.schedule(), path)


def _key_sql(lat: Lattice, sch: SplitSchedule | None = None) -> str:
    sch = sch or lat.schedule()
    return " + ".join(f"(((a{a} >> {bit}) & 1) << {sch.q - 1 - k})" for k, (a, bit) in enumerate(sch.steps))


# Lattices and keys -------------------------------------------------------------------------------------------------------
for _name in ("events", "lineitem", "terrain", "smooth", "plane_dense", "documents", "pages", "conversations", "object_orders", "object_customer", "object_part", "object_click", "embedding4"):
    _lat = LATTICES[_name]
    _axes = ", ".join(_lat.names)
    add(f"lattice_{_name}", lambda s, d, lat=_lat: lat.points(s, d).groupBy(*lat.names).agg(F.count(F.lit(1)).alias("m")), f"WITH {sql.points(_lat)} SELECT {_axes}, count(*) AS m FROM pts GROUP BY {_axes}")

_EV, _LI, _TS, _TG = (LATTICES[k] for k in ("events", "lineitem", "smooth", "terrain"))
add("lattice_bounds", lambda s, d: _EV.points(s, d).agg(*[f(c).alias(f"{n}_{c}") for c in _EV.names for n, f in (("lo", F.min), ("hi", F.max))]), f"WITH {sql.points(_EV)} SELECT " + ", ".join(f"min({c}) AS lo_{c}, max({c}) AS hi_{c}" for c in _EV.names) + " FROM pts")
add("uniform_points", lambda s, d: LATTICES["uniform_keys"].points(s, d), f"WITH {sql.points(LATTICES['uniform_keys'])} SELECT * FROM pts")
def _measured_schedule(s, d):
    """The schedule that a table needs: as many halvings an axis as its largest coordinate has bits."""
    top = _LI.points(s, d).agg(*[F.greatest(F.max(c), F.lit(0)) for c in _LI.names]).first()
    return s.createDataFrame(SplitSchedule.round_robin(tuple(int(x).bit_length() for x in top)).rows(), "level int, axis int, bit int")


# The twin orders the halvings of each axis by round and axis, from the bit widths alone.
_WIDTHS = "(" + " UNION ALL ".join(f"SELECT {i} AS axis, CASE WHEN max({c}) > 0 THEN length(bin(max({c}))) ELSE 0 END AS bits FROM pts" for i, c in enumerate(_LI.names)) + ")"
add("schedule_table", _measured_schedule, f"WITH {sql.points(_LI)} SELECT CAST(row_number() OVER (ORDER BY turn, axis) - 1 AS INT) AS level, CAST(axis AS INT) AS axis, CAST(bits - 1 - turn AS INT) AS bit FROM (SELECT axis, bits, unnest(range(bits)) AS turn FROM {_WIDTHS} w) x")
add("cell_keys", lambda s, d: _EV.points(s, d).select(*_EV.names, keys.cell_key(_EV.schedule()).alias("key")), f"WITH {sql.points(_EV)} SELECT a0, a1, a2, {_key_sql(_EV)} AS key FROM pts")
add("fn_bitstring", lambda s, d: _EV.points(s, d).select(*_EV.names, F.lpad(F.bin(keys.cell_key(_EV.schedule())), 43, "0").alias("bits")), f"WITH {sql.points(_EV)} SELECT a0, a1, a2, lpad(bin({_key_sql(_EV)}), 43, '0') AS bits FROM pts")
for _k in (2, 4):
    add(f"key_axis_d{_k}", lambda s, d, lat=LATTICES[f"embedding{_k}"]: lat.points(s, d).withColumn("key", keys.cell_key(lat.schedule())).select(*[keys.key_axis(lat.schedule(), i, F.col("key")).alias(n) for i, n in enumerate(lat.names)]), f"WITH {sql.points(LATTICES[f'embedding{_k}'])} SELECT * FROM pts")

# Count trees ----------------------------------------------------------------------------------------------------------------
for _name, _l in (("tree_1d_orders", "line_days"), ("tree_1d_cents", "line_cents"), ("tree_2d_orders", "plane"), ("tree_2d_dense", "plane_dense"), ("tree_3d_events", "events"), ("tree_terrain", "terrain"), ("tree_smooth", "smooth"), ("tree_documents", "documents"), ("tree_uniform", "uniform_keys")):
    _lat = LATTICES[_l]
    add(_name, lambda s, d, lat=_lat: tree.with_coordinates(nodes_of(lat)(s, d), lat.schedule()), f"{sql.tree(_lat)} SELECT level, {sql.axes_of(_lat)}, cnt, left_cnt FROM node")
for _path in ("cascade", "sweep"):
    add(f"tree_{_path}_events", lambda s, d, p=_path: tree.with_coordinates(nodes_of(_EV, p)(s, d), _EV.schedule()), CATALOG["tree_3d_events"][1])
_PER = "count(*) AS nodes, CAST(sum(cnt) AS BIGINT) AS points, CAST(sum(left_cnt) AS BIGINT) AS lefts"
for _name, _l, _path in (("tree_4d_lineitem", "lineitem", "explode"), ("tree_4d_lineitem_sweep", "lineitem", "sweep"), ("tree_7d_attributes", "attributes", "sweep")):
    add(_name, lambda s, d, lat=LATTICES[_l], p=_path: nodes_of(lat, p)(s, d).groupBy("level").agg(F.count(F.lit(1)).alias("nodes"), F.sum("cnt").alias("points"), F.sum("left_cnt").alias("lefts")), f"{sql.tree(LATTICES[_l])} SELECT level, {_PER} FROM node GROUP BY level")


def _wide(d: int) -> Lattice:
    base = LATTICES["embedding2"]
    return Lattice(base.tables, tuple((base.axes[0][0].replace(":0}", f":{k}}}"), 8) for k in range(d)), base.source)


for _d in (8, 16, 64):
    add(f"tree_wide_{8 * _d}_bits", lambda s, d, lat=_wide(_d): tree.wide_tree(lat.points(s, d), lat.schedule()).groupBy("level").agg(F.count(F.lit(1)).alias("nodes"), F.sum("cnt").alias("points"), F.sum("left_cnt").alias("lefts")), f"{sql.tree(_wide(_d))} SELECT level, {_PER} FROM node GROUP BY level" if _d < 64 else None)


def _wide_trip(s, d):
    lat = _wide(16)
    pts = lat.points(s, d)
    stream = written(stream_codec.encode_wide(pts, lat.schedule()), "wide")
    back = stream_codec.decode_wide(stream, pts.count(), lat.schedule())
    return back.select(F.concat_ws("-", F.transform("key", lambda w: w.cast("string"))).alias("key"), "cnt")


def _wide_key_sql(lat: Lattice) -> str:
    steps = lat.schedule().steps
    words = [steps[k : k + 60] for k in range(0, len(steps), 60)]
    return " || '-' || ".join("CAST(" + " + ".join(f"(CAST((a{a} >> {bit}) & 1 AS BIGINT) << {len(w) - 1 - k})" for k, (a, bit) in enumerate(w)) + " AS VARCHAR)" for w in words)


add("stream_roundtrip_wide", _wide_trip, f"WITH {sql.points(_wide(16))} SELECT {_wide_key_sql(_wide(16))} AS key, count(*) AS cnt FROM pts GROUP BY 1")


def _halves(s, d):
    p = s.read.parquet(f"{d}/events.parquet")
    halves = []
    for rest in (0, 1):
        lat = Lattice(_EV.tables, _EV.axes, f"{{events}} WHERE event_id % 2 = {rest}")
        halves.append(tree.count_tree(lat.points(s, d), _EV.schedule()))
    return tree.with_coordinates(tree.merge_trees(*halves), _EV.schedule())


add("merge_two_halves", _halves, CATALOG["tree_3d_events"][1])


def _header(s, d):
    """The header that a written codestream is read back with."""
    from ..sources.shared import fresh

    lat = LATTICES["object_orders"]
    place = fresh(s, "codestream")
    Codestream.encode(lat.points(s, d), lat.schedule(), tile_bits=4).write(place)
    h = Codestream.read(s, place).header
    return s.createDataFrame([(h["version"], h["n"], h["q"], h["tile_bits"], " ".join(map(str, h["bits"])), " ".join(map(str, h["axes"])), sum(h["models"]), h["law"])], "version int, n long, q int, tile_bits int, bits string, axes string, predicted_waves int, law string")


add("stream_header", _header, "SELECT 2 AS version, count(*) AS n, 24 AS q, 4 AS tile_bits, '8 8 8' AS bits, trim(repeat('0 1 2 ', 8)) AS axes, 0 AS predicted_waves, 'uniform' AS law FROM orders")


def _nation(s, d):
    lat = Lattice(("customer",), (("c_nationkey", 5), *LATTICES["object_customer"].axes[:2]), "{customer}")
    pts = lat.points(s, d)
    sch = SplitSchedule.round_robin((8, 8))
    own = pts.select(F.col("a0").alias("nation"), keys.cell_key(sch, ["a1", "a2"]).alias("key"), F.explode(F.sequence(F.lit(0), F.lit(15))).alias("level"))
    cells = own.groupBy("nation", "level", F.expr("shiftright(key, 16 - level)").alias("prefix")).agg(F.count(F.lit(1)).alias("cnt"))
    names = s.read.parquet(f"{d}/nation.parquet").select(F.col("n_nationkey").cast("long").alias("nation"), "n_name")
    return cells.join(names, "nation").groupBy("n_name").agg(F.count(F.lit(1)).alias("nodes"), F.round(F.sum(F.log2(F.col("cnt") + 1)), 3).alias("bits"))


_CU = LATTICES["object_customer"].axes
add("tree_by_nation", _nation, "WITH pts AS (SELECT c_nationkey AS nation, " + ", ".join(f"CAST({e} AS BIGINT) AS a{i}" for i, (e, _) in enumerate(_CU[:2])).replace(" div ", " // ").replace("{customer}", "customer") + f" FROM customer), {sql.schedule(SplitSchedule.round_robin((8, 8)))}, c AS (SELECT nation, level, a0 >> r0 AS c0, a1 >> r1 AS c1, count(*) AS cnt FROM pts CROSS JOIN sch GROUP BY ALL) SELECT n_name, count(*) AS nodes, round(sum(log2(cnt + 1)), 3) AS bits FROM c JOIN nation ON n_nationkey = nation GROUP BY n_name")

# Streams of symbols and decoders -----------------------------------------------------------------------------------------------
_SMALL = LATTICES["object_customer"]


def _symbols_sql(lat: Lattice, order: str) -> str:
    q = lat.schedule().q
    by = "level, k" if order == "breadth" else f"(k << ({q} - level)), level"
    text = sql.tree(lat).replace("SELECT level, (a0", f"SELECT ({_key_sql(lat)}) >> ({q} - level) AS k, level, (a0", 1)
    text = text.replace("node AS (SELECT level", "node AS (SELECT k, level").replace("GROUP BY level", "GROUP BY k, level")
    return f"{text}, sym AS (SELECT row_number() OVER (ORDER BY {by}) AS ord, level, k, {sql.axes_of(lat)}, s, cnt, left_cnt FROM node)"


for _order in ("breadth", "depth"):
    add(f"symbols_{_order}", lambda s, d, o=_order: tree.with_coordinates(tree.symbol_stream(nodes_of(_SMALL)(s, d), _SMALL.schedule().q, o), _SMALL.schedule()), f"{_symbols_sql(_SMALL, _order)} SELECT ord, level, {sql.axes_of(_SMALL)}, cnt, left_cnt FROM sym")


def _invariance(s, d):
    parts = [tree.symbol_stream(nodes_of(_SMALL)(s, d), _SMALL.schedule().q, o).agg(F.lit(o).alias("traversal"), F.count(F.lit(1)).alias("nodes"), F.round(F.sum(F.log2(F.col("cnt") + 1)), 3).alias("bits")) for o in ("breadth", "depth")]
    return parts[0].unionByName(parts[1])


add("order_invariance", _invariance, f"{sql.tree(_SMALL)}, t AS (SELECT count(*) AS nodes, round(sum(log2(cnt + 1)), 3) AS bits FROM node) SELECT 'breadth' AS traversal, * FROM t UNION ALL SELECT 'depth', * FROM t")


def _whole_points(lat: Lattice) -> str:
    return f"WITH {sql.points(lat)} SELECT {', '.join(f'a{i} AS c{i}' for i in range(len(lat.axes)))}, count(*) AS cnt FROM pts GROUP BY ALL"


def _relational(lat: Lattice):
    def run(s, d):
        pts, frame = framed(lat.points(s, d), lat.schedule())
        sch = frame.schedule
        symbols = written(tree.symbol_stream(tree.count_tree(pts, sch), sch.q), "symbols")
        n = symbols.where("level = 0").agg(F.sum("cnt")).first()[0] or 0
        return frame.coordinates(progressive.decode_symbols(symbols, n, sch), frame.own.q).drop("level")

    return run


def _coded(lat: Lattice, model: int = 0, level=None, precision=None, tile_bits=None, path="explode"):
    def run(s, d):
        sch = lat.schedule()
        pts, frame = framed(lat.points(s, d), sch)
        stream = Codestream.encode(pts, frame.schedule, model, path, None if tile_bits is None else tile_bits + frame.extra)
        stream.df = written(stream.df, "codestream")
        to = sch.level_of_precision(precision) if precision is not None else sch.q if level is None else level
        return frame.coordinates(stream.cells(to + frame.extra), to)

    return run


def _at_level(lat: Lattice, level: int) -> str:
    used = lat.schedule().used(level)
    cells = ", ".join(f"a{i} >> {b - u} AS c{i}" for i, (b, u) in enumerate(zip(lat.bits, used, strict=True)))
    return f"WITH {sql.points(lat)} SELECT {level} AS level, {cells}, count(*) AS cnt FROM pts GROUP BY ALL"


add("decode_1d_orders", _relational(LATTICES["line_days"]), _whole_points(LATTICES["line_days"]))
add("decode_3d_object", _relational(LATTICES["object_click"]), _whole_points(LATTICES["object_click"]))
for _name, _l, _model, _t in (("decode_3d_events", "events", 0, 6), ("decode_4d_lineitem", "lineitem", 0, 8), ("stream_roundtrip", "object_orders", 0, 4), ("stream_roundtrip_predicted", "smooth", 1, 3), ("stream_roundtrip_dense", "plane_dense", 1, 2), ("stream_roundtrip_line", "line_cents", 1, None)):
    add(_name, _coded(LATTICES[_l], _model, tile_bits=_t), _at_level(LATTICES[_l], LATTICES[_l].schedule().q))
for _lv in (6, 14, 24, 36):
    add(f"progressive_level_{_lv}", _coded(_EV, level=_lv, tile_bits=5), _at_level(_EV, _lv))
for _r in range(6, 11):
    add(f"progressive_precision_{_r}", _coded(_TS, precision=_r, tile_bits=4), _at_level(_TS, _TS.schedule().level_of_precision(_r)))


def _roundtrip(lat):
    def run(s, d):
        sch, pts = lat.schedule(), lat.points(s, d)
        inside, frame = framed(pts, sch)
        stream = Codestream.encode(inside, frame.schedule, tile_bits=6 + frame.extra)
        stream.df = written(stream.df, "codestream")
        back = written(stream.cells(), "cells")
        back = frame.coordinates(back, sch.q).select(*[F.col(f"c{i}").alias(f"a{i}") for i in range(len(sch.bits))], F.explode(F.sequence(F.lit(1).cast("long"), F.col("cnt")))).drop("col")
        lost, made = pts.exceptAll(back), back.exceptAll(pts)
        return lost.agg(F.count(F.lit(1)).alias("lost")).crossJoin(made.agg(F.count(F.lit(1)).alias("made")))

    return run


add("roundtrip_events", _roundtrip(_EV), "SELECT 0 AS lost, 0 AS made")
add("roundtrip_orders", _roundtrip(LATTICES["plane"]), "SELECT 0 AS lost, 0 AS made")
add("stream_sizes", lambda s, d: Codestream.encode(LATTICES["object_orders"].points(s, d), LATTICES["object_orders"].schedule(), tile_bits=4).sizes(), None)


_CODED_TILES = {"events": 4, "lineitem": 4, "smooth": 0, "terrain": 0}


def _coded_rows(names, s, d, model="choose"):
    """(name, payload_bytes, header_bytes, uniform_bits, payloads) of real codestreams, tiles as small as the queries use."""
    out = None
    for name in names:
        lat = LATTICES[name]
        row = Codestream.encode(lat.points(s, d), lat.schedule(), model, tile_bits=_CODED_TILES.get(name, 2)).coded().select(F.lit(name).alias("name"), "*")
        out = row if out is None else out.unionByName(row)
    return out


def _overhead(s, d):
    """Whether payloads of the uniform model are within 2 % of the ideal bits and four bytes a payload, never below it."""
    rows = _coded_rows((*TERRAIN, *OBJECTS), s, d, 0)
    return rows.select("name", ((F.col("payload_bytes") * 8 <= F.col("uniform_bits") * 1.02 + 32 * F.col("payloads")) & (F.col("payload_bytes") * 8 >= F.col("uniform_bits"))).alias("within_bound"))


add("coder_overhead_check", _overhead, " UNION ALL ".join(f"SELECT '{n}' AS name, TRUE AS within_bound" for n in (*TERRAIN, *OBJECTS)))


def _frontier(s, d):
    symbols = tree.symbol_stream(nodes_of(_SMALL)(s, d), _SMALL.schedule().q)
    return tree.with_coordinates(progressive.frontier_after(symbols, 1000, _SMALL.schedule().q), _SMALL.schedule())


_child = ", ".join(f"CASE WHEN s = {i} THEN 2 * c{i} + h ELSE c{i} END AS c{i}" for i in range(3))
add("anytime_frontier", _frontier, f"{_symbols_sql(_SMALL, 'breadth')}, sent AS (SELECT * FROM sym WHERE ord <= 1000), kids AS (SELECT level + 1 AS level, {_child}, CASE h WHEN 0 THEN left_cnt ELSE cnt - left_cnt END AS cnt FROM sent CROSS JOIN (VALUES (0), (1)) AS hh(h)), known AS (SELECT level, c0, c1, c2, cnt FROM sym WHERE level = 0 UNION ALL SELECT * FROM kids WHERE cnt > 0) SELECT * FROM known k WHERE NOT EXISTS (SELECT 1 FROM sent t WHERE t.level = k.level AND t.c0 = k.c0 AND t.c1 = k.c1 AND t.c2 = k.c2)")

# Code lengths, phases, theory -----------------------------------------------------------------------------------------------------
for _name in (*TERRAIN, *OBJECTS, "plane", "line_cents"):
    _lat = LATTICES[_name]
    add(f"bits_uniform_{_name}", lambda s, d, lat=_lat: codelen.code_length(nodes_of(lat)(s, d)), f"{sql.tree(_lat)} SELECT level, count(*) AS nodes, CAST(sum(cnt) AS BIGINT) AS points, round(sum(log2(cnt + 1)), 3) AS bits FROM node GROUP BY level")
for _name in (*TERRAIN, "object_orders", "object_part"):
    add(f"bits_integer_{_name}", lambda s, d, lat=LATTICES[_name]: codelen.code_length(nodes_of(lat)(s, d), "integer"), f"{sql.tree(LATTICES[_name])} SELECT level, count(*) AS nodes, CAST(sum(cnt) AS BIGINT) AS points, CAST(sum(length(bin(cnt))) AS DOUBLE) AS bits FROM node GROUP BY level")
_EMP = "p AS (SELECT level, cnt, left_cnt, count(*) AS n FROM node GROUP BY ALL), a AS (SELECT cnt, left_cnt, sum(n) AS np FROM p GROUP BY ALL), b AS (SELECT cnt, sum(n) AS nt FROM p GROUP BY ALL), e AS (SELECT level, CAST(sum(n) AS BIGINT) AS nodes, CAST(sum(n * cnt) AS BIGINT) AS points, round(sum(n * log2(CAST(nt AS DOUBLE) / np)), 3) AS bits FROM p JOIN a USING (cnt, left_cnt) JOIN b USING (cnt) GROUP BY level)"
for _name in ("smooth", "object_part"):
    add(f"entropy_left_given_p_{_name}", lambda s, d, lat=LATTICES[_name]: codelen.empirical(nodes_of(lat)(s, d)), f"{sql.tree(LATTICES[_name])}, {_EMP} SELECT * FROM e")


def _redundancy(s, d):
    nodes = nodes_of(_TS)(s, d)
    u, e = codelen.code_length(nodes).agg(F.sum("bits").alias("uniform")), codelen.empirical(nodes).agg(F.sum("bits").alias("conditional"))
    return u.crossJoin(e).select(F.round("uniform", 2).alias("uniform"), F.round("conditional", 2).alias("conditional"), F.round(F.col("uniform") - F.col("conditional"), 2).alias("gap"))


add("redundancy_gap", _redundancy, f"{sql.tree(_TS)}, {_EMP}, u AS (SELECT sum(bits) AS uniform FROM (SELECT round(sum(log2(cnt + 1)), 3) AS bits FROM node GROUP BY level)), c AS (SELECT sum(bits) AS conditional FROM e) SELECT round(uniform, 2) AS uniform, round(conditional, 2) AS conditional, round(uniform - conditional, 2) AS gap FROM u, c")
add("phase_costs_lineitem", lambda s, d: codelen.phase_costs(nodes_of(_LI)(s, d)), f"{sql.tree(_LI)} SELECT CASE WHEN cnt > 1 THEN 'separation' ELSE 'localisation' END AS phase, count(*) AS nodes, round(sum(log2(cnt + 1)), 3) AS bits FROM node GROUP BY 1")


def _curve_sql(lat: Lattice) -> str:
    sch = lat.schedule()
    rounds = ", ".join(f"({lv}, {sch.round_of(lv + 1)})" for lv in range(sch.q))
    return f"{sql.tree(lat)}, per AS (SELECT level, sum(log2(cnt + 1)) AS b, sum(cnt) AS n FROM node GROUP BY level), rr(level, precision) AS (VALUES {rounds}) SELECT level, precision, round(b, 3) AS bits_level, round(sum(b) OVER (ORDER BY level), 3) AS bits_cum, round(n * {sch.q} / sum(b) OVER (ORDER BY level), 4) AS cf FROM per JOIN rr USING (level)"


for _name in ("events", "terrain", "smooth", "object_orders"):
    add(f"rate_curve_{_name}", lambda s, d, lat=LATTICES[_name]: codelen.rate_curve(nodes_of(lat)(s, d), lat.schedule()), _curve_sql(LATTICES[_name]))


def _progress(s, d):
    out = None
    for name in ("smooth", "terrain"):
        lat = LATTICES[name]
        sch = lat.schedule()
        ends = {sch.level_of_precision(r): r for r in range(6, 11)}
        curve = codelen.rate_curve(nodes_of(lat)(s, d), sch).where(F.col("level").isin([lv - 1 for lv in ends]))
        n = lat.points(s, d).agg(F.count(F.lit(1)).alias("n"))
        error = progressive.distortion(lat.points(s, d), sch, list(ends))
        rows = curve.join(F.broadcast(n)).withColumn("at", F.col("level") + 1).join(error.withColumnRenamed("level", "at"), "at").select(F.lit(name).alias("name"), "precision", F.round(F.col("bits_cum") / F.col("n"), 3).alias("bpv"), "cf", "max_error")
        out = rows if out is None else out.unionByName(rows)
    return out


for _name in (*TERRAIN, *OBJECTS, "plane", "attributes"):
    add(f"size_report_{_name}", lambda s, d, lat=LATTICES[_name]: codelen.summary(nodes_of(lat)(s, d), lat.schedule().q), sql.summary(LATTICES[_name]))


def _table(names):
    def run(s, d):
        rows = [codelen.summary_of(LATTICES[n].points(s, d), LATTICES[n].schedule()).select(F.lit(n).alias("name"), "*") for n in names]
        out = rows[0]
        for r in rows[1:]:
            out = out.unionByName(r)
        return out

    return run


def _table_sql(names, columns="*") -> str:
    return " UNION ALL ".join(f"SELECT {columns} FROM ({sql.summary(LATTICES[n], name=n)}) t" for n in names)


_FIG = ("name", "n", "source_bytes", "ideal_bytes", "bpv", "cf", "theor_cf")
add("exp_terrain_table", lambda s, d: _table(TERRAIN)(s, d).select(*_FIG), _table_sql(TERRAIN, ", ".join(_FIG)))
add("theory_vs_measured", lambda s, d: _table(("uniform", *TERRAIN, *OBJECTS))(s, d).select("name", "cf", "theor_cf", F.round(F.col("cf") / F.col("theor_cf"), 3).alias("ratio")), f"SELECT name, cf, theor_cf, round(cf / theor_cf, 3) AS ratio FROM ({_table_sql(('uniform', *TERRAIN, *OBJECTS))}) x")
_WORK = ("name", "n", "nodes", "touches", "decoder_estimate", "space_units")
add("complexity_counts", lambda s, d: _table(TERRAIN)(s, d).select(*_WORK), _table_sql(TERRAIN, ", ".join(_WORK)))
_GAIN = ("name", "n", "gain", "integer_gain", "theor_gain", "order_bits")
add("order_gain", lambda s, d: _table(TERRAIN)(s, d).select(*_GAIN), _table_sql(TERRAIN, ", ".join(_GAIN)))
add("ablation_matrix", lambda s, d: _table(("smooth", "object_orders", "object_part"))(s, d).select("name", "ideal_bits", "integer_bits", "gain", "integer_gain"), _table_sql(("smooth", "object_orders", "object_part"), "name, ideal_bits, integer_bits, gain, integer_gain"))
_SWEEP = ("embedding2", "embedding4", "plane", "events", "lineitem", "attributes")
add("dimension_sweep", lambda s, d: _table(_SWEEP)(s, d).select("name", "n", "q_ratio", "cf"), _table_sql(_SWEEP, "name, n, q_ratio, cf"))


def _wide_sweep(*dims):
    def run(s, d):
        rows = [codelen.summary(tree.wide_tree(_wide(k).points(s, d), _wide(k).schedule()).select("level", "cnt", "left_cnt"), 8 * k).select(F.lit(f"embedding{k}").alias("name"), "n", "q_ratio", "cf") for k in dims]
        return rows[0] if len(rows) == 1 else rows[0].unionByName(rows[1])

    return run


add("dimension_sweep_wide", _wide_sweep(8, 16), " UNION ALL ".join(f"SELECT name, n, q_ratio, cf FROM ({sql.summary(_wide(k), name=f'embedding{k}')}) t" for k in (8, 16)))
add("dimension_sweep_64", _wide_sweep(64), None)
add("suite_totals", lambda s, d: _table(OBJECTS)(s, d).rollup("name").agg(F.sum("n").alias("n"), F.sum("source_bytes").alias("source_bytes"), F.sum("ideal_bytes").alias("ideal_bytes")), f"SELECT name, CAST(sum(n) AS BIGINT) AS n, CAST(sum(source_bytes) AS BIGINT) AS source_bytes, CAST(sum(ideal_bytes) AS BIGINT) AS ideal_bytes FROM ({_table_sql(OBJECTS)}) x GROUP BY ROLLUP (name)")


def _coded_table(names):
    """Bytes of coded files beside the ideal ones: payload and header, bits a point and factor of both together."""

    def run(s, d):
        coded, ideal = _coded_rows(names, s, d), _table(names)(s, d).select("name", "n", "source_bytes", "ideal_bytes", "theor_cf")
        both_ = coded.join(F.broadcast(ideal), "name").withColumn("coded_bytes", F.col("payload_bytes") + F.col("header_bytes"))
        return both_.select("name", "n", "source_bytes", "ideal_bytes", "payload_bytes", "header_bytes", "coded_bytes", F.round(F.col("coded_bytes") * 8 / F.col("n"), 3).alias("bpv"), F.round(F.col("source_bytes") / F.col("coded_bytes"), 4).alias("cf"), "theor_cf")

    return run


def _coded_progress(s, d):
    """Bytes that must have arrived for each precision: bands up to its last wave, and the header."""
    out = None
    for name in ("smooth", "terrain"):
        lat = LATTICES[name]
        sch = lat.schedule()
        stream = Codestream.encode(lat.points(s, d), sch, "choose", tile_bits=0)
        head = stream.coded().select("header_bytes")
        ends = s.createDataFrame([(r, sch.level_of_precision(r)) for r in range(6, 11)], "precision int, level int")
        size = written(stream.df.select("wave", F.length("payload").alias("b")), "bands")
        got = ends.join(size, size["wave"] < ends["level"]).groupBy("precision").agg(F.sum("b").alias("payload_bytes")).crossJoin(head)
        n = lat.points(s, d).agg(F.count(F.lit(1)).alias("n"))
        row = got.crossJoin(n).select(F.lit(name).alias("name"), "precision", "payload_bytes", F.round((F.col("payload_bytes") + F.col("header_bytes")) * 8 / F.col("n"), 3).alias("bpv"), F.round(F.col("n") * sch.q / 8 / (F.col("payload_bytes") + F.col("header_bytes")), 4).alias("cf"))
        out = row if out is None else out.unionByName(row)
    return out


def _coded_gain(s, d):
    """What the prediction gains in payload bytes, all waves predicted and the cheaper model for each wave; both signs."""
    out = None
    for name in (*TERRAIN, *OBJECTS):
        lat, t = LATTICES[name], _CODED_TILES.get(name, 2)
        sch = lat.schedule()
        leaves = written(tree.leaf_multiset(lat.points(s, d), sch), "leaves")
        row = s.createDataFrame([(name,)], "name string")
        for label, models in (("uniform", [0] * sch.q), ("predicted", [1] * sch.q), ("chosen", stream_codec.choose_models(leaves, sch, t))):
            row = row.crossJoin(stream_codec.encode_leaves(leaves, sch, t, models).agg(F.sum(F.length("payload")).alias(label)))
        out = row if out is None else out.unionByName(row)
    return out.select("*", *[F.round((1 - F.col(c) / F.col("uniform")) * 100, 2).alias(f"gain_{c}") for c in ("predicted", "chosen")])


add("exp_terrain_table_coded", _coded_table(TERRAIN), None)
add("exp_object_table_coded", _coded_table(OBJECTS), None)
add("suite_totals_coded", lambda s, d: _coded_table(OBJECTS)(s, d).rollup("name").agg(F.sum("n").alias("n"), F.sum("source_bytes").alias("source_bytes"), F.sum("coded_bytes").alias("coded_bytes")), None)
add("exp_progressive_coded", _coded_progress, None)
add("prediction_gain_coded", _coded_gain, None)
#: Lattices whose numbers of points the closed forms are taken at.
_NQ = ("events", "lineitem", "plane", "object_orders", "object_part")


def _theory(s, d):
    rows = [(LATTICES[k].points(s, d).agg(F.count("a0")).first()[0], LATTICES[k].schedule().q) for k in _NQ]
    return s.createDataFrame([(n, q, round(theory.separation_bits(n), 3), round(theory.localisation_bits(n, q), 3), round(theory.total_bits(n, q), 3), round(theory.gain(n), 4), round(theory.gain(n, False), 4), round(theory.factor(n, q), 4), theory.source_bytes(n, q)) for n, q in rows], "n long, q int, separation double, localisation double, total double, gain double, integer_gain double, factor double, source_bytes long")


add("theory_table", _theory, "SELECT n, q, round(2.402::DOUBLE * n, 3) AS separation, round(n * (q - log2(n)), 3) AS localisation, round(n * (q - log2(n) + 2.402::DOUBLE), 3) AS total, round(log2(n) - 2.402::DOUBLE, 4) AS gain, round(log2(n) - 3, 4) AS integer_gain, round(q / (q - log2(n) + 2.402::DOUBLE), 4) AS factor, CAST(ceil(n * q / 8.0) AS BIGINT) AS source_bytes FROM (" + " UNION ALL ".join(f"SELECT count(a0) AS n, {LATTICES[n].schedule().q} AS q FROM ({LATTICES[n].duck()}) p" for n in _NQ) + ") AS t")
for _name, _l in (("uniform", "uniform_keys"), ("events", "events"), ("smooth", "smooth")):
    _n = f"{sql.tree(LATTICES[_l])}, per AS (SELECT level, sum(log2(cnt + 1)) AS b, sum(cnt) AS n FROM node GROUP BY level)"
    add(f"wave_bound_check_{_name}", lambda s, d, lat=LATTICES[_l]: codelen.wave_bounds(nodes_of(lat)(s, d)), f"{_n} SELECT level, round(b, 3) AS bits, round(least(CAST(n AS DOUBLE), pow(2.0, level) * log2(1 + n / pow(2.0, level))), 3) AS bound, b <= least(CAST(n AS DOUBLE), pow(2.0, level) * log2(1 + n / pow(2.0, level))) + 1e-6 AS holds FROM per")
    add(f"empty_cells_{_name}", lambda s, d, lat=LATTICES[_l]: codelen.empty_cells(nodes_of(lat)(s, d)), f"{sql.tree(LATTICES[_l])} SELECT level, CAST(sum(CASE WHEN left_cnt = 0 THEN 1 ELSE 0 END + CASE WHEN left_cnt = cnt THEN 1 ELSE 0 END) AS BIGINT) AS empty, count(*) AS nodes FROM node GROUP BY level")
add("bits_huffman", lambda s, d: baselines.huffman(nodes_of(LATTICES["object_part"])(s, d)), None)

# Split orders ---------------------------------------------------------------------------------------------------------------------
_POLICIES = {"round_robin": SplitSchedule.round_robin, "axis_major": SplitSchedule.axis_major, "align_low": SplitSchedule.align_low, "longest_side": SplitSchedule.longest_side, "reversed": lambda b: SplitSchedule.round_robin(b, list(range(len(b)))[::-1])}


def _orders(lat):
    def run(s, d):
        out = None
        for name, make in _POLICIES.items():
            n = tree.count_tree(lat.points(s, d), make(lat.bits))
            row = n.agg(F.lit(name).alias("policy"), F.count(F.lit(1)).alias("nodes"), F.round(F.sum(F.log2(F.col("cnt") + 1)), 3).alias("bits"))
            out = row if out is None else out.unionByName(row)
        return out

    return run


for _name in ("smooth", "object_orders"):
    add(f"split_order_ablation_{_name}", _orders(LATTICES[_name]), " UNION ALL ".join(f"SELECT * FROM ({sql.tree(LATTICES[_name], make(LATTICES[_name].bits))} SELECT '{p}' AS policy, count(*) AS nodes, round(sum(log2(cnt + 1)), 3) AS bits FROM node) t" for p, make in _POLICIES.items()))


def greedy_axes(points: DataFrame, bits: tuple[int, ...], most: int = 1_000_000) -> list[int]:
    """One axis a wave, the one whose next wave has the lowest ideal cost; one aggregate an axis and wave on about ``most`` points at
    most (a sample that is written once; any order codes the set without loss), with a few numbers to the driver."""
    left, axes = list(bits), []
    cells = points.select(*[f"a{i}" for i in range(len(bits))])
    n = cells.count()
    cells = written(cells.sample(most / n, seed=7) if n > most else cells, "sample")
    for _ in range(sum(bits)):
        open_ = [i for i in range(len(bits)) if left[i]]
        costs = []
        for i in open_:
            nxt = [left[k] - (k == i) for k in range(len(bits))]
            c = cells.groupBy(*[F.shiftright(f"a{k}", nxt[k]).alias(f"c{k}") for k in range(len(bits))]).agg(F.count(F.lit(1)).alias("n"))
            costs.append(c.agg(F.lit(i).alias("axis"), F.round(F.sum(F.log2(F.col("n") + 1)), 6).alias("bits")))
        both = costs[0]
        for c in costs[1:]:
            both = both.unionByName(c)
        axes.append(both.orderBy("bits", "axis").first()["axis"])
        left[axes[-1]] -= 1
    return axes


def _greedy(s, d):
    lat = LATTICES["object_part"]
    pts = lat.points(s, d)
    sch = SplitSchedule.explicit(lat.bits, greedy_axes(pts, lat.bits))
    plain = codelen.summary(nodes_of(lat)(s, d), lat.schedule().q).select(F.lit("round_robin").alias("policy"), "nodes", "ideal_bits")
    return plain.unionByName(codelen.summary(tree.count_tree(pts, sch), sch.q).select(F.lit("greedy").alias("policy"), "nodes", "ideal_bits"))


add("split_order_greedy", _greedy, None)


def _cell_order(s, d):
    out = None
    for name in ("smooth", "object_part", "object_click"):
        lat = LATTICES[name]
        own = cell_order.cell_order_cost(lat.points(s, d), lat.schedule(), 1 << 10)
        fixed = codelen.code_length(nodes_of(lat)(s, d))
        for label, cost in (("cell", own), ("round_robin", fixed)):
            row = cost.agg(F.lit(name).alias("name"), F.lit(label).alias("policy"), F.sum("nodes").alias("nodes"), F.round(F.sum("bits"), 2).alias("bits"))
            out = row if out is None else out.unionByName(row)
    return out


add("split_order_cell", _cell_order, None)

# Prediction -----------------------------------------------------------------------------------------------------------------------
for _name in ("smooth", "terrain", "object_orders"):
    _lat = LATTICES[_name]
    _cols = f"level, {sql.axes_of(_lat)}, cnt, left_cnt, round(nb_left, 6) AS nb_left, round(nb_right, 6) AS nb_right"
    for _label, _order, _w in (("face", 1, "1/dist"), ("order3", 3, "1/dist"), ("geometric3", 3, "geometric")):
        add(f"neighbours_{_label}_{_name}", lambda s, d, lat=_lat, o=_order, w=_w: tree.with_coordinates(predict.neighbour_counts(nodes_of(lat)(s, d), lat.schedule(), o, w), lat.schedule()).withColumn("nb_left", F.round("nb_left", 6)).withColumn("nb_right", F.round("nb_right", 6)), f"{sql.neighbours(_lat, _order, _w)} SELECT {_cols} FROM ctx")
    add(f"predict_left_{_name}", lambda s, d, lat=_lat: tree.with_coordinates(predict.neighbour_counts(nodes_of(lat)(s, d), lat.schedule()).select("level", "prefix", "cnt", "left_cnt", F.round(predict.predicted_left(F.col("nb_left"), F.col("nb_right"), F.col("cnt")), 6).alias("mu")), lat.schedule()), f"{sql.neighbours(_lat)} SELECT level, {sql.axes_of(_lat)}, cnt, left_cnt, CASE WHEN nb_left + nb_right > 0 THEN round(cnt * nb_left / (nb_left + nb_right), 6) END AS mu FROM ctx")
    add(f"bits_predicted_{_name}", lambda s, d, lat=_lat: predict.predicted_cost(predict.neighbour_counts(nodes_of(lat)(s, d), lat.schedule())).select("level", "nodes", "uniform_bits", F.round("predicted_bits", 2).alias("predicted_bits")), f"{sql.neighbours(_lat)} SELECT level, count(*) AS nodes, round(sum(log2(cnt + 1)), 3) AS uniform_bits, round(round(sum({sql.gaussian(0.5, 16.0)}), 3), 2) AS predicted_bits FROM ctx GROUP BY level")

_PL = LATTICES["plane_dense"]
_near = lambda axis, sign: " + ".join(f"coalesce((SELECT m.cnt FROM node m WHERE m.level = n.level AND m.c0 = n.c0 + {x} AND m.c1 = n.c1 + {y}), 0)" for x in (-1, 0, 1) for y in (-1, 0, 1) if (x, y)[axis] == sign)
add("neighbours_moore2d", lambda s, d: tree.with_coordinates(predict.neighbour_counts(nodes_of(_PL)(s, d), _PL.schedule(), shape="moore"), _PL.schedule()), f"{sql.tree(_PL)} SELECT level, c0, c1, cnt, left_cnt, CAST(CASE s WHEN 0 THEN {_near(0, -1)} ELSE {_near(1, -1)} END AS DOUBLE) AS nb_left, CAST(CASE s WHEN 0 THEN {_near(0, 1)} ELSE {_near(1, 1)} END AS DOUBLE) AS nb_right FROM node n")


#: prediction_gain_coded has all lattices, in bytes.
_GAINED = ("smooth", "terrain", *OBJECTS)


def _gains(s, d):
    out = None
    for name in _GAINED:
        lat = LATTICES[name]
        context = predict.neighbour_counts(nodes_of(lat)(s, d), lat.schedule())
        fixed = predict.predicted_cost(context).agg(F.sum("uniform_bits").alias("u"), F.sum("predicted_bits").alias("p"))
        free = predict.choose_model_per_wave(context).agg(F.sum("bits").alias("w"))
        row = fixed.crossJoin(free).select(F.lit(name).alias("name"), F.round((1 - F.col("p") / F.col("u")) * 100, 1).alias("gain_fixed"), F.round((1 - F.col("w") / F.col("u")) * 100, 1).alias("gain_per_wave"))
        out = row if out is None else out.unionByName(row)
    return out


def _gain_sql(name: str) -> str:
    costs = {0: "log2(cnt + 1)", **{k: sql.gaussian(c, sh) for k, (c, sh) in enumerate(predict.GRID, 1)}}
    sums = ", ".join(f"round(sum({e}), 3) AS m{k}" for k, e in costs.items())
    fixed = f"round(sum({sql.gaussian(0.5, 16.0)}), 3) AS p"
    return f"SELECT * FROM ({sql.neighbours(LATTICES[name])}, per AS (SELECT level, {sums}, {fixed} FROM ctx GROUP BY level) SELECT '{name}' AS name, round((1 - sum(p) / sum(m0)) * 100, 1) AS gain_fixed, round((1 - sum(least({', '.join(f'm{k}' for k in costs)})) / sum(m0)) * 100, 1) AS gain_per_wave FROM per) t"


add("prediction_gain", _gains, " UNION ALL ".join(map(_gain_sql, _GAINED)))
_MODELS = ["log2(cnt + 1)", *(sql.gaussian(c, sh) for c, sh in predict.GRID)]
_BEST = f"least({', '.join(f'm{k}' for k in range(len(_MODELS)))})"
_MODEL_SQL = f"{sql.neighbours(_TS)}, per AS (SELECT level, {', '.join(f'round(sum({e}), 3) AS m{k}' for k, e in enumerate(_MODELS))} FROM ctx GROUP BY level) SELECT level, CASE {' '.join(f'WHEN m{k} = {_BEST} THEN {k}' for k in range(len(_MODELS)))} END AS model, round({_BEST}, 2) AS bits FROM per"
add("model_per_wave", lambda s, d: predict.choose_model_per_wave(predict.neighbour_counts(nodes_of(_TS)(s, d), _TS.schedule())).withColumn("bits", F.round("bits", 2)), _MODEL_SQL)
add("gaussian_cost_smooth", lambda s, d: tree.with_coordinates(predict.neighbour_counts(nodes_of(_TS)(s, d), _TS.schedule()).select("level", "prefix", "cnt", "left_cnt", F.round(predict.gaussian_bits(F.col("cnt"), F.col("left_cnt"), predict.predicted_left(F.col("nb_left"), F.col("nb_right"), F.col("cnt"), 16.0)), 4).alias("bits")), _TS.schedule()), f"{sql.neighbours(_TS)} SELECT level, {sql.axes_of(_TS)}, cnt, left_cnt, round({sql.gaussian(0.5, 16.0)}, 4) AS bits FROM ctx")


def _known(column, names, settings):
    """Gain of the prediction for each setting of what a cell may know of its neighbours."""

    def run(s, d):
        out = None
        for name in names:
            lat = LATTICES[name]
            nodes = nodes_of(lat)(s, d)
            for label, setting in settings.items():
                cost = predict.predicted_cost(predict.neighbour_counts(nodes, lat.schedule(), **setting))
                row = cost.agg(F.lit(name).alias("name"), F.lit(label).alias(column), F.round((1 - F.sum("predicted_bits") / F.sum("uniform_bits")) * 100, 1).alias("gain"))
                out = row if out is None else out.unionByName(row)
        return out

    return run


def _known_sql(column, names, settings) -> str:
    return " UNION ALL ".join(f"SELECT * FROM ({sql.neighbours(LATTICES[n], **setting)} SELECT '{n}' AS name, '{label}' AS {column}, round((1 - sum({sql.gaussian(0.5, 16.0)}) / sum(log2(cnt + 1))) * 100, 1) AS gain FROM ctx) t" for n in names for label, setting in settings.items())


_POLICY = {c: {"context": c} for c in ("wave", "two_colour", "sequential")}
_SCOPE = {"global": {}, "tile_4": {"tile_bits": 4}, "tile_8": {"tile_bits": 8}}
for _name, _settings, _column in (("context_policies", _POLICY, "context"), ("scope_ablation", _SCOPE, "scope")):
    add(_name, _known(_column, ("smooth", "object_orders"), _settings), _known_sql(_column, ("smooth", "object_orders"), _settings))


def _contexts(s, d):
    out = None
    for order, w in ((1, "1/dist"), (2, "1/dist"), (3, "1/dist"), (3, "geometric")):
        cost = predict.predicted_cost(predict.neighbour_counts(nodes_of(_TS)(s, d), _TS.schedule(), order, w))
        row = cost.agg(F.lit(order).alias("k"), F.lit(w).alias("weights"), F.round((1 - F.sum("predicted_bits") / F.sum("uniform_bits")) * 100, 1).alias("gain"))
        out = row if out is None else out.unionByName(row)
    return out


add("context_order_ablation", _contexts, " UNION ALL ".join(f"SELECT * FROM ({sql.neighbours(_TS, k, w)} SELECT {k} AS k, '{w}' AS weights, round((1 - sum({sql.gaussian(0.5, 16.0)}) / sum(log2(cnt + 1))) * 100, 1) AS gain FROM ctx) t" for k, w in ((1, "1/dist"), (2, "1/dist"), (3, "1/dist"), (3, "geometric"))))


_VARIED = ("smooth", "terrain", "object_orders", "object_part")


def _density(s, d):
    """How unequal the cells of the middle wave are, beside what the prediction gains over all waves."""
    out = None
    for name in _VARIED:
        lat = LATTICES[name]
        nodes = nodes_of(lat)(s, d)
        cost = predict.predicted_cost(predict.neighbour_counts(nodes, lat.schedule())).agg(F.round((1 - F.sum("predicted_bits") / F.sum("uniform_bits")) * 100, 1).alias("gain"))
        row = nodes.where(F.col("level") == lat.schedule().q // 2).agg(F.lit(name).alias("name"), F.round(F.stddev_samp("cnt") / F.avg("cnt"), 4).alias("cv")).crossJoin(cost)
        out = row if out is None else out.unionByName(row)
    return out


add("gain_vs_density", _density, " UNION ALL ".join(f"SELECT * FROM ({sql.neighbours(LATTICES[n])} SELECT '{n}' AS name, (SELECT round(stddev_samp(cnt) / avg(cnt), 4) FROM node WHERE level = {LATTICES[n].schedule().q // 2}) AS cv, round((1 - sum({sql.gaussian(0.5, 16.0)}) / sum(log2(cnt + 1))) * 100, 1) AS gain FROM ctx) t" for n in _VARIED))

# Regions, distortion, laws ------------------------------------------------------------------------------------------------------------
_BOXES = [[(1_000_000, 1_014_400), (0, 5_000), (0, 7)], [(2_000_000, 2_300_000), (1_000, 20_000), (2, 3)]]
_PTS_IN = " OR ".join("(" + " AND ".join(f"(c{i} << r{i}) <= {b} AND ((c{i} + 1) << r{i}) - 1 >= {a}" for i, (a, b) in enumerate(box)) + ")" for box in _BOXES)
_NR = f"{sql.tree(_EV)}, nr AS (SELECT n.*, ({_PTS_IN}) AS inside FROM node n JOIN sch USING (level))"


def _two_levels(points, sch, *levels):
    """Cells of the levels that a refined view shows, from one multiset."""
    leaves = written(tree.leaf_multiset(points, sch), "leaves")
    cells = [leaves.groupBy(F.shiftright("key", sch.q - lv).alias("prefix")).agg(F.sum("m").alias("cnt")).select(F.lit(lv).alias("level"), "prefix", "cnt") for lv in levels]
    return cells[0].unionByName(cells[1])


add("roi_refine_events", lambda s, d: tree.with_coordinates(progressive.refine(_two_levels(_EV.points(s, d), _EV.schedule(), 9, 30), _EV.schedule(), _BOXES, 9, 30), _EV.schedule()), f"{_NR} SELECT level, c0, c1, c2, cnt FROM nr WHERE (level = 30 AND inside) OR (level = 9 AND NOT inside)")
add("roi_cost", lambda s, d: progressive.roi_cost(nodes_of(_EV)(s, d), _EV.schedule(), _BOXES), f"{_NR} SELECT round(sum(log2(cnt + 1)), 3) AS bits_all, round(sum(CASE WHEN inside THEN log2(cnt + 1) END), 3) AS bits_roi, round(sum(CASE WHEN inside THEN log2(cnt + 1) END) / sum(log2(cnt + 1)), 4) AS share FROM nr")
_each = ["(" + " AND ".join(f"(c{i} << r{i}) <= {b} AND ((c{i} + 1) << r{i}) - 1 >= {a}" for i, (a, b) in enumerate(box)) + ")" for box in _BOXES]
add("roi_session_bits", lambda s, d: progressive.roi_session(nodes_of(_EV)(s, d), _EV.schedule(), _BOXES), f"{sql.tree(_EV)}, st AS (SELECT n.*, CASE WHEN {_each[0]} THEN 0 WHEN {_each[1]} THEN 1 END AS step FROM node n JOIN sch USING (level)) SELECT step, count(*) AS nodes_sent, round(sum(log2(cnt + 1)), 3) AS bits_sent FROM st WHERE step IS NOT NULL GROUP BY step")


def _roi_stream(s, d):
    stream = Codestream.encode(_EV.points(s, d), _EV.schedule(), tile_bits=8)
    cells = stream.cells(ranges=keys.box_to_ranges(_EV.schedule(), _BOXES[0]))
    full = tree.with_coordinates(cells, _EV.schedule())
    for i, (a, b) in enumerate(_BOXES[0]):
        full = full.where(F.col(f"c{i}").between(a, b))
    return full.drop("level")


_IN0 = " AND ".join(f"a{i} BETWEEN {a} AND {b}" for i, (a, b) in enumerate(_BOXES[0]))
add("roi_stream_events", _roi_stream, f"WITH {sql.points(_EV)} SELECT a0 AS c0, a1 AS c1, a2 AS c2, count(*) AS cnt FROM pts WHERE {_IN0} GROUP BY ALL")


def _key_range(s, d):
    ranges = keys.box_to_ranges(_EV.schedule(), _BOXES[0], 32)
    keyed = _EV.points(s, d).withColumn("key", keys.cell_key(_EV.schedule()))
    near = F.lit(False)
    for a, b in ranges:
        near = near | F.col("key").between(a, b)
    exact = F.lit(True)
    for i, (a, b) in enumerate(_BOXES[0]):
        exact = exact & F.col(f"a{i}").between(a, b)
    return keyed.where(near & exact).drop("key")


add("filter_key_range", _key_range, f"WITH {sql.points(_EV)} SELECT * FROM pts WHERE {_IN0}")
_LEVELS = (6, 12, 18, 24)


def _distortion_sql(lat: Lattice, levels=_LEVELS) -> str:
    sch = lat.schedule()
    rows = []
    for lv in levels:
        err = [f"abs(a{i} - (((a{i} >> {b - u}) << {b - u}) + (1 << {b - u}) / 2.0 - 0.5))" for i, (b, u) in enumerate(zip(lat.bits, sch.used(lv), strict=True))]
        rows.append(f"SELECT {lv} AS level, CAST(max(greatest({', '.join(err)})) AS DOUBLE) AS max_error, round(sqrt(sum(CAST({' + '.join(f'{e} * {e}' for e in err)} AS DOUBLE)) / count(*)), 4) AS rmse FROM pts")
    return f"WITH {sql.points(lat)} " + " UNION ALL ".join(rows)




def _progress_sql(name: str) -> str:
    lat = LATTICES[name]
    sch = lat.schedule()
    ends = [sch.level_of_precision(r) for r in range(6, 11)]
    return f"SELECT '{name}' AS name, c.precision, round(c.bits_cum / (SELECT count(*) FROM ({lat.duck()})), 3) AS bpv, c.cf, e.max_error FROM ({_curve_sql(lat)}) c JOIN ({_distortion_sql(lat, ends)}) e ON e.level = c.level + 1"


add("exp_progressive", _progress, " UNION ALL ".join(map(_progress_sql, ("smooth", "terrain"))))
add("distortion_by_wave", lambda s, d: progressive.distortion(_TS.points(s, d), _TS.schedule(), list(_LEVELS)).withColumn("max_error", F.col("max_error").cast("double")), _distortion_sql(_TS))


def _synth(law):
    return lambda s, d: progressive.synthesise(tree.cells_at(_TS.points(s, d), _TS.schedule(), 14), _TS.schedule(), law)


def _synth_sql(law: str) -> str:
    sch = _TS.schedule()
    used = sch.used(14)
    cells = ", ".join(f"(a{i} >> {b - u}) << {b - u} AS l{i}" for i, (b, u) in enumerate(zip(_TS.bits, used, strict=True)))
    head = f"WITH {sql.points(_TS)}, c AS (SELECT ({_key_sql(_TS)}) >> {sch.q - 14} AS prefix, {cells}, count(*) AS cnt FROM pts GROUP BY ALL), p AS (SELECT c.*, unnest(range(1, cnt + 1)) AS i FROM c)"
    out = []
    for k, (b, u) in enumerate(zip(_TS.bits, used, strict=True)):
        side = 1 << (b - u)
        x = f"(((prefix % 65521) * 7919 + i * 104729 + {15485863 * (k + 1) + 7}) % 2147483647 * 48271 % 2147483647)"
        out.append({"uniform": f"l{k} + {x} % {side}", "regular": f"l{k} + (2 * i - 1) * {side} // (2 * cnt)", "grid": f"greatest(l{k}, (l{k} + {side // 2}) - (l{k} + {side // 2}) % 16)"}[law] + f" AS a{k}")
    return f"{head} SELECT {', '.join(out)} FROM p"


for _law in ("uniform", "regular", "grid"):
    add(f"synth_{_law}", _synth(_law), _synth_sql(_law))
add("synth_gaussian", _synth("gaussian"), None)
add("synth_linear", _synth("linear"), None)

_LAW_LEVELS = (12, 18, 24)


def _laws(s, d):
    out = None
    for level in _LAW_LEVELS:
        row = progressive.law_errors(_TS.points(s, d), _TS.schedule(), level).select(F.lit(level).alias("level"), "*")
        out = row if out is None else out.unionByName(row)
    return out


def _law_sql(level: int) -> str:
    used = _TS.schedule().used(level)
    sides = [1 << (b - u) for b, u in zip(_TS.bits, used, strict=True)]
    cells = ", ".join(f"a{i} // {w} * {w} AS l{i}" for i, w in enumerate(sides))
    grid = [f"greatest(l{i}, l{i} + {w // 2} - (l{i} + {w // 2}) % 16)" for i, w in enumerate(sides)]
    mid = [f"(l{i} + {(w - 1) / 2})" for i, w in enumerate(sides)]
    law = {"centre": (mid, "0.0"), "gaussian": (mid, "({w} * {w} - 1) / 48.0"), "grid": (grid, "0.0"), "regular": (mid, "{w} * {w} / 12.0 * (1 - 1.0 / (cnt * cnt))"), "uniform": (mid, "({w} * {w} - 1) / 12.0")}
    errors = ", ".join("round(sqrt(avg(CAST(" + " + ".join(f"(a{i} - {mean[i]}) * (a{i} - {mean[i]}) + " + var.format(w=w) for i, w in enumerate(sides)) + f" AS DOUBLE))), 4) AS {n}" for n, (mean, var) in law.items())
    rows = " UNION ALL ".join(f"SELECT {level} AS level, '{n}' AS law, {n} AS rmse, {n} = least({', '.join(law)})" + "".join(f" AND {n} <> {before}" for before in list(law)[:k]) + " AS chosen FROM e" for k, n in enumerate(law))
    return f"WITH {sql.points(_TS)}, k AS (SELECT *, {cells} FROM pts), c AS (SELECT *, count(*) OVER (PARTITION BY l0, l1, l2) AS cnt FROM k), e AS (SELECT {errors} FROM c) {rows}"


add("law_choice", _laws, " UNION ALL ".join(f"SELECT * FROM ({_law_sql(lv)}) t{lv}" for lv in _LAW_LEVELS))

# Baselines ----------------------------------------------------------------------------------------------------------------------------
add("baseline_raw", lambda s, d: _EV.points(s, d).agg(F.count(F.lit(1)).alias("n"), (F.count(F.lit(1)) * 43).alias("bits")), "SELECT count(*) AS n, count(*) * 43 AS bits FROM events")
_TSI = "WITH pts0 AS (SELECT * FROM ({p})), g AS (SELECT a0 // 16 AS i, a1 // 16 AS j, a2 AS z FROM pts0)".format(p=_TS.duck())
_HB = "SELECT CAST(sum(c) AS BIGINT) AS n, count(*) AS \"distinct\", round(sum(c * log2(CAST(t AS DOUBLE) / c)), 3) AS bits FROM (SELECT v, count(*) AS c, sum(count(*)) OVER () AS t FROM r GROUP BY v) h"


def _grid(s, d, lat=_TS):
    return lat.points(s, d).select((F.col("a0") / 16).cast("int").alias("i"), (F.col("a1") / 16).cast("int").alias("j"), F.col("a2").alias("z"))


for _k, _w in (("previous", [1.0]), ("linear", [2.0, -1.0])):
    _guess = " + ".join(f"{w} * coalesce(lag(z, {k}) OVER (PARTITION BY i ORDER BY j), 0)" for k, w in enumerate(_w, 1))
    add(f"baseline_strip_{_k}", lambda s, d, w=_w: baselines.entropy(baselines.strip_linear(_grid(s, d), "i", "j", ["z"], w), "r_z"), f"{_TSI}, r AS (SELECT z - round({_guess}) AS v FROM g) {_HB}")
_PAR = "u AS (SELECT *, lag(z) OVER (PARTITION BY j ORDER BY i) AS up, lag(z) OVER (PARTITION BY i ORDER BY j) AS lf FROM g), w AS (SELECT *, lag(up) OVER (PARTITION BY i ORDER BY j) AS co FROM u), q AS (SELECT i, j, z - CASE WHEN co IS NOT NULL THEN up + lf - co ELSE coalesce(lf, up, 0) END AS v FROM w)"
add("baseline_parallelogram", lambda s, d: baselines.entropy(baselines.parallelogram(_grid(s, d), "i", "j", "z"), "r"), f"{_TSI}, {_PAR}, r AS (SELECT v FROM q) {_HB}")
add("baseline_crease", lambda s, d: baselines.entropy(baselines.crease(_grid(s, d), "i", "j", "z"), "r2"), f"{_TSI}, {_PAR}, r AS (SELECT v - round(coalesce(avg(v) OVER (PARTITION BY i ORDER BY j ROWS BETWEEN 4 PRECEDING AND 1 PRECEDING), 0.0)) AS v FROM q) {_HB}")


def _delta(s, d):
    lat = LATTICES["object_orders"]
    return baselines.delta_varlen(lat.points(s, d).withColumn("key", keys.cell_key(lat.schedule())), "key", lat.names, 18)


_zig = lambda e: f"(2 * length(bin((CASE WHEN {e} < 0 THEN -2 * ({e}) - 1 ELSE 2 * ({e}) END) + 1)) - 1)"
add("baseline_delta_gamma", _delta, f"WITH {sql.points(LATTICES['object_orders'])}, k AS (SELECT *, {_key_sql(LATTICES['object_orders'])} AS key FROM pts), dd AS (SELECT " + ", ".join(f"a{i} - coalesce(lag(a{i}) OVER (PARTITION BY key >> 18 ORDER BY key, a0, a1, a2), 0) AS d{i}" for i in range(3)) + f" FROM k) SELECT count(*) AS n, CAST(sum({' + '.join(_zig(f'd{i}') for i in range(3))}) AS BIGINT) AS bits FROM dd")


_PROXIES = ("strip", "polygon", "crease")


def _objects(s, d):
    """Ideal bytes of the counts beside the differential code and the proxies of the strip and polygon codecs."""
    pts, ours = None, None
    for name in OBJECTS:
        lat = LATTICES[name]
        p = lat.points(s, d).withColumn("key", keys.cell_key(lat.schedule())).withColumn("name", F.lit(name))
        o = codelen.summary(nodes_of(lat)(s, d), lat.schedule().q).select(F.lit(name).alias("name"), "n", "source_bytes", "ideal_bytes")
        pts, ours = (p, o) if pts is None else (pts.unionByName(p), ours.unionByName(o))
    axes = ["a0", "a1", "a2"]
    residuals = written(baselines.object_residuals(pts, "name", "key", axes, 18), "residuals")
    columns = [f"{p}_{a}" for p in _PROXIES for a in axes]
    hist = residuals.unpivot(["name"], columns, "which", "v").groupBy("name", "which", "v").agg(F.count(F.lit(1)).alias("c"))
    n = residuals.groupBy("name").agg(F.count(F.lit(1)).alias("n"), F.ceil(F.sum("gamma") / 8.0).cast("long").alias("delta_bytes"))
    cost = hist.join(F.broadcast(n.select("name", "n")), "name").groupBy("name", "which").agg(F.round(F.sum(F.col("c") * F.log2(F.col("n") / F.col("c"))), 3).alias("bits"))
    proxies = cost.groupBy("name").agg(*[F.ceil(F.sum(F.when(F.col("which").startswith(p), F.col("bits"))) / 8).cast("long").alias(f"{p}_bytes") for p in _PROXIES])
    return ours.join(n.drop("n"), "name").join(proxies, "name")


def _objects_sql(name: str) -> str:
    lat = LATTICES[name]
    axes = range(len(lat.axes))
    win = "OVER (PARTITION BY key >> 18 ORDER BY key)"
    lag = lambda k, i: f"coalesce(lag(a{i}, {k}) {win}, 0)"
    first = ", ".join(f"a{i} - {lag(1, i)} AS d{i}, CAST(a{i} - round(2.0 * {lag(1, i)} - {lag(2, i)}) AS BIGINT) AS strip{i}, CAST(a{i} - round(1.0 * {lag(1, i)} + {lag(2, i)} - {lag(3, i)}) AS BIGINT) AS polygon{i}" for i in axes)
    second = ", ".join(f"CAST(polygon{i} - round(coalesce(avg(polygon{i}) OVER (PARTITION BY key >> 18 ORDER BY place ROWS BETWEEN 4 PRECEDING AND 1 PRECEDING), 0.0)) AS BIGINT) AS crease{i}" for i in axes)
    delta = " + ".join(_zig(f"d{i}") for i in axes)
    cost = lambda c: f"(SELECT round(sum(c * log2(CAST(t AS DOUBLE) / c)), 3) FROM (SELECT {c}, count(*) AS c, sum(count(*)) OVER () AS t FROM ee GROUP BY {c}))"
    proxies = ", ".join(f"{' + '.join(cost(f'{p}{i}') for i in axes)} AS {p}" for p in _PROXIES)
    parts = f"WITH {sql.points(lat)}, k AS (SELECT *, {_key_sql(lat)} AS key FROM pts), dd AS (SELECT *, row_number() OVER (ORDER BY key) AS place, {first} FROM k), ee AS (SELECT *, {second} FROM dd)"
    return f"SELECT '{name}' AS name, o.*, CAST(ceil(sums.gamma / 8.0) AS BIGINT) AS delta_bytes, {', '.join(f'CAST(ceil(sums.{p} / 8) AS BIGINT) AS {p}_bytes' for p in _PROXIES)} FROM (SELECT n, source_bytes, ideal_bytes FROM ({sql.summary(lat)}) s) o, ({parts} SELECT (SELECT sum({delta}) FROM dd) AS gamma, {proxies}) sums"


add("exp_object_table", _objects, " UNION ALL ".join(_objects_sql(n) for n in OBJECTS))

# Meshes ---------------------------------------------------------------------------------------------------------------------------------
def _mesh(s, d):
    # Written, since each corner reads it: the table is read once.
    return topology.grid_triangles(written(_grid(s, d, _TG).select("i", "j", (F.col("i") * 61 + F.col("j")).alias("v")), "grid"))


add("grid_mesh_triangles", _mesh, f"{_TSI.replace(_TS.duck(), _TG.duck())}, p AS (SELECT i, j, i * 61 + j AS v FROM g) SELECT a.v AS v0, b.v AS v1, x.v AS v2 FROM p a JOIN p b ON b.i = a.i + 1 AND b.j = a.j JOIN p x ON x.i = a.i + 1 AND x.j = a.j + 1 UNION ALL SELECT a.v, x.v, u.v FROM p a JOIN p x ON x.i = a.i + 1 AND x.j = a.j + 1 JOIN p u ON u.i = a.i AND u.j = a.j + 1")


def _corners(s, d):
    return _CU_PTS.points(s, d).select("a0", "a1")


_CU_PTS = LATTICES["object_customer"]
add("delaunay_tiles", lambda s, d: topology.delaunay_tiles(_corners(s, d), 64), None)


def _topology_kept(s, d):
    """Triangles of the set and of the set decoded from its codestream: what is in one and not in the other."""
    sch = _CU_PTS.schedule()
    back = tree.with_coordinates(Codestream.encode(_CU_PTS.points(s, d), sch, tile_bits=3).cells(), sch).select(F.col("c0").alias("a0"), F.col("c1").alias("a1"))
    a, b = written(topology.delaunay_tiles(_corners(s, d), 64), "before"), written(topology.delaunay_tiles(back, 64), "after")
    return a.exceptAll(b).agg(F.count(F.lit(1)).alias("lost")).crossJoin(b.exceptAll(a).agg(F.count(F.lit(1)).alias("made")))


add("topology_kept", _topology_kept, "SELECT 0 AS lost, 0 AS made")


def _file_codecs(s, d):
    """Bytes of the lattice table as Parquet under general-purpose codecs, sorted by key, beside the ideal bytes of the counts."""
    out = []
    for name in ("events", "smooth", "object_orders", "object_part"):
        lat = LATTICES[name]
        pts = written(lat.points(s, d).withColumn("key", keys.cell_key(lat.schedule())).orderBy("key").drop("key"), "points")
        out.append((name, *(baselines.file_bytes(pts, c) for c in ("uncompressed", "snappy", "zstd"))))
    sizes = s.createDataFrame(out, "name string, plain long, snappy long, zstd long")
    return sizes.join(_table([r[0] for r in out])(s, d).select("name", "n", "source_bytes", "ideal_bytes"), "name")


add("baseline_file_codecs", _file_codecs, None)

# Windows over time (batch twins of the streams) ---------------------------------------------------------------------------------------------
_SCH2 = SplitSchedule.round_robin((16, 3))


def _windowed(kind, extra):
    def run(s, d):
        ev = trees.with_time(s.read.parquet(f"{d}/events.parquet"))
        code = F.element_at(F.create_map(*[x for k, t in enumerate(("click", "error", "purchase", "signup", "view")) for x in (F.lit(t), F.lit(k).cast("long"))]), F.col("event_type"))
        pts = ev.select("ts", "user_id", F.round(F.col("value") * 100).cast("long").alias("a0"), code.alias("a1"))
        # Values past the lattice, or null, are cells of their own; so are rows without a time a window of their own, in each of its kinds.
        outer = [f"o{i}" for i in range(2)]
        pts = pts.select("ts", "user_id", *[outer_cell(f"a{i}", b).alias(f"o{i}") for i, b in enumerate(_SCH2.bits)], *[inner(f"a{i}", b).alias(f"a{i}") for i, b in enumerate(_SCH2.bits)])
        key, timeless = keys.cell_key(_SCH2), pts.where("ts is null")
        cells = trees.windowed_tree(pts.where("ts is not null"), _SCH2, trees.window_of(kind), key, _SCH2.q, extra, kind == "session", outer)
        none = F.lit(None).cast("struct<start:timestamp,end:timestamp>")
        cells = cells.unionByName(trees.windowed_tree(timeless.unionByName(timeless) if kind == "sliding" else timeless, _SCH2, none, key, _SCH2.q, extra, False, outer))
        return cells.groupBy(*(extra or []), "level", F.col("start").cast("timestamp_ntz").alias("start")).agg(F.count(F.lit(1)).alias("cells"), F.sum("cnt").alias("points"))

    return run


_W0 = f"WITH ev AS (SELECT ts, user_id, CAST(round(value * 100) AS BIGINT) AS a0, {LATTICES['events'].axes[2][0]} AS a1 FROM events), s2(level, r0, r1) AS (VALUES " + ", ".join(str((lv, 16 - _SCH2.used(lv)[0], 3 - _SCH2.used(lv)[1])) for lv in range(_SCH2.q + 1)) + ")"
_WC = "c AS (SELECT {x}start, level, a0 >> r0 AS c0, a1 >> r1 AS c1, count(*) AS cnt FROM w CROSS JOIN s2 GROUP BY ALL) SELECT {x}level, start, count(*) AS cells, CAST(sum(cnt) AS BIGINT) AS points FROM c GROUP BY ALL"
add("tumbling_trees", _windowed("tumbling", None), f"{_W0}, w AS (SELECT *, date_trunc('day', ts) AS start FROM ev), {_WC.format(x='')}".replace("date_trunc('day', ts)", "CAST(date_trunc('day', ts) AS TIMESTAMP)"))
add("sliding_trees", _windowed("sliding", None), f"{_W0}, w AS (SELECT ev.*, time_bucket(INTERVAL '12 hours', ts, TIMESTAMP '2024-01-01') - k * INTERVAL '12 hours' AS start FROM ev CROSS JOIN (VALUES (0), (1)) AS kk(k)), {_WC.format(x='')}")
add("session_trees", _windowed("session", ["user_id"]), f"{_W0}, o AS (SELECT *, CASE WHEN lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL '30 minutes' > ts THEN 0 ELSE 1 END AS fresh FROM ev), n AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS sid FROM o), w AS (SELECT *, min(ts) OVER (PARTITION BY user_id, sid) AS start FROM n), {_WC.format(x='user_id, ')}")


# Relational operators around the methods: one text for both engines, over trees and points that each builds its own way --------------------
def _tree_text(lat: Lattice) -> str:
    return f"({sql.tree(lat)} SELECT level, {sql.axes_of(lat)}, cnt, left_cnt FROM node)"


def _table_of(kind: str, lat: Lattice | None):
    """A table by kind: the nodes or points of a lattice, or its schedule; for Spark and for DuckDB."""
    if kind == "sch":
        rows = lat.schedule().rows()
        return lambda s, d: s.createDataFrame(rows, "level int, axis int, bit int"), f"(SELECT * FROM (VALUES {', '.join(map(str, rows))}) AS v(level, axis, bit))"
    if kind == "pts":
        return lat.points, f"({lat.duck()})"
    return lambda s, d: tree.with_coordinates(nodes_of(lat)(s, d), lat.schedule()), _tree_text(lat)


_CUST, _CLICK, _VIEW = (LATTICES[f"object_{k}"] for k in ("customer", "click", "view"))
#: Names that the texts below may use in brackets.
_TABLES = {
    "node": _table_of("node", _CUST), "sch": _table_of("sch", _CUST), "pts": _table_of("pts", _CUST), "click": _table_of("node", _CLICK), "view": _table_of("node", _VIEW),
    "click_pts": _table_of("pts", _CLICK), "view_pts": _table_of("pts", _VIEW), "days": _table_of("pts", LATTICES["line_days"]), "event_pts": _table_of("pts", _EV),
}


def over(name: str, text: str, duck: str | None = None) -> None:
    used = [t for t in _TABLES if f"[{t}]" in text]
    marked, plain = text, duck or text
    for t in used:
        marked, plain = marked.replace(f"[{t}]", f"{{{t}}}"), plain.replace(f"[{t}]", _TABLES[t][1])
    add(name, lambda s, d: s.sql(marked, **{t: _TABLES[t][0](s, d) for t in used}), plain)


def both(name: str, tables: tuple[str, ...], text: str, duck: str) -> None:
    """Scalar functions on raw columns."""
    marked, plain = text, duck
    for t in tables:
        marked, plain = marked.replace(f"[{t}]", f"{{{t}}}"), plain.replace(f"[{t}]", t)
    add(name, lambda s, d: s.sql(marked, **{t: s.read.parquet(f"{d}/{t}.parquet") for t in tables}), plain)


_BITS = "log2(cnt + 1)"
_PHASE = "CASE WHEN cnt > 1 THEN 'separation' ELSE 'localisation' END"
_HALF = "CASE WHEN s.axis = {i} THEN {up}.c{i} * 2 + {h} ELSE {up}.c{i} END"
_UP = " AND ".join(f"(k.c{i} >> CASE WHEN s.axis = {i} THEN 1 ELSE 0 END) = p.c{i}" for i in range(3))
_LOW = " AND ".join(f"k.c{i} = " + _HALF.format(i=i, up="p", h=0) for i in range(3))
over("filter_box", f"SELECT a0, a1, a2 FROM [event_pts] WHERE {' AND '.join(f'a{i} BETWEEN {a} AND {b}' for i, (a, b) in enumerate(_BOXES[1]))}")
over("predicate_mix", "SELECT level, c0, c1, c2, cnt FROM [node] WHERE (level IN (3, 6, 9) OR cnt > 40) AND left_cnt IS NOT NULL AND NOT (left_cnt BETWEEN 1 AND 3) AND nullif(cnt, 2) IS NOT NULL")
over("join_cell_match", "SELECT a.level, a.c0, a.c1, a.c2, a.cnt * b.cnt AS pairs FROM [click] a JOIN [view] b ON a.level = b.level AND a.c0 = b.c0 AND a.c1 = b.c1 AND a.c2 = b.c2")
# Children meet the schedule before their parents, so that the parent's cell is a key of the join and not a test on all cells of a level.
_DAD = ", ".join(f"k.c{i} >> CASE WHEN s.axis = {i} THEN 1 ELSE 0 END AS c{i}" for i in range(3))
over("join_parent_child", f"SELECT p.level, p.c0, p.c1, p.c2, p.cnt, count(*) AS children, max(k.cnt) AS largest, p.cnt = sum(k.cnt) AS whole FROM [node] p JOIN (SELECT s.level, {_DAD}, k.cnt FROM [node] k JOIN [sch] s ON k.level = s.level + 1) k ON k.level = p.level AND k.c0 = p.c0 AND k.c1 = p.c1 AND k.c2 = p.c2 GROUP BY p.level, p.c0, p.c1, p.c2, p.cnt", f"SELECT p.level, p.c0, p.c1, p.c2, p.cnt, count(*) AS children, max(k.cnt) AS largest, p.cnt = sum(k.cnt) AS whole FROM [node] p JOIN [sch] s ON s.level = p.level JOIN [node] k ON k.level = p.level + 1 AND {_UP} GROUP BY p.level, p.c0, p.c1, p.c2, p.cnt")
over("schedule_join", f"SELECT s.axis, count(*) AS nodes, round(sum({_BITS}), 3) AS bits FROM [node] n JOIN [sch] s ON n.level = s.level GROUP BY s.axis")
over("tree_diff", "SELECT coalesce(a.level, b.level) AS level, coalesce(a.c0, b.c0) AS c0, coalesce(a.c1, b.c1) AS c1, coalesce(a.c2, b.c2) AS c2, coalesce(a.cnt, 0) - coalesce(b.cnt, 0) AS diff FROM [click] a FULL OUTER JOIN [view] b ON a.level = b.level AND a.c0 = b.c0 AND a.c1 = b.c1 AND a.c2 = b.c2")
over("roi_semi", "SELECT p.a0, p.a1, p.a2 FROM [click_pts] p WHERE EXISTS (SELECT 1 FROM [view] v WHERE v.level = 9 AND v.cnt > 4 AND v.c0 = (p.a0 >> 5) AND v.c1 = (p.a1 >> 5) AND v.c2 = (p.a2 >> 5))")
over("empty_children_anti", f"SELECT p.level, p.c0, p.c1, p.c2, p.left_cnt FROM (SELECT n.*, q.axis FROM [node] n JOIN [sch] q ON q.level = n.level WHERE n.level < 20) p WHERE NOT EXISTS (SELECT 1 FROM [node] k WHERE k.level = p.level + 1 AND {_LOW.replace('s.axis', 'p.axis')})")
over("box_overlap_join", "SELECT b.box, count(*) AS cells, CAST(sum(n.cnt) AS BIGINT) AS points FROM (VALUES (0, 10, 60, 0, 100), (1, 50, 200, 90, 255), (2, 0, 255, 250, 255)) AS b(box, x0, x1, y0, y1) JOIN (SELECT * FROM [click] WHERE level = 12) n ON (n.c0 << 4) <= b.x1 AND ((n.c0 + 1) << 4) > b.x0 AND (n.c1 << 4) <= b.y1 AND ((n.c1 + 1) << 4) > b.y0 GROUP BY b.box")
for _how in ("rollup", "cube"):
    over(f"bits_{_how}", f"SELECT axis, phase, count(*) AS nodes, round(sum(bits), 3) AS bits FROM (SELECT s.axis, {_PHASE} AS phase, {_BITS} AS bits FROM [node] n JOIN [sch] s ON n.level = s.level) x GROUP BY {_how.upper()} (axis, phase)")
over("bits_grouping_sets", f"SELECT level, phase, count(*) AS nodes, round(sum(bits), 3) AS bits FROM (SELECT level, {_PHASE} AS phase, {_BITS} AS bits FROM [node]) x GROUP BY GROUPING SETS ((level), (phase), ())")
over("axis_stats", "SELECT a2, count(*) AS n, min(a0) AS lo, max(a0) AS hi, round(avg(a0), 4) AS mean, round(stddev_samp(a0), 4) AS sd, round(corr(a0, a1), 4) AS r FROM [event_pts] GROUP BY a2")
over("axis_percentiles", "SELECT a2, round(percentile(a1, 0.5), 4) AS p50, round(percentile(a1, 0.9), 4) AS p90, round(median(a0), 4) AS mid FROM [event_pts] GROUP BY a2", "SELECT a2, round(quantile_cont(a1, 0.5), 4) AS p50, round(quantile_cont(a1, 0.9), 4) AS p90, round(median(a0), 4) AS mid FROM [event_pts] GROUP BY a2")
over("occupied_cells", "SELECT level, count(*) AS cells, count(DISTINCT c0) AS columns, count(DISTINCT c2) AS layers FROM [node] GROUP BY level")
add("occupied_cells_approx", lambda s, d: _EV.points(s, d).agg(F.approx_count_distinct(keys.cell_key(_EV.schedule()), 0.02).alias("cells")), None)
over("rank_cells", "SELECT level, c0, c1, c2, cnt, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER (PARTITION BY level ORDER BY cnt DESC, c0, c1, c2) AS nt, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM [node] WINDOW w AS (PARTITION BY level ORDER BY cnt DESC)")
over("window_analytics", "SELECT level, c0, c1, c2, cnt - lag(cnt) OVER w AS d, lead(cnt) OVER w AS nx, first_value(cnt) OVER w AS fv, nth_value(cnt, 2) OVER w AS sv FROM [node] WINDOW w AS (PARTITION BY level ORDER BY c0, c1, c2)")
over("topk_cells", "SELECT level, c0, c1, c2, cnt FROM [node] WHERE level = 12 ORDER BY cnt DESC, c0, c1, c2 LIMIT 10")
over("topk_offset", "SELECT level, c0, c1, c2, cnt FROM [node] WHERE level = 12 ORDER BY cnt DESC, c0, c1, c2 LIMIT 10 OFFSET 5")
over("hash_sample", "SELECT a0, a1, a2 FROM [event_pts] WHERE (a0 * 48271 + a1) % 97 < 5")
over("set_union", "SELECT a0, a1 FROM [click_pts] UNION SELECT a0, a1 FROM [view_pts]")
over("set_intersect", "SELECT a0 >> 2 AS x, a1 >> 2 AS y FROM [click_pts] INTERSECT SELECT a0 >> 2, a1 >> 2 FROM [view_pts]")
over("set_except", "SELECT a0 >> 2 AS x, a1 >> 2 AS y FROM [click_pts] EXCEPT SELECT a0 >> 2, a1 >> 2 FROM [view_pts]")
over("set_except_all", "SELECT a0 >> 4 AS x FROM [click_pts] EXCEPT ALL SELECT a0 >> 4 FROM [view_pts]")
over("sql_exists_roi", "SELECT count(*) AS n, CAST(sum(cnt) AS BIGINT) AS points FROM [click] a WHERE level = 12 AND cnt > (SELECT avg(cnt) FROM [click] WHERE level = 12) AND EXISTS (SELECT 1 FROM [view] b WHERE b.level = 12 AND b.c0 = a.c0 AND b.c1 = a.c1 AND b.c2 = a.c2)")
_REC = "WITH RECURSIVE up(level, c) AS (SELECT 12, c FROM (SELECT DISTINCT a0 AS c FROM [days]) t UNION ALL SELECT level - 1, c >> 1 FROM up WHERE level > 0) SELECT level, count(DISTINCT c) AS cells FROM up GROUP BY level"
over("sql_cte_tree", _REC)
over("bits_pivot", "SELECT * FROM (SELECT s.axis, n.level, n.cnt FROM [node] n JOIN [sch] s ON n.level = s.level) PIVOT (count(cnt) FOR axis IN (0 AS x, 1 AS y, 2 AS z))", "SELECT n.level, nullif(count(*) FILTER (s.axis = 0), 0) AS x, nullif(count(*) FILTER (s.axis = 1), 0) AS y, nullif(count(*) FILTER (s.axis = 2), 0) AS z FROM [node] n JOIN [sch] s ON n.level = s.level GROUP BY n.level")
over("interval_containment", "SELECT n.c0 << 5 AS lo, count(*) AS points FROM (SELECT DISTINCT c0 FROM [click] WHERE level = 9) n JOIN [view_pts] p ON (p.a0 >> 5) = n.c0 AND p.a0 >= (n.c0 << 5) AND p.a0 < (n.c0 << 5) + 16 GROUP BY n.c0")
over("lateral_levels", "SELECT x.level, x.cell, count(*) AS n FROM [days] p, LATERAL (SELECT v.level, p.a0 >> (12 - v.level) AS cell FROM (VALUES (0), (3), (6), (9), (12)) AS v(level)) x GROUP BY x.level, x.cell", "SELECT v.level, p.a0 >> (12 - v.level) AS cell, count(*) AS n FROM [days] p CROSS JOIN (VALUES (0), (3), (6), (9), (12)) AS v(level) GROUP BY 1, 2")
over("bits_unpivot", "SELECT level, measure, total FROM (SELECT level, CAST(count(*) AS BIGINT) AS nodes, CAST(sum(left_cnt) AS BIGINT) AS lower, CAST(sum(cnt - left_cnt) AS BIGINT) AS upper FROM [node] GROUP BY level) UNPIVOT (total FOR measure IN (nodes, lower, upper))")
over("fn_maps", "SELECT level, c0, c1, c2, element_at(m, 'lower') AS lower, size(m) AS n, array_join(array_sort(map_keys(m)), ',') AS names FROM (SELECT *, map_concat(map('lower', left_cnt), map_from_entries(array(struct('upper', cnt - left_cnt)))) AS m FROM [node]) t", "SELECT level, c0, c1, c2, m['lower'] AS lower, CAST(cardinality(m) AS INT) AS n, array_to_string(list_sort(map_keys(m)), ',') AS names FROM (SELECT *, map_concat(MAP {'lower': left_cnt}, map_from_entries([('upper', cnt - left_cnt)])) AS m FROM [node]) t")
# A chunk has 1024 symbols of one wave at most, so its array is bounded whatever the data.
add("wave_symbol_arrays", lambda s, d: tree.symbol_stream(nodes_of(_SMALL)(s, d), _SMALL.schedule().q).groupBy("level", F.floor(F.col("ord") / 1024).alias("chunk")).agg(F.concat_ws(" ", F.transform(F.array_sort(F.collect_list(F.struct("ord", "left_cnt"))), lambda x: x["left_cnt"].cast("string"))).alias("symbols")), f"{_symbols_sql(_SMALL, 'breadth')} SELECT level, ord // 1024 AS chunk, string_agg(CAST(left_cnt AS VARCHAR), ' ' ORDER BY ord) AS symbols FROM sym GROUP BY 1, 2")
add("topk_costly_nodes", lambda s, d: tree.with_coordinates(nodes_of(_EV)(s, d).select("level", "prefix", "cnt", "left_cnt", F.round(F.log2(F.col("cnt") + 1), 3).alias("bits")).orderBy(F.desc("cnt"), "level", "prefix").limit(25), _EV.schedule()), f"{_symbols_sql(_EV, 'breadth')} SELECT level, {sql.axes_of(_EV)}, cnt, left_cnt, round(log2(cnt + 1), 3) AS bits FROM sym ORDER BY cnt DESC, level, k LIMIT 25")
both("fn_ticks", ("events",), "SELECT event_id, datediff(ts, date'2024-01-01') AS days, CAST(hour(ts) AS INT) AS h, CAST(extract(minute FROM ts) AS INT) AS mi FROM [events]", "SELECT event_id, date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS days, hour(ts) AS h, minute(ts) AS mi FROM [events]")
both("fn_json", ("events",), "SELECT event_id, CAST(get_json_object(props, '$.k') AS BIGINT) AS k FROM [events]", "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM [events]")
both("fn_arrays", ("embeddings",), "SELECT vec_id, size(embedding) AS n, size(filter(embedding, x -> x > 0)) AS pos, exists(embedding, x -> x > 0.3) AS far FROM [embeddings]", "SELECT vec_id, len(embedding) AS n, len(list_filter(embedding, lambda x: x > 0)) AS pos, len(list_filter(embedding, lambda x: x > 0.3)) > 0 AS far FROM [embeddings]")
both("asof_event_snapshot", ("events",), "SELECT event_id, last_value(CASE WHEN event_type = 'purchase' THEN event_id END) IGNORE NULLS OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS snap FROM [events]", "SELECT event_id, last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS snap FROM [events]")


def queries() -> dict[str, Query]:
    return {name: run for name, (run, _) in CATALOG.items()}


def oracle_sql() -> dict[str, str]:
    return {name: duck for name, (_, duck) in CATALOG.items() if duck}


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return CATALOG["rate_curve_events"][0](spark, sf_dir)
