"""DuckDB SQL of the queries, from the lattice text and a schedule table; cells are grouped by shifted coordinates."""

from __future__ import annotations

from ..functions.schedule import SplitSchedule
from ..sources.workloads import Lattice


def points(lat: Lattice) -> str:
    return f"pts AS ({lat.duck()})"


def schedule(sch: SplitSchedule, last: bool = False) -> str:
    """sch(level, r0.., s): open bits of each axis, and the axis split next; ``last`` adds the row of whole points."""
    rows = []
    for level in range(sch.q + last):
        used = sch.used(level)
        axis = sch.steps[level][0] if level < sch.q else 0
        rows.append("(" + ", ".join(map(str, [level, *(b - u for b, u in zip(sch.bits, used, strict=True)), axis])) + ")")
    names = ", ".join(["level", *(f"r{i}" for i in range(len(sch.bits))), "s"])
    return f"sch({names}) AS (VALUES {', '.join(rows)})"


def tree(lat: Lattice, sch: SplitSchedule | None = None, where: str = "TRUE", source: str = "pts") -> str:
    """WITH parts up to node(level, c0.., s, cnt, left_cnt)."""
    sch = sch or lat.schedule()
    axes = range(len(sch.bits))
    cells = ", ".join(f"(a{i} >> r{i}) AS c{i}" for i in axes)
    low = "CASE s " + " ".join(f"WHEN {i} THEN (a{i} >> (r{i} - 1)) & 1" for i in axes) + " END"
    groups = ", ".join(["level", *(f"c{i}" for i in axes), "s"])
    return (
        f"WITH {points(lat)}, {schedule(sch)}, spread AS (SELECT level, {cells}, s, {low} AS high FROM {source} CROSS JOIN sch WHERE {where}), "
        f"node AS (SELECT {groups}, count(*) AS cnt, CAST(sum(1 - high) AS BIGINT) AS left_cnt FROM spread GROUP BY {groups})"
    )


def axes_of(lat: Lattice) -> str:
    return ", ".join(f"c{i}" for i in range(len(lat.axes)))


SUMMARY = (
    "SELECT {name}n, CAST(ceil(n * {q} / 8.0) AS BIGINT) AS source_bytes, CAST(ceil(round(b, 3) / 8) AS BIGINT) AS ideal_bytes, round(b, 3) AS ideal_bits, integer_bits, round(b / n, 4) AS bpv, round(n * {q} / b, 4) AS cf,"
    " round({q} / ({q} - log2(n) + 2.402), 4) AS theor_cf, round(log2(n) - 2.402, 4) AS theor_gain, round({q} - b / n, 4) AS gain, round({q} - integer_bits / n, 4) AS integer_gain, round(n * log2(n), 3) AS order_bits,"
    " nodes, touches, round(n * ({q} - log2(n) + 1), 3) AS decoder_estimate, n * ({q} + 4) AS space_units, round({q} / log2(n), 4) AS q_ratio FROM ("
    "SELECT max(CASE WHEN level = 0 THEN cnt END) AS n, count(*) AS nodes, CAST(sum(cnt) AS BIGINT) AS touches, sum(log2(cnt + 1)) AS b, CAST(sum(length(bin(cnt))) AS BIGINT) AS integer_bits FROM node) x"
)


def summary(lat: Lattice, sch: SplitSchedule | None = None, name: str = "") -> str:
    sch = sch or lat.schedule()
    return f"{tree(lat, sch)} " + SUMMARY.format(q=sch.q, name=f"'{name}' AS name, " if name else "")


def neighbours(lat: Lattice, order: int = 1, weights: str = "1/dist", levels: list[int] | None = None, context: str = "wave", tile_bits: int | None = None) -> str:
    """WITH parts up to ctx(level, c0.., cnt, left_cnt, nb_left, nb_right)."""
    d = len(lat.axes)
    parts = []
    tile = []
    if tile_bits is not None:
        # Bits settled since the tile: those open at the tile's level and closed at the node's.
        settled = [b - u for b, u in zip(lat.bits, lat.schedule().used(tile_bits), strict=True)]
        tile = [f"CASE WHEN level > {tile_bits} THEN c{i} >> ({o} - (SELECT any_value(r{i}) FROM sch z WHERE z.level = node.level)) ELSE 0 END" for i, o in enumerate(settled)]
    for axis in range(d):
        others = ", ".join(["level", *tile, *(f"c{i}" for i in range(d) if i != axis)])
        line = f"OVER (PARTITION BY {others} ORDER BY c{axis} RANGE BETWEEN"
        near_left, near_right = f"coalesce(sum(2 * (cnt - left_cnt)) {line} 1 PRECEDING AND 1 PRECEDING), 0)", f"coalesce(sum(2 * left_cnt) {line} 1 FOLLOWING AND 1 FOLLOWING), 0)"

        def side(way, axis=axis, others=others):
            terms = []
            for k in range(1, order + 1):
                w = 1 / k if weights == "1/dist" else 0.5 ** (k - 1)
                terms.append(f"coalesce(sum(cnt) OVER (PARTITION BY {others} ORDER BY c{axis} RANGE BETWEEN {k} {way} AND {k} {way}), 0) * CAST({w!r} AS DOUBLE)")
            return " + ".join(terms)

        left, right = side("PRECEDING"), side("FOLLOWING")
        if context == "sequential":
            left = near_left
        elif context == "two_colour":
            left, right = (f"CASE WHEN c{axis} % 2 = 1 THEN {near} ELSE {plain} END" for near, plain in ((near_left, left), (near_right, right)))
        chosen = "" if levels is None else f" AND level IN ({', '.join(map(str, levels))})"
        parts.append(f"SELECT level, {axes_of(lat)}, cnt, left_cnt, CAST({left} AS DOUBLE) AS nb_left, CAST({right} AS DOUBLE) AS nb_right FROM node WHERE s = {axis}{chosen}")
    return f"{tree(lat)}, ctx AS ({' UNION ALL '.join(parts)})"


def gaussian(c: float, shrink: float, floor: float = 0.05) -> str:
    """Expression of the predicted cost over ctx."""
    sigma = f"greatest(0.3, {c!r} * sqrt(CAST(cnt AS DOUBLE)))"
    mu = f"(cnt * (nb_left + {shrink!r}) / (nb_left + nb_right + {2 * shrink!r}))"
    weight = lambda k: f"exp(-pow(({k} - {mu}) / {sigma}, 2) / 2)"
    inside = f"(1 / (1 + exp(-1.702 * (cnt + 0.5 - {mu}) / {sigma})) - 1 / (1 + exp(1.702 * ({mu} + 0.5) / {sigma})))"
    total = f"CASE WHEN cnt <= 4096 THEN list_sum(list_transform(range(0, least(cnt, 4096) + 1), lambda k: {weight('k')})) ELSE {sigma} * 2.5066282746310002 * {inside} END"
    return f"CASE WHEN nb_left + nb_right > 0 THEN -log2({1 - floor!r} * least(1.0, {weight('left_cnt')} / ({total})) + {floor!r} / (cnt + 1)) ELSE log2(cnt + 1) END"
