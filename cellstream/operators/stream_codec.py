"""Codestream: payloads of a tile's waves, written as Parquet partitioned by wave, with a one-row header.

A tile is a subtree; its payloads need nothing but the count of the tile's root, so tiles are coded and decoded in
parallel and a reader takes only the waves and tiles it wants. Tiles stand in stages: those of a stage begin at one level (a
cut) and end at the next cut, so no tile has more than 2**16 cells a level but those of the last stage, which hold a bounded number
of points. A payload holds a band of waves, as many as are worth a few bytes of overhead. Cells of one point need one
plain bit a wave and bypass the range coder. The model of each wave is in the header: 0 is uniform, 1 predicts
from the tile's own neighbours in the wave before it is split.
"""

from __future__ import annotations

import json

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.schedule import SplitSchedule
from .arith import MOST, Decoder, Encoder, bell_bins, bell_bits, get_digits, put_digits

STREAM = "stage int, tile long, wave int, waves int, payload binary, n_sym long, n_bits double"
CELLS = "level int, prefix long, cnt long"
#: Levels of a tile above the last stage, and ideal bits at which a band of waves is closed.
STAGE, BAND = 16, 1 << 14


def choose_tile_bits(nodes: DataFrame, q: int, cap: int = 2_000_000) -> int:
    """Smallest level whose fullest cell has at most ``cap`` points (Q rows come to the driver); heavy unit cells are one row."""
    rows = nodes.groupBy("level").agg(F.max("cnt").alias("most")).orderBy("level").collect()
    return next((r["level"] for r in rows if r["most"] <= cap), max(0, q - 1))


def cuts(tile_bits: int) -> list[int]:
    """Levels at which the stages begin."""
    return [*range(0, tile_bits, STAGE), tile_bits]


def face_neighbours(prefix: np.ndarray, cnt: np.ndarray, level: int, schedule: SplitSchedule) -> tuple[np.ndarray, np.ndarray]:
    """Points in the cells next to each cell along the axis split at this level; ``prefix`` sorted."""
    axis = schedule.steps[level][0]
    places = [level - 1 - k for k, (a, _) in enumerate(schedule.steps[:level]) if a == axis]
    coordinate = np.zeros(len(prefix), np.int64)
    for p in places:
        coordinate = coordinate << 1 | (prefix >> p & 1)
    rest = prefix & ~np.int64(sum(1 << p for p in places))
    out = []
    for sign in (-1, 1):
        moved = coordinate + sign
        key = rest.copy()
        for k, p in enumerate(places):
            key |= (moved >> (len(places) - 1 - k) & 1) << p
        at = np.minimum(np.searchsorted(prefix, key), max(0, len(prefix) - 1))
        there = (moved >= 0) & (moved < 1 << len(places)) & (prefix[at] == key)
        out.append(np.where(there, cnt[at], 0))
    return out[0], out[1]


def _kinds(prefix, cnt, level, schedule, model: int):
    """Places of single points, of cells coded uniformly and of predicted ones, with the neighbours of these."""
    single = cnt == 1
    if not model:
        return np.flatnonzero(single), np.flatnonzero(~single), np.zeros(0, np.int64), None
    low, high = face_neighbours(prefix, cnt, level, schedule)
    bell = ~single & (low + high > 0)
    at = np.flatnonzero(bell)
    return np.flatnonzero(single), np.flatnonzero(~single & ~bell), at, (low[at], high[at])


class BandEncoder:
    """One payload: coded symbols from its front, plain bits of single points from its end."""

    def __init__(self):
        self._coder, self._bits = Encoder(), []

    def put(self, prefix, cnt, left, level, schedule, model: int, chunk: int = 4096) -> None:
        single, plain, bell, near = _kinds(prefix, cnt, level, schedule, model)
        self._bits.append(left[single].astype(np.uint8))
        put_digits(self._coder, left[plain], cnt[plain] + 1)
        for k in range(0, len(bell), chunk):
            at = bell[k : k + chunk]
            edges, weights = bell_bins(cnt[at], near[0][k : k + chunk], near[1][k : k + chunk])
            run, row = (edges[:, 1:] <= left[at, None]).sum(1), np.arange(len(at))
            before = np.cumsum(weights, 1)[row, run] - weights[row, run]
            inside, size = left[at] - edges[row, run], edges[row, run + 1] - edges[row, run]
            for c, w, t, v, n in zip(before.tolist(), weights[row, run].tolist(), weights.sum(1).tolist(), inside.tolist(), size.tolist(), strict=True):
                self._coder.put(c, w, t)
                self._coder.put_uniform(v, n)

    def finish(self) -> bytes:
        bits = np.concatenate(self._bits) if self._bits else np.zeros(0, np.uint8)
        return self._coder.finish() + np.packbits(bits).tobytes()[::-1]


class BandDecoder:
    def __init__(self, payload: bytes):
        self._coder, self._payload, self._bits, self._at = Decoder(payload), payload, None, 0

    def get(self, prefix, cnt, level, schedule, model: int, chunk: int = 4096) -> np.ndarray:
        """Lower-half counts of one wave's cells."""
        if self._bits is None:
            self._bits = np.unpackbits(np.frombuffer(self._payload[::-1], np.uint8))
        single, plain, bell, near = _kinds(prefix, cnt, level, schedule, model)
        left = np.zeros(len(cnt), np.int64)
        if self._at + len(single) > len(self._bits):
            raise ValueError("damaged or cut payload")
        left[single] = self._bits[self._at : self._at + len(single)]
        self._at += len(single)
        left[plain] = get_digits(self._coder, cnt[plain] + 1)
        for k in range(0, len(bell), chunk):
            at = bell[k : k + chunk]
            edges, weights = bell_bins(cnt[at], near[0][k : k + chunk], near[1][k : k + chunk])
            upto = np.cumsum(weights, 1)
            for row, place in enumerate(at.tolist()):
                total = int(upto[row, -1])
                run = int(np.searchsorted(upto[row], self._coder.target(total), "right"))
                freq = int(weights[row, run])
                self._coder.take(int(upto[row, run]) - freq, freq, total)
                first = int(edges[row, run])
                left[place] = first + self._coder.get_uniform(int(edges[row, run + 1]) - first)
        return left


def _split(prefix, cnt, left):
    both, counts = np.stack([2 * prefix, 2 * prefix + 1], 1).reshape(-1), np.stack([left, cnt - left], 1).reshape(-1)
    return both[counts > 0], counts[counts > 0]


def decode_bands(bands: list[tuple[int, int, bytes]], prefix, cnt, first: int, to_level: int, schedule: SplitSchedule, models: list[int]):
    """Cells at ``to_level`` of one tile, from its root at level ``first`` and its (wave, waves, payload)."""
    level = first
    for wave, waves, payload in sorted(bands):
        if wave != level:
            raise ValueError(f"the payload of wave {level} is missing")
        band = BandDecoder(payload)
        for level in range(wave, min(wave + waves, to_level)):
            prefix, cnt = _split(prefix, cnt, band.get(prefix, cnt, level, schedule, models[level]))
        level = min(wave + waves, to_level)
        if level == to_level:
            break
    if level != to_level:
        raise ValueError(f"the payload of wave {level} is missing")
    return prefix, cnt


def _staged(nodes: DataFrame, tile_bits: int) -> DataFrame:
    """Nodes with the stage and tile that code them."""
    stage, first = F.lit(0), F.lit(0)
    for k, c in enumerate(cuts(tile_bits)):
        stage, first = F.when(F.col("level") >= c, k).otherwise(stage), F.when(F.col("level") >= c, c).otherwise(first)
    return nodes.withColumn("stage", stage).withColumn("tile", F.call_function("shiftright", "prefix", (F.col("level") - first).cast("int")))


def _waves(table: pa.Table):
    """(level, prefix, cnt, left) of each wave of a tile, in order."""
    level, prefix, cnt, left = (table.column(c).to_numpy() for c in ("level", "prefix", "cnt", "left_cnt"))
    order = np.lexsort((prefix, level))
    level, prefix, cnt, left = level[order], prefix[order], cnt[order], left[order]
    if len(cnt) and cnt.max() >= MOST:
        raise ValueError("a cell of 2**42 points or more; cut the set first")
    for wave in np.unique(level).tolist():
        a, b = np.searchsorted(level, [wave, wave + 1])
        yield wave, prefix[a:b], cnt[a:b], left[a:b]


def stage_leaves(leaves: DataFrame, q: int, tile_bits: int) -> DataFrame:
    """(stage, tile, key, m): what each tile is built from, its cells where its stage ends. ``leaves`` (key, m) is read once a stage."""
    out = None
    ends = list(dict.fromkeys([*cuts(tile_bits), q]))
    for k, (first, last) in enumerate(zip(ends, ends[1:], strict=False)):
        own = leaves if last == q else leaves.groupBy(F.shiftright("key", q - last).alias("key")).agg(F.sum("m").alias("m"))
        own = own.select(F.lit(k).alias("stage"), F.shiftright("key", last - first).alias("tile"), "key", "m")
        out = own if out is None else out.unionByName(own)
    return leaves.select(F.lit(0).alias("stage"), F.col("key").alias("tile"), "key", "m").limit(0) if out is None else out


def _leaf_waves(table: pa.Table, ends: list[int]):
    """(level, prefix, cnt, left) of each wave of a tile, in order, from its leaves: one wave is held at a time."""
    stage = table.column("stage")[0].as_py()
    first, last = ends[stage : stage + 2]
    key, m = (table.column(c).to_numpy() for c in ("key", "m"))
    order = np.argsort(key, kind="stable")
    key, m = key[order], m[order]
    if m.sum() >= MOST:
        raise ValueError("a cell of 2**42 points or more; cut the set first")
    for wave in range(first, last):
        prefix = key >> (last - wave)
        starts = np.flatnonzero(np.concatenate([[True], prefix[1:] != prefix[:-1]]))
        yield wave, prefix[starts], np.add.reduceat(m, starts), np.add.reduceat(np.where(key >> (last - wave - 1) & 1, 0, m), starts)


COSTS = "wave int, u double, p double"


def _costs(waves, schedule: SplitSchedule) -> pa.Table:
    rows = []
    for wave, prefix, cnt, left in waves:
        plain = np.log2(cnt + 1.0)
        _, _, bell, near = _kinds(prefix, cnt, wave, schedule, 1)
        told = plain.copy()
        told[bell] = bell_bits(cnt[bell], *near, left[bell])
        rows.append((wave, float(plain.sum()), float(told.sum())))
    return pa.table(dict(zip(("wave", "u", "p"), map(list, zip(*rows, strict=True)), strict=True)), pa.schema([("wave", pa.int32()), ("u", pa.float64()), ("p", pa.float64())]))


def _total(rows: DataFrame) -> DataFrame:
    return rows.groupBy("wave").agg(F.sum("u").alias("uniform_bits"), F.sum("p").alias("predicted_bits"))


def wave_costs(nodes: DataFrame, schedule: SplitSchedule, tile_bits: int) -> DataFrame:
    """(wave, uniform_bits, predicted_bits): what the coder pays for each wave under either model, tiles as they are coded."""
    return _total(_staged(nodes, tile_bits).groupBy("stage", "tile").applyInArrow(lambda table: _costs(_waves(table), schedule), COSTS))


def leaf_costs(leaves: DataFrame, schedule: SplitSchedule, tile_bits: int) -> DataFrame:
    """``wave_costs`` of a leaf multiset (key, m): a row a different point is all that moves."""
    ends = list(dict.fromkeys([*cuts(tile_bits), schedule.q]))
    return _total(stage_leaves(leaves, schedule.q, tile_bits).groupBy("stage", "tile").applyInArrow(lambda table: _costs(_leaf_waves(table, ends), schedule), COSTS))


def choose_models(nodes: DataFrame, schedule: SplitSchedule, tile_bits: int) -> list[int]:
    """The cheaper model of each wave (Q rows come to the driver); of a tree, or of a leaf multiset."""
    costs = leaf_costs if "m" in nodes.columns else wave_costs
    best = {r["wave"]: int(r["predicted_bits"] < r["uniform_bits"]) for r in costs(nodes, schedule, tile_bits).collect()}
    return [best.get(k, 0) for k in range(schedule.q)]


def _payloads(table: pa.Table, waves, schedule: SplitSchedule, models: list[int], band: int) -> pa.Table:
    """Rows of one tile; a band's payload is finished as soon as it is closed."""
    rows, held = [], None

    def close():
        rows.append((held[1], held[2], held[0].finish(), held[3], held[4]))

    for wave, prefix, cnt, left in waves:
        if held is None:
            held = [BandEncoder(), wave, 0, 0, 0.0]
        held[0].put(prefix, cnt, left, wave, schedule, models[wave])
        held[2:] = [held[2] + 1, held[3] + len(cnt), held[4] + float(np.log2(cnt + 1.0).sum())]
        if held[4] >= band:
            close()
            held = None
    if held is not None:
        close()
    stage, tile = (table.column(c)[0].as_py() for c in ("stage", "tile"))
    columns = [[stage] * len(rows), [tile] * len(rows), *([r[k] for r in rows] for k in range(5))]
    kinds = (pa.int32(), pa.int64(), pa.int32(), pa.int32(), pa.binary(), pa.int64(), pa.float64())
    return pa.table([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], [f.split()[0] for f in STREAM.split(", ")])


def encode_tiles(nodes: DataFrame, schedule: SplitSchedule, tile_bits: int | None = None, models: list[int] | None = None, band: int = BAND) -> DataFrame:
    """Codestream rows: (stage, tile, first wave, waves) with payload, symbols and ideal uniform bits."""
    t = choose_tile_bits(nodes, schedule.q) if tile_bits is None else tile_bits
    models = models or [0] * schedule.q
    return _staged(nodes, t).groupBy("stage", "tile").applyInArrow(lambda table: _payloads(table, _waves(table), schedule, models, band), STREAM)


def encode_leaves(leaves: DataFrame, schedule: SplitSchedule, tile_bits: int, models: list[int] | None = None, band: int = BAND) -> DataFrame:
    """``encode_tiles`` of a leaf multiset (key, m), the same rows: each tile's task builds its waves, so the tree is neither written nor moved."""
    models, ends = models or [0] * schedule.q, list(dict.fromkeys([*cuts(tile_bits), schedule.q]))
    return stage_leaves(leaves, schedule.q, tile_bits).groupBy("stage", "tile").applyInArrow(lambda table: _payloads(table, _leaf_waves(table, ends), schedule, models, band), STREAM)


def leaf_tile_bits(leaves: DataFrame, q: int, cap: int = 2_000_000) -> int:
    """``choose_tile_bits`` of a leaf multiset, by halving: a row for each of log2(Q) levels comes to the driver."""
    low, high = 0, max(0, q - 1)
    while low < high:
        level = (low + high) // 2
        most = leaves.groupBy(F.shiftright("key", q - level).alias("p")).agg(F.sum("m").alias("c")).agg(F.max("c")).first()[0] or 0
        low, high = (low, level) if most <= cap else (level + 1, high)
    return low


def make_header(n: int, schedule: SplitSchedule, tile_bits: int, models: list[int] | None = None, law: str = "uniform", lattice: str = "") -> dict:
    return {"version": 2, "n": n, "q": schedule.q, "bits": list(schedule.bits), "axes": [a for a, _ in schedule.steps], "tile_bits": tile_bits, "models": models or [0] * schedule.q, "law": law, "lattice": lattice}


def schedule_of(header: dict) -> SplitSchedule:
    return SplitSchedule.explicit(header["bits"], header["axes"])


def _meets(ranges: list[tuple[int, int]], q: int, level: int) -> Column:
    """Whether the keys below a prefix at a level meet one of the ranges."""
    low = F.shiftleft("tile", q - level)
    high = F.shiftleft(F.col("tile") + 1, q - level) - 1
    out = F.lit(False)
    for a, b in ranges:
        out = out | ((low <= b) & (high >= a))
    return out


def decode_tiles(stream: DataFrame, header: dict, to_level: int | None = None, ranges: list[tuple[int, int]] | None = None) -> DataFrame:
    """(level, prefix, cnt) cells at ``to_level``; ``ranges`` of keys keep only the tiles that meet them.

    Stage by stage: the cells that a stage ends with are the roots of the next one's tiles and meet their payloads in a
    join, so no cell passes the driver. Waves below the level are all that is read (partition pruning); tiles are
    filtered before any payload is decoded.
    """
    schedule, q = schedule_of(header), header["q"]
    level_to = q if to_level is None else to_level
    spark, models = stream.sparkSession, header["models"]
    cells = spark.createDataFrame([(0, header["n"])] if header["n"] else [], "prefix long, cnt long")
    stages = [c for c in dict.fromkeys(cuts(header["tile_bits"])) if c < level_to]
    for k, (first, last) in enumerate(zip(stages, [*stages[1:], level_to], strict=True)):
        known = cells.select(F.col("prefix").alias("tile"), "cnt")
        if ranges is not None:
            known = known.where(_meets(ranges, q, first))
        rows = stream.where((F.col("stage") == k) & (F.col("wave") < last)).select("tile", "wave", "waves", "payload").join(known, "tile")

        cells = rows.groupBy("tile").applyInArrow(_opener(schedule, models, first, last), "prefix long, cnt long")
    return cells.select(F.lit(level_to).alias("level"), "prefix", "cnt")


def _opener(schedule: SplitSchedule, models: list[int], first: int, last: int):
    """Decoder of one tile's joined payloads between two levels."""

    def open_(table: pa.Table) -> pa.Table:
        bands = list(zip(*(table.column(c).to_pylist() for c in ("wave", "waves", "payload")), strict=True))
        prefix, cnt = (np.array([table.column(c)[0].as_py()], np.int64) for c in ("tile", "cnt"))
        prefix, cnt = decode_bands(bands, prefix, cnt, first, last, schedule, models)
        return pa.table({"prefix": prefix, "cnt": cnt})

    return open_


class Box:
    """Closed intervals of whole numbers, one an axis."""

    def __init__(self, sides: list[tuple[int, int]]):
        self.sides = [(int(a), int(b)) for a, b in sides]

    def to_ranges(self, schedule: SplitSchedule, max_ranges: int = 64) -> list[tuple[int, int]]:
        from ..functions.keys import box_to_ranges

        return box_to_ranges(schedule, self.sides, max_ranges)

    def holds(self, names: list[str]) -> Column:
        out = F.lit(True)
        for c, (a, b) in zip(names, self.sides, strict=True):
            out = out & F.col(c).between(a, b)
        return out


class Codestream:
    """A coded point set: the payload table and its header."""

    def __init__(self, df: DataFrame, header: dict):
        self.df, self.header = df, header

    @classmethod
    def encode(cls, points: DataFrame, schedule: SplitSchedule, model: int | str = 0, path: str = "explode", tile_bits: int | None = None, law: str = "uniform", lattice: str = "") -> Codestream:
        """Code a set. ``model``: 0, 1, or "choose" for the cheaper one of each wave; ``law`` "choose" takes the law of the
        smallest error half-way down. The different points are written once, and each tile's task builds its part of the tree
        from them, so ``path`` (that of a tree that is built apart) makes no difference here."""
        from ..sources.shared import written
        from .progressive import choose_law
        from .tree import leaf_multiset

        leaves = written(leaf_multiset(points, schedule), "leaves")
        n = leaves.agg(F.sum("m")).first()[0] or 0
        t = leaf_tile_bits(leaves, schedule.q) if tile_bits is None else tile_bits
        models = choose_models(leaves, schedule, t) if model == "choose" else [int(model)] * schedule.q
        if law == "choose":
            law = choose_law(points, schedule, schedule.q // 2) or "uniform"
        return cls(encode_leaves(leaves, schedule, t, models), make_header(n, schedule, t, models, law, lattice))

    @property
    def schedule(self) -> SplitSchedule:
        return schedule_of(self.header)

    def write(self, path: str, mode: str = "error") -> None:
        self.df.repartitionByRange("wave", "stage", "tile").sortWithinPartitions("wave", "stage", "tile").write.mode(mode).partitionBy("wave").parquet(f"{path}/waves")
        self.df.sparkSession.createDataFrame([(json.dumps(self.header),)], "header string").coalesce(1).write.mode(mode).text(f"{path}/header")

    @classmethod
    def read(cls, spark: SparkSession, path: str) -> Codestream:
        header = json.loads(spark.read.text(f"{path}/header").first()[0])
        return cls(spark.read.schema("stage int, tile long, waves int, payload binary, n_sym long, n_bits double, wave int").parquet(f"{path}/waves"), header)

    def cells(self, level: int | None = None, precision: int | None = None, ranges=None, boxes: list[Box] | None = None) -> DataFrame:
        if precision is not None:
            level = self.schedule.level_of_precision(precision)
        if boxes is not None:
            ranges = [r for b in boxes for r in b.to_ranges(self.schedule)]
        return decode_tiles(self.df, self.header, level, ranges)

    def points(self, level: int | None = None, law: str | None = None, **which) -> DataFrame:
        """One row a point: exact at the last level, else placed in its cell by the header's law or the one given."""
        from .progressive import synthesise

        law = law or self.header["law"]
        return synthesise(self.cells(level, **which), self.schedule, "regular" if law == "centre" else law)

    def sizes(self) -> DataFrame:
        """(wave, bytes, n_sym, ideal_bits) by first wave of a band."""
        return self.df.groupBy("wave").agg(F.sum(F.length("payload")).alias("bytes"), F.sum("n_sym").alias("n_sym"), F.round(F.sum("n_bits"), 3).alias("ideal_bits"))

    def coded(self) -> DataFrame:
        """One row: payload and header bytes, ideal uniform bits, number of payloads."""
        header = len(json.dumps(self.header, separators=(",", ":")))
        return self.df.agg(F.coalesce(F.sum(F.length("payload")), F.lit(0)).cast("long").alias("payload_bytes"), F.lit(header).cast("long").alias("header_bytes"), F.round(F.coalesce(F.sum("n_bits"), F.lit(0.0)), 3).alias("uniform_bits"), F.count(F.lit(1)).alias("payloads"))

    def rate_curve(self, nodes: DataFrame) -> DataFrame:
        from .codelen import rate_curve

        return rate_curve(nodes, self.schedule)


class PointCodec:
    """What a stream is coded with: lattice, schedule, model, law, points a tile holds."""

    def __init__(self, spec, schedule: SplitSchedule, model: int | str = "choose", law: str = "uniform", tile_cap: int = 2_000_000):
        self.spec, self.schedule, self.model, self.law, self.tile_cap = spec, schedule, model, law, tile_cap

    def _points(self, df: DataFrame) -> DataFrame:
        from ..functions.lattice import to_lattice

        return df if self.spec is None else to_lattice(df, self.spec)

    def nodes(self, df: DataFrame, path: str = "sweep") -> DataFrame:
        from .tree import count_tree

        return count_tree(self._points(df), self.schedule, path)

    def symbols(self, df: DataFrame, order: str = "breadth") -> DataFrame:
        from .tree import symbol_stream

        return symbol_stream(self.nodes(df), self.schedule.q, order)

    def encode(self, df: DataFrame, path: str = "sweep") -> Codestream:
        lattice = "" if self.spec is None else self.spec.to_json()
        nodes = self.nodes(df, path)
        return Codestream.encode(self._points(df), self.schedule, self.model, path, choose_tile_bits(nodes, self.schedule.q, self.tile_cap), self.law, lattice)

    def cost(self, df: DataFrame) -> DataFrame:
        from .codelen import summary

        return summary(self.nodes(df), self.schedule.q)


WIDE = "stage int, tile array<long>, wave int, waves int, payload binary, n_sym long, n_bits double"


def encode_wide(points: DataFrame, schedule: SplitSchedule, band: int = BAND) -> DataFrame:
    """Codestream rows of keys of any width, uniform model: a stage a word of the key, a tile its words before."""
    from ..functions.keys import WORD
    from .tree import wide_tree

    nodes = wide_tree(points, schedule)
    stage = F.floor(F.col("level") / WORD).cast("int")
    own = nodes.select(stage.alias("stage"), F.slice("prefix", F.lit(1), stage).alias("tile"), (F.col("level") - stage * WORD).cast("int").alias("level"), F.element_at("prefix", -1).alias("prefix"), "cnt", "left_cnt")

    def code(table: pa.Table) -> pa.Table:
        rows, held = [], None
        for wave, prefix, cnt, left in _waves(table):
            held = held or [BandEncoder(), wave, 0, 0, 0.0]
            held[0].put(prefix, cnt, left, wave, schedule, 0)
            held[2:] = [held[2] + 1, held[3] + len(cnt), held[4] + float(np.log2(cnt + 1.0).sum())]
            if held[4] >= band:
                rows.append(held)
                held = None
        rows += [held] if held is not None else []
        stage, tile = table.column("stage")[0].as_py(), table.column("tile")[0].as_py()
        columns = [[stage] * len(rows), [tile] * len(rows), [r[1] for r in rows], [r[2] for r in rows], [r[0].finish() for r in rows], [r[3] for r in rows], [r[4] for r in rows]]
        kinds = (pa.int32(), pa.list_(pa.int64()), pa.int32(), pa.int32(), pa.binary(), pa.int64(), pa.float64())
        return pa.table([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], [f.split()[0] for f in WIDE.split(", ")])

    return own.groupBy("stage", "tile").applyInArrow(code, WIDE)


def decode_wide(stream: DataFrame, n: int, schedule: SplitSchedule) -> DataFrame:
    """(key array<long>, cnt): whole points, word by word."""
    from ..functions.keys import WORD

    cells = stream.sparkSession.createDataFrame([([], n)] if n else [], "tile array<long>, cnt long")
    for k, first in enumerate(range(0, schedule.q, WORD)):
        rows = stream.where(F.col("stage") == k).select("tile", "wave", "waves", "payload").join(cells, "tile")
        opened = rows.groupBy("tile").applyInArrow(_wide_opener(schedule, min(WORD, schedule.q - first)), "tile array<long>, cnt long")
        cells = opened
    return cells.select(F.col("tile").alias("key"), "cnt")


def _wide_opener(schedule: SplitSchedule, width: int):
    def open_(table: pa.Table) -> pa.Table:
        bands = list(zip(*(table.column(c).to_pylist() for c in ("wave", "waves", "payload")), strict=True))
        prefix, cnt = decode_bands(bands, np.zeros(1, np.int64), np.array([table.column("cnt")[0].as_py()], np.int64), 0, width, schedule, [0] * width)
        head = table.column("tile")[0].as_py()
        return pa.table([pa.array([[*head, p] for p in prefix.tolist()], pa.list_(pa.int64())), pa.array(cnt)], ["tile", "cnt"])

    return open_
