"""``spark.read.format("cellstream")``: decoded cells of a codestream folder, a read split per slice of the key space.

Options: ``path``, ``level`` (default: all levels), ``box`` (closed intervals, one an axis: "0:9,5:7"), ``slices`` (read splits, 64).
The driver reads only the header. A split reads the payloads of the tiles that meet its slice, found by row-group
statistics on (stage, tile), and decodes them from the root down. Register with ``register(spark)``. The folder must be
readable by pyarrow's file systems; through Spark's own readers use ``Codestream.read``.
"""

from __future__ import annotations

import json

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SCHEMA = "level int, prefix long, cnt long"


class _Slice(InputPartition):
    def __init__(self, ranges: list[tuple[int, int]]):
        self.ranges = ranges


class _Reader(DataSourceReader):
    def __init__(self, options):
        self._path, self._level, self._box = options["path"].removeprefix("file://"), options.get("level"), options.get("box")
        self._slices = int(options.get("slices", 64))

    def _place(self):
        from pyarrow import fs

        return fs.FileSystem.from_uri(self._path) if "://" in self._path else (fs.LocalFileSystem(), self._path)

    def _header(self) -> dict:
        from pyarrow import fs

        files, place = self._place()
        infos = [i for i in files.get_file_info(fs.FileSelector(f"{place}/header")) if i.base_name.startswith("part-")]
        return json.loads(files.open_input_stream(infos[0].path).read())

    def partitions(self):
        from ..operators.stream_codec import Box, schedule_of

        header = self._header()
        if not header["n"]:
            return []
        whole = 1 << header["q"]
        wanted = [(0, whole - 1)]
        if self._box:
            sides = [tuple(map(int, side.split(":"))) for side in self._box.split(",")]
            wanted = Box(sides).to_ranges(schedule_of(header))
        # Slices are whole tiles of the last stage, or whole cells of a coarser level, so that none is in two of them.
        target = header["q"] if self._level is None else int(self._level)
        tile = 1 << (header["q"] - min(target, header["tile_bits"]))
        step = max(tile, -(-whole // self._slices // tile) * tile)
        slices = []
        for at in range(0, whole, step):
            own = [(max(a, at), min(b, at + step - 1)) for a, b in wanted if a < at + step and b >= at]
            if own:
                slices.append(_Slice(own))
        return slices

    def read(self, partition):
        import numpy as np
        import pyarrow.dataset as ds

        from ..operators.stream_codec import cuts, decode_bands, schedule_of

        header = self._header()
        files, place = self._place()
        waves = ds.dataset(f"{place}/waves", filesystem=files, format="parquet", partitioning="hive")
        schedule, q, to = schedule_of(header), header["q"], header["q"] if self._level is None else int(self._level)
        prefix, cnt = np.zeros(1, np.int64), np.array([header["n"]], np.int64)
        stages = [c for c in dict.fromkeys(cuts(header["tile_bits"])) if c < to]

        def inside(level):
            low, high = prefix << (q - level), ((prefix + 1) << (q - level)) - 1
            return np.any([(low <= b) & (high >= a) for a, b in partition.ranges], axis=0)

        for k, (first, last) in enumerate(zip(stages, [*stages[1:], to], strict=True)):
            take = inside(first)
            prefix, cnt = prefix[take], cnt[take]
            if not len(prefix):
                return
            field = ds.field("tile")
            rows = waves.to_table(filter=(ds.field("stage") == k) & (field >= int(prefix.min())) & (field <= int(prefix.max())) & (ds.field("wave") < last)).to_pylist()
            bands: dict[int, list] = {}
            for r in rows:
                bands.setdefault(r["tile"], []).append((r["wave"], r["waves"], r["payload"]))
            parts = [decode_bands(bands[int(p)], np.array([p]), np.array([c]), first, last, schedule, header["models"]) for p, c in zip(prefix, cnt, strict=True)]
            prefix, cnt = np.concatenate([p for p, _ in parts]), np.concatenate([c for _, c in parts])
        mine = inside(to)
        for p, c in zip(prefix[mine].tolist(), cnt[mine].tolist(), strict=True):
            yield to, p, c


class CellstreamSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "cellstream"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)


def register(spark) -> None:
    spark.dataSource.register(CellstreamSource)
