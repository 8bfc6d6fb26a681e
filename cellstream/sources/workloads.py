"""The lattices on the given tables. One text serves both engines: {us:col:date}, {days:col:date} and `div` differ by engine."""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from ..functions.schedule import SplitSchedule


@dataclass(frozen=True)
class Lattice:
    tables: tuple[str, ...]
    axes: tuple[tuple[str, int], ...]
    source: str  # what stands after FROM, tables as {name}

    @property
    def bits(self) -> tuple[int, ...]:
        return tuple(b for _, b in self.axes)

    @property
    def names(self) -> list[str]:
        return [f"a{i}" for i in range(len(self.axes))]

    def schedule(self) -> SplitSchedule:
        return SplitSchedule.round_robin(self.bits)

    def _select(self) -> str:
        return "SELECT " + ", ".join(f"CAST({e} AS BIGINT) AS a{i}" for i, (e, _) in enumerate(self.axes)) + f" FROM {self.source}"

    def duck(self) -> str:
        """DuckDB text of the points."""
        t = re.sub(r"\{us:(\w+):([\d-]+)\}", r"date_diff('microsecond', TIMESTAMP '\2', \1)", self._select())
        t = re.sub(r"\{days:(\w+):([\d-]+)\}", r"date_diff('day', DATE '\2', CAST(\1 AS DATE))", t)
        t = re.sub(r"\{elem:(\w+):(\d+)\}", lambda m: f"{m[1]}[{int(m[2]) + 1}]", t)
        return re.sub(r"\{(\w+)\}", r"\1", t).replace(" div ", " // ")

    def points(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        t = re.sub(r"\{us:(\w+):([\d-]+)\}", r"timestampdiff(MICROSECOND, timestamp_ntz'\2', \1)", self._select())
        t = re.sub(r"\{days:(\w+):([\d-]+)\}", r"datediff(\1, date'\2')", t)
        t = re.sub(r"\{elem:(\w+):(\d+)\}", r"\1[\2]", t)
        return spark.sql(t, **{n: spark.read.parquet(f"{sf_dir}/{n}.parquet") for n in self.tables})


def cents(c: str) -> str:
    return f"CAST(round({c} * 100) AS BIGINT)"


_GRID = "least(60, {days:l_shipdate:1995-01-01} * 61 div 2500)", "least(60, CAST(floor(l_extendedprice) AS BIGINT) * 61 div 105000)"
_TYPES = ("click", "error", "purchase", "signup", "view")

_LI = (("{days:l_shipdate:1995-01-01}", 12), (cents("l_extendedprice"), 24), ("l_quantity", 6), ("CASE WHEN l_linestatus = 'O' THEN 1 ELSE 0 END", 1))
_SMOOTH = (
    "(SELECT i, j, 63 * CAST(sum(r) OVER (PARTITION BY i ORDER BY j) AS BIGINT) div n AS z FROM ("
    " SELECT i, j, CAST(sum(c) OVER (PARTITION BY j ORDER BY i) AS BIGINT) AS r, CAST(sum(c) OVER () AS BIGINT) AS n FROM ("
    "  SELECT x.i AS i, y.j AS j, coalesce(g.c, 0) AS c FROM"
    "   (SELECT explode_i AS i FROM (VALUES " + ", ".join(f"({k})" for k in range(61)) + ") AS v(explode_i)) x"
    "   CROSS JOIN (SELECT explode_j AS j FROM (VALUES " + ", ".join(f"({k})" for k in range(61)) + ") AS w(explode_j)) y"
    f"   LEFT JOIN (SELECT {_GRID[0]} AS i, {_GRID[1]} AS j, count(*) AS c FROM {{lineitem}} GROUP BY 1, 2) g ON g.i = x.i AND g.j = y.j) s) t) u"
)

LATTICES: dict[str, Lattice] = {
    "events": Lattice(("events",), (("{us:ts:2024-01-01} div 250000", 24), (cents("value"), 16), ("CASE event_type " + " ".join(f"WHEN '{t}' THEN {k}" for k, t in enumerate(_TYPES)) + " END", 3)), "{events}"),
    "lineitem": Lattice(("lineitem",), _LI, "{lineitem}"),
    "terrain": Lattice(("lineitem",), (("16 * i", 10), ("16 * j", 10), ("floor(q)", 6)), f"(SELECT {_GRID[0]} AS i, {_GRID[1]} AS j, avg(l_quantity) AS q FROM {{lineitem}} GROUP BY 1, 2) g"),
    "smooth": Lattice(("lineitem",), (("16 * i", 10), ("16 * j", 10), ("z", 6)), _SMOOTH),
    **{
        f"object_{t}": Lattice(("events",), (("{us:ts:2024-01-01} * 256 div 2592000000000", 8), (f"least(255, {cents('value')} * 256 div 57344)", 8), ("user_id * 256 div ((SELECT max(user_id) FROM {events}) + 1)", 8)), f"{{events}} WHERE event_type = '{t}'")
        for t in _TYPES
    },
    "object_customer": Lattice(("customer",), (("c_custkey * 256 div ((SELECT max(c_custkey) FROM {customer}) + 1)", 8), (f"({cents('c_acctbal')} + 100000) * 256 div 1100001", 8), ("c_nationkey", 5)), "{customer}"),
    "object_orders": Lattice(("orders",), (("{days:o_orderdate:1995-01-01} * 256 div 2500", 8), ("CAST(floor(o_totalprice) AS BIGINT) * 256 div 500000", 8), ("o_custkey * 256 div ((SELECT max(o_custkey) FROM {orders}) + 1)", 8)), "{orders}"),
    "object_part": Lattice(("part",), (("p_size", 6), ("CAST(round((p_retailprice - 900) * 10) AS BIGINT) * 256 div 1000", 8), ("p_partkey * 256 div ((SELECT max(p_partkey) FROM {part}) + 1)", 8)), "{part}"),
    "line_days": Lattice(("orders",), (("{days:o_orderdate:1995-01-01}", 12),), "{orders}"),
    "line_cents": Lattice(("orders",), ((cents("o_totalprice"), 26),), "{orders}"),
    "plane": Lattice(("orders",), (("{days:o_orderdate:1995-01-01}", 12), (cents("o_totalprice"), 26)), "{orders}"),
    "plane_dense": Lattice(("lineitem",), (("l_quantity", 6), ("round(l_discount * 100)", 4)), "{lineitem}"),
    "attributes": Lattice(("lineitem",), (*_LI, ("round(l_discount * 100)", 4), ("round(l_tax * 100)", 4), ("l_linenumber", 3)), "{lineitem}"),
    **{f"embedding{d}": Lattice(("embeddings",), tuple((f"least(255, greatest(0, floor((CAST({{elem:embedding:{k}}} AS DOUBLE) + 0.6) / 1.2 * 256)))", 8) for k in range(d)), "{embeddings}") for d in (2, 4)},
    "documents": Lattice(("documents", "labels"), (("coalesce(n_chars, 0)", 18), ("length(coalesce(text, '')) - length(replace(coalesce(text, ''), chr(10), ''))", 12), ("CASE lang WHEN 'de' THEN 0 WHEN 'en' THEN 1 WHEN 'es' THEN 2 ELSE 3 END", 2), ("coalesce(quality, 0)", 1), ("coalesce(toxic, 0)", 1)), "{documents} d LEFT JOIN {labels} l ON d.doc_id = l.doc_id"),
    "pages": Lattice(("pages",), (("length(html)", 16), ("length(url)", 6)), "{pages}"),
    "conversations": Lattice(("conversations",), (("turn", 3), ("length(text)", 11)), "{conversations}"),
    #: The same draws on the keys of a given table, of any size and sign; an order without a key draws as key 0.
    "uniform_keys": Lattice(("orders",), tuple((f"((coalesce(o_orderkey, 0) % {m} + {m}) * {f} + {c}) % {m} % 1024", 10) for f, c, m in ((48271, 11, 65521), (16807, 7, 65519))), "{orders}"),
    "uniform": Lattice((), (("(id * 48271 + 11) % 65521 % 1024", 10), ("(id * 16807 + 7) % 65519 % 1024", 10)), "(SELECT range AS id FROM range(4096)) r"),
}


class _Range(Lattice):
    def points(self, spark, sf_dir):
        return spark.sql(self._select().replace("(SELECT range AS id FROM range(4096)) r", "range(4096) r"))


LATTICES["uniform"] = _Range(**{k: getattr(LATTICES["uniform"], k) for k in ("tables", "axes", "source")})
TERRAIN = ("events", "lineitem", "terrain", "smooth")
OBJECTS = tuple(k for k in LATTICES if k.startswith("object_"))
