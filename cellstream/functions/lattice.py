"""Lattice mapping: table columns to integer axes and back."""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class AxisSpec:
    """One axis. Kinds: int, decimal (10**-step units), uniform (quantiser), ieee (order-preserving bits of
    single precision, to which doubles are rounded), tick (microseconds
    per tick since ``lo``), date, bool, dict (``values``)."""

    name: str
    source: str
    kind: str = "int"
    lo: float = 0
    hi: float = 0
    bits: int = 0
    step: int = 0
    on_null: str = "error"
    values: tuple = ()


@dataclass(frozen=True)
class LatticeSpec:
    axes: tuple[AxisSpec, ...]

    @property
    def d(self) -> int:
        return len(self.axes)

    @property
    def bits(self) -> tuple[int, ...]:
        return tuple(a.bits for a in self.axes)

    @property
    def q(self) -> int:
        return sum(self.bits)

    def to_json(self) -> str:
        return json.dumps([asdict(a) for a in self.axes], sort_keys=True)

    @staticmethod
    def from_json(text: str) -> LatticeSpec:
        return LatticeSpec(tuple(AxisSpec(**{**a, "values": tuple(a["values"])}) for a in json.loads(text)))


def _raw(a: AxisSpec) -> Column:
    c = F.col(a.source)
    if a.kind == "decimal":
        return F.round(c * 10**a.step).cast("long")
    if a.kind == "ieee":
        return _ieee(c.cast("double"))
    if a.kind == "tick":
        return F.expr(f"timestampdiff(MICROSECOND, timestamp_ntz'1970-01-01', cast({a.source} as timestamp_ntz)) div {max(1, a.step)}")
    if a.kind == "date":
        return F.datediff(c, F.lit("1970-01-01")).cast("long")
    if a.kind == "bool":
        return c.cast("boolean").cast("long")
    if a.kind == "dict":
        return F.array_position(F.array(*[F.lit(v) for v in a.values]), c).cast("long") - 1
    return c.cast("long")


def _ieee(c: Column) -> Column:
    """Order-preserving whole numbers of finite doubles at single precision: sign, exponent and fraction as one number."""
    size = F.abs(c)
    exponent = F.greatest(F.lit(-126.0), F.floor(F.log2(F.when(size > 0, size).otherwise(F.lit(1e-45)))))
    code = (F.lit(1 << 23) * (exponent + 126) + F.floor(size / F.pow(F.lit(2.0), exponent) * (1 << 23))).cast("long")
    return F.when(c < 0, -code).otherwise(code)


def infer_lattice(df: DataFrame, axes: list[AxisSpec], bits: dict[str, int] | None = None, lossless: bool = True) -> LatticeSpec:
    """Bounds and bits of each axis by one aggregate over the table (2 numbers an axis come to the driver)."""
    asked = [a for a in axes if a.kind not in ("dict", "bool")]
    values = {}
    if asked:
        row = df.agg(*[f(F.col(a.source).cast("double") if a.kind == "uniform" else _raw(a)).alias(f"{n}{k}") for k, a in enumerate(asked) for n, f in (("lo", F.min), ("hi", F.max))]).first()
        values = {a.name: (row[f"lo{k}"] or 0, row[f"hi{k}"] or 0) for k, a in enumerate(asked)}
    out = []
    for a in axes:
        if a.kind == "dict":
            out.append(AxisSpec(**{**asdict(a), "bits": max(0, (len(a.values) - 1).bit_length())}))
        elif a.kind == "bool":
            out.append(AxisSpec(**{**asdict(a), "bits": 1}))
        else:
            lo, hi = values[a.name]
            wanted = (bits or {}).get(a.name, a.bits)
            if a.kind != "uniform" and not lossless and wanted:
                a = AxisSpec(**{**asdict(a), "kind": "uniform"})
            width = wanted if a.kind == "uniform" else int(hi - lo).bit_length()
            out.append(AxisSpec(**{**asdict(a), "lo": lo, "hi": hi, "bits": width}))
    return LatticeSpec(tuple(out))


def to_lattice(df: DataFrame, spec: LatticeSpec) -> DataFrame:
    """Columns a0.. of whole numbers; null axis values are an error, dropped, or a flag axis after the others."""
    columns, drop = [], []
    for k, a in enumerate(spec.axes):
        if a.kind == "uniform":
            width = (a.hi - a.lo) or 1
            value = F.least(F.lit((1 << a.bits) - 1), F.floor((F.col(a.source).cast("double") - a.lo) / width * (1 << a.bits))).cast("long")
        elif a.kind in ("dict", "bool"):
            value = _raw(a)
        else:
            value = _raw(a) - int(a.lo)
        missing = F.col(a.source).isNull()
        # A value outside the axis (below lo, or not in the dictionary) would name a wrong cell.
        strange = ~missing & ((value < 0) | (value >= (1 << a.bits)))
        value = F.when(strange, F.raise_error(F.concat(F.lit(f"value outside axis {a.name}: "), F.col(a.source).cast("string"))).cast("long")).otherwise(value)
        if a.on_null == "error":
            value = F.when(missing, F.raise_error(F.lit(f"null in axis {a.name}")).cast("long")).otherwise(value)
        elif a.on_null == "drop":
            drop.append(~missing)
        else:
            value = F.coalesce(value, F.lit(0).cast("long"))
        columns.append(value.alias(f"a{k}"))
    flags = [F.col(a.source).isNull().cast("long").alias(f"a{spec.d + j}") for j, a in enumerate(x for x in spec.axes if x.on_null == "flag")]
    for keep in drop:
        df = df.where(keep)
    return df.select(*columns, *flags)


def from_lattice(df: DataFrame, spec: LatticeSpec, at: str = "center") -> DataFrame:
    """User units again; quantised axes at the cell's centre or its low corner."""
    out = []
    for k, a in enumerate(spec.axes):
        c = F.col(f"a{k}")
        if a.kind == "uniform":
            value = F.lit(a.lo) + (c + (0.5 if at == "center" else 0.0)) * ((a.hi - a.lo) / (1 << a.bits))
        elif a.kind == "decimal":
            value = (c + int(a.lo)) / 10**a.step
        elif a.kind == "dict":
            value = F.element_at(F.array(*[F.lit(v) for v in a.values]), c.cast("int") + 1)
        elif a.kind == "bool":
            value = c == 1
        elif a.kind == "date":
            value = F.date_add(F.lit("1970-01-01").cast("date"), (c + int(a.lo)).cast("int"))
        elif a.kind == "tick":
            value = F.timestamp_micros((c + int(a.lo)) * max(1, a.step))
        elif a.kind == "ieee":
            code = c + int(a.lo)
            size, top = F.abs(code), F.lit(1 << 23)
            exponent = F.floor(size / top) - 1
            value = F.when(size < (1 << 23), F.signum(code) * size * F.pow(F.lit(2.0), F.lit(-149.0))).otherwise(F.signum(code) * (size - exponent * (1 << 23)) / (1 << 23) * F.pow(F.lit(2.0), exponent - 126))
        else:
            value = c + int(a.lo)
        out.append(value.alias(a.name))
    return df.select(*out, *[c for c in df.columns if not c.startswith("a") or not c[1:].isdigit()])
