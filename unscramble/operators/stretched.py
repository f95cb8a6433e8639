"""Windows over the points of panels, for all sensors at once.

A panel's rows are dealt to stretches that lead in as many points as the windows need. A stretch is a matrix of points and
sensors in one task, cut in tiles that stay in a processor's cache; readings are taken up in the order that a window over a
sensor's rows has, so that sums are the same to the last bit.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, StructField, StructType
from pyspark.sql.window import Window

from unscramble.scratch import few
from unscramble.sources import panels

LENGTH = 1 << 14  # points of a stretch, if panels.STRETCH isn't less
TILE = 1024
Compute = Callable[["Tile"], dict[str, np.ndarray]]


class Tile:
    """Points n with their readings x (NaN where NULL), known (not NULL), those of the points around them that a window can
    reach, and models (arrays by name)."""

    def __init__(self, x: np.ndarray, known: np.ndarray, n: np.ndarray, before: int, models: dict[str, np.ndarray]):
        self.x, self.known, self.n, self.points, self.before, self.models = x, known, n, len(n), before, models
        self.whole = bool(known.all())

    def at(self, step: int) -> tuple[np.ndarray, np.ndarray]:
        """Readings so many points later (or before), and which are known."""
        place = slice(self.before + step, self.before + step + self.points)
        return self.x[place], self.known[place]

    def unset(self, name: str) -> np.ndarray:
        """Sensors whose model lacks the value."""
        return self.models[f"{name} unset"]

    def total(self, first: int, last: int, value: Callable[[np.ndarray], np.ndarray] | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Sum (from 0) of known readings, or of their values, between two steps, and their number."""
        out, count = np.zeros((self.points, self.x.shape[1])), np.zeros((self.points, self.x.shape[1]))
        for step in range(first, last + 1):
            x, known = self.at(step)
            v = x if value is None else value(x)
            out += v if self.whole else np.where(known, v, 0.0)
            count += 1 if self.whole else known
        return out, count


def above(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """a > b, with NaN above all else."""
    return (a > b) | (np.isnan(a) & ~np.isnan(b))


def null(values: np.ndarray, where: np.ndarray) -> np.ma.MaskedArray:
    return np.ma.MaskedArray(values, where)


def _models(rows: list[dict], width: int) -> dict[str, np.ndarray]:
    rows = [r for r in rows if r["m"] < width]
    out = {c: np.full(width, np.nan) for c in (rows[0] if rows else {}) if c != "m"}
    out |= {f"{c} unset": np.ones(width, bool) for c in out} | {"has": np.zeros(width, bool)}
    for r in rows:
        out["has"][r["m"]] = True
        for c, v in r.items():
            if c != "m" and v is not None:
                out[c][r["m"]], out[f"{c} unset"][r["m"]] = v, False
    return out


def _computed(table: pa.Table, rows: list[dict] | None, before: int, after: int, kinds: dict[str, pa.DataType], compute: Compute, plain: bool = False) -> pa.Table:
    table = table.take(np.argsort(table["n"].to_numpy(), kind="stable"))
    lead, ns = table["_lead"].to_numpy(), table["n"].to_numpy()
    own, kept = np.flatnonzero(~lead), table.filter(pa.array(~lead)).drop_columns(["_s", "_lead"])
    lists = table["x"].combine_chunks()
    lengths, flat = lists.value_lengths().to_numpy(), lists.flatten()
    width = int(lengths[0]) if len(lengths) else 0
    if (lengths != width).any():
        raise ValueError("points of an equipment hold different numbers of sensors")
    x, known = flat.to_numpy(zero_copy_only=False).reshape(-1, width), np.asarray(flat.is_valid()).reshape(-1, width)
    pad = lambda v, fill: np.concatenate([np.full((before, width), fill), v, np.full((after, width), fill)])
    x, known = pad(x, np.nan), pad(known, False)
    models = {"has": np.ones(width, bool)} if rows is None else _models(rows, width)
    parts: dict[str, list[np.ma.MaskedArray]] = {name: [] for name in kinds}
    first, stop = (own[0], own[-1] + 1) if len(own) else (0, 0)
    with np.errstate(all="ignore"):
        for at in range(first, stop, TILE) if width and models["has"].any() else ():
            n = ns[at : min(at + TILE, stop)]
            reach = slice(at, at + len(n) + before + after)
            for name, v in compute(Tile(x[reach], known[reach], n, before, models)).items():
                parts[name].append(v)
    if not any(parts.values()):
        kept = kept.slice(0, 0)
    fields = []
    for name, kind in kinds.items():
        v = np.ma.concatenate(parts[name]) if parts[name] else np.ma.MaskedArray(np.zeros((0, width)))
        fields.append(pa.array(v.data.ravel(), kind, mask=np.ma.getmaskarray(v).ravel()))
    if plain:
        has = np.flatnonzero(models["has"])
        places = pa.array((np.arange(len(kept))[:, None] * width + has).ravel())
        ends = pa.array((np.arange(len(kept) + 1) * len(has)).astype(np.int32))
        kept = kept.set_column(kept.schema.get_field_index("x"), "x", pa.ListArray.from_arrays(ends, kept["x"].combine_chunks().flatten().take(places)))
        for name, v in zip(kinds, fields, strict=True):
            kept = kept.append_column(name, pa.ListArray.from_arrays(ends, v.take(places)))
        return kept
    lacks = pa.array(np.tile(~models["has"], len(kept)))
    cells = pa.StructArray.from_arrays(fields, list(kinds), mask=lacks)
    ends = pa.array((np.arange(len(kept) + 1) * width).astype(np.int32))
    return kept.append_column("_out", pa.ListArray.from_arrays(ends, cells))


def over_stretches(panel: DataFrame, before: int, after: int, fields: dict[str, str], compute: Compute, models: DataFrame | None = None, plain: bool = False) -> DataFrame:
    """The panel with what compute gives for its readings, from windows that reach so many points back and ahead: the column
    _out, an array of structs of fields (name: double or boolean). models: long rows (eq_id, m, ...); a sensor without a
    model has NULL, an equipment without any no rows. plain: an array column for each field in the place of _out, and sensors without
    a model left out, of x too."""
    schema = StructType.fromDDL(", ".join(f"{name} {kind}" for name, kind in fields.items()))
    kinds = {name: {"double": pa.float64(), "boolean": pa.bool_()}[kind] for name, kind in fields.items()}
    more = [StructField(f.name, ArrayType(f.dataType)) for f in schema.fields] if plain else [StructField("_out", ArrayType(schema))]
    out = StructType([*panel.schema.fields, *more])
    rows = panels.stretches(panel.filter("x IS NOT NULL"), before, after, min(LENGTH, panels.STRETCH))
    keys = ["eq_id", "_s"]
    if models is None:
        return rows.groupBy(*keys).applyInArrow(lambda table: _computed(table, None, before, after, kinds, compute, plain), out)
    fits = few(models.groupBy("eq_id").agg(F.collect_list(F.struct(*[c for c in models.columns if c != "eq_id"])).alias("_fit")), "models")
    fits = rows.select(F.col("eq_id").alias("_e"), F.col("_s").alias("_t")).distinct().join(fits, F.col("_e") == F.col("eq_id")).select("_e", "_t", "_fit")

    def run(table: pa.Table, fit: pa.Table) -> pa.Table:
        return _computed(table, fit["_fit"][0].as_py() if len(fit) else [], before, after, kinds, compute, plain)

    return rows.groupBy(*keys).cogroup(fits.groupBy("_e", "_t")).applyInArrow(run, out)


def long(wide: DataFrame) -> DataFrame:
    """A row for each reading of what over_stretches gives, beside its sensor m; those without a model are left out."""
    first = [c for c in wide.columns if c not in ("x", "_out")]
    rows = wide.select(*first, F.posexplode(F.arrays_zip("x", "_out")).alias("m", "_c")).filter("_c._out IS NOT NULL")
    return rows.select(*first, "m", F.col("_c.x").alias("x"), "_c._out.*")


def with_last(panel: DataFrame) -> DataFrame:
    """Long rows with each sensor's reading before (p)."""
    w = Window.partitionBy("eq_id", "_s").orderBy("n")
    rows = panels.stretches(panel.filter("x IS NOT NULL"), 1).withColumn("_p", F.lag("x").over(w)).filter("NOT _lead").drop("_s", "_lead")
    return panels.to_long(rows).withColumn("p", F.get("_p", F.col("m"))).drop("_p")
