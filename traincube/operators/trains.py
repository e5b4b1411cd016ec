"""Trains as rows: one row holds a whole train, its statistics and its error bound.

``vmin``, ``vmax`` and ``fro2`` (the squared norm) are those of the array that was
compressed, over the ``n_original`` entries that are not padding for the first two.
After arithmetic the array is not at hand: ``fro2`` is then that of the train itself, the
range is null unless it follows, and ``err_abs`` bounds the distance to the same
arithmetic on the arrays. ``err_measured`` is null where no array was there to measure against.
``block`` numbers the blocks of entities of a segment that is too large for one train; else it is 0.
"""

from collections.abc import Callable, Iterator
from math import prod, sqrt

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from traincube.functions import kernels as K

_CORE = pa.struct([("k", pa.int32()), ("r_left", pa.int32()), ("n", pa.int32()), ("r_right", pa.int32()), ("core", pa.list_(pa.float64()))])
ARROW = pa.schema([
    ("variable", pa.string()), ("level", pa.int32()), ("seg", pa.int64()), ("modes", pa.list_(pa.int32())), ("ranks", pa.list_(pa.int32())), ("cores", pa.list_(_CORE)),
    ("n", pa.int64()), ("n_original", pa.int64()), ("vmin", pa.float64()), ("vmax", pa.float64()), ("fro2", pa.float64()), ("err_abs", pa.float64()), ("steps", pa.int32()), ("err_measured", pa.float64()), ("block", pa.int32()),
])
SCHEMA = (
    "variable string, level int, seg long, modes array<int>, ranks array<int>, cores array<struct<k: int, r_left: int, n: int, r_right: int, core: array<double>>>, "
    "n long, n_original long, vmin double, vmax double, fro2 double, err_abs double, steps int, err_measured double, block int"
)


def pack(cores: K.Train, **row) -> dict:
    parts = [{"k": k, "r_left": c.shape[0], "n": c.shape[1], "r_right": c.shape[2], "core": c.ravel(order="F")} for k, c in enumerate(cores)]
    return {"block": 0} | row | {"modes": [c.shape[1] for c in cores], "ranks": K.ranks(cores), "cores": parts, "n": row.get("n", prod(c.shape[1] for c in cores))}


def unpack(row: dict) -> K.Train:
    parts = sorted(row["cores"], key=lambda c: c["k"])
    return [np.asarray(c["core"], float).reshape(c["r_left"], c["n"], c["r_right"], order="F") for c in parts]


def rows_of(t: pa.Table | pa.RecordBatch) -> Iterator[dict]:
    """Rows one at a time; cores stay arrays, as lists of numbers would take many times their bytes."""
    whole = {f.name: t.column(f.name) for f in t.schema if pa.types.is_list(f.type) and pa.types.is_struct(f.type.value_type)}
    rest = t.select([c for c in t.schema.names if c not in whole])
    for i in range(t.num_rows):
        row = rest.slice(i, 1).to_pylist()[0] if rest.num_columns else {}
        for name, column in whole.items():
            parts = column[i].values
            row[name] = parts if parts is None else [
                {"k": k, "r_left": a, "n": n, "r_right": b, "core": core.values.to_numpy(zero_copy_only=False)}
                for k, a, n, b, core in zip(*(parts.field(c).to_pylist() for c in ("k", "r_left", "n", "r_right")), parts.field("core"))
            ]
        yield row


def table(rows: list[dict]) -> pa.Table:
    return pa.Table.from_pylist(rows, ARROW)


def compressed(x: np.ndarray, modes: list[int], budget, share: float = 1.0, original: np.ndarray | None = None, max_rank: int | None = None, measure: bool = False, **row) -> dict:
    """The row of an array's train within ``share`` of a budget; original: the entries that are not padding.

    With max_rank the error may pass the budget; ``err_abs`` says by how much. measure: expand the train and measure its error.
    """
    own = x if original is None else original
    vmin, vmax, norm = float(own.min()), float(own.max()), float(np.linalg.norm(x))
    allowed = budget.absolute(own.size, vmin, vmax, float(np.linalg.norm(own))) * share
    cores, lost = K.decompose(x, modes, allowed / norm if norm else 0.0, max_rank)
    measured = K.distance(cores, x) if measure else None
    return pack(cores, n=x.size, n_original=own.size, vmin=vmin, vmax=vmax, fro2=norm**2, err_abs=sqrt(lost), err_measured=measured, **row)


def restated(row: dict, cores: K.Train, err: float, span: tuple[float, float] | None = None) -> dict:
    """The row of a train that arithmetic made from that of ``row``, with statistics of its own."""
    n = prod(c.shape[1] for c in cores)
    whole = row["n_original"] == row["n"]
    original = n if whole else row["n_original"] if n == row["n"] else None
    low, high = span or (None, None)
    return pack(cores, variable=row["variable"], level=row["level"], seg=row["seg"], steps=row["steps"], block=row["block"], n=n, n_original=original, vmin=low, vmax=high, fro2=K.dot(cores, cores), err_abs=err)


Changed = K.Train | tuple[K.Train, float]


def _parted(out: Changed) -> tuple[K.Train, float]:
    return out if isinstance(out, tuple) else (out, 0.0)


def map_trains(trains: DataFrame, change: Callable[[K.Train], Changed], gain: float | Callable[[list[int]], float] = 1.0, span: Callable[[float, float], tuple[float, float]] | None = None) -> DataFrame:
    """A function of each train by itself.

    change returns a train, or a train and the squared error that rounding made. gain: how
    many times it can enlarge the norm of an error, or that by the modes. span: least and
    greatest entry after it, where these follow from those before.
    """

    def run(batches):
        for x in batches:
            for r in rows_of(x):
                yield pa.RecordBatch.from_pylist([changed(r, change, gain, span)], ARROW)

    return trains.mapInArrow(run, SCHEMA)


def changed(r: dict, change: Callable[[K.Train], Changed], gain: float | Callable[[list[int]], float] = 1.0, span: Callable[[float, float], tuple[float, float]] | None = None) -> dict:
    """One row of map_trains()."""
    cores, lost = _parted(change(unpack(r)))
    by = gain(r["modes"]) if callable(gain) else gain
    return restated(r, cores, by * r["err_abs"] + sqrt(lost), span(r["vmin"], r["vmax"]) if span and r["vmin"] is not None else None)


def scaled(trains: DataFrame, c: float) -> DataFrame:
    return map_trains(trains, *_scaling(c))


def scaled_row(r: dict, c: float) -> dict:
    """One row of scaled()."""
    return changed(r, *_scaling(c))


def _scaling(c: float):
    return lambda t: K.scale(t, c), abs(c), lambda a, b: (min(a * c, b * c), max(a * c, b * c))


def rounded(trains: DataFrame, tau: float) -> DataFrame:
    """Smaller ranks at a relative error of tau on top of what is there."""
    return map_trains(trains, lambda t: K.recompress(t, tau))


def contracted(trains: DataFrame, weights: dict[int, np.ndarray]) -> DataFrame:
    """Weighted sums over some modes, which disappear; an error grows by the norms of the weights at most."""
    gain = prod(float(np.linalg.norm(w)) for w in weights.values())
    return map_trains(trains, lambda t: K.contract(t, weights), gain)


def _sum_bound(a: dict, b: dict) -> float:
    return a["err_abs"] + b["err_abs"]


def product_bound(a: dict, b: dict) -> float:
    """Entries are at most the norm, so each error grows by the other factor's norm at most."""
    return (sqrt(a["fro2"]) + a["err_abs"]) * b["err_abs"] + (sqrt(b["fro2"]) + b["err_abs"]) * a["err_abs"]


def pair_trains(a: DataFrame, b: DataFrame, combine: Callable[[K.Train, K.Train], Changed], bound: Callable[[dict, dict], float] = _sum_bound) -> DataFrame:
    """A function of two trains of the same variable, segment and block; bound: of the errors' effect, from both rows."""
    other = b.select("variable", "seg", "block", *(F.col(c).alias(f"_{c}") for c in ("cores", "fro2", "err_abs")))

    def run(batches):
        for x in batches:
            for r in rows_of(x):
                yield pa.RecordBatch.from_pylist([paired(r, {c: r.pop(f"_{c}") for c in ("cores", "fro2", "err_abs")}, combine, bound)], ARROW)

    return a.join(other, ["variable", "seg", "block"]).select(*a.columns, "_cores", "_fro2", "_err_abs").mapInArrow(run, SCHEMA)


def paired(a: dict, b: dict, combine: Callable[[K.Train, K.Train], Changed], bound: Callable[[dict, dict], float] = _sum_bound) -> dict:
    """One row of pair_trains()."""
    cores, lost = _parted(combine(unpack(a), unpack(b)))
    return restated(a, cores, bound(a, b) + sqrt(lost))


def product(a: DataFrame, b: DataFrame, tau: float) -> DataFrame:
    """Entry by entry, rounded, as ranks multiply."""
    return pair_trains(a, b, lambda x, y: K.recompress(K.hadamard(x, y), tau), product_bound)


def multiplied(a: dict, b: dict, tau: float) -> dict:
    """One row of product()."""
    return paired(a, b, lambda x, y: K.recompress(K.hadamard(x, y), tau), product_bound)


def pair_numbers(a: DataFrame, b: DataFrame, measure: Callable[[K.Train, K.Train], float]) -> DataFrame:
    """variable, seg, block and a number of two trains: inner product, distance."""
    other = b.select("variable", "seg", "block", F.col("cores").alias("cores_b"))

    def run(batches):
        for x in batches:
            for r in rows_of(x):
                yield pa.RecordBatch.from_pylist([{"variable": r["variable"], "seg": r["seg"], "block": r["block"], "val": float(measure(unpack(r), unpack({"cores": r["cores_b"]})))}], _NUMBER)

    return a.join(other, ["variable", "seg", "block"]).select("variable", "seg", "block", "cores", "cores_b").mapInArrow(run, "variable string, seg long, block int, val double")


_NUMBER = pa.schema([("variable", pa.string()), ("seg", pa.int64()), ("block", pa.int32()), ("val", pa.float64())])


def pieces(cores: K.Train, most: int) -> Iterator[tuple[int, np.ndarray]]:
    """Entries of a train, in pieces of at most ``most`` where one index of the last modes has no more: the first index and the entries of each."""
    count = prod(c.shape[1] for c in cores)
    if count <= most or len(cores) == 1:
        yield 0, K.expand(cores)
        return
    size = count // cores[-1].shape[1]
    for j in range(cores[-1].shape[1]):
        head = [*cores[:-2], np.tensordot(cores[-2], cores[-1][:, j], (2, 0))]
        for first, v in pieces(head, most):
            yield j * size + first, v


def expand(trains: DataFrame, most: int = 1 << 20) -> DataFrame:
    """variable, seg, block, idx and val of every entry.

    A task makes about ``most`` entries at a time, so that none holds a whole large array.
    """

    def cells(batches):
        for x in batches:
            for r in rows_of(x):
                yield from expanded(r, most)

    return trains.select("variable", "seg", "block", "cores").mapInArrow(cells, EXPANDED)


EXPANDED = "variable string, seg long, block int, idx long, val double"


def expanded(r: dict, most: int = 1 << 20) -> Iterator[pa.RecordBatch]:
    """One row of expand()."""
    for first, v in pieces(unpack(r), most):
        n = len(v)
        yield pa.RecordBatch.from_pydict({"variable": pa.array([r["variable"]] * n, pa.string()), "seg": pa.array(np.full(n, r["seg"], np.int64)), "block": pa.array(np.full(n, r["block"], np.int32)), "idx": pa.array(first + np.arange(n)), "val": pa.array(v)})


def light(r: dict) -> Iterator[pa.RecordBatch]:
    """A row of SCHEMA without its cores, for what only asks for statistics."""
    yield pa.RecordBatch.from_pylist([r | {"cores": None}], ARROW)


def read_entries(trains: DataFrame, points: DataFrame, deals: int = 8) -> DataFrame:
    """points (variable, seg, idx, ..., and block where trains have blocks) with val.

    A train and its points meet in one task, where all entries are contracted together.
    The points of a train are dealt over ``deals`` tasks, and the train, which is small, goes to each.
    """
    keys = ["variable", "seg", *(["block"] if "block" in points.columns else []), "_deal"]
    own = trains.select(*keys[:-1], F.explode(F.sequence(F.lit(0), F.lit(deals - 1))).alias("_deal"), "cores")
    dealt = points.withColumn("_deal", F.pmod(F.xxhash64("idx"), F.lit(deals)).cast("int"))
    names = points.columns

    def read(some: pa.Table, train: pa.Table) -> pa.Table:
        if not train.num_rows:
            return some.select(names).slice(0, 0).append_column("val", pa.array([], pa.float64()))
        cores = unpack(next(rows_of(train.select(["cores"]))))
        rest, digits = some.column("idx").to_numpy(), []
        for c in cores:
            rest, d = np.divmod(rest, c.shape[1])
            digits.append(d)
        return some.select(names).append_column("val", pa.array(K.entries(cores, np.stack(digits, 1))))

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in points.schema) + ", val double"
    return dealt.groupBy(*keys).cogroup(own.groupBy(*keys)).applyInArrow(read, schema)


def numel(trains: DataFrame) -> DataFrame:
    """trains with ``numel``, the numbers in all cores, and the error bound as NRMSE (null where the range is unknown) and relative error."""
    size = F.aggregate(F.transform("modes", lambda n, i: F.get("ranks", i).cast("long") * n * F.get("ranks", i + 1)), F.lit(0).cast("long"), lambda s, c: s + c)
    return _relative(trains.withColumn("numel", size))


def _relative(t: DataFrame) -> DataFrame:
    span = F.col("vmax") - F.col("vmin")
    return t.withColumn("nrmse", F.when(span > 0, F.col("err_abs") / (F.sqrt("n_original") * span)).when((span == 0) & (F.col("err_abs") == 0), 0.0)).withColumn("rel_fro", F.when(F.col("fro2") > 0, F.col("err_abs") / F.sqrt("fro2")).otherwise(0.0))


def pooled(trains: DataFrame) -> DataFrame:
    """One row for each variable, level and segment: the trains of its blocks side by side; trains with numel. modes and ranks are those of the block with the largest rank."""
    widest = F.array_max("ranks")
    out = trains.groupBy("variable", "level", "seg").agg(
        *(F.sum(c).alias(c) for c in ("n", "n_original", "fro2", "numel")), F.min("vmin").alias("vmin"), F.max("vmax").alias("vmax"), F.max("steps").alias("steps"),
        F.when(F.count("*") == 1, F.max("err_abs")).otherwise(F.sqrt(F.sum(F.col("err_abs") * F.col("err_abs")))).alias("err_abs"), F.max_by("modes", widest).alias("modes"), F.max_by("ranks", widest).alias("ranks"),
    )
    return _relative(out)


def valid(trains: DataFrame) -> DataFrame:
    """Trains whose neighbouring cores fit and whose outer ranks are 1."""
    c = F.col("cores")
    fit = F.forall(F.sequence(F.lit(1), F.size(c)), lambda k: F.element_at(c, k)["r_left"] == F.when(k == 1, 1).otherwise(F.element_at(c, F.greatest(k - 1, F.lit(1)))["r_right"]))
    return trains.where(fit & (F.element_at(c, -1)["r_right"] == 1))
