"""Cost and accuracy measures over tables."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from traincube.sources.scratch import stored


def autocorrelation(series: DataFrame, keys: list[str], step: str, y: str) -> DataFrame:
    """keys, lag and ac of each series at all lags, by one fast transform of each.

    At lag k the mean product of deviations over the n - k pairs is divided by the
    variance over all n, both about the mean of all. Constant series give no rows.
    """
    kept = series.select(*keys, F.col(step).alias("step"), F.col(y).cast("double").alias("y"))
    packed = kept.groupBy(*keys).agg(F.transform(F.array_sort(F.collect_list(F.struct("step", "y"))), lambda s: s["y"]).alias("ys"))
    out = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in packed.schema if f.name != "ys")

    def run(batches):
        for x in batches:
            own, lags, acs = [], [], []
            for i, ys in enumerate(x.column("ys")):
                v = ys.values.to_numpy(zero_copy_only=False)
                n, d = len(v), v - v.mean()
                var = float(d @ d) / n
                if var > 1e-12:
                    f = np.fft.rfft(d, 2 * n)
                    acs.append(np.fft.irfft(f * f.conj(), 2 * n)[:n] / np.arange(n, 0, -1) / var)
                    own.append(np.full(n, i))
                    lags.append(np.arange(n))
            own, lags, acs = (np.concatenate(v) if v else np.zeros(0, t) for v, t in ((own, np.int64), (lags, np.int64), (acs, float)))
            yield pa.RecordBatch.from_arrays([*(x.column(k).take(pa.array(own)) for k in keys), pa.array(lags), pa.array(acs)], [*keys, "lag", "ac"])

    return packed.mapInArrow(run, out + ", lag long, ac double")


def nrmse(original: DataFrame, other: DataFrame, keys: list[str], by: list[str] = []) -> DataFrame:  # noqa: B006
    """Root mean square error over all cells, or those of each ``by``, and relative to the range and the norm; both have keys and val."""
    both = original.select(*keys, F.col("val").alias("x")).join(other.select(*keys, F.col("val").alias("y")), keys)
    e2 = F.sum(F.pow(F.col("x") - F.col("y"), 2))
    span = F.max("x") - F.min("x")
    return both.groupBy(*by).agg(F.sqrt(e2 / F.count("*")).alias("rmse"), F.when(span > 0, F.sqrt(e2 / F.count("*")) / span).alias("nrmse"), F.when(F.sum(F.col("x") * F.col("x")) > 0, F.sqrt(e2 / F.sum(F.col("x") * F.col("x")))).otherwise(0.0).alias("rel_fro"))


def spectral_norm(cells: DataFrame, rounds: int = 40) -> float:
    """The largest singular value of a matrix of cells (i, j, val) by power iteration; only norms reach the driver.

    Two products of matrix and vector a round, each a join and a sum by key; every vector is a stored table.
    """
    v = stored(cells.select("j").distinct().select("j", F.hash("j").cast("double").alias("x")))
    sigma = 0.0
    for _ in range(rounds):
        size = v.agg(F.sqrt(F.sum(F.col("x") * F.col("x")))).first()[0]
        if not size:
            return 0.0
        u = stored(cells.join(v, "j").groupBy("i").agg((F.sum(F.col("val") * F.col("x")) / size).alias("y")))
        sigma = u.agg(F.sqrt(F.sum(F.col("y") * F.col("y")))).first()[0]
        v = stored(cells.join(u, "i").groupBy("j").agg(F.sum(F.col("val") * F.col("y")).alias("x")))
    return float(sigma)


def report(trains: DataFrame, dataset: str, order_bytes: int = 0) -> DataFrame:
    """Ratios, errors, ranks and bytes by variable and level, with and without the bytes of the order tables; trains with numel."""
    ceiling = F.max(F.aggregate("modes", F.lit(1.0), lambda s, n: s * n) / F.aggregate("modes", F.lit(0.0), lambda s, n: s + n))
    out = overall_ratio(trains, "variable", "level").join(trains.groupBy("variable", "level").agg(ceiling.alias("ratio_ceiling"), F.sum("n_original").alias("n")), ["variable", "level"])
    # The order is one for all variables; each carries it whole here, as each needs it to be read alone.
    with_order = 8 * F.col("n") / (F.col("train_bytes") + order_bytes)
    return out.select(F.lit(dataset).alias("dataset"), "*", F.lit(order_bytes).cast("long").alias("order_bytes"), with_order.alias("ratio_with_order"))


def to_markdown(rows: DataFrame, digits: int = 3) -> str:
    """A small report as a Markdown table."""
    show = lambda x: f"{x:.{digits}g}" if isinstance(x, float) else str(x)
    body = [rows.columns, ["-"] * len(rows.columns), *([show(x) for x in r] for r in rows.collect())]
    return "\n".join("| " + " | ".join(r) + " |" for r in body)


def overall_ratio(trains: DataFrame, *keys: str) -> DataFrame:
    """Pooled ratio, all entries by all numbers, and the mean of the trains' ratios; trains with numel."""
    return trains.groupBy(*keys).agg(
        F.count("*").alias("segments"), F.max("steps").alias("steps"), (F.sum("n_original") / F.sum("numel")).alias("ratio_pooled"), F.avg(F.col("n_original") / F.col("numel")).alias("ratio_mean"),
        (F.sum("n") / F.sum("numel")).alias("ratio_padded"), F.max("nrmse").alias("max_nrmse"), F.max("rel_fro").alias("max_rel_fro"), F.max(F.array_max("ranks")).alias("max_rank"), (8 * F.sum("numel")).alias("train_bytes"),
    )
