"""Cost models of lanes from probe tables: probe(kind, stage, size, rep, seconds) -> thresholds, fits, predictions.

All steps are table operations on a few rows, so any probe table (measured or synthetic) can be used, and the same SQL runs elsewhere.
Forms: 'line' time = a * size + b; 'log' time = size / (a * ln(size) + b); 'sqrtlog' time = size / (a * sqrt(ln(size)) + b);
'sqrt' time = size / (a * sqrt(size) + b). The curve forms are fitted to speed = size / time by least squares.
"""

from __future__ import annotations

import math
import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from blockmf.functions.ids import PRIME, mixed
from blockmf.session import cut

PROBE = "kind string, stage string, size long, rep int, seconds double"
FORMS = {"line": "size", "log": "ln(size)", "sqrtlog": "sqrt(ln(size))", "sqrt": "sqrt(size)"}


def probe_parts(ratings: DataFrame, parts: int, seed: int = 1, spacing: str = "equal") -> DataFrame:
    """ratings with part 0 .. parts - 1 by an arithmetic hash. spacing 'equal': equal parts (prefixes grow by equal steps); 'geometric':
    prefixes double."""
    h = F.expr(f"((u * 7919 + v * 104729 + {seed}) % 1000003)")
    if spacing == "equal":
        return ratings.withColumn("part", F.floor(h * parts / 1000003).cast("int"))
    share = (h + 1) / 1000003
    return ratings.withColumn("part", F.greatest(F.lit(0), parts - 1 + F.ceil(F.log2(share))).cast("int"))


def prefix_sizes(parted: DataFrame, scheme: str = "prefix") -> DataFrame:
    """part, size: of each part alone ('disjoint'), or of all parts up to it ('prefix')."""
    alone = parted.groupBy("part").agg(F.count(F.lit(1)).alias("size"))
    if scheme == "disjoint":
        return alone
    return alone.select("part", F.sum("size").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, 0)).alias("size"))


def average(probe: DataFrame) -> DataFrame:
    return probe.groupBy("kind", "stage", "size").agg(F.avg("seconds").alias("seconds"))


def throughput(probe: DataFrame) -> DataFrame:
    """kind, stage, size, speed."""
    return average(probe).withColumn("speed", F.col("size") / F.col("seconds"))


def find_tau(probe: DataFrame, tol: float = 0.02) -> DataFrame:
    """kind, stage, tau: the earlier size of the first neighbouring pair of sizes whose speeds differ by less than tol; the largest size if there is none."""
    w = Window.partitionBy("kind", "stage").orderBy("size")
    steps = throughput(probe).withColumn("next", F.lead("speed").over(w))
    flat = F.min(F.when(F.abs(F.col("next") / F.col("speed") - 1) < tol, F.col("size")))
    return steps.groupBy("kind", "stage").agg(F.coalesce(flat, F.max("size")).alias("tau"))


def fit_line(probe: DataFrame) -> DataFrame:
    """kind, stage, form, a, b, r2."""
    p = average(probe)
    return p.groupBy("kind", "stage").agg(F.lit("line").alias("form"), F.regr_slope("seconds", "size").alias("a"), F.regr_intercept("seconds", "size").alias("b"), F.regr_r2("seconds", "size").alias("r2"))


def fit_piecewise(probe: DataFrame, curve: str, tol: float = 0.02) -> DataFrame:
    """kind, stage, tau, form, a, b (curve up to tau), line_a, line_b (line from tau on), least (probed size). A stage without two points above tau keeps
    the speed that it has at tau."""
    x = F.expr(FORMS[curve])
    p = throughput(probe).join(F.broadcast(find_tau(probe, tol)), ["kind", "stage"]).withColumn("x", x)
    low, high = F.col("size") <= F.col("tau"), F.col("size") >= F.col("tau")
    fit = p.groupBy("kind", "stage", "tau").agg(
        F.regr_slope(F.when(low, F.col("speed")), F.when(low, F.col("x"))).alias("a"),
        F.regr_intercept(F.when(low, F.col("speed")), F.when(low, F.col("x"))).alias("b"),
        F.regr_slope(F.when(high, F.col("seconds")), F.when(high, F.col("size").cast("double"))).alias("la"),
        F.regr_intercept(F.when(high, F.col("seconds")), F.when(high, F.col("size").cast("double"))).alias("lb"),
        F.max(F.when(F.col("size") == F.col("tau"), F.col("seconds"))).alias("at_tau"),
        F.count_if(high).alias("n_high"),
        F.min("size").alias("least"),
    )
    enough, steady = F.col("n_high") >= 2, F.col("a").isNull()  # one point up to tau: no curve, the speed there
    first = [F.when(steady, F.lit(0.0)).otherwise(F.col("a")).alias("a"), F.when(steady, F.col("tau") / F.col("at_tau")).otherwise(F.col("b")).alias("b")]
    return fit.select("kind", "stage", "tau", F.lit(curve).alias("form"), *first, F.when(enough, F.col("la")).otherwise(F.col("at_tau") / F.col("tau")).alias("line_a"), F.when(enough, F.col("lb")).otherwise(F.lit(0.0)).alias("line_b"), "least")


@dataclass(frozen=True)
class Piecewise:
    """One stage's model on the driver. Below the least probed size its speed stands in, and where the curve's speed is not positive, that at tau."""

    form: str
    a: float
    b: float
    tau: float
    line_a: float
    line_b: float
    least: float = 0.0

    def __call__(self, size: float) -> float:
        if size <= 0:
            return 0.0
        if self.form == "line":
            return max(0.0, self.a * size + self.b)
        if size < self.least:
            return size / self.least * self(self.least)
        if size > self.tau:
            return max(self.line_a * size + self.line_b, self(self.tau))
        x = {"log": math.log, "sqrtlog": lambda s: math.sqrt(max(math.log(s), 0.0)), "sqrt": math.sqrt}[self.form](size)
        speed = self.a * x + self.b
        return size / speed if speed > 0 else self.line_a * size + max(self.line_b, 0.0)


def models(fit: DataFrame) -> dict[tuple[str, str], Piecewise]:
    """The rows of a fit (few: one per lane kind and stage) as functions."""
    out = {}
    for r in fit.collect():
        d = r.asDict()
        out[(d["kind"], d["stage"])] = Piecewise(d["form"], d["a"], d["b"], d.get("tau") or math.inf, d.get("line_a") or 0.0, d.get("line_b") or 0.0, d.get("least") or 0.0)
    return out


def combine(transfer_in, kernel, transfer_out=None, how: str = "max"):
    """Time of a wide lane from its stages: 'max' (they overlap), 'max3' (with the way back), 'sum' (they do not)."""
    if how == "sum":
        return lambda s: transfer_in(s) + kernel(s) + (transfer_out(s) if transfer_out else 0.0)
    if how == "max3":
        return lambda s: max(transfer_in(s), kernel(s), transfer_out(s))
    return lambda s: max(transfer_in(s), kernel(s))


def model_error(probe: DataFrame, fit: DataFrame) -> DataFrame:
    """kind, stage, mape of a line or piecewise fit on a probe."""
    p = average(probe).join(F.broadcast(fit), ["kind", "stage"])
    if "tau" in fit.columns:
        x = F.when(F.col("form") == "log", F.ln("size")).when(F.col("form") == "sqrtlog", F.sqrt(F.ln("size"))).otherwise(F.sqrt("size"))
        guess = F.when(F.col("size") > F.col("tau"), F.col("line_a") * F.col("size") + F.col("line_b")).otherwise(F.col("size") / (F.col("a") * x + F.col("b")))
    else:
        guess = F.col("a") * F.col("size") + F.col("b")
    return p.groupBy("kind", "stage").agg(F.avg(F.abs(guess / F.col("seconds") - 1)).alias("mape"))


# --- synthetic devices and real probes ------------------------------------------------------------------------------

#: Closed forms of test devices: SQL text in `size`, for each kind and stage.
DEVICES = {
    "linear": {("narrow", "kernel"): "size * 1e-6", ("wide", "kernel"): "size * 2e-7", ("wide", "to"): "size * 5e-8", ("wide", "from"): "size * 2e-8"},
    "saturating": {("narrow", "kernel"): "size * 1e-6", ("wide", "kernel"): "size / (1e6 * ln(least(size, 1048576)) - 6e6)", ("wide", "to"): "size / (4e6 * sqrt(ln(least(size, 262144))) - 8e6)", ("wide", "from"): "size / (8e6 * sqrt(ln(least(size, 262144))) - 16e6)"},
    "transfer_bound": {("narrow", "kernel"): "size * 1e-6", ("wide", "kernel"): "size * 1e-8", ("wide", "to"): "size * 3e-7", ("wide", "from"): "size * 1e-8"},
    "kernel_bound": {("narrow", "kernel"): "size * 1e-6", ("wide", "kernel"): "size * 3e-7", ("wide", "to"): "size * 1e-8", ("wide", "from"): "size * 1e-9"},
}


def device_sql(device: str, noise: float = 0.01, least: int = 10, most: int = 24, sizes: str | None = None) -> str:
    """SQL text (Spark and DuckDB) of the probe table of a synthetic device: doubling sizes (or those of a query), three repeats around the exact time."""
    sizes = sizes or " UNION ALL ".join(f"SELECT CAST({2**i} AS BIGINT) AS size" for i in range(least, most + 1))
    reps = " UNION ALL ".join(f"SELECT {i} AS rep, CAST({(i - 1) * noise} AS DOUBLE) AS shift" for i in range(3))
    parts = [f"SELECT '{k}' AS kind, '{s}' AS stage, size, rep, CAST(({t}) * (1 + shift) AS DOUBLE) AS seconds FROM s, r" for (k, s), t in DEVICES[device].items()]
    return f"WITH s AS ({sizes}), r AS ({reps}) " + " UNION ALL ".join(parts)


def device_probe(spark: SparkSession, device: str, noise: float = 0.01) -> DataFrame:
    return spark.sql(device_sql(device, noise))


#: A probe of a table: its prefixes double up to all of its ratings, and each rating stands for so many.
PREFIXES, EACH = 15, 1000


def table_sizes(ratings: DataFrame) -> DataFrame:
    """size: ratings that each doubling prefix of the table stands for; a few rows, kept. The largest one is the whole table."""
    prefixes = prefix_sizes(probe_parts(ratings, PREFIXES, spacing="geometric"))
    return cut(prefixes.select((F.col("size") * EACH).cast("long").alias("size")), "sizes")


def table_sizes_sql(view: str) -> str:
    """The same in DuckDB, for the text of a view."""
    part = f"greatest(0, {PREFIXES - 1} + CAST(ceil(log2(((u * 7919 + v * 104729 + 1) % 1000003 + 1) / 1000003e0)) AS INT))"
    return f"SELECT CAST({EACH} * sum(n) OVER (ORDER BY part) AS BIGINT) AS size FROM (SELECT {part} AS part, count(*) AS n FROM ({view}) r GROUP BY 1) c"


def table_probe(sizes: DataFrame, device: str, noise: float = 0.01) -> DataFrame:
    """The probe table of a synthetic device at the sizes of a table."""
    return sizes.sparkSession.sql(device_sql(device, noise, sizes="SELECT size FROM {sizes}"), sizes=sizes)


def probe_sample(ratings: DataFrame, most: int, seed: int = 1) -> DataFrame:
    """Up to `most` ratings in a shuffled order (place): the rows of a bounded hash range, so the sample is as mixed as the data."""
    total = ratings.count()
    h = F.expr(mixed("u * 4099 + v", seed))
    kept = ratings.where(h < int(PRIME * min(1.0, 1.2 * most / max(total, 1))) + 1)
    return kept.select("u", "v", "r", h.alias("place")).orderBy("place", "u", "v").limit(most)


def probe_lane(sample: DataFrame, kind: str, params, sizes: list[int], repeats: int = 3) -> DataFrame:
    """Measured seconds of one lane's kernel (as runs use it) on growing prefixes of a shuffled sample(u, v, r, place). One task; the clock runs inside it."""
    from blockmf.operators.kernels import ordered_kernel, wide_kernel

    kernel = {"narrow": ordered_kernel, "wide": wide_kernel}[kind]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        held = [b for b in batches if b.num_rows]
        if not held:
            return
        t = pa.Table.from_batches(held)
        u, v, r = (t.column(c).to_numpy() for c in ("u", "v", "r"))
        rng = np.random.default_rng(3)
        for size in sorted({min(s, len(u)) for s in sizes}):
            (ids_u, rows), (ids_v, cols) = (np.unique(x[:size], return_inverse=True) for x in (u, v))
            p, q = rng.random((len(ids_u), params.k)) * 0.1, rng.random((len(ids_v), params.k)) * 0.1
            kernel(rows, cols, r[:size], p.copy(), q.copy(), params)  # once without the clock
            for rep in range(repeats):
                began = time.perf_counter()
                kernel(rows, cols, r[:size], p, q, params)
                yield pa.RecordBatch.from_pydict({"kind": [kind], "stage": ["kernel"], "size": [size], "rep": pa.array([rep], pa.int32()), "seconds": [time.perf_counter() - began]})

    return sample.repartition(1).sortWithinPartitions("place", "u", "v").select("u", "v", "r").mapInArrow(run, PROBE)


def probe_transfer(sample: DataFrame, direction: str, params, sizes: list[int], repeats: int = 3) -> DataFrame:
    """Measured seconds to move blocks of a sample to a lane ('to': ratings into a Python worker) or their factors back ('from').

    The clock starts inside the worker, so it counts no job or worker start: on the way in from the first batch that is asked for to the last one that has come, on the
    way out from the first batch handed over to the moment after the last one was taken."""
    parts = []
    for size in sizes:
        prefix = sample.orderBy("place", "u", "v").limit(size)
        for rep in range(repeats):
            parts += prefix.repartition(1).select("u", "v", "r").mapInArrow(_timed(direction, size, rep, params.k), "kind string, stage string, size long, rep int, seconds double, vec array<double>").where("seconds is not null").drop("vec").collect()
    return sample.sparkSession.createDataFrame([tuple(x) for x in parts], PROBE)


def _timed(direction: str, size: int, rep: int, k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        from blockmf.operators.kernels import vectors

        def rows(n: int, seconds: float | None, vec: pa.Array) -> pa.RecordBatch:
            same = lambda x, kind: pa.array([x] * n, kind)
            return pa.RecordBatch.from_arrays([same("wide", pa.string()), same(direction, pa.string()), same(count, pa.int64()), same(rep, pa.int32()), same(seconds, pa.float64()), vec], ["kind", "stage", "size", "rep", "seconds", "vec"])

        began, count, ids = time.perf_counter(), 0, []
        for b in batches:
            count += b.num_rows
            ids.append((b.column(0).to_numpy(), b.column(1).to_numpy()))
        took = time.perf_counter() - began
        if not count:
            return
        if direction == "from":
            n = sum(len(np.unique(np.concatenate(x))) for x in zip(*ids, strict=True))
            m = np.full((n, k), 0.5)
            began = time.perf_counter()
            for lo in range(0, n, 8192):
                part = m[lo : lo + 8192]
                yield rows(len(part), None, vectors(part))
            took = time.perf_counter() - began
        yield rows(1, took, pa.array([None], pa.list_(pa.float64())))

    return run


def estimate_costs(ratings: DataFrame, params, path: str | None = None, sizes: tuple[int, ...] = tuple(1 << i for i in range(9, 17)), repeats: int = 3) -> DataFrame:
    """Probe -> fit -> (optionally) store: kind, stage, tau, form, a, b, line_a, line_b, least for both lane kinds. Done once per kind of machine; any run can take the stored table.

    Narrow lanes: a line through the times of growing prefixes. Wide lanes: kernel and transfers, each a curve up to its threshold and a line beyond."""
    spark = ratings.sparkSession
    sample = cut(probe_sample(ratings, max(sizes)), "probe")
    n = sample.count()
    sizes = sorted({min(s, n) for s in sizes})
    kernel = spark.createDataFrame([tuple(r) for kind in ("narrow", "wide") for r in probe_lane(sample, kind, params, sizes, repeats).collect()], PROBE)
    moved = probe_transfer(sample, "to", params, sizes, repeats).unionByName(probe_transfer(sample, "from", params, sizes, repeats))
    wide = fit_piecewise(kernel.where("kind = 'wide'"), "log").unionByName(fit_piecewise(moved, "sqrtlog"))
    fit = line_rows(fit_line(kernel.where("kind = 'narrow'"))).unionByName(wide)
    if path:
        fit.coalesce(1).write.mode("overwrite").parquet(path)
        return spark.read.parquet(path)
    return cut(fit, "fit")


def line_rows(fit: DataFrame) -> DataFrame:
    """Straight lines in the columns of fit_piecewise()."""
    empty = {"tau": "long", "line_a": "double", "line_b": "double", "least": "long"}
    return fit.select("kind", "stage", F.lit(None).cast("long").alias("tau"), "form", "a", "b", *[F.lit(None).cast(t).alias(c) for c, t in empty.items() if c != "tau"])


def cost_of(fit: DataFrame, how: str = "max3") -> Callable[[str, float], float]:
    """The fits of estimate_costs() as the cost function that plans take."""
    m = models(fit)
    back = m.get(("wide", "from"))
    wide = combine(m["wide", "to"], m["wide", "kernel"], back, how if back or how == "max" else "max")
    return lambda kind, size: m["narrow", "kernel"](size) if kind == "narrow" else wide(size)
