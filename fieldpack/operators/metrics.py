"""Accuracy and cost measures."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.stages import keep
from ..spec import AXES, FieldSpec


def errors(a: DataFrame, b: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """n, mse, rmse, max_error of two voxel views, in all or by columns; a voxel missing in `b` counts as 0."""
    d = F.col("v") - F.coalesce("_b", F.lit(0.0))
    both = a.join(b.select(*AXES, F.col("v").alias("_b")), list(AXES), "left").select(*AXES, d.alias("d"))
    return both.groupBy(*by).agg(F.count("*").alias("n"), F.avg(F.col("d") * F.col("d")).alias("mse"), F.sqrt(F.avg(F.col("d") * F.col("d"))).alias("rmse"), F.max(F.abs("d")).alias("max_error"))


def decibel(mse: Column, peak: Column) -> Column:
    return 20 * F.log10(peak) - 10 * F.log10(mse)


def psnr(a: DataFrame, b: DataFrame, per_time_peak: bool = False) -> DataFrame:
    """t, mse, psnr. The peak is the original's range over the whole field (or over each timestep)."""
    span = F.max("v") - F.min("v")
    by_time = errors(a, b, ("t",))
    if per_time_peak:
        peaked = by_time.join(a.groupBy("t").agg(span.alias("peak")), "t")
    else:
        peaked = by_time.crossJoin(F.broadcast(a.agg(span.alias("peak"))))
    return peaked.select("t", "mse", decibel(F.col("mse"), F.col("peak")).alias("psnr"))


def avg_psnr(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: the mean of the timesteps' PSNR."""
    return psnr(a, b).agg(F.avg("psnr").alias("psnr"))


def compression_rate(spec: FieldSpec, archive_bytes: Column) -> Column:
    """Raw 32-bit size over the archive's size with its header."""
    return F.lit(float(spec.raw_bytes)) / archive_bytes


def net_loss(block_errors: DataFrame, assignment: DataFrame) -> DataFrame:
    """net_id, loss: mean over a net's blocks of the block's mean squared error (columns block_id, mse)."""
    return block_errors.join(assignment.select("block_id", "net_id"), "block_id").groupBy("net_id").agg(F.avg("mse").alias("loss"), F.count("*").alias("blocks"))


def iso_points(vox: DataFrame, value: float) -> DataFrame:
    """t, px, py, pz: where grid edges cross the value, by linear interpolation. A window holds one grid line."""
    out = None
    for a in ("x", "y", "z"):
        line = Window.partitionBy(*[b for b in AXES if b != a]).orderBy(a)
        cross = vox.withColumn("_n", F.lead("v").over(line)).where((F.col("v") - value) * (F.col("_n") - value) < 0)
        at = F.col(a) + (F.lit(value) - F.col("v")) / (F.col("_n") - F.col("v"))
        rows = cross.select("t", *[(at if b == a else F.col(b).cast("double")).alias(f"p{b}") for b in ("x", "y", "z")])
        out = rows if out is None else out.unionByName(rows)
    return out


def _nearest(p: DataFrame, q: DataFrame, cell: float | None) -> DataFrame:
    """Distance from each point of p to the nearest of q at the same t."""
    d2 = lambda: sum((F.col(f"p{a}") - F.col(f"q{a}")) ** 2 for a in "xyz")
    if cell is None:
        other = q.select(F.col("t").alias("t"), *[F.col(f"p{a}").alias(f"q{a}") for a in "xyz"])
        return p.join(other, "t").groupBy("t", "px", "py", "pz").agg(F.sqrt(F.min(d2())).alias("d"))
    key = lambda a: F.floor(F.col(f"p{a}") / cell).cast("int")
    other = q.select("t", *[key(a).alias(f"_c{a}") for a in "xyz"], *[F.col(f"p{a}").alias(f"q{a}") for a in "xyz"])
    keyed = p.select("t", "px", "py", "pz")
    for a in "xyz":
        keyed = keyed.withColumn(f"_c{a}", F.explode(F.array(*[key(a) + i for i in (-1, 0, 1)])))
    return keyed.join(other, ["t", "_cx", "_cy", "_cz"], "left").groupBy("t", "px", "py", "pz").agg(F.sqrt(F.min(d2())).alias("d"))


def _points(df: DataFrame) -> DataFrame:
    """Equal points count once: a kept table of the others."""
    return keep(df.select("t", "px", "py", "pz").distinct(), "points")


def nearest_distances(p: DataFrame, q: DataFrame, cell: float = 1.0, rounds: int = 6) -> DataFrame:
    """Exact nearest distances in rings: cells are tried at a size, a distance up to that size is final, and
    only points without one go on at twice the size; what is left after the last round meets all points of its t.
    Points and every round's distances are kept tables, so no plan holds an earlier round."""
    return _rings(_points(p), _points(q), cell, rounds)


def _rings(open_: DataFrame, q: DataFrame, cell: float = 1.0, rounds: int = 6) -> DataFrame:
    done = None
    for _ in range(rounds):
        got = keep(_nearest(open_, q, cell), "nearest")
        sure = got.where(F.col("d") <= cell)
        done = sure if done is None else done.unionByName(sure)
        open_ = got.where("d IS NULL OR d > " + repr(cell)).select("t", "px", "py", "pz")
        if open_.isEmpty():
            return done
        cell *= 2
    rest = _nearest(open_, q, None)
    return rest if done is None else done.unionByName(rest)


def chamfer(p: DataFrame, q: DataFrame, squared: bool = False, half: bool = False, exact_cells: bool = False) -> DataFrame:
    """One row: the sum (or half of it) of both directed mean distances between point sets."""
    def mean(a: DataFrame, b: DataFrame, name: str) -> DataFrame:
        near = _rings(a, b) if exact_cells else _nearest(a.distinct(), b.distinct(), None)
        return near.agg(F.avg(F.col("d") * F.col("d") if squared else F.col("d")).alias(name))

    if exact_cells:
        p, q = _points(p), _points(q)
    total = F.col("pq") + F.col("qp")
    return mean(p, q, "pq").crossJoin(mean(q, p, "qp")).select("pq", "qp", (total / 2 if half else total).alias("chamfer"))


def render(vox: DataFrame, density: float = 0.2) -> DataFrame:
    """Emission-absorption along z, front first: t, px, py, r, g, b. Values are taken as in [-1, 1]."""
    u = F.greatest(F.lit(0.0), F.least(F.lit(1.0), (F.col("v") + 1) / 2))
    alpha = density * u
    front = Window.partitionBy("t", "x", "y").orderBy("z").rowsBetween(Window.unboundedPreceding, -1)
    seen = vox.select("t", "x", "y", "z", u.alias("u"), alpha.alias("a")).withColumn("through", F.exp(F.coalesce(F.sum(F.log(1 - F.col("a"))).over(front), F.lit(0.0))))
    part = F.col("through") * F.col("a")
    return seen.groupBy("t", F.col("x").alias("px"), F.col("y").alias("py")).agg(F.sum(part * F.col("u")).alias("r"), F.sum(part * (1 - F.abs(2 * F.col("u") - 1))).alias("g"), F.sum(part * (1 - F.col("u"))).alias("b"))


def render_iso(vox: DataFrame, value: float) -> DataFrame:
    """First hit along z: t, px, py, depth, shade (by the step of the value at the hit)."""
    line = Window.partitionBy("t", "x", "y").orderBy("z")
    hit = vox.withColumn("_n", F.lead("v").over(line)).where((F.col("v") - value) * (F.col("_n") - value) < 0)
    depth = F.col("z") + (F.lit(value) - F.col("v")) / (F.col("_n") - F.col("v"))
    return hit.groupBy("t", F.col("x").alias("px"), F.col("y").alias("py")).agg(F.min_by(depth, "z").alias("depth"), F.min_by(F.abs(F.col("_n") - F.col("v")), "z").alias("shade"))


def cieluv(r: Column, g: Column, b: Column) -> tuple[Column, Column, Column]:
    """sRGB in [0, 1] to L*, u*, v* (white point D65)."""
    lin = [F.when(c <= 0.04045, c / 12.92).otherwise(F.pow((c + 0.055) / 1.055, F.lit(2.4))) for c in (r, g, b)]
    x, y, z = (m[0] * lin[0] + m[1] * lin[1] + m[2] * lin[2] for m in ((0.4124564, 0.3575761, 0.1804375), (0.2126729, 0.7151522, 0.0721750), (0.0193339, 0.1191920, 0.9503041)))
    big = F.when(y > 0.008856, 116 * F.pow(y, F.lit(1.0 / 3)) - 16).otherwise(903.3 * y)
    s = x + 15 * y + 3 * z
    un, vn = 0.19783982, 0.46833631
    u = F.when(s > 0, 13 * big * (4 * x / s - un)).otherwise(F.lit(0.0))
    v = F.when(s > 0, 13 * big * (9 * y / s - vn)).otherwise(F.lit(0.0))
    return big, u, v


def cieluv_diff(a: DataFrame, b: DataFrame) -> DataFrame:
    """t, px, py, delta: distance of two images' pixels in CIELUV."""
    clip = lambda c: F.greatest(F.lit(0.0), F.least(F.lit(1.0), c))
    both = a.join(b.select("t", "px", "py", *[F.col(c).alias(f"_{c}") for c in "rgb"]), ["t", "px", "py"])
    p, q = cieluv(*[clip(F.col(c)) for c in "rgb"]), cieluv(*[clip(F.col(f"_{c}")) for c in "rgb"])
    return both.select("t", "px", "py", F.sqrt(sum((i - j) ** 2 for i, j in zip(p, q))).alias("delta"))


def image_distance(a: DataFrame, b: DataFrame, levels: int = 3) -> DataFrame:
    """t, distance: a stand-in for learned image distances, from gradients of averaged images at several
    sizes: mean over levels of 1 - 2*cov/(var + var) of the horizontal and vertical steps."""
    grey = lambda df, name: df.select("t", "px", "py", ((F.col("r") + F.col("g") + F.col("b")) / 3).alias(name))
    both = grey(a, "p").join(grey(b, "q"), ["t", "px", "py"])
    parts = None
    for level in range(levels):
        small = both.groupBy("t", F.floor(F.col("px") / (1 << level)).alias("px"), F.floor(F.col("py") / (1 << level)).alias("py")).agg(F.avg("p").alias("p"), F.avg("q").alias("q"))
        for a_, b_ in (("px", "py"), ("py", "px")):
            w = Window.partitionBy("t", b_).orderBy(a_)
            d = small.select("t", (F.lead("p").over(w) - F.col("p")).alias("dp"), (F.lead("q").over(w) - F.col("q")).alias("dq")).where("dp IS NOT NULL")
            c = 1e-6
            part = d.groupBy("t").agg((1 - (2 * F.sum(F.col("dp") * F.col("dq")) + c) / (F.sum(F.col("dp") ** 2) + F.sum(F.col("dq") ** 2) + c)).alias("d"))
            parts = part if parts is None else parts.unionByName(part)
    return parts.groupBy("t").agg(F.avg("d").alias("distance"))


def speedup(runs: DataFrame, base: str, metric: str) -> DataFrame:
    """workload, method, speedup: the base method's time over each method's."""
    r = runs.where(F.col("metric") == metric)
    b = r.where(F.col("method") == base).select("workload", F.col("value").alias("_base"))
    return r.where(F.col("method") != base).join(b, "workload").select("workload", "method", (F.col("_base") / F.col("value")).alias("speedup"))


def mean_gain(runs: DataFrame, method: str, metric: str = "psnr") -> DataFrame:
    """baseline, gain: mean over workloads of the method's value less the baseline's."""
    r = runs.where(F.col("metric") == metric)
    own = r.where(F.col("method") == method).select("workload", F.col("value").alias("_own"))
    return r.where(F.col("method") != method).join(own, "workload").groupBy(F.col("method").alias("baseline")).agg(F.avg(F.col("_own") - F.col("value")).alias("gain"))


def best_of(runs: DataFrame, higher: tuple[str, ...] = ("psnr", "cr")) -> DataFrame:
    """workload, metric, method, value: the best method of each metric (ties by name)."""
    score = F.when(F.col("metric").isin(*higher), F.col("value")).otherwise(-F.col("value"))
    w = Window.partitionBy("workload", "metric").orderBy(F.desc("_s"), "method")
    return runs.withColumn("_s", score).withColumn("_r", F.row_number().over(w)).where("_r = 1").select("workload", "metric", "method", "value")


def rank_methods(runs: DataFrame, higher: tuple[str, ...] = ("psnr", "cr")) -> DataFrame:
    """metric, method, mean_rank, place: methods by their mean rank over workloads."""
    score = F.when(F.col("metric").isin(*higher), -F.col("value")).otherwise(F.col("value"))
    w = Window.partitionBy("workload", "metric").orderBy("_s")
    mean = runs.withColumn("_s", score).withColumn("_r", F.dense_rank().over(w)).groupBy("metric", "method").agg(F.avg("_r").alias("mean_rank"))
    return mean.withColumn("place", F.dense_rank().over(Window.partitionBy("metric").orderBy("mean_rank")))


def rd_curve(runs: DataFrame) -> DataFrame:
    """method, cr, psnr: one row per run, by method and rate (runs carry a run id in `workload`)."""
    return runs.where(F.col("metric").isin("cr", "psnr")).groupBy("workload", "method").pivot("metric", ["cr", "psnr"]).agg(F.first("value")).select("method", "cr", "psnr").orderBy("method", "cr")


def memory_profile(profile: DataFrame, spec: FieldSpec) -> DataFrame:
    """scale, resident_bytes: effective blocks of a scale as 32-bit floats (columns scale, effective)."""
    return profile.select("scale", (F.col("effective") * spec.block_voxels * 4).alias("resident_bytes"))
