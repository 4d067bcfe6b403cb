"""The experiments as functions that return run records (workload, method, metric, value, config).

Each takes a preset: `SMALL` trains briefly on small fields, `PUBLISHED` has the published schedules
on the volumes made from the tables. Those that the survey puts on the tables' volumes (`w03`, `w17`,
`w19`) read whole tables and train by the published schedule unless another preset is given.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..baselines.globalnet import global_decode, global_encode, grid_encode, match_width
from ..baselines.spline import spline_decode, spline_encode
from ..baselines.tucker import tucker_decode, tucker_encode
from ..operators import metrics as M
from ..operators.blocks import seam_ratio
from ..operators.grid import analytic_field, normalize
from ..operators.seam import SeamNet
from ..operators.sinenet import NetSpec
from ..operators.train import Schedule
from ..operators.volumes import lineitem_cells, volume
from ..sources.raw import run_records
from ..sources.tables import load
from ..spec import FieldSpec
from .codec import CodecConfig, decode, encode
from .field_queries import q6, r6
from .stages import keep
from .twins import F1_CELLS


@dataclass(frozen=True)
class Preset:
    name: str
    config: CodecConfig
    analytic: FieldSpec
    iterations: int
    volumes: tuple[str, ...] = ()


SMALL = Preset("small", CodecConfig.quick(16, tau=5e-2, per_net=(4, 8), net=NetSpec(hidden=12, latent_dim=2), kmeans_steps=2), FieldSpec(8, 8, 8, 2, 4, 4, 4, 2), 8)
PUBLISHED = Preset("published", CodecConfig(seam=SeamNet()), FieldSpec(32, 32, 32, 16, 8, 8, 8, 3), 2000, ("f9", "f10"))
PUBLISHED_STATIC = Preset("static", CodecConfig(schedule=Schedule.static(), per_net=(1, 2, 4)), FieldSpec(32, 32, 32, 1, 8, 8, 8, 3), 2000, ("f4", "f6"))
PUBLISHED_LARGE = Preset("large", CodecConfig(schedule=Schedule.large(), per_net=(1, 2, 4, 8)), FieldSpec(64, 64, 64, 1, 8, 8, 8, 4), 2000, ("f3",))


def field(spark: SparkSession, sf_dir: str, preset: Preset, name: str = "f0") -> tuple[DataFrame, FieldSpec]:
    if name == "f0":
        return keep(normalize(analytic_field(spark, preset.analytic)), "field"), preset.analytic
    vox, spec = volume(spark, sf_dir, name)
    return keep(normalize(vox), "field"), spec


def _timed(f):
    began = time.perf_counter()
    got = f()
    return got, time.perf_counter() - began


def _records(workload: str, method: str, values: dict[str, float], **config) -> list[tuple]:
    return [(workload, method, k, float(v), {a: str(b) for a, b in config.items()}) for k, v in values.items() if v is not None]


def judge(vox: DataFrame, decoded: DataFrame, iso: float = 0.0, chamfer: bool = True) -> dict[str, float]:
    """PSNR averaged over timesteps, the image distance of renderings, and the chamfer distance of isosurfaces."""
    out = {"psnr": M.avg_psnr(vox, decoded).first()[0]}
    out["image_distance"] = M.image_distance(M.render(vox), M.render(decoded)).agg(F.avg("distance")).first()[0]
    if chamfer:
        out["chamfer"] = M.chamfer(M.iso_points(vox, iso), M.iso_points(decoded, iso)).first()["chamfer"]
    return out


def run_method(workload: str, method: str, vox: DataFrame, spec: FieldSpec, cfg: CodecConfig, full: bool = True, **config) -> list[tuple]:
    (archive, decoded), et = _timed(lambda: encode(vox, spec, cfg))
    again, dt = _timed(lambda: keep(decode(archive), "again"))
    values = {"cr": spec.raw_bytes / archive.bytes, "model_bytes": archive.bytes, "encode_s": et, "decode_s": dt}
    values |= judge(vox, decoded) if full else {"psnr": M.avg_psnr(vox, decoded).first()[0]}
    return _records(workload, method, values, **config)


def run_spline(workload: str, vox: DataFrame, spec: FieldSpec, eps: float, full: bool = True, kind: str = "cubic") -> list[tuple]:
    archive, et = _timed(lambda: spline_encode(vox, spec, eps, kind=kind))
    decoded, dt = _timed(lambda: keep(spline_decode(archive), "spline-decoded"))
    values = {"cr": spec.raw_bytes / archive.bytes, "model_bytes": archive.bytes, "encode_s": et, "decode_s": dt}
    values |= judge(vox, decoded) if full else {"psnr": M.avg_psnr(vox, decoded).first()[0]}
    return _records(workload, "spline", values, eps=eps)


def run_tucker(workload: str, vox: DataFrame, spec: FieldSpec, tol: float, full: bool = True) -> list[tuple]:
    archive, et = _timed(lambda: tucker_encode(vox, spec, tol))
    decoded, dt = _timed(lambda: keep(tucker_decode(archive), "tucker-decoded"))
    values = {"cr": spec.raw_bytes / archive.bytes, "model_bytes": archive.bytes, "encode_s": et, "decode_s": dt}
    values |= judge(vox, decoded) if full else {"psnr": M.avg_psnr(vox, decoded).first()[0]}
    return _records(workload, "tucker", values, tol=tol)


def run_global(workload: str, vox: DataFrame, spec: FieldSpec, target_cr: float, iterations: int, depth: int = 3, full: bool = True) -> list[tuple]:
    width = match_width(spec, target_cr, depth)
    archive = global_encode(vox, spec, width, depth, iterations, sample=0.5, rate=1e-3, check_every=iterations)
    decoded, dt = _timed(lambda: keep(global_decode(archive, vox), "global-decoded"))
    values = {"cr": spec.raw_bytes / archive.bytes, "model_bytes": archive.bytes, "encode_s": archive.seconds, "decode_s": dt}
    values |= judge(vox, decoded) if full else {"psnr": M.avg_psnr(vox, decoded).first()[0]}
    return _records(workload, "global", values, width=width)


def match_rate(make, target_cr: float, lo: float, hi: float, spec: FieldSpec, steps: int = 12, within: float = 0.05) -> float:
    """Bisection (in logarithms) of a tolerance until the archive's rate is within 5 % of the target."""
    for _ in range(steps):
        mid = (lo * hi) ** 0.5
        rate = spec.raw_bytes / make(mid).bytes
        if abs(rate / target_cr - 1) <= within:
            return mid
        lo, hi = (mid, hi) if rate < target_cr else (lo, mid)
    return (lo * hi) ** 0.5


def match_size(target_bytes: float, blocks: int, bytes_each: float, base: NetSpec) -> NetSpec:
    """The widest net without latent codes of which one for each block takes at most the target's bytes (at least one unit)."""
    fits = lambda w: blocks * replace(base, hidden=w, latent_dim=0).parameters * bytes_each <= target_bytes
    width = 1
    while fits(width + 1):
        width += 1
    return replace(base, hidden=width, latent_dim=0)


def match_params(parameters: int, blocks: int, base: NetSpec) -> NetSpec:
    """The widest net of which one for each block has at most so many parameters in all."""
    return match_size(float(parameters), blocks, 1.0, base)


def w01(spark, sf_dir, preset=SMALL):
    """Main comparison of four methods, the coders' tolerances matched to the method's own rate."""
    rows = []
    for name in ("f0", *preset.volumes):
        vox, spec = field(spark, sf_dir, preset, name)
        own = run_method(f"w01-{name}", "method", vox, spec, preset.config)
        rate = max(1.0, next(r[3] for r in own if r[2] == "cr"))
        eps = match_rate(lambda e, v=vox, s=spec: spline_encode(v, s, e), rate, 1e-4, 1.0, spec)
        tol = match_rate(lambda e, v=vox, s=spec: tucker_encode(v, s, e), rate, 1e-4, 0.9, spec)
        rows += own + run_spline(f"w01-{name}", vox, spec, eps) + run_tucker(f"w01-{name}", vox, spec, tol) + run_global(f"w01-{name}", vox, spec, rate, preset.iterations)
    return run_records(spark, rows)


def w02(spark, sf_dir, preset=SMALL):
    """Rate against distortion: the method by block extent, the coders by tolerance."""
    vox, spec = field(spark, sf_dir, preset)
    rows = []
    for b in (2, 4):
        rows += run_method(f"w02-{b}", "method", vox, replace(spec, bx=b, by=b, bz=b), preset.config, False, block=b)
    for eps in (0.01, 0.05, 0.2):
        rows += run_spline(f"w02-{eps}", vox, spec, eps, False)
    for tol in (0.02, 0.1, 0.3):
        rows += run_tucker(f"w02-{tol}", vox, spec, tol, False)
    return run_records(spark, rows)


def w03(spark, sf_dir, preset=PUBLISHED, volumes=("f9", "f10")):
    """Model size and resident bytes by scale."""
    rows = []
    for name in volumes:
        vox, spec = field(spark, sf_dir, preset, name)
        archive, _ = encode(vox, spec, preset.config)
        for p in archive.parts:
            n = p.flags.where("effective").count()
            rows += _records(f"w03-{name}", f"scale {p.scale}", {"model_bytes": sum(p.sizes.values()), "effective": n, "blocks": p.flags.count(), "resident_bytes": 4.0 * n * p.spec.block_voxels})
    return run_records(spark, rows)


def w04(spark, sf_dir, preset=SMALL):
    """Large spatial extent: more scales, more blocks per net at fine scales, more bits."""
    cfg = replace(preset.config, per_net=(1, 2, 4, 8), schedule=replace(preset.config.schedule, beta=9))
    spec = replace(preset.analytic, nt=1, nx=16, scales=3)
    vox, _ = field(spark, sf_dir, replace(preset, analytic=spec))
    return run_records(spark, run_method("w04", "method", vox, spec, cfg) + run_global("w04", vox, spec, 4.0, preset.iterations))


def w05(spark, sf_dir, preset=SMALL):
    """Two resolutions of one field, with blocks as much larger as the field."""
    rows = []
    for k in (1, 2):
        spec = replace(preset.analytic, nt=1, nx=8 * k, ny=8 * k, nz=8 * k, bx=4 * k, by=4 * k, bz=4 * k)
        vox, _ = field(spark, sf_dir, replace(preset, analytic=spec))
        rows += run_method(f"w05-{k}", "method", vox, spec, preset.config, False, factor=k)
    return run_records(spark, rows)


def w06(spark, sf_dir, preset=SMALL):
    """Block assignment: equal clusters, plain k-means, spatial order, and one net per block, with the same net and
    with nets that take the same bytes or have the same parameters in all."""
    vox, spec = field(spark, sf_dir, preset)
    rows = []
    for scheme in ("uniform", "kmeans", "order"):
        rows += run_method("w06", scheme, vox, spec, replace(preset.config, scheme=scheme), False)
    rows += run_method("w06", "single", vox, spec, CodecConfig.single(preset.config), False)
    rows += run_method("w06", "single+", vox, spec, CodecConfig.single(preset.config, True), False)
    archive, _ = encode(vox, spec, preset.config)
    blocks = sum(p.codes.count() for p in archive.parts)
    parameters = sum(p.nets.count() for p in archive.parts) * preset.config.net.parameters
    for name, compress, net in (
        ("single, equal size", False, match_size(archive.bytes, blocks, 4.0, preset.config.net)),
        ("single+, equal size", True, match_size(archive.bytes, blocks, preset.config.schedule.beta / 8, preset.config.net)),
        ("single, equal parameters", False, match_params(parameters, blocks, preset.config.net)),
    ):
        cfg = replace(CodecConfig.single(preset.config, compress), net=net)
        rows += run_method("w06", name, vox, spec, cfg, False, width=net.hidden)
    return run_records(spark, rows)


def w07(spark, sf_dir, preset=SMALL):
    """With and without the seam network."""
    vox, spec = field(spark, sf_dir, preset)
    rows = []
    for name, seam in (("plain", None), ("seam", preset.config.seam or SeamNet(layers=3, channels=4, epochs=6, rate=1e-3))):
        (archive, decoded), et = _timed(lambda seam=seam: encode(vox, spec, replace(preset.config, seam=seam)))
        ratio = seam_ratio(decoded, spec).agg(F.avg("ratio")).first()[0]
        rows += _records("w07", name, {"psnr": M.avg_psnr(vox, decoded).first()[0], "seam_ratio": ratio, "model_bytes": archive.bytes, "encode_s": et})
    return run_records(spark, rows)


def w08(spark, sf_dir, preset=SMALL):
    """Volume renderings of decoded fields: pixel differences in CIELUV."""
    vox, spec = field(spark, sf_dir, preset)
    _, decoded = encode(vox, spec, preset.config)
    rows = []
    for name, df in (("method", decoded), ("spline", spline_decode(spline_encode(vox, spec, 0.1)))):
        r = M.cieluv_diff(M.render(vox), M.render(df)).agg(F.avg("delta"), F.max("delta")).first()
        rows += _records("w08", name, {"mean_delta": r[0], "max_delta": r[1]})
    return run_records(spark, rows)


def w09(spark, sf_dir, preset=SMALL):
    """Isosurface renderings: depth differences and chamfer distance by isovalue."""
    vox, spec = field(spark, sf_dir, preset)
    _, decoded = encode(vox, spec, preset.config)
    rows = []
    for iso in (-0.3, 0.0, 0.2):
        both = M.render_iso(vox, iso).alias("a").join(M.render_iso(decoded, iso).alias("b"), ["t", "px", "py"])
        depth = both.agg(F.avg(F.abs(F.col("a.depth") - F.col("b.depth")))).first()[0]
        rows += _records("w09", "method", {"depth": depth, "chamfer": M.chamfer(M.iso_points(vox, iso), M.iso_points(decoded, iso)).first()["chamfer"]}, iso=iso)
    return run_records(spark, rows)


def w10_13(spark, sf_dir, preset=SMALL):
    """Sparse against dense, the ladder of compression stages, block-guided against magnitude and local pruning, global against local codebooks."""
    vox, spec = field(spark, sf_dir, preset)
    base, rows = preset.config, []
    for name, cfg in (
        ("dense", replace(base, prune=None, quant=None, entropy=False)), ("pruned", replace(base, quant=None, entropy=False)), ("quantized", replace(base, entropy=False)), ("coded", base),
        ("magnitude", replace(base, prune="magnitude")), ("local_pruning", replace(base, prune="local")), ("local_codebooks", replace(base, quant="net")),
    ):
        rows += run_method("w10-13", name, vox, spec, cfg, False)
    return run_records(spark, rows)


def w14(spark, sf_dir, preset=SMALL):
    """Block extents."""
    vox, spec = field(spark, sf_dir, preset)
    return run_records(spark, [r for b in (2, 4, 8) for r in run_method("w14", f"block {b}", vox, replace(spec, bx=b, by=b, bz=b), preset.config, False)])


def w15(spark, sf_dir, preset=SMALL):
    """Number of scales."""
    vox, spec = field(spark, sf_dir, preset)
    return run_records(spark, [r for s in (1, 2) for r in run_method("w15", f"scales {s}", vox, replace(spec, scales=s), preset.config, False)])


def w16(spark, sf_dir, preset=SMALL):
    """The weight of the block loss in pruning."""
    vox, spec = field(spark, sf_dir, preset)
    return run_records(spark, [r for lam in (0.0, 0.1, 1.0) for r in run_method("w16", f"lambda {lam}", vox, spec, replace(preset.config, lam=lam), False)])


def w17(spark, sf_dir, preset=PUBLISHED, volumes=tuple(f"f{i}" for i in range(11))):
    """What every part of an archive takes, for every volume: volume, scale, part, bytes."""
    out = None
    for name in volumes:
        vox, spec = field(spark, sf_dir, preset, name)
        archive, _ = encode(vox, spec, preset.config)
        part = archive.breakdown(spark).select(F.lit(name).alias("volume"), "scale", "part", "bytes")
        out = part if out is None else out.unionByName(part)
    return out


#: Short training on the tables' own volumes: one encode takes some two minutes on 8 cores.
TABLES = Preset("tables", CodecConfig.quick(60, tau=1e-2, net=NetSpec(hidden=16), kmeans_steps=3), FieldSpec(8, 8, 8, 2, 4, 4, 4, 2), 100, ("f9",))


def codec_lineitem(spark, sf_dir):
    """The trained codec over the whole line item volume: of every scale how many voxels and blocks its decoded field
    has, whether the archive's reader gets the encoder's field, and whether accuracy rises from scale to scale."""
    from ..operators.pyramid import upsample

    vox, spec = field(spark, sf_dir, TABLES, "f9")
    archive, decoded = encode(vox, spec, TABLES.config)
    rows, before = [], float("-inf")
    for scale in range(spec.scales, 0, -1):
        got = keep(decode(archive, scale), "progressive")
        fine = got
        for s in range(scale - 1, 0, -1):
            fine = upsample(fine, spec.at_scale(s))
        psnr = M.avg_psnr(vox, fine).first()[0]
        same = scale > 1 or M.errors(decoded, got).first()["max_error"] < 1e-9
        part = next(p for p in archive.parts if p.scale == scale)
        rows.append((scale, got.count(), part.flags.count(), bool(same), psnr > before))
        before = psnr
    return spark.createDataFrame(rows, "scale int, voxels long, blocks long, same_field boolean, more_accurate boolean")


def w18(spark, sf_dir, preset=SMALL, volume="f0"):
    """Progressive decoding: accuracy of every scale's field, brought to the finest grid."""
    from ..operators.pyramid import upsample

    vox, spec = field(spark, sf_dir, preset, volume)
    archive, _ = encode(vox, spec, preset.config)
    rows = []
    for scale in range(spec.scales, 0, -1):
        got = decode(archive, scale)
        for s in range(scale - 1, 0, -1):
            got = upsample(got, spec.at_scale(s))
        rows += _records("w18", f"scale {scale}", {"psnr": M.avg_psnr(vox, got).first()[0]})
    return run_records(spark, rows)


def w19(spark, sf_dir, preset=PUBLISHED, volume="f1"):
    """Accuracy of the global network over its training."""
    vox, spec = field(spark, sf_dir, preset, volume)
    archive = global_encode(vox, spec, 16, 3, preset.iterations, 0.5, 1e-2, check_every=max(1, preset.iterations // 4))
    return run_records(spark, [r for step, value in archive.history for r in _records("w19", "global", {"psnr": value}, step=step)])


def w20(spark, sf_dir, preset=SMALL, volumes=("f9", "f10")):
    """The feature-grid stand-in for grid-based comparators. It isn't trained, so no preset shortens it."""
    rows = []
    for name in volumes:
        vox, spec = field(spark, sf_dir, preset, name)
        decoded, size = grid_encode(vox, spec, 1)
        rows += _records(f"w20-{name}", "grid", {"psnr": M.avg_psnr(vox, decoded).first()[0], "cr": spec.raw_bytes / size})
    return run_records(spark, rows)


def w21(spark, sf_dir, preset=SMALL):
    """Static settings on one timestep."""
    spec = replace(preset.analytic, nt=1)
    vox, _ = field(spark, sf_dir, replace(preset, analytic=spec))
    cfg = replace(preset.config, per_net=(1, 2, 4), schedule=replace(preset.config.schedule, epochs=(24, 18, 15), rounds=((12, 0.2), (16, 0.3))))
    return run_records(spark, run_method("w21", "method", vox, spec, cfg))


WORKLOADS = {f.__name__: f for f in (w01, w02, w03, w04, w05, w06, w07, w08, w09, w10_13, w14, w15, w16, w17, w18, w19, w20, w21)}
#: Registered is what runs over its whole tables without training; the others run by `WORKLOADS[name](spark, sf_dir)`.
#: Their values have no SQL twin.
QUERIES = {"w20": w20}
ORACLES: dict[str, str] = {}

#: One mean stands for all cells of a timestep's group: the whole step, a slab, a column, or a block of 4 x 2 x 2 cells.
MEANS = {"global": "0", "slab": "z", "column": "x * 8 + y", "block": "(floor(z / 2) * 4 + floor(y / 2)) * 4 + floor(x / 4)"}


def table_runs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """workload, method, metric, value: run records of `MEANS` over the line item volume's filled cells (mean prices), a
    workload for each timestep. psnr is against the range of all cells and is missing where nothing is lost. The other
    metrics count work, which a repeated run has again: encode_ops an addition a cell and a division a mean, update_ops
    the cells that are added up again when one cell changes."""
    cells = keep(lineitem_cells(spark, sf_dir).select("x", "y", "z", "t", (F.col("v") / F.col("n") / 100).alias("v")), "run-cells")
    groups = F.explode(F.array(*[F.struct(F.lit(m).alias("method"), F.expr(f"CAST({g} AS INT)").alias("g")) for m, g in MEANS.items()])).alias("k")
    sizes = cells.select("t", "v", groups).groupBy("t", "k.method", "k.g").agg(F.count("*").alias("n"), F.var_pop("v").alias("var"))
    total = F.sum("n")
    runs = sizes.groupBy("t", "method").agg((total + F.count("*")).cast("double").alias("encode_ops"), (F.sum(F.col("n") * F.col("n")) / total).alias("update_ops"), F.round(F.sum(F.col("n") * F.col("var")) / total, 6).alias("mse"))
    peaked = runs.crossJoin(F.broadcast(cells.agg((F.max("v") - F.min("v")).alias("peak"))))
    values = peaked.select(F.concat(F.lit("q"), F.col("t")).alias("workload"), "method", r6(M.decibel(F.col("mse"), F.col("peak")), "psnr", 9), "encode_ops", "update_ops")
    return values.unpivot(["workload", "method"], ["psnr", "encode_ops", "update_ops"], "metric", "value").where("value IS NOT NULL")


_RUNS = f"""WITH c AS MATERIALIZED (SELECT x, y, z, t, v / n / 100.0 AS v FROM ({F1_CELLS})),
 s AS (SELECT t, method, CASE method WHEN 'global' THEN 0 WHEN 'slab' THEN z WHEN 'column' THEN x * 8 + y ELSE (z // 2 * 4 + y // 2) * 4 + x // 4 END AS g, count(*) AS n, var_pop(v) AS var FROM c, (VALUES ('global'), ('slab'), ('column'), ('block')) k(method) GROUP BY 1, 2, 3),
 w AS (SELECT 'q' || t AS workload, method, CAST(sum(n) + count(*) AS DOUBLE) AS encode_ops, CAST(sum(n * n) AS DOUBLE) / CAST(sum(n) AS DOUBLE) AS update_ops, nullif(round(sum(n * var) / CAST(sum(n) AS DOUBLE), 6), 0) AS mse FROM s GROUP BY t, method),
 p AS (SELECT nullif(max(v) - min(v), 0) AS peak FROM c),
 l AS (SELECT workload, method, 'psnr' AS metric, {q6('20 * log10(peak) - 10 * log10(mse)', 'value', 9)} FROM w, p WHERE mse IS NOT NULL AND peak IS NOT NULL
  UNION ALL SELECT workload, method, 'encode_ops', encode_ops FROM w UNION ALL SELECT workload, method, 'update_ops', update_ops FROM w)"""


def _audit(name: str, sql: str):
    def add(f):
        QUERIES[name], ORACLES[name] = f, sql
        return f

    return add


@_audit("audit_speedup", f"{_RUNS} SELECT a.workload, a.metric, {q6('b.value / a.value', 'speedup', 4)} FROM l a JOIN l b ON a.workload = b.workload AND a.metric = b.metric AND a.method = 'block' AND b.method = 'global' WHERE a.metric <> 'psnr'")
def audit_speedup(spark, sf_dir):
    r = table_runs(spark, sf_dir)
    out = None
    for metric in ("encode_ops", "update_ops"):
        s = M.speedup(r, "global", metric).where("method = 'block'").select("workload", F.lit(metric).alias("metric"), r6(F.col("speedup"), "speedup", 4))
        out = s if out is None else out.unionByName(s)
    return out


@_audit("audit_mean_gain", f"{_RUNS} SELECT b.method AS baseline, {q6('avg(a.value - b.value)', 'gain', 4)} FROM l a JOIN l b ON a.workload = b.workload AND a.metric = 'psnr' AND b.metric = 'psnr' AND a.method = 'block' AND b.method <> 'block' GROUP BY 1")
def audit_mean_gain(spark, sf_dir):
    return M.mean_gain(table_runs(spark, sf_dir), "block").select("baseline", r6(F.col("gain"), "gain", 4))


@_audit("audit_best_of", f"{_RUNS} SELECT workload, metric, method, {q6('value', 'value')} FROM (SELECT *, row_number() OVER (PARTITION BY workload, metric ORDER BY CASE WHEN metric = 'psnr' THEN -value ELSE value END, method) AS r FROM l) WHERE r = 1")
def audit_best_of(spark, sf_dir):
    return M.best_of(table_runs(spark, sf_dir)).withColumn("value", r6(F.col("value"), "value"))


@_audit("audit_rank_methods", f"{_RUNS}, k AS (SELECT *, dense_rank() OVER (PARTITION BY workload, metric ORDER BY CASE WHEN metric = 'psnr' THEN -value ELSE value END) AS r FROM l), m AS (SELECT metric, method, avg(r) AS mean_rank FROM k GROUP BY 1, 2) SELECT metric, method, {q6('mean_rank', 'mean_rank')}, dense_rank() OVER (PARTITION BY metric ORDER BY mean_rank) AS place FROM m")
def audit_rank_methods(spark, sf_dir):
    return M.rank_methods(table_runs(spark, sf_dir)).select("metric", "method", r6(F.col("mean_rank"), "mean_rank"), F.col("place").cast("long").alias("place"))


@_audit("audit_net_sizes", "SELECT CAST(h AS INTEGER) AS hidden, CAST(l AS INTEGER) AS latent, count(*) AS items, CAST((3 + l) * h + h + 2 * (h * h + h) + h + 1 AS BIGINT) AS parameters FROM (SELECT CAST(floor(l_quantity) AS BIGINT) AS h, CAST(l_linenumber - 1 AS BIGINT) AS l FROM lineitem) GROUP BY h, l")
def audit_net_sizes(spark, sf_dir):
    """Parameters of the nets as wide as the line items' quantities, with as many latent values as lines before the item."""
    size = F.udf(lambda h, n: None if h is None or n is None else NetSpec(hidden=h, latent_dim=n).parameters, "long")
    shapes = load(spark, sf_dir, "lineitem", "l_quantity", "l_linenumber").groupBy(F.floor("l_quantity").cast("int").alias("hidden"), (F.col("l_linenumber") - 1).alias("latent")).agg(F.count("*").alias("items"))
    return shapes.select("hidden", "latent", "items", size("hidden", "latent").alias("parameters"))


@_audit("audit_seam_size", "SELECT CAST(c AS INTEGER) AS channels, CAST(l AS INTEGER) AS layers, count(*) AS items, CAST((27 * c + c) + (l - 2) * (27 * c * c + c) + (27 * c + 1) AS BIGINT) AS parameters FROM (SELECT CAST(floor(l_quantity) AS BIGINT) AS c, CAST(l_linenumber + 1 AS BIGINT) AS l FROM lineitem) GROUP BY c, l")
def audit_seam_size(spark, sf_dir):
    """Parameters of the seam networks with as many channels as the line items' quantities and a layer more than their line numbers."""
    size = F.udf(lambda c, n: None if c is None or n is None else SeamNet(layers=n, channels=c).parameters, "long")
    shapes = load(spark, sf_dir, "lineitem", "l_quantity", "l_linenumber").groupBy(F.floor("l_quantity").cast("int").alias("channels"), (F.col("l_linenumber") + 1).alias("layers")).agg(F.count("*").alias("items"))
    return shapes.select("channels", "layers", "items", size("channels", "layers").alias("parameters"))


def spline_bound(spark, sf_dir):
    """The coder's promise on the given data: no voxel is off by more than the bound."""
    vox, spec = field(spark, sf_dir, SMALL, "f9")
    e = M.errors(vox, spline_decode(spline_encode(vox, spec, 0.02))).first()
    return spark.createDataFrame([(e["n"], bool(e["max_error"] <= 0.02 + 1e-9))], "n long, within boolean")


def tucker_error(spark, sf_dir):
    """The decomposition's promise: the relative error is within the tolerance."""
    vox, spec = field(spark, sf_dir, SMALL, "f9")
    d = tucker_decode(tucker_encode(vox, spec, 0.05))
    err = M.errors(vox, d).first()["mse"]
    power = vox.agg(F.avg(F.col("v") * F.col("v"))).first()[0]
    return spark.createDataFrame([(bool((err / power) ** 0.5 <= 0.05 + 1e-9),)], "within boolean")


QUERIES |= {"spline_bound": spline_bound, "tucker_error": tucker_error, "codec_lineitem": codec_lineitem}
#: The line item volume is 16 x 8 x 8 x 28 in blocks of 4 x 2 x 2; every scale halves all four axes.
ORACLES["codec_lineitem"] = """WITH s AS (SELECT CAST(i AS INTEGER) AS scale, CAST(pow(2, i - 1) AS BIGINT) AS k FROM range(1, 4) r(i)), t AS (SELECT max(4 * (year(l_shipdate) - 1995) + quarter(l_shipdate) - 1) + 1 AS nt FROM lineitem),
 e AS (SELECT scale, CAST(ceil(16 / k) AS BIGINT) AS x, CAST(ceil(8 / k) AS BIGINT) AS y, CAST(ceil(8 / k) AS BIGINT) AS z, CAST(ceil(nt / k) AS BIGINT) AS t FROM s, t)
 SELECT scale, x * y * z * t AS voxels, CAST(ceil(x / 4) * ceil(y / 2) * ceil(z / 2) * t AS BIGINT) AS blocks, true AS same_field, true AS more_accurate FROM e"""
ORACLES |= {"spline_bound": "SELECT CAST(16 * 8 * 8 * 28 AS BIGINT) AS n, true AS within", "tucker_error": "SELECT true AS within"}
