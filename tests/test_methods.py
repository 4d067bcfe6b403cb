"""Worked examples, invariants and exact references of the methods."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from fieldpack.baselines.spline import spline_decode, spline_encode
from fieldpack.operators import assign, entropy, prune, quant, sinenet
from fieldpack.operators import grid as G
from fieldpack.operators import metrics as M
from fieldpack.operators import pyramid as P
from fieldpack.operators.blocks import pack_blocks, unpack_blocks
from fieldpack.operators.seam import SeamNet, apply_seam, convolve, convolve_gradient
from fieldpack.plans import codec as C
from fieldpack.spec import KNOWN_FIELDS, FieldSpec


def voxels(spark, a):
    rows = [(x, y, z, t, float(a[x, y, z, t])) for x in range(a.shape[0]) for y in range(a.shape[1]) for z in range(a.shape[2]) for t in range(a.shape[3])]
    return spark.createDataFrame(rows, "x int, y int, z int, t int, v double")


def array(df, shape):
    out = np.full(shape, np.nan)
    for r in df.collect():
        out[r["x"], r["y"], r["z"], r["t"]] = r["v"]
    return out


def test_up_micro_examples():
    assert P.up_array(np.array([0.0, 4, 2]), (6,), (0,)).tolist() == [0, 2, 4, 3, 2, 2]
    assert P.up_array(np.array([0.0, 4, 2]), (5,), (0,)).tolist() == [0, 2, 4, 3, 2]


@pytest.mark.parametrize("shape", [(5, 4, 3, 3), (4, 4, 1, 1), (3, 1, 2, 6)])
def test_pyramid_equals_whole_array_twin(spark, shape):
    spec = FieldSpec(*shape, 2, 2, 2, 2)
    axes = tuple(i for i, n in enumerate(shape) if n > 1)
    a = np.random.default_rng(1).normal(size=shape)
    low = P.downsample(voxels(spark, a), spec)
    small = P.down_array(a, axes)
    assert np.array_equal(array(low, small.shape), small)
    up = P.upsample(low, spec)
    assert np.allclose(array(up, shape), P.up_array(small, shape, axes), atol=0, rtol=0)
    assert np.array_equal(P.down_array(P.up_array(small, shape, axes), axes), small)  # down(up(c)) = c


def test_up_over_tile_borders(spark):
    shape, axes = (19, 5, 1, 11), (0, 1, 3)
    spec = FieldSpec(*shape, 2, 2, 1, 2)
    small = np.random.default_rng(2).normal(size=(10, 3, 1, 6))
    low = voxels(spark, small)
    assert np.array_equal(array(P.upsample(low, spec), shape), P.up_array(small, shape, axes))
    with pytest.raises(Exception, match="not dense"):
        P.upsample(low.where("x <> 3 OR t <> 2"), spec).count()


def test_ragged_blocks_round_trip(spark):
    spec = FieldSpec(5, 3, 4, 2, 2, 2, 3, 1)
    a = np.random.default_rng(2).normal(size=(5, 3, 4, 2))
    assert np.array_equal(array(unpack_blocks(pack_blocks(voxels(spark, a), spec), spec), a.shape), a)


def test_uniform_fill_worked_example():
    points = np.array([0.0, 1, 2, 3, 10])
    d2 = np.stack([(points - c) ** 2 for c in (1.5, 10.0)], axis=1)
    got = assign.uniform_fill(d2, np.arange(5))
    assert got.tolist() == [0, 0, 1, 0, 1]


def test_uniform_fill_replays_and_sizes():
    rng = np.random.default_rng(3)
    for n, k in ((10, 9), (50, 7), (100, 100), (33, 4), (3, 5)):
        d2 = rng.random((n, k))
        got = assign.uniform_fill(d2, np.arange(n))
        size = np.bincount(got, minlength=k)
        assert size.sum() == n and set(size) <= {n // k, -(-n // k)} and (size == -(-n // k)).sum() in (n % k, k)


def test_importance_worked_example(spark):
    rows = [(1, 1, 1, "w", i, 0, v, True) for i, v in ((0, 0.1), (1, 0.5))] + [(1, 2, 1, "w", i, 0, v, True) for i, v in ((0, 0.2), (1, 0.9))]
    p = spark.createDataFrame(rows, "scale int, net_id long, layer int, kind string, row int, col int, value double, alive boolean")
    loss = spark.createDataFrame([(1, 0.1), (2, 0.3)], "net_id long, loss double")
    got = {(r["net_id"], r["row"]): r["importance"] for r in prune.importance(p, loss, 0.1).collect()}
    assert [round(got[k], 9) for k in ((1, 0), (1, 1), (2, 0), (2, 1))] == [0, 0.5, 0.225, 1.1]
    dead = prune.prune_to(p, loss, 0.5).where("NOT alive").select("net_id", "row").collect()
    assert {tuple(r) for r in dead} == {(1, 0), (2, 0)}
    dead = prune.prune_to(p, loss, 0.5, lam=1.0).where("NOT alive").select("net_id", "row").collect()
    assert {tuple(r) for r in dead} == {(1, 0), (1, 1)}


def test_kth_smallest_narrows_without_loss(spark):
    df = spark.range(5000).select(F.col("id").alias("net_id"), F.lit(0).alias("layer"), F.lit("w").alias("kind"), F.lit(0).alias("row"), F.lit(0).alias("col"), ((F.col("id") * 7919) % 977 / 7.0).alias("importance"))
    want = df.orderBy("importance", "net_id").limit(1234).select("net_id")
    got = prune.kth_smallest(df, 1234, bins=16, most_rows=50).select("net_id")
    assert got.count() == 1234 and got.exceptAll(want).isEmpty()


def test_huffman_examples():
    freq = {0: 5, 1: 2, 2: 1, 3: 1}
    length = entropy.code_lengths(freq)
    assert length == {0: 1, 1: 2, 2: 3, 3: 3} and sum(freq[s] * n for s, n in length.items()) == 15
    assert entropy.code_lengths({7: 7}) == {7: 1}
    rng = np.random.default_rng(4)
    for _ in range(5):
        s = rng.integers(0, 40, 500)
        f = dict(zip(*np.unique(s, return_counts=True)))
        codes = entropy.canonical(entropy.code_lengths({int(k): int(v) for k, v in f.items()}))
        assert math.isclose(sum(2.0 ** -len(c) for c in codes.values()), 1)
        h = -sum(v / 500 * math.log2(v / 500) for v in f.values())
        mean = sum(len(codes[int(k)]) * int(v) for k, v in f.items()) / 500
        assert h <= mean < h + 1
        assert entropy.unpack_symbols(entropy.pack_symbols(s, codes), codes, 500) == s.tolist()


def test_codebook_error_never_rises():
    v = np.random.default_rng(5).normal(size=3000)
    centers, history = quant.lloyd_1d(v, np.ones(3000), 16)
    assert len(centers) <= 16 and all(b <= a + 1e-9 for a, b in zip(history, history[1:]))


def test_network_sizes_and_gradients():
    assert [sinenet.NetSpec(latent_dim=n).parameters for n in (0, 4, 8)] == [1321, 1417, 1513]
    assert SeamNet().parameters == 84_801
    spec = sinenet.NetSpec(hidden=5, depth=2, omega=3.0, latent_dim=2)
    rng = np.random.default_rng(6)
    theta, lat = sinenet.init_params(spec, 1, 1), rng.normal(size=(3, 2))
    coords, values = sinenet.local_coordinates(2, 2, 2), rng.normal(size=(3, 8))
    for loss in ("mse", "l2"):
        _, g, gl = sinenet.loss_and_gradient(spec, theta, lat, coords, values, loss)
        for i in (0, 7, len(theta) - 1):
            d = np.zeros_like(theta)
            d[i] = 1e-6
            num = (sinenet.loss_and_gradient(spec, theta + d, lat, coords, values, loss)[0] - sinenet.loss_and_gradient(spec, theta - d, lat, coords, values, loss)[0]) / 2e-6
            assert abs(num - g[i]) < 1e-5
        d = np.zeros_like(lat)
        d[1, 1] = 1e-6
        num = (sinenet.loss_and_gradient(spec, theta, lat + d, coords, values, loss)[0] - sinenet.loss_and_gradient(spec, theta, lat - d, coords, values, loss)[0]) / 2e-6
        assert abs(num - gl[1, 1]) < 1e-5


def test_width_fits_the_budget():
    for budget in (2_000, 50_000, 1_000_000):
        w = sinenet.width_for_bytes(budget, 8)
        assert 4 * sinenet.parameters_for_width(w, 8) <= budget < 4 * sinenet.parameters_for_width(w + 1, 8)


def test_seam_network_gradient_and_tiles(spark):
    net = SeamNet(layers=2, channels=3, seed=2)
    theta = net.start() + np.random.default_rng(7).normal(0, 0.05, net.parameters)
    tile, inside = np.random.default_rng(8).normal(size=(4, 4, 4)), np.ones((4, 4, 4))
    kept = []
    out = convolve(net, theta, tile, inside, kept)
    g = convolve_gradient(net, theta, kept, inside, 2 * out)
    for i in (0, 40, len(theta) - 1):
        d = np.zeros_like(theta)
        d[i] = 1e-6
        num = (np.sum(convolve(net, theta + d, tile, inside) ** 2) - np.sum(convolve(net, theta - d, tile, inside) ** 2)) / 2e-6
        assert abs(num - g[i]) < 1e-3 * max(1, abs(num))
    a = np.random.default_rng(9).normal(size=(5, 6, 4, 1))
    net.theta = theta
    whole = convolve(net, theta, a[..., 0], np.ones(a.shape[:3]))
    got = array(apply_seam(voxels(spark, a), FieldSpec(5, 6, 4, 1, 2, 3, 2, 1), net), a.shape)
    assert np.allclose(got[..., 0], whole)


def test_known_geometry():
    want = {"combustion": [107520, 6720, 432], "half_cylinder": [51200, 3200, 200], "tangaroa": [259200, 16200, 1026], "supernova_2": [13824, 1728, 216, 27]}
    for name, blocks in want.items():
        spec = KNOWN_FIELDS[name][0]
        got = [math.ceil(spec.nx / (2**i * spec.bx)) * math.ceil(spec.ny / (2**i * spec.by)) * math.ceil(spec.nz / (2**i * spec.bz)) * math.ceil(spec.nt / 2**i) for i in range(spec.scales)]
        assert got == blocks
    assert KNOWN_FIELDS["combustion"][0].raw_bytes == 11_612_160_000


def test_measures_micro(spark):
    p = spark.createDataFrame([(0, 0.0, 0.0, 0.0)], "t int, px double, py double, pz double")
    q = spark.createDataFrame([(0, 1.0, 0.0, 0.0), (0, 3.0, 0.0, 0.0)], "t int, px double, py double, pz double")
    for cells in (False, True):
        assert M.chamfer(p, q, exact_cells=cells).first()["chamfer"] == pytest.approx(3.0)
    v = spark.createDataFrame([(0, 0, 0, 0, 1.0), (1, 0, 0, 0, 3.0)], "x int, y int, z int, t int, v double")
    assert M.iso_points(v, 1.5).first()["px"] == pytest.approx(0.25)


@pytest.mark.parametrize("kind", ["linear", "cubic"])
def test_spline_bound_and_determinism(spark, kind):
    spec = FieldSpec(7, 6, 5, 3, 2, 2, 2, 2)
    vox = G.analytic_field(spark, spec)
    got = M.errors(vox, spline_decode(spline_encode(vox, spec, 0.03, 2, kind))).first()
    assert got["n"] == spec.voxels and got["max_error"] <= 0.03 + 1e-9


def test_codec_round_trip(spark, tmp_path):
    spec = FieldSpec(8, 8, 8, 2, 4, 4, 4, 2)
    vox = C.keep(G.normalize(G.analytic_field(spark, spec)), "test")
    cfg = C.CodecConfig.quick(10, tau=5e-2, per_net=(4, 8), net=sinenet.NetSpec(hidden=8, latent_dim=2), kmeans_steps=2)
    archive, decoded = C.encode(vox, spec, cfg)
    C.write_archive(archive, str(tmp_path / "a"))
    again = C.read_archive(spark, str(tmp_path / "a"))
    whole = C.decode(again)
    assert M.errors(decoded, whole).first()["max_error"] < 1e-9
    assert {c for f in ("streams", "masks", "latents", "bitmap") for c, t in spark.read.parquet(str(tmp_path / "a" / f)).dtypes if "double" in t or "float" in t} == set()
    stored = sum(spark.read.parquet(str(tmp_path / "a" / f)).agg(F.sum(F.octet_length(c))).first()[0] for f, c in (("streams", "data"), ("masks", "mask"), ("latents", "latent")))
    assert stored == sum(p.sizes[k] for p in archive.parts for k in ("parameters", "mask", "latents"))
    assert again.parts[0].flags.exceptAll(archive.parts[0].flags).isEmpty() and again.parts[1].flags.exceptAll(archive.parts[1].flags).isEmpty()
    part = C.decode(again, region={"x": (2, 5), "t": (1, 1)})
    assert part.exceptAll(whole.where("x BETWEEN 2 AND 5 AND t = 1")).isEmpty() and part.count() == 4 * 8 * 8
    assert C.decode(again, upto=2).count() == 4 * 4 * 4 * 1
    rows = archive.parts[-1].nets
    assert rows.where(F.exists(F.arrays_zip("theta", "alive"), lambda s: ~s["alive"] & (s["theta"] != 0))).isEmpty()  # pruned stay zero


@pytest.mark.parametrize("change", [{"quant": "net"}, {"quant": None, "entropy": False}, {"entropy": False, "prune": None, "loss": "l2"}])
def test_stored_forms(spark, tmp_path, change):
    spec = FieldSpec(4, 4, 4, 2, 2, 2, 2, 1)
    vox = C.keep(G.normalize(G.analytic_field(spark, spec)), "test")
    cfg = C.CodecConfig.quick(4, per_net=(4,), net=sinenet.NetSpec(hidden=4, latent_dim=2), kmeans_steps=1, **change)
    archive, decoded = C.encode(vox, spec, cfg)
    C.write_archive(archive, str(tmp_path / "a"))
    assert M.errors(decoded, C.decode(C.read_archive(spark, str(tmp_path / "a")))).first()["max_error"] < 1e-9


def test_empty_and_constant_fields(spark):
    spec = FieldSpec(4, 4, 4, 2, 2, 2, 2, 2)
    none = spark.createDataFrame([], "x int, y int, z int, t int, v double")
    assert G.densify(none, spec, 0.0).count() == spec.voxels
    flat = G.normalize(G.analytic_field(spark, spec, "constant"))
    assert flat.where("v <> 0").isEmpty()


def test_registered_workloads_read_their_tables(spark, sf_dir, monkeypatch):
    from fieldpack.plans import workloads as W

    assert not {"w03", "w17", "w19"} & set(W.QUERIES)  # trained: only with the whole schedule, outside the registry
    seen = []

    def stop(vox, spec, *a, **b):
        raise StopIteration

    monkeypatch.setattr(W, "encode", stop)
    monkeypatch.setattr(W, "global_encode", stop)
    monkeypatch.setattr(W, "field", lambda s, d, preset, name="f0": seen.append((preset.name, name)) or (None, None))
    for name in ("w03", "w17", "w19"):
        with pytest.raises(StopIteration):
            W.WORKLOADS[name](spark, sf_dir)
    assert seen == [("published", "f9"), ("published", "f0"), ("published", "f1")]
    monkeypatch.undo()
    rows = {(r["workload"], r["metric"]): r["value"] for r in W.QUERIES["w20"](spark, sf_dir).collect()}
    assert {w for w, _ in rows} == {"w20-f9", "w20-f10"} and all(v > 0 for v in rows.values())


def test_assignment_is_the_same_at_every_size(spark, monkeypatch):
    x = np.random.default_rng(8).normal(size=(26, 4))
    blocks = spark.createDataFrame([(i, [float(v) for v in row]) for i, row in enumerate(x)], "block_id long, values array<double>")
    got = lambda scheme: {r["block_id"]: r["net_id"] for r in C.assign_blocks(blocks, 4, C.CodecConfig(scheme=scheme, kmeans_steps=2), 4).collect()}
    want = {s: got(s) for s in ("uniform", "kmeans")}
    monkeypatch.setattr(C, "MOST_FILLED", 0, raising=False)
    monkeypatch.setattr(assign, "uniformize_sharded", lambda *a, **b: pytest.fail("shards were not asked for"))
    assert {s: got(s) for s in want} == want
    monkeypatch.setattr(assign, "MOST_CENTROID_VALUES", 0)
    for s in want:
        with pytest.raises(ValueError, match="sharded"):
            got(s)


def test_matched_nets():
    from fieldpack.plans.workloads import match_params, match_size

    base = sinenet.NetSpec(hidden=24, latent_dim=4)
    for target in (1e4, 1e5, 1e6):
        net = match_size(target, 50, 4.0, base)
        wider = sinenet.NetSpec(hidden=net.hidden + 1, latent_dim=0)
        assert net.latent_dim == 0 and 50 * 4 * wider.parameters > target and (net.hidden == 1 or 50 * 4 * net.parameters <= target)
    assert match_params(50 * sinenet.NetSpec(hidden=9, latent_dim=0).parameters, 50, base).hidden == 9


def test_nearest_distances_in_short_plans(spark):
    """Copies, far points and a timestep without partners: as brute force, and no plan repeats an earlier round."""
    rng = np.random.default_rng(4)
    a, b = np.round(rng.uniform(0, 20, (60, 3)), 1), np.round(rng.uniform(0, 12, (40, 3)), 1)
    a[0], a[1] = (500.0, 0.0, 0.0), (-90.0, 3.0, 2.0)
    rows = lambda x, t=0: [(t, *map(float, r)) for r in x]
    kind = "t int, px double, py double, pz double"
    p, q = spark.createDataFrame(rows(a) * 3 + rows(a[:5], 1), kind), spark.createDataFrame(rows(b) * 4, kind)
    near = M.nearest_distances(p, q)
    want = {r: min(math.dist(r[1:], s) for s in b) for r in rows(a)}
    got = {tuple(r[:4]): r["d"] for r in near.collect()}
    assert near.count() == len(got) and got == pytest.approx(want)
    for df, joins in ((near, 1), (M.chamfer(p, q, exact_cells=True), 3)):
        assert df._jdf.queryExecution().optimizedPlan().toString().count("Join ") <= joins
