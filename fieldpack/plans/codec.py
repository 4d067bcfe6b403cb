"""The multiscale network codec: encode, decode, archive."""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass, field, replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import assign as A
from ..operators import entropy as E
from ..operators import prune as Z
from ..operators import quant as Q
from ..operators import train as N
from ..operators.blocks import empty_bitmap, pack_blocks, unpack_blocks, values_energy
from ..operators.pyramid import compose, downsample, residual, upsample, upsample_sparse
from ..operators.seam import SeamNet, apply_seam, train_seam
from ..operators.sinenet import NetSpec, backward, forward, local_coordinates, net_inputs
from ..spec import AXES, FieldSpec
from .stages import keep


@dataclass(frozen=True)
class CodecConfig:
    """Everything that an encoder may vary; the defaults follow the published configuration for time-varying fields."""

    tau: float = 1e-4
    energy: str = "l2"
    per_net: tuple[int, ...] = (8, 16, 32)  # from the coarsest scale
    net: NetSpec = NetSpec()
    schedule: N.Schedule = N.Schedule()
    scheme: str = "uniform"  # uniform, kmeans, single, order, sharded
    prune: str | None = "block"  # block, magnitude, local or None
    lam: float = 0.1
    quant: str | None = "scale"  # scale, net or None
    entropy: bool = True
    loss: str = "mse"
    loop: str = "closed"
    seam: SeamNet | None = None
    seed: int = 0
    kmeans_steps: int = 8

    @staticmethod
    def quick(epochs: int = 40, **changes) -> CodecConfig:
        """The same method with short training, for tests and small machines."""
        rounds = ((epochs // 2, 0.2), (3 * epochs // 4, 0.3))
        base = CodecConfig(schedule=N.Schedule(epochs=(epochs,), rate=3e-3, rounds=rounds, finetune=2), kmeans_steps=4)
        return replace(base, **changes)

    @staticmethod
    def single(base: CodecConfig, compress: bool = False) -> CodecConfig:
        """One small net per block, without latent codes; with `compress`, pruned, quantized and coded."""
        c = replace(base, scheme="single", net=replace(base.net, latent_dim=0))
        return c if compress else replace(c, prune=None, quant=None, entropy=False)


@dataclass
class StoredScale:
    """A scale as it lies in the archive: coded streams, masks, quantized latents, and the small tables to read them."""

    streams: DataFrame  # net_id, grp, n, data, centers (a codebook of the net's own, else null)
    masks: DataFrame  # net_id, mask: a bit for each parameter
    latents: DataFrame  # block_id, net_id, latent
    words: dict[int, dict[int, str]]  # by group of a layer and kind: each code's word
    centers: dict[int, list[float]]  # by group: the codebook
    low: float = 0.0
    step: float = 0.0  # 0: latents are 32-bit floats


@dataclass
class ScalePart:
    """What the archive keeps of a scale, and its sizes in bytes."""

    scale: int
    spec: FieldSpec
    flags: DataFrame  # block_id, effective
    nets: DataFrame  # N.NETS, values as the archive's reader gets them
    codes: DataFrame  # N.CODES, the same
    sizes: dict[str, float] = field(default_factory=dict)
    stored: StoredScale | None = None


@dataclass
class Archive:
    spec: FieldSpec
    config: CodecConfig
    parts: list[ScalePart]  # from the coarsest scale
    seam: SeamNet | None = None
    header_bytes: int = 256

    def breakdown(self, spark: SparkSession) -> DataFrame:
        """scale, part, bytes; scale 0 holds the header and the seam network."""
        rows = [(p.scale, k, float(v)) for p in self.parts for k, v in p.sizes.items()]
        rows.append((0, "header", float(self.header_bytes)))
        if self.seam is not None:
            rows.append((0, "seam", float(self.seam.bytes)))
        return spark.createDataFrame(rows, "scale int, part string, bytes double")

    @property
    def bytes(self) -> float:
        return sum(sum(p.sizes.values()) for p in self.parts) + self.header_bytes + (self.seam.bytes if self.seam else 0)


#: So many distances are filled in one task; beyond that the same assignment is made in rounds of proposals.
MOST_FILLED = 50_000_000


def assign_blocks(blocks: DataFrame, b: int, cfg: CodecConfig, size: int) -> DataFrame:
    """block_id, net_id by the configured scheme, which is the same at every size; shards only where they are asked for."""
    if cfg.scheme == "single":
        return A.assign_single(blocks)
    if cfg.scheme == "order":
        return A.assign_order(blocks, b)
    if cfg.scheme == "sharded":
        return A.uniformize_sharded(blocks, size, b).select("block_id", "net_id")
    n = blocks.count()
    k = A.net_count(n, b)
    if k <= 1:
        return blocks.select("block_id", F.lit(0).alias("net_id"))
    if k * size > A.MOST_CENTROID_VALUES:
        raise ValueError(f"too many centroids to send to workers for scheme '{cfg.scheme}': ask for 'sharded'")
    centers, _ = A.kmeans(blocks, k, cfg.kmeans_steps)
    if cfg.scheme == "kmeans":
        return A.assign_nearest(blocks, centers).select("block_id", "net_id")
    if k * n > MOST_FILLED:
        table = blocks.sparkSession.createDataFrame([(i, [float(x) for x in c]) for i, c in enumerate(centers)], "net_id int, center array<double>")
        return A.uniformize_rounds(keep(A.distances(blocks, table), "uniform-distances"), most_rounds=k * n).select("block_id", "net_id")
    return A.uniform_blocks(blocks, centers)


def _finetune(blocks: DataFrame, nets: DataFrame, codes: DataFrame, coded: DataFrame, books: DataFrame, by: list[str], spec: FieldSpec, net: NetSpec, epochs: int, rate: float, scale: int, loss: str) -> DataFrame:
    """Codebooks after some epochs with fixed indices: a center's gradient is the sum over its members. Each epoch
    one pass makes partial sums in the workers; only (codes x groups) sums reach the driver."""
    rows = books.orderBy(*by, "code").collect()
    place = {tuple(r[c] for c in [*by, "code"]): i for i, r in enumerate(rows)}
    centers = np.array([r["center"] for r in rows], dtype=float)
    layout = nets.sparkSession.createDataFrame([(p, *w) for p, w in enumerate(net.layout())], "p int, layer int, kind string, row int, col int")
    index = nets.sparkSession.createDataFrame([(*k, i) for k, i in place.items()], ", ".join(f"{c} {dict(coded.dtypes)[c]}" for c in by) + ", code int, slot int")
    slots = coded.join(F.broadcast(index), [*by, "code"], "left").join(F.broadcast(layout), ["layer", "kind", "row", "col"]).groupBy("net_id").agg(F.array_sort(F.collect_list(F.struct("p", F.coalesce("slot", F.lit(-1)).alias("slot")))).alias("x"))
    work = keep(blocks.select("block_id", "values").join(codes, "block_id").join(slots.select("net_id", F.transform("x", lambda s: s["slot"]).alias("slots")), "net_id").select("values", "latent", "slots"), "finetune")
    coords = local_coordinates(spec.bx, spec.by, spec.bz)
    n = max(1, work.count())
    from ..operators.sinenet import Adam

    adam = Adam(len(centers), decay=0.0)
    for _ in range(epochs):
        now = centers

        def run(batches, now=now):
            total = np.zeros(len(now))
            for pdf in batches:
                for values, latent, slot in zip(pdf["values"], pdf["latent"], pdf["slots"]):
                    slot = np.asarray(slot)
                    theta = np.where(slot >= 0, now[np.maximum(slot, 0)], 0.0)
                    kept: list = []
                    e = forward(net, theta, net_inputs(coords, np.asarray(latent, dtype=float).reshape(1, -1)), kept) - np.asarray(values)
                    d = 2 * e / len(e) if loss == "mse" else e / (np.sqrt((e * e).sum()) + 1e-12)
                    g, _ = backward(net, theta, kept, d)
                    np.add.at(total, slot[slot >= 0], g[slot >= 0])
            yield pd.DataFrame({"slot": np.arange(len(now)), "g": total})

        sums = work.mapInPandas(run, "slot long, g double").groupBy("slot").agg(F.sum("g").alias("g")).collect()
        g = np.zeros(len(centers))
        for r in sums:
            g[r["slot"]] = r["g"] / n
        centers = adam.step(centers, g, rate)
    return nets.sparkSession.createDataFrame([(*k, float(centers[i])) for k, i in place.items()], ", ".join(f"{c} {dict(coded.dtypes)[c]}" for c in by) + ", code int, center double")


RAW = -1  # the group of parameters that are kept as 32-bit floats
STREAMS = "net_id long, grp int, n int, data binary, centers binary"


def _group(layer, kind):
    return F.col(layer) * 2 + (F.col(kind) == "b").cast("int")


def _streams(coded: DataFrame, words: dict[int, dict[int, str]], net: NetSpec, local: DataFrame | None) -> DataFrame:
    """One row per net, layer and kind: its alive codes in the layout's order, coded. A group holds a net's layer."""
    layout = coded.sparkSession.createDataFrame([(p, *w) for p, w in enumerate(net.layout())], "p int, layer int, kind string, row int, col int")
    placed = coded.where("alive").join(F.broadcast(layout), ["layer", "kind", "row", "col"])
    lists = placed.groupBy("net_id", _group("layer", "kind").alias("grp"), "kind").agg(F.transform(F.array_sort(F.collect_list(F.struct("p", "code"))), lambda s: s["code"]).alias("codes"))
    if local is not None:
        books = local.groupBy("net_id", "kind").agg(F.transform(F.array_sort(F.collect_list(F.struct("code", "center"))), lambda s: s["center"]).alias("book"))
        lists = lists.join(books, ["net_id", "kind"])
    else:
        lists = lists.withColumn("book", F.lit(None).cast("array<double>"))

    def run(batches):
        for pdf in batches:
            data = [E.pack_symbols(np.asarray(c), words[g]) for c, g in zip(pdf["codes"], pdf["grp"])]
            own = [None if x is None else np.asarray(x, dtype="<f4").tobytes() for x in pdf["book"]]
            yield pd.DataFrame({"net_id": pdf["net_id"], "grp": pdf["grp"], "n": [len(c) for c in pdf["codes"]], "data": data, "centers": own})

    return lists.select("net_id", "grp", "codes", "book").mapInPandas(run, STREAMS)


def _raw_streams(nets: DataFrame) -> DataFrame:
    def run(batches):
        for pdf in batches:
            alive = [np.asarray(t, dtype="<f4")[np.asarray(a, dtype=bool)] for t, a in zip(pdf["theta"], pdf["alive"])]
            yield pd.DataFrame({"net_id": pdf["net_id"], "grp": RAW, "n": [len(x) for x in alive], "data": [x.tobytes() for x in alive], "centers": None})

    return nets.select("net_id", "theta", "alive").mapInPandas(run, STREAMS)


def _masks(nets: DataFrame) -> DataFrame:
    def run(batches):
        for pdf in batches:
            yield pd.DataFrame({"net_id": pdf["net_id"], "mask": [np.packbits(np.asarray(a, dtype=bool)).tobytes() for a in pdf["alive"]]})

    return nets.select("net_id", "alive").mapInPandas(run, "net_id long, mask binary")


def _latent_type(step: float, beta: int) -> str:
    return "<f4" if step == 0 else "<u1" if beta <= 8 else "<u2"


def _pack_latents(codes: DataFrame, low: float, step: float, beta: int) -> DataFrame:
    def run(batches):
        for pdf in batches:
            x = [np.asarray(v, dtype=float) for v in pdf["latent"]]
            x = [(np.round((v - low) / step) if step else v).astype(_latent_type(step, beta)).tobytes() for v in x]
            yield pd.DataFrame({"block_id": pdf["block_id"], "net_id": pdf["net_id"], "latent": x})

    return codes.select("block_id", "net_id", "latent").mapInPandas(run, "block_id long, net_id long, latent binary")


def restore(stored: StoredScale, net: NetSpec, beta: int) -> tuple[DataFrame, DataFrame]:
    """Nets and latent codes out of the stored form: what decoders see. Codebooks and words are small tables."""
    places = [(layer * 2 + (kind == "b")) for layer, kind, _, _ in net.layout()]
    places, words, centers = np.array(places), stored.words, stored.centers
    low, step, kind = stored.low, stored.step, _latent_type(stored.step, beta)

    def nets(batches):
        for pdf in batches:
            thetas, alives = [], []
            for mask, streams in zip(pdf["mask"], pdf["streams"]):
                alive = np.unpackbits(np.frombuffer(mask, dtype=np.uint8))[: len(places)].astype(bool)
                theta = np.zeros(len(places))
                for s in streams:
                    if s["grp"] == RAW:
                        theta[alive] = np.frombuffer(s["data"], dtype="<f4")
                        continue
                    book = np.array(centers[s["grp"]]) if s["centers"] is None else np.frombuffer(s["centers"], dtype="<f4").astype(float)
                    got = E.unpack_symbols(bytes(s["data"]), words[s["grp"]], s["n"])
                    theta[alive & (places == s["grp"])] = book[got]
                thetas.append(theta), alives.append(alive)
            yield pd.DataFrame({"net_id": pdf["net_id"], "theta": thetas, "alive": alives, "loss": [float("nan")] * len(pdf)})

    def latents(batches):
        for pdf in batches:
            x = [np.frombuffer(v, dtype=kind).astype(float) for v in pdf["latent"]]
            yield pd.DataFrame({"block_id": pdf["block_id"], "net_id": pdf["net_id"], "latent": [v * step + low if step else v for v in x]})

    of_net = stored.streams.groupBy("net_id").agg(F.collect_list(F.struct("grp", "n", "data", "centers")).alias("streams"))
    return stored.masks.join(of_net, "net_id", "left").mapInPandas(nets, N.NETS), stored.latents.mapInPandas(latents, N.CODES)


def _compress(part: ScalePart, blocks: DataFrame, cfg: CodecConfig) -> None:
    """Brings the scale into its stored form, counts every part's bytes in it, and reads nets and codes back from it."""
    net, spec, scale, beta = cfg.net, part.spec, part.scale, cfg.schedule.beta
    n_nets, n_blocks = part.nets.count(), part.codes.count()
    low = step = 0.0
    if net.latent_dim and cfg.quant:  # latents share a uniform grid of 2^beta values between their ends
        ends = part.codes.select(F.explode("latent").alias("v")).agg(F.min("v"), F.max("v")).first()
        low, high = ends[0] or 0.0, ends[1] or 0.0
        step = (high - low) / ((1 << beta) - 1) or 1.0
    words: dict[int, dict[int, str]] = {}
    centers: dict[int, list[float]] = {}
    symbols = 0
    if cfg.quant is None:
        streams = _raw_streams(part.nets)
    else:
        rows = keep(N.parameter_rows(part.nets, net, scale), "parameters")
        by = Q.group_columns("net" if cfg.quant == "net" else "scale", group="all" if cfg.quant == "net" else "layer")
        books = keep(Q.codebooks(rows, beta, by), "codebooks")
        coded = keep(Q.quantize(rows, books, by), "coded")
        if cfg.schedule.finetune and cfg.quant == "scale":  # a net's own codebook is not fine-tuned: its centers are its own least squares
            books = _finetune(blocks, part.nets, part.codes, coded, books, by, spec, net, cfg.schedule.finetune, cfg.schedule.finetune_rate, scale, cfg.loss)
        if cfg.quant == "scale":
            for r in books.orderBy("layer", "kind", "code").collect():  # at most 2^beta of a group
                centers.setdefault(r["layer"] * 2 + (r["kind"] == "b"), []).append(float(np.float32(r["center"])))
        counts: dict[int, dict[int, int]] = {}
        for r in coded.where("alive").groupBy(_group("layer", "kind").alias("grp"), "code").agg(F.count("*").alias("n")).collect():
            counts.setdefault(r["grp"], {})[r["code"]] = r["n"]
        for g, freq in counts.items():  # one table for each group; without entropy coding words of beta bits
            words[g] = E.canonical(E.code_lengths(freq)) if cfg.entropy else {c: format(c, f"0{beta}b") for c in freq}
        symbols = sum(map(len, words.values())) if cfg.entropy else 0
        streams = _streams(coded, words, net, books if cfg.quant == "net" else None)
    kept = lambda df, name: keep(df, f"{name}-{scale}")
    part.stored = StoredScale(kept(streams, "streams"), kept(_masks(part.nets), "masks"), kept(_pack_latents(part.codes, low, step, beta), "latents"), words, centers, low, step)
    size = lambda df, col: float(df.agg(F.sum(F.octet_length(col).cast("long"))).first()[0] or 0)
    part.sizes = {
        "bitmap": 8 * -(-part.flags.count() // 64), "assignment": 0.0 if cfg.scheme == "single" else n_blocks * max(1, int(np.ceil(np.log2(max(2, n_nets))))) / 8,
        "latents": size(part.stored.latents, "latent"), "parameters": size(part.stored.streams, "data"),
        "codebooks": 4.0 * sum(map(len, centers.values())) + size(part.stored.streams, "centers"), "huffman": 3.0 * symbols, "mask": size(part.stored.masks, "mask") if cfg.prune else 0.0,
    }
    nets, codes = restore(part.stored, net, beta)
    part.nets, part.codes = kept(nets, "nets"), kept(codes, "codes")


def encode_scale(target: DataFrame, spec: FieldSpec, scale: int, level: int, cfg: CodecConfig, coarsest: bool) -> tuple[ScalePart, DataFrame]:
    """One scale: the archive's part and the decoded target as voxels."""
    blocks = keep(pack_blocks(target, spec), f"blocks-{scale}")
    live = F.lit(True) if coarsest else values_energy(F.col("values"), cfg.energy) >= cfg.tau
    flags = keep(blocks.select("block_id", live.alias("effective")), f"flags-{scale}")
    used = keep(blocks.where(live).select("block_id", "values"), f"effective-{scale}")
    b = cfg.per_net[min(level, len(cfg.per_net) - 1)]
    assigned = keep(assign_blocks(used, b, cfg, spec.block_voxels), f"assign-{scale}")
    nets, codes = N.start_nets(assigned, cfg.net, scale, cfg.seed)
    for epochs, sparsity, rate in cfg.schedule.segments(level, cfg.prune is not None):
        if sparsity is not None:
            rows = keep(N.parameter_rows(nets, cfg.net, scale), "parameters")
            lam = cfg.lam if cfg.prune == "block" else 0.0
            cut = Z.prune_to(rows, nets, sparsity, lam, len(cfg.net.layers), "net" if cfg.prune == "local" else "scale")
            nets = N.nets_of_rows(cut, cfg.net, nets)
        trained = keep(N.train_segment(used, nets, codes, spec, cfg.net, epochs, rate, cfg.loss), f"trained-{scale}")
        nets, codes = N.trained_nets(trained), N.trained_codes(trained, cfg.net.latent_dim)
    part = ScalePart(scale, spec, flags, nets, codes)
    _compress(part, used, cfg)
    return part, decode_scale(part, cfg)


def decode_scale(part: ScalePart, cfg: CodecConfig) -> DataFrame:
    """The voxels of a scale's kept blocks."""
    return unpack_blocks(N.infer(part.nets, part.codes, part.spec, cfg.net), part.spec)


def encode(vox: DataFrame, spec: FieldSpec, cfg: CodecConfig) -> tuple[Archive, DataFrame]:
    """The archive of a normalised dense field, and the decoded field."""
    fields, specs = [vox], [spec]
    for _ in range(spec.scales - 1):
        fields.append(downsample(fields[-1], specs[-1]))
        specs.append(specs[-1].coarser())
    parts: list[ScalePart] = []
    decoded = None
    for level, scale in enumerate(range(spec.scales, 0, -1)):
        s, own = specs[scale - 1], fields[scale - 1]
        if decoded is None:
            part, decoded = encode_scale(own, s, scale, level, cfg, True)
        else:
            up = keep(upsample(decoded, s), f"up-{scale}")
            base = up if cfg.loop == "closed" else upsample(fields[scale], s)
            part, res = encode_scale(residual(own, base), s, scale, level, cfg, False)
            decoded = compose(up, res)
        decoded = keep(decoded.select(*AXES, "v"), f"decoded-{scale}")
        parts.append(part)
    archive = Archive(spec, cfg, parts)
    if cfg.seam is not None:
        archive.seam = train_seam(decoded, vox, spec, cfg.seam)
        decoded = keep(apply_seam(decoded, spec, archive.seam), "seam")
    return archive, decoded


def decode(archive: Archive, upto: int = 1, region: dict[str, tuple[int, int]] | None = None) -> DataFrame:
    """The field at scale `upto` (1 is the finest). A region {axis: (first, last)} at the finest scale limits which
    blocks are inferred at every scale: its box, halved per scale and widened by the interpolation's reach."""
    decoded = None
    for part in archive.parts:
        if part.scale < upto:
            break
        need = part
        if region is not None:
            need = replace(part, codes=part.codes.join(_needed(part, region), "block_id", "left_semi"))
        got = decode_scale(need, archive.config)
        if decoded is None:
            decoded = got
        else:
            up = upsample if region is None else upsample_sparse  # a region's field has holes
            decoded = compose(up(decoded, part.spec), got)
    if upto == 1 and archive.seam is not None:
        decoded = apply_seam(decoded, archive.spec, archive.seam)
    if region is not None:
        for a, (lo, hi) in region.items():
            decoded = decoded.where((F.col(a) >= lo) & (F.col(a) <= hi))
    return decoded


def _needed(part: ScalePart, region: dict[str, tuple[int, int]]) -> DataFrame:
    from ..operators.grid import block_coords

    c = block_coords(part.spec, F.col("block_id"))
    size = {"x": part.spec.bx, "y": part.spec.by, "z": part.spec.bz, "t": 1}
    keep_if = F.lit(True)
    shrink = 1 << (part.scale - 1)
    for a, (lo, hi) in region.items():
        halved = shrink if part.spec.extents[a] > 1 and (a != "t" or part.spec.halve_time) else 1
        first, last = lo // halved - 1 - (lo // halved > 0), hi // halved + 2
        cell = c["t"] if a == "t" else c[f"b{a}"]
        keep_if = keep_if & (cell * size[a] <= last) & ((cell + 1) * size[a] > first)
    return part.flags.where(keep_if).select("block_id")


def write_archive(archive: Archive, path: str) -> None:
    """Parquet folders streams, masks and latents, partitioned by scale, the bitmap of effective blocks, and one header
    row with the geometry, the configuration, codebooks and code words. Nothing uncoded is written."""
    spark = archive.parts[0].flags.sparkSession
    small = {str(p.scale): {"sizes": p.sizes, "low": p.stored.low, "step": p.stored.step, "words": p.stored.words, "centers": p.stored.centers} for p in archive.parts}
    header = {"spec": asdict(archive.spec), "config": {**asdict(replace(archive.config, seam=None))}, "scales": small, "seam": archive.seam.state() if archive.seam else None}
    spark.createDataFrame([(json.dumps(header),)], "header string").coalesce(1).write.mode("overwrite").parquet(f"{path}/header")
    for name in ("streams", "masks", "latents", "bitmap"):
        out = None
        for p in archive.parts:
            df = empty_bitmap(p.flags.withColumn("scale", F.lit(p.scale))).drop("scale") if name == "bitmap" else getattr(p.stored, name)
            df = df.withColumn("scale", F.lit(p.scale))
            out = df if out is None else out.unionByName(df)
        out.write.mode("overwrite").partitionBy("scale").parquet(f"{path}/{name}")


def read_archive(spark: SparkSession, path: str) -> Archive:
    head = json.loads(spark.read.parquet(f"{path}/header").first()[0])
    spec = FieldSpec(**head["spec"])
    c = head["config"]
    cfg = CodecConfig(**{**c, "net": NetSpec(**c["net"]), "per_net": tuple(c["per_net"]), "schedule": N.Schedule(**{**c["schedule"], "epochs": tuple(c["schedule"]["epochs"]), "rounds": tuple(map(tuple, c["schedule"]["rounds"]))})})
    parts = []
    for scale in range(spec.scales, 0, -1):
        of = lambda name: spark.read.parquet(f"{path}/{name}").where(F.col("scale") == scale).drop("scale")  # noqa: E731, B023
        small, own = head["scales"][str(scale)], spec.at_scale(scale)
        words = {int(g): {int(c): w for c, w in t.items()} for g, t in small["words"].items()}
        stored = StoredScale(of("streams"), of("masks"), of("latents"), words, {int(g): c for g, c in small["centers"].items()}, small["low"], small["step"])
        block = spark.range(own.blocks).withColumn("word", F.floor(F.col("id") / 64))
        set_ = F.expr("coalesce(shiftrightunsigned(bits, cast(id % 64 as int)) & 1, 0) = 1")
        flags = block.join(of("bitmap"), "word", "left").select(F.col("id").alias("block_id"), set_.alias("effective"))
        parts.append(ScalePart(scale, own, flags, *restore(stored, cfg.net, cfg.schedule.beta), small["sizes"], stored))
    return Archive(spec, cfg, parts, SeamNet.from_state(head["seam"]) if head["seam"] else None)
