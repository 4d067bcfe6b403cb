"""Queries over gridded fields, with their SQL twins."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import blocks as B
from ..operators import grid as G
from ..operators import metrics as M
from ..operators import pyramid as P
from ..operators.volumes import event_cells, lineitem_cells, volume
from ..spec import AXES, F1, F2, F3, F4, F7, KNOWN_FIELDS, FieldSpec
from . import mean_codec as MC
from . import twins as T

QUERIES, ORACLES = {}, {}
TAU = 0.01


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return add


def r6(c, name: str, digits: int = 6):
    """Rounded for comparison between engines; -0.0 becomes 0.0."""
    return (F.round(c, digits) + 0.0).alias(name)


def q6(e: str, name: str, digits: int = 6) -> str:
    return f"round({e}, {digits}) + 0.0 AS {name}"


VOX = f"x, y, z, t, {q6('v', 'v')}"


def vox6(df: DataFrame) -> DataFrame:
    return df.select(*AXES, r6(F.col("v"), "v"))


def f9(spark: SparkSession, sf_dir: str) -> DataFrame:
    return G.normalize(volume(spark, sf_dir, "f9")[0])


# gridding and geometry


@query("grid_lineitem", f"SELECT x, y, z, t, v AS cents, n, {q6('v / n / 100.0', 'v')} FROM ({T.F1_CELLS})")
def grid_lineitem(spark, sf_dir):
    return lineitem_cells(spark, sf_dir).select(*AXES, F.col("v").alias("cents"), "n", r6(F.col("v") / F.col("n") / 100, "v"))


@query("grid_events", f"SELECT x, y, z, t, v AS cents, n FROM ({T.F2_CELLS})")
def grid_events(spark, sf_dir):
    return event_cells(spark, sf_dir).select(*AXES, F.col("v").alias("cents"), "n")


@query("densify_lineitem", f"WITH cells AS ({T.F1_CELLS}) {T.dense('cells', F1)}")
def densify_lineitem(spark, sf_dir):
    return G.densify(lineitem_cells(spark, sf_dir).select(*AXES, "v"), F1, 0)


@query("prefix_lineitem", f"WITH {T.f9_ctes()} SELECT x, y, z, t, v AS cents FROM cube")
def prefix_lineitem(spark, sf_dir):
    return G.prefix_cube(G.densify(lineitem_cells(spark, sf_dir).select(*AXES, "v"), F1, 0)).select(*AXES, F.col("v").alias("cents"))


@query("prefix_events", f"WITH {T.f9_ctes(T.F2_CELLS, F2)} SELECT x, y, z, t, v AS cents FROM cube")
def prefix_events(spark, sf_dir):
    return G.prefix_cube(G.densify(event_cells(spark, sf_dir).select(*AXES, "v"), F2, 0)).select(*AXES, F.col("v").alias("cents"))


@query("normalize_field", f"WITH {T.f9_ctes()} SELECT {VOX} FROM v1")
def normalize_field(spark, sf_dir):
    return vox6(f9(spark, sf_dir))


@query("denormalize_field", f"WITH {T.f9_ctes()} SELECT x, y, z, t, {q6('v / 1.0', 'v', 2)} FROM cube")
def denormalize_field(spark, sf_dir):
    raw = volume(spark, sf_dir, "f9")[0]
    return G.denormalize(G.normalize(raw), G.value_range(raw)).select(*AXES, r6(F.col("v"), "v", 2))


@query("crop_time", f"WITH {T.f9_ctes()} SELECT x, y, z, CAST(t - 4 AS INTEGER) AS t, v AS cents FROM cube WHERE t >= 4 AND t < 12")
def crop_time(spark, sf_dir):
    cube = G.prefix_cube(G.densify(lineitem_cells(spark, sf_dir).select(*AXES, "v"), F1, 0))
    return G.crop_time(cube, 4, 12).select(*AXES, F.col("v").alias("cents"))


@query("grid_multivariate", """SELECT CAST(l_partkey % 16 AS INTEGER) AS x, CAST(l_suppkey % 8 AS INTEGER) AS y, 0 AS z, 0 AS t, var, CAST(v AS BIGINT) AS v FROM (
  SELECT l_partkey % 16 AS l_partkey, l_suppkey % 8 AS l_suppkey, sum(CAST(round(l_extendedprice * 100) AS BIGINT)) AS price, sum(CAST(round(l_discount * 100) AS BIGINT)) AS discount, sum(CAST(round(l_tax * 100) AS BIGINT)) AS tax FROM lineitem GROUP BY 1, 2)
  UNPIVOT (v FOR var IN (price, discount, tax))""")
def grid_multivariate(spark, sf_dir):
    from ..sources.tables import load

    df = load(spark, sf_dir, "lineitem", "l_partkey", "l_suppkey", "l_extendedprice", "l_discount", "l_tax")
    return G.rasterize_many(df, {"x": F.col("l_partkey") % 16, "y": F.col("l_suppkey") % 8}, {"price": G.cents("l_extendedprice"), "discount": G.cents("l_discount"), "tax": G.cents("l_tax")}, "sum")


def _sizes_sql() -> str:
    rows = ", ".join(f"('{n}', {s.nx}, {s.ny}, {s.nz}, {s.nt}, {s.bx}, {s.by}, {s.bz}, {s.scales}, [{', '.join(map(str, b))}])" for n, (s, b) in KNOWN_FIELDS.items())
    return f"WITH f(name, nx, ny, nz, nt, bx, b_y, bz, s, b) AS (VALUES {rows}) SELECT name, CAST(4 AS BIGINT) * nx * ny * nz * nt AS raw_bytes FROM f"


def known_specs(spark: SparkSession) -> DataFrame:
    rows = [(n, s.nx, s.ny, s.nz, s.nt, s.bx, s.by, s.bz, s.scales, list(b)) for n, (s, b) in KNOWN_FIELDS.items()]
    return spark.createDataFrame(rows, "name string, nx int, ny int, nz int, nt int, bx int, by int, bz int, s int, b array<int>")


#: How the suppliers' boxes are cut: as the first of the known fields.
CUT, PER_NET = KNOWN_FIELDS["combustion"]


@query("block_geometry", f"""WITH f AS (SELECT l_suppkey, max(l_partkey) - min(l_partkey) + 1 AS nx, max(l_orderkey) - min(l_orderkey) + 1 AS ny, CAST(floor(max(l_quantity) - min(l_quantity)) AS BIGINT) + 1 AS nz,
  max(4 * year(l_shipdate) + quarter(l_shipdate)) - min(4 * year(l_shipdate) + quarter(l_shipdate)) + 1 AS nt FROM lineitem GROUP BY 1),
 c AS (SELECT l_suppkey, scale, CAST(ceil(nx / (pow(2, scale - 1) * {CUT.bx})) * ceil(ny / (pow(2, scale - 1) * {CUT.by})) * ceil(nz / (pow(2, scale - 1) * {CUT.bz})) * ceil(nt / pow(2, scale - 1)) AS BIGINT) AS blocks FROM f, range(1, {CUT.scales + 1}) r(scale))
 SELECT l_suppkey, CAST(scale AS INTEGER) AS scale, blocks, CAST(ceil(blocks / [{', '.join(map(str, PER_NET))}][scale]) AS BIGINT) AS nets FROM c""")
def block_geometry(spark, sf_dir):
    """Blocks and nets at every scale of the box that a supplier's line items span: parts, orders, quantities, quarters."""
    from ..sources.tables import load

    axes = {"nx": F.col("l_partkey"), "ny": F.col("l_orderkey"), "nz": F.col("l_quantity"), "nt": 4 * F.year("l_shipdate") + F.quarter("l_shipdate")}
    df = load(spark, sf_dir, "lineitem", "l_suppkey", "l_partkey", "l_orderkey", "l_quantity", "l_shipdate")
    boxes = df.groupBy("l_suppkey").agg(*[(F.floor(F.max(c) - F.min(c)) + 1).alias(n) for n, c in axes.items()])
    stride = F.pow(F.lit(2.0), F.col("scale") - 1)
    e = boxes.withColumn("scale", F.explode(F.sequence(F.lit(1), F.lit(CUT.scales))))
    blocks = F.ceil(F.col("nx") / (stride * CUT.bx)) * F.ceil(F.col("ny") / (stride * CUT.by)) * F.ceil(F.col("nz") / (stride * CUT.bz)) * F.ceil(F.col("nt") / stride)
    each = F.element_at(F.array(*map(F.lit, PER_NET)), F.col("scale"))
    return e.withColumn("blocks", blocks.cast("long")).select("l_suppkey", "scale", "blocks", F.ceil(F.col("blocks") / each).alias("nets"))


@query("raw_sizes", _sizes_sql())
def raw_sizes(spark, sf_dir):
    return known_specs(spark).select("name", (F.lit(4).cast("long") * F.col("nx") * F.col("ny") * F.col("nz") * F.col("nt")).alias("raw_bytes"))


@query("morton_ids", """SELECT DISTINCT x, y, z, CAST(list_sum(list_transform(range(0, 10), lambda b: (((x >> b) & 1) << (3 * b)) + (((y >> b) & 1) << (3 * b + 1)) + (((z >> b) & 1) << (3 * b + 2)))) AS BIGINT) AS morton,
  CAST(((CAST(0 AS BIGINT) * 8 + z) * 8 + y) * 16 + x AS BIGINT) AS row_major FROM (SELECT CAST(l_partkey % 16 AS BIGINT) AS x, CAST(l_suppkey % 8 AS BIGINT) AS y, CAST(l_orderkey % 8 AS BIGINT) AS z FROM lineitem)""")
def morton_ids(spark, sf_dir):
    from ..sources.tables import load

    df = load(spark, sf_dir, "lineitem", "l_partkey", "l_suppkey", "l_orderkey").select((F.col("l_partkey") % 16).alias("x"), (F.col("l_suppkey") % 8).alias("y"), (F.col("l_orderkey") % 8).alias("z")).distinct()
    return df.select("x", "y", "z", G.morton3(F.col("x"), F.col("y"), F.col("z")).alias("morton"), G.block_id(FieldSpec(16, 8, 8, 1, 1, 1, 1), F.lit(0), F.col("x"), F.col("y"), F.col("z")).alias("row_major"))


WAVE = "sin(6.0 * (x / 31.0) + 4.0 * (y / 31.0) + 2.0 * (z / 31.0) + 3.0 * (t / 3.0))"


@query("analytic_wave", f"""SELECT x, y, z, t, n, {q6(WAVE, 'v')} FROM (SELECT CAST(l_partkey % 32 AS INTEGER) AS x, CAST(l_suppkey % 32 AS INTEGER) AS y, CAST(l_orderkey % 32 AS INTEGER) AS z, CAST(quarter(l_shipdate) - 1 AS INTEGER) AS t, count(*) AS n FROM lineitem GROUP BY 1, 2, 3, 4)""")
def analytic_wave(spark, sf_dir):
    """The plane wave at the cells that line items fill, with the number of items in each."""
    from ..sources.tables import load

    df = load(spark, sf_dir, "lineitem", "l_partkey", "l_suppkey", "l_orderkey", "l_shipdate")
    cells = G.rasterize(df, {"x": F.col("l_partkey") % 32, "y": F.col("l_suppkey") % 32, "z": F.col("l_orderkey") % 32, "t": F.quarter("l_shipdate") - 1}, F.lit(1), "count", "n").drop("v")
    return G.analytic_field(spark, FieldSpec(32, 32, 32, 4, 8, 8, 8), "wave", cells).select(*AXES, "n", r6(F.col("v"), "v"))


# pyramid

PYR = f"{T.f9_ctes()}, v2 AS ({T.down('v1', F1)}), v3 AS ({T.down('v2', F1.coarser())})"


@query("down_subsample", f"WITH {PYR} SELECT {VOX} FROM v2")
def down_subsample(spark, sf_dir):
    return vox6(P.downsample(f9(spark, sf_dir), F1))


@query("down_mean", f"WITH {PYR} SELECT CAST(x // 2 AS INTEGER) AS x, CAST(y // 2 AS INTEGER) AS y, CAST(z // 2 AS INTEGER) AS z, CAST(t // 2 AS INTEGER) AS t, {q6('avg(v)', 'v')} FROM v1 GROUP BY 1, 2, 3, 4")
def down_mean(spark, sf_dir):
    return vox6(P.downsample(f9(spark, sf_dir), F1, "mean"))


@query("pyramid_levels", f"WITH {PYR} SELECT 1 AS scale, {VOX} FROM v1 UNION ALL SELECT 2, {VOX} FROM v2 UNION ALL SELECT 3, {VOX} FROM v3")
def pyramid_levels(spark, sf_dir):
    return P.pyramid(f9(spark, sf_dir), F1).select("scale", *AXES, r6(F.col("v"), "v"))


@query("pyramid_space_only", f"WITH {T.f9_ctes()} SELECT {VOX} FROM ({T.down('v1', FieldSpec(16, 8, 8, 28, 4, 2, 2, 3, False))})")
def pyramid_space_only(spark, sf_dir):
    return vox6(P.downsample(f9(spark, sf_dir), FieldSpec(16, 8, 8, 28, 4, 2, 2, 3, False)))


@query("up_linear", f"WITH {PYR} SELECT {VOX} FROM ({T.up('v2', F1)})")
def up_linear(spark, sf_dir):
    return vox6(P.upsample(P.downsample(f9(spark, sf_dir), F1), F1))


@query("up_time_first", f"WITH {PYR} SELECT {VOX} FROM ({T.up('v2', F1)})")
def up_time_first(spark, sf_dir):
    """Order of the axes does not matter: the same twin as space first."""
    return vox6(P.upsample(P.downsample(f9(spark, sf_dir), F1), F1, ("t", "z", "y", "x")))


RES1 = f"{PYR}, u1 AS ({T.up('v2', F1)}), r1 AS ({T.residual('v1', 'u1')})"


@query("residual_scale1", f"WITH {RES1} SELECT {VOX} FROM r1")
def residual_scale1(spark, sf_dir):
    v = f9(spark, sf_dir)
    return vox6(P.residual(v, P.upsample(P.downsample(v, F1), F1)))


@query("compose_exact", f"WITH {T.f9_ctes()} SELECT {VOX} FROM v1")
def compose_exact(spark, sf_dir):
    """up + residual gives the field back: the twin is the field itself."""
    v = f9(spark, sf_dir)
    up = P.upsample(P.downsample(v, F1), F1)
    return vox6(P.compose(up, P.residual(v, up)))


@query("halo_counts", f"""WITH {T.f9_ctes()}, b AS (SELECT unnest(range(0, 4)) AS bx), c AS (SELECT unnest(range(0, 4)) AS b_y), d AS (SELECT unnest(range(0, 4)) AS bz)
  SELECT CAST(bx AS INTEGER) AS bx, CAST(b_y AS INTEGER) AS "by", CAST(bz AS INTEGER) AS bz, t, count(*) AS n, {q6('sum(v)', 'total')} FROM v1, b, c, d
  WHERE x BETWEEN bx * 4 - 1 AND bx * 4 + 4 AND y BETWEEN b_y * 2 - 1 AND b_y * 2 + 2 AND z BETWEEN bz * 2 - 1 AND bz * 2 + 2 GROUP BY ALL""")
def halo_counts(spark, sf_dir):
    return P.with_halo(f9(spark, sf_dir), F1, 1).groupBy(F.col("_bx").alias("bx"), F.col("_by").alias("by"), F.col("_bz").alias("bz"), "t").agg(F.count("*").alias("n"), r6(F.sum("v"), "total"))


# blocks


@query("pack_blocks", f"""WITH {T.f9_ctes()} SELECT {T.block(F1)} AS block_id, count(*) AS valid, {q6('sum(v)', 'total')}, {q6('arg_min(v, x * 64 + y * 8 + z)', 'first')}, {q6('arg_max(v, x * 64 + y * 8 + z)', 'last')} FROM v1 GROUP BY 1""")
def pack_blocks(spark, sf_dir):
    b = B.pack_blocks(f9(spark, sf_dir), F1)
    return b.select("block_id", F.col("valid").cast("long").alias("valid"), r6(F.aggregate("values", F.lit(0.0), lambda a, v: a + v), "total"), r6(F.element_at("values", 1), "first"), r6(F.element_at("values", -1), "last"))


@query("unpack_blocks", f"WITH {T.f9_ctes()} SELECT {VOX} FROM v1")
def unpack_blocks(spark, sf_dir):
    return vox6(B.unpack_blocks(B.pack_blocks(f9(spark, sf_dir), F1), F1))


@query("block_energy", f"WITH {RES1}, e AS ({T.energy('r1', F1)}) SELECT block_id, {q6('energy', 'energy')} FROM e")
def block_energy(spark, sf_dir):
    v = f9(spark, sf_dir)
    return B.block_energy(P.residual(v, P.upsample(P.downsample(v, F1), F1)), F1).select("block_id", r6(F.col("energy"), "energy"))


@query("block_energy_kinds", f"""WITH {RES1} SELECT {T.block(F1)} AS block_id, {q6('sqrt(sum(v * v))', 'l2')}, {q6('sqrt(avg(v * v))', 'rms')}, {q6('avg(v * v)', 'mse', 9)} FROM r1 GROUP BY 1""")
def block_energy_kinds(spark, sf_dir):
    v = f9(spark, sf_dir)
    b = B.pack_blocks(P.residual(v, P.upsample(P.downsample(v, F1), F1)), F1)
    return b.select("block_id", *[r6(B.values_energy(F.col("values"), k), k, 9 if k == "mse" else 6) for k in B.ENERGIES])


ENERGIES = f"""{RES1}, r2 AS ({T.residual('v2', '(' + T.up('v3', F1.coarser()) + ')')}),
 e AS (SELECT 1 AS scale, * FROM ({T.energy('r1', F1)}) UNION ALL SELECT 2, * FROM ({T.energy('r2', F1.coarser())}) UNION ALL SELECT 3, * FROM ({T.energy('v3', F1.at_scale(3))}))"""


def f9_energies(spark, sf_dir) -> DataFrame:
    """Energies of all scales against exactly kept coarser scales."""
    v1 = f9(spark, sf_dir)
    c, cc = F1.coarser(), F1.at_scale(3)
    v2 = P.downsample(v1, F1)
    v3 = P.downsample(v2, c)
    parts = [(1, P.residual(v1, P.upsample(v2, F1)), F1), (2, P.residual(v2, P.upsample(v3, c)), c), (3, v3, cc)]
    out = None
    for scale, df, spec in parts:
        e = B.block_energy(df, spec).select(F.lit(scale).alias("scale"), "block_id", "energy")
        out = e if out is None else out.unionByName(e)
    return out


@query("effective_profile", f"""WITH {ENERGIES} SELECT CAST(scale AS INTEGER) AS scale, count(*) AS blocks, CAST(sum(CASE WHEN scale = 3 OR energy >= {TAU} THEN 1 ELSE 0 END) AS BIGINT) AS effective,
  {q6(f'1 - sum(CASE WHEN scale = 3 OR energy >= {TAU} THEN 1.0 ELSE 0.0 END) / count(*)', 'discarded')} FROM e GROUP BY scale""")
def effective_profile(spark, sf_dir):
    return B.effective_profile(f9_energies(spark, sf_dir), TAU, 3).select("scale", "blocks", "effective", r6(F.col("discarded"), "discarded"))


@query("empty_bitmap", f"""WITH {ENERGIES} SELECT CAST(scale AS INTEGER) AS scale, CAST(block_id // 64 AS BIGINT) AS word, CAST(sum(CASE WHEN energy >= {TAU} AND block_id % 64 < 63 THEN 1::BIGINT << (block_id % 64) ELSE 0 END) AS BIGINT) AS bits FROM e GROUP BY 1, 2""")
def empty_bitmap(spark, sf_dir):
    flags = f9_energies(spark, sf_dir).select("scale", "block_id", ((F.col("energy") >= TAU) & (F.col("block_id") % 64 < 63)).alias("effective"))
    return B.empty_bitmap(flags)


@query("ragged_blocks", f"""WITH c AS ({T.F2_CELLS}), g AS ({T.dense('c', F2)}), w AS (SELECT * FROM g WHERE x < 14 AND y < 22)
 SELECT CAST(((CAST(t AS BIGINT) * 4 + z // 2) * 4 + y // 6) * 4 + x // 4 AS BIGINT) AS block_id, count(*) AS valid, CAST(sum(v) AS BIGINT) AS cents FROM w GROUP BY 1""")
def ragged_blocks(spark, sf_dir):
    spec = FieldSpec(14, 22, 8, 30, 4, 6, 2, 3)
    v = G.densify(event_cells(spark, sf_dir).select(*AXES, "v"), F2, 0).where("x < 14 AND y < 22")
    b = B.pack_blocks(v, spec)
    return B.unpack_blocks(b, spec).groupBy(B.block_of(spec).alias("block_id")).agg(F.sum("v").cast("long").alias("cents")).join(b.select("block_id", F.col("valid").cast("long").alias("valid")), "block_id")


def _seam_sql() -> str:
    parts = []
    for a, size in (("x", 4), ("y", 2), ("z", 2)):
        others = ", ".join(b for b in AXES if b != a)
        parts.append(f"""SELECT '{a}' AS axis, {q6(f'avg(d) FILTER ({a} % {size} = {size - 1})', 'seam')}, {q6(f'avg(d) FILTER ({a} % {size} <> {size - 1})', 'inner_step')},
          {q6(f'avg(d) FILTER ({a} % {size} = {size - 1}) / avg(d) FILTER ({a} % {size} <> {size - 1})', 'ratio', 5)} FROM (SELECT {a}, abs(lead(v) OVER (PARTITION BY {others} ORDER BY {a}) - v) AS d FROM v1)""")
    return f"WITH {T.f9_ctes()} " + " UNION ALL ".join(parts)


@query("seam_ratio", _seam_sql())
def seam_ratio(spark, sf_dir):
    return B.seam_ratio(f9(spark, sf_dir), F1).select("axis", r6(F.col("seam"), "seam"), r6(F.col("inner"), "inner_step"), r6(F.col("ratio"), "ratio", 5))


@query("box_hierarchy", f"""WITH {ENERGIES}, b AS (SELECT CAST(block_id % 4 AS INTEGER) AS bx, CAST((block_id // 4) % 4 AS INTEGER) AS b_y, CAST((block_id // 16) % 4 AS INTEGER) AS bz, CAST(block_id // 64 AS INTEGER) AS t FROM e WHERE scale = 1 AND energy >= {TAU})
 SELECT t, CAST(bx // 2 AS INTEGER) AS px, CAST(b_y // 2 AS INTEGER) AS py, CAST(bz // 2 AS INTEGER) AS pz, count(*) AS n, min(bx) AS lo_bx, max(bx) AS hi_bx, min(b_y) AS lo_by, max(b_y) AS hi_by, min(bz) AS lo_bz, max(bz) AS hi_bz FROM b GROUP BY ALL""")
def box_hierarchy(spark, sf_dir):
    flags = f9_energies(spark, sf_dir).where("scale = 1").withColumn("effective", F.col("energy") >= TAU)
    return B.box_hierarchy(flags, F1)


# the mean-block codec, from table to accuracy


def mean_codec_sql(cells: str, spec: FieldSpec, tau: float) -> str:
    ctes = [T.f9_ctes(cells, spec)]
    s = spec
    for i in range(2, spec.scales + 1):
        ctes.append(f"v{i} AS ({T.down(f'v{i - 1}', s)})")
        s = s.coarser()
    top = spec.scales
    for i in range(top, 0, -1):
        si = spec.at_scale(i)
        if i == top:
            ctes.append(f"g{i} AS (SELECT * FROM v{i})")
        else:
            ctes += [f"u{i} AS ({T.up(f'd{i + 1}', si)})", f"g{i} AS ({T.residual(f'v{i}', f'u{i}')})"]
        live = "true" if i == top else f"sqrt(sum(v * v)) >= {tau}"
        ctes.append(f"b{i} AS (SELECT {T.block(si)} AS block_id, avg(v) AS mean, {live} AS live FROM g{i} GROUP BY 1)")
        if i == top:
            ctes.append(f"d{i} AS (SELECT x, y, z, t, mean AS v FROM g{i} JOIN b{i} ON {T.block(si)} = block_id)")
        else:
            ctes.append(f"d{i} AS (SELECT x, y, z, t, u.v + CASE WHEN live THEN mean ELSE 0 END AS v FROM u{i} u JOIN b{i} ON {T.block(si)} = block_id)")
    return "WITH " + ", ".join(ctes)


@query("mean_block_codec", mean_codec_sql(T.F1_CELLS, F1, TAU) + f""", p AS (SELECT max(v) - min(v) AS peak FROM v1)
 SELECT t, {q6('avg((v1.v - d1.v) * (v1.v - d1.v))', 'mse', 8)}, {q6('20 * log10(any_value(peak)) - 10 * log10(avg((v1.v - d1.v) * (v1.v - d1.v)))', 'psnr', 4)} FROM v1 JOIN d1 USING (x, y, z, t), p GROUP BY t""")
def mean_block_codec(spark, sf_dir):
    v = f9(spark, sf_dir)
    levels = MC.encode_levels(v, F1, TAU)
    return M.psnr(v, levels[-1].decoded).select("t", r6(F.col("mse"), "mse", 8), r6(F.col("psnr"), "psnr", 4))


@query("mean_block_codec_events", mean_codec_sql(T.F2_CELLS, F2, TAU) + f""", p AS (SELECT max(v) - min(v) AS peak FROM v1)
 SELECT t, {q6('avg((v1.v - d1.v) * (v1.v - d1.v))', 'mse', 8)}, {q6('20 * log10(any_value(peak)) - 10 * log10(avg((v1.v - d1.v) * (v1.v - d1.v)))', 'psnr', 4)} FROM v1 JOIN d1 USING (x, y, z, t), p GROUP BY t""")
def mean_block_codec_events(spark, sf_dir):
    v = G.normalize(volume(spark, sf_dir, "f10")[0])
    return M.psnr(v, MC.encode_levels(v, F2, TAU)[-1].decoded).select("t", r6(F.col("mse"), "mse", 8), r6(F.col("psnr"), "psnr", 4))


@query("compression_rate", mean_codec_sql(T.F1_CELLS, F1, TAU) + ", s AS (" + " UNION ALL ".join(f"SELECT {i} AS scale, count(*) AS blocks, CAST(sum(live::INTEGER) AS BIGINT) AS effective FROM b{i}" for i in (1, 2, 3)) + f"""),
 k AS (SELECT *, CAST(effective * 4 + 8 * ceil(blocks / 64) + CASE WHEN scale = 3 THEN 64 ELSE 0 END AS BIGINT) AS bytes FROM s)
 SELECT CAST(scale AS INTEGER) AS scale, blocks, effective, bytes, {q6(f'{F1.raw_bytes}.0 / sum(bytes) OVER ()', 'rate')} FROM k""")
def compression_rate(spark, sf_dir):
    levels = MC.encode_levels(f9(spark, sf_dir), F1, TAU)
    sizes = MC.archive_bytes(levels)
    return sizes.crossJoin(F.broadcast(sizes.agg(F.sum("bytes").alias("all_bytes")))).select("scale", "blocks", "effective", "bytes", r6(M.compression_rate(F1, F.col("all_bytes")), "rate"))


@query("exact_codec", f"WITH {T.f9_ctes()} SELECT {VOX} FROM v1")
def exact_codec(spark, sf_dir):
    """Residuals kept whole and nothing dropped: the codec's loop is lossless, so the twin is the field."""
    return vox6(MC.encode_levels(f9(spark, sf_dir), F1, 0.0, keep="exact")[-1].decoded)


@query("closed_loop_gap", mean_codec_sql(T.F1_CELLS, F1, TAU) + f""" SELECT {q6('sum((v1.v - d1.v) * (v1.v - d1.v))', 'field_error', 4)}, {q6('sum((g1.v - (d1.v - u1.v)) * (g1.v - (d1.v - u1.v)))', 'residual_error', 4)}
 FROM v1 JOIN d1 USING (x, y, z, t) JOIN g1 USING (x, y, z, t) JOIN u1 USING (x, y, z, t)""")
def closed_loop_gap(spark, sf_dir):
    v = f9(spark, sf_dir)
    levels = MC.encode_levels(v, F1, TAU)
    last = levels[-1]
    kept = P.residual(last.decoded, P.upsample(levels[-2].decoded, F1))
    return P.closed_loop_gap(v, last.decoded, last.target, kept).select(r6(F.col("field_error"), "field_error", 4), r6(F.col("residual_error"), "residual_error", 4))


@query("open_loop_codec", None)
def open_loop_codec(spark, sf_dir):
    v = f9(spark, sf_dir)
    return M.errors(v, MC.encode_levels(v, F1, TAU, loop="open")[-1].decoded).select("n", r6(F.col("mse"), "mse", 8))


@query("memory_profile", f"""WITH {ENERGIES} SELECT CAST(scale AS INTEGER) AS scale, CAST(sum(CASE WHEN scale = 3 OR energy >= {TAU} THEN 1 ELSE 0 END) * 64 AS BIGINT) AS resident_bytes FROM e GROUP BY scale""")
def memory_profile(spark, sf_dir):
    return M.memory_profile(B.effective_profile(f9_energies(spark, sf_dir), TAU, 3), F1)


# static and categorical volumes


@query("grid_static16", f"SELECT x, y, z, t, v AS cents, n FROM ({T.mod_cells(16)})")
def grid_static16(spark, sf_dir):
    from ..sources.tables import load

    df = load(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey", "l_suppkey", "l_extendedprice")
    return G.rasterize(df, {"x": F.col("l_partkey") % 16, "y": F.col("l_suppkey") % 16, "z": F.col("l_orderkey") % 16}, G.cents("l_extendedprice"), "sum", "n").select(*AXES, F.col("v").alias("cents"), "n")


@query("static_profile", f"""WITH c AS ({T.mod_cells(64)}), g AS ({T.dense('(SELECT x, y, z, t, v / n / 100.0 AS v FROM c)', F3, '0.0')}), v1 AS ({T.normal('g')}),
 v2 AS ({T.down('v1', F3)}), v3 AS ({T.down('v2', F3.coarser())}), v4 AS ({T.down('v3', F3.at_scale(3))}),
 k AS (SELECT 1 AS scale, count(*) AS voxels, {q6('avg(v)', 'mean')} FROM v1 UNION ALL SELECT 2, count(*), {q6('avg(v)', 'm')} FROM v2 UNION ALL SELECT 3, count(*), {q6('avg(v)', 'm')} FROM v3 UNION ALL SELECT 4, count(*), {q6('avg(v)', 'm')} FROM v4)
 SELECT CAST(scale AS INTEGER) AS scale, voxels, mean FROM k""")
def static_profile(spark, sf_dir):
    v, spec = volume(spark, sf_dir, "f3")
    return P.pyramid(G.normalize(v), spec).groupBy("scale").agg(F.count("*").alias("voxels"), r6(F.avg("v"), "mean"))


@query("grid_documents", f"""WITH c AS (SELECT CAST(list_position(['de', 'en', 'es', 'fr'], lang) - 1 AS INTEGER) AS x, CAST(substr(source, 4) AS INTEGER) AS y, CAST(least(15, length(bin(n_chars)) - 1) AS INTEGER) AS z, 0 AS t, count(*) AS v
 FROM documents WHERE lang IN ('de', 'en', 'es', 'fr') GROUP BY 1, 2, 3), g AS ({T.dense('c', F7)}) SELECT x, y, z, t, CAST(v AS DOUBLE) AS v FROM g""")
def grid_documents(spark, sf_dir):
    return volume(spark, sf_dir, "f7")[0]


# measures


@query("iso_points", f"WITH {T.f9_ctes()}, " + "p AS (" + " UNION ALL ".join(
    "SELECT t, " + ", ".join((f"CAST({b} AS DOUBLE) + (-0.5 - v) / (n - v)" if b == a else f"CAST({b} AS DOUBLE)") + f" AS p{b}" for b in "xyz") + f" FROM (SELECT *, lead(v) OVER (PARTITION BY {', '.join(c for c in AXES if c != a)} ORDER BY {a}) AS n FROM v1) WHERE (v + 0.5) * (n + 0.5) < 0" for a in "xyz") + f""")
 SELECT t, {q6('px', 'px', 5)}, {q6('py', 'py', 5)}, {q6('pz', 'pz', 5)} FROM p""")
def iso_points(spark, sf_dir):
    return M.iso_points(f9(spark, sf_dir), -0.5).select("t", *[r6(F.col(f"p{a}"), f"p{a}", 5) for a in "xyz"])


@query("chamfer_small", """WITH p AS (SELECT event_id, CAST(user_id % 16 AS DOUBLE) AS x, CAST(hour(ts) AS DOUBLE) AS y, CAST(event_id % 7 AS DOUBLE) AS z FROM events WHERE event_type = 'purchase' AND event_id < 4000),
 q AS (SELECT event_id, CAST(user_id % 16 AS DOUBLE) + 0.25 AS x, CAST(hour(ts) AS DOUBLE) AS y, CAST(event_id % 7 AS DOUBLE) AS z FROM events WHERE event_type = 'error' AND event_id < 4000),
 a AS (SELECT DISTINCT x, y, z FROM p), b AS (SELECT DISTINCT x, y, z FROM q),
 d AS (SELECT sqrt((a.x - b.x) ** 2 + (a.y - b.y) ** 2 + (a.z - b.z) ** 2) AS d, a.x AS ax, a.y AS ay, a.z AS az, b.x AS bx, b.y AS b_y, b.z AS bz FROM a, b),
 f AS (SELECT avg(m) AS pq FROM (SELECT min(d) AS m FROM d GROUP BY ax, ay, az)), g AS (SELECT avg(m) AS qp FROM (SELECT min(d) AS m FROM d GROUP BY bx, b_y, bz))
 SELECT round(pq, 6) AS pq, round(qp, 6) AS qp, round(pq + qp, 6) AS chamfer FROM f, g""")
def chamfer_small(spark, sf_dir):
    from ..sources.tables import load

    e = load(spark, sf_dir, "events", "event_id", "user_id", "ts", "event_type").where("event_id < 4000")
    pts = lambda kind, dx: e.where(F.col("event_type") == kind).select(F.lit(0).alias("t"), ((F.col("user_id") % 16).cast("double") + dx).alias("px"), F.hour("ts").cast("double").alias("py"), (F.col("event_id") % 7).cast("double").alias("pz"))
    return M.chamfer(pts("purchase", 0.0), pts("error", 0.25), exact_cells=True).select(*[F.round(c, 6).alias(c) for c in ("pq", "qp", "chamfer")])


@query("chamfer_events", """WITH p AS (SELECT event_id, CAST(user_id % 16 AS DOUBLE) AS x, CAST(hour(ts) AS DOUBLE) AS y, CAST(event_id % 7 AS DOUBLE) AS z FROM events WHERE event_type = 'purchase'),
 q AS (SELECT event_id, CAST(user_id % 16 AS DOUBLE) + 0.25 AS x, CAST(hour(ts) AS DOUBLE) AS y, CAST(event_id % 7 AS DOUBLE) AS z FROM events WHERE event_type = 'error'),
 a AS (SELECT DISTINCT x, y, z FROM p), b AS (SELECT DISTINCT x, y, z FROM q),
 d AS (SELECT sqrt((a.x - b.x) ** 2 + (a.y - b.y) ** 2 + (a.z - b.z) ** 2) AS d, a.x AS ax, a.y AS ay, a.z AS az, b.x AS bx, b.y AS b_y, b.z AS bz FROM a, b),
 f AS (SELECT avg(m) AS pq FROM (SELECT min(d) AS m FROM d GROUP BY ax, ay, az)), g AS (SELECT avg(m) AS qp FROM (SELECT min(d) AS m FROM d GROUP BY bx, b_y, bz))
 SELECT round(pq, 6) AS pq, round(qp, 6) AS qp, round(pq + qp, 6) AS chamfer FROM f, g""")
def chamfer_events(spark, sf_dir):
    """As `chamfer_small`, whose SQL fixes a range of ids, over all events."""
    from ..sources.tables import load

    e = load(spark, sf_dir, "events", "event_id", "user_id", "ts", "event_type")
    pts = lambda kind, dx: e.where(F.col("event_type") == kind).select(F.lit(0).alias("t"), ((F.col("user_id") % 16).cast("double") + dx).alias("px"), F.hour("ts").cast("double").alias("py"), (F.col("event_id") % 7).cast("double").alias("pz"))
    return M.chamfer(pts("purchase", 0.0), pts("error", 0.25), exact_cells=True).select(*[F.round(c, 6).alias(c) for c in ("pq", "qp", "chamfer")])


RAY = f"""r AS (SELECT t, x AS px, y AS py, u, a, exp(coalesce(sum(ln(1 - a)) OVER (PARTITION BY t, x, y ORDER BY z ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) AS through
 FROM (SELECT *, greatest(0.0, least(1.0, (v + 1) / 2)) AS u, 0.2 * greatest(0.0, least(1.0, (v + 1) / 2)) AS a FROM v1)),
 im AS (SELECT t, px, py, sum(through * a * u) AS r, sum(through * a * (1 - abs(2 * u - 1))) AS g, sum(through * a * (1 - u)) AS b FROM r GROUP BY 1, 2, 3)"""


@query("render_ray", f"WITH {T.f9_ctes()}, {RAY} SELECT t, px, py, {q6('r', 'r')}, {q6('g', 'g')}, {q6('b', 'b')} FROM im")
def render_ray(spark, sf_dir):
    return M.render(f9(spark, sf_dir)).select("t", "px", "py", *[r6(F.col(c), c) for c in "rgb"])


@query("render_iso", f"""WITH {T.f9_ctes()}, h AS (SELECT *, z + (-0.5 - v) / (n - v) AS depth, abs(n - v) AS shade FROM (SELECT *, lead(v) OVER (PARTITION BY t, x, y ORDER BY z) AS n FROM v1) WHERE (v + 0.5) * (n + 0.5) < 0)
 SELECT t, x AS px, y AS py, {q6('arg_min(depth, z)', 'depth')}, {q6('arg_min(shade, z)', 'shade')} FROM h GROUP BY 1, 2, 3""")
def render_iso(spark, sf_dir):
    return M.render_iso(f9(spark, sf_dir), -0.5).select("t", "px", "py", r6(F.col("depth"), "depth"), r6(F.col("shade"), "shade"))


def _luv_sql() -> str:
    lin = lambda c: f"CASE WHEN {c} <= 0.04045 THEN {c} / 12.92 ELSE pow(({c} + 0.055) / 1.055, 2.4) END"
    mix = lambda m: f"({m[0]} * lr + {m[1]} * lg + {m[2]} * lb)"
    x, y, z = mix((0.4124564, 0.3575761, 0.1804375)), mix((0.2126729, 0.7151522, 0.0721750)), mix((0.0193339, 0.1191920, 0.9503041))
    return f"""l AS (SELECT i, t, px, py, {lin('r')} AS lr, {lin('g')} AS lg, {lin('b')} AS lb FROM c),
     xyz AS (SELECT i, t, px, py, {x} AS x, {y} AS y, {z} AS z FROM l),
     luv AS (SELECT *, CASE WHEN y > 0.008856 THEN 116 * pow(y, {1.0 / 3!r}) - 16 ELSE 903.3 * y END AS big, x + 15 * y + 3 * z AS s FROM xyz),
     fin AS (SELECT i, t, px, py, big, CASE WHEN s > 0 THEN 13 * big * (4 * x / s - 0.19783982) ELSE 0 END AS u, CASE WHEN s > 0 THEN 13 * big * (9 * y / s - 0.46833631) ELSE 0 END AS v FROM luv)"""


@query("cieluv_diff", f"""WITH {T.f9_ctes()}, {RAY}, o AS (SELECT t + 1 AS t, px, py, r, g, b FROM im),
 c AS (SELECT 1 AS i, t, px, py, greatest(0, least(1, r)) AS r, greatest(0, least(1, g)) AS g, greatest(0, least(1, b)) AS b FROM im UNION ALL SELECT 2, t, px, py, greatest(0, least(1, r)), greatest(0, least(1, g)), greatest(0, least(1, b)) FROM o),
 {_luv_sql()} SELECT a.t, a.px, a.py, {q6('sqrt((a.big - b.big) ** 2 + (a.u - b.u) ** 2 + (a.v - b.v) ** 2)', 'delta', 5)} FROM fin a JOIN fin b ON a.i = 1 AND b.i = 2 AND a.t = b.t AND a.px = b.px AND a.py = b.py""")
def cieluv_diff(spark, sf_dir):
    im = M.render(f9(spark, sf_dir))
    return M.cieluv_diff(im, im.withColumn("t", F.col("t") + 1)).select("t", "px", "py", r6(F.col("delta"), "delta", 5))


@query("image_distance", None)
def image_distance(spark, sf_dir):
    v = f9(spark, sf_dir)
    return M.image_distance(M.render(v), M.render(MC.encode_levels(v, F1, TAU)[-1].decoded)).select("t", r6(F.col("distance"), "distance"))


@query("psnr_by_time_peak", mean_codec_sql(T.F1_CELLS, F1, TAU) + f""", p AS (SELECT t, max(v) - min(v) AS peak FROM v1 GROUP BY t)
 SELECT v1.t, {q6('20 * log10(any_value(peak)) - 10 * log10(avg((v1.v - d1.v) * (v1.v - d1.v)))', 'psnr', 4)} FROM v1 JOIN d1 USING (x, y, z, t) JOIN p ON p.t = v1.t GROUP BY v1.t""")
def psnr_by_time_peak(spark, sf_dir):
    v = f9(spark, sf_dir)
    return M.psnr(v, MC.encode_levels(v, F1, TAU)[-1].decoded, per_time_peak=True).select("t", r6(F.col("psnr"), "psnr", 4))
