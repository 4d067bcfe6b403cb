"""Queries over block assignment and deep compression; blocks and parameters come from `embeddings`."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import assign as A
from ..operators import entropy as E
from ..operators import prune as Z
from ..operators import quant as Q
from ..operators.volumes import embedding_blocks
from ..sources.tables import load
from .field_queries import q6, r6

QUERIES, ORACLES = {}, {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return add


def label_centroids(spark: SparkSession, sf_dir: str) -> DataFrame:
    """net_id, center: the mean block of each label (ten labels of 64 values)."""
    e = load(spark, sf_dir, "embeddings", "label", "embedding").select("label", F.posexplode("embedding").alias("p", "v"))
    means = e.groupBy("label", "p").agg(F.avg(F.col("v").cast("double")).alias("m"))
    return means.groupBy(F.col("label").alias("net_id")).agg(F.transform(F.array_sort(F.collect_list(F.struct("p", "m"))), lambda s: s["m"]).alias("center"))


def label_distances(spark: SparkSession, sf_dir: str) -> DataFrame:
    return A.distances(embedding_blocks(spark, sf_dir), label_centroids(spark, sf_dir))


LONG = "l AS (SELECT vec_id, label, unnest(range(0, 64)) AS p, CAST(unnest(embedding) AS DOUBLE) AS v FROM embeddings)"
DIST = f"{LONG}, c AS (SELECT label AS net_id, p, avg(v) AS m FROM l GROUP BY 1, 2), dist AS (SELECT vec_id AS block_id, net_id, sum((v - m) * (v - m)) AS d2 FROM l JOIN c USING (p) GROUP BY 1, 2)"


@query("embed_distances", f"WITH {DIST} SELECT block_id, CAST(net_id AS INTEGER) AS net_id, {q6('d2', 'd2')} FROM dist")
def embed_distances(spark, sf_dir):
    return label_distances(spark, sf_dir).select("block_id", F.col("net_id").cast("int").alias("net_id"), r6(F.col("d2"), "d2"))


@query("embed_gain", f"WITH {DIST} SELECT block_id, {q6('max(d2) - min(d2)', 'gain')} FROM dist GROUP BY 1")
def embed_gain(spark, sf_dir):
    return A.gain(label_distances(spark, sf_dir)).select("block_id", r6(F.col("gain"), "gain"))


@query("embed_nearest", f"WITH {DIST} SELECT block_id, CAST(arg_min(net_id, d2) AS INTEGER) AS net_id, {q6('min(d2)', 'd2')} FROM dist GROUP BY 1")
def embed_nearest(spark, sf_dir):
    return A.nearest(label_distances(spark, sf_dir)).select("block_id", F.col("net_id").cast("int").alias("net_id"), r6(F.col("d2"), "d2"))


@query("cluster_quality", f"WITH {DIST}, o AS (SELECT block_id, arg_min(net_id, d2) AS own FROM dist GROUP BY 1) SELECT {q6('avg(sqrt(d2)) FILTER (net_id = own)', 'inner_distance')}, {q6('avg(sqrt(d2)) FILTER (net_id <> own)', 'outer_distance')} FROM dist JOIN o USING (block_id)")
def cluster_quality(spark, sf_dir):
    d = label_distances(spark, sf_dir)
    return A.cluster_quality(A.nearest(d), d).select(r6(F.col("inner"), "inner_distance"), r6(F.col("outer"), "outer_distance"))


@query("net_counts", "SELECT CAST(b AS INTEGER) AS b, count(*) AS n, CAST(ceil(count(*) / b) AS BIGINT) AS nets FROM embeddings, (VALUES (1), (2), (4), (8), (16), (32)) v(b) GROUP BY b")
def net_counts(spark, sf_dir):
    n = load(spark, sf_dir, "embeddings", "vec_id").agg(F.count("*").alias("n"))
    return n.withColumn("b", F.explode(F.array(*[F.lit(b) for b in (1, 2, 4, 8, 16, 32)]))).select("b", "n", A.net_count(F.col("n"), F.col("b")).alias("nets"))


def _lloyd_sql(k: int, steps: int) -> str:
    out = f"WITH {LONG}, c0 AS (SELECT vec_id AS net_id, p, v AS m FROM l WHERE vec_id < {k})"
    for i in range(steps):
        out += f""", a{i} AS (SELECT vec_id, arg_min(net_id, d2) AS net_id, min(d2) AS d2 FROM (SELECT vec_id, net_id, sum((v - m) * (v - m)) AS d2 FROM l JOIN c{i} USING (p) GROUP BY 1, 2) GROUP BY 1),
        c{i + 1} AS (SELECT net_id, p, avg(v) AS m FROM l JOIN a{i} USING (vec_id) GROUP BY 1, 2)"""
    return out


@query("kmeans_fixed_steps", _lloyd_sql(6, 3) + ", n AS (SELECT net_id, count(*) AS blocks FROM a2 GROUP BY 1) " + f"SELECT CAST(n.net_id AS INTEGER) AS net_id, blocks, {q6('sum(m)', 'center_sum')}, {q6('sum(m * m)', 'center_square')} FROM c3 JOIN n USING (net_id) GROUP BY 1, 2")
def kmeans_fixed_steps(spark, sf_dir):
    b = embedding_blocks(spark, sf_dir)
    first = np.array([r["values"] for r in b.where("block_id < 6").orderBy("block_id").collect()])
    before, _ = A.kmeans(b, 6, 2, first)
    centers, _ = A.kmeans(b, 6, 1, before)
    rows = [(i, float(c.sum()), float((c * c).sum())) for i, c in enumerate(centers)]
    sizes = A.assign_nearest(b, before).groupBy("net_id").agg(F.count("*").alias("blocks"))
    return spark.createDataFrame(rows, "net_id int, center_sum double, center_square double").join(sizes, "net_id").select("net_id", "blocks", r6(F.col("center_sum"), "center_sum"), r6(F.col("center_square"), "center_square"))


UNIFORM_K = 63


def uniform_assignment(spark: SparkSession, sf_dir: str, k: int = UNIFORM_K) -> DataFrame:
    b = embedding_blocks(spark, sf_dir)
    centers, _ = A.kmeans(b, k, 4)
    d = A.distances(b, spark.createDataFrame([(i, [float(x) for x in c]) for i, c in enumerate(centers)], "net_id int, center array<double>"))
    return A.uniformize(d)


@query("uniform_sizes", f"""WITH n AS (SELECT count(*) AS n FROM embeddings), s AS (SELECT n // {UNIFORM_K} AS size, {UNIFORM_K} - n % {UNIFORM_K} AS nets FROM n UNION ALL SELECT n // {UNIFORM_K} + 1, n % {UNIFORM_K} FROM n)
 SELECT CAST(size AS BIGINT) AS size, CAST(nets AS BIGINT) AS nets FROM s WHERE nets > 0""")
def uniform_sizes(spark, sf_dir):
    return uniform_assignment(spark, sf_dir).groupBy("net_id").agg(F.count("*").alias("size")).groupBy("size").agg(F.count("*").alias("nets"))


@query("uniform_assignment", f"""WITH RECURSIVE {DIST}, i AS (SELECT net_id, row_number() OVER (ORDER BY net_id) AS pos FROM (SELECT DISTINCT net_id FROM dist)),
 o AS (SELECT block_id, row_number() OVER (ORDER BY max(d2) - min(d2) DESC, block_id) AS step, list(pos ORDER BY d2, net_id) AS choices FROM dist JOIN i USING (net_id) GROUP BY block_id),
 k AS (SELECT (SELECT count(*) FROM o) // count(*) AS low, CAST(ceil((SELECT count(*) FROM o) / count(*)) AS BIGINT) AS high, count(*) AS nets FROM i),
 w(step, sizes, block_id, pos) AS (
  SELECT CAST(0 AS BIGINT), list_transform(range(0, nets), lambda x: CAST(0 AS BIGINT)), CAST(NULL AS BIGINT), CAST(NULL AS BIGINT) FROM k
  UNION ALL
  SELECT step, list_transform(sizes, lambda s, p: s + CASE WHEN p = pos THEN 1 ELSE 0 END), block_id, pos FROM (
   SELECT o.step, w.sizes, o.block_id, list_filter(o.choices, lambda c: w.sizes[c] < CASE WHEN list_min(w.sizes) < k.low THEN k.low ELSE k.high END)[1] AS pos
   FROM w JOIN o ON o.step = w.step + 1, k))
 SELECT w.block_id, CAST(i.net_id AS INTEGER) AS net_id FROM w JOIN i USING (pos)""")
def uniform_assignment_by_block(spark, sf_dir):
    """The whole assignment of the equal-size fill over the label centroids."""
    rows = sorted(label_centroids(spark, sf_dir).collect())
    centers = np.array([r["center"] for r in rows], dtype=float)
    nets = F.array(*[F.lit(int(r["net_id"])) for r in rows])
    return A.uniform_blocks(embedding_blocks(spark, sf_dir), centers).select("block_id", F.get(nets, F.col("net_id")).alias("net_id"))


@query("uniform_rounds_equal", "SELECT count(*) AS blocks, count(*) AS equal FROM embeddings")
def uniform_rounds_equal(spark, sf_dir):
    """The distributed fill gives the sequential fill's assignment: the twin counts all blocks as equal."""
    d = label_distances(spark, sf_dir)
    from .stages import keep

    one, many = A.uniformize(d), A.uniformize_rounds(keep(d, "uniform-distances"), keep)
    return one.join(many.select("block_id", F.col("net_id").alias("other")), "block_id").agg(F.count("*").alias("blocks"), F.sum((F.col("net_id") == F.col("other")).cast("long")).alias("equal"))


@query("sharded_sizes", "SELECT true AS within, count(*) AS blocks FROM embeddings")
def sharded_sizes(spark, sf_dir):
    got = A.uniformize_sharded(embedding_blocks(spark, sf_dir), 64, 8, 128)
    sizes = got.groupBy("net_id").agg(F.count("*").alias("n"))
    return sizes.agg((F.max("n") <= 8).alias("within"), F.sum("n").alias("blocks"))


@query("assign_order", "SELECT vec_id AS block_id, CAST((row_number() OVER (ORDER BY vec_id) - 1) // 8 AS BIGINT) AS net_id FROM embeddings")
def assign_order(spark, sf_dir):
    return A.assign_order(embedding_blocks(spark, sf_dir), 8)


@query("assign_single", "SELECT vec_id AS block_id, CAST(row_number() OVER (ORDER BY vec_id) - 1 AS BIGINT) AS net_id FROM embeddings")
def assign_single(spark, sf_dir):
    return A.assign_single(embedding_blocks(spark, sf_dir))


@query("assign_balance", f"WITH {DIST}, o AS (SELECT block_id, arg_min(net_id, d2) AS net_id FROM dist GROUP BY 1), s AS (SELECT net_id, count(*) AS n FROM o GROUP BY 1) SELECT count(*) AS nets, min(n) AS smallest, max(n) AS largest, {q6('stddev_pop(n)', 'deviation')}, {q6('max(n) / avg(n)', 'imbalance')} FROM s")
def assign_balance(spark, sf_dir):
    return A.balance(A.nearest(label_distances(spark, sf_dir))).select("nets", "smallest", "largest", r6(F.col("deviation"), "deviation"), r6(F.col("imbalance"), "imbalance"))


# parameters: every embedding stands for a small network


def stand_in_parameters(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = load(spark, sf_dir, "embeddings", "vec_id", "embedding").select(F.col("vec_id").alias("net_id"), F.posexplode("embedding").alias("p", "value"))
    row = F.col("p") % 16
    return e.select(F.lit(1).alias("scale"), "net_id", F.floor(F.col("p") / 16).cast("int").alias("layer"), F.when(row < 12, "w").otherwise("b").alias("kind"), row.cast("int").alias("row"), F.lit(0).alias("col"), F.col("value").cast("double").alias("value"), F.lit(True).alias("alive"))


def stand_in_losses(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "embeddings", "vec_id", "label").select(F.col("vec_id").alias("net_id"), (F.col("label") / 10.0).alias("loss"))


PARAMS = f"""{LONG}, par AS (SELECT vec_id AS net_id, CAST(p // 16 AS INTEGER) AS layer, CASE WHEN p % 16 < 12 THEN 'w' ELSE 'b' END AS kind, CAST(p % 16 AS INTEGER) AS row, v AS value, label / 10.0 AS loss FROM l),
 cand AS (SELECT *, abs(value) AS size FROM par WHERE (kind = 'w' AND layer < 3) OR (kind = 'b' AND layer > 0 AND layer < 3)),
 imp AS (SELECT *, (size - min(size) OVER ()) / (max(size) OVER () - min(size) OVER ()) + LAMBDA * (loss - min(loss) OVER ()) / (max(loss) OVER () - min(loss) OVER ()) AS importance FROM cand)"""
IMP, MAGNITUDE = PARAMS.replace("LAMBDA", "0.1"), PARAMS.replace("LAMBDA", "0.0")


@query("importance_scores", f"WITH {IMP} SELECT net_id, layer, kind, row, {q6('importance', 'importance')} FROM imp")
def importance_scores(spark, sf_dir):
    return Z.importance(stand_in_parameters(spark, sf_dir), stand_in_losses(spark, sf_dir)).select("net_id", "layer", "kind", "row", r6(F.col("importance"), "importance"))


RANKED = "r AS (SELECT *, row_number() OVER (ORDER BY importance, net_id, layer, kind, row) AS k, count(*) OVER () AS n FROM imp)"


@query("prune_threshold", f"WITH {IMP}, {RANKED} SELECT net_id, layer, kind, row FROM r WHERE k <= round(n * 0.4)")
def prune_threshold(spark, sf_dir):
    p = Z.prune_to(stand_in_parameters(spark, sf_dir), stand_in_losses(spark, sf_dir), 0.4)
    return p.where("NOT alive").select("net_id", "layer", "kind", "row")


@query("prune_magnitude", f"WITH {MAGNITUDE}, {RANKED} SELECT net_id, layer, kind, row FROM r WHERE k <= round(n * 0.3)")
def prune_magnitude(spark, sf_dir):
    p = Z.prune_to(stand_in_parameters(spark, sf_dir), stand_in_losses(spark, sf_dir), 0.3, lam=0.0)
    return p.where("NOT alive").select("net_id", "layer", "kind", "row")


@query("prune_local", f"WITH {IMP}, r AS (SELECT *, row_number() OVER (PARTITION BY net_id ORDER BY importance, layer, kind, row) AS k, count(*) OVER (PARTITION BY net_id) AS n FROM imp) SELECT net_id, layer, kind, row FROM r WHERE k <= round(n * 0.5)")
def prune_local(spark, sf_dir):
    p = Z.prune_to(stand_in_parameters(spark, sf_dir), stand_in_losses(spark, sf_dir), 0.5, scope="net")
    return p.where("NOT alive").select("net_id", "layer", "kind", "row")


@query("sparsity_by_net", f"WITH {IMP}, {RANKED} SELECT net_id, count(*) AS candidates, CAST(sum(CASE WHEN k <= round(n * 0.4) THEN 1 ELSE 0 END) AS BIGINT) AS dead, {q6('sum(CASE WHEN k <= round(n * 0.4) THEN 1.0 ELSE 0.0 END) / count(*)', 'sparsity')} FROM r GROUP BY 1")
def sparsity_by_net(spark, sf_dir):
    p = Z.prune_to(stand_in_parameters(spark, sf_dir), stand_in_losses(spark, sf_dir), 0.4)
    return Z.sparsity_by_net(p).select("net_id", "candidates", F.col("dead").cast("long").alias("dead"), r6(F.col("sparsity"), "sparsity"))


@query("mask_bytes", f"WITH {IMP}, {RANKED}, d AS (SELECT net_id, sum(CASE WHEN k <= round(n * 0.4) THEN 1 ELSE 0 END) AS dead FROM r GROUP BY 1) SELECT net_id, CAST(8 AS BIGINT) AS bitmap, CAST(2 * dead AS BIGINT) AS positions, CAST(least(8, 2 * dead) AS BIGINT) AS bytes FROM d")
def mask_bytes(spark, sf_dir):
    p = Z.prune_to(stand_in_parameters(spark, sf_dir), stand_in_losses(spark, sf_dir), 0.4)
    return Z.mask_bytes(p)


CENTERS = [round(-0.35 + 0.05 * i, 2) for i in range(15)]
CODES = f"""{IMP}, code AS (SELECT *, CAST(len(list_filter([{', '.join(f'CAST(({a!r} + {b!r}) / 2 AS DOUBLE)' for a, b in zip(CENTERS, CENTERS[1:]))}], lambda m: m < value)) AS INTEGER) AS code FROM par)"""


def fixed_codes(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    params = stand_in_parameters(spark, sf_dir)
    books = spark.createDataFrame([(1, i, c) for i, c in enumerate(CENTERS)], "scale int, code int, center double")
    return Q.quantize(params, books, ["scale"]), books


@query("nearest_codes", f"WITH {CODES} SELECT net_id, layer, kind, row, code FROM code")
def nearest_codes(spark, sf_dir):
    return fixed_codes(spark, sf_dir)[0].select("net_id", "layer", "kind", "row", "code")


@query("quant_error", f"WITH {CODES}, q AS (SELECT layer, kind, abs(value - [{', '.join(map(repr, CENTERS))}][code + 1]) AS d FROM code) SELECT layer, kind, count(*) AS n, {q6('avg(d * d)', 'mse', 9)}, {q6('max(d)', 'max_error')} FROM q GROUP BY 1, 2")
def quant_error(spark, sf_dir):
    coded, books = fixed_codes(spark, sf_dir)
    back = Q.dequantize(coded, books, ["scale"])
    return Q.quant_error(stand_in_parameters(spark, sf_dir), back, ["layer", "kind"]).select("layer", "kind", "n", r6(F.col("mse"), "mse", 9), r6(F.col("max_error"), "max_error"))


@query("symbol_freq", f"WITH {CODES} SELECT code AS symbol, count(*) AS freq FROM code GROUP BY 1")
def symbol_freq(spark, sf_dir):
    return E.symbol_freq(fixed_codes(spark, sf_dir)[0])


@query("code_entropy", f"WITH {CODES}, f AS (SELECT code, count(*) AS freq FROM code GROUP BY 1) SELECT count(*) AS symbols, CAST(sum(freq) AS BIGINT) AS total, {q6('log2(sum(freq)) - sum(freq * log2(freq)) / sum(freq)', 'entropy')} FROM f")
def code_entropy(spark, sf_dir):
    return E.entropy(E.symbol_freq(fixed_codes(spark, sf_dir)[0])).select("symbols", "total", r6(F.col("entropy"), "entropy"))


@query("coded_bits", f"""WITH RECURSIVE {CODES}, f AS (SELECT count(*) AS freq FROM code GROUP BY code),
 h(weights, bits) AS (SELECT list_sort(list(freq)), CAST(0 AS BIGINT) FROM f UNION ALL
  SELECT list_sort(list_append(weights[3:], weights[1] + weights[2])), CAST(bits + weights[1] + weights[2] AS BIGINT) FROM h WHERE len(weights) > 1)
 SELECT 'all' AS grp, max(bits) AS bits, CAST((SELECT sum(freq) FROM f) AS BIGINT) AS symbols FROM h""")
def coded_bits(spark, sf_dir):
    return E.coded_bits(E.huffman_table(E.symbol_freq(fixed_codes(spark, sf_dir)[0])))


@query("huffman_roundtrip", "SELECT vec_id AS net_id, true AS lossless FROM embeddings")
def huffman_roundtrip(spark, sf_dir):
    """Every net's codes are coded and decoded: the twin says that none is lost."""
    coded = fixed_codes(spark, sf_dir)[0]
    codes = {r["symbol"]: r["code"] for r in E.huffman_table(E.symbol_freq(coded)).collect()}
    nets = coded.groupBy("net_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("layer", "kind", "row", "code"))), lambda s: s["code"]).alias("symbols"))
    packed = nets.withColumn("data", E.huffman_encode(F.col("symbols"), codes))
    return packed.select("net_id", (E.huffman_decode(F.col("data"), codes, F.size("symbols")) == F.col("symbols")).alias("lossless"))


@query("global_codebooks")
def global_codebooks(spark, sf_dir):
    by = Q.group_columns()
    return Q.codebooks(stand_in_parameters(spark, sf_dir), 4, by).select(*by, "code", r6(F.col("center"), "center"))


@query("local_codebooks")
def local_codebooks(spark, sf_dir):
    by = Q.group_columns("net", group="all")
    return Q.codebooks(stand_in_parameters(spark, sf_dir), 2, by).groupBy("net_id").agg(F.count("*").alias("centers"))


BYTES = """b AS (SELECT ascii(unnest(string_split(text, ''))) AS symbol FROM benchmark)"""


@query("byte_entropy", f"WITH {BYTES}, f AS (SELECT symbol, count(*) AS freq FROM b GROUP BY 1) SELECT count(*) AS symbols, CAST(sum(freq) AS BIGINT) AS total, {q6('log2(sum(freq)) - sum(freq * log2(freq)) / sum(freq)', 'entropy')} FROM f")
def byte_entropy(spark, sf_dir):
    chars = load(spark, sf_dir, "benchmark", "text").select(F.explode(F.split("text", "")).alias("c")).where("c <> ''")
    return E.entropy(E.symbol_freq(chars.select(F.ascii("c").alias("code")))).select("symbols", "total", r6(F.col("entropy"), "entropy"))
