"""Pruning over parameter rows (scale, net_id, layer, kind, row, col, value, alive)."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

KEYS = ("net_id", "layer", "kind", "row", "col")


def candidates(params: DataFrame, depth: int = 4) -> DataFrame:
    """All but the last layer's weights and the first and last layers' biases."""
    last = depth - 1
    return params.where(F.when(F.col("kind") == "w", F.col("layer") < last).otherwise((F.col("layer") > 0) & (F.col("layer") < last)))


def minmax_over(df: DataFrame, col: str, by: str = "scale") -> DataFrame:
    """Adds `<col>_n`: the column in [0, 1] over the rows of each `by`; a constant becomes 0. One small aggregate is broadcast."""
    ends = df.groupBy(by).agg(F.min(col).alias("_lo"), F.max(col).alias("_hi"))
    n = F.when(F.col("_hi") > F.col("_lo"), (F.col(col) - F.col("_lo")) / (F.col("_hi") - F.col("_lo"))).otherwise(F.lit(0.0))
    return df.join(F.broadcast(ends), by).withColumn(f"{col}_n", n).drop("_lo", "_hi")


def importance(params: DataFrame, net_loss: DataFrame, lam: float = 0.1, depth: int = 4) -> DataFrame:
    """Alive candidates with `importance`: normalised magnitude plus lam times the normalised loss of their net.

    lam = 0 is plain magnitude pruning. Both are normalised over the alive candidates of a scale."""
    alive = candidates(params, depth).where("alive").withColumn("size", F.abs("value")).join(net_loss.select("net_id", "loss"), "net_id")
    both = minmax_over(minmax_over(alive, "size"), "loss")
    return both.withColumn("importance", F.col("size_n") + lam * F.col("loss_n")).drop("size_n", "loss_n")


def kth_smallest(ranked: DataFrame, k: int, col: str = "importance", bins: int = 4096, most_rows: int = 200_000) -> DataFrame:
    """The k rows that are smallest by `col` (ties by KEYS). Histograms narrow the k-th value down until few rows
    share its bin; only those are ordered. No global sort, whatever the number of rows."""
    if k <= 0:
        return ranked.limit(0)
    lo, hi, n = ranked.agg(F.min(col), F.max(col), F.count("*")).first()
    if k >= (n or 0):
        return ranked
    before = 0  # rows surely below the open interval [lo, hi]
    inside = n
    while inside > most_rows and hi > lo:
        width = (hi - lo) / bins
        bin_of = F.least(F.floor((F.col(col) - lo) / width), F.lit(bins - 1))
        counts = dict(ranked.where((F.col(col) >= lo) & (F.col(col) <= hi)).groupBy(bin_of.alias("b")).count().collect())
        at = 0
        for b in sorted(counts):
            if before + counts[b] >= k:
                at = b
                break
            before += counts[b]
        nlo, nhi = ranked.where((F.col(col) >= lo) & (F.col(col) <= hi) & (bin_of == at)).agg(F.min(col), F.max(col)).first()
        if (nlo, nhi) == (lo, hi):
            break
        lo, hi, inside = nlo, nhi, counts[at]
    below = ranked.where(F.col(col) < lo)
    edge = ranked.where((F.col(col) >= lo) & (F.col(col) <= hi)).withColumn("_r", F.row_number().over(Window.orderBy(col, *KEYS))).where(F.col("_r") <= k - before).drop("_r")
    return below.unionByName(edge)


def prune_to(params: DataFrame, net_loss: DataFrame, sparsity: float, lam: float = 0.1, depth: int = 4, scope: str = "scale", unit: str = "parameter") -> DataFrame:
    """`params` with `alive` off (and value 0) for the least important candidates, until `sparsity` of all
    candidates is dead, those pruned earlier included.

    scope "net" prunes every net to the same sparsity; unit "neuron" sums importance over a row and prunes rows."""
    ranked = importance(params, net_loss, lam, depth)
    if scope == "net":
        total = candidates(params, depth).groupBy("net_id").agg(F.count("*").alias("_all"), F.sum(F.when(F.col("alive"), 0).otherwise(1)).alias("_dead"))
        w = Window.partitionBy("net_id").orderBy("importance", *KEYS[1:])
        gone = ranked.join(total, "net_id").withColumn("_r", F.row_number().over(w)).where(F.col("_r") <= F.round(F.col("_all") * sparsity) - F.col("_dead")).select(*KEYS)
    else:
        n, dead = candidates(params, depth).agg(F.count("*"), F.sum(F.when(F.col("alive"), 0).otherwise(1))).first()
        k = round((n or 0) * sparsity) - (dead or 0)
        if unit == "neuron":
            rows = ranked.groupBy("net_id", "layer", "kind", "row").agg(F.sum("importance").alias("importance"), F.count("*").alias("_n"), F.min("col").alias("col"))
            mean = n / max(1, rows.count())
            gone = ranked.join(kth_smallest(rows, int(k // mean)).select("net_id", "layer", "kind", "row"), ["net_id", "layer", "kind", "row"], "left_semi").select(*KEYS)
        else:
            gone = kth_smallest(ranked, k).select(*KEYS)
    marked = params.join(gone.withColumn("_gone", F.lit(True)), list(KEYS), "left")
    stays = F.col("alive") & F.col("_gone").isNull()
    return marked.withColumn("value", F.when(stays | ~F.col("alive"), F.col("value")).otherwise(F.lit(0.0))).withColumn("alive", stays).drop("_gone")


def sparsity_by_net(params: DataFrame, depth: int = 4) -> DataFrame:
    """net_id, candidates, dead, sparsity."""
    dead = F.sum(F.when(F.col("alive"), 0).otherwise(1))
    return candidates(params, depth).groupBy("net_id").agg(F.count("*").alias("candidates"), dead.alias("dead"), (dead / F.count("*")).alias("sparsity"))


def mask_bytes(params: DataFrame) -> DataFrame:
    """net_id, bitmap, positions, bytes: a bit per parameter, or 2 bytes per dead one; the smaller counts."""
    dead = F.sum(F.when(F.col("alive"), 0).otherwise(1))
    sizes = params.groupBy("net_id").agg(F.ceil(F.count("*") / 8).alias("bitmap"), (2 * dead).alias("positions"))
    return sizes.withColumn("bytes", F.least("bitmap", "positions"))
