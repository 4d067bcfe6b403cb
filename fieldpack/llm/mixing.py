"""Mixing sources to target weights by exponential keys.

Each source gets a share of the words in proportion to its weight, at most `cap` times its size;
what a capped source leaves goes to the others by weight. Within a source whole epochs come first;
the rest is a fractional selection: each document gets an Efraimidis-Spirakis key -ln(u)/w, with u
from a seeded hash of its id and w its quality weight, and documents are taken in the order of the
keys until the prefix sum of their sizes reaches the budget. The document at the border gives the
words that are still missing, so every source meets its target.

The prefix sums never put a source into one task: keys are cut into ranges and ranges are summed;
only the range in which a source's budget ends is ordered by row. That gives one border per source,
and every document is then held against its source's border where it lies, without a shuffle.

Cases: null or empty texts have size 0 and are taken with 0 words; the null source is a source of
its own, placed last; equal keys are ordered by id, size and text hash; rows that
are equal in all of these share what the border gives;
an empty table gives an empty mix;
further columns may have any names.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import read_table, stage

#: Fixed value: what is a word.
WORD = r"[^\x20\x09-\x0D]+"


@dataclass(frozen=True)
class MixPlan:
    """Weights go to the sources in code point order, repeating; the mix has `total` times all words."""

    weights: tuple[int, ...] = (3, 1, 2)
    total: float = 1.5
    cap: float = 2.0
    seed: int = 17
    rows_per_range: int = 1024


def source_targets(sizes: list[tuple[str | None, int]], plan: MixPlan) -> dict[str | None, float]:
    """The words that each source gives. Water-filling: sources above their cap are fixed at it until none is above."""
    ordered = sorted(sizes, key=lambda x: (x[0] is None, (x[0] or "").encode("utf-8")))
    weight = {s: plan.weights[i % len(plan.weights)] for i, (s, _) in enumerate(ordered)}
    size = dict(ordered)
    target: dict[str | None, float] = {s: 0.0 for s in size}
    left, free = plan.total * sum(size.values()), [s for s, _ in ordered]
    while free:
        whole = sum(weight[s] for s in free)
        over = [s for s in free if left * weight[s] / whole > plan.cap * size[s]]
        if not over:
            for s in free:
                target[s] = left * weight[s] / whole
            break
        for s in over:
            target[s] = plan.cap * size[s]
        left -= sum(target[s] for s in over)
        free = [s for s in free if s not in over]
    return target


def quality_weight(text: Column) -> Column:
    """From 0.25 to 1: the share of letters among a text's characters that are not blank, as a double."""
    solid = F.length(F.regexp_replace(text, r"[\x20\x09-\x0D]+", ""))
    odd = F.length(F.regexp_replace(text, r"[^!-@\[-`{-~]+", ""))
    return F.lit(0.25) + F.lit(0.75) * F.when(solid > 0, 1 - odd / solid).otherwise(F.lit(0.0))


def exponential_key(id_col: Column, weight: Column, seed: int) -> Column:
    """-ln(u)/w with u in (0, 1) from a seeded hash of the id: reruns agree."""
    bits = F.shiftrightunsigned(F.xxhash64(F.lit(seed), F.coalesce(id_col.cast("string"), F.lit(""))), 11).cast("double")
    return -F.log((bits + 0.5) / float(1 << 53)) / weight


def measured(docs: DataFrame, plan: MixPlan) -> DataFrame:
    """`docs` with mix_size, mix_key and mix_hash (orders equal keys)."""
    text = F.coalesce(F.col("text"), F.lit(""))
    return docs.withColumns({
        "mix_size": F.regexp_count(text, F.lit(WORD)).cast("long"),
        "mix_key": exponential_key(F.col("doc_id"), quality_weight(text), plan.seed),
        "mix_hash": F.xxhash64(text),
    })


def _place(alias: str = "") -> Column:
    return F.struct(*[F.col(f"{alias}{c}") for c in ("mix_key", "doc_id", "mix_size", "mix_hash")])


def plan_mix(measures: DataFrame, plan: MixPlan) -> DataFrame:
    """One row per source: mix_source, source_size, target, epochs (whole copies), and the border: the
    place in the order of keys where the fractional selection ends and the words that the border gives.

    `measures` has source, doc_id, mix_size, mix_key, mix_hash and should be staged. The driver sees
    one row per source (a list of sources, not of documents)."""
    spark = measures.sparkSession
    stats = measures.groupBy("source").agg(F.sum("mix_size").cast("long").alias("size"), F.count("*").alias("n")).collect()
    targets = source_targets([(r["source"], int(r["size"] or 0)) for r in stats], plan)
    rows = []
    for r in stats:
        size, words = int(r["size"] or 0), round(targets[r["source"]])
        epochs = words // size if size else 0
        ranges = 1 << max(0, (int(r["n"]) // plan.rows_per_range)).bit_length()
        rows.append((r["source"], size, float(targets[r["source"]]), int(epochs), words - epochs * size, ranges))
    facts = spark.createDataFrame(rows, "mix_source string, source_size long, target double, epochs long, budget long, ranges int")
    beside = (lambda df: F.broadcast(df)) if len(rows) <= 100_000 else (lambda df: df)
    # rises with the key from 0 to 1; the mean of three weights' distributions, so that whatever weights (0.25 to 1) a
    # source has, no range holds more than some four times its share of the rows
    spread = 1 - (F.exp(-F.col("mix_key")) + F.exp(-F.col("mix_key") / 2) + F.exp(-F.col("mix_key") / 4)) / 3
    placed = measures.join(beside(facts), F.col("source").eqNullSafe(F.col("mix_source"))).withColumn("mix_range", F.least(F.floor(spread * F.col("ranges")), F.col("ranges") - 1).cast("int"))
    sums = placed.groupBy("mix_source", "mix_range").agg(F.sum("mix_size").alias("words"))
    upto = Window.partitionBy("mix_source").orderBy("mix_range").rowsBetween(Window.unboundedPreceding, 0)
    summed = sums.withColumn("after", F.sum("words").over(upto)).withColumn("offset", F.col("after") - F.col("words"))
    last = summed.join(beside(facts.select(F.col("mix_source").alias("s"), "budget")), F.col("mix_source").eqNullSafe(F.col("s"))).where((F.col("offset") < F.col("budget")) & (F.col("budget") <= F.col("after")))
    ends = stage(last.select("s", F.col("mix_range").alias("end_range"), "offset"), "mix-ends")
    near = placed.join(beside(ends), F.col("mix_source").eqNullSafe(F.col("s")) & (F.col("mix_range") == F.col("end_range")))
    tied = near.groupBy("s", "mix_key", "doc_id", "mix_size", "mix_hash", "offset", "budget").agg(F.count("*").alias("alike"))
    order = Window.partitionBy("s").orderBy("mix_key", "doc_id", "mix_size", "mix_hash").rowsBetween(Window.unboundedPreceding, 0)
    run = tied.withColumn("after", F.col("offset") + F.sum(F.col("mix_size") * F.col("alike")).over(order)).withColumn("left", F.col("budget") - F.col("after") + F.col("mix_size") * F.col("alike"))
    border = run.where((F.col("left") > 0) & (F.col("after") >= F.col("budget"))).select("s", _place().alias("border"), F.round(F.col("left") / F.col("alike")).cast("long").alias("border_words"))
    return facts.join(border, F.col("mix_source").eqNullSafe(F.col("s")), "left").select("mix_source", "source_size", "target", "epochs", "border", "border_words")


def apply_mix(docs: DataFrame, sources: DataFrame, n_sources: int | None = None) -> DataFrame:
    """`docs` (measured) with source_size, target, epochs, part (words of one more, partial copy) and taken."""
    beside = F.broadcast(sources) if (n_sources if n_sources is not None else sources.count()) <= 100_000 else sources
    joined = docs.join(beside, F.col("source").eqNullSafe(F.col("mix_source")))
    part = F.when(F.col("border").isNull() | (_place() > F.col("border")), F.lit(0)).when(_place() == F.col("border"), F.least("border_words", "mix_size")).otherwise(F.col("mix_size"))
    return joined.withColumn("part", part.cast("long")).withColumn("taken", F.col("epochs") * F.col("mix_size") + F.col("part")).drop("mix_source", "border", "border_words")


def mix_plan_of(docs: DataFrame, plan: MixPlan = MixPlan()) -> tuple[DataFrame, DataFrame]:
    """The staged measures of `docs` and the staged plan of its sources."""
    measures = stage(measured(docs, plan).select("doc_id", "source", "mix_size", "mix_key", "mix_hash"), "mix-measures")
    return measures, stage(plan_mix(measures, plan), "mix-sources")


def mix_documents(docs: DataFrame, plan: MixPlan = MixPlan()) -> DataFrame:
    """The mixed corpus with the columns of `docs`: whole copies first, then the partial one, cut after its last word taken.
    Columns that only ride along are kept in a struct meanwhile, whatever their names."""
    cols, used = docs.columns, ("doc_id", "text", "source")
    rest = [c for c in cols if c not in used]
    base = docs.select(*used, F.struct(F.lit(0).alias("none"), *[docs[c].alias(f"c_{c}") for c in rest]).alias("mix_row"))
    _, sources = mix_plan_of(base, plan)
    dealt = apply_mix(measured(base, plan), sources)
    copies = F.concat(F.array_repeat(F.lit(-1).cast("long"), F.col("epochs").cast("int")), F.when((F.col("part") > 0) | ((F.col("mix_size") == 0) & (F.col("epochs") == 0)), F.array("part")).otherwise(F.array().cast("array<long>")))
    cut = F.when((F.col("copy_words") < 0) | (F.col("copy_words") >= F.col("mix_size")), F.col("text")).otherwise(first_words(F.col("text"), F.col("copy_words")))
    out = dealt.withColumn("copy_words", F.explode(copies)).withColumn("text", cut)
    row = lambda c: F.col("mix_row").getField(f"c_{c}").alias(c)
    return out.select(*[F.length("text").cast("long").alias(c) if c == "n_chars" else F.col(c) if c in used else row(c) for c in cols])


def first_words(text: Column, n: Column) -> Column:
    """The text up to the end of its n-th word; its white space stays as it is."""
    with_gaps = F.regexp_extract_all(text, F.lit(r"[\x20\x09-\x0D]*" + WORD), F.lit(0))
    return F.when(n <= 0, F.lit("")).otherwise(F.array_join(F.slice(with_gaps, F.lit(1), F.greatest(n.cast("int"), F.lit(1))), ""))


def op6_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    measures, sources = mix_plan_of(read_table(spark, sf_dir, "documents", "doc_id", "text", "source"))
    return apply_mix(measures, sources).select("doc_id", F.col("mix_size").alias("size"), "source_size", "target", "taken", "epochs", "part")
