"""MinHash near-duplicate detection with fast similarity sketches.

A document's set is its distinct k-word shingles. The sketch throws every element into a hashed
bin, round after round, until all bins are filled; from round t on, one bin is filled at a time, so
no coordinate stays empty and collisions of two sketches concentrate around the Jaccard similarity.
Bands of coordinates give buckets; how many bands of how many coordinates follows from the
similarity asked for, so that a pair at exactly that similarity misses every bucket with probability
below `miss`. With `exact`, buckets are the rarest shingles of each set instead (as many as make two
sets of that similarity share one for certain), and no sketch decides anything.

Copies are folded first (equal sets are one class, told by a digest of the set). Then

1. in every bucket each class is paired with one centre only, the class that meets most others (the
   text that copies were made from meets more of them than they do each other); pairs are confirmed
   on full sets, and confirmed pairs make components;
2. in buckets that hold two or more components, the members outside the bucket's largest component
   meet the members of other components, every pair in the first bucket that it shares. Sizes are
   compared first, then the sketches that gave the buckets, then finer ones made for these members
   only; what is left becomes rows. A large bucket is cut into blocks that go to many tasks;
3. of those pairs the closest of any two components is confirmed first, and components are joined;
   what then still lies between components is confirmed pair by pair.

Sketches are compared by two bits of every coordinate; a pair at the similarity asked for differs in
more than `most_apart` with a probability of some 3e-7.

Cases: null and empty texts have an empty set and are linked with nothing; fewer than k words make
one shingle of the whole sequence; repeated rows get equal results; rows of one doc_id with different
texts are told apart by their texts; rows without a doc_id are linked with nothing and kept; texts of
any length are taken whole.
"""

from __future__ import annotations

import hashlib
import math
from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import count

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import bound_batches, drop_staged, read_table, stage
from .components import connected_components

_U = np.uint64
#: Odd multipliers of the 64-bit mixers (fixed values).
_M1, _M2, _M3 = _U(0x9E3779B97F4A7C15), _U(0xBF58476D1CE4E5B9), _U(0x94D049BB133111EB)
_EMPTY = _U(0xFFFFFFFFFFFFFFFF)


#: Coordinates that a sketch has at least: fewer would blur the comparison of sketches.
LEAST_BINS = 288
#: Coordinates of the finer sketches.
FINE_BINS = 2048
#: Words of the bitmap that goes to every task (4 MB).
FILTER_WORDS = 1 << 18
#: Values that one step of sketching works on.
SKETCH_VALUES = 1 << 21
#: Members of a block on either side, and about how many rows a worker gets at once.
BLOCK_MEMBERS, GROUP_ROWS = 4096, 16384


@dataclass(frozen=True)
class NearDup:
    """Shingle length, similarity in percent, the chance of missing a pair at that similarity, and the exact mode."""

    words: int = 5
    percent: int = 80
    miss: float = 1e-6
    exact: bool = False

    @property
    def rows(self) -> int:
        """Coordinates of a band: as many as leave a pair at the similarity a chance of a quarter to agree in all of them."""
        return max(1, int(math.log(0.25) / math.log(self.percent / 100))) if self.percent < 100 else 12

    @property
    def bands(self) -> int:
        agree = (self.percent / 100) ** self.rows
        return max(1, math.ceil(math.log(self.miss) / math.log(1 - agree))) if agree < 1 else 1

    @property
    def bins(self) -> int:
        return max(LEAST_BINS, self.bands * self.rows)

    def most_apart(self, bins: int) -> int:
        """Of so many coordinates, in how many two bits may differ: five deviations beyond what the similarity gives."""
        q = (1 - self.percent / 100) * 0.75
        return math.ceil(bins * q + 5 * math.sqrt(bins * q * (1 - q)))


def mix64(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> _U(30))) * _M2
    x = (x ^ (x >> _U(27))) * _M3
    return x ^ (x >> _U(31))


def shingle_sets(texts: list[str | None], k: int) -> list[np.ndarray]:
    """Sorted distinct 64-bit shingles of each text; words are lower-cased in A-Z only."""
    ids: dict[bytes, int] = defaultdict(count().__next__)
    words = [(t or "").encode("utf-8", "surrogatepass").lower().split() for t in texts]
    codes = [np.fromiter(map(ids.__getitem__, w), dtype=np.int64, count=len(w)) for w in words]
    of = np.fromiter((xxhash.xxh64_intdigest(w) for w in ids), dtype=np.uint64, count=len(ids))
    out = []
    with np.errstate(over="ignore"):
        for c in codes:
            if not len(c):
                out.append(np.empty(0, dtype=np.uint64))
                continue
            h, width = of[c], min(k, len(c))
            n = len(h) - width + 1
            acc = np.full(n, _U(width), dtype=np.uint64)
            for i in range(width):
                acc = mix64(acc * _M1 + h[i : i + n])
            out.append(np.unique(acc))
    return out


def sketch(sets: list[np.ndarray], bins: int) -> np.ndarray:
    """Fast similarity sketches, one row of `bins` coordinates for each set; empty sets give empty coordinates.

    A coordinate is the least (round, hash) of the elements that fall into its bin. Ever more rounds are
    made at once, of those sets only that still have an empty bin."""
    n = len(sets)
    table = np.full(n * bins, _EMPTY, dtype=np.uint64)
    live = np.flatnonzero(np.array([len(s) for s in sets], dtype=np.int64))
    done, step = 0, 1
    with np.errstate(over="ignore"):
        while len(live) and done < 2 * bins:
            x = np.concatenate([sets[i] for i in live])
            owner = np.repeat(live, [len(sets[i]) for i in live]) * bins
            step = max(1, min(2 * step, SKETCH_VALUES // len(x), 2 * bins - done))
            for r in range(done, done + step, 64):
                rounds = np.arange(r, min(r + 64, done + step), dtype=np.uint64)[:, None]
                h = mix64(x[None, :] + (rounds + _U(1)) * _M1)
                at = (mix64(h ^ _M3) >> _U(32)) * _U(bins) >> _U(32)
                at = np.where(rounds < _U(bins), at, rounds - _U(bins)).astype(np.int64)
                np.minimum.at(table, (owner[None, :] + at).ravel(), ((rounds << _U(48)) | (h >> _U(16))).ravel())
            done += step
            live = live[(table.reshape(n, bins)[live] == _EMPTY).any(axis=1)]
    return table.reshape(n, bins)


def band_keys(table: np.ndarray, p: NearDup) -> np.ndarray:
    """One 64-bit bucket key for each band, the band's number mixed in."""
    with np.errstate(over="ignore"):
        part = table[:, : p.bands * p.rows].reshape(len(table), p.bands, p.rows)
        key = np.broadcast_to(np.arange(1, p.bands + 1, dtype=np.uint64) * _M1, part.shape[:2])
        for i in range(p.rows):
            key = mix64(key * _M2 + part[:, :, i])
    return np.ascontiguousarray(key).view(np.int64)


def sketch_planes(table: np.ndarray) -> np.ndarray:
    """(sets, longs): two well-mixed bits of each coordinate, all first bits and then all second bits, packed."""
    with np.errstate(over="ignore"):
        mixed = mix64(table ^ _M3)
    wide = np.zeros((len(table), -(-table.shape[1] // 64) * 64), dtype=np.uint64)
    out = []
    for shift in (17, 18):
        wide[:, : table.shape[1]] = (mixed >> _U(shift)) & _U(1)
        out.append((wide.reshape(len(table), -1, 64) << np.arange(64, dtype=np.uint64)).sum(axis=2, dtype=np.uint64))
    return np.concatenate(out, axis=1).view(np.int64)


def planes_apart(a: Column, b: Column, longs: int) -> Column:
    """In how many coordinates two packed sketches differ."""
    apart = F.lit(0)
    for i in range(longs):
        differ = [F.get(a, F.lit(j)).bitwiseXOR(F.get(b, F.lit(j))) for j in (i, longs + i)]
        apart = apart + F.bit_count(differ[0].bitwiseOR(differ[1]))
    return apart


def sketch_documents(docs: DataFrame, p: NearDup) -> DataFrame:
    """(doc_id, mark, n_shingles, digest, bands, planes): the digest is equal for equal sets."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            for i in range(0, len(pdf), 250):
                part = pdf.iloc[i : i + 250]
                sets = shingle_sets(part["text"].tolist(), p.words)
                table = sketch(sets, p.bins)
                keys = band_keys(table, p)
                yield pd.DataFrame({
                    "doc_id": part["doc_id"].array, "mark": part["mark"].array, "n_shingles": [len(s) for s in sets],
                    "digest": [hashlib.blake2b(s.tobytes(), digest_size=16).digest() for s in sets],
                    "bands": [k if len(s) else [] for k, s in zip(keys, sets)], "planes": list(sketch_planes(table)),
                })

    return docs.select("doc_id", "mark", "text").mapInPandas(run, "doc_id long, mark long, n_shingles long, digest binary, bands array<long>, planes array<long>")


def set_bytes(text: Column, k: int) -> Column:
    @F.pandas_udf("binary")
    def run(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for col in batches:
            yield pd.Series([s.tobytes() for s in shingle_sets(col.tolist(), k)], dtype=object)

    return run(text)


def overlap(a: Column, b: Column) -> Column:
    """Size of the intersection of two packed sets."""

    @F.pandas_udf("long")
    def run(left: pd.Series, right: pd.Series) -> pd.Series:
        read = lambda x: np.frombuffer(x, dtype=np.uint64)
        return pd.Series([len(np.intersect1d(read(x), read(y), assume_unique=True)) for x, y in zip(left, right)], dtype="int64")

    return run(a, b)


def maybe_named(texts: DataFrame, named: DataFrame) -> DataFrame:
    """The texts whose mark's place in a bitmap is set by a named one: most others stay where they lie and aren't
    shuffled. The bitmap has at most FILTER_WORDS words of 64 bits, whatever the input's size."""
    place = F.shiftrightunsigned("mark", 6).bitwiseAND(F.lit(FILTER_WORDS - 1))
    bit = F.expr("shiftleft(1L, cast(mark & 63 as int))")
    words = named.groupBy(place.alias("_word")).agg(F.bit_or(bit).alias("_bits"))
    return texts.withColumn("_word", place).join(F.broadcast(words), "_word").where(F.col("_bits").bitwiseAND(bit) != 0).drop("_word", "_bits")


class SetStore:
    """The full sets of those classes that a pair has named so far, staged; texts are read again only for new names."""

    def __init__(self, texts: DataFrame, classes: DataFrame, p: NearDup):
        self.texts, self.classes, self.p, self.parts = texts, classes.select("id", "doc_id", "mark"), p, []

    def sets(self, named: DataFrame) -> DataFrame:
        known = self._all()
        fresh = stage((named if known is None else named.join(known.select("id"), "id", "left_anti")).join(self.classes, "id"), "near-named")
        if known is None or not fresh.isEmpty():
            own = maybe_named(self.texts, fresh).join(fresh, ["doc_id", "mark"]).dropDuplicates(["id"])
            self.parts.append(stage(own.select("id", set_bytes(F.col("text"), self.p.words).alias("shingles")), "near-sets"))
        return self._all()

    def _all(self) -> DataFrame | None:
        out = None
        for part in self.parts:
            out = part if out is None else out.unionByName(part)
        return out

    def drop(self) -> None:
        drop_staged(*self.parts)

    def confirm(self, pairs: DataFrame) -> DataFrame:
        """The pairs (a, b) whose full sets reach the similarity. `pairs` should be staged."""
        bound_batches(pairs.sparkSession, 500)
        sets = self.sets(pairs.select(F.col("a").alias("id")).union(pairs.select(F.col("b").alias("id"))).distinct())
        left, right = sets.select(F.col("id").alias("a"), F.col("shingles").alias("set_a")), sets.select(F.col("id").alias("b"), F.col("shingles").alias("set_b"))
        size = lambda c: (F.octet_length(c) / 8).cast("long")
        both = pairs.select("a", "b").join(right, "b").join(left, "a").select("a", "b", size("set_a").alias("size_a"), size("set_b").alias("size_b"), overlap(F.col("set_a"), F.col("set_b")).alias("common"))
        return stage(both.where(F.col("common") * 100 >= (F.col("size_a") + F.col("size_b") - F.col("common")) * self.p.percent).select("a", "b"), "near-links")


def rare_shingles(texts: DataFrame, classes: DataFrame, p: NearDup) -> DataFrame:
    """(id, n, band, bucket) of the exact mode: of each set the n - ceil(n * similarity) + 1 rarest shingles. Two sets of that
    similarity share one of them for certain."""
    own = texts.join(classes.select("id", "n", "doc_id", "mark"), ["doc_id", "mark"]).dropDuplicates(["id"])

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            for i, n, text in zip(pdf["id"], pdf["n"], pdf["text"]):
                yield pd.DataFrame({"id": i, "n": n, "bucket": shingle_sets([text], p.words)[0].view(np.int64)})

    rows = stage(own.select("id", "n", "text").mapInPandas(run, "id long, n long, bucket long"), "near-shingles")
    known = stage(rows.groupBy("bucket").agg(F.count("*").alias("held")), "near-held")
    order = Window.partitionBy("id").orderBy("held", "bucket")  # one set
    ranked = rows.join(known, "bucket").withColumn("_r", F.row_number().over(order))
    return ranked.where(F.col("_r") <= F.col("n") - F.ceil(F.col("n") * p.percent / 100) + 1).select("id", "n", F.lit(0).alias("band"), "bucket")


def may_link(p: NearDup, n: Column, m: Column, planes: Column, other: Column) -> Column:
    """What sizes and sketches allow."""
    fits = F.least(n, m) * 100 >= F.greatest(n, m) * p.percent
    return fits if p.exact else fits & (planes_apart(planes, other, -(-p.bins // 64)) <= p.most_apart(p.bins))


def fine_sketches(sets: DataFrame) -> DataFrame:
    """(id, fine) of staged sets."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            for i in range(0, len(pdf), 100):
                part = pdf.iloc[i : i + 100]
                table = sketch([np.frombuffer(x, dtype=np.uint64) for x in part["shingles"]], FINE_BINS)
                yield pd.DataFrame({"id": part["id"].array, "fine": [x.tobytes() for x in sketch_planes(table)]})

    parts = int(sets.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return sets.select("id", "shingles").repartition(parts, "id").mapInPandas(run, "id long, fine binary")


class Members:
    """One side of a block, as arrays."""

    def __init__(self, pdf: pd.DataFrame, p: NearDup):
        stacked = lambda c: np.stack(pdf[c].to_numpy()).view(np.uint64) if len(pdf) and not p.exact else None
        self.ids, self.parts, self.sizes = (pdf[c].to_numpy(dtype=np.int64) for c in ("id", "part", "n"))
        self.planes, self.bands = stacked("planes"), stacked("bands")
        self.fine = np.frombuffer(b"".join(pdf["fine"]), dtype=np.uint64).reshape(len(pdf), -1) if len(pdf) and not p.exact else None


def apart(one: np.ndarray, many: np.ndarray) -> np.ndarray:
    """In how many coordinates a packed sketch differs from others."""
    half = len(one) // 2
    x = many ^ one
    return np.bitwise_count(x[:, :half] | x[:, half:]).sum(axis=1)


def block_pairs(left: Members, right: Members, main: int, band: int, p: NearDup) -> list[tuple[int, int, int, int, int]]:
    """(a, b, part_a, part_b, apart) of what may link between both sides of a block."""
    out = []
    for i in range(len(left.ids)):
        n, m = left.sizes[i], right.sizes
        at = np.flatnonzero((right.parts != left.parts[i]) & (np.minimum(n, m) * 100 >= np.maximum(n, m) * p.percent) & ((right.parts == main) | (right.ids > left.ids[i])))
        far = np.zeros(len(at), dtype=np.int64)
        if not p.exact and len(at):
            at = at[apart(left.planes[i], right.planes[at]) <= p.most_apart(p.bins)]
            at = at[(right.bands[at] == left.bands[i]).argmax(axis=1) == band]  # the first bucket that both share
            far = apart(left.fine[i], right.fine[at]) if len(at) else np.zeros(0, dtype=np.int64)
            at, far = at[far <= p.most_apart(FINE_BINS)], far[far <= p.most_apart(FINE_BINS)]
        for j, d in zip(at, far):
            ends = sorted(((int(left.ids[i]), int(left.parts[i])), (int(right.ids[j]), int(right.parts[j]))))
            out.append((ends[0][0], ends[1][0], ends[0][1], ends[1][1], int(d)))
    return out


def pairs_across(member: DataFrame, classes: DataFrame, parts: DataFrame, store: SetStore, p: NearDup) -> DataFrame:
    """(a, b, part_a, part_b, apart): what may link in buckets that hold several components.

    One side of a block holds members outside the bucket's largest component, the other any members; a pair outside
    the largest component is taken from its smaller id. Blocks are dealt to groups of some GROUP_ROWS rows."""
    placed = member.where("members > 2").join(parts, "id", "left").select("bucket", "band", "id", F.coalesce("component", "id").alias("part"))
    mixed = placed.groupBy("bucket").agg(F.min("part").alias("lo"), F.max("part").alias("hi")).where("lo <> hi").select("bucket")
    open_ = stage(placed.join(mixed, "bucket"), "near-open")
    sizes = open_.groupBy("bucket", "part").agg(F.count("*").alias("held"))
    main = sizes.groupBy("bucket").agg(F.max(F.struct("held", "part")).alias("top"), F.sum("held").alias("all"))
    blocks = lambda n: F.ceil(n / BLOCK_MEMBERS).cast("int")
    main = stage(main.select("bucket", F.col("top.part").alias("main"), blocks(F.col("all") - F.col("top.held")).alias("lefts"), blocks(F.col("all")).alias("rights")), "near-main")
    about = classes.select("id", "n", "planes", "bands")
    if p.exact:
        about = about.select("id", "n", *[F.lit(None).cast(t).alias(c) for c, t in (("planes", "array<long>"), ("bands", "array<long>"), ("fine", "binary"))])
    else:
        named = stage(open_.select("id").distinct(), "near-open-ids")
        about = about.join(stage(fine_sketches(store.sets(named).join(named, "id", "left_semi")), "near-fine"), "id")
    rows = open_.join(main, "bucket").join(about, "id")
    own = F.xxhash64("id")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    left = rows.where("part <> main").withColumns({"side": F.lit(0), "lc": F.pmod(own, "lefts").cast("int")}).withColumn("rc", every("rights"))
    right = rows.withColumns({"side": F.lit(1), "rc": F.pmod(own, "rights").cast("int")}).withColumn("lc", every("lefts"))
    total = main.join(open_.groupBy("bucket").agg(F.count("*").alias("n")), "bucket").agg(F.sum(F.col("n") * F.greatest("lefts", "rights"))).first()[0] or 0
    groups = max(1, math.ceil(total / GROUP_ROWS))
    dealt = left.unionByName(right).withColumn("grp", F.pmod(F.xxhash64("bucket", "lc", "rc"), F.lit(groups)))
    columns = ["grp", "bucket", "lc", "rc", "side", "band", "main", "id", "part", "n", "planes", "fine", "bands"]

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        found = []
        for _, block in pdf.groupby(["bucket", "lc", "rc"], sort=False):
            sides = [Members(block[block["side"] == k], p) for k in (0, 1)]
            if len(sides[0].ids) and len(sides[1].ids):
                found += block_pairs(*sides, int(block["main"].iloc[0]), int(block["band"].iloc[0]), p)
        return pd.DataFrame(found, columns=["a", "b", "part_a", "part_b", "apart"], dtype="int64")

    found = dealt.select(*columns).groupBy("grp").applyInPandas(run, "a long, b long, part_a long, part_b long, apart long")
    return found.distinct() if p.exact else found


def near_classes(docs: DataFrame, p: NearDup) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Staged sketches of all rows, staged classes of equal sets, and (id, component) of the linked classes."""
    bound_batches(docs.sparkSession)
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_mark(F.col("text")).alias("mark"), "text")
    sketched = stage(sketch_documents(texts, p), "near-sketches")
    usable = sketched.where(F.col("doc_id").isNotNull() & (F.col("n_shingles") > 0))
    first = usable.groupBy("digest").agg(F.min(F.struct("doc_id", "mark", "n_shingles", "bands", "planes")).alias("c"))
    # numbers are given once, as the table is written
    classes = stage(first.select(F.monotonically_increasing_id().alias("id"), "digest", F.col("c.doc_id").alias("doc_id"), F.col("c.mark").alias("mark"), F.col("c.n_shingles").alias("n"), "c.bands", "c.planes"), "near-classes")
    banded = stage(rare_shingles(texts, classes, p), "near-rare") if p.exact else classes.select("id", "n", F.posexplode("bands").alias("band", "bucket"))
    shared = stage(banded.groupBy("bucket").agg(F.count("*").alias("members")).where("members > 1"), "near-buckets")
    member = stage(banded.join(shared, "bucket"), "near-members")
    # how many others a class meets: the text that copies were made from meets more than they meet each other
    met = stage(member.groupBy("id").agg(F.sum("members").alias("met")), "near-met")
    centres = member.join(met, "id").groupBy("bucket").agg(F.max(F.struct("met", (-F.col("id")).alias("neg"), "n")).alias("c"))
    centres = stage(centres.select("bucket", (-F.col("c.neg")).alias("centre"), F.col("c.n").alias("centre_n")), "near-centres")
    spokes = member.join(centres, "bucket").where((F.col("id") != F.col("centre")) & (F.least("n", "centre_n") * 100 >= F.greatest("n", "centre_n") * p.percent))
    spokes = spokes.select(F.least("id", "centre").alias("a"), F.greatest("id", "centre").alias("b")).distinct()
    sides = [classes.select(F.col("id").alias(k), F.col("n").alias(f"n_{k}"), F.col("planes").alias(f"planes_{k}")) for k in "ab"]
    near = spokes.join(sides[1], "b").join(sides[0], "a").where(may_link(p, F.col("n_a"), F.col("n_b"), F.col("planes_a"), F.col("planes_b")))
    store = SetStore(texts, classes, p)
    near = stage(near.select("a", "b"), "near-pairs")
    links = store.confirm(near)
    parts = stage(connected_components(links), "near-parts")
    left = stage(pairs_across(member, classes, parts, store, p), "near-across")
    best = left.groupBy(F.least("part_a", "part_b").alias("lo"), F.greatest("part_a", "part_b").alias("hi")).agg(F.min(F.struct("apart", "a", "b")).alias("p"))
    best = stage(best.select("p.a", "p.b", "lo", "hi"), "near-closest")
    sure = store.confirm(best)
    if not sure.isEmpty():  # what these links join needs no further test
        joined = best.join(sure, ["a", "b"], "left_semi").select(F.col("lo").alias("a"), F.col("hi").alias("b"))
        now = stage(connected_components(joined), "near-joined")
        for k in "ab":
            left = left.join(now.select(F.col("id").alias(f"part_{k}"), F.col("component").alias(f"now_{k}")), f"part_{k}", "left")
        left = left.where(F.coalesce("now_a", "part_a") != F.coalesce("now_b", "part_b")).select("a", "b")
        left = stage(left, "near-across")
    sure = stage(sure.unionByName(store.confirm(left.select("a", "b"))), "near-more-links")
    if not sure.isEmpty():
        parts = stage(connected_components(links.unionByName(sure)), "near-parts")
    store.drop()
    drop_staged(member)
    return sketched, classes, parts


def text_mark(text: Column) -> Column:
    """Tells texts of one doc_id apart."""
    return F.xxhash64(F.coalesce(text, F.lit("")))


def near_duplicates(docs: DataFrame, p: NearDup = NearDup()) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept, mark, chosen), one row for each row of `docs` (columns doc_id, text).
    `chosen` marks one doc_id and text of each group: the smallest doc_id, then the smallest mark of its text."""
    sketched, classes, parts = near_classes(docs, p)
    placed = classes.join(parts, "id", "left").select("digest", "doc_id", "mark", F.coalesce("component", "id").alias("component"))
    placed = stage(placed, "near-placed")
    least = stage(placed.groupBy("component").agg(F.min(F.struct("doc_id", "mark")).alias("least")), "near-least")
    named = stage(placed.join(least, "component").select("digest", "least"), "near-named-classes")
    alone = F.col("doc_id").isNull() | (F.col("n_shingles") == 0)
    none = sketched.where(alone).select("doc_id", "n_shingles", F.col("doc_id").alias("component_id"), "mark", F.lit(True).alias("chosen"))
    linked = sketched.where(~alone).join(named, "digest")
    linked = linked.select("doc_id", "n_shingles", F.col("least.doc_id").alias("component_id"), "mark", (F.struct("doc_id", "mark") == F.col("least")).alias("chosen"))
    return linked.union(none).select("doc_id", "n_shingles", "component_id", F.col("doc_id").eqNullSafe(F.col("component_id")).alias("kept"), "mark", "chosen")


def op9_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(read_table(spark, sf_dir, "documents", "doc_id", "text"), NearDup(words=2)).select("doc_id", "n_shingles", "component_id", "kept")


OP9_SQL = r"""
WITH RECURSIVE d AS (
  SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda w: w <> '') AS w FROM documents),
s AS (
  SELECT DISTINCT doc_id, CASE WHEN len(w) = 1 THEN w[1] ELSE w[i] || ' ' || w[i + 1] END AS g
  FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w), 2))) AS i FROM d WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) AS n, md5(string_agg(g, chr(10) ORDER BY g)) AS h FROM s GROUP BY doc_id),
r AS (SELECT min(doc_id) AS doc_id, h, any_value(n) AS n FROM n GROUP BY h),
t AS (SELECT s.doc_id, g, r.n FROM s JOIN r USING (doc_id)),
p AS (
  SELECT a.doc_id AS a, b.doc_id AS b FROM t a JOIN t b ON a.g = b.g AND a.doc_id < b.doc_id AND 100 * least(a.n, b.n) >= 80 * greatest(a.n, b.n)
  GROUP BY a.doc_id, b.doc_id, a.n, b.n HAVING 100 * count(*) >= 80 * (a.n + b.n - count(*))),
e AS (SELECT a, b FROM p UNION ALL SELECT b, a FROM p),
reach AS (SELECT doc_id AS a, doc_id AS b FROM r UNION SELECT reach.a, e.b FROM reach JOIN e ON reach.b = e.a),
c AS (SELECT a, min(b) AS c FROM reach GROUP BY a)
SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, coalesce(c.c, d.doc_id) AS component_id, d.doc_id = coalesce(c.c, d.doc_id) AS kept
FROM d LEFT JOIN n USING (doc_id) LEFT JOIN r ON n.h = r.h LEFT JOIN c ON c.a = r.doc_id
"""
