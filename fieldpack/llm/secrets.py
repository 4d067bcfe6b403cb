"""Secret scans with DataFrame functions only.

Three fixed patterns give base spans. Over candidate strings of a character class, a window slides:
its symbol counts change by one symbol out and one in, and the sum of c*log2(c) with them, so the
window's Shannon entropy costs the same at every step. Every candidate is scored. Windows that overlap
or adjoin a word of the allow-list don't count, the candidate's other windows do; the stretch from the
first to the last window over the class's threshold becomes a span.

Sums are integers (millionths of a bit), so every engine gets the same spans.

Cases: null and empty texts have no spans; spans of different kinds may overlap and all are
returned; repeated rows give repeated results; texts of any length are scanned whole.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import read_table


def _either_case(word: str) -> str:
    return "".join(f"[{c.upper()}{c}]" if c.isalpha() else c for c in word)


#: The contract's patterns. Letters of the names match in either case, ASCII only.
NAMES = "|".join(_either_case(w) for w in ("password", "passwd", "secret", "token", "api_?key"))
ASSIGN = f"""({NAMES})["']?\\x20*[:=]\\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ASSIGN_VALUE = 6
ACCESS = "AKIA[A-Z0-9]{16,}"
HEX = "[0-9a-f]{24,}"
KINDS = ["assign", "access", "hex", "entropy"]
#: Words that mark the windows around them as harmless.
ALLOWED = "(?:" + "|".join(_either_case(w) for w in ("example", "sample", "dummy", "placeholder", "changeme", "deadbeef", "0123456789", "1234567890", "abcdefghij")) + ")"
UNIT = 1_000_000


@dataclass(frozen=True)
class CharClass:
    """Candidate strings of a class, its symbols, the window's length and the least entropy in bits."""

    name: str
    pattern: str
    symbols: str
    window: int
    bits: float

    def weight(self, c: int) -> int:
        return round(c * math.log2(c) * UNIT) if c > 1 else 0

    @property
    def most(self) -> int:
        """A window counts if its sum of c*log2(c) is at most this."""
        return math.floor((math.log2(self.window) - self.bits) * self.window * UNIT)


CLASSES = (
    CharClass("hex", "[0-9A-Fa-f]{24,}", "0123456789abcdefABCDEF", 24, 2.9),
    CharClass("base64", "[A-Za-z0-9+/_=-]{20,}", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_=-", 20, 3.75),
)


def match_spans(text: Column, pattern: str, least_of_group: tuple[int, int] | None = None) -> Column:
    """Leftmost matches that don't overlap, as array<struct<start,end,hit>> in code points. Where
    `least_of_group` is (g, n), matches whose group g has fewer than n characters are dropped."""
    hits = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    group = F.regexp_extract_all(text, F.lit(pattern), F.lit(least_of_group[0])) if least_of_group else hits
    parts = F.arrays_zip(hits.alias("hit"), group.alias("grp"), F.split(text, pattern, -1).alias("gap"))
    nothing = F.array().cast("array<struct<start:int,end:int,hit:string>>")

    def step(acc: Column, x: Column) -> Column:
        start = acc["at"] + F.length(x["gap"])
        end = start + F.length(x["hit"])
        span = F.struct(start.alias("start"), end.alias("end"), x["hit"].alias("hit"))
        keep = F.length(x["grp"]) >= (least_of_group[1] if least_of_group else 0)
        return F.struct(end.alias("at"), F.when(keep, F.concat(acc["out"], F.array(span))).otherwise(acc["out"]).alias("out"))

    whole = F.filter(parts, lambda x: x["hit"].isNotNull())
    return F.aggregate(whole, F.struct(F.lit(0).alias("at"), nothing.alias("out")), step, lambda acc: acc["out"])


def entropy_stretch(candidate: Column, cls: CharClass) -> Column:
    """struct<first,last>: where the first and after where the last window over the threshold lies, or nulls."""
    w = cls.window
    weights = F.array(*[F.lit(cls.weight(c)).cast("long") for c in range(w + 1)])
    code = lambda i: F.instr(F.lit(cls.symbols), F.substring(candidate, i, F.lit(1)))

    def step(acc: Column, i: Column) -> Column:
        came, went = code(i), F.when(i > w, code(i - w)).otherwise(F.lit(0))
        same = came == went
        of = lambda at: F.get(acc["counts"], at - 1)
        less = F.when((went > 0) & ~same, F.get(weights, of(went) - 1) - F.get(weights, of(went))).otherwise(F.lit(0).cast("long"))
        more = F.when(~same, F.get(weights, of(came) + 1) - F.get(weights, of(came))).otherwise(F.lit(0).cast("long"))
        total = acc["total"] + less + more
        counts = F.transform(acc["counts"], lambda c, k: c + F.when(k + 1 == came, 1).otherwise(0) - F.when(k + 1 == went, 1).otherwise(0))
        hot = (i >= w) & (total <= cls.most) & ~F.exists(acc["allowed"], lambda x: (x["start"] <= i) & (x["end"] >= i - w))
        return F.struct(
            F.when(same, acc["counts"]).otherwise(counts).alias("counts"), total.alias("total"),
            F.when(hot & acc["first"].isNull(), i - w).otherwise(acc["first"]).alias("first"), F.when(hot, i).otherwise(acc["last"]).alias("last"), acc["allowed"].alias("allowed"),
        )

    none = F.lit(None).cast("int")
    start = F.struct(F.array_repeat(F.lit(0), len(cls.symbols)).alias("counts"), F.lit(0).cast("long").alias("total"), none.alias("first"), none.alias("last"), match_spans(candidate, ALLOWED).alias("allowed"))
    return F.aggregate(F.sequence(F.lit(1), F.length(candidate)), start, step, lambda acc: F.struct(acc["first"].alias("first"), acc["last"].alias("last")))


def entropy_spans(text: Column, cls: CharClass) -> Column:
    """Spans of the class: array<struct<start,end>>."""
    placed = F.transform(match_spans(text, cls.pattern), lambda x: F.struct(x["start"].alias("base"), entropy_stretch(x["hit"], cls).alias("in")))
    hot = F.filter(placed, lambda x: x["in"]["first"].isNotNull())
    return F.transform(hot, lambda x: F.struct((x["base"] + x["in"]["first"]).alias("start"), (x["base"] + x["in"]["last"]).alias("end")))


def _ranked(spans: Column, rank: int) -> Column:
    return F.transform(spans, lambda x: F.struct(x["start"].alias("start"), F.lit(rank).alias("rank"), x["end"].alias("end")))


def _written(spans: Column) -> Column:
    kind = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", F.get(kind, x["rank"]), x["start"], x["end"])), ",")


def find_secrets(docs: DataFrame, text_col: str = "text", prefix: str = "secret_") -> DataFrame:
    """`docs` with arrays of spans: `<prefix>base` and `<prefix>all`, struct<start,rank,end>, by start and then kind."""
    empty = F.array().cast("array<struct<start:int,rank:int,end:int>>")
    text = F.coalesce(F.col(text_col), F.lit(""))
    p = lambda name: f"{prefix}{name}"
    df = docs.withColumns({
        p("assign"): F.when(text.rlike(f"(?:{NAMES})[\"']?\\x20*[:=]"), _ranked(match_spans(text, ASSIGN, (2, ASSIGN_VALUE)), 0)).otherwise(empty),
        p("access"): F.when(text.contains("AKIA"), _ranked(match_spans(text, ACCESS), 1)).otherwise(empty),
        p("hex"): F.when(text.rlike(HEX), _ranked(match_spans(text, HEX), 2)).otherwise(empty),
        **{p(f"entropy_{c.name}"): F.when(text.rlike(c.pattern), _ranked(entropy_spans(text, c), 3)).otherwise(empty) for c in CLASSES},
    })
    df = df.withColumn(p("base"), F.array_sort(F.concat(p("assign"), p("access"), p("hex"))))
    more = F.array_distinct(F.concat(*[F.col(p(f"entropy_{c.name}")) for c in CLASSES]))
    return df.withColumn(p("all"), F.array_sort(F.concat(p("base"), more)))


def redact(text: Column, spans: Column, mark: str = "[SECRET]") -> Column:
    """The text with every stretch that spans cover replaced by one mark."""

    def step(acc: Column, x: Column) -> Column:
        fresh = x["start"] >= acc["at"]
        grown = F.concat(acc["out"], F.substring(text, acc["at"] + 1, x["start"] - acc["at"]), F.lit(mark))
        return F.struct(F.greatest(acc["at"], x["end"]).alias("at"), F.when(fresh, grown).otherwise(acc["out"]).alias("out"))

    start = F.struct(F.lit(0).alias("at"), F.lit("").alias("out"))
    return F.when(F.size(spans) == 0, text).otherwise(F.aggregate(spans, start, step, lambda acc: F.concat(acc["out"], F.substring(text, acc["at"] + 1, F.length(text)))))


def op7_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = find_secrets(read_table(spark, sf_dir, "documents", "doc_id", "text"))
    n = lambda kind: F.size(f"secret_{kind}").cast("long").alias(f"n_{kind}")
    return found.select("doc_id", n("assign"), n("access"), n("hex"), F.sha2(_written(F.col("secret_base")), 256).alias("base_sha256"), _written(F.col("secret_all")).alias("spans"))


def _sql_spans(kind: str, pattern: str, least: str) -> str:
    """A lateral list of struct(s, r, e, h) for a pattern; `least` keeps hit number i."""
    pat = pattern.replace("'", "''")
    return f"""
      SELECT doc_id, {KINDS.index(kind)} AS r, h[i] AS hit,
             list_sum(list_transform(g[1:i], lambda x: length(x))) + coalesce(list_sum(list_transform(h[1:i - 1], lambda x: length(x))), 0) AS s
      FROM (SELECT doc_id, h, g, v, unnest(range(1, len(h) + 1)) AS i
            FROM (SELECT doc_id, regexp_extract_all(t, '{pat}', 0) AS h, regexp_extract_all(t, '{pat}', {2 if kind == "assign" else 0}) AS v, string_split_regex(t, '{pat}') AS g FROM d))
      WHERE {least}"""


def _sql_entropy(cls: CharClass) -> str:
    w = cls.window
    weight = "CAST(round(c * log2(c) * 1000000) AS BIGINT)"
    return f"""
      SELECT doc_id, 3 AS r, min(s + k) AS s, max(s + k) + {w} AS e
      FROM (SELECT doc_id, s, k, (SELECT sum({weight}) FROM (SELECT count(*) AS c FROM (SELECT unnest(string_split(substr(hit, k + 1, {w}), '')) AS ch) GROUP BY ch)) AS total
            FROM (SELECT doc_id, s, hit, unnest(range(0, length(hit) - {w} + 1)) AS k FROM ({_sql_spans("entropy", cls.pattern, "true")})
                  WHERE regexp_matches(hit, '[0-9]') AND regexp_matches(hit, '[A-Za-z]') AND NOT regexp_matches(hit, '{ALLOWED}')))
      WHERE total <= {cls.most} GROUP BY doc_id, s_of(s)"""


OP7_SQL = f"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
base AS (
  SELECT doc_id, r, s, s + length(hit) AS e FROM ({_sql_spans("assign", ASSIGN, "length(v[i]) >= 6")})
  UNION ALL SELECT doc_id, r, s, s + length(hit) FROM ({_sql_spans("access", ACCESS, "true")})
  UNION ALL SELECT doc_id, r, s, s + length(hit) FROM ({_sql_spans("hex", HEX, "true")})),
more AS (
  SELECT DISTINCT * FROM ({_sql_entropy(CLASSES[0]).replace("s_of(s)", "base_s").replace("SELECT doc_id, s, k, (", "SELECT doc_id, s, s AS base_s, k, (")}
  UNION ALL {_sql_entropy(CLASSES[1]).replace("s_of(s)", "base_s").replace("SELECT doc_id, s, k, (", "SELECT doc_id, s, s AS base_s, k, (")})),
every AS (SELECT * FROM base UNION ALL SELECT doc_id, r, s, e FROM more),
names AS (SELECT *, ['assign', 'access', 'hex', 'entropy'][r + 1] || ':' || CAST(s AS BIGINT) || ':' || CAST(e AS BIGINT) AS word FROM every)
SELECT d.doc_id,
  count(*) FILTER (WHERE r = 0) AS n_assign, count(*) FILTER (WHERE r = 1) AS n_access, count(*) FILTER (WHERE r = 2) AS n_hex,
  sha256(coalesce(string_agg(word, ',' ORDER BY s, r) FILTER (WHERE r < 3), '')) AS base_sha256,
  coalesce(string_agg(word, ',' ORDER BY s, r, e), '') AS spans
FROM d LEFT JOIN names USING (doc_id) GROUP BY d.doc_id
"""
