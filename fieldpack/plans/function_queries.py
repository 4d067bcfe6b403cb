"""Scalar function families over the given tables, each with an SQL twin."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.vectors import register as register_vectors
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


@query("fn_math", f"""SELECT event_id, CAST(floor(value) AS BIGINT) AS fl, CAST(ceil(value) AS BIGINT) AS ce, {q6('sqrt(value)', 'sq')}, {q6('ln(value + 1)', 'l')}, {q6('log10(value + 1)', 'l10')}, {q6('log2(value + 1)', 'l2')},
 {q6('exp(-value / 100)', 'ex')}, {q6('sin(value)', 'si')}, {q6('cos(value)', 'co')}, {q6('pow(value, 0.5)', 'po')}, CAST(sign(value - 50) AS DOUBLE) AS sg, {q6('abs(value - 50)', 'ab')}, CAST(user_id % 7 AS BIGINT) AS md,
 {q6('greatest(value, 50)', 'gr')}, {q6('least(value, 50)', 'le')}, {q6('sqrt(value * value + 9)', 'hy')} FROM events""")
def fn_math(spark, d):
    v = F.col("value")
    return load(spark, d, "events", "event_id", "user_id", "value").select(
        "event_id", F.floor(v).alias("fl"), F.ceil(v).alias("ce"), r6(F.sqrt(v), "sq"), r6(F.log(v + 1), "l"), r6(F.log10(v + 1), "l10"), r6(F.log2(v + 1), "l2"), r6(F.exp(-v / 100), "ex"), r6(F.sin(v), "si"), r6(F.cos(v), "co"),
        r6(F.pow(v, F.lit(0.5)), "po"), F.sign(v - 50).alias("sg"), r6(F.abs(v - 50), "ab"), F.pmod("user_id", F.lit(7)).alias("md"), r6(F.greatest(v, F.lit(50.0)), "gr"), r6(F.least(v, F.lit(50.0)), "le"), r6(F.hypot(v, F.lit(3.0)), "hy"),
    )


@query("fn_bits", "SELECT o_orderkey, CAST(o_orderkey << 3 AS BIGINT) AS sl, CAST(o_orderkey >> 2 AS BIGINT) AS sr, CAST(o_orderkey & 255 AS BIGINT) AS an, CAST(o_orderkey | 1024 AS BIGINT) AS orr, CAST(xor(o_orderkey, 77) AS BIGINT) AS xo, CAST(bit_count(o_orderkey) AS INTEGER) AS bc, upper(to_hex(o_orderkey)) AS hx, to_binary(o_orderkey) AS bn FROM orders")
def fn_bits(spark, d):
    k = F.col("o_orderkey")
    one = lambda n: F.lit(n).cast("long")
    return load(spark, d, "orders", "o_orderkey").select("o_orderkey", F.shiftleft(k, 3).alias("sl"), F.shiftright(k, 2).alias("sr"), k.bitwiseAND(one(255)).alias("an"), k.bitwiseOR(one(1024)).alias("orr"), k.bitwiseXOR(one(77)).alias("xo"), F.bit_count(k).alias("bc"), F.hex(k).alias("hx"), F.bin(k).alias("bn"))


@query("fn_string", """SELECT page_id, split_part(url, '/', 3) AS host, regexp_extract(url, 'page=([0-9]+)', 1) AS page, regexp_replace(url, '[0-9]+', '#', 'g') AS masked, concat_ws('|', substr(url, 1, 4), CAST(length(url) AS VARCHAR)) AS cw,
 lpad(CAST(page_id AS VARCHAR), 8, '0') AS lp, rpad(CAST(page_id AS VARCHAR), 6, '.') AS rp, upper(substr(url, 8, 5)) AS up, translate(url, 'aeiou', 'AEIOU') AS tr, CAST(instr(url, 'example') AS INTEGER) AS ins, reverse(url) AS rev, repeat('ab', CAST(page_id % 4 AS INTEGER)) AS rep, CAST(levenshtein(substr(url, 1, 12), 'http://thtre.') AS INTEGER) AS lev, trim('  ' || substr(url, 1, 5) || ' ') AS tm FROM pages""")
def fn_string(spark, d):
    u, p = F.col("url"), F.col("page_id").cast("string")
    return load(spark, d, "pages", "page_id", "url").select(
        "page_id", F.split_part(u, F.lit("/"), F.lit(3)).alias("host"), F.regexp_extract(u, "page=([0-9]+)", 1).alias("page"), F.regexp_replace(u, "[0-9]+", "#").alias("masked"), F.concat_ws("|", F.substring(u, 1, 4), F.length(u)).alias("cw"),
        F.lpad(p, 8, "0").alias("lp"), F.rpad(p, 6, ".").alias("rp"), F.upper(F.substring(u, 8, 5)).alias("up"), F.translate(u, "aeiou", "AEIOU").alias("tr"), F.instr(u, "example").alias("ins"), F.reverse(u).alias("rev"),
        F.repeat(F.lit("ab"), (F.col("page_id") % 4).cast("int")).alias("rep"), F.levenshtein(F.substring(u, 1, 12), F.lit("http://thtre.")).alias("lev"), F.trim(F.concat(F.lit("  "), F.substring(u, 1, 5), F.lit(" "))).alias("tm"),
    )


@query("fn_bytes", "SELECT item_id, CAST(ascii(text) AS INTEGER) AS first_char, CAST(strlen(text) AS INTEGER) AS octets, base64(encode(substr(text, 1, 12))) AS b64, lower(hex(encode(substr(text, 1, 6)))) AS hx FROM benchmark")
def fn_bytes(spark, d):
    t = F.col("text")
    return load(spark, d, "benchmark", "item_id", "text").select("item_id", F.ascii(t).alias("first_char"), F.octet_length(t).alias("octets"), F.base64(F.encode(F.substring(t, 1, 12), "UTF-8")).alias("b64"), F.lower(F.hex(F.encode(F.substring(t, 1, 6), "UTF-8"))).alias("hx"))


@query("fn_date", """SELECT o_orderkey, CAST(CAST(date_trunc('month', o_orderdate) AS DATE) AS VARCHAR) AS m, CAST(datediff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS dd, CAST(quarter(o_orderdate) AS INTEGER) AS q, CAST(month(o_orderdate) AS INTEGER) AS mo,
 CAST(hour(o_orderdate) AS INTEGER) AS h, CAST(dayofweek(o_orderdate) + 1 AS INTEGER) AS dw, CAST(CAST(CAST(o_orderdate AS DATE) + INTERVAL 3 MONTH AS DATE) AS VARCHAR) AS am, CAST(make_date(CAST(year(o_orderdate) AS INTEGER), 1, 1) AS VARCHAR) AS md, CAST(last_day(CAST(o_orderdate AS DATE)) AS VARCHAR) AS ld, CAST(CAST(o_orderdate AS DATE) + 10 AS VARCHAR) AS da FROM orders""")
def fn_date(spark, d):
    o = F.col("o_orderdate")
    return load(spark, d, "orders", "o_orderkey", "o_orderdate").select(
        "o_orderkey", F.trunc(o, "month").cast("string").alias("m"), F.datediff(o, F.lit("1992-01-01")).alias("dd"), F.quarter(o).alias("q"), F.month(o).alias("mo"), F.hour(o).alias("h"), F.dayofweek(o).alias("dw"),
        F.add_months(F.to_date(o), 3).cast("string").alias("am"), F.make_date(F.year(o), F.lit(1), F.lit(1)).cast("string").alias("md"), F.last_day(o).cast("string").alias("ld"), F.date_add(F.to_date(o), 10).cast("string").alias("da"),
    )


@query("fn_array", f"""SELECT vec_id, {q6('list_sum(list_transform(e, lambda x: x * x))', 'sq')}, CAST(len(list_filter(e, lambda x: x > 0)) AS INTEGER) AS pos, {q6('list_min(e)', 'lo')}, {q6('list_max(e)', 'hi')}, {q6('list_sum(e[5:12])', 'part')}, {q6('list_sort(e)[1]', 'first')}, {q6('e[64]', 'last')}, len(list_filter(e, lambda x: x > 0.3)) > 0 AS anybig, CAST(list_position(e, list_max(e)) AS BIGINT) AS at
 FROM (SELECT vec_id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS e FROM embeddings)""")
def fn_array(spark, d):
    e = F.col("e")
    total = lambda a: F.aggregate(a, F.lit(0.0), lambda x, y: x + y)
    v = load(spark, d, "embeddings", "vec_id", "embedding").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("e"))
    return v.select("vec_id", r6(total(F.transform(e, lambda x: x * x)), "sq"), F.size(F.filter(e, lambda x: x > 0)).alias("pos"), r6(F.array_min(e), "lo"), r6(F.array_max(e), "hi"), r6(total(F.slice(e, 5, 8)), "part"), r6(F.array_sort(e)[0], "first"), r6(F.element_at(e, -1), "last"), F.exists(e, lambda x: x > 0.3).alias("anybig"), F.array_position(e, F.array_max(e)).alias("at"))


@query("fn_map", "SELECT conv_id, CAST(count(DISTINCT role) AS INTEGER) AS roles, CAST(max(turn) FILTER (role = 'user') AS BIGINT) AS last_user FROM conversations GROUP BY 1")
def fn_map(spark, d):
    c = load(spark, d, "conversations", "conv_id", "role", "turn").groupBy("conv_id", "role").agg(F.max("turn").alias("t"))
    m = c.groupBy("conv_id").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("role", "t")))).alias("m"))
    return m.select("conv_id", F.size(F.map_keys("m")).alias("roles"), F.element_at(F.transform_values("m", lambda k, v: v), "user").alias("last_user"))


@query("fn_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k, CAST(json_extract_string(props, '$.k') AS INTEGER) + 1 AS k1, '{\"k\":' || json_extract_string(props, '$.k') || '}' AS j FROM events")
def fn_json(spark, d):
    p = F.from_json("props", "k int")
    return load(spark, d, "events", "event_id", "props").select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k"), (p["k"] + 1).alias("k1"), F.to_json(p).alias("j"))


@query("fn_struct", "SELECT n_nationkey, n_regionkey * 10 AS a, n_name AS b, n_nationkey + 1 AS c FROM nation")
def fn_struct(spark, d):
    s = F.struct((F.col("n_regionkey") * 10).alias("a"), F.col("n_name").alias("b")).withField("c", F.col("n_nationkey") + 1)
    return load(spark, d, "nation").select("n_nationkey", F.inline(F.array(s)))


@query("fn_cond", "SELECT event_id, CASE WHEN value > 100 THEN 'high' WHEN value > 20 THEN 'mid' ELSE 'low' END AS band, nullif(event_type, 'view') AS nv, coalesce(nullif(event_type, 'view'), 'none') AS cv, CASE WHEN user_id % 2 = 0 THEN 1 ELSE 0 END AS even FROM events")
def fn_cond(spark, d):
    v = F.col("value")
    return load(spark, d, "events", "event_id", "user_id", "event_type", "value").select("event_id", F.when(v > 100, "high").when(v > 20, "mid").otherwise("low").alias("band"), F.nullif("event_type", F.lit("view")).alias("nv"), F.nvl(F.nullif("event_type", F.lit("view")), F.lit("none")).alias("cv"), F.expr("if(user_id % 2 = 0, 1, 0)").alias("even"))


@query("fn_cast", "SELECT o_orderkey, CAST(round(o_totalprice * 100) AS BIGINT) AS cents, CAST(o_orderkey AS VARCHAR) AS s, CAST(o_orderkey AS DOUBLE) AS dbl, TRY_CAST(o_orderpriority AS INTEGER) AS none, CAST(substr(o_orderpriority, 1, 1) AS VARCHAR) AS p FROM orders")
def fn_cast(spark, d):
    return load(spark, d, "orders", "o_orderkey", "o_totalprice", "o_orderpriority").select("o_orderkey", F.round(F.col("o_totalprice") * 100).cast("long").alias("cents"), F.col("o_orderkey").cast("string").alias("s"), F.col("o_orderkey").cast("double").alias("dbl"), F.col("o_orderpriority").try_cast("int").alias("none"), F.substring("o_orderpriority", 1, 1).alias("p"))


@query("fn_hash", "SELECT c_custkey, md5(c_name) AS m, sha256(c_name) AS s FROM customer")
def fn_hash(spark, d):
    return load(spark, d, "customer", "c_custkey", "c_name").select("c_custkey", F.md5("c_name").alias("m"), F.sha2("c_name", 256).alias("s"))


@query("fn_vector", f"""WITH c AS (SELECT embedding AS q FROM embeddings WHERE vec_id = 0), v AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS e, (SELECT list_transform(q, lambda x: CAST(x AS DOUBLE)) FROM c) AS q FROM embeddings)
 SELECT vec_id, {q6('list_sum(list_transform(list_zip(e, q), lambda p: p[1] * p[2]))', 'dot')}, {q6('sqrt(list_sum(list_transform(list_zip(e, q), lambda p: (p[1] - p[2]) * (p[1] - p[2]))))', 'l2')}, {q6('list_sum(list_transform(list_zip(e, q), lambda p: 2 * p[1] + p[2]))', 'axpy')}, {q6('sqrt(list_sum(list_transform(e, lambda x: x * x)))', 'energy')} FROM v""")
def fn_vector(spark, d):
    register_vectors(spark)
    e = load(spark, d, "embeddings", "vec_id", "embedding").selectExpr("vec_id", "transform(embedding, x -> CAST(x AS DOUBLE)) AS e")
    q = e.where("vec_id = 0").selectExpr("e AS q")
    return spark.sql("SELECT vec_id, round(fp_dot(e, q), 6) + 0.0 AS dot, round(fp_l2(e, q), 6) + 0.0 AS l2, round(fp_total(fp_axpy(2.0D, e, q)), 6) + 0.0 AS axpy, round(fp_block_energy(e), 6) + 0.0 AS energy FROM {e} CROSS JOIN {q}", e=e, q=F.broadcast(q))


@query("fn_udtf", "SELECT n_nationkey, CAST(s AS INTEGER) AS scale, CAST(ceil((n_nationkey + 1) / pow(2, s - 1)) AS INTEGER) AS extent FROM nation, (SELECT unnest([1, 2, 3]) AS s)")
def fn_udtf(spark, d):
    from ..functions.tables import register as register_tables

    register_tables(spark)
    return spark.sql("SELECT n_nationkey, p.scale, p.extent FROM {n}, LATERAL fp_pyramid_levels(n_nationkey + 1, 3) p", n=load(spark, d, "nation", "n_nationkey"))


@query("fn_udaf", f"SELECT l_returnflag, {q6('20 * log10(105000.0) - 10 * log10(avg((l_extendedprice - l_quantity * 2000) * (l_extendedprice - l_quantity * 2000)))', 'psnr', 4)} FROM lineitem GROUP BY 1")
def fn_udaf(spark, d):
    from ..functions.aggregates import psnr_agg

    li = load(spark, d, "lineitem", "l_returnflag", "l_extendedprice", "l_quantity")
    return li.groupBy("l_returnflag").agg(r6(psnr_agg(F.col("l_extendedprice"), F.col("l_quantity") * 2000, 105000.0), "psnr", 4))
