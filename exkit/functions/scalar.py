"""Scalar and nested functions on the given tables, each held against SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from exkit.book import Book

BOOK = Book()
query, both = BOOK.query, BOOK.both

both("fn_string_case", "SELECT p_partkey, upper(p_name) AS u, lower(p_brand) AS l, trim(concat('  ', p_type, ' ')) AS t, length(p_name) AS n, reverse(p_brand) AS r, repeat(p_brand, 2) AS rr FROM {part}",
     "SELECT p_partkey, upper(p_name) AS u, lower(p_brand) AS l, trim(concat('  ', p_type, ' ')) AS t, CAST(length(p_name) AS BIGINT) AS n, reverse(p_brand) AS r, repeat(p_brand, 2) AS rr FROM {part}")
both("fn_string_parts", "SELECT p_partkey, substr(p_name, 2, 3) AS s, instr(p_name, 'a') AS i, lpad(p_brand, 12, '*') AS lp, rpad(p_brand, 12, '-') AS rp, split_part(p_type, ' ', 1) AS sp, concat_ws('/', p_brand, p_type) AS c, translate(p_brand, 'Bd', 'xy') AS tr, levenshtein(p_brand, p_type) AS lv FROM {part}",
     "SELECT p_partkey, substr(p_name, 2, 3) AS s, CAST(instr(p_name, 'a') AS BIGINT) AS i, lpad(p_brand, 12, '*') AS lp, rpad(p_brand, 12, '-') AS rp, split_part(p_type, ' ', 1) AS sp, concat_ws('/', p_brand, p_type) AS c, translate(p_brand, 'Bd', 'xy') AS tr, CAST(levenshtein(p_brand, p_type) AS BIGINT) AS lv FROM {part}")


@query(r"SELECT doc_id, regexp_extract(text, '([a-z]+)tion', 1) AS stem, regexp_replace(lang, '[aeiou]', '_', 'g') AS l, CAST(strlen(text) AS BIGINT) AS bytes FROM documents")
def fn_string_regex(t):
    return t.documents.select("doc_id", F.regexp_extract("text", "([a-z]+)tion", 1).alias("stem"), F.regexp_replace("lang", "[aeiou]", "_").alias("l"), F.octet_length("text").cast("long").alias("bytes"))


@query("SELECT o_orderkey, md5(o_orderkey::VARCHAR) AS m, sha256(o_orderpriority) AS s FROM orders")
def fn_hash(t):
    return t.orders.select("o_orderkey", F.md5(F.col("o_orderkey").cast("string")).alias("m"), F.sha2("o_orderpriority", 256).alias("s"))


@query()
def fn_hash_native(t):
    return t.orders.select("o_orderkey", F.xxhash64("o_orderkey").alias("x"), F.hash("o_orderkey").alias("h"), F.crc32("o_orderpriority").alias("c"))


@query("""SELECT o_orderkey, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(quarter(o_orderdate) AS INTEGER) AS q, CAST(month(o_orderdate) AS INTEGER) AS m, CAST(dayofweek(o_orderdate) + 1 AS INTEGER) AS dow,
CAST(CAST(date_trunc('month', o_orderdate) AS DATE) AS VARCHAR) AS mon, CAST(date_diff('day', DATE '1992-01-01', o_orderdate::DATE) AS INTEGER) AS days, CAST(CAST(o_orderdate::DATE + INTERVAL 2 MONTH AS DATE) AS VARCHAR) AS later,
CAST(last_day(o_orderdate::DATE) AS VARCHAR) AS ld, strftime(o_orderdate, '%Y/%m/%d') AS f FROM orders""")
def fn_date(t):
    d = F.to_date("o_orderdate")
    return t.orders.select(
        "o_orderkey", F.year(d).alias("y"), F.quarter(d).alias("q"), F.month(d).alias("m"), F.dayofweek(d).alias("dow"), F.trunc(d, "month").cast("string").alias("mon"),
        F.datediff(d, F.lit("1992-01-01").cast("date")).alias("days"), F.add_months(d, 2).cast("string").alias("later"), F.last_day(d).cast("string").alias("ld"), F.date_format(d, "yyyy/MM/dd").alias("f"),
    )


both("fn_math", """SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, round(l_extendedprice, 1) AS r, floor(l_quantity / 7) AS f, ceil(l_quantity / 7) AS c, round(power(l_discount, 2), 6) AS p, round(sqrt(l_quantity), 6) AS s, round(ln(l_quantity), 6) AS n,
round(exp(l_tax), 6) AS e, greatest(l_discount, l_tax) AS g, least(l_discount, l_tax) AS l, abs(l_discount - l_tax) AS a, sign(l_discount - l_tax) AS sg FROM {lineitem}""",
     """SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, round(l_extendedprice, 1) AS r, CAST(floor(l_quantity / 7) AS DOUBLE) AS f, CAST(ceil(l_quantity / 7) AS DOUBLE) AS c, round(power(l_discount, 2), 6) AS p, round(sqrt(l_quantity), 6) AS s, round(ln(l_quantity), 6) AS n,
round(exp(l_tax), 6) AS e, greatest(l_discount, l_tax) AS g, least(l_discount, l_tax) AS l, abs(l_discount - l_tax) AS a, CAST(sign(l_discount - l_tax) AS INT) AS sg FROM {lineitem}""")  # fmt: skip


@query("SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x)), 4) AS sq, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INTEGER) AS pos, CAST(len(embedding[2:5]) AS INTEGER) AS cut FROM embeddings")
def fn_array(t):
    e = F.col("embedding")
    return t.embeddings.select(
        "vec_id", F.round(F.aggregate(e, F.lit(0.0), lambda a, x: a + x.cast("double") * x), 4).alias("sq"),
        F.size(F.filter(e, lambda x: x > 0)).alias("pos"), F.size(F.slice(e, 2, 4)).alias("cut"),
    )


@query("SELECT doc_id, CAST(len(list_distinct(string_split(text, ' '))) AS INTEGER) AS words, list_contains(string_split(text, ' '), 'the') AS the FROM documents")
def fn_array_words(t):
    words = F.split("text", " ")
    return t.documents.select("doc_id", F.size(F.array_distinct(words)).alias("words"), F.array_contains(words, "the").alias("the"))


@query("SELECT doc_id, CAST(pos AS INTEGER) AS pos, piece FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS piece, unnest(range(len(string_split(text, chr(10))))) AS pos FROM documents)")
def fn_posexplode(t):
    return t.documents.select("doc_id", F.posexplode(F.split("text", "\n")).alias("pos", "piece"))


@query("SELECT event_id, user_id AS u, value AS v, 2 AS n FROM events")
def fn_map(t):
    m = F.map_from_arrays(F.array(F.lit("u"), F.lit("v")), F.array(F.col("user_id").cast("double"), F.col("value")))
    return t.events.withColumn("m", m).select("event_id", F.element_at("m", "u").cast("long").alias("u"), F.element_at("m", "v").alias("v"), F.size(F.map_keys("m")).alias("n"))


@query("SELECT o_custkey, max(o_totalprice) AS price FROM orders GROUP BY 1")
def fn_struct(t):
    s = F.max(F.struct(F.col("o_totalprice").alias("price"), F.col("o_orderkey").alias("id"))).alias("s")
    return t.orders.groupBy("o_custkey").agg(s).select("o_custkey", "s.price")


@query("SELECT event_id, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k FROM events")
def fn_json(t):
    return t.events.select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@query()
def fn_variant(t):
    return t.events.select("event_id", F.try_variant_get(F.parse_json("props"), "$.k", "int").alias("k"))


@query("SELECT a.vec_id AS a, b.vec_id AS b, round(list_dot_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 3) + 0.0 AS dot FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")
def fn_vector(t):
    a = t.embeddings.select(F.col("vec_id").alias("a"), F.col("embedding").alias("x"))
    b = t.embeddings.select((F.col("vec_id") - 1).alias("a"), F.col("vec_id").alias("b"), F.col("embedding").alias("y"))
    dot = F.aggregate(F.zip_with("x", "y", lambda u, v: u.cast("double") * v), F.lit(0.0), lambda s, p: s + p)
    return a.join(b, "a").select("a", "b", (F.round(dot, 3) + 0.0).alias("dot"))


both("fn_conditional", "SELECT l_orderkey, l_linenumber, l_partkey, CASE WHEN l_quantity > 25 THEN 'x' ELSE 'y' END AS i, coalesce(nullif(l_returnflag, 'N'), '-') AS c, CASE WHEN l_discount = 0 THEN NULL ELSE round(l_tax / l_discount, 6) END AS d FROM {lineitem}",
     "SELECT l_orderkey, l_linenumber, l_partkey, if(l_quantity > 25, 'x', 'y') AS i, nvl(nullif(l_returnflag, 'N'), '-') AS c, round(try_divide(l_tax, l_discount), 6) AS d FROM {lineitem}")


@query("SELECT page_id, regexp_extract(html, '<title>([^<]*)</title>', 1) AS title, CAST(length(regexp_replace(html, '<[^>]*>', '', 'g')) AS INTEGER) AS n FROM pages")
def fn_html(t):
    return t.pages.select("page_id", F.regexp_extract("html", "<title>([^<]*)</title>", 1).alias("title"), F.length(F.regexp_replace("html", "<[^>]*>", "")).alias("n"))


both("fn_bitwise", "SELECT o_orderkey, o_orderkey & 255 AS a, o_orderkey | 7 AS o, xor(o_orderkey, o_custkey) AS x, o_orderkey >> 2 AS r, CAST(bit_count(o_orderkey) AS INTEGER) AS c FROM {orders}",
     "SELECT o_orderkey, o_orderkey & 255 AS a, o_orderkey | 7 AS o, o_orderkey ^ o_custkey AS x, shiftright(o_orderkey, 2) AS r, bit_count(o_orderkey) AS c FROM {orders}")


@query("SELECT event_id, CAST(floor(epoch(ts)) AS BIGINT) AS s, CAST(date_diff('hour', TIMESTAMP '2024-01-01', date_trunc('hour', ts)) AS BIGINT) AS h FROM events")
def fn_interval(t):
    s = F.unix_timestamp(F.col("ts").cast("timestamp"))
    return t.events.select("event_id", s.alias("s"), F.floor((s - 1704067200) / 3600).alias("h"))
