"""Relational operators around the methods: scans, sinks, projections, joins, aggregations, windows, sorts, set operations."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from exkit.book import Book, Tables
from exkit.operators.randomize import numbered
from exkit.plans.partitioning import by_hash, equal_width, portable_hash
from exkit.sources import records
from exkit.staging import new_path, stage

BOOK = Book()
query, both = BOOK.query, BOOK.both

def count():
    return F.count(F.lit(1)).alias("n")


def dec(c: str):
    return F.col(c).cast("decimal(18,2)")


def total(c: str, name: str):
    return F.sum(dec(c)).cast("double").alias(name)


# ---------------------------------------------------------------- scans, sources, sinks


@query("SELECT l_orderkey, l_quantity FROM lineitem")
def scan_parquet(t):
    return t.lineitem.select("l_orderkey", "l_quantity")


@query("SELECT o_orderkey, o_totalprice FROM orders WHERE o_orderdate >= TIMESTAMP '1996-01-01' AND o_orderdate < TIMESTAMP '1997-01-01'")
def scan_pushdown(t):
    day = lambda d: F.lit(d).cast("timestamp_ntz")
    return t.orders.where((F.col("o_orderdate") >= day("1996-01-01")) & (F.col("o_orderdate") < day("1997-01-01"))).select("o_orderkey", "o_totalprice")


@query("SELECT vec_id, CAST(len(embedding) AS INTEGER) AS dims, CAST(embedding[1] AS DOUBLE) AS first FROM embeddings")
def scan_nested(t):
    return t.embeddings.select("vec_id", F.size("embedding").alias("dims"), F.element_at("embedding", 1).cast("double").alias("first"))


def _roundtrip(df: DataFrame, fmt: str, **options) -> DataFrame:
    path = new_path(df.sparkSession, fmt)
    df.write.format(fmt).options(**options).save(path)
    return df.sparkSession.read.format(fmt).schema(df.schema).options(**options).load(path)


for _fmt in ("csv", "json", "orc", "parquet"):
    BOOK.add(f"scan_roundtrip_{_fmt}", lambda t, f=_fmt: _roundtrip(t.nation, f, **({"header": "true"} if f == "csv" else {})), "SELECT * FROM nation")


@query("SELECT event_type || '|' || user_id::VARCHAR AS value FROM events")
def scan_roundtrip_text(t):
    return _roundtrip(t.events.select(F.concat_ws("|", "event_type", F.col("user_id").cast("string")).alias("value")), "text")


@query("SELECT l_orderkey, l_linestatus, l_returnflag FROM lineitem WHERE l_returnflag = 'R'")
def sink_partitioned(t):
    path = new_path(t.spark, "partitioned")
    t.lineitem.select("l_orderkey", "l_linestatus", "l_returnflag").write.partitionBy("l_returnflag").parquet(path)
    return t.spark.read.parquet(path).where("l_returnflag = 'R'").select("l_orderkey", "l_linestatus", "l_returnflag")


@query("SELECT o_orderpriority, count(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def sink_bucketed(t):
    """Two tables bucketed alike join without an exchange of either."""
    tag = uuid.uuid4().hex[:12]
    names = {}
    for name, key, cols in (("orders", "o_orderkey", ["o_orderkey", "o_orderpriority"]), ("lineitem", "l_orderkey", ["l_orderkey"])):
        names[name] = f"exkit_{name}_{tag}"
        getattr(t, name).select(*cols).write.bucketBy(8, key).sortBy(key).option("path", new_path(t.spark, name)).saveAsTable(names[name])
    o, li = t.spark.table(names["orders"]), t.spark.table(names["lineitem"])
    return o.join(li.hint("merge"), o.o_orderkey == li.l_orderkey).groupBy("o_orderpriority").agg(count())


@query()
def source_records(t):
    t.spark.dataSource.register(records.RecordSource)
    return t.spark.read.format("exkit_records").option("rows", 500).option("parts", 4).load()


@query("SELECT upper(substr(md5(o_orderkey::VARCHAR), 1, 20)) AS key, o_orderkey, o_custkey, 100 AS n_bytes FROM orders")
def source_binary_records(t):
    """Orders as 100-byte records (key of 10, payload of 90), written as one binary column and cut again; a null is blank in the payload."""
    blank = lambda c, k: F.lpad(F.coalesce(F.col(c).cast("string"), F.lit("")), k, " ")
    key = F.coalesce(F.unhex(records.hex_key(F.col("o_orderkey"))), F.unhex(F.lit("00" * records.KEY_BYTES)))
    payload = F.encode(F.concat(blank("o_orderkey", 20), blank("o_custkey", 20), F.lit(" " * 50)), "UTF-8")
    packed = stage(t.orders.select(F.concat(key, payload).alias("record")), "records")
    field = lambda at: F.nullif(F.trim(F.decode(F.substring("record", at, 20), "UTF-8")), F.lit("")).cast("long")
    key = F.when(field(11).isNotNull(), F.hex(F.substring("record", 1, records.KEY_BYTES)))
    return packed.select(key.alias("key"), field(11).alias("o_orderkey"), field(31).alias("o_custkey"), F.length("record").alias("n_bytes"))


@query("SELECT r_name, r_regionkey FROM region")
def source_values(t):
    rows = [(r["r_name"], r["r_regionkey"]) for r in t.region.collect()]  # five rows
    return t.spark.createDataFrame(rows, "r_name string, r_regionkey int")


# ---------------------------------------------------------------- projection, filter, predicates

both("project_arith", """SELECT l_orderkey, l_linenumber, CAST(CAST(l_extendedprice AS DECIMAL(18,2)) * CAST(1 - l_discount AS DECIMAL(6,2)) AS DOUBLE) AS revenue FROM {lineitem}""")


@query("SELECT o_totalprice AS price, o_orderkey AS id, o_custkey FROM orders")
def project_rename_drop(t):
    return t.orders.withColumnsRenamed({"o_orderkey": "id", "o_totalprice": "price"}).drop("o_orderstatus", "o_orderdate", "o_orderpriority").select("price", "id", "o_custkey")


@query("SELECT l_orderkey, l_linenumber FROM lineitem WHERE (l_quantity BETWEEN 10 AND 20 AND l_returnflag IN ('R', 'A')) OR NOT (l_discount < 0.09)")
def filter_compound(t):
    c = F.col
    return t.lineitem.where((c("l_quantity").between(10, 20) & c("l_returnflag").isin("R", "A")) | ~(c("l_discount") < 0.09)).select("l_orderkey", "l_linenumber")


@query("SELECT doc_id FROM documents WHERE text LIKE '%tion%' AND (regexp_matches(text, '[0-9]{3}') OR starts_with(lang, 'e')) AND NOT contains(text, '%%%')")
def filter_like(t):
    x = F.col("text")
    return t.documents.where(x.like("%tion%") & (x.rlike("[0-9]{3}") | F.col("lang").startswith("e")) & ~x.contains("%%%")).select("doc_id")


NULLS = "customer LEFT JOIN (SELECT * FROM orders WHERE o_totalprice > 200000) o ON c_custkey = o_custkey"


def _outer(t: Tables) -> DataFrame:
    big = t.orders.where("o_totalprice > 200000")
    return t.customer.join(big, F.col("c_custkey") == F.col("o_custkey"), "left")


@query(f"SELECT c_custkey, o_orderkey IS NULL AS missing, coalesce(o_orderkey, -1) AS o, nullif(c_nationkey, 3) AS nn, o_custkey IS NOT DISTINCT FROM c_custkey AS same FROM {NULLS}")
def filter_null(t):
    c = F.col
    return _outer(t).select("c_custkey", c("o_orderkey").isNull().alias("missing"), F.coalesce("o_orderkey", F.lit(-1)).alias("o"), F.nullif(c("c_nationkey"), F.lit(3)).alias("nn"), c("o_custkey").eqNullSafe(c("c_custkey")).alias("same"))


both("case_when", "SELECT o_orderkey, CASE WHEN o_totalprice > 300000 THEN 'high' WHEN o_totalprice > 100000 THEN 'mid' ELSE 'low' END AS band FROM {orders}")
both("cast_types", "SELECT event_id, CAST(event_id AS VARCHAR(20)) AS s, CAST(user_id AS DOUBLE) AS d, try_cast(event_type AS INT) AS bad, CAST(value AS DECIMAL(10,1)) > 5 AS big FROM {events}", "SELECT event_id, CAST(event_id AS STRING) AS s, CAST(user_id AS DOUBLE) AS d, try_cast(event_type AS INT) AS bad, CAST(value AS DECIMAL(10,1)) > 5 AS big FROM {events}")
both("filter_subquery_in", "SELECT p_partkey FROM {part} WHERE p_partkey IN (SELECT l_partkey FROM {lineitem} WHERE l_quantity > 49)")
both("filter_not_in", "SELECT p_partkey FROM {part} WHERE p_partkey NOT IN (SELECT l_partkey FROM {lineitem} WHERE l_quantity > 40)")


@query("SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)")
def filter_exists(t):
    big = t.orders.where((F.col("o_custkey") == F.col("c_custkey").outer()) & (F.col("o_totalprice") > 300000))
    return t.customer.where(big.exists()).select("c_custkey")


@query("SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT 1.5 * quantile_cont(o_totalprice, 0.5) FROM orders)")
def filter_scalar_subquery(t):
    limit = t.orders.select((F.percentile("o_totalprice", F.lit(0.5)) * 1.5).alias("x")).scalar()
    return t.orders.where(F.col("o_totalprice") > limit).select("o_orderkey")


both("distinct_rows", "SELECT DISTINCT l_returnflag, l_linestatus FROM {lineitem}")


@query("SELECT doc_id, lang FROM (SELECT *, row_number() OVER (PARTITION BY text ORDER BY doc_id) AS k FROM documents) WHERE k = 1")
def drop_duplicates_keys(t):
    k = F.row_number().over(W.partitionBy(F.xxhash64("text"), "text").orderBy("doc_id"))
    return t.documents.withColumn("k", k).where("k = 1").select("doc_id", "lang")


PORTABLE = "('0x' || substr(md5({0}::VARCHAR), 1, 8))::BIGINT"


@query(f"SELECT event_id FROM events WHERE {PORTABLE.format('event_id')} % 100 < 10")
def sample_fraction(t):
    return t.events.where(portable_hash(F.col("event_id")) % 100 < 10).select("event_id")


@query(f"SELECT event_id, event_type FROM events WHERE {PORTABLE.format('event_id')} % 100 < CASE event_type WHEN 'purchase' THEN 50 WHEN 'view' THEN 5 ELSE 10 END")
def sample_stratified(t):
    share = F.when(F.col("event_type") == "purchase", 50).when(F.col("event_type") == "view", 5).otherwise(10)
    return t.events.where(portable_hash(F.col("event_id")) % 100 < share).select("event_id", "event_type")


@query(f"SELECT vec_id, {PORTABLE.format('vec_id')} % 5 = 0 AS held_out FROM embeddings")
def split_random(t):
    return t.embeddings.select("vec_id", (portable_hash(F.col("vec_id")) % 5 == 0).alias("held_out"))


@query("""WITH a AS (SELECT l_returnflag, CAST(count(*) AS DOUBLE) AS n, CAST(sum(CAST(l_quantity AS DECIMAL(18,2))) AS DOUBLE) AS qty FROM lineitem GROUP BY 1)
SELECT l_returnflag, 'n' AS measure, n AS v FROM a UNION ALL SELECT l_returnflag, 'qty', qty FROM a""")
def unpivot_measures(t):
    a = t.lineitem.groupBy("l_returnflag").agg(F.count(F.lit(1)).cast("double").alias("n"), total("l_quantity", "qty"))
    return a.unpivot("l_returnflag", ["n", "qty"], "measure", "v")


@query("""WITH a AS (SELECT l_returnflag AS f, CAST(count(*) AS DOUBLE) AS n, CAST(sum(CAST(l_quantity AS DECIMAL(18,2))) AS DOUBLE) AS qty FROM lineitem GROUP BY 1)
SELECT 'n' AS key, max(n) FILTER (f = 'A') AS "A", max(n) FILTER (f = 'N') AS "N", max(n) FILTER (f = 'R') AS "R" FROM a
UNION ALL SELECT 'qty', max(qty) FILTER (f = 'A'), max(qty) FILTER (f = 'N'), max(qty) FILTER (f = 'R') FROM a""")
def transpose_small(t):
    """Rows become columns; the table is one row a return flag."""
    a = t.lineitem.groupBy("l_returnflag").agg(F.count(F.lit(1)).cast("double").alias("n"), total("l_quantity", "qty"))
    return a.transpose("l_returnflag")


# ---------------------------------------------------------------- joins

SUPPLIED = "SELECT s_nationkey, count(*) AS n FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1"


@query(SUPPLIED)
def join_broadcast_hash(t):
    small = t.supplier.select("s_suppkey", "s_nationkey")
    small = F.broadcast(small) if small.count() <= 100_000 else small
    return t.lineitem.join(small, F.col("l_suppkey") == F.col("s_suppkey")).groupBy("s_nationkey").agg(count())


@query("SELECT o_orderkey, c_mktsegment FROM orders JOIN customer ON o_custkey = c_custkey")
def join_shuffle_hash(t):
    return t.orders.join(t.customer.hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_mktsegment")


@query("SELECT o_orderpriority, count(*) AS n, CAST(sum(CAST(l_quantity AS DECIMAL(18,2))) AS DOUBLE) AS qty FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def join_sort_merge(t):
    """Both sides through one partitioner: rows that meet are in partitions of the same id."""
    left = by_hash(t.orders.select("o_orderkey", "o_orderpriority"), ["o_orderkey"], 8).repartitionById(8, "reduce_id")
    right = by_hash(t.lineitem.select("l_orderkey", "l_quantity"), ["l_orderkey"], 8).withColumnRenamed("reduce_id", "rid").repartitionById(8, "rid")
    on = (F.col("reduce_id") == F.col("rid")) & (F.col("o_orderkey") == F.col("l_orderkey"))
    return left.hint("merge").join(right, on).groupBy("o_orderpriority").agg(count(), total("l_quantity", "qty"))


for _how, _sql in (("left", "LEFT"), ("right", "RIGHT"), ("full", "FULL")):

    def _outer_join(t, how=_how):
        big = t.orders.where("o_totalprice > 200000 OR o_custkey > 1400").select("o_orderkey", "o_custkey")
        return t.customer.where("c_custkey <= 1400").select("c_custkey").join(big, F.col("c_custkey") == F.col("o_custkey"), how)

    BOOK.add(f"join_{_how}", _outer_join, f"SELECT c_custkey, o_orderkey, o_custkey FROM (SELECT c_custkey FROM customer WHERE c_custkey <= 1400) {_sql} JOIN (SELECT o_orderkey, o_custkey FROM orders WHERE o_totalprice > 200000 OR o_custkey > 1400) ON c_custkey = o_custkey")


for _how, _sql in (("left", "LEFT"), ("right", "RIGHT"), ("full", "FULL")):

    def _whole_outer_join(t, how=_how):
        """Both tables over all ids; the price leaves customers unmatched, the segment orders, in proportion at every size."""
        big = t.orders.where("o_totalprice > 400000").select("o_orderkey", "o_custkey")
        return t.customer.where("c_mktsegment <> 'BUILDING'").select("c_custkey").join(big, F.col("c_custkey") == F.col("o_custkey"), how)

    BOOK.add(f"join_{_how}_whole", _whole_outer_join, f"SELECT c_custkey, o_orderkey, o_custkey FROM (SELECT c_custkey FROM customer WHERE c_mktsegment <> 'BUILDING') {_sql} JOIN (SELECT o_orderkey, o_custkey FROM orders WHERE o_totalprice > 400000) ON c_custkey = o_custkey")


@query("SELECT p_partkey FROM part WHERE p_partkey IN (SELECT l_partkey FROM lineitem WHERE l_quantity > 45)")
def join_semi(t):
    return t.part.join(t.lineitem.where("l_quantity > 45"), F.col("p_partkey") == F.col("l_partkey"), "left_semi").select("p_partkey")


@query("SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def join_anti(t):
    return t.customer.join(t.orders, F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


@query("SELECT r_name, n_name FROM region, nation WHERE r_regionkey < n_regionkey")
def join_cross_nested_loop(t):
    """A theta join of two catalogues of fixed size."""
    return t.region.join(F.broadcast(t.nation), F.col("r_regionkey") < F.col("n_regionkey")).select("r_name", "n_name")


BANDS = [(i, 900.0 + 120.0 * i, 900.0 + 120.0 * (i + 1)) for i in range(10)]


@query("SELECT p_partkey, CAST(b AS INTEGER) AS band FROM part JOIN (SELECT i AS b, 900.0 + 120.0 * i AS lo, 900.0 + 120.0 * (i + 1) AS hi FROM range(10) r(i)) ON p_retailprice >= lo AND p_retailprice < hi")
def join_range(t):
    """Range predicate as an equi-join on bins, each band listed in every bin it meets, with the predicate as residue."""
    width = 100.0
    bands = t.spark.createDataFrame(BANDS, "band int, lo double, hi double")
    bands = bands.withColumn("bin", F.explode(F.sequence(F.floor(F.col("lo") / width), F.floor(F.col("hi") / width))))
    parts = t.part.withColumn("bin", F.floor(F.col("p_retailprice") / width))
    return parts.join(F.broadcast(bands), "bin").where("p_retailprice >= lo AND p_retailprice < hi").select("p_partkey", "band")


@query("SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'purchase' AND b.event_type <> 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 2 HOUR")
def join_interval(t):
    """Each purchase meets the hours its interval covers; keys are (user, hour), the interval is the residue."""
    hour = lambda c: F.floor(F.unix_timestamp(F.col(c).cast("timestamp")) / 3600)
    left = t.events.where("event_type = 'purchase'").select(F.col("event_id").alias("a"), "user_id", F.col("ts").alias("ta")).withColumn("h", F.explode(F.sequence(hour("ta"), hour("ta") + 2)))
    right = t.events.where("event_type <> 'purchase'").select(F.col("event_id").alias("b"), "user_id", F.col("ts").alias("tb")).withColumn("h", hour("tb"))
    return left.join(right, ["user_id", "h"]).where("tb > ta AND tb <= ta + INTERVAL 2 HOURS").select("a", "b")


@query("""SELECT a.event_id AS purchase, (SELECT max(b.event_id) FROM events b WHERE b.user_id = a.user_id AND b.event_type = 'view' AND (b.ts < a.ts OR (b.ts = a.ts AND b.event_id < a.event_id))) AS view
FROM events a WHERE a.event_type = 'purchase'""")
def join_asof(t):
    """Latest earlier view of each purchase: one sort by user and time, no join."""
    seen = F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, -1))
    both_ = t.events.where("event_type IN ('purchase', 'view')").withColumn("view", seen)
    return both_.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), "view")


@query("SELECT s_nationkey, count(*) AS n FROM (SELECT CASE WHEN l_quantity > 20 THEN 1 ELSE l_suppkey END AS k FROM lineitem) JOIN supplier ON k = s_suppkey GROUP BY 1")
def join_skewed_aqe(t):
    hot = t.lineitem.select(F.when(F.col("l_quantity") > 20, F.lit(1)).otherwise(F.col("l_suppkey")).alias("k"))
    return hot.join(t.supplier.hint("merge"), F.col("k") == F.col("s_suppkey")).groupBy("s_nationkey").agg(count())


@query("""SELECT r_name, count(*) AS n, CAST(sum(CAST(l_extendedprice AS DECIMAL(18,2))) AS DOUBLE) AS price FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey
JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1""")
def join_multiway_star(t):
    geo = F.broadcast(t.nation.join(t.region, F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "r_name"))
    who = t.customer.join(geo, F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "r_name")
    what = t.orders.select("o_orderkey", "o_custkey").join(who, F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "r_name")
    return t.lineitem.select("l_orderkey", "l_extendedprice").join(what, F.col("l_orderkey") == F.col("o_orderkey")).groupBy("r_name").agg(count(), total("l_extendedprice", "price"))


@query("SELECT c_custkey, o_orderkey FROM (SELECT c_custkey, o_orderkey, row_number() OVER (PARTITION BY c_custkey ORDER BY o_totalprice DESC, o_orderkey) AS k FROM customer JOIN orders ON c_custkey = o_custkey) WHERE k = 1")
def join_lateral(t):
    """Top order of each customer; the lateral form with a limit is decorrelated to a ranked join."""
    top = t.orders.groupBy("o_custkey").agg(F.min_by("o_orderkey", F.struct(-F.col("o_totalprice"), "o_orderkey")).alias("o_orderkey"))
    return t.customer.lateralJoin(top.where(F.col("o_custkey") == F.col("c_custkey").outer()).select("o_orderkey")).select("c_custkey", "o_orderkey")


#: Orders of a cogroup; each of its tables is held whole by a task.
COGROUP_ROWS = 250_000


@query("SELECT o_orderkey, count(l_orderkey) AS n_lines FROM orders LEFT JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def join_cogroup(t):
    """Cogroups are hash buckets of about ``COGROUP_ROWS`` keys; lines are counted per batch first, so a frequent key is short too."""
    import pyarrow as pa
    import pyarrow.compute as pc

    def combine(batches):
        for batch in batches:
            yield from pa.table(batch.column("l_orderkey").value_counts().flatten(), names=["l_orderkey", "n"]).to_batches()

    def meet(a: pa.Table, b: pa.Table) -> pa.Table:
        orders = a.group_by("o_orderkey", use_threads=False).aggregate([([], "count_all")])
        lines = b.group_by("l_orderkey", use_threads=False).aggregate([("n", "sum")])
        met = orders.join(lines, "o_orderkey", "l_orderkey", "left outer", use_threads=False)
        return pa.table({"o_orderkey": met["o_orderkey"], "n_lines": pc.multiply(met["count_all"], pc.fill_null(met["n_sum"], 0))})

    orders, lines = t.orders.select(F.col("o_orderkey").cast("long")), t.lineitem.select(F.col("l_orderkey").cast("long")).where("l_orderkey IS NOT NULL")
    buckets = orders.count() // COGROUP_ROWS + 1
    bucket = lambda key: F.pmod(F.xxhash64(key), F.lit(buckets))
    left = orders.withColumn("bucket", bucket("o_orderkey")).groupBy("bucket")
    right = lines.mapInArrow(combine, "l_orderkey long, n long").withColumn("bucket", bucket("l_orderkey")).groupBy("bucket")
    return left.cogroup(right).applyInArrow(meet, "o_orderkey long, n_lines long")


# ---------------------------------------------------------------- aggregations


@query("""SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(CAST(l_quantity AS DECIMAL(18,2))) AS DOUBLE) AS qty, round(avg(l_discount), 6) AS disc, min(l_tax) AS lo, max(l_tax) AS hi FROM lineitem GROUP BY 1, 2""")
def agg_hash_partial_final(t):
    return t.lineitem.groupBy("l_returnflag", "l_linestatus").agg(count(), total("l_quantity", "qty"), F.round(F.avg("l_discount"), 6).alias("disc"), F.min("l_tax").alias("lo"), F.max("l_tax").alias("hi"))


@query("SELECT l_suppkey, count(*) AS n FROM lineitem GROUP BY 1")
def agg_hash_premerge(t):
    first = t.lineitem.coalesce(4).groupBy((F.col("l_orderkey") % 4).alias("merge_id"), "l_suppkey").agg(count())
    return first.groupBy("l_suppkey").agg(F.sum("n").alias("n"))


both("agg_global", "SELECT count(*) AS n, CAST(sum(CAST(o_totalprice AS DECIMAL(18,2))) AS DOUBLE) AS total, min(o_orderkey) AS lo, max(o_orderkey) AS hi FROM {orders}")


@query("SELECT o_orderpriority, string_agg(o_orderstatus, '' ORDER BY o_orderstatus) AS s FROM (SELECT DISTINCT o_orderpriority, o_orderstatus FROM orders) GROUP BY 1")
def agg_sort_based(t):
    return t.orders.groupBy("o_orderpriority").agg(F.array_join(F.array_sort(F.collect_set("o_orderstatus")), "").alias("s"))


both("agg_distinct", "SELECT l_returnflag, count(DISTINCT l_suppkey) AS s FROM {lineitem} GROUP BY 1")
both("agg_multi_distinct", "SELECT l_returnflag, count(DISTINCT l_suppkey) AS s, count(DISTINCT l_partkey) AS p, count(*) AS n FROM {lineitem} GROUP BY 1")
both("agg_filter_clause", "SELECT l_linestatus, count(*) FILTER (WHERE l_quantity > 25) AS big, count(*) AS n FROM {lineitem} GROUP BY 1")
both("agg_having", "SELECT l_suppkey, count(*) AS n FROM {lineitem} GROUP BY 1 HAVING count(*) > 600")

GEO = "{customer} JOIN {nation} ON c_nationkey = n_nationkey JOIN {region} ON n_regionkey = r_regionkey"
both("agg_rollup", f"SELECT r_name, n_name, count(*) AS n FROM {GEO} GROUP BY ROLLUP (r_name, n_name)")
both("agg_cube", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM {lineitem} GROUP BY CUBE (l_returnflag, l_linestatus)")
both("agg_grouping_sets", "SELECT l_returnflag, l_linestatus, l_linenumber, count(*) AS n FROM {lineitem} GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_linenumber), ())")


@query("SELECT user_id, " + ", ".join(f"count(*) FILTER (WHERE event_type = '{x}') AS {x}" for x in ("click", "purchase", "view")) + " FROM events GROUP BY 1")
def agg_pivot(t):
    return t.events.groupBy("user_id").pivot("event_type", ["click", "purchase", "view"]).count().na.fill(0)


@query("SELECT l_returnflag, round(stddev_samp(l_quantity), 4) AS sd, round(var_pop(l_quantity), 4) AS vp, round(corr(l_quantity, l_extendedprice), 4) AS cr, round(covar_pop(l_quantity, l_discount), 4) AS cv FROM lineitem GROUP BY 1")
def agg_stats(t):
    r = lambda c, n: F.round(c, 4).alias(n)
    return t.lineitem.groupBy("l_returnflag").agg(r(F.stddev_samp("l_quantity"), "sd"), r(F.var_pop("l_quantity"), "vp"), r(F.corr("l_quantity", "l_extendedprice"), "cr"), r(F.covar_pop("l_quantity", "l_discount"), "cv"))


@query("SELECT l_returnflag, round(quantile_cont(l_extendedprice, 0.5), 4) AS p50, round(quantile_cont(l_extendedprice, 0.9), 4) AS p90 FROM lineitem GROUP BY 1")
def agg_percentile(t):
    p = lambda q, n: F.round(F.percentile("l_extendedprice", F.lit(q)), 4).alias(n)
    return t.lineitem.groupBy("l_returnflag").agg(p(0.5, "p50"), p(0.9, "p90"))


@query()
def agg_percentile_approx(t):
    return t.lineitem.groupBy("l_returnflag").agg(F.percentile_approx("l_extendedprice", F.lit(0.5), 1000).alias("p50"))


@query()
def agg_approx_distinct(t):
    return t.events.agg(F.approx_count_distinct("user_id", 0.02).alias("approx"), F.countDistinct("user_id").alias("exact"))


@query()
def agg_hll_merge(t):
    """Sketches per round, merged like any other state."""
    rounds = t.events.groupBy((F.col("event_id") % 8).alias("round")).agg(F.hll_sketch_agg("user_id").alias("s"))
    return rounds.agg(F.hll_sketch_estimate(F.hll_union_agg("s")).alias("users"))


@query()
def agg_theta_merge(t):
    rounds = t.events.groupBy((F.col("event_id") % 8).alias("round")).agg(F.theta_sketch_agg("user_id").alias("s"))
    return rounds.agg(F.theta_sketch_estimate(F.theta_union_agg("s")).alias("users"))


@query()
def agg_cms(t):
    sketch = t.events.agg(F.count_min_sketch("user_id", F.lit(0.01), F.lit(0.95), F.lit(7)).alias("s"))
    return sketch.select(F.length("s").alias("n_bytes"))


@query()
def agg_approx_top_k(t):
    return t.sql("SELECT inline(approx_top_k(CASE WHEN l_quantity > 20 THEN 0 ELSE l_suppkey END, 3)) FROM {lineitem}")


@query("SELECT o_orderpriority, first(o_orderkey ORDER BY o_totalprice DESC, o_orderkey) AS best FROM orders GROUP BY 1")
def agg_argmax(t):
    return t.orders.groupBy("o_orderpriority").agg(F.min_by("o_orderkey", F.struct(-F.col("o_totalprice"), "o_orderkey")).alias("best"))


both("agg_bool", "SELECT bool_and(quality = 1) AS every_good, bool_or(toxic = 1) AS some_toxic FROM {labels}")
both("agg_bits", "SELECT quality, bit_and(doc_id) AS a, bit_or(doc_id) AS o, bit_xor(doc_id) AS x FROM {labels} GROUP BY 1")
both("agg_string", "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM {nation} GROUP BY 1", "SELECT n_regionkey, listagg(n_name, ',') WITHIN GROUP (ORDER BY n_name) AS names FROM {nation} GROUP BY 1")


@query("SELECT user_id, event_type FROM (SELECT user_id, event_type, row_number() OVER (PARTITION BY user_id ORDER BY count(*) DESC, event_type) AS k FROM events GROUP BY 1, 2) WHERE k = 1")
def agg_mode_deterministic(t):
    n = t.events.groupBy("user_id", "event_type").agg(count())
    return n.groupBy("user_id").agg(F.min_by("event_type", F.struct(-F.col("n"), "event_type")).alias("event_type"))


@query("SELECT CAST(floor((p_retailprice - 900) / 150) AS BIGINT) AS bin, count(*) AS n FROM part GROUP BY 1")
def agg_histogram(t):
    return t.part.groupBy(F.floor((F.col("p_retailprice") - 900) / 150).alias("bin")).agg(count())


@query("SELECT event_type, round(count(*) / CAST((SELECT count(*) FROM events) AS DOUBLE), 6) AS share FROM events GROUP BY 1")
def agg_ratio(t):
    n = t.events.groupBy("event_type").agg(count())
    whole = n.agg(F.sum("n").alias("w"))
    return n.join(F.broadcast(whole)).select("event_type", F.round(F.col("n") / F.col("w"), 6).alias("share"))


# ---------------------------------------------------------------- windows

both("win_rank", """SELECT o_orderkey, CAST(row_number() OVER w AS INT) AS rn, CAST(rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS INT) AS rk, CAST(dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS INT) AS dr,
CAST(ntile(3) OVER w AS INT) AS nt, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM {orders} WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey)""")
both("win_lag_lead", "SELECT event_id, lag(event_id, 1, -1) OVER w AS prev, lead(event_id, 2) OVER w AS nxt FROM {events} WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)", "SELECT event_id, lag(event_id, 1, -1L) OVER w AS prev, lead(event_id, 2) OVER w AS nxt FROM {events} WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
both("win_first_last_nth", """SELECT event_id, first_value(event_type) OVER w AS f, last_value(event_type) OVER w AS l, nth_value(event_type, 2) OVER w AS s FROM {events}
WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)""")
both("win_running_sum", "SELECT o_orderkey, CAST(sum(CAST(o_totalprice AS DECIMAL(18,2))) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS DOUBLE) AS run FROM {orders}")


@query("SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY date_diff('day', DATE '1992-01-01', o_orderdate::DATE) RANGE BETWEEN 90 PRECEDING AND CURRENT ROW) AS n FROM orders")
def win_range_frame(t):
    day = F.datediff(F.to_date("o_orderdate"), F.lit("1992-01-01").cast("date"))
    return t.orders.withColumn("d", day).select("o_orderkey", F.count(F.lit(1)).over(W.partitionBy("o_custkey").orderBy("d").rangeBetween(-90, 0)).alias("n"))


both("win_moving_avg", "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING), 4) AS ma FROM {events}")
both("win_whole_partition_share", "SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, round(l_quantity / sum(l_quantity) OVER (PARTITION BY l_orderkey), 6) AS share FROM {lineitem}")


@query("""SELECT user_id, session, count(*) AS n FROM (SELECT user_id, CAST(sum(CASE WHEN prev IS NULL OR ts > prev + INTERVAL 6 HOUR THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS BIGINT) AS session
FROM (SELECT *, lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS prev FROM events)) GROUP BY 1, 2""")
def win_sessionize(t):
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    gap = t.events.withColumn("prev", F.lag("ts").over(w)).withColumn("new", F.when(F.col("prev").isNull() | F.expr("ts > prev + INTERVAL 6 HOURS"), 1).otherwise(0))
    return gap.withColumn("session", F.sum("new").over(w.rowsBetween(W.unboundedPreceding, 0))).groupBy("user_id", "session").agg(count())


TOPK = "SELECT l_suppkey, l_orderkey, l_extendedprice FROM (SELECT *, row_number() OVER (PARTITION BY l_suppkey ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber, l_partkey) AS k FROM lineitem) WHERE k <= 3"


def _topk(t):
    k = F.row_number().over(W.partitionBy("l_suppkey").orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_linenumber", "l_partkey"))
    return t.lineitem.withColumn("k", k).where("k <= 3").select("l_suppkey", "l_orderkey", "l_extendedprice")


BOOK.add("win_topk_per_group", _topk, TOPK)
BOOK.add("topk_per_group", _topk, TOPK)


@query("SELECT user_id, event_id FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY ts DESC, event_id DESC) AS k FROM events) WHERE k = 1")
def win_dedupe_latest(t):
    return t.events.groupBy("user_id").agg(F.max_by("event_id", F.struct("ts", "event_id")).alias("event_id"))


@query("SELECT o_orderkey, row_number() OVER (ORDER BY md5(o_orderkey::VARCHAR), o_orderkey) - 1 AS ordinal FROM orders")
def win_global_rownum(t):
    key = t.orders.select("o_orderkey", F.md5(F.col("o_orderkey").cast("string")).alias("k"))
    return numbered(key.withColumn("b", equal_width(F.col("k"), 64)), ["k", "o_orderkey"], "b", "ordinal").select("o_orderkey", "ordinal")


# ---------------------------------------------------------------- sorts, limits


@query("SELECT o_orderkey, row_number() OVER (ORDER BY md5(o_orderkey::VARCHAR), o_orderkey) AS rk FROM orders")
def sort_global(t):
    """Total order: ranges of the key, sorted inside; the rank is carried as a column."""
    key = t.orders.select("o_orderkey", F.md5(F.col("o_orderkey").cast("string")).alias("k"))
    return numbered(key.withColumn("b", equal_width(F.col("k"), 8)), ["k", "o_orderkey"], "b", "i").select("o_orderkey", (F.col("i") + 1).alias("rk"))


@query("SELECT o_orderkey, o_totalprice FROM orders")
def sort_within_partitions(t):
    return t.orders.select("o_orderkey", "o_totalprice").repartition(4, "o_orderkey").sortWithinPartitions("o_totalprice")


@query(f"SELECT c_custkey, o_orderkey, CAST(row_number() OVER (PARTITION BY c_nationkey ORDER BY o_orderkey NULLS LAST, c_custkey) AS INTEGER) AS last_rk, CAST(row_number() OVER (PARTITION BY c_nationkey ORDER BY o_orderkey NULLS FIRST, c_custkey) AS INTEGER) AS first_rk FROM {NULLS}")
def sort_nulls_first_last(t):
    w = lambda o: F.row_number().over(W.partitionBy("c_nationkey").orderBy(o, "c_custkey"))
    o = F.col("o_orderkey")
    return _outer(t).select("c_custkey", "o_orderkey", w(o.asc_nulls_last()).alias("last_rk"), w(o.asc_nulls_first()).alias("first_rk"))


both("sort_multi_direction", "SELECT o_orderkey, CAST(row_number() OVER (PARTITION BY o_orderstatus ORDER BY o_orderpriority DESC, o_totalprice ASC, o_orderkey DESC) AS INT) AS rk FROM {orders}")


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")
def topk_global(t):
    return t.orders.select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10)


@query("SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 10 OFFSET 20")
def limit_offset(t):
    return t.orders.select("o_orderkey").orderBy("o_orderkey").offset(20).limit(10)


@query("SELECT quantile_disc(l_extendedprice, 0.25) AS b1, quantile_disc(l_extendedprice, 0.5) AS b2, quantile_disc(l_extendedprice, 0.75) AS b3 FROM lineitem")
def quantile_bounds(t):
    return t.sql("SELECT " + ", ".join(f"percentile_disc({q}) WITHIN GROUP (ORDER BY l_extendedprice) AS b{i}" for i, q in enumerate((0.25, 0.5, 0.75), 1)) + " FROM {lineitem}")


@query("SELECT CAST(h * 4 // 4294967296 AS INTEGER) AS reduce_id, row_number() OVER (PARTITION BY h * 4 // 4294967296 ORDER BY k) AS pos, k FROM (SELECT md5(o_orderkey::VARCHAR) AS k, ('0x' || substr(md5(o_orderkey::VARCHAR), 1, 8))::BIGINT AS h FROM orders)")
def merge_sorted_runs(t):
    """Sorted runs of rounds meet at their reducer; its sort finds the runs already in order."""
    key = t.orders.select(F.md5(F.col("o_orderkey").cast("string")).alias("k")).withColumn("reduce_id", equal_width(F.col("k"), 4))
    runs = key.repartition(3, "k").sortWithinPartitions("reduce_id", "k")
    merged = runs.repartitionById(4, "reduce_id").sortWithinPartitions("reduce_id", "k")
    return merged.select("reduce_id", F.row_number().over(W.partitionBy("reduce_id").orderBy("k")).cast("long").alias("pos"), "k")


# ---------------------------------------------------------------- set operations

both("union_all", "SELECT c_nationkey AS k FROM {customer} UNION ALL SELECT s_nationkey FROM {supplier}")
both("union_distinct", "SELECT c_nationkey AS k FROM {customer} UNION SELECT s_nationkey FROM {supplier}")


@query("SELECT c_nationkey AS k, c_name AS name, NULL::DOUBLE AS bal FROM customer UNION ALL SELECT s_nationkey, NULL, s_acctbal FROM supplier")
def union_by_name(t):
    a = t.customer.select(F.col("c_nationkey").alias("k"), F.col("c_name").alias("name"))
    return a.unionByName(t.supplier.select(F.col("s_acctbal").alias("bal"), F.col("s_nationkey").alias("k")), allowMissingColumns=True)


both("intersect", "SELECT l_partkey FROM {lineitem} WHERE l_quantity > 45 INTERSECT SELECT l_partkey FROM {lineitem} WHERE l_quantity < 5")
both("intersect_all", "SELECT l_suppkey FROM {lineitem} WHERE l_quantity > 49 INTERSECT ALL SELECT l_suppkey FROM {lineitem} WHERE l_quantity < 2")
both("except_distinct", "SELECT p_partkey FROM {part} EXCEPT SELECT l_partkey FROM {lineitem} WHERE l_quantity > 40")
both("except_all", "SELECT l_suppkey FROM {lineitem} WHERE l_quantity > 25 EXCEPT ALL SELECT l_suppkey FROM {lineitem} WHERE l_quantity <= 24")

# ---------------------------------------------------------------- SQL surface


@query("WITH RECURSIVE r(n, s) AS (SELECT 1, 1 UNION ALL SELECT n + 1, s + n + 1 FROM r WHERE n < 20) SELECT n, s FROM r")
def sql_recursive_cte(t):
    return t.spark.sql("WITH RECURSIVE r(n, s) AS (SELECT 1, 1 UNION ALL SELECT n + 1, s + n + 1 FROM r WHERE n < 20) SELECT n, s FROM r")


@query("SELECT r_name, unnest(string_split(r_name, 'A')) AS piece FROM region")
def sql_lateral_view(t):
    return t.sql("SELECT r_name, piece FROM {region} LATERAL VIEW explode(split(r_name, 'A')) x AS piece")


@query("SELECT o_orderstatus, count(*) AS n FROM orders WHERE o_totalprice > 1000 GROUP BY 1")
def sql_pipe(t):
    return t.sql("FROM {orders} |> WHERE o_totalprice > 1000 |> AGGREGATE count(*) AS n GROUP BY o_orderstatus")
