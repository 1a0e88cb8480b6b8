"""Queries of the relational operators around the methods, over the given tables, with their SQL."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ertransfer.functions import vectors as V
from ertransfer.operators import blocking as B
from ertransfer.operators.classifiers import fit
from ertransfer.operators.clusters import clusters
from ertransfer.plans import encoding_queries as Q
from ertransfer.plans import sqlbase as S
from ertransfer.plans.tasks import SOURCE, TARGET, all_tokens, dictionary, encodings, sides, similarity, tuples
from ertransfer.sources import files
from ertransfer.streaming import events as E

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(sql=None, name: str | None = None):
    def keep(f):
        QUERIES[name or f.__name__] = f
        if sql:
            SQL[name or f.__name__] = sql
        return f

    return keep


BASE = S.base()


def _table(spark, sf_dir, name):
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


# --- sources and sinks -------------------------------------------------------------------------------------------


@query("SELECT f AS format, count(*) AS n, sum(c_custkey)::BIGINT AS ids, round(sum(c_acctbal), 2) AS balance FROM customer, (VALUES ('csv'), ('json'), ('orc'), ('parquet')) v(f) GROUP BY f")
def formats_round_trip(spark, sf_dir):
    """Customers written and read in each format, the schema given."""
    t, out = _table(spark, sf_dir, "customer"), None
    for kind in ("csv", "json", "orc", "parquet"):
        back = files.read_table(spark, files.write_table(t, files.scratch(spark, kind), kind), t.schema, kind)
        one = back.agg(F.lit(kind).alias("format"), F.count("*").alias("n"), F.sum("c_custkey").alias("ids"), F.round(F.sum("c_acctbal"), 2).alias("balance"))
        out = one if out is None else out.union(one)
    return out


@query(f"{BASE} SELECT token, {S.text('vec')} AS vec FROM dict")
def dictionary_text(spark, sf_dir):
    """The dictionary written as text lines and read back."""
    path = files.write_dictionary_text(dictionary(spark, sf_dir, all_tokens(spark, sf_dir)), files.scratch(spark, "words"))
    return files.read_dictionary_text(spark, path, 64)[0].select("token", V.as_text("vec").alias("vec"))


@query(f"{BASE} SELECT doc AS value, count(*) AS n FROM src GROUP BY doc")
def sentence_dump(spark, sf_dir):
    path = files.dump_sentences(tuples(spark, sf_dir), files.scratch(spark, "sentences"))
    return spark.read.text(path).groupBy("value").agg(F.count("*").alias("n"))


@query(f"{BASE} SELECT dataset, id, {S.text('x')} AS x FROM encl")
def bucketed_vectors(spark, sf_dir):
    """Tuple vectors through a table bucketed by id."""
    left, _ = encodings(spark, sf_dir)
    return files.save_bucketed(left, buckets=8).select("dataset", "id", V.as_text("x").alias("x"))


@query()
def model_round_trip(spark, sf_dir):
    """Pairs scored by a logistic regression that was saved and loaded."""
    sim = similarity(spark, sf_dir)
    made = fit("lr", sim.where(F.col("dataset") == SOURCE).select("x", "y", F.lit(1.0).alias("w")))
    back = files.load_model("lr", files.save_model(made, files.scratch(spark, "model")))
    return back.score(sim.where(F.col("dataset") == TARGET)).select("id_l", "id_r", F.round("p", 6).alias("p"))


# --- joins -------------------------------------------------------------------------------------------------------


@query(f"{BASE} SELECT a.id AS id_l, b.id AS id_r, (a.id = b.id)::INT AS y FROM nl a JOIN nr b ON a.dataset = b.dataset WHERE a.dataset = 'supplier' AND a.id <= b.id")
def block_exhaustive(spark, sf_dir):
    """All pairs of the smallest task, each of equal ids or the smaller one first; their number grows with the square of the table."""
    left, right = (t.where("dataset = 'supplier'") for t in sides(spark, sf_dir))
    return B.exhaustive(left, right).where("id_l <= id_r").select("id_l", "id_r", "y")


@query("SELECT o_orderkey, o_custkey FROM orders ANTI JOIN (SELECT c_custkey FROM customer WHERE c_mktsegment = 'MACHINERY') c ON o_custkey = c_custkey")
def join_anti(spark, sf_dir):
    some = _table(spark, sf_dir, "customer").where("c_mktsegment = 'MACHINERY'").select(F.col("c_custkey").alias("o_custkey"))
    return _table(spark, sf_dir, "orders").join(some, "o_custkey", "left_anti").select("o_orderkey", "o_custkey")


@query("SELECT o_orderkey FROM orders SEMI JOIN (SELECT c_custkey FROM customer WHERE c_mktsegment = 'MACHINERY') c ON o_custkey = c_custkey")
def join_semi(spark, sf_dir):
    some = _table(spark, sf_dir, "customer").where("c_mktsegment = 'MACHINERY'").select(F.col("c_custkey").alias("o_custkey"))
    return _table(spark, sf_dir, "orders").join(some, "o_custkey", "left_semi").select("o_orderkey")


@query("SELECT coalesce(c.nation, s.nation) AS nation, c.n AS customers, s.n AS suppliers FROM (SELECT c_nationkey AS nation, count(*) AS n FROM customer WHERE c_custkey % 3 = 0 GROUP BY 1) c FULL JOIN (SELECT s_nationkey AS nation, count(*) AS n FROM supplier GROUP BY 1) s ON c.nation = s.nation")
def join_full(spark, sf_dir):
    c = _table(spark, sf_dir, "customer").where("c_custkey % 3 = 0").groupBy(F.col("c_nationkey").alias("nation")).agg(F.count("*").alias("customers"))
    s = _table(spark, sf_dir, "supplier").groupBy(F.col("s_nationkey").alias("nation")).agg(F.count("*").alias("suppliers"))
    return c.join(s, "nation", "full")


@query("SELECT s_suppkey, c_custkey FROM supplier JOIN customer ON c_nationkey = s_nationkey AND abs(c_acctbal - s_acctbal) <= 100")
def join_band(spark, sf_dir):
    """Suppliers and customers of a nation whose balances lie within 100: an equi-join on the band and its neighbours."""
    s = _table(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey", "s_acctbal", F.explode(F.transform(F.array(F.lit(-1), F.lit(0), F.lit(1)), lambda k: F.floor(F.col("s_acctbal") / 100) + k)).alias("band"))
    c = _table(spark, sf_dir, "customer").select("c_custkey", F.col("c_nationkey").alias("s_nationkey"), "c_acctbal", F.floor(F.col("c_acctbal") / 100).alias("band"))
    return s.join(c, ["s_nationkey", "band"]).where("abs(c_acctbal - s_acctbal) <= 100").select("s_suppkey", "c_custkey")


@query("SELECT e.event_id, p.event_id AS purchase_id FROM events e ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'purchase' GROUP BY user_id, ts) p ON e.user_id = p.user_id AND e.ts >= p.ts WHERE e.event_type = 'error'")
def join_asof(spark, sf_dir):
    """For each error the user's latest purchase up to then: one ordered pass a user, no range join."""
    t = _table(spark, sf_dir, "events").where("event_type in ('error', 'purchase')")
    bought = F.when(F.col("event_type") == "purchase", F.col("event_id"))
    order = Window.partitionBy("user_id").orderBy("ts", F.col("event_type") == "error", "event_id")
    last = t.withColumn("purchase_id", F.last(bought, ignorenulls=True).over(order.rowsBetween(Window.unboundedPreceding, 0)))
    return last.where("event_type = 'error'").select("event_id", "purchase_id")


@query("SELECT a.event_id AS first_id, b.event_id AS second_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE WHERE a.event_type = 'error' AND b.event_type = 'purchase'")
def join_interval(spark, sf_dir):
    """Purchases within ten minutes after an error of the same user: an equi-join on user and time slot."""
    t = _table(spark, sf_dir, "events")
    slot = F.floor(F.unix_timestamp("ts") / 600)
    a = t.where("event_type = 'error'").select("user_id", F.col("event_id").alias("first_id"), F.col("ts").alias("ta"), F.explode(F.array(slot, slot + 1)).alias("slot"))
    b = t.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("second_id"), F.col("ts").alias("tb"), slot.alias("slot"))
    return a.join(b, ["user_id", "slot"]).where("tb > ta and tb <= ta + interval 10 minutes").select("first_id", "second_id")


@query(f"{Q._GRAMS}, e AS (SELECT id_l, id_r FROM gold WHERE j >= 0.5), b AS (SELECT id_l, id_r FROM e UNION SELECT id_r, id_l FROM e), reach AS (SELECT id_l AS id, id_r AS other FROM b UNION SELECT reach.id, b.id_r FROM reach JOIN b ON reach.other = b.id_l) SELECT id, least(id, min(other)) AS cluster FROM reach GROUP BY id".replace("WITH w AS", "WITH RECURSIVE w AS"))
def match_clusters(spark, sf_dir):
    """Clusters of documents that copies connect."""
    pairs = B.same_language_copies(_table(spark, sf_dir, "documents")).where("y = 1")
    return clusters(pairs)


# --- aggregates, windows, sets -----------------------------------------------------------------------------------


@query("SELECT count(*) AS orders, (abs(count(DISTINCT o_custkey) - 0) >= 0) AS near FROM orders")
def approx_distinct(spark, sf_dir):
    """Whether the sketched number of customers lies within five percent of the exact one."""
    t = _table(spark, sf_dir, "orders").agg(F.count("*").alias("orders"), F.countDistinct("o_custkey").alias("d"), F.approx_count_distinct("o_custkey", 0.02).alias("a"))
    return t.select("orders", (F.abs(F.col("a") - F.col("d")) <= 0.05 * F.col("d") + 1).alias("near"))


@query("SELECT o_orderstatus, count(*) FILTER (o_orderpriority = '1-URGENT') AS urgent, count(*) FILTER (o_orderpriority = '5-LOW') AS low FROM orders GROUP BY o_orderstatus")
def pivot_counts(spark, sf_dir):
    t = _table(spark, sf_dir, "orders").groupBy("o_orderstatus").pivot("o_orderpriority", ["1-URGENT", "5-LOW"]).agg(F.count(F.lit(1)))
    return t.select("o_orderstatus", F.coalesce("1-URGENT", F.lit(0)).alias("urgent"), F.coalesce("5-LOW", F.lit(0)).alias("low"))


@query("SELECT l_returnflag, round(quantile_cont(l_quantity, 0.5), 4) AS middle, round(quantile_cont(l_extendedprice, 0.9), 4) AS high, round(stddev_samp(l_discount), 6) AS spread FROM lineitem GROUP BY l_returnflag")
def percentiles(spark, sf_dir):
    t = _table(spark, sf_dir, "lineitem").groupBy("l_returnflag")
    return t.agg(F.round(F.percentile("l_quantity", 0.5), 4).alias("middle"), F.round(F.percentile("l_extendedprice", 0.9), 4).alias("high"), F.round(F.stddev_samp("l_discount"), 6).alias("spread"))


@query(f"{BASE} SELECT token, n FROM freq WHERE n >= 100")
def heavy_tokens(spark, sf_dir):
    """Tokens frequent enough to skew a join."""
    return all_tokens(spark, sf_dir).groupBy("token").agg(F.count("*").alias("n")).where("n >= 100")


@query("SELECT o_custkey, o_orderkey, place FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS place FROM orders) WHERE place <= 3")
def top_per_group(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return _table(spark, sf_dir, "orders").withColumn("place", F.row_number().over(w)).where("place <= 3").select("o_custkey", "o_orderkey", F.col("place").cast("long").alias("place"))


@query("SELECT o_orderkey, rank() OVER w AS r, dense_rank() OVER w AS d, ntile(4) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS q, round(percent_rank() OVER w, 6) AS p, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 2) AS last3, lag(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS before, count(*) OVER (PARTITION BY o_custkey ORDER BY epoch(o_orderdate)::BIGINT RANGE BETWEEN 2592000 PRECEDING AND CURRENT ROW) AS month FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate)")
def window_functions(spark, sf_dir):
    t = _table(spark, sf_dir, "orders")
    w, unique = Window.partitionBy("o_custkey").orderBy("o_orderdate"), Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    month = Window.partitionBy("o_custkey").orderBy(F.unix_timestamp("o_orderdate")).rangeBetween(-2592000, 0)
    long = lambda c: c.cast("long")
    return t.select("o_orderkey", long(F.rank().over(w)).alias("r"), long(F.dense_rank().over(w)).alias("d"), long(F.ntile(4).over(unique)).alias("q"), F.round(F.percent_rank().over(w), 6).alias("p"), F.round(F.sum("o_totalprice").over(unique.rowsBetween(-2, 0)), 2).alias("last3"), F.lag("o_orderkey").over(unique).alias("before"), F.count("*").over(month).alias("month"))


@query("SELECT 'union' AS op, count(*) AS n FROM (SELECT c_nationkey FROM customer UNION ALL SELECT s_nationkey FROM supplier) UNION ALL SELECT 'intersect all', count(*) FROM (SELECT c_nationkey FROM customer INTERSECT ALL SELECT s_nationkey FROM supplier) UNION ALL SELECT 'except all', count(*) FROM (SELECT c_nationkey FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier) UNION ALL SELECT 'distinct', count(*) FROM (SELECT DISTINCT c_nationkey FROM customer)")
def set_operations(spark, sf_dir):
    c, s = _table(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("k")), _table(spark, sf_dir, "supplier").select(F.col("s_nationkey").alias("k"))
    tables = {"union": c.unionByName(s), "intersect all": c.intersectAll(s), "except all": c.exceptAll(s), "distinct": c.dropDuplicates()}
    out = None
    for name, t in tables.items():
        one = t.agg(F.lit(name).alias("op"), F.count("*").alias("n"))
        out = one if out is None else out.union(one)
    return out


@query("SELECT event_type, (props->>'$.k')::BIGINT % 10 AS k, count(*) AS n FROM events GROUP BY ALL")
def json_fields(spark, sf_dir):
    k = F.from_json("props", "k BIGINT")["k"]
    return _table(spark, sf_dir, "events").groupBy("event_type", (k % 10).alias("k")).agg(F.count("*").alias("n"))


@query("SELECT year(o_orderdate)::INT AS year, strftime(o_orderdate, '%m') AS month, count(*) AS n, min(date_diff('day', o_orderdate::DATE, DATE '1999-12-31'))::INT AS least_days FROM orders GROUP BY ALL")
def date_functions(spark, sf_dir):
    d = F.col("o_orderdate")
    return _table(spark, sf_dir, "orders").groupBy(F.year(d).alias("year"), F.date_format(d, "MM").alias("month")).agg(F.count("*").alias("n"), F.min(F.datediff(F.lit("1999-12-31").cast("date"), d)).alias("least_days"))


@query(f"{BASE} SELECT id_l, id_r, list_sum(x)::BIGINT AS l1, {S.text(S.phi_s('x', 64))} AS z FROM sim WHERE dataset = 'supplier'")
def sql_functions(spark, sf_dir):
    """Vector functions called from SQL text."""
    V.register(spark)
    similarity(spark, sf_dir).where("dataset = 'supplier'").createOrReplaceTempView("ertransfer_sim")
    return spark.sql("SELECT id_l, id_r, vec_l1(x, array_repeat(0L, size(x))) AS l1, array_join(transform(phi_s(x), v -> cast(v as string)), ',') AS z FROM ertransfer_sim")


@query("SELECT page_id, length(regexp_replace(regexp_replace(html, '<[^>]*>', ' ', 'g'), '\\s+', ' ', 'g')) AS n FROM pages")
def html_text(spark, sf_dir):
    """Length of the pages' text without tags, runs of space as one."""
    text = F.regexp_replace(F.regexp_replace("html", r"<[^>]*>", " "), r"\s+", " ")
    return _table(spark, sf_dir, "pages").select("page_id", F.length(text).cast("long").alias("n"))


# --- streams -----------------------------------------------------------------------------------------------------

_BUCKET = "time_bucket(INTERVAL 10 MINUTE, ts)"


@query(f"SELECT start, event_type, count(*) AS n FROM (SELECT {_BUCKET}::TIMESTAMP AS start, event_type FROM events) WHERE start + INTERVAL 10 MINUTE <= (SELECT max(ts) - INTERVAL 10 MINUTE FROM events) GROUP BY start, event_type")
def stream_tumbling(spark, sf_dir):
    """Counts of closed ten-minute windows, read as a stream."""
    return E.run_to_table(E.tumbling_counts(E.read_events(spark, sf_dir)), "tumbling")


@query("SELECT count(DISTINCT (user_id, event_type, props, ts)) AS n FROM events")
def stream_without_copies(spark, sf_dir):
    """Events without repeats of one instant, read as a stream."""
    got = E.run_to_table(E.without_copies(E.read_events(spark, sf_dir)), "copies")
    return got.agg(F.count("*").alias("n"))


@query("SELECT a.event_id AS first_id, b.event_id AS second_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE WHERE a.event_type = 'error' AND b.event_type = 'purchase'")
def stream_interval_join(spark, sf_dir):
    return E.run_to_table(E.error_then_purchase(E.read_events(spark, sf_dir)), "interval")


@query("SELECT event_type AS token, count(*) AS n FROM events GROUP BY event_type")
def stream_vocabulary(spark, sf_dir):
    """Running counts kept in state, the last of each token."""
    got = E.run_to_table(E.running_counts(E.read_events(spark, sf_dir)), "vocabulary", "update")
    return got.groupBy("token").agg(F.max("n").alias("n"))


@query()
def stream_scoring(spark, sf_dir):
    """New pairs scored by a frozen classifier, batch by batch."""
    return E.score_stream(spark, similarity(spark, sf_dir), SOURCE, TARGET)


@query()
def stream_drift(spark, sf_dir):
    """MCC and d_A of each arriving batch of pairs against reference pairs."""
    return E.drift_stream(spark, similarity(spark, sf_dir), SOURCE, TARGET)
