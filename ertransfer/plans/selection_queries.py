"""Queries of relatedness, source choice, budgeted estimation and measures, with their SQL."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ertransfer.functions.portable import pair_key
from ertransfer.operators import estimate as G
from ertransfer.operators import measures as M
from ertransfer.operators import relatedness as R
from ertransfer.operators import transfer as T
from ertransfer.operators.classifiers import fit
from ertransfer.plans import sqlbase as S
from ertransfer.plans.tasks import SECOND, SOURCE, TARGET, WIDTH, roles, similarity

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
CANDIDATES = (SOURCE, SECOND, "customer")


def _keyed(spark, sf_dir, name):
    return similarity(spark, sf_dir).where(F.col("dataset") == name).select(pair_key().alias("key"), "x", "y")


def _runs_sql(a: str, b: str, runs: int, tag: str, most: int | None = None) -> tuple[str, str]:
    """(expressions, selection of run, tp, tn, fp, fn) of repeated origin classifiers between tables a and b (key, x)."""
    parts, picks = [], []
    for run in range(runs):
        draw = f"{S.h32(chr(39) + f'rel{run}:' + chr(39) + ' || key')} % 100"
        rows = f"(SELECT key, x, 1 AS o FROM {a} UNION ALL SELECT key, x, 0 FROM {b})"
        parts.append(S.bayes(f"SELECT x AS z, o AS y, 1.0 AS w FROM {rows} WHERE {draw} < 80", f"SELECT key, o AS truth, x AS z FROM {rows} WHERE {draw} >= 80", f"_{tag}{run}"))
        picks.append(f"SELECT {run} AS run, * FROM ({S.confusion(f'scored_{tag}{run}')})")
    return ", ".join(parts), " UNION ALL ".join(picks)


_SRC = f"sa AS (SELECT key, x FROM cut WHERE dataset = '{SOURCE}'), tb AS (SELECT key, x FROM cut WHERE dataset = '{TARGET}')"
_P10, _S10 = _runs_sql("sa", "tb", 10, "r")


@query(f"{BASE}, {_SRC}, {_P10} SELECT run, tp, tn, fp, fn, {S.MCC} FROM ({_S10})")
def origin_runs(spark, sf_dir):
    """Ten origin classifiers between source and target, judged on held-out pairs."""
    got = R.origin_runs(_keyed(spark, sf_dir, SOURCE), _keyed(spark, sf_dir, TARGET))
    return got.withColumns({"mcc": F.round("mcc", 6), "d_a": F.round("d_a", 6)})


@query(f"{BASE}, {_SRC}, {_P10} SELECT round(avg(mcc), 5) AS mean_mcc, round(stddev_samp(mcc), 5) AS spread, round(avg(d_a), 5) AS mean_d_a, avg(mcc) <= 0.2 AS related, CASE WHEN avg(mcc) > 0.2 THEN 'refuse' ELSE 'reuse' END AS verdict FROM (SELECT {S.MCC} FROM ({_S10}))")
def relatedness(spark, sf_dir):
    got = R.relatedness(R.origin_runs(_keyed(spark, sf_dir, SOURCE), _keyed(spark, sf_dir, TARGET)))
    return got.withColumn("verdict", T.should_transfer(F.col("mean_mcc"))).withColumns({c: F.round(c, 5) for c in ("mean_mcc", "spread", "mean_d_a")})


def _rank_sql(by: str) -> str:
    parts, picks = [], []
    for k, name in enumerate(CANDIDATES):
        size = f"least((SELECT count(*) FROM cut WHERE dataset = '{TARGET}'), (SELECT count(*) FROM cut WHERE dataset = '{name}'))"
        cutter = lambda d: f"SELECT key, x FROM (SELECT key, x, row_number() OVER (ORDER BY {S.h32(chr(39) + 'size:' + chr(39) + ' || key')}, key) AS place FROM cut WHERE dataset = '{d}') WHERE place <= {size}"
        p, s = _runs_sql(f"a{k}", f"b{k}", 3, f"k{k}_")
        parts.append(f"a{k} AS ({cutter(name)}), b{k} AS ({cutter(TARGET)}), {p}")
        picks.append(f"SELECT '{name}' AS source, avg(2 * ((tp + tn)::DOUBLE / (tp + fp + fn + tn) - 0.5)) AS d_a, avg(coalesce((tp::DOUBLE * tn - fp::DOUBLE * fn) / nullif(sqrt((tp + fp)::DOUBLE * (tp + fn) * (tn + fp) * (tn + fn)), 0), 0)) AS mcc FROM ({s})")
    return f"{BASE}, {', '.join(parts)} SELECT source, round(d_a, 5) AS d_a, round(mcc, 5) AS mcc, row_number() OVER (ORDER BY {by}, source)::INT AS rank FROM ({' UNION ALL '.join(picks)})"


def _rank(by: str, k: int | None = None):
    def run(spark, sf_dir):
        sources = {n: _keyed(spark, sf_dir, n) for n in CANDIDATES}
        return R.rank_sources(sources, _keyed(spark, sf_dir, TARGET), by, k, runs=3).withColumns({c: F.round(c, 5) for c in ("d_a", "mcc")})

    return run


query(_rank_sql("d_a"), "rank_sources")(_rank("d_a"))
query(_rank_sql("mcc"), "rank_sources_mcc")(_rank("mcc"))
query(f"SELECT * FROM ({_rank_sql('d_a')}) WHERE rank <= 2", "best_sources")(_rank("d_a", 2))


# A truth and three scores that the line items carry; all are compared with 0.5.
_LINE_TRUTH = "(l_discount >= 0.05)::INT"
_LINE_SCORES = {"target_only": "l_quantity / 50", "source_only": "l_tax * 10", "augmented": "(l_quantity / 50 + l_tax * 10) / 2"}
_LINES = " UNION ALL ".join(f"SELECT l_returnflag AS task, '{a}' AS algorithm, {p} AS p, {_LINE_TRUTH} AS truth FROM lineitem" for a, p in _LINE_SCORES.items())


def _lines(spark, sf_dir):
    """Rows (task, algorithm, p, y) of the line items, a task for each return flag."""
    scores = F.array(*[F.struct(F.lit(a).alias("algorithm"), F.expr(p).alias("p")) for a, p in _LINE_SCORES.items()])
    rows = spark.read.parquet(f"{sf_dir}/lineitem.parquet").select(F.col("l_returnflag").alias("task"), (F.col("l_discount") >= 0.05).cast("int").alias("y"), F.explode(scores).alias("s"))
    return rows.select("task", "s.algorithm", "s.p", "y")


@query(f"SELECT task, algorithm, tp, fp, fn, tn, {S.MCC} FROM ({S.confusion(f'({_LINES})', 'task, algorithm')})")
def mcc_from_confusion(spark, sf_dir):
    rows = M.measures(_lines(spark, sf_dir), by=("task", "algorithm")).select("task", "algorithm", "tp", "fp", "fn", "tn")
    return M.matthews(rows).withColumns({"mcc": F.round("mcc", 6), "d_a": F.round("d_a", 6)})


_SIZE = "list_sum(list_transform(x, lambda v: trunc(v / 1000)::BIGINT * trunc(v / 1000)::BIGINT))"


@query(f"{BASE}, z AS (SELECT *, {_SIZE} AS size FROM cut WHERE dataset = '{TARGET}'), m AS (SELECT y, quantile_cont(size, 0.5) AS middle FROM z GROUP BY y) SELECT id_l, id_r, y, CASE WHEN size <= middle THEN 1 ELSE 2 END AS half FROM z JOIN m USING (y)")
def adversarial_split(spark, sf_dir):
    rows = similarity(spark, sf_dir).where(F.col("dataset") == TARGET)
    return R.adversarial_split(rows).select("id_l", "id_r", "y", "half")


# --- scored pairs ------------------------------------------------------------------------------------------------

_TEST = f"SELECT key, y AS truth, x AS z FROM cut WHERE dataset = '{TARGET}'"
_SCORED = S.bayes(f"SELECT x AS z, y, 1.0 AS w FROM cut WHERE dataset = '{SOURCE}'", _TEST)


def _scored(spark, sf_dir):
    """All target pairs (key, y, p), scored by the source's classifier; p in millionths, as the draws hang on its bins."""
    sim = similarity(spark, sf_dir)
    model = fit("gnb", sim.where(F.col("dataset") == SOURCE).select("x", "y", F.lit(1.0).alias("w")))
    scored = model.score(sim.where(F.col("dataset") == TARGET).withColumn("key", pair_key()))
    return scored.select("key", "y", F.round("p", 6).alias("p"))


_SC = "sc AS (SELECT key, truth, round(p, 6) AS p, least(floor(round(p, 6) * 5), 4)::INT AS stratum FROM scored)"


@query(f"{BASE}, {_SCORED}, {_SC} SELECT stratum, count(*) AS size, round(sum(p * (1 - p)), 5) AS v FROM sc GROUP BY stratum")
def strata(spark, sf_dir):
    return G.strata_table(_scored(spark, sf_dir)).withColumn("v", F.round("v", 5))


def _allocation(how: str, budget: int):
    """Allocations over five strata of the line items by a score of eleven values, their discount."""

    def run(spark, sf_dir):
        scored = spark.read.parquet(f"{sf_dir}/lineitem.parquet").where("l_discount is not null").select(F.round(F.col("l_discount") * 10, 1).alias("p"))
        rows = scored.groupBy("p").agg(F.count("*").alias("n"))  # v from whole numbers, so that it is one whatever the order
        tenths = F.round(F.col("p") * 10).cast("long")
        table = rows.groupBy(G.stratum(F.col("p")).alias("stratum")).agg(F.sum("n").alias("size"), (F.sum(F.col("n") * tenths * (10 - tenths)) / 100).alias("v"))
        got = G.allocate(sorted((r.stratum, r["size"], r.v) for r in table.collect()), budget, how)  # a row for each stratum
        return spark.createDataFrame(sorted(got.items()), "stratum int, labels int")

    raw = {"equal": "1.0", "proportional": "size::DOUBLE", "variability": "v * size"}[how]
    # Whole parts first, then one each to the largest remainders; no stratum overflows in this table.
    sql = f"WITH q AS (SELECT round(l_discount * 10, 1) AS p FROM lineitem WHERE l_discount IS NOT NULL), t AS (SELECT least(floor(p * 5), 4)::INT AS stratum, count(*) AS size, sum(round(p * 10)::BIGINT * (10 - round(p * 10)::BIGINT))::DOUBLE / 100 AS v FROM q GROUP BY 1), s AS (SELECT stratum, {budget} * {raw} / sum({raw}) OVER () AS share FROM t), f AS (SELECT stratum, floor(share + 1e-9)::INT AS base, share - floor(share) AS rest FROM s), r AS (SELECT *, row_number() OVER (ORDER BY rest DESC, stratum) AS place FROM f) SELECT stratum, (base + CASE WHEN place <= {budget} - (SELECT sum(base) FROM f) THEN 1 ELSE 0 END)::INT AS labels FROM r"
    query(sql, f"alloc_{how}")(run)


for _how in ("equal", "proportional", "variability"):
    _allocation(_how, 103)


def _estimate_sql(budget: int, how: str) -> str:
    cell = "0" if how == "none" else "stratum"
    raw = {"none": "size", "equal": "1.0", "proportional": "size::DOUBLE", "variability": "v * size"}[how]
    return f"""{BASE}, {_SCORED}, {_SC}, st AS (SELECT {cell} AS stratum, count(*) AS size, sum(p * (1 - p)) AS v FROM sc GROUP BY 1),
sh AS (SELECT stratum, size, {budget} * {raw} / sum({raw}) OVER () AS share FROM st), fl AS (SELECT stratum, size, floor(share + 1e-9)::INT AS b, share - floor(share) AS rest FROM sh),
rk AS (SELECT *, row_number() OVER (ORDER BY rest DESC, stratum) AS place FROM fl), al AS (SELECT stratum, size, b + CASE WHEN place <= {budget} - (SELECT sum(b) FROM fl) THEN 1 ELSE 0 END AS labels FROM rk),
dr AS (SELECT *, row_number() OVER (PARTITION BY {cell} ORDER BY {S.h32("'b:' || key")}, key) AS place FROM sc),
ex AS (SELECT al.stratum, size, count(*)::DOUBLE AS k, count(*) FILTER ((p >= 0.5) = (truth = 1))::DOUBLE AS ok, count(*) FILTER (p >= 0.5 AND truth = 1)::DOUBLE AS tp, count(*) FILTER (p >= 0.5 AND truth = 0)::DOUBLE AS fp, count(*) FILTER (p < 0.5 AND truth = 1)::DOUBLE AS fn FROM dr JOIN al ON al.stratum = {'0' if how == 'none' else 'dr.stratum'} WHERE place <= labels GROUP BY al.stratum, size),
tt AS (SELECT sum(k)::BIGINT AS labels, sum(ok / k * size) / sum(size) AS a, coalesce(sum(tp / nullif(tp + fn, 0) * size) / sum(size) FILTER (tp + fn > 0), 0) AS r, sum(tp * size / k) AS t, sum(fp * size / k) AS f, sum(fn * size / k) AS n FROM ex)
SELECT labels, round(a, 6) AS accuracy, round(r, 6) AS recall, round(coalesce(2 * a * r / nullif(a + r, 0), 0), 6) AS f, round(coalesce(t / nullif(t + f, 0), 0), 6) AS precision, round(coalesce(t / nullif(t + n, 0), 0), 6) AS pooled_recall, round(coalesce(2 * t / nullif(2 * t + f + n, 0), 0), 6) AS pooled_f FROM tt"""


def _estimate(budget: int, how: str):
    def run(spark, sf_dir):
        got = G.estimate(G.draw(_scored(spark, sf_dir), budget, how=how))
        return got.select("labels", *[F.round(c, 6).alias(c) for c in got.columns if c != "labels"])

    return run


for _how in ("variability", "none"):
    query(_estimate_sql(150, _how), f"estimate_{_how}")(_estimate(150, _how))
for _how in ("equal", "proportional"):
    query(None, f"estimate_{_how}")(_estimate(150, _how))


@query()
def estimator_error(spark, sf_dir):
    """Rows (allocation, budget, f_estimated, f_true, error) of the pooled estimate."""
    scored = _scored(spark, sf_dir).cache()
    true, out = M.measures(scored).select(F.col("f").alias("f_true")), None
    for how in ("none", "equal", "proportional", "variability"):
        for budget in (100, 400):
            one = G.estimate(G.draw(scored, budget, how=how)).select(F.lit(how).alias("allocation"), F.lit(budget).alias("budget"), F.col("pooled_f").alias("f_estimated"))
            out = one if out is None else out.union(one)
    return out.crossJoin(F.broadcast(true)).withColumn("error", F.abs(F.col("f_estimated") - F.col("f_true")))  # one row


# --- measures ----------------------------------------------------------------------------------------------------

_BINS = "CASE WHEN p >= 0.9 THEN 'sure' WHEN p >= 0.5 THEN 'likely' ELSE 'no' END"


@query(f"{BASE}, {S.bayes(f'SELECT x AS z, y, 1.0 AS w FROM cut WHERE dataset = {chr(39)}{SOURCE}{chr(39)}', 'SELECT key, y AS truth, x AS z FROM cut')}, d AS (SELECT dataset, truth, p FROM scored JOIN cut USING (key)) SELECT dataset, tp, fp, fn, tn, {S.PRF} FROM ({S.confusion('d', 'dataset')})")
def prf_by_task(spark, sf_dir):
    """The source's classifier on every task."""
    sim = similarity(spark, sf_dir)
    model = fit("gnb", sim.where(F.col("dataset") == SOURCE).select("x", "y", F.lit(1.0).alias("w")))
    return M.measures(model.score(sim), by=("dataset",)).withColumns({c: F.round(c, 6) for c in ("precision", "recall", "f")})


@query(f"{BASE}, r AS (SELECT dataset, y, {S.h32(chr(39) + 'm' + chr(39) + ' || j || ' + chr(39) + ':' + chr(39) + ' || key')} % 2 AS v, key FROM cut, range(3) t(j) WHERE dataset = 'supplier') SELECT key, sum(v)::BIGINT AS votes, count(*) AS models, (sum(v) * 2 > count(*))::INT AS prediction FROM r GROUP BY key")
def ensemble_vote(spark, sf_dir):
    """Majority of three predictions for each pair (drawn by hash: the vote is what is tested)."""
    from ertransfer.functions.portable import h32

    rows = similarity(spark, sf_dir).where("dataset = 'supplier'").select(pair_key().alias("key"), F.explode(F.array(F.lit(0), F.lit(1), F.lit(2))).alias("j"))
    return M.vote(rows.select("key", F.col("j").alias("model"), (h32("m", F.col("j"), ":", F.col("key")) % 2).alias("prediction")))


@query(f"{BASE} SELECT dataset, count(*) AS n, sum(y)::BIGINT AS matches, round(avg(y), 6) AS prior, round((count(*) - sum(y))::DOUBLE / sum(y), 6) AS ratio FROM sim GROUP BY dataset")
def class_ratio(spark, sf_dir):
    return M.class_ratio(similarity(spark, sf_dir)).withColumns({"prior": F.round("prior", 6), "ratio": F.round("ratio", 6)})


_RANKS = "SELECT c_nationkey AS source, row_number() OVER (ORDER BY sum(round(c_acctbal * 100)::BIGINT), c_nationkey) AS predicted, row_number() OVER (ORDER BY count(*), c_nationkey) AS measured FROM customer GROUP BY c_nationkey"


@query(f"WITH r AS ({_RANKS}) SELECT count(*) AS pairs, count(*) FILTER ((a.predicted - b.predicted) * (a.measured - b.measured) < 0) AS inversions FROM r a JOIN r b ON a.source < b.source")
def ranking_agreement(spark, sf_dir):
    """Nations in the order of their customers' balance and in that of their number."""
    nations = spark.read.parquet(f"{sf_dir}/customer.parquet").groupBy(F.col("c_nationkey").alias("source")).agg(F.sum(F.round(F.col("c_acctbal") * 100).cast("long")).alias("balance"), F.count("*").alias("n"))
    place = lambda c: F.row_number().over(Window.orderBy(c, "source"))  # noqa: E731 - a row for each nation
    return M.ranking_agreement(nations.select("source", place("balance").alias("predicted"), place("n").alias("measured")))


@query(f"WITH r AS (SELECT task, 'line' AS classifier, 100 AS size, algorithm, coalesce(2.0 * tp / nullif(2.0 * tp + fp + fn, 0), 0)::DOUBLE AS f FROM ({S.confusion(f'({_LINES})', 'task, algorithm')})), b AS (SELECT task, max(f) AS best FROM r WHERE algorithm <> 'augmented' GROUP BY task) SELECT task, classifier, size, algorithm, f, best, (f - best)::DOUBLE AS delta FROM r JOIN b USING (task)")
def improvement_table(spark, sf_dir):
    """F of each score of the line items minus the best of the baselines, a task for each return flag."""
    rows = M.measures(_lines(spark, sf_dir), by=("task", "algorithm")).select("task", F.lit("line").alias("classifier"), F.lit(100).alias("size"), "algorithm", "f")
    return M.improvement(rows, ["target_only", "source_only"])


def _shift_sql() -> str:
    pairs = [(SOURCE, TARGET), (SECOND, TARGET), ("customer", TARGET)]
    parts, out = [], []
    for k, (a, b) in enumerate(pairs):
        p, s = _runs_sql(f"sa{k}", f"sb{k}", 1, f"q{k}_")
        parts.append(f"sa{k} AS (SELECT key, x FROM cut WHERE dataset = '{a}'), sb{k} AS (SELECT key, x FROM cut WHERE dataset = '{b}'), {p}")
        prior = lambda d: f"(SELECT avg(y) FROM sim WHERE dataset = '{d}')"
        size = lambda d: f"(SELECT count(*) FROM sim WHERE dataset = '{d}')"
        out.append(f"SELECT '{a}' AS source, '{b}' AS target, round({prior(a)}, 6) AS source_prior, round({prior(b)}, 6) AS target_prior, {size(a)} AS source_size, {size(b)} AS target_size, round(2 * ((tp + tn)::DOUBLE / (tp + fp + fn + tn) - 0.5), 6) AS d_a FROM ({s})")
    return f"{BASE}, {', '.join(parts)} {' UNION ALL '.join(out)}"


@query(_shift_sql())
def shift_report(spark, sf_dir):
    """Prior shift, size imbalance and covariate shift (d_A) between each source and the target."""
    ratio = M.class_ratio(similarity(spark, sf_dir)).cache()
    out = None
    for a in (SOURCE, SECOND, "customer"):
        runs = R.origin_runs(_keyed(spark, sf_dir, a), _keyed(spark, sf_dir, TARGET), 1).select(F.round("d_a", 6).alias("d_a"))
        side = lambda d, n: ratio.where(F.col("dataset") == d).select(F.lit(d).alias(n), F.round("prior", 6).alias(f"{n}_prior"), F.col("n").alias(f"{n}_size"))
        one = side(a, "source").crossJoin(side(TARGET, "target")).crossJoin(runs)  # one row each
        out = one if out is None else out.union(one)
    return out.select("source", "target", "source_prior", "target_prior", "source_size", "target_size", "d_a")


@query(f"{BASE}, {_SCORED} SELECT {_BINS} AS verdict, truth, count(*) AS n FROM scored GROUP BY GROUPING SETS (({_BINS}, truth), ({_BINS}), ())")
def metric_rollup(spark, sf_dir):
    """Decisions by truth, with totals."""
    scored = _scored(spark, sf_dir).select(F.when(F.col("p") >= 0.9, "sure").when(F.col("p") >= 0.5, "likely").otherwise("no").alias("verdict"), F.col("y").alias("truth"))
    return scored.rollup("verdict", "truth").agg(F.count("*").alias("n"))


@query(f"{BASE} SELECT dataset, y, count(*) AS n FROM sim GROUP BY CUBE (dataset, y)")
def metric_cube(spark, sf_dir):
    return similarity(spark, sf_dir).cube("dataset", "y").agg(F.count("*").alias("n"))


def threshold_curve(scored):
    """F at eleven thresholds."""
    tried = scored.withColumn("threshold", F.explode(F.array(*[F.lit(i) for i in range(11)])))
    hit, y = F.col("p") * 10 >= F.col("threshold"), F.col("y") == 1
    n = lambda c: F.count(F.when(c, 1))
    t = tried.groupBy("threshold").agg(n(hit & y).alias("tp"), n(hit & ~y).alias("fp"), n(~hit & y).alias("fn"))
    f = F.coalesce(F.try_divide(2.0 * F.col("tp"), 2.0 * F.col("tp") + F.col("fp") + F.col("fn")), F.lit(0.0))
    return t.withColumn("f", F.round(f, 6)).withColumn("gain", F.round(F.col("f") - F.lag("f").over(Window.orderBy("threshold")), 6))  # eleven rows


QUERIES["threshold_curve"] = lambda spark, sf_dir: threshold_curve(_scored(spark, sf_dir))
