"""Queries of the training strategies, of balancing and of the feature maps, with their SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from ertransfer.functions import vectors as V
from ertransfer.functions.portable import pair_key
from ertransfer.operators import balance as L
from ertransfer.operators import classifiers as C
from ertransfer.operators import measures as M
from ertransfer.operators import transfer as T
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


def _rounded(t):
    return t.withColumns({c: F.round(c, 6) for c in ("precision", "recall", "f")})


# --- strategies with the closed-form classifier ------------------------------------------------------------------


def _strategy_sql(strategy: str, scenario: int, names: tuple[str, ...], tie: str = "last") -> str:
    n = len(names)
    small = " AND h < 10" if scenario == 3 else ""
    src = [f"FROM cut WHERE dataset = '{s}'{small}" for s in names]
    target = f"FROM cut WHERE dataset = '{TARGET}' AND h"
    lab, test = f"{target} < 7", f"{target} >= 70"
    unl = f"{target} < 70" if scenario == 1 else f"{target} >= 7 AND h < 21" if scenario == 3 else f"{target} >= 7 AND h < 70"
    one = lambda z, frm: f"SELECT {z} AS z, y, 1.0 AS w {frm}"
    join = " UNION ALL "
    sources = join.join(one("x", s) for s in src)
    before, z = "", "x"
    if strategy == "target_only":
        train = one("x", lab)
    elif strategy == "source_only":
        train = sources
    elif strategy == "pooled":
        train = sources + join + one("x", lab)
    elif strategy == "weighted":
        origin = join.join(f"SELECT x AS z, 1 AS y, 1.0 AS w {s}" for s in src) + f"{join}SELECT x, 0, 1.0 {unl}"
        every = join.join(f"SELECT key, y AS truth, x AS z {s}" for s in src)
        before = S.bayes(origin, every, "_o") + ", "
        ws = "SELECT key, 1 / greatest(p, 1e-12) - 1 AS w FROM scored_o"
        train = f"SELECT x AS z, y, CASE WHEN (SELECT sum(w) * sum(w) / sum(w * w) FROM ({ws})) < 10 THEN 1.0 ELSE w END AS w FROM ({ws}) JOIN cut USING (key)"
    else:
        train = join.join(one(S.phi_s("x", WIDTH, i, n), s) for i, s in enumerate(src, 1)) + join + one(S.phi_t("x", WIDTH, n), lab)
        if strategy == "semi":
            for i in [n] if tie == "last" else range(1, n + 1):
                train += "".join(f"{join}SELECT {S.phi_u('x', WIDTH, n, i)}, {y}, 1.0 {unl}" for y in (0, 1))
        z = S.phi_t("x", WIDTH, n)
    body = S.bayes(train, f"SELECT key, y AS truth, {z} AS z {test}")
    return f"{BASE}, {before}{body} SELECT tp, fp, fn, tn, {S.PRF} FROM ({S.confusion('scored')})"


def strategy_query(strategy: str, scenario: int, names: tuple[str, ...] = (SOURCE,), tie: str = "last", kind: str = "gnb"):
    def run(spark, sf_dir):
        sources, labelled, free, test = roles(similarity(spark, sf_dir), scenario, names)
        options = {"tie": tie} if strategy == "semi" else {}
        return _rounded(M.measures(T.apply_strategy(strategy, sources, labelled, free, test, WIDTH, kind, **options)))

    return run


#: The scenario whose labels each strategy is made for.
SCENARIO_OF = {"target_only": 2, "source_only": 2, "pooled": 2, "weighted": 1, "augmented": 2, "semi": 3}
for _s, _k in SCENARIO_OF.items():
    query(_strategy_sql(_s, _k, (SOURCE,)), f"transfer_{_s}")(strategy_query(_s, _k))
    if _s != "target_only":
        query(_strategy_sql(_s, _k, (SOURCE, SECOND)), f"multi_{_s}")(strategy_query(_s, _k, (SOURCE, SECOND)))
query(_strategy_sql("semi", 3, (SOURCE, SECOND), "each"), "multi_semi_each")(strategy_query("semi", 3, (SOURCE, SECOND), "each"))


# --- the four classifiers ----------------------------------------------------------------------------------------


def strategies_with(kind: str):
    """Rows (classifier, scenario, strategy, precision, recall, f): every strategy of its scenario beside the baselines."""

    def run(spark, sf_dir):
        sim, out, done = similarity(spark, sf_dir), None, {}
        for scenario, names in ((1, ["source_only", "weighted"]), (2, ["target_only", "source_only", "pooled", "augmented"]), (3, ["target_only", "source_only", "pooled", "semi"])):
            sources, labelled, free, test = roles(sim, scenario)
            for name in names:
                options = {"origin": "lr", "clip": 20.0} if name == "weighted" else {}
                # Scenarios 1 and 2 have the same sources, 2 and 3 the same labels, all the same test: one training is enough.
                same = (name, scenario == 3) if name == "source_only" else name if name == "target_only" else (name, scenario)
                if same not in done:
                    done[same] = _rounded(M.measures(T.apply_strategy(name, sources, labelled, free, test, WIDTH, kind, **options)))
                one = done[same].select(F.lit(kind).alias("classifier"), F.lit(scenario).alias("scenario"), F.lit(name).alias("strategy"), "precision", "recall", "f")
                out = one if out is None else out.union(one)
        return out

    return run


for _kind in C.KINDS:
    query(None, f"classifiers_{_kind}")(strategies_with(_kind))


# --- weights -----------------------------------------------------------------------------------------------------

_ORIGIN = S.bayes(f"SELECT x AS z, 1 AS y, 1.0 AS w FROM cut WHERE dataset = '{SOURCE}' UNION ALL SELECT x, 0, 1.0 FROM cut WHERE dataset = '{TARGET}' AND h < 70", f"SELECT key, y AS truth, x AS z FROM cut WHERE dataset = '{SOURCE}'", "_o")
_W = "1 / greatest(p, 1e-12) - 1"


def _weighted(spark, sf_dir, **options):
    sources, _, free, _ = roles(similarity(spark, sf_dir), 1)
    return T.origin_weights(sources[0], free, **options)


@query(f"{BASE}, {_ORIGIN} SELECT id_l, id_r, round(p, 6) AS p_origin, round(least({_W}, 20.0), 4) AS w FROM scored_o JOIN cut USING (key)")
def instance_weights(spark, sf_dir):
    return _weighted(spark, sf_dir, clip=20.0).select("id_l", "id_r", F.round("p_origin", 6).alias("p_origin"), F.round("w", 4).alias("w"))


@query(f"{BASE}, {_ORIGIN}, ratio AS (SELECT count(*) FILTER (dataset = '{SOURCE}')::DOUBLE / count(*) FILTER (dataset = '{TARGET}' AND h < 70) AS r FROM cut) SELECT id_l, id_r, round(least(({_W}) * r, 20.0), 4) AS w FROM scored_o JOIN cut USING (key), ratio")
def prior_corrected_weights(spark, sf_dir):
    return _weighted(spark, sf_dir, clip=20.0, prior_correct=True).select("id_l", "id_r", F.round("w", 4).alias("w"))


@query(f"{BASE}, {_ORIGIN} SELECT count(*) AS n, round(sum(w) * sum(w) / sum(w * w), 3) AS ess FROM (SELECT least({_W}, 20.0) AS w FROM scored_o)")
def effective_size(spark, sf_dir):
    return T.effective_size(_weighted(spark, sf_dir, clip=20.0)).withColumn("ess", F.round("ess", 3))


# --- feature maps ------------------------------------------------------------------------------------------------


def _register_phi():
    """Maps are built inside the queries, as columns need a session."""
    maps = {
        "phi_source": (lambda x: V.phi_source(x, WIDTH), S.phi_s("x", WIDTH)),
        "phi_target": (lambda x: V.phi_target(x, WIDTH), S.phi_t("x", WIDTH)),
        "phi_unlabeled": (lambda x: V.phi_unlabeled(x, WIDTH), S.phi_u("x", WIDTH)),
        "phi_source_2_of_3": (lambda x: V.phi_source(x, WIDTH, 2, 3), S.phi_s("x", WIDTH, 2, 3)),
        "phi_target_of_3": (lambda x: V.phi_target(x, WIDTH, 3), S.phi_t("x", WIDTH, 3)),
        "phi_unlabeled_of_3": (lambda x: V.phi_unlabeled(x, WIDTH, 3), S.phi_u("x", WIDTH, 3)),
    }
    for name, (make, sql) in maps.items():

        def run(spark, sf_dir, make=make):
            return similarity(spark, sf_dir).where("dataset = 'supplier'").select("id_l", "id_r", V.as_text(make(F.col("x"))).alias("z"))

        query(f"{BASE} SELECT id_l, id_r, {S.text(sql)} AS z FROM cut WHERE dataset = 'supplier'", name)(run)


_register_phi()


# --- which scenario ----------------------------------------------------------------------------------------------

_STATE = lambda n, of: f"CASE WHEN {n} = 0 THEN 'none' WHEN {n} < 0.1 * {of} THEN 'limited' ELSE 'adequate' END"


# Customers in three parts: none labelled, five of a hundred, half.
_PART, _LABELLED = "c_custkey % 3", "floor(c_custkey / 3) % 100 < CASE c_custkey % 3 WHEN 0 THEN 0 WHEN 1 THEN 5 ELSE 50 END"


@query(f"""WITH p AS (SELECT {_PART} AS part, count(*) AS n, count(*) FILTER ({_LABELLED}) AS labels FROM customer GROUP BY 1),
s AS (SELECT a.labels AS source_labels, b.labels AS target_labels, {_STATE('a.labels', 'a.n')} AS s, {_STATE('b.labels', 'b.n')} AS t FROM p a, p b)
SELECT source_labels, target_labels, s AS source_state, t AS target_state, CASE WHEN t = 'adequate' THEN 'target_only' WHEN s = 'none' AND t = 'none' THEN 'no labels' WHEN s = 'none' THEN 'target_only' WHEN t = 'none' THEN 'weighted' WHEN s = 'adequate' THEN 'augmented' ELSE 'semi' END AS strategy FROM s""")
def scenario_rules(spark, sf_dir):
    """The strategy for each part of the customers as source and each as target, by what is labelled."""
    parts = spark.read.parquet(f"{sf_dir}/customer.parquet").groupBy(F.expr(_PART).alias("part")).agg(F.count("*").alias("n"), F.count(F.when(F.expr(_LABELLED), 1)).alias("labels"))
    side = lambda n: parts.select(F.col("labels").alias(f"{n}_labels"), T.label_state(F.col("labels"), F.col("n")).alias(f"{n}_state"))
    both = side("source").crossJoin(side("target")).select("source_labels", "target_labels", "source_state", "target_state")  # three rows each
    return both.select("*", T.scenario(F.col("source_state"), F.col("target_state")).alias("strategy"))


# --- balance -----------------------------------------------------------------------------------------------------


def _keyed(spark, sf_dir, dataset=SOURCE):
    return similarity(spark, sf_dir).where(F.col("dataset") == dataset).select(pair_key().alias("key"), "dataset", "id_l", "id_r", "y", "x")


def _ranked(seed: str, dataset: str, by: str = "") -> str:
    part = f"PARTITION BY {by} " if by else ""
    return f"SELECT *, row_number() OVER ({part}ORDER BY {S.h32(chr(39) + seed + ':' + chr(39) + ' || key')}, key) AS place FROM cut WHERE dataset = '{dataset}'"


def _undersample_sql(n: int) -> str:
    return f"{BASE}, r AS ({_ranked('u', SOURCE, 'y')}), c AS (SELECT least(count(*) FILTER (y = 1), {n // 4}) AS m, count(*) FILTER (y = 0) AS o FROM cut WHERE dataset = '{SOURCE}') SELECT id_l, id_r, y FROM r, c WHERE place <= CASE WHEN y = 1 THEN m ELSE least(o, {n} - m) END"


def _undersample(n):
    return lambda spark, sf_dir: L.undersample(_keyed(spark, sf_dir), n).select("id_l", "id_r", "y")


query(_undersample_sql(200), "undersample_small")(_undersample(200))
query(_undersample_sql(6000), "undersample_1to3")(_undersample(6000))


@query(f"{BASE}, c AS (SELECT y, count(*) AS n FROM cut WHERE dataset = '{SOURCE}' GROUP BY y) SELECT y, n, round((SELECT sum(n) FROM c)::DOUBLE / (2 * n), 6) AS w FROM c")
def class_weights(spark, sf_dir):
    return L.class_weights(_keyed(spark, sf_dir)).groupBy("y").agg(F.count("*").alias("n"), F.round(F.max("w"), 6).alias("w"))


def _limited(spark, sf_dir):
    """(source pairs, labelled target pairs), named."""
    sources, labelled, _, _ = roles(similarity(spark, sf_dir), 2)
    return sources[0].select("key", "dataset", "y", "x"), labelled.select("key", "dataset", "y", "x")


_LAB = f"lab AS (SELECT * FROM cut WHERE dataset = '{TARGET}' AND h < 7), srcp AS (SELECT * FROM cut WHERE dataset = '{SOURCE}')"


@query(f"{BASE}, {_LAB} SELECT dataset, count(*) AS n, round(CASE WHEN dataset = '{SOURCE}' THEN least(1.0, (SELECT count(*) FROM lab)::DOUBLE / (SELECT count(*) FROM srcp)) ELSE 1.0 END, 6) AS w FROM (SELECT * FROM srcp UNION ALL SELECT * FROM lab) GROUP BY dataset")
def dataset_weights(spark, sf_dir):
    return L.dataset_weights(*_limited(spark, sf_dir)).groupBy("dataset").agg(F.count("*").alias("n"), F.round(F.max("w"), 6).alias("w"))


@query(f"{BASE}, {_LAB}, placed AS (SELECT key, row_number() OVER (ORDER BY key) - 1 AS place FROM lab) SELECT copy, key FROM (SELECT r AS copy, {S.h32(chr(39) + 'r:' + chr(39) + ' || r')} % (SELECT count(*) FROM lab) AS place FROM range(5000) t(r)) JOIN placed USING (place)")
def replicate_random(spark, sf_dir):
    return L.replicate_random(_limited(spark, sf_dir)[1], 5000).select("copy", "key")


@query(f"{BASE}, {_LAB} SELECT r AS copy, key FROM lab, range(10) t(r)")
def replicate_fixed(spark, sf_dir):
    return L.replicate_fixed(_limited(spark, sf_dir)[1], 10).select("copy", "key")


@query(f"{BASE}, {_LAB} SELECT (SELECT count(*) FROM srcp) AS source_size, (SELECT count(*) FROM lab) AS target_size, least((SELECT count(*) FROM srcp), 10 * (SELECT count(*) FROM lab)) AS most")
def cap_source(spark, sf_dir):
    source, target = _limited(spark, sf_dir)
    n, m = source.count(), target.count()
    return spark.createDataFrame([(n, m, L.cap(n, m))], "source_size long, target_size long, most long")


_WEIGHED = f"ws AS (SELECT key, round(least({_W}, 20.0), 4) AS w FROM scored_o)"
_WAIT = f"-ln(({S.h32(chr(39) + 'i:' + chr(39) + ' || key')} + 0.5) / 4294967296.0) / w"


def _weights4(spark, sf_dir):
    return _weighted(spark, sf_dir, clip=20.0).select("key", F.round("w", 4).alias("w"))


@query(f"{BASE}, {_ORIGIN}, {_WEIGHED} SELECT key, w FROM ws WHERE w > 0 ORDER BY {_WAIT}, key LIMIT 500")
def importance_sample(spark, sf_dir):
    return L.importance_sample(_weights4(spark, sf_dir), 500).select("key", "w")


@query(f"{BASE}, {_ORIGIN}, {_WEIGHED} SELECT key, w FROM ws ORDER BY w DESC, key LIMIT 500")
def top_weight(spark, sf_dir):
    return L.top_weight(_weights4(spark, sf_dir), 500).select("key", "w")


@query()
def importance_sample_with_replacement(spark, sf_dir):
    return L.importance_sample_with_replacement(_weights4(spark, sf_dir), 500).select("copy", "key", "w")
