"""The experiments on small grids, as queries; the sweeps are in :mod:`ertransfer.experiments`."""

from __future__ import annotations

from pyspark.sql import functions as F

from ertransfer import experiments as X
from ertransfer.functions import vectors as V
from ertransfer.functions.portable import h32
from ertransfer.operators import blocking as B
from ertransfer.operators import measures as M
from ertransfer.operators.truncation import truncated_pair_features
from ertransfer.plans import sqlbase as S
from ertransfer.plans.tasks import REACH, SECOND, SOURCE, TARGET, WIDTH, sides, similarity

QUERIES: dict = {}
SQL: dict[str, str] = {}


def _rounded(t):
    return t.withColumn("f", F.round("f", 6))


def query(sql=None, name: str | None = None):
    def keep(f):
        QUERIES[name or f.__name__] = f
        if sql:
            SQL[name or f.__name__] = sql
        return f

    return keep


@query()
def exp1_histogram_text(spark, sf_dir):
    """Cosine histograms of copies and others, language by language."""
    return M.histogram(X.text_cosines(spark, sf_dir)).withColumn("overlap", F.round("overlap", 6))


def _grid(name, run):
    QUERIES[name] = lambda spark, sf_dir: _rounded(run(spark, sf_dir))


_PAIR = [(SOURCE, TARGET)]
_grid("exp1_baselines", lambda s, d: X.baselines(s, similarity(s, d), _PAIR, ("gnb",), (10,)))
_grid("exp2_scenario1", lambda s, d: X.scenario_1(s, similarity(s, d), _PAIR, ("gnb",), (10,)))
_grid("exp2_scenario2", lambda s, d: X.scenario_2(s, similarity(s, d), _PAIR, ("lr",), (10,)))
_grid("exp2_scenario3", lambda s, d: X.scenario_3(s, similarity(s, d), _PAIR, ("gnb",), (20,)))
_grid("exp2_dimension", lambda s, d: X.dimensions(s, lambda w: similarity(s, d, width=w), _PAIR[0], ("gnb",), (32, WIDTH)))
_grid("exp3_multi_source", lambda s, d: X.several_sources(s, similarity(s, d), (SOURCE, SECOND), TARGET, ("gnb",), (10,)))
_grid("exp3_ranking", lambda s, d: X.ranking(s, similarity(s, d), (SOURCE, SECOND, "customer"), TARGET, "gnb", 2).withColumn("d_a", F.round("d_a", 6)))
_grid("exp4_cross_domain", lambda s, d: X.cross_domain(s, X.adversarial(similarity(s, d)).unionByName(similarity(s, d).where("dataset = 'customer'")), "half1", "customer", "half2", ("gnb",), (10,)))
_grid("exp5_negative", lambda s, d: X.negative(s, X.adversarial(similarity(s, d)), ("gnb",), (10,)))
_grid("ablation_balance", lambda s, d: X.balance_ablation(s, similarity(s, d), "gnb"))
_grid("ablation_encoder", lambda s, d: X.encoder_ablation(s, d, "gnb"))


@query()
def exp2_improvement(spark, sf_dir):
    """Gain of feature augmentation over the better baseline."""
    got = X.scenario_2(spark, similarity(spark, sf_dir), _PAIR, ("gnb",), (10,))
    return X.improvements(got, ["target_only", "source_only"]).withColumns({c: F.round(c, 6) for c in ("f", "best", "delta")})


# --- truncated features ------------------------------------------------------------------------------------------

_TABLES = {"customer": ("c_custkey", "c_name", "c_nationkey", "c_acctbal"), "supplier": ("s_suppkey", "s_name", "s_nationkey", "s_acctbal")}


def _attributes(spark, sf_dir):
    out = None
    for table, (key, name, nation, balance) in _TABLES.items():
        one = spark.read.parquet(f"{sf_dir}/{table}.parquet").select(F.lit(table).alias("dataset"), F.col(key).alias("id"), F.col(name).alias("name"), F.col(nation).alias("nation"), F.col(balance).alias("balance"))
        out = one if out is None else out.union(one)
    return out


def _nulled(attributes):
    """A copy in which a hash takes each attribute away from one tuple in seven."""
    keep = lambda c: F.when(h32(f"n:{c}:", F.col("dataset"), ":", F.col("id")) % 7 > 0, F.col(c)).alias(c)
    return attributes.select("dataset", "id", *[keep(c) for c in ("name", "nation", "balance")])


def _sql() -> str:
    rows = " UNION ALL ".join(f"SELECT '{t}' AS dataset, {k}::BIGINT AS id, {n} AS name, {c} AS nation, {b} AS balance FROM {t}" for t, (k, n, c, b) in _TABLES.items())
    gone = ", ".join(f"CASE WHEN {S.h32(chr(39) + f'n:{c}:' + chr(39) + ' || dataset || ' + chr(39) + ':' + chr(39) + ' || id')} % 7 > 0 THEN {c} END AS {c}" for c in ("name", "nation", "balance"))
    parts = ["1 - levenshtein(a.name, b.name)::DOUBLE / greatest(length(a.name), length(b.name), 1)", "(a.nation = b.nation)::INT::DOUBLE", "1 - least(1.0, abs(a.balance - b.balance) / greatest(abs(a.balance), abs(b.balance), 1e-9))"]
    x = ", ".join(f"coalesce(round(({p}) * 1000000)::BIGINT, 0)" for p in parts)
    guarded = x.replace("coalesce(round((1 - levenshtein", "coalesce(round((CASE WHEN a.name IS NULL OR b.name IS NULL THEN NULL ELSE 1 - levenshtein").replace("length(b.name), 1))", "length(b.name), 1) END)", 1)
    guarded = guarded.replace("(1 - least(1.0, abs(a.balance - b.balance) / greatest(abs(a.balance), abs(b.balance), 1e-9)))", "(CASE WHEN a.balance IS NULL OR b.balance IS NULL THEN NULL ELSE 1 - least(1.0, abs(a.balance - b.balance) / greatest(abs(a.balance), abs(b.balance), 1e-9)) END)")
    return f"{S.base()}, att AS ({rows}), dirt AS (SELECT dataset, id, {gone} FROM att) SELECT c.dataset, id_l, id_r, y, array_to_string([{guarded}], ',') AS x FROM cand c JOIN att a ON a.dataset = c.dataset AND a.id = id_l JOIN dirt b ON b.dataset = c.dataset AND b.id = id_r"


def _truncated(spark, sf_dir):
    pairs = B.by_neighbourhood(*sides(spark, sf_dir), REACH).where(F.col("dataset").isin(list(_TABLES)))
    attributes = _attributes(spark, sf_dir)
    return truncated_pair_features(pairs, attributes, _nulled(attributes), ["name"], ["nation"], ["balance"])


@query(_sql())
def pair_truncated(spark, sf_dir):
    """Features of the three attributes that customers and suppliers share."""
    return _truncated(spark, sf_dir).select("dataset", "id_l", "id_r", "y", V.as_text("x").alias("x"))


@query()
def ablation_feature_space(spark, sf_dir):
    """Naive transfer from customers to suppliers with truncated and with standardised features."""
    from ertransfer.durable import settle

    rows = []
    for name, sim, width in (("truncated", settle(_truncated(spark, sf_dir), "truncated"), 3), ("standardised", similarity(spark, sf_dir), WIDTH)):
        task = X.Task(sim, "customer", "supplier", width=width)
        rows.append((f"feature space {name}", *task.row("", "source_only", "gnb", 100, source=100)[1:]))
    return _rounded(spark.createDataFrame(rows, X.SCHEMA))
