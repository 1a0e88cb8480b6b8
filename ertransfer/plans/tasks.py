"""The ER tasks over the given tables: a table against a deterministic dirty copy of itself, equal ids being matches.

Three parts of ``part`` of different dirt are two sources and the target; ``customer`` and ``supplier``, of other schemas,
are sources of other domains.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ertransfer.durable import settle
from ertransfer.functions.portable import pair_draw, pair_key
from ertransfer.operators import blocking as B
from ertransfer.operators import encoding as E

#: dataset: (table, rows, id, attributes, blocking key, percent of tokens that the copy lacks)
TASKS = {
    "part_a": ("part", "p_partkey % 3 = 0", "p_partkey", ["p_name", "p_brand", "p_type", "p_size", "cast(floor(p_retailprice) as bigint)"], ["p_size"], 10),
    "part_b": ("part", "p_partkey % 3 = 1", "p_partkey", ["p_name", "p_brand", "p_type", "p_size", "cast(floor(p_retailprice) as bigint)"], ["p_size"], 25),
    "part_c": ("part", "p_partkey % 3 = 2", "p_partkey", ["p_name", "p_brand", "p_type", "p_size", "cast(floor(p_retailprice) as bigint)"], ["p_size"], 18),
    "customer": ("customer", "true", "c_custkey", ["c_name", "c_nationkey", "c_mktsegment", "cast(floor(c_acctbal) as bigint)"], ["c_nationkey"], 15),
    "supplier": ("supplier", "true", "s_suppkey", ["s_name", "s_nationkey", "cast(floor(s_acctbal) as bigint)"], ["s_nationkey"], 15),
}
DIRT = {name: task[5] for name, task in TASKS.items()}
SOURCE, SECOND, TARGET = "part_a", "part_c", "part_b"
REACH = 10
WIDTH = E.WIDTH
_settled: dict = {}


def tuples(spark: SparkSession, sf_dir: str, names=tuple(TASKS)) -> DataFrame:
    out = None
    for name in names:
        table, where, key, attributes, block, _ = TASKS[name]
        one = E.tuple_document(spark.read.parquet(f"{sf_dir}/{table}.parquet").where(where), name, key, [F.expr(a) for a in attributes], [F.expr(b) for b in block])
        out = one if out is None else out.union(one)
    return out


def all_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    return E.tokenize(tuples(spark, sf_dir))


def dictionary(spark: SparkSession, sf_dir: str, tokens: DataFrame, width: int = WIDTH) -> DataFrame:
    return E.hashed_dictionary(tokens, spark.read.parquet(f"{sf_dir}/embeddings.parquet"), width)


def _side(both: DataFrame, tokens: DataFrame) -> DataFrame:
    """Tuples with their tokens as text, in order."""
    text = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("pos", "token"))), lambda t: t["token"]), " ")
    return tokens.groupBy("dataset", "id").agg(text.alias("doc")).join(both.select("dataset", "id", "block"), ["dataset", "id"])


def sides(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """(clean, dirty) tuples (dataset, id, doc, block)."""
    both = tuples(spark, sf_dir)
    tokens = E.tokenize(both)
    return _side(both, tokens), _side(both, E.dirty(tokens, DIRT))


def encodings(spark: SparkSession, sf_dir: str, width: int = WIDTH, weighting: str = "sif", policy: str = "context") -> tuple[DataFrame, DataFrame]:
    """(clean, dirty) tuple vectors by the whole encoder: known vectors, contexts of unknown tokens, weighted mean."""
    tokens = all_tokens(spark, sf_dir)
    words = settle(E.extended_dictionary(tokens, dictionary(spark, sf_dir, tokens, width), policy, width), "dictionary")
    frequency = E.token_frequency(tokens) if weighting == "sif" else None
    return E.encode(tokens, words, width, frequency), E.encode(E.dirty(tokens, DIRT), words, width, frequency)


def similarity(spark: SparkSession, sf_dir: str, op: str = "diff", width: int = WIDTH, weighting: str = "sif", policy: str = "context") -> DataFrame:
    """Rows (dataset, id_l, id_r, y, x): pair vectors of all tasks, written once a session and read by every method."""
    name = (spark.sparkContext.applicationId, sf_dir, op, width, weighting, policy)
    if name not in _settled:
        _settled[name] = settle(pair_table(spark, sf_dir, op, width, weighting, policy), "similarity")
    return _settled[name]


def pair_table(spark: SparkSession, sf_dir: str, op: str = "diff", width: int = WIDTH, weighting: str = "sif", policy: str = "context", names=tuple(TASKS), component: bool = True) -> DataFrame:
    """Rows (dataset, id_l, id_r, y, x) of the datasets ``names``, with words and frequencies of all of them.

    Without ``component``, the common component of all clean and dirty tuples is removed from their vectors.

    Where the dictionary can travel to the tasks, each makes the vectors of its tuples itself; else vectors are joined.
    """
    tokens, lists = all_tokens(spark, sf_dir), E.listed(tuples(spark, sf_dir))
    known = dictionary(spark, sf_dir, tokens, width)
    frequency = E.token_frequency(tokens) if weighting == "sif" else None
    if policy == "context":
        near = E.carried(known)
        extended = near and known.union(E.contexts_of_listed(lists, near, width))
    else:
        extended = E.extended_dictionary(tokens, known, policy, width)
    words = extended and E.carried(extended, frequency)
    of = F.col("dataset").isin(list(names))
    if words is None:
        left, right = (side.where(of) for side in sides(spark, sf_dir))
        both = encodings(spark, sf_dir, width, weighting, policy)
        if not component:
            marked, _ = E.remove_common_component(both[0].withColumn("side", F.lit(0)).unionByName(both[1].withColumn("side", F.lit(1))), width)
            both = [marked.where(F.col("side") == s) for s in (0, 1)]
        return E.pair_vectors(B.by_neighbourhood(left, right, REACH), *both, op, width)
    by = 1 if frequency is None else E.MICRO
    every = lists.union(E.dirty_listed(lists, DIRT))
    along = None if component else E.common_component(E.vectors_of_listed(every, words, by), width)
    some = lists.where(of)
    return E.neighbour_vectors(some, E.dirty_listed(some, DIRT), words, REACH, op, width, by, along)


def roles(sim: DataFrame, scenario: int = 2, source: str | tuple = SOURCE, target: str = TARGET, percent: int = 10) -> tuple:
    """(sources, labelled target, unlabelled target, test): 70 of 100 target pairs may train, the rest are for tests.

    Scenario 1 has no target labels, 2 labels a tenth of the training pairs, 3 also keeps ``percent`` of each source only
    and takes a fifth of the training pairs without labels.
    """
    drawn = sim.withColumn("h", pair_draw("split")).withColumn("key", pair_key())
    of = drawn.where(F.col("dataset") == target)
    names = (source,) if isinstance(source, str) else source
    sources = [drawn.where(F.col("dataset") == s) for s in names]
    if scenario == 3:
        sources = [s.where(F.col("h") < percent) for s in sources]
    labelled = of.where("h < 7")
    free = of.where("h < 70") if scenario == 1 else of.where("h >= 7 and h < 21") if scenario == 3 else of.where("h >= 7 and h < 70")
    return sources, labelled, free, of.where("h >= 70")
