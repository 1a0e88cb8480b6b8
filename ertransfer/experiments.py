"""The experiments: training sizes swept over tasks, strategies and classifiers.

``python -m ertransfer.experiments [SF_DIR] [NAME...]`` runs the full sweeps and prints one JSON row a line; the queries
of :mod:`ertransfer.plans.experiment_queries` run the same functions on small grids.
"""

from __future__ import annotations

import json
import sys

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ertransfer.durable import release, settle
from ertransfer.functions.portable import h32, pair_key
from ertransfer.functions.vectors import cosine
from ertransfer.operators import balance as L
from ertransfer.operators import blocking as B
from ertransfer.operators import encoding as E
from ertransfer.operators import measures as M
from ertransfer.operators import relatedness as R
from ertransfer.operators import texts as D
from ertransfer.operators import transfer as T
from ertransfer.operators.classifiers import KINDS
from ertransfer.plans.tasks import SECOND, SOURCE, TARGET, WIDTH, pair_table, similarity

CLIP = 20.0
SCHEMA = "experiment string, source string, target string, classifier string, algorithm string, size int, f double"
_text: dict = {}


def text_similarity(spark: SparkSession, sf_dir: str, width: int = WIDTH) -> DataFrame:
    """Rows (dataset, id_l, id_r, y, x, cosine) of the document tasks, one dataset for each language."""
    name = (spark.sparkContext.applicationId, sf_dir, width)
    if name not in _text:
        docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
        encoded = D.text_vectors(docs, spark.read.parquet(f"{sf_dir}/embeddings.parquet"), width)
        encoded = D.as_arrays(encoded, width)
        both = E.paired(B.same_language_copies(docs).select("dataset", "id_l", "id_r", "y"), encoded, encoded, width)
        x = F.zip_with("xl", "xr", lambda a, b: F.abs(a - b))
        _text[name] = settle(both.select("dataset", "id_l", "id_r", "y", x.alias("x"), cosine("xl", "xr").alias("cosine")), "text-similarity")
    return _text[name]


def text_cosines(spark: SparkSession, sf_dir: str, width: int = WIDTH) -> DataFrame:
    """Rows (dataset, y, cosine) of all pairs of documents of one language that share a word 3-gram, y 1 for copies."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    encoded = D.text_vectors(docs, spark.read.parquet(f"{sf_dir}/embeddings.parquet"), width)
    return D.copies_with_cosine(D.listed_texts(docs), encoded, width, most=None)


def _drawn(sim: DataFrame, name: str) -> DataFrame:
    return sim.where(F.col("dataset") == name).withColumn("key", pair_key()).withColumn("h", h32("size:", F.col("key")) % 1000)


class Task:
    """A source (or several) and a target of one similarity table; sizes are percent of the labelled training pairs.

    Seven of ten target pairs may train. Sources are cut to ten times the labelled target pairs by importance sampling
    where the target has labels, and to ``ratio`` non-matches for each match. ``keep`` caches the target pairs.
    """

    def __init__(self, sim: DataFrame, sources: str | tuple, target: str, ratio: int = 3, width: int = WIDTH, keep: bool = True):
        self.names = (sources,) if isinstance(sources, str) else tuple(sources)
        self.target_name, self.ratio, self.width = target, ratio, width
        self.all_sources = [_drawn(sim, s) for s in self.names]
        self.target = _drawn(sim, target).cache() if keep else _drawn(sim, target)
        self.test = self.target.where("h >= 700")

    def _balanced(self, rows: DataFrame) -> DataFrame:
        counts = {r.y: r.n for r in rows.groupBy("y").agg(F.count("*").alias("n")).collect()}
        return L.undersample(rows, (1 + self.ratio) * counts.get(1, 0), self.ratio) if counts.get(1) else rows

    def sources(self, percent: float) -> list[DataFrame]:
        """Balanced source pairs; several sources share the percentage equally."""
        return [self._balanced(s.where(F.col("h") < int(10 * percent / len(self.names)))) for s in self.all_sources]

    def labelled(self, percent: float) -> DataFrame:
        return self._balanced(self.target.where(F.col("h") < int(7 * percent)))

    def free(self, percent: float, labelled: float = 0) -> DataFrame:
        return self.target.where((F.col("h") >= int(7 * labelled)) & (F.col("h") < min(700, int(7 * (labelled + percent)))))

    def f(self, strategy: str, kind: str, source: float = 10, target: float = 0, free: float = 100) -> float:
        """F on the test pairs; 0 where a training set lacks a class."""
        sources, labelled, unlabelled = self.sources(source), self.labelled(target), self.free(free, target)
        options = {"origin": "lr", "clip": CLIP} if strategy == "weighted" else {}
        try:
            if strategy in ("augmented", "semi") and target:
                most = L.cap(1 << 62, labelled.count()) // len(sources)
                sources = [L.importance_sample(T.origin_weights(s, unlabelled, CLIP, "lr"), most).select(*s.columns) if s.count() > most else s for s in sources]
            scored = T.apply_strategy(strategy, sources, labelled, unlabelled, self.test, self.width, kind, **options)
            return M.measures(scored).first().f
        except ValueError:
            return 0.0

    def row(self, experiment: str, strategy: str, kind: str, size: float, **amounts) -> tuple:
        return experiment, "+".join(self.names), self.target_name, kind, strategy, int(size), float(self.f(strategy, kind, **amounts))


def _table(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame(rows, SCHEMA)


def baselines(spark, sim, pairs, kinds=KINDS, sizes=(10, 50, 100)) -> DataFrame:
    """No transfer and naive transfer by training size, both directions; the worse direction counts."""
    rows = []
    for a, b in pairs:
        for s, t in ((a, b), (b, a)):
            task = Task(sim, s, t)
            for kind in kinds:
                for size in sizes:
                    rows.append(task.row("baselines", "target_only", kind, size, target=size))
                    rows.append(task.row("baselines", "source_only", kind, size, source=size))
    return _table(spark, rows)


def scenario_1(spark, sim, pairs, kinds=KINDS, sizes=(1, 2, 5, 10)) -> DataFrame:
    """No target labels: weighted training beside naive transfer."""
    tasks = [Task(sim, s, t) for s, t in pairs]
    return _table(spark, [task.row("scenario_1", a, kind, size, source=size) for task in tasks for kind in kinds for size in sizes for a in ("source_only", "weighted")])


def scenario_2(spark, sim, pairs, kinds=KINDS, sizes=(1, 5, 10), target=10) -> DataFrame:
    """A tenth of the target labelled: feature augmentation beside the baselines."""
    tasks = [Task(sim, s, t) for s, t in pairs]
    return _table(spark, [task.row("scenario_2", a, kind, size, source=size, target=target) for task in tasks for kind in kinds for size in sizes for a in ("target_only", "source_only", "pooled", "augmented")])


def scenario_3(spark, sim, pairs, kinds=KINDS, sizes=(1, 5, 10, 20)) -> DataFrame:
    """Both sides limited, a fifth of the training pairs without labels: the semi-supervised form beside the baselines."""
    tasks = [Task(sim, s, t) for s, t in pairs]
    return _table(spark, [task.row("scenario_3", a, kind, size, source=size, target=size, free=20) for task in tasks for kind in kinds for size in sizes for a in ("target_only", "source_only", "pooled", "semi")])


def dimensions(spark, make_similarity, pair, kinds=("lr",), widths=(16, 32, 64)) -> DataFrame:
    """Scenario 2 at several vector widths (the size column); ``make_similarity(width)`` gives the pairs."""
    rows = []
    for width in widths:
        task = Task(make_similarity(width), *pair, width=width)
        rows += [task.row("dimensions", a, kind, width, source=10, target=10) for kind in kinds for a in ("target_only", "augmented")]
    return _table(spark, rows)


def several_sources(spark, sim, sources, target, kinds=("svm", "rf"), sizes=(2, 10)) -> DataFrame:
    """Two sources, sharing the size equally, beside each alone."""
    tasks = [Task(sim, s, target) for s in (*sources, tuple(sources))]
    return _table(spark, [task.row("several_sources", "augmented", kind, size, source=size, target=10) for task in tasks for kind in kinds for size in sizes])


def ranking(spark, sim, sources, target, kind="lr", runs=3) -> DataFrame:
    """Rows (source, d_a, predicted, f, measured): the order by d_A beside that of the F each source alone brings."""
    keyed = lambda n: sim.where(F.col("dataset") == n).select(pair_key().alias("key"), "x")
    got = R.rank_sources({s: keyed(s) for s in sources}, keyed(target), runs=runs).collect()
    scores = {s: Task(sim, s, target).f("weighted", kind, source=100) for s in sources}
    place = {s: i for i, s in enumerate(sorted(scores, key=lambda s: (-scores[s], s)), 1)}
    return spark.createDataFrame([(r.source, r.d_a, r["rank"], float(scores[r.source]), place[r.source]) for r in got], "source string, d_a double, predicted int, f double, measured int")


def cross_domain(spark, sim, near, far, target, kinds=("lr", "rf"), sizes=(10,)) -> DataFrame:
    """A source of the target's own domain beside one of another."""
    tasks = [Task(sim, s, target) for s in (near, far)]
    return _table(spark, [task.row("cross_domain", "source_only", kind, size, source=size) for task in tasks for kind in kinds for size in sizes])


def adversarial(sim: DataFrame, names=(SOURCE, TARGET, SECOND)) -> DataFrame:
    """The pairs of some datasets cut into two that differ as much as can be: datasets half1 and half2."""
    rows = sim.where(F.col("dataset").isin(list(names)))
    return R.adversarial_split(rows).select(F.concat(F.lit("half"), F.col("half").cast("string")).alias("dataset"), "id_l", "id_r", "y", "x")


def negative(spark, halves, kinds=("lr",), sizes=(1, 5, 10, 50)) -> DataFrame:
    """Weighted beside naive transfer between adversarial halves."""
    task = Task(halves, "half1", "half2")
    return _table(spark, [task.row("negative", a, kind, size, source=size) for kind in kinds for size in sizes for a in ("source_only", "weighted")])


def encoder_ablation(spark, sf_dir, kind="lr") -> DataFrame:
    """F of naive transfer by encoder: weighting, treatment of unknown tokens, pair operation."""
    rows = []
    encoders = [("mean", "ignore", "diff", True), ("sif", "ignore", "diff", True), ("sif", "random", "diff", True), ("sif", "context", "diff", True), ("sif", "context", "product", True), ("sif", "context", "diff", False)]
    for weighting, policy, op, component in encoders:
        # Pairs of the two datasets only, one encoder's on disk at a time.
        sim = settle(pair_table(spark, sf_dir, op, WIDTH, weighting, policy, (SOURCE, TARGET), component), "similarity")
        name, *rest = Task(sim, SOURCE, TARGET, keep=False).row("encoder", "source_only", kind, 100, source=100)
        rows.append((f"{name} {weighting} {policy} {op}" + ("" if component else " without component"), *rest))
        release(sim)
    return _table(spark, rows)


def balance_ablation(spark, sim, kind="lr") -> DataFrame:
    """F of pooled training under each way of balancing classes and datasets."""
    task = Task(sim, SOURCE, TARGET)
    columns = ["key", "x", "y"]
    source, labelled = _drawn(sim, SOURCE).select(*columns), task.target.where("h < 70").select(*columns)
    weigh = lambda t: t.withColumn("w", F.lit(1.0))
    n = labelled.count()
    some = L.importance_sample(T.origin_weights(source, task.free(100, 10), CLIP, "lr"), L.cap(1 << 62, n)).select(*columns)
    top = L.top_weight(T.origin_weights(source, task.free(100, 10), CLIP, "lr"), L.cap(1 << 62, n)).select(*columns)
    tables = {
        "as it is": weigh(source.unionByName(labelled)),
        "1:3": weigh(task._balanced(source).unionByName(task._balanced(labelled))),
        "class weights": L.class_weights(source.unionByName(labelled)),
        "dataset weights": L.dataset_weights(source, labelled),
        "replicated at random": weigh(source.unionByName(L.replicate_random(labelled, source.count()).select(*columns))),
        "replicated": weigh(source.unionByName(L.replicate_fixed(labelled, max(1, source.count() // max(1, n))).select(*columns))),
        "importance sample": weigh(some.unionByName(labelled)),
        "top weights": weigh(top.unionByName(labelled)),
    }
    from ertransfer.operators.classifiers import fit

    rows = [(f"balance {name}", SOURCE, TARGET, kind, "pooled", 10, float(M.measures(fit(kind, t.select("x", "y", "w")).score(task.test)).first().f)) for name, t in tables.items()]
    return _table(spark, rows)


def improvements(results: DataFrame, baselines: list[str]) -> DataFrame:
    """Improvement over the best baseline of result rows."""
    keyed = results.select(F.concat_ws(">", "source", "target").alias("task"), "classifier", "size", "algorithm", "f")
    return M.improvement(keyed, baselines).where(~F.col("algorithm").isin(baselines))


#: Source and target of the sweeps, on the dirty-copy tables and on the documents.
PART_PAIRS, TEXT_PAIRS = [(SOURCE, TARGET), ("customer", TARGET)], [("en", "fr"), ("en", "de")]


def sweeps(spark: SparkSession, sf_dir: str) -> dict:
    """The full experiments, by name."""
    sim, text = (lambda: similarity(spark, sf_dir)), (lambda: text_similarity(spark, sf_dir))
    return {
        "baselines": lambda: baselines(spark, sim(), [(SOURCE, TARGET)]),
        "baselines_adversarial": lambda: baselines(spark, adversarial(sim()), [("half1", "half2")], ("lr", "svm", "rf"), (10, 100)),
        "scenario_1": lambda: scenario_1(spark, sim(), PART_PAIRS[:1]),
        "scenario_1_text": lambda: scenario_1(spark, text(), TEXT_PAIRS, ("lr", "rf")),
        "scenario_2": lambda: scenario_2(spark, sim(), PART_PAIRS[:1]),
        "scenario_2_text": lambda: scenario_2(spark, text(), TEXT_PAIRS, ("lr", "rf")),
        "scenario_3": lambda: scenario_3(spark, sim(), PART_PAIRS[:1]),
        "dimensions": lambda: dimensions(spark, lambda w: similarity(spark, sf_dir, width=w), (SOURCE, TARGET)),
        "several_sources": lambda: several_sources(spark, sim(), (SOURCE, SECOND), TARGET),
        "ranking": lambda: ranking(spark, sim(), (SOURCE, SECOND, "customer", "supplier"), TARGET),
        "cross_domain": lambda: cross_domain(spark, adversarial(sim()).unionByName(sim().where("dataset = 'customer'")), "half1", "customer", "half2"),
        "negative": lambda: negative(spark, adversarial(sim())),
        "encoder": lambda: encoder_ablation(spark, sf_dir),
        "balance": lambda: balance_ablation(spark, sim()),
    }


def main(argv: list[str]) -> None:
    from ertransfer.session import local_session

    sf_dir = argv[0] if argv else "/root/testdata/sf0.01"
    spark = local_session(8)
    spark.sparkContext.setLogLevel("ERROR")
    for name, run in sweeps(spark, sf_dir).items():
        if not argv[1:] or name in argv[1:]:
            for row in run().collect():
                print(json.dumps({"sweep": name} | row.asDict()), flush=True)


if __name__ == "__main__":
    main(sys.argv[1:])
