"""Candidate pairs between two sides of tuples, and how good they are.

Sides are rows (dataset, id, doc, block); candidates are rows (dataset, id_l, id_r, y), y 1 where the ids agree.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ertransfer.durable import settle
from ertransfer.operators import texts
from ertransfer.operators.encoding import words


def once(value: Column, use) -> Column:
    """``use(value)`` with the value worked out once a row: inside lambdas a plain column would be worked out again and again."""
    return F.transform(F.array(value), use)[0]


def _out(both: DataFrame) -> DataFrame:
    return both.select("dataset", "id_l", "id_r", (F.col("id_l") == F.col("id_r")).cast("int").alias("y"))


def by_key(left: DataFrame, right: DataFrame, most: int | None = None) -> DataFrame:
    """Pairs that share a block; with ``most``, larger blocks are purged. Null keys match nothing."""
    if most is None:
        l, r = (t.select("dataset", "block", F.col("id").alias(name)) for t, name in ((left, "id_l"), (right, "id_r")))  # noqa: E741
        return _out(l.join(r, ["dataset", "block"]))
    n = lambda t, name: t.groupBy("dataset", "block").agg(F.count("*").alias(name))
    fine = n(left, "nl").join(n(right, "nr"), ["dataset", "block"]).where(F.col("nl") * F.col("nr") <= most).select("dataset", "block")
    l = left.select("dataset", "block", F.col("id").alias("id_l")).join(fine, ["dataset", "block"])  # noqa: E741
    return _out(l.join(right.select("dataset", "block", F.col("id").alias("id_r")), ["dataset", "block"]))


def key_counts(left: DataFrame, right: DataFrame) -> DataFrame:
    """Rows (dataset, pairs, matches) of :func:`by_key` from the sizes of its blocks: no pair is made but the matches."""
    n = lambda t, name: t.groupBy("dataset", "block").agg(F.count("*").alias(name))
    sizes = n(left, "nl").join(n(right, "nr"), ["dataset", "block"]).groupBy("dataset").agg(F.sum(F.col("nl") * F.col("nr")).alias("pairs"))
    true = left.select("dataset", "block", "id").join(right.select("dataset", "block", "id"), ["dataset", "block", "id"]).groupBy("dataset").agg(F.count("*").alias("matches"))
    return sizes.join(true, "dataset", "left").fillna(0, ["matches"])


def exhaustive(left: DataFrame, right: DataFrame, cells: int = 16) -> DataFrame:
    """All pairs of a dataset, dealt by hash over ``cells`` squared parts, so that no task meets more than its share."""
    every = F.explode(F.sequence(F.lit(0), F.lit(cells - 1)))
    own = F.pmod(F.xxhash64("id"), F.lit(cells)).cast("int")
    l = left.select("dataset", F.col("id").alias("id_l"), own.alias("cl"), every.alias("cr"))  # noqa: E741
    r = right.select("dataset", F.col("id").alias("id_r"), every.alias("cl"), own.alias("cr"))
    return _out(l.join(r, ["dataset", "cl", "cr"]))


def by_neighbourhood(left: DataFrame, right: DataFrame, reach: int = 10) -> DataFrame:
    """Pairs of one block whose texts lie within ``reach`` places of each other in the sorted block.

    Their number grows with the table, whatever the blocks' sizes: offsets make the range join an equi-join.
    """
    side = lambda t, s: t.where("block is not null").select("dataset", "block", "id", "doc", F.lit(s).alias("side"))
    order = Window.partitionBy("dataset", "block").orderBy("doc", "side", "id")
    both = side(left, 0).union(side(right, 1)).withColumn("at", F.row_number().over(order))
    l = both.where("side = 0").select("dataset", "block", F.col("id").alias("id_l"), F.explode(F.transform(F.sequence(F.lit(-reach), F.lit(reach)), lambda k: F.col("at") + k)).alias("at"))  # noqa: E741
    return _out(l.join(both.where("side = 1").select("dataset", "block", "at", F.col("id").alias("id_r")), ["dataset", "block", "at"]))


def by_rare_token(left: DataFrame, right: DataFrame, most: int = 20) -> DataFrame:
    """Pairs that share a token held by at most ``most`` tuples of both sides together."""
    long = lambda t: t.select("dataset", "id", F.explode(F.array_distinct(words("doc"))).alias("token"))
    l, r = long(left), long(right)  # noqa: E741
    rare = l.union(r).groupBy("dataset", "token").agg(F.count("*").alias("n")).where(F.col("n") <= most).select("dataset", "token")
    both = l.join(rare, ["dataset", "token"]).withColumnRenamed("id", "id_l").join(r.withColumnRenamed("id", "id_r"), ["dataset", "token"])
    return _out(both.select("dataset", "id_l", "id_r").distinct())


def by_minhash(left: DataFrame, right: DataFrame, bands: int = 12, rows: int = 3, most: int = 40_000) -> DataFrame:
    """Pairs whose token sets agree on a band of ``rows`` least hashes; bands of more than ``most`` pairs are purged."""

    def keys(tokens: Column) -> Column:
        least = lambda j: F.array_min(F.transform(tokens, lambda x: F.xxhash64(F.lit(j), x)))
        return F.array(*[F.xxhash64(F.lit(b), *[least(b * rows + j) for j in range(rows)]).cast("string") for b in range(bands)])

    def banded(t: DataFrame) -> DataFrame:
        some = t.select("dataset", "id", "doc", once(F.array_distinct(words("doc")), lambda w: F.when(F.size(w) > 0, keys(w))).alias("keys"))
        return some.select("dataset", "id", "doc", F.explode("keys").alias("block"))

    return by_key(banded(left), banded(right), most).distinct()


def same_language_copies(documents: DataFrame, most: int = 40, least: float = 0.5, grams: int = 3) -> DataFrame:
    """Rows (dataset, id_l, id_r, y, jaccard) of documents of one language that share a rare word 3-gram.

    ``dataset`` is the language; y is 1 from ``least`` Jaccard of distinct word 3-grams on. A 3-gram held by more than
    ``most`` documents brings no pair about, but counts in the similarity; shorter documents are one gram. Grams are 64-bit hashes.

    Grams that the same documents hold are one code with their number. Cells of two groups of documents get the documents'
    codes and work out their pairs (:mod:`texts`): no pair is shuffled, and no table is broadcast.
    """
    characters = documents.agg(F.sum(F.length("text"))).first()[0] or 0
    return texts.copies(texts.listed_texts(documents), characters, most, least, grams, settle)


def containing(documents: DataFrame, items: DataFrame) -> DataFrame:
    """Rows (doc_id, item_id) of documents whose words hold all words of an item in a row; found through its rarest word.

    ``items`` are few beside the documents, but are joined, not broadcast.
    """
    pad = lambda c: F.concat(F.lit(" "), F.concat_ws(" ", c), F.lit(" "))
    d = documents.select("doc_id", words("text").alias("w")).where(F.size("w") > 0)
    i = items.select("item_id", words("text").alias("w")).where(F.size("w") > 0)
    long = d.select("doc_id", F.explode(F.array_distinct("w")).alias("token"))
    often = long.groupBy("token").agg(F.count("*").alias("n"))
    each = i.select("item_id", F.explode(F.array_distinct("w")).alias("token")).join(often, "token", "left").fillna(0, ["n"])
    rarest = each.groupBy("item_id").agg(F.min(F.struct("n", "token")).alias("r")).select("item_id", F.col("r.token").alias("token"))
    met = long.join(rarest, "token").select("doc_id", "item_id")
    whole = met.join(d.select("doc_id", pad("w").alias("dt")), "doc_id").join(i.select("item_id", pad("w").alias("it")), "item_id")
    return whole.where(F.contains("dt", "it")).select("doc_id", "item_id").distinct()


def counted(pairs: DataFrame) -> DataFrame:
    """Rows (dataset, pairs, matches) of a blocking."""
    return pairs.groupBy("dataset").agg(F.count("*").alias("pairs"), F.sum("y").alias("matches"))


def quality(got: DataFrame, left: DataFrame, right: DataFrame) -> DataFrame:
    """Rows (dataset, pairs, matches, true_pairs, completeness, reduction) of a blocking's counts (dataset, pairs, matches)."""
    truth = left.join(right.select("dataset", "id"), ["dataset", "id"], "left_semi").groupBy("dataset").agg(F.count("*").alias("true_pairs"))
    sizes = left.groupBy("dataset").agg(F.count("*").alias("nl")).join(right.groupBy("dataset").agg(F.count("*").alias("nr")), "dataset")
    both = sizes.join(truth, "dataset").join(got, "dataset", "left").fillna(0, ["pairs", "matches"])
    return both.select("dataset", "pairs", "matches", "true_pairs", F.round(F.col("matches") / F.col("true_pairs"), 6).alias("completeness"), F.round(1 - F.col("pairs") / (F.col("nl") * F.col("nr")), 6).alias("reduction"))
