"""From tuples of any schema to vectors of one space.

Vectors are held as arrays of longs, in millionths: sums are exact whatever their order.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ertransfer.functions.portable import h32
from ertransfer.functions.vectors import MICRO, sif_weight, zeros

#: Width of the vectors that ``embeddings`` holds.
WIDTH = 64


def tuple_document(df: DataFrame, dataset: str, id_col: str, attributes: list, block: list) -> DataFrame:
    """Rows (dataset, id, doc, block): attribute values joined to one text, and the blocking key."""
    return df.select(F.lit(dataset).alias("dataset"), F.col(id_col).cast("long").alias("id"), F.concat_ws(" ", *attributes).alias("doc"), F.concat_ws("|", *block).alias("block"))


def words(text: Column | str) -> Column:
    """Lower-cased runs of letters and digits; a null text has none."""
    return F.filter(F.split(F.lower(text), r"[^\p{L}\p{N}]+"), lambda x: x != "")


def tokenize(tuples: DataFrame) -> DataFrame:
    """Rows (dataset, id, pos, token)."""
    return tuples.select("dataset", "id", F.posexplode(words("doc")).alias("pos", "token"))


def dirty(tokens: DataFrame, percent: int | dict[str, int] = 10) -> DataFrame:
    """A copy of ``tokens`` without those that a hash picks; the share may differ by dataset (10 where not named)."""
    limit = F.lit(percent if isinstance(percent, int) else 10)
    for name, share in ({} if isinstance(percent, int) else percent).items():
        limit = F.when(F.col("dataset") == name, share).otherwise(limit)
    return tokens.where(h32("d:", F.col("dataset"), ":", F.col("id"), ":", F.col("pos")) % 100 >= limit)


def token_frequency(tokens: DataFrame) -> DataFrame:
    """Rows (token, n, p): occurrences in the scope of ``tokens`` and their share."""
    counts = tokens.groupBy("token").agg(F.count("*").alias("n"))
    total = counts.agg(F.sum("n").alias("total"))  # one row
    return counts.join(F.broadcast(total)).select("token", "n", (F.col("n") / F.col("total")).alias("p"))


# --- dictionaries ------------------------------------------------------------------------------------------------


def hashed_dictionary(vocabulary: DataFrame, embeddings: DataFrame, width: int = WIDTH, unknown_mod: int = 10) -> DataFrame:
    """Rows (token, vec) for the known tokens of ``vocabulary``: the scaled sum of two rows of ``embeddings``.

    A token's hash names two ids up to the greatest of ``embeddings``; tokens whose rows do not exist are unknown.
    """
    n = embeddings.agg(F.max("vec_id") + 1).first()[0] or 1
    rows = embeddings.select(F.col("vec_id").alias("k"), F.slice("embedding", 1, width).cast("array<double>").alias("v"))
    token = F.col("token")
    keyed = vocabulary.select("token").distinct().where(h32("oov:", token) % unknown_mod != 0).select("token", (h32("a:", token) % n).alias("ka"), (h32("b:", token) % n).alias("kb"))
    pairs = keyed.join(rows.withColumnsRenamed({"k": "ka", "v": "va"}), "ka").join(rows.withColumnsRenamed({"k": "kb", "v": "vb"}), "kb")
    return pairs.select("token", F.zip_with("va", "vb", lambda a, b: F.round((a + b) / F.sqrt(F.lit(2.0)) * MICRO).cast("long")).alias("vec"))


def trained_dictionary(tokens: DataFrame, width: int = 50, min_count: int = 5, seed: int = 1) -> DataFrame:
    """Rows (token, vec) trained on ``tokens`` from nothing, one tuple a sentence."""
    from pyspark.ml.feature import Word2Vec
    from pyspark.ml.functions import vector_to_array

    sentences = tokens.groupBy("dataset", "id").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "token"))), lambda t: t["token"]).alias("words"))
    model = Word2Vec(vectorSize=width, minCount=min_count, inputCol="words", seed=seed, maxIter=1, numPartitions=4).fit(sentences)
    return model.getVectors().select(F.col("word").alias("token"), F.transform(vector_to_array("vector"), lambda v: F.round(v * MICRO).cast("long")).alias("vec"))


def adapted_dictionary(tokens: DataFrame, dictionary: DataFrame, width: int = WIDTH, share: int = 50, half: int = 5) -> DataFrame:
    """One pass of re-training on a domain: each vector moves ``share`` percent of the way to the mean of its contexts.

    Spark's trainer cannot start from given vectors; moving towards the contexts stands in for that.
    """
    near = context_vectors(tokens, dictionary, width, half, known=True).withColumnRenamed("vec", "near")
    moved = F.zip_with("vec", "near", lambda v, c: F.round((v * (100 - share) + c * share) / 100).cast("long"))
    return dictionary.join(near, "token", "left").select("token", F.coalesce(moved, "vec").alias("vec"))


# --- unknown tokens ----------------------------------------------------------------------------------------------


def unknown_tokens(vocabulary: DataFrame, dictionary: DataFrame) -> DataFrame:
    """Distinct tokens without a vector."""
    return vocabulary.select("token").distinct().join(dictionary, "token", "left_anti")


def context_vectors(tokens: DataFrame, dictionary: DataFrame, width: int = WIDTH, half: int = 5, only: DataFrame | None = None, known: bool = False) -> DataFrame:
    """Rows (token, vec): the mean over a token's occurrences of the mean of its known neighbours' vectors.

    Unknown tokens are asked for, or with ``known`` the known ones; ``only`` restricts them to its tokens, while
    contexts still come from all of ``tokens``. Occurrences without known neighbours do not count.
    """
    marked = tokens.join(dictionary, "token", "left")
    order = Window.partitionBy("dataset", "id").orderBy("pos")
    near = order.rowsBetween(-half, half)
    sums = [F.sum(F.col("vec")[i]).over(near).alias(f"s{i}") for i in range(width)]
    around = marked.select("token", "vec", F.count("vec").over(near).alias("m"), *sums)
    if known:
        around = around.where("vec is not null and m > 1").withColumn("m", F.col("m") - 1)
        around = around.withColumns({f"s{i}": F.col(f"s{i}") - F.col("vec")[i] for i in range(width)})
    else:
        around = around.where("vec is null and m > 0")
    if only is not None:
        around = around.join(only.select("token").distinct(), "token", "left_semi")
    parts = [F.sum(F.round(F.col(f"s{i}") / F.col("m")).cast("long")).alias(f"s{i}") for i in range(width)]
    each = around.groupBy("token").agg(F.count("*").alias("n"), *parts)
    return each.select("token", F.array(*[F.round(F.col(f"s{i}") / F.col("n")).cast("long") for i in range(width)]).alias("vec"))


def random_vectors(unknown: DataFrame, width: int = WIDTH, seed: int = 1) -> DataFrame:
    """Rows (token, vec): components from -1 to 1 drawn by the hash of seed, token and place."""
    draw = lambda i: (h32(f"r:{seed}:", F.col("token"), ":", i) % (2 * MICRO + 1)) - MICRO
    return unknown.select("token", F.transform(F.sequence(F.lit(0), F.lit(width - 1)), draw).alias("vec"))


def subword_vectors(unknown: DataFrame, width: int = WIDTH, low: int = 3, high: int = 6, seed: int = 2) -> DataFrame:
    """Rows (token, vec): the mean of the vectors of the character pieces of the token with its borders marked."""
    marked = F.concat(F.lit("<"), "token", F.lit(">"))
    pieces = F.flatten(F.transform(F.sequence(F.lit(low), F.lit(high)), lambda n: F.when(F.length(marked) >= n, F.transform(F.sequence(F.lit(1), F.length(marked) - n + 1), lambda i: F.substr(marked, i, n))).otherwise(F.array().cast("array<string>"))))
    each = unknown.select("token", F.explode(pieces).alias("piece"))
    draw = lambda i: (h32(f"r:{seed}:", F.col("piece"), ":", i) % (2 * MICRO + 1)) - MICRO
    long = each.select("token", "piece", F.posexplode(F.transform(F.sequence(F.lit(0), F.lit(width - 1)), draw)).alias("i", "v"))
    means = long.groupBy("token", "i").agg(F.round(F.avg("v")).cast("long").alias("v"))
    return means.groupBy("token").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "v"))), lambda t: t["v"]).alias("vec"))


def extended_dictionary(tokens: DataFrame, dictionary: DataFrame, policy: str = "context", width: int = WIDTH, rare_below: int = 5, half: int = 5, trained: DataFrame | None = None, only: DataFrame | None = None) -> DataFrame:
    """``dictionary`` with vectors for unknown tokens: ``ignore``, ``random``, ``subword``, ``context``, or ``rare``.

    ``rare`` gives unknown tokens of fewer than ``rare_below`` occurrences their contexts, more frequent ones the vector
    that ``trained`` holds, and contexts again where it holds none.
    """
    if policy == "ignore":
        return dictionary
    if policy in ("random", "subword"):
        make = random_vectors if policy == "random" else subword_vectors
        return dictionary.union(make(unknown_tokens(tokens if only is None else only, dictionary), width))
    found = context_vectors(tokens, dictionary, width, half, only)
    if policy == "context":
        return dictionary.union(found)
    if policy != "rare" or trained is None:
        raise ValueError(f"unknown policy {policy}, or no trained vectors for the rare rule")
    counts = tokens.groupBy("token").agg(F.count("*").alias("n"))
    mixed = found.join(counts, "token").join(trained.withColumnRenamed("vec", "own"), "token", "left")
    return dictionary.union(mixed.select("token", F.when(F.col("n") < rare_below, F.col("vec")).otherwise(F.coalesce("own", "vec")).alias("vec")))


# --- whole tuples in a task -------------------------------------------------------------------------------------

#: Dictionaries of at most this many tokens travel to the tasks; larger ones are joined.
CARRIED = 200_000


def listed(tuples: DataFrame) -> DataFrame:
    """Rows (dataset, id, block, w) of the tuples that have tokens, w being their tokens in order."""
    return tuples.select("dataset", "id", "block", words("doc").alias("w")).where(F.size("w") > 0)


def dirty_listed(lists: DataFrame, percent: dict[str, int]) -> DataFrame:
    """:func:`dirty` of the tuples that :func:`listed` gives; those left without tokens go."""
    limit = F.lit(10)
    for name, share in percent.items():
        limit = F.when(F.col("dataset") == name, share).otherwise(limit)
    kept = F.filter("w", lambda w, i: h32("d:", F.col("dataset"), ":", F.col("id"), ":", i) % 100 >= limit)
    return lists.withColumn("w", kept).where(F.size("w") > 0)


class Carried:
    """A dictionary in the tasks: ``codes`` of tokens (-1: no vector) and their ``rows``, the last being zero."""

    def __init__(self, spark, table: pa.Table, weight: str | None = None):
        rows = np.vstack([np.asarray(table["vec"].combine_chunks().flatten(), np.int64).reshape(table.num_rows, -1)]) if table.num_rows else np.zeros((0, 1), np.int64)
        if weight:
            rows = rows * np.asarray(table[weight], np.int64)[:, None]
        self.shared = spark.sparkContext.broadcast((table["token"].to_pylist(), np.vstack([rows, np.zeros((1, rows.shape[1]), np.int64)])))

    def opened(self):
        """(token to code, rows) in a task."""
        tokens, rows = self.shared.value
        return {t: i for i, t in enumerate(tokens)}, rows


def carried(dictionary: DataFrame, frequency: DataFrame | None = None, a: float = 1e-4) -> Carried | None:
    """``dictionary`` for the tasks, weighted by a / (a + p) where ``frequency`` is given; none if it is too large."""
    table = dictionary
    if frequency is not None:
        table = dictionary.join(frequency.select("token", sif_weight(F.col("p"), a).alias("weight")), "token")
    table = table.limit(CARRIED + 1).toArrow()
    return Carried(dictionary.sparkSession, table, None if frequency is None else "weight") if table.num_rows <= CARRIED else None


def _half_up(x: np.ndarray) -> np.ndarray:
    """Rounded as SQL does: halves away from zero."""
    return (np.sign(x) * np.floor(np.abs(x) + 0.5)).astype(np.int64)


def _codes(column: pa.ListArray, of: dict) -> tuple[np.ndarray, np.ndarray]:
    """(codes of all tokens of a column of lists, where each list starts, and the end)."""
    starts = np.asarray(column.offsets, np.int64)
    flat = column.flatten().to_pylist()
    return np.fromiter((of.get(t, -1) for t in flat), np.int64, len(flat)), starts - starts[0]


def contexts_of_listed(lists: DataFrame, dictionary: Carried, width: int = WIDTH, half: int = 5) -> DataFrame:
    """What :func:`context_vectors` gives for unknown tokens, from whole tuples: no token's vector is shuffled."""

    def found(batches):
        of, rows = dictionary.opened()
        sums: dict = {}
        for batch in batches:
            column = batch.column(0)
            flat = column.flatten()
            codes, starts = _codes(column, of)
            lengths = np.diff(starts)
            first, end = np.repeat(starts[:-1], lengths), np.repeat(starts[1:], lengths)
            unknown = np.flatnonzero(codes < 0)
            for some in np.array_split(unknown, len(unknown) // 8192 + 1):
                total, m = np.zeros((len(some), width), np.int64), np.zeros(len(some), np.int64)
                for step in [k for k in range(-half, half + 1) if k]:
                    at = some + step
                    inside = (at >= first[some]) & (at < end[some])
                    code = np.where(inside, codes[np.clip(at, 0, max(0, len(codes) - 1))], -1)
                    total += rows[code]
                    m += code >= 0
                some, total, m = some[m > 0], total[m > 0], m[m > 0]
                if not len(some):
                    continue
                names, place = np.unique(np.array(flat.take(pa.array(some)).to_pylist(), object), return_inverse=True)
                each = np.zeros((len(names), width + 1), np.int64)
                np.add.at(each, place, np.column_stack([_half_up(total / m[:, None]), np.ones(len(m), np.int64)]))
                for name, row in zip(names, each):
                    sums[name] = sums[name] + row if name in sums else row
            if len(sums) > 50_000:
                yield out(sums)
                sums = {}
        yield out(sums)

    def out(sums):
        return pa.RecordBatch.from_arrays([pa.array(list(sums), pa.string()), _lists(np.array(list(sums.values()), np.int64).reshape(len(sums), width + 1))], ["token", "s"])

    parts = lists.select("w").mapInArrow(found, "token string, s array<long>")
    each = parts.groupBy("token").agg(F.sum(F.col("s")[width]).alias("n"), *[F.sum(F.col("s")[i]).alias(f"s{i}") for i in range(width)])
    return each.select("token", F.array(*[F.round(F.col(f"s{i}") / F.col("n")).cast("long") for i in range(width)]).alias("vec"))


def _means(column: pa.ListArray, of: dict, rows: np.ndarray, by: int, without: np.ndarray | None = None) -> np.ndarray:
    """The vectors of a column of token lists, less their projection on the direction ``without``."""
    codes, starts = _codes(column, of)
    if not len(codes):
        return np.zeros((0, rows.shape[1]), np.int64)
    x = _half_up(np.add.reduceat(rows[codes], starts[:-1], axis=0) / np.diff(starts)[:, None] / by)
    if without is None:
        return x
    along = np.zeros(len(x))
    for i, v in enumerate(without):
        along += x[:, i] * v
    return _half_up(x - along[:, None] * without)


def _lists(x: np.ndarray) -> pa.ListArray:
    return pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1, dtype=np.int32) * x.shape[1]), pa.array(x.reshape(-1)))


def vectors_of_listed(lists: DataFrame, dictionary: Carried, by: int = MICRO) -> DataFrame:
    """Rows (x) of listed tuples, as :func:`encode` gives them; map-only."""

    def made(batches):
        of, rows = dictionary.opened()
        for batch in batches:
            yield pa.RecordBatch.from_arrays([_lists(_means(batch.column(0), of, rows, by))], ["x"])

    return lists.select("w").mapInArrow(made, "x array<long>")


def neighbour_vectors(left: DataFrame, right: DataFrame, dictionary: Carried, reach: int, op: str = "diff", width: int = WIDTH, by: int = MICRO, without: np.ndarray | None = None) -> DataFrame:
    """Rows (dataset, id_l, id_r, y, x) of the pairs that sorted neighbourhood finds between two listed sides.

    The tuples, not their vectors, are sorted inside their blocks; a task makes each tuple's vector once and pairs it
    with the ``reach`` before it. ``by`` is the unit of the dictionary's weights, ``without`` a direction to remove.
    """
    text = F.array_join("w", " ").alias("doc")
    side = lambda t, s: t.where("block is not null").select("dataset", "block", text, F.lit(s).alias("side"), "id", "w")
    order = ["dataset", "block", "doc", "side", "id"]
    both = side(left, 0).union(side(right, 1)).repartition("dataset", "block").sortWithinPartitions(*order)

    def paired_up(batches):
        of, rows = dictionary.opened()
        before = None
        for batch in batches:
            now = {"name": np.array(batch.column("dataset").to_pylist(), object), "block": np.array(batch.column("block").to_pylist(), object), "side": np.asarray(batch.column("side")), "id": np.asarray(batch.column("id")), "x": _means(batch.column("w"), of, rows, by, without)}
            old = 0 if before is None else len(before["id"])
            every = now if before is None else {k: np.concatenate([before[k], now[k]]) for k in now}
            for step in range(1, reach + 1):
                b = np.arange(max(old, step), len(every["id"]))
                a = b - step
                met = (every["side"][a] != every["side"][b]) & (every["block"][a] == every["block"][b]) & (every["name"][a] == every["name"][b])
                a, b = a[met], b[met]
                if not len(a):
                    continue
                l, r = np.where(every["side"][a] == 0, a, b), np.where(every["side"][a] == 0, b, a)  # noqa: E741
                u, v = every["x"][l], every["x"][r]
                x = np.abs(u - v) if op == "diff" else np.abs(_half_up((u * v) / MICRO))
                il, ir = every["id"][l], every["id"][r]
                yield pa.RecordBatch.from_arrays([pa.array(every["name"][l], pa.string()), pa.array(il), pa.array(ir), pa.array((il == ir).astype(np.int32)), _lists(x)], ["dataset", "id_l", "id_r", "y", "x"])
            before = {k: v[-reach:] for k, v in every.items()}

    if op not in ("diff", "product"):
        raise KeyError(op)
    return both.mapInArrow(paired_up, "dataset string, id_l long, id_r long, y int, x array<long>")


# --- tuple vectors -----------------------------------------------------------------------------------------------


def encode(tokens: DataFrame, dictionary: DataFrame, width: int = WIDTH, frequency: DataFrame | None = None, a: float = 1e-4, known_only: bool = False) -> DataFrame:
    """Rows (dataset, id, n_tokens, x): mean of the token vectors, with weight a / (a + p) where ``frequency`` is given.

    The divisor counts all tokens, or with ``known_only`` those with a vector; unknown ones add nothing, so a tuple of
    unknown tokens alone lies at the origin. Repeated tokens of a tuple are counted before they meet their vectors.
    """
    found = tokens.groupBy("dataset", "id", "token").agg(F.count("*").alias("times")).join(dictionary, "token", "left")
    if frequency is not None:
        found = found.join(frequency.select("token", sif_weight(F.col("p"), a).alias("w")), "token", "left")
        value, by = lambda i: F.col("times") * F.col("w") * F.col("vec")[i], MICRO
    else:
        value, by = lambda i: F.col("times") * F.col("vec")[i], 1
    sums = [F.coalesce(F.sum(value(i)), F.lit(0)).alias(f"s{i}") for i in range(width)]
    counted = F.when(F.col("vec").isNotNull(), F.col("times")).otherwise(0) if known_only else F.col("times")
    total = found.groupBy("dataset", "id").agg(F.sum(counted).alias("n_tokens"), *sums)
    n = F.greatest("n_tokens", F.lit(1))
    return total.select("dataset", "id", "n_tokens", F.array(*[F.round(F.col(f"s{i}") / n / by).cast("long") for i in range(width)]).alias("x"))


def common_component(encoded: DataFrame, width: int = WIDTH, center: bool = False) -> np.ndarray:
    """The first principal direction of the vectors: partial width x width sums of the map tasks, added up by Spark."""

    def gram(batches):
        total, mean, n = np.zeros((width, width)), np.zeros(width), 0
        for batch in batches:
            column = batch.column("x")
            x = column.flatten().to_numpy(zero_copy_only=False).reshape(len(column), width) / MICRO
            total, mean, n = total + x.T @ x, mean + x.sum(0), n + len(x)
        out = np.concatenate([total.ravel(), mean, [n]])
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(out), dtype=np.int32)), pa.array(out)], ["i", "v"])

    parts = encoded.select("x").mapInArrow(gram, "i int, v double").groupBy("i").agg(F.sum("v").alias("v"))
    flat = np.zeros(width * width + width + 1)
    for r in parts.collect():  # width squared numbers
        flat[r.i] = r.v
    total, mean, n = flat[: width * width].reshape(width, width), flat[width * width : -1], flat[-1]
    if center and n:
        total = total - np.outer(mean, mean) / n
    return np.linalg.eigh(total)[1][:, -1]


def remove_common_component(encoded: DataFrame, width: int = WIDTH, center: bool = False) -> tuple[DataFrame, np.ndarray]:
    """(``encoded`` without its projection on the first principal direction, that direction); the second step is map-only."""
    u = common_component(encoded, width, center)
    lit = F.array(*[F.lit(float(v)) for v in u])
    along = F.aggregate(F.zip_with("x", lit, lambda x, w: x * w), F.lit(0.0), lambda acc, v: acc + v)
    spread = encoded.withColumn("_along", along)
    return spread.withColumn("x", F.zip_with("x", lit, lambda x, w: F.round(x - F.col("_along") * w).cast("long"))).drop("_along"), u


def encode_tf(tokens: DataFrame, idf: DataFrame | None = None) -> DataFrame:
    """Rows (dataset, id, token, v): sparse term frequencies, times the inverse document frequency where ``idf`` is given."""
    tf = tokens.groupBy("dataset", "id", "token").agg(F.count("*").alias("n"))
    return tf.withColumn("v", F.col("n").cast("double")) if idf is None else tf.join(idf, "token").withColumn("v", F.col("n") * F.col("idf"))


def inverse_document_frequency(tokens: DataFrame) -> DataFrame:
    """Rows (token, idf): ln((1 + N) / (1 + df)) + 1 over the tuples in scope."""
    places = tokens.select("dataset", "id", "token").distinct()
    n = places.select("dataset", "id").distinct().agg(F.count("*").alias("total"))  # one row
    return places.groupBy("token").agg(F.count("*").alias("df")).join(F.broadcast(n)).select("token", (F.log((1.0 + F.col("total")) / (1.0 + F.col("df"))) + 1).alias("idf"))


def sparse_cosine(pairs: DataFrame, left: DataFrame, right: DataFrame) -> DataFrame:
    """``pairs`` (dataset, id_l, id_r, y) with cosine of the sparse vectors (dataset, id, token, v) of both sides."""
    size = lambda t, name: t.groupBy("dataset", F.col("id").alias(name)).agg(F.sqrt(F.sum(F.col("v") * F.col("v"))).alias(f"n_{name}"))
    l = left.select("dataset", F.col("id").alias("id_l"), "token", F.col("v").alias("vl"))  # noqa: E741
    r = right.select("dataset", F.col("id").alias("id_r"), "token", F.col("v").alias("vr"))
    both = pairs.select("dataset", "id_l", "id_r").join(l, ["dataset", "id_l"]).join(r, ["dataset", "id_r", "token"])
    dots = both.groupBy("dataset", "id_l", "id_r").agg(F.sum(F.col("vl") * F.col("vr")).alias("dot"))
    out = pairs.join(dots, ["dataset", "id_l", "id_r"], "left").join(size(left, "id_l"), ["dataset", "id_l"], "left").join(size(right, "id_r"), ["dataset", "id_r"], "left")
    return out.select(*pairs.columns, F.coalesce(F.try_divide(F.col("dot"), F.col("n_id_l") * F.col("n_id_r")), F.lit(0.0)).alias("cosine"))


def pair_vectors(pairs: DataFrame, left: DataFrame, right: DataFrame, op: str = "diff", width: int = WIDTH) -> DataFrame:
    """``pairs`` (dataset, id_l, id_r, y) with x: the absolute difference or product of the two vectors, place by place.

    A tuple without tokens lies at the origin.
    """
    from ertransfer.functions import vectors as V

    how = {"diff": V.absdiff, "product": V.product}[op]
    return paired(pairs, left, right, width).select("dataset", "id_l", "id_r", "y", how("xl", "xr").alias("x"))


def paired(pairs: DataFrame, left: DataFrame, right: DataFrame, width: int = WIDTH) -> DataFrame:
    """``pairs`` with the vectors xl and xr of their sides."""
    l = left.select("dataset", F.col("id").alias("id_l"), F.col("x").alias("xl"))  # noqa: E741
    r = right.select("dataset", F.col("id").alias("id_r"), F.col("x").alias("xr"))
    both = pairs.join(l, ["dataset", "id_l"], "left").join(r, ["dataset", "id_r"], "left")
    return both.withColumns({"xl": F.coalesce("xl", zeros(width)), "xr": F.coalesce("xr", zeros(width))})
