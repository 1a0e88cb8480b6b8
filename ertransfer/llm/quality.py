"""Quality classification by co-training of two views.

One classifier sees the text's words, the other what can be told without reading: lengths, shares of character kinds,
repetition, language and source. Over a few rounds each names the unlabelled documents that it is sure of, and the
other learns from these as well. At the end each view's margin is calibrated on held-out labelled rows and the two
log odds are combined by a model fitted on the same rows.

The classifiers learn from at most ``sample`` labelled documents, chosen by a hash of the id, and from counts over all
unlabelled ones; scoring covers every document whole, in one map-only pass.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ertransfer.durable import release, settle
from ertransfer.llm.batches import text_pieces

#: Hashed words.
WIDTH = 1 << 20
WORD = re.compile(rb"[^\x00-\x40\x5B-\x60\x7B-\x7F]+")
CLASSES = np.zeros(256, np.int64)
for _lo, _hi, _kind in ((48, 58, 1), (65, 91, 2), (97, 123, 3), (9, 11, 4), (32, 33, 4), (128, 256, 5)):
    CLASSES[_lo:_hi] = _kind
BANDS = 12
META = 9 * BANDS + 128


def word_places(text: bytes) -> np.ndarray:
    """Places of the distinct lower-cased words, ascending."""
    return np.unique(np.array([xxhash.xxh32_intdigest(w) % WIDTH for w in set(WORD.findall(text.lower()))], np.int64))


def meta_places(text: bytes, lang: str | None, source: str | None) -> np.ndarray:
    """Places of the set features: each measure falls into one of its bands; language and source are hashed."""
    data = np.frombuffer(text, np.uint8)
    kinds = np.bincount(CLASSES[data], minlength=6) / max(1, len(data))
    lines = text.split(b"\n")
    words = max(1, len(text.split()))
    measures = [
        min(1.0, np.log1p(len(data)) / 14), *kinds[[0, 1, 2, 4, 5]] ** 0.5,
        len(set(lines)) / len(lines), min(1.0, len(data) / words / 20), min(1.0, len(lines) / words * 5) ** 0.5,
    ]
    places = [i * BANDS + min(BANDS - 1, int(x * BANDS)) for i, x in enumerate(measures)]
    places += [9 * BANDS + xxhash.xxh32_intdigest(f"{k}:{v}") % 128 for k, v in (("lang", lang), ("source", source))]
    return np.array(sorted(set(places)), np.int64)


def _sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def fit_logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1.0) -> np.ndarray:
    """Weights (the last for the constant) of a ridge logistic regression, by Newton steps that never go uphill."""
    x = np.concatenate([x, np.ones((len(x), 1))], 1)
    keep = np.full(x.shape[1], ridge)
    keep[-1] = 1e-6
    loss = lambda w: np.logaddexp(0, np.where(y > 0.5, -1, 1) * (x @ w)).sum() + (keep * w * w).sum() / 2
    w = np.zeros(x.shape[1])
    now = loss(w)
    for _ in range(40):
        p = _sigmoid(x @ w)
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + np.diag(keep + 1e-9), x.T @ (p - y) + keep * w)
        size = 1.0
        while size > 1e-4 and loss(w - size * step) > now:
            size /= 2
        w = w - size * step
        before, now = now, loss(w)
        if before - now < 1e-7:
            break
    return w


@dataclass
class Counts:
    """Pseudo-labels given to one view: documents of each kind that hold each place, and how many there are."""

    bad: np.ndarray
    good: np.ndarray
    n_bad: float
    n_good: float


def _evidence(rows: list[np.ndarray], y: np.ndarray, given: Counts | None, width: int) -> tuple[np.ndarray, list[np.ndarray]]:
    """Evidence of each place for a bad document, and each row's evidence learnt without the row itself.

    Pseudo-labels of a kind weigh at most as much together as the true labels of that kind, however many they are.
    """
    bad, good = np.zeros(width), np.zeros(width)
    for r, mark in zip(rows, y):
        (good if mark > 0.5 else bad)[r] += 1
    n1 = float(y.sum())
    n0 = len(y) - n1
    if given is not None:
        w0, w1 = min(1.0, n0 / max(1.0, given.n_bad)), min(1.0, n1 / max(1.0, given.n_good))
        bad, good, n0, n1 = bad + w0 * given.bad, good + w1 * given.good, n0 + w0 * given.n_bad, n1 + w1 * given.n_good
    ratio = lambda b, g: np.log((b + 0.3) / (n0 + 0.6)) - np.log((g + 0.3) / (n1 + 0.6))
    own = [ratio(np.maximum(0, bad[r] - (m <= 0.5)), np.maximum(0, good[r] - (m > 0.5))) * (bad[r] + good[r] > 1) for r, m in zip(rows, y)]
    return np.where(bad + good > 0, ratio(bad, good), 0).astype(np.float32), own


@dataclass
class TextView:
    """Evidence of each word for a bad document, and a logistic model over the strongest and the mean evidence."""

    evidence: np.ndarray
    weights: np.ndarray

    @staticmethod
    def _summary(e: np.ndarray) -> list[float]:
        top = np.sort(e)[::-1][:3] if e.size else np.zeros(0)
        return [*top, *[0.0] * (3 - len(top)), float(e.mean()) if e.size else 0.0, float(e.min()) if e.size else 0.0]

    @classmethod
    def learn(cls, rows: list[np.ndarray], y: np.ndarray, given: Counts | None = None) -> TextView:
        evidence, own = _evidence(rows, y, given, WIDTH)
        return cls(evidence, fit_logistic(np.array([cls._summary(e) for e in own]), y))

    def margin(self, rows: list[np.ndarray]) -> np.ndarray:
        x = np.array([self._summary(self.evidence[r]) for r in rows]).reshape(-1, 5)
        return x @ self.weights[:-1] + self.weights[-1]


@dataclass
class MetaView:
    """A logistic model over set features and the evidence of each measure."""

    evidence: np.ndarray
    weights: np.ndarray

    @staticmethod
    def _inputs(rows: list[np.ndarray], evidence: list[np.ndarray]) -> np.ndarray:
        x = np.zeros((len(rows), META + 10))
        for i, (r, e) in enumerate(zip(rows, evidence)):
            x[i, r] = 1
            np.add.at(x[i], META + np.minimum(9, r // BANDS), e)
        return x

    @classmethod
    def learn(cls, rows: list[np.ndarray], y: np.ndarray, given: Counts | None = None) -> MetaView:
        evidence, own = _evidence(rows, y, given, META)
        return cls(evidence, fit_logistic(cls._inputs(rows, own), y))

    def margin(self, rows: list[np.ndarray]) -> np.ndarray:
        return self._inputs(rows, [self.evidence[r] for r in rows]) @ self.weights[:-1] + self.weights[-1]


@dataclass
class CoTrained:
    """Two views, the calibration of their margins and the combination of the calibrated log odds."""

    views: tuple
    scales: list[np.ndarray]
    both: np.ndarray | None = None

    def odds(self, words: list[np.ndarray], meta: list[np.ndarray]) -> list[np.ndarray]:
        """Calibrated log odds of each view."""
        return [s[0] * v.margin(rows) + s[1] for v, s, rows in zip(self.views, self.scales, (words, meta))]

    def probabilities(self, words: list[np.ndarray], meta: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        odds = self.odds(words, meta)
        return _sigmoid(odds[0]), _sigmoid(odds[1]), _sigmoid(_paired(*odds) @ self.both[:-1] + self.both[-1])


def _paired(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    a, b = np.clip(a, -10, 10), np.clip(b, -10, 10)
    return np.stack([a, b, np.minimum(a, b)], 1)


@dataclass
class Sample:
    """Places of the features of some documents, and whether each is good (None: unknown)."""

    words: list[np.ndarray]
    meta: list[np.ndarray]
    y: np.ndarray

    @property
    def sides(self) -> tuple[list[np.ndarray], list[np.ndarray]]:
        return self.words, self.meta


_PLACES = "id string, y int, content long, words array<int>, meta array<int>"
#: Columns of the counts that a task sends: view, place (-1: the documents themselves), documents of each kind.
_GIVEN = "view int, place int, bad long, good long"


def _places(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Features of rows (id, y, text, lang, source), worked out where the texts lie; ``content`` is a hash of them."""
    kind = pa.list_(pa.int32())
    for piece in text_pieces(batches, "text", 1 << 20):
        raws = list(piece.raw())
        words = [word_places(r).astype(np.int32) for r in raws]
        meta = [meta_places(*x).astype(np.int32) for x in zip(raws, piece.rows.column("lang").to_pylist(), piece.rows.column("source").to_pylist())]
        content = np.array([xxhash.xxh64_intdigest(w.tobytes() + m.tobytes(), len(w)) for w, m in zip(words, meta)], np.uint64).view(np.int64)
        arrays = [piece.rows.column("id"), piece.rows.column("y"), pa.array(content), pa.array(words, kind), pa.array(meta, kind)]
        yield pa.RecordBatch.from_arrays(arrays, ["id", "y", "content", "words", "meta"])


def _lists(column: pa.Array | pa.ChunkedArray) -> list[np.ndarray]:
    chunks = column.chunks if isinstance(column, pa.ChunkedArray) else [column]
    return [np.asarray(c.values.to_numpy()[a:b], np.int64) for c in chunks for a, b in zip(c.offsets.to_pylist(), c.offsets.to_pylist()[1:])]


def _sample(features: DataFrame, draw) -> tuple[Sample, list[int]]:
    """Brings the features of a bounded number of rows to the driver, in the drawn order, and the hashes of their content.

    A document counts with at most WIDTH distinct places of four bytes, whatever its length.
    """
    one = features.groupBy("id").agg(F.min(F.struct("content", "y", "words", "meta")).alias("s"))
    table = one.select("id", "s.content", "s.y", "s.words", "s.meta").orderBy(draw, "id").toArrow()
    return Sample(_lists(table.column("words")), _lists(table.column("meta")), np.array(table.column("y").to_pylist(), float)), table.column("content").to_pylist()


def _count_sure(shared, sure: float):
    """Over feature rows: for each view, how many documents that the other view is sure of hold each place."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        edge = np.log(sure / (1 - sure))
        sums = [np.zeros((2, width + 1), np.int64) for width in (WIDTH, META)]
        for batch in batches:
            for lo in range(0, batch.num_rows, 1000):
                part = batch.slice(lo, 1000)
                sides = [_lists(part.column(c)) for c in ("words", "meta")]
                odds = model.odds(*sides)
                for v in (0, 1):
                    # A label is passed on only where the taking view does not lean the opposite way: each sees faults
                    # that the other is blind to, and confident ignorance would unteach it.
                    told = np.where((odds[v] > 0) == (odds[1 - v] > 0), odds[1 - v], 0.0)
                    for good, ids in ((0, np.flatnonzero(told <= -edge)), (1, np.flatnonzero(told >= edge))):
                        for i in ids.tolist():
                            sums[v][good][sides[v][i]] += 1  # places of a row are distinct
                        sums[v][good][-1] += len(ids)
        for v, both in enumerate(sums):
            at = np.flatnonzero(both.any(0))
            place = np.where(at == both.shape[1] - 1, -1, at)
            arrays = [np.full(len(at), v, np.int32), place.astype(np.int32), both[0, at], both[1, at]]
            yield pa.RecordBatch.from_arrays([pa.array(a) for a in arrays], ["view", "place", "bad", "good"])

    return run


def exchange(pool: DataFrame, sure: float):
    """A function from a model to what each view is given, counted over all rows of ``pool`` in one pass.

    Tasks send at most one row a place, and so does the sum: what reaches the driver is bounded by WIDTH.
    """
    spark = pool.sparkSession

    def give(model: CoTrained) -> list[Counts]:
        shared = spark.sparkContext.broadcast(model)  # of fixed size
        found = pool.select("words", "meta").mapInArrow(_count_sure(shared, sure), _GIVEN)
        table = found.groupBy("view", "place").agg(F.sum("bad").alias("bad"), F.sum("good").alias("good")).toArrow()
        shared.destroy()
        view, place, bad, good = (table.column(c).to_numpy() for c in ("view", "place", "bad", "good"))
        out = []
        for v, width in enumerate((WIDTH, META)):
            sums = np.zeros((2, width + 1))
            mine = view == v
            sums[0, place[mine]], sums[1, place[mine]] = bad[mine], good[mine]  # place -1 is the last
            out.append(Counts(sums[0, :-1], sums[1, :-1], sums[0, -1], sums[1, -1]))
        return out

    return give


def learn_views(labelled: Sample, give=None, rounds: int = 3) -> CoTrained:
    """Co-training over ``rounds``; a fifth of the labelled rows, by place, serves calibration and combination only.

    ``give`` turns the model of a round into the pseudo-labels that each view learns from in the next (None: none).
    """
    y = labelled.y
    held = np.arange(len(y)) % 5 == 4
    if len(np.unique(y[held])) < 2 or len(np.unique(y[~held])) < 2:  # too few to set any apart
        held = np.ones(len(y), bool)
    learn = ~held if not held.all() else held
    sides = labelled.sides
    given: list[Counts | None] = [None, None]
    for turn in range(rounds + 1):
        views = [kind.learn([r for r, m in zip(rows, learn) if m], y[learn], g) for kind, rows, g in zip((TextView, MetaView), sides, given)]
        scales = [fit_logistic(view.margin([r for r, m in zip(rows, held) if m])[:, None], y[held], 0.1) for view, rows in zip(views, sides)]
        model = CoTrained(tuple(views), scales)
        if turn == rounds or give is None:
            break
        given = give(model)
    model.both = fit_logistic(_paired(*model.odds(*([r for r, m in zip(side, held) if m] for side in sides))), y[held], 0.1)
    return model


def co_train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", source_col: str = "source", sample: int = 12_000, rounds: int = 3, sure: float = 0.98, keep_at: float = 0.5) -> DataFrame:
    """Rows (row struct of all columns, p_text, p_meta, score double, keep boolean) for every row of ``docs``.

    A document is good if its label says quality 1 and toxic 0; several labels must all say so, rows with both null
    are no labels. ``sample`` bounds the labelled rows learnt from, the smallest hashes of the id; pseudo-labels are
    exchanged over all other documents, each distinct content once, by ``rounds`` passes over their settled features.
    A null text is empty; null language or source are values; without labels of both kinds every score is the share of
    good ones (one without labels). Repeated rows get equal scores; of rows that share an id one is learnt from as
    labelled; texts are read whole, however long; further columns pass through inside ``row``; an empty table gives no
    rows.
    """
    spark = docs.sparkSession
    good = (F.coalesce("quality", F.lit(1)) == 1) & (F.coalesce("toxic", F.lit(0)) == 0)
    marks = labels.where("quality is not null or toxic is not null").groupBy(F.col(id_col).alias("id")).agg(F.min(good.cast("int")).alias("y"))
    base = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"), F.col(lang_col).cast("string").alias("lang"), F.col(source_col).cast("string").alias("source"))
    draw = F.xxhash64(F.lit("sample"), "id")
    chosen = marks.join(base.select("id").distinct(), "id", "left_semi").orderBy(draw, "id").limit(sample)

    def features(rows: DataFrame) -> DataFrame:
        return rows.select(F.col("id").cast("string").alias("id"), F.col("y").cast("int").alias("y"), "text", "lang", "source").mapInArrow(_places, _PLACES)

    labelled, known = _sample(features(base.join(F.broadcast(chosen), "id")), draw)  # at most `sample` documents
    rows = docs.select(F.struct(*docs.columns).alias("row"), F.col(text_col).alias("text"), F.col(lang_col).cast("string").alias("lang"), F.col(source_col).cast("string").alias("source"))
    if len(np.unique(labelled.y)) < 2:
        flat = float(labelled.y.mean()) if len(labelled.y) else 1.0
        p = F.lit(flat)
        return rows.select("row", p.alias("p_text"), p.alias("p_meta"), p.alias("score"), (p >= keep_at).alias("keep"))
    # The content of labelled rows is left out, copies of it too: a view would take its own lesson for a confirmation.
    seen = spark.createDataFrame([(h,) for h in set(known)], "content long")  # at most `sample` numbers
    free = features(base.withColumn("y", F.lit(None))).join(F.broadcast(seen), "content", "left_anti")
    pool = settle(free.select("content", "words", "meta").dropDuplicates(["content"]), "features")
    shared = spark.sparkContext.broadcast(learn_views(labelled, exchange(pool, sure), rounds))  # of fixed size
    release(pool)

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        for piece in text_pieces(batches, "text", 1 << 20):
            raws = list(piece.raw())
            meta = [meta_places(*x) for x in zip(raws, piece.rows.column("lang").to_pylist(), piece.rows.column("source").to_pylist())]
            p, q, both = model.probabilities([word_places(r) for r in raws], meta)
            arrays = [piece.rows.column("row"), pa.array(p), pa.array(q), pa.array(both), pa.array(both >= keep_at)]
            yield pa.RecordBatch.from_arrays(arrays, ["row", "p_text", "p_meta", "score", "keep"])

    kind = rows.schema["row"].dataType.simpleString()
    return rows.mapInArrow(score, f"row {kind}, p_text double, p_meta double, score double, keep boolean")
