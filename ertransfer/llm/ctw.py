"""Language-model scoring by context-tree weighting over bytes.

A text is its lower-cased bytes and one end byte; each byte is eight binary decisions. For each context of up to
``depth`` bytes and each decision there is a Krichevsky-Trofimov estimate, and the tree mixes all depths by how well
each would have coded the training bytes.

Map tasks sum up the (depth + 1)-grams of their texts. Grams whose contexts end in the same ``ROOT`` bytes form whole
subtrees, so one sort by these bytes lets a task climb from the deepest contexts up to the root bytes in arrays; the
few levels above are joins and aggregations over one row for each pair of root bytes and decision. A second walk over the
same sorted grams takes what the upper levels leave and goes down, giving the log probability of every gram of the
corpus, seen in training or not. Texts look up the commonest grams and words in tables of a fixed number of rows, which
are broadcast; the rest, one row for each text and rare code, meets the whole model in a join. The driver holds the
broadcast tables and a few counts, whatever the corpus.

Words are told apart by 64 bits of hash.
"""

from __future__ import annotations

from collections.abc import Iterator
from math import log, log10, pi

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ertransfer.durable import partitions_for, release, settle
from ertransfer.llm.batches import text_pieces
from ertransfer.llm.words import LOWER, words_of

DEPTH = 3
END = 255
#: Bytes of context that a task's subtrees share.
ROOT = 2
#: Rows of a table of grams or of words that is broadcast, whatever the size of the model.
BLOCK_ROWS = 500_000
#: The end of a text as a word.
END_WORD = np.uint64(0xE0D0E0D0E0D0E0D1)
#: Grams that a task holds before it passes on their counts, and before it works out whole subtrees.
HELD_GRAMS = 1_000_000
PIECE = 1 << 20


def grams_of(text: bytes, depth: int) -> np.ndarray:
    """One code for each byte of the lower-cased text and for its end: the byte, below the bytes before it (0 pads)."""
    return piece_grams(np.frombuffer(text, np.uint8), np.array([0, len(text)]), depth)[0]


def piece_grams(data: np.ndarray, starts: np.ndarray, depth: int) -> tuple[np.ndarray, np.ndarray]:
    """(codes, bounds) of the grams of the texts that begin at ``starts``; text k owns codes bounds[k] to bounds[k + 1]."""
    if depth > 6:
        raise ValueError("a gram of over seven bytes does not fit a positive long")
    sizes = np.diff(starts)
    bounds = starts + np.arange(len(starts))
    padded = np.zeros(len(data) + len(sizes) * (depth + 1), np.uint8)
    padded[np.arange(len(data)) + np.repeat(np.arange(len(sizes)) * (depth + 1) + depth, sizes)] = LOWER[data]
    padded[bounds[1:] - 1 + np.arange(1, len(sizes) + 1) * depth] = END
    code = np.zeros(len(padded) - depth, np.int64)
    for i in range(depth + 1):
        code = (code << 8) | padded[i : i + len(code)]
    first = np.repeat(np.arange(len(sizes)) * depth, sizes + 1) + np.arange(bounds[-1])
    return code[first], bounds


def _words(piece) -> tuple[np.ndarray, np.ndarray]:
    """(word codes, bounds) of the texts of a piece, each with its end as the last word."""
    found = words_of(piece.data, piece.starts)
    counts = np.bincount(found.owner, minlength=len(piece.starts) - 1)
    bounds = np.r_[0, np.cumsum(counts + 1)]
    out = np.full(bounds[-1], END_WORD, np.uint64)
    out[np.arange(len(found.owner)) + found.owner] = found.value
    return out.view(np.int64), bounds


class _Tally:
    """Counts of codes, merged as they come; passed on when they outgrow the task's share."""

    def __init__(self, is_gram: bool):
        self.is_gram, self.parts, self.size, self.most = is_gram, [], 0, 0

    def add(self, codes: np.ndarray, weight: int) -> None:
        if len(codes):
            code, n = np.unique(codes, return_counts=True)
            self.parts.append((code, n * weight))
            self.size += len(code)
        if self.size > max(2 * self.most, HELD_GRAMS // 4):
            self._merge()

    def _merge(self) -> None:
        if len(self.parts) > 1:
            code, n = (np.concatenate(x) for x in zip(*self.parts))
            order = np.argsort(code)
            code, n = code[order], n[order]
            head = np.flatnonzero(np.r_[True, code[1:] != code[:-1]])
            self.parts = [(code[head], np.add.reduceat(n, head))]
        self.size = self.most = sum(len(c) for c, _ in self.parts)

    def drain(self, least: int) -> Iterator[pa.RecordBatch]:
        if self.size < least:
            return
        self._merge()
        if self.size < least:
            return
        for code, n in self.parts:
            for k in range(0, len(code), 200_000):
                c = code[k : k + 200_000]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(c), self.is_gram)), pa.array(c), pa.array(n[k : k + 200_000])], ["is_gram", "code", "n"])
        self.parts, self.size, self.most = [], 0, 0


def _count(depth: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        grams, words = _Tally(True), _Tally(False)
        for piece in text_pieces(batches, "text", PIECE):
            train = piece.rows.column("train").to_numpy(zero_copy_only=False).astype(bool)
            code, bounds = piece_grams(piece.data, piece.starts, depth)
            mine = np.repeat(train, np.diff(bounds))
            grams.add(code[mine], 1)
            grams.add(code[~mine], 0)
            code, bounds = _words(piece)
            words.add(code[np.repeat(train, np.diff(bounds))], 1)
            yield from grams.drain(HELD_GRAMS)
            yield from words.drain(HELD_GRAMS)
        yield from grams.drain(1)
        yield from words.drain(1)

    return run


# --- the tree ----------------------------------------------------------------------------------------------------


def _lgamma(x, ln=F.log):
    """Log gamma for x > 0, of columns or arrays: Stirling's series after seven steps up."""
    z = x + 7
    steps = x
    for i in range(1, 7):
        steps = steps * (x + i)
    series = 1 / (12 * z) - 1 / (360 * z**3) + 1 / (1260 * z**5)
    return (z - 0.5) * ln(z) - z + 0.5 * log(2 * pi) + series - ln(steps)


def _own(a, b, ln=F.log):
    """Log probability that the Krichevsky-Trofimov estimate gives to a zeros and b ones."""
    return _lgamma(a + 0.5, ln) + _lgamma(b + 0.5, ln) - log(pi) - _lgamma(a + b + 1, ln)


def _root_of(code: Column, depth: int) -> Column:
    return F.shiftright(code, 8).bitwiseAND(F.lit((1 << 8 * min(ROOT, depth)) - 1).cast("long"))


def _subtrees(code: np.ndarray, n: np.ndarray, depth: int):
    """For each bit of the last byte: (ones, levels from the deepest to the root bytes) of the grams.

    A level is (keys of context and node, place of each row of the level below, a, b, log weight, kt, beta).
    """
    root = min(ROOT, depth)
    byte, ctx = code & 255, code >> 8
    n = n.astype(float)
    for bit in range(8):
        one = (byte >> (7 - bit)) & 1
        key = (ctx << 8) | (1 << bit) | (byte >> (8 - bit))
        levels, a, b, deeper = [], n * (1 - one), n * one, None
        for d in range(depth, root - 1, -1):
            key, inverse = np.unique(key, return_inverse=True)
            a, b = np.bincount(inverse, a, len(key)), np.bincount(inverse, b, len(key))
            own = _own(a, b, np.log)
            if deeper is None:
                weight, beta = own, np.ones(len(key))
            else:
                both = np.logaddexp(own, np.bincount(inverse, deeper, len(key)))
                weight, beta = both - log(2), np.exp(own - both)
            levels.append((key, inverse, a, b, weight, (b + 0.5) / (a + b + 1), beta))
            deeper = weight
            if d > root:
                key = ((key >> 8) & ((1 << 8 * (d - 1)) - 1)) << 8 | (key & 255)
        yield bit, one, levels


def _whole_roots(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """Tables of rows sorted by ``root``, each with all rows of the roots that it holds."""
    held, size = [], 0
    for batch in batches:
        if not batch.num_rows:
            continue
        held.append(batch)
        size += batch.num_rows
        if size >= HELD_GRAMS:
            table = pa.Table.from_batches(held)
            root = table.column("root").to_numpy()
            cut = int(np.searchsorted(root, root[-1], "left"))
            if cut:
                yield table.slice(0, cut)
                held, size = table.slice(cut).to_batches(), table.num_rows - cut
    if held:
        yield pa.Table.from_batches(held)


def _climb(depth: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in _whole_roots(batches):
            for _, _, levels in _subtrees(table.column("code").to_numpy(), table.column("n").to_numpy(), depth):
                key, _, a, b, weight, *_ = levels[-1]
                yield pa.RecordBatch.from_arrays([pa.array(key >> 8), pa.array((key & 255).astype(np.int32)), pa.array(a.astype(np.int64)), pa.array(b.astype(np.int64)), pa.array(weight)], ["ctx", "node", "a", "b", "lpw"])

    return run


def _descend(depth: int):
    """Rows (root, code, n) and (root, node key, p, rest), the rest with n null, to (code, n, lp)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in _whole_roots(batches):
            is_top = table.column("n").is_null().to_numpy()
            code, n = table.column("code").to_numpy(), table.column("n").fill_null(0).to_numpy()
            tops = code[is_top]
            order = np.argsort(tops)
            tops, above, rest = tops[order], table.column("p").to_numpy()[is_top][order], table.column("rest").to_numpy()[is_top][order]
            code, n = code[~is_top], n[~is_top]
            lp = np.zeros(len(code))
            for _, one, levels in _subtrees(code, n, depth):
                at = np.searchsorted(tops, levels[-1][0])
                p, left = above[at], rest[at]
                for i in range(len(levels) - 1, -1, -1):
                    _, _, _, _, _, kt, beta = levels[i]
                    p, left = p + left * beta * kt, left * (1 - beta)
                    p, left = p[levels[i][1]], left[levels[i][1]]
                lp += np.log10(np.where(one == 1, p, 1 - p))
            yield pa.RecordBatch.from_arrays([pa.array(code), pa.array(n), pa.array(lp)], ["code", "n", "lp"])

    return run


def _upper(roots: DataFrame, depth: int) -> DataFrame:
    """Rows (root, code, n null, p, rest): what the levels above the root bytes give to each (root, node), and leave."""
    level, levels = roots, []
    top = min(ROOT, depth)
    for d in range(top - 1, -1, -1):
        mask = (1 << (8 * d)) - 1
        level = level.groupBy(F.col("ctx").bitwiseAND(F.lit(mask).cast("long")).alias("ctx"), "node").agg(F.sum("a").alias("a"), F.sum("b").alias("b"), F.sum("lpw").alias("deeper"))
        a, b = F.col("a").cast("double"), F.col("b").cast("double")
        most = F.greatest("own", "deeper")
        level = level.withColumn("own", _own(a, b))
        both = most + F.log(F.exp(F.col("own") - most) + F.exp(F.col("deeper") - most))
        level = level.withColumn("lpw", both - log(2)).withColumn("beta", F.exp(F.col("own") - both)).withColumn("kt", (b + 0.5) / (a + b + 1))
        levels.append((mask, level.select("ctx", "node", "kt", "beta")))
    out = roots.select(F.col("ctx").alias("root"), "node", F.lit(0.0).alias("p"), F.lit(1.0).alias("rest"))
    for mask, table in levels[::-1]:
        at = out.withColumn("ctx", F.col("root").bitwiseAND(F.lit(mask).cast("long"))).join(table, ["ctx", "node"])
        share = F.col("rest") * F.col("beta")
        out = at.select("root", "node", (F.col("p") + share * F.col("kt")).alias("p"), (F.col("rest") - share).alias("rest"))
    return out.select("root", (F.shiftleft("root", 8) + F.col("node")).alias("code"), F.lit(None).cast("long").alias("n"), "p", "rest")


def gram_model(grams: DataFrame, depth: int = DEPTH) -> DataFrame:
    """Rows (code, n, lp): log10 probability of the last byte of each gram given those before it, trained on column n.

    One task holds the distinct grams whose contexts end in the same ROOT bytes.
    """
    parts = partitions_for(grams.sparkSession)
    rooted = grams.select(_root_of(F.col("code"), depth).alias("root"), "code", "n")
    laid = lambda t: t.repartition(parts, "root").sortWithinPartitions("root")
    roots = settle(laid(rooted).mapInArrow(_climb(depth), "ctx long, node int, a long, b long, lpw double"), "roots")
    both = rooted.select("root", "code", "n", F.lit(0.0).alias("p"), F.lit(0.0).alias("rest")).unionByName(_upper(roots, depth))
    model = settle(laid(both).mapInArrow(_descend(depth), "code long, n long, lp double"), "model")
    release(roots)
    return model


# --- scoring -----------------------------------------------------------------------------------------------------


class _Lookup:
    """Values of codes by open addressing in flat arrays; -1 marks a free place and is no code."""

    def __init__(self, keys: np.ndarray, values: np.ndarray):
        self.bits = max(4, int(2 * len(keys)).bit_length())
        self.keys, self.values = np.full(1 << self.bits, -1, np.int64), np.zeros(1 << self.bits)
        at = self._place(keys)
        while len(keys):
            free = self.keys[at] == -1
            slot, who = np.unique(at[free], return_index=True)
            won = np.flatnonzero(free)[who]
            self.keys[slot], self.values[slot] = keys[won], values[won]
            lost = np.ones(len(keys), bool)
            lost[won] = False
            keys, values, at = keys[lost], values[lost], (at[lost] + 1) & ((1 << self.bits) - 1)

    def _place(self, keys: np.ndarray) -> np.ndarray:
        return ((keys.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.bits)).astype(np.int64)

    def get(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(values, found) for ``keys``; codes not held have the value 0."""
        at = self._place(keys)
        met = self.keys[at]
        found = met == keys
        out = self.values[at]
        out[~found] = 0
        which = np.flatnonzero(~found & (met != -1))
        at = at[which]
        while len(which):
            at = (at + 1) & ((1 << self.bits) - 1)
            met = self.keys[at]
            hit = met == keys[which]
            out[which[hit]], found[which[hit]] = self.values[at[hit]], True
            on = ~hit & (met != -1)
            which, at = which[on], at[on]
        return out, found


#: Lookups that this worker has built, by broadcast.
_ready: dict = {}


def _head(table: DataFrame, value: str) -> tuple[np.ndarray, np.ndarray]:
    """The commonest rows of (code, n, value), at most BLOCK_ROWS of them: whole classes of n by powers of two."""
    size = F.floor(F.log2(F.col("n") + 1)).cast("int")
    least, rows = 99, 0
    for r in sorted(table.groupBy(size.alias("size")).count().collect(), key=lambda r: -r["size"]):  # at most 64 rows
        if rows + r["count"] > BLOCK_ROWS:
            break
        least, rows = r["size"], rows + r["count"]
    found = table.where(size >= least).select("code", value).toArrow()
    return found.column("code").to_numpy(), found.column(value).to_numpy()


def _score(shared, depth: int):
    """Adds to rows (row, text) the sums over common codes, and the rare codes themselves."""

    def nested(codes: np.ndarray, rare: np.ndarray, bounds: np.ndarray) -> pa.Array:
        counts = np.r_[0, np.cumsum(rare)][bounds]
        return pa.ListArray.from_arrays(pa.array(counts.astype(np.int32)), pa.array(codes[rare]))

    def summed(values: np.ndarray, bounds: np.ndarray) -> np.ndarray:
        return np.add.reduceat(values, bounds[:-1]) if len(bounds) > 1 else np.zeros(0)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if shared not in _ready:
            _ready.clear()
            _ready[shared] = tuple(_Lookup(*x) for x in shared.value)
        grams, words = _ready[shared]
        for piece in text_pieces(batches, "text", PIECE):
            code, bounds = piece_grams(piece.data, piece.starts, depth)
            value, found = grams.get(code)
            word, ends = _words(piece)
            base, known = words.get(word)
            yield pa.RecordBatch.from_arrays(
                [
                    piece.rows.column("row"), piece.rows.column("key"), pa.array(np.diff(bounds)), pa.array(np.diff(ends)), pa.array(summed(known.astype(np.int64), ends)),
                    pa.array(summed(base, ends)), pa.array(summed(value, bounds)), nested(code, ~found, bounds), nested(word, ~known, ends),
                ],
                ["row", "key", "n_codes", "n_tokens", "n_known", "base", "score", "grams", "words"],
            )

    return run


def score_texts(docs: DataFrame, train: Column, text_col: str = "text", depth: int = DEPTH, keep: list[str] | None = None) -> DataFrame:
    """Rows (row struct of the columns ``keep``, n_tokens, n_known, train_tokens, base_score, base_norm, score, bits_per_byte).

    ``keep`` names the columns that the result carries (default: all). ``base_score`` sums log10((c + 1) / (N + V + 1))
    over the tokens, probabilities that add up to one with one unknown token, and ``base_norm`` is the same; ``score`` is the model's log10 probability
    of the lower-cased bytes and the end, ``bits_per_byte`` its code length over the bytes and the end.

    ``train`` says which rows are learnt from (null: not). Null texts are empty and have the end token alone; with no
    training rows every bit is coded at one half and no token is known; texts are scored whole however long, and a very
    long one is held by one task; repeated rows get equal scores; further columns pass through inside ``row``; an empty
    table gives no rows.
    """
    spark = docs.sparkSession
    source = docs.select(F.coalesce(train, F.lit(False)).alias("train"), F.col(text_col).cast("string").alias("text"))
    counted = source.mapInArrow(_count(depth), "is_gram boolean, code long, n long")
    sums = settle(counted.groupBy("is_gram", "code").agg(F.sum("n").alias("n")), "counts")
    words = sums.where("not is_gram").select("code", "n", F.log10(F.col("n") + 1.0).alias("lc"))
    total, distinct = words.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count("*")).first()
    model = gram_model(sums.where("is_gram").select("code", "n"), depth)
    shared = spark.sparkContext.broadcast((_head(model, "lp"), _head(words, "lc")))  # of at most BLOCK_ROWS rows each
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    rows = docs.select(F.struct(*(keep or docs.columns)).alias("row"), F.unhex(F.md5(text.cast("binary"))).alias("key"), text.alias("text"))
    kind = rows.schema["row"].dataType.simpleString()
    part = settle(rows.mapInArrow(_score(shared, depth), f"row {kind}, key binary, n_codes long, n_tokens long, n_known long, base double, score double, grams array<bigint>, words array<bigint>"), "scored")
    # Equal texts have equal rare codes: one row for each text.
    rare = part.where("size(grams) + size(words) > 0").groupBy("key").agg(F.first("grams").alias("grams"), F.first("words").alias("words"))
    rare = settle(rare, "rare")
    some = lambda name: rare.select("key", F.explode(name).alias("code")).groupBy("key", "code").agg(F.count("*").alias("times"))
    late = some("grams").join(model.select("code", "lp"), "code").groupBy("key").agg(F.sum(F.col("times") * F.col("lp")).alias("late_score"))
    late_words = some("words").join(words, "code").groupBy("key").agg(F.sum("times").alias("late_known"), F.sum(F.col("times") * F.col("lc")).alias("late_base"))
    late = settle(late.join(late_words, "key", "full"), "late")
    shared.unpersist()
    release(sums, model, rare)
    # A hot text is one key of a plain join against one row, which AQE may split.
    both = part.drop("grams", "words").join(late, "key", "left")
    floor = float(np.log10(total + distinct + 1.0))
    base = F.col("base") + F.coalesce("late_base", F.lit(0.0)) - F.col("n_tokens") * F.lit(floor)
    score = F.col("score") + F.coalesce("late_score", F.lit(0.0))
    return both.select(
        "row", "n_tokens", (F.col("n_known") + F.coalesce("late_known", F.lit(0))).alias("n_known"), F.lit(total).cast("long").alias("train_tokens"),
        base.alias("base_score"), base.alias("base_norm"), score.alias("score"), (-score / log10(2) / F.col("n_codes")).alias("bits_per_byte"),
    )
