"""Removal of repeated byte strings by suffix arrays, built by two-stage sorting.

Two equal strings of ``span`` bytes hold the same gram of least hash at the same place. Each such anchor gives two
pieces of text, which together hold all strings around it. A string shared by two pieces contains a core that both
share, so only pieces of one core can repeat each other. Pieces are dealt by core, those of hot cores over all tasks, and
sorted: equal pieces lie together and all but the first go, and pieces of a core with more than one text are read again
and brought to suffix arrays of bounded size. There, suffixes smaller than their
successors are sorted directly, the others are induced by scans over the buckets of first bytes, and common prefixes of
neighbours tell which strings are equal. Cores that more than one array holds pass on one place for each string.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ertransfer.durable import partitions_for, release, settle
from ertransfer.llm.batches import text_pieces
from ertransfer.llm.words import Prefix, window_least

SPAN = 100
#: Bytes of text in one suffix array, small enough for a processor's cache; a single core is cut at 16 times as many.
ARRAY_BYTES = 1 << 18
_PLACE = ("id", "tie")


def gram_of(span: int) -> int:
    """Length of the grams among which an anchor is the least; short, as the cores do the sifting."""
    return min(12, max(1, span // 3))


# --- anchors -----------------------------------------------------------------------------------------------------


def anchors(data: np.ndarray, starts: np.ndarray, span: int, prefix: Prefix | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(positions, text numbers) of the grams of least hash in any ``span`` bytes of a text; ties go to the left."""
    sizes = np.diff(starts)
    if not len(data) or sizes.max() < span:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    gram = gram_of(span)
    first = np.arange(len(data) - gram + 1)
    least = window_least((prefix or Prefix(data)).of(first, first + gram), span - gram + 1)
    inside = np.zeros(len(data) + 1, np.int8)
    fit = sizes >= span
    np.add.at(inside, starts[:-1][fit], 1)
    np.add.at(inside, starts[1:][fit] - span + 1, -1)
    chosen = least[np.cumsum(inside[: len(least)]).astype(bool)]
    chosen = chosen[np.r_[True, chosen[1:] != chosen[:-1]]]
    return chosen, np.searchsorted(starts, chosen, "right") - 1


def _pieces(span: int, hot: tuple[np.ndarray, np.ndarray] | None = None):
    """Rows (core, content, id, tie, at, over): at holds the first string's start and the number of further ones.

    ``hot`` names frequent cores and over how many tasks each is dealt.
    """
    gram = gram_of(span)
    reach = span - gram
    half = (reach + 1) // 2

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece in text_pieces(batches, "text", 1 << 20):
            prefix = Prefix(piece.data)
            p, owner = anchors(piece.data, piece.starts, span, prefix)
            begin, last = piece.starts[owner], piece.starts[owner + 1] - span
            out = []
            for side, lo, hi, a, b in (
                (1, np.maximum(begin, p - reach), np.minimum(p - half, last), p - half, p + gram),
                (2, np.maximum(begin, p - half), np.minimum(p, last), p, p + span - half),
            ):
                ok = lo <= hi
                lo, hi, a, b, who = lo[ok], hi[ok], a[ok], b[ok], owner[ok]
                at = ((lo - piece.starts[who]) << 16) | (hi - lo)
                out.append((prefix.of(a, b, side).view(np.int64), prefix.of(lo, hi + span).view(np.int64), who, at))
            core, content, who, at = (np.concatenate(x) for x in zip(*out))
            over = np.ones(len(core), np.int32)
            if hot and len(hot[0]):
                near = np.minimum(np.searchsorted(hot[0], core), len(hot[0]) - 1)
                over = np.where(hot[0][near] == core, hot[1][near], over).astype(np.int32)
            who = pa.array(who)
            yield pa.RecordBatch.from_arrays(
                [pa.array(core), pa.array(content), piece.rows.column("id").take(who), piece.rows.column("tie").take(who), pa.array(at), pa.array(over)],
                ["core", "content", "id", "tie", "at", "over"],
            )

    return run


_PIECE = "core long, content long, id long, tie long, at long, over int"


def _hot_cores(texts: DataFrame, span: int, share: int = 64) -> tuple[np.ndarray, np.ndarray]:
    """Cores that hold more pieces than half a task's share, at most two for each task, and how many tasks each needs.

    Read off one text in ``share``; this decides only in which task a piece lies, not what becomes of it.
    """
    some = texts.where(F.pmod(F.xxhash64(*_PLACE, F.octet_length("text")), F.lit(share)) == 0).mapInArrow(_pieces(span), _PIECE)
    counts = settle(some.groupBy("core").agg(F.count("*").alias("n")), "cores")
    total = counts.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    least = max(32, total // (2 * partitions_for(texts.sparkSession)))
    found = sorted((r.core, 1 + r.n // least) for r in counts.where(F.col("n") >= least).collect())
    release(counts)
    return np.array([r[0] for r in found], np.int64), np.array([r[1] for r in found], np.int32)


def _sift(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Over sorted pieces: the later ones of equal pieces (again), the first ones where a core has several texts.

    First pieces of hot cores, of which other tasks hold more, and single pieces at either end of a batch are passed on
    as well; the suffix arrays judge them.
    """
    before = None
    for batch in batches:
        if not batch.num_rows:
            continue
        rows = np.stack([c.to_numpy(zero_copy_only=False).astype(np.int64) for c in batch.columns])
        if before is not None:
            rows = np.concatenate([before, rows], 1)
        same = rows[:, 1:] == rows[:, :-1]
        new_core = np.r_[True, ~same[0]]
        new = np.r_[True, ~(same[0] & same[1])]
        twice = np.r_[before is not None, same.all(0)]
        run = np.cumsum(new_core) - 1
        several = np.bincount(run, new)[run] > 1
        several |= (run == 0) | (run == run[-1]) | (rows[5] > 1)
        again = ~new & ~twice
        # a repeated row of the first place is no later piece
        keep = again | (new & several & ~twice)
        before = rows[:, -1:]
        core, _, ids, tie, at, _ = rows[:, keep]
        lo = at >> 16
        yield pa.RecordBatch.from_arrays([pa.array(again[keep]), pa.array(core), pa.array(ids), pa.array(tie), pa.array(lo), pa.array(lo + (at & 0xFFFF))], ["again", "core", "id", "tie", "lo", "hi"])


# --- suffix arrays -----------------------------------------------------------------------------------------------


def _words(text: np.ndarray, span: int) -> tuple[np.ndarray, list[tuple[int, np.uint64]]]:
    """Big-endian 64-bit word at each position, and (offset, mask) of the words that make up ``span`` bytes."""
    word = np.concatenate([text, np.zeros(span + 16, np.uint8)]).astype(np.uint64)
    for width in (1, 2, 4):
        word = (word[:-width] << np.uint64(8 * width)) | word[width:]
    parts = [(k, np.uint64(0xFFFFFFFFFFFFFFFF) if k + 8 <= span else np.uint64(((1 << 8 * (span - k)) - 1) << 8 * (8 - (span - k)))) for k in range(0, span, 8)]
    return word, parts


def _direct(at: np.ndarray, word: np.ndarray, parts: list) -> np.ndarray:
    """Suffixes ``at`` by their first bytes; each further word sorts only those still tied."""
    order = at[np.argsort(word[at] & parts[0][1], kind="stable")]
    key = word[order] & parts[0][1]
    group = np.cumsum(np.r_[True, key[1:] != key[:-1]])[: len(order)]
    for offset, mask in parts[1:]:
        if not len(order):
            break
        equal = group[1:] == group[:-1]
        tied = np.flatnonzero(np.r_[False, equal] | np.r_[equal, False])
        if not len(tied):
            break
        key, of = word[order[tied] + offset] & mask, group[tied]
        mixed = of[1:][(key[1:] != key[:-1]) & (of[1:] == of[:-1])]
        if not len(mixed):
            continue
        apart = np.zeros(int(group[-1]) + 1, bool)
        apart[mixed] = True
        some = apart[of]  # groups of one key stay as they are
        tied, key, of = tied[some], key[some], of[some]
        by = np.lexsort((key, of))
        order[tied], key = order[tied][by], key[by]
        step = np.ones(len(order), bool)
        step[1:] = ~equal
        step[tied[1:]] |= (key[1:] != key[:-1]) & (of[1:] == of[:-1])
        group = np.cumsum(step)
    return order


def two_stage(text: np.ndarray, span: int) -> np.ndarray:
    """Suffix array of ``text``, exact on the first ``span`` bytes: smaller ones sorted, larger ones induced."""
    n = len(text)
    if not n:
        return np.zeros(0, np.int64)
    rising = np.zeros(n, bool)
    change = np.flatnonzero(text[1:] != text[:-1])
    up = text[change + 1] > text[change]
    before = np.cumsum(np.r_[False, text[1:] != text[:-1]])  # changes before each place
    known = before < len(change)
    rising[known] = up[before[known]]
    word, parts = _words(text, span)
    small = _direct(np.flatnonzero(rising), word, parts)
    edges = np.searchsorted(text[small], np.arange(257), "left")
    induced: list[list[np.ndarray]] = [[] for _ in range(256)]
    induced[text[-1]].append(np.array([n - 1]))
    out = []
    for c in range(256):
        bucket = []
        now = np.concatenate(induced[c]) if induced[c] else np.zeros(0, np.int64)
        while len(now):
            bucket.append(now)
            now = now[now > 0] - 1
            now = now[text[now] == c]
        bucket.append(small[edges[c] : edges[c + 1]])
        whole = np.concatenate(bucket)
        out.append(whole)
        back = whole[whole > 0] - 1
        back = back[text[back] > c]
        by = text[back]
        back = back[np.argsort(by, kind="stable")]
        counts = np.bincount(by, minlength=256)
        ends = np.cumsum(counts)
        for d in np.flatnonzero(counts).tolist():
            induced[d].append(back[ends[d] - counts[d] : ends[d]])
    return np.concatenate(out)


def common_prefixes(text: np.ndarray, order: np.ndarray, span: int) -> np.ndarray:
    """Common prefix of each suffix of ``order`` with the one before, at most ``span``; the first has none."""
    word, parts = _words(text, span)
    common = np.zeros(len(order), np.int64)
    live = np.arange(1, len(order))
    for offset, mask in parts:
        differ = (word[order[live] + offset] ^ word[order[live - 1] + offset]) & mask
        same = differ == 0
        odd = differ[~same]
        lead = np.zeros(len(odd), np.int64)
        for k in range(1, 8):
            lead += (odd >> np.uint64(64 - 8 * k)) == 0
        common[live[~same]] = offset + lead
        live = live[same]
    common[live] = span
    return common


def _array(rows: list[tuple], is_open: np.ndarray, span: int) -> tuple[list[np.ndarray], list]:
    """Of pieces (core, id, tie, lo, text): removed (id, tie, from, to), and one place for each string of open cores."""
    sizes = np.array([len(r[4]) for r in rows])
    begin = np.cumsum(sizes) - sizes
    text = np.frombuffer(b"".join(r[4] for r in rows), np.uint8)
    order = two_stage(text, span)
    owner = np.repeat(np.arange(len(sizes)), sizes)[order]
    fit = order - begin[owner] <= sizes[owner] - span
    order, owner = order[fit], owner[fit]
    string = np.cumsum(common_prefixes(text, order, span) < span)
    more = (np.bincount(string)[string] > 1) | is_open[owner]  # a string met once matters only to other arrays
    string, order, owner = string[more], order[more], owner[more]
    ids, ties, lows = (np.array([r[k] for r in rows], np.int64) for k in (1, 2, 3))
    start = lows[owner] + order - begin[owner]
    opened = np.zeros(int(string[-1]) + 1, bool) if len(string) else np.zeros(0, bool)
    opened[string[is_open[owner]]] = True
    by = np.lexsort((start, ties[owner], ids[owner], string))
    string, order = string[by], order[by]
    place = np.stack([ids[owner[by]], ties[owner[by]], start[by]])
    first = np.r_[True, string[1:] != string[:-1]][: len(string)]
    lead = np.flatnonzero(first)
    later = (place != place[:, lead[np.cumsum(first) - 1]]).any(0) if len(string) else first
    gone = merge_starts(place[:, later], span)
    at = lead[opened[string[lead]]]
    shown = []
    raw = text.tobytes()
    for i, s in zip(at.tolist(), order[at].tolist()):
        h = xxhash.xxh3_128_digest(raw[s : s + span])
        shown.append((int.from_bytes(h[:8], "big", signed=True), int.from_bytes(h[8:], "big", signed=True), *place[:, i].tolist()))
    return gone, shown


def merge_starts(place: np.ndarray, span: int) -> list[np.ndarray]:
    """(id, tie, from, to) of the runs that the strings at ``place`` cover."""
    place = place[:, np.lexsort(place[::-1])]
    n = place.shape[1]
    cut = np.r_[True, (place[:2, 1:] != place[:2, :-1]).any(0) | (place[2, 1:] > place[2, :-1] + span)][:n]
    head = np.flatnonzero(cut)
    tail = np.r_[head[1:] - 1, n - 1][: len(head)]
    return [place[0, head], place[1, head], place[2, head], place[2, tail] + span]


_JUDGED = "w1 long, w2 long, id long, tie long, lo long, to long"


def _judge(span: int, limit: int):
    """Suffix arrays over pieces sorted by core; a core whose pieces may lie in another array too is open."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        size, first_core, cut_core = 0, None, None

        def flush(ending: bool):
            """The pieces held; the last core waits for more, unless it fills the array or the rows end."""
            nonlocal held, size, cut_core
            now, rest = held, []
            if not ending:
                at = len(held) - 1
                while at and held[at - 1][0] == held[-1][0]:
                    at -= 1
                if at:
                    now, rest = held[:at], held[at:]
            open_cores = {first_core, cut_core}
            if ending or not rest:
                open_cores.add(now[-1][0])
                cut_core = now[-1][0]
            gone, shown = _array(now, np.array([r[0] in open_cores for r in now]), span)
            held, size = rest, sum(len(r[4]) for r in rest)
            none = pa.nulls(len(gone[0]), pa.int64())
            yield pa.RecordBatch.from_arrays([none, none, *(pa.array(x) for x in gone)], ["w1", "w2", "id", "tie", "lo", "to"])
            for k in range(0, len(shown), 10_000):
                w1, w2, ids, tie, lo = (pa.array(x, pa.int64()) for x in zip(*shown[k : k + 10_000]))
                yield pa.RecordBatch.from_arrays([w1, w2, ids, tie, lo, pa.nulls(len(lo), pa.int64())], ["w1", "w2", "id", "tie", "lo", "to"])

        for batch in batches:
            for row in zip(*(batch.column(c).to_pylist() for c in ("core", "id", "tie", "lo", "text"))):
                if first_core is None:
                    first_core = row[0]
                if size >= limit and row[0] != held[-1][0] or size >= 16 * limit:
                    yield from flush(False)
                held.append(row)
                size += len(row[4])
        if held:
            yield from flush(True)

    return run


# --- the operator ------------------------------------------------------------------------------------------------


def _cut(span: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece in text_pieces(batches, "text"):
            out = []
            for i, t, wanted, raw in zip(*(piece.rows.column(c).to_pylist() for c in ("id", "tie", "wanted")), piece.raw()):
                out += [(w["core"], i, t, w["lo"], raw[w["lo"] : w["hi"] + span]) for w in wanted]
            for k in range(0, len(out), 10_000):
                yield pa.RecordBatch.from_arrays([pa.array(x, kind) for x, kind in zip(zip(*out[k : k + 10_000]), (*[pa.int64()] * 4, pa.binary()))], ["core", "id", "tie", "lo", "text"])

    return run


def _apply(text_at: int):
    kind = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))

    def with_text(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            text = batch.column("row").field(text_at).cast(pa.string())
            yield pa.RecordBatch.from_arrays([*batch.columns, text], [*batch.schema.names, "text"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece in text_pieces(with_text(batches), "text"):
            spans, kept = [], []
            for gone, raw in zip(piece.rows.column("gone").to_pylist(), piece.raw()):
                runs: list[list[int]] = []
                for a, b in sorted((g["lo"], g["to"]) for g in gone or ()):
                    if runs and a <= runs[-1][1]:
                        runs[-1][1] = max(b, runs[-1][1])
                    else:
                        runs.append([a, b])
                spans.append([{"start": a, "end": b} for a, b in runs])
                inner = [0, *(x for r in runs for x in r), len(raw)]
                kept.append(b"".join(raw[a:b] for a, b in zip(inner[::2], inner[1::2])))
            yield pa.RecordBatch.from_arrays([piece.rows.column("row"), piece.rows.column("id"), piece.rows.column("tie"), pa.array(np.diff(piece.starts)), pa.array(spans, kind), pa.array(kept, pa.binary())], ["row", "id", "tie", "n_bytes", "spans", "kept"])

    return run


def remove_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", span: int = SPAN, limit: int = ARRAY_BYTES) -> DataFrame:
    """``docs`` rows as (row struct of all columns, n_bytes, spans array<struct<start, end>>, kept binary).

    A byte goes if a string of ``span`` bytes that covers it also starts earlier, in a document of smaller id or
    before it in its own; strings are judged on the texts as given. Null texts count as empty; null ids come first;
    texts of one id are ordered by their hash; of repeated rows one is the first and the others repeat it; an empty
    table gives no rows.
    """
    if not 2 <= span < 1 << 16:
        raise ValueError("span must be from 2 to 65535")
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    key = F.coalesce(F.col(id_col).cast("long"), F.lit(-(1 << 63)))
    single = docs.groupBy(key.alias("id")).agg(F.count("*").alias("n")).where("n > 1").isEmpty()
    # Only rows of one id need telling apart.
    place = (key.alias("id"), (F.lit(0).cast("long") if single else F.xxhash64(text)).alias("tie"))
    texts = docs.select(*place, text.alias("text"))
    pieces = texts.mapInArrow(_pieces(span, _hot_cores(texts, span)), _PIECE)
    by = ["core", "content", *_PLACE, "at"]
    dealt = pieces.repartition("core", F.when(F.col("over") > 1, F.pmod(F.xxhash64(*by), F.col("over"))).otherwise(0))
    sifted = settle(dealt.sortWithinPartitions(*by).mapInArrow(_sift, "again boolean, core long, id long, tie long, lo long, hi long"), "sifted")
    wanted = sifted.where("not again").groupBy(*_PLACE).agg(F.collect_list(F.struct("core", "lo", "hi")).alias("wanted"))
    slices = settle(texts.join(wanted, [*_PLACE]).select(*_PLACE, "text", "wanted").mapInArrow(_cut(span), "core long, id long, tie long, lo long, text binary"), "slices")
    by = ["core", *_PLACE, "lo"]
    judged = settle(slices.repartitionByRange(*by).sortWithinPartitions(*by).mapInArrow(_judge(span, limit), _JUDGED), "judged")
    shown = judged.where("w1 is not null").select("w1", "w2", F.struct(*_PLACE, "lo").alias("place"))
    firsts = shown.groupBy("w1", "w2").agg(F.min("place").alias("first"))
    across = shown.join(firsts, ["w1", "w2"]).where("place > first").select("place.*", (F.col("place.lo") + span).alias("to")).distinct()
    gone = (
        sifted.where("again").select(*_PLACE, "lo", (F.col("hi") + span).alias("to"))
        .union(judged.where("w1 is null").select(*_PLACE, "lo", "to")).union(across)
        .groupBy(*_PLACE).agg(F.collect_list(F.struct("lo", "to")).alias("gone"))
    )
    gone = settle(gone, "gone")
    release(sifted, slices, judged)
    rows = docs.select(F.struct(*docs.columns).alias("row"), *place)
    shape = docs.select(F.struct(*docs.columns).alias("row")).schema["row"].dataType.simpleString()
    done = rows.join(gone, [*_PLACE], "left").select("row", *_PLACE, "gone").mapInArrow(_apply(docs.columns.index(text_col)), f"row {shape}, id long, tie long, n_bytes long, spans array<struct<start: bigint, end: bigint>>, kept binary")
    if single:
        return done.select("row", "n_bytes", "spans", "kept")
    twice = texts.groupBy(*_PLACE).agg(F.count("*").alias("n")).where("n > 1").drop("n")
    if not twice.isEmpty():
        twice = settle(twice, "twice")
        nth = F.row_number().over(Window.partitionBy(*_PLACE).orderBy(F.xxhash64("row")))
        marked = done.join(twice, [*_PLACE], "left_semi").withColumn("copy", (nth > 1) & (F.col("n_bytes") >= span))
        whole = F.array(F.struct(F.lit(0).cast("long").alias("start"), F.col("n_bytes").alias("end")))
        copies = marked.select(
            "row", *_PLACE, "n_bytes",
            F.when(F.col("copy"), whole).otherwise(F.col("spans")).alias("spans"),
            F.when(F.col("copy"), F.lit(b"")).otherwise(F.col("kept")).alias("kept"),
        )
        done = done.join(twice, [*_PLACE], "left_anti").select(*copies.columns).union(copies)
    return done.select("row", "n_bytes", "spans", "kept")


def digest(found: DataFrame) -> DataFrame:
    """Counts and the hash of the kept bytes in place of spans and bytes."""
    removed = F.aggregate("spans", F.lit(0).cast("long"), lambda total, s: total + s["end"] - s["start"])
    return found.select(
        "row", "n_bytes", removed.alias("n_removed"),
        F.size("spans").cast("long").alias("n_spans"),
        F.sha2("kept", 256).alias("kept_sha256"),
    )
