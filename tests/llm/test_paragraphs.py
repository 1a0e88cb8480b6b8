"""Paragraph classes against brute force over all pairs."""

import itertools

import pyarrow.parquet as pq

from ertransfer.llm import paragraphs


def brute(rows):
    lines = [(i, n, tuple(x.lower().split())) for i, t in rows for n, x in enumerate((t or "").encode().split(b"\n")) if x.split()]
    sets = {w: {w[i : i + 5] for i in range(max(1, len(w) - 4))} for *_, w in lines}
    lead = {w: w for w in sets}

    def root(w):
        while lead[w] != w:
            w = lead[w]
        return w

    having = {}
    for w, s in sets.items():
        for g in s:
            having.setdefault(g, []).append(w)
    for ws in having.values():
        for a, b in itertools.combinations(ws, 2):
            if root(a) != root(b) and len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]):
                lead[root(a)] = root(b)
    groups = {}
    for i, n, w in lines:
        groups.setdefault(root(w), []).append((i, n))
    return sorted((*p, *min(g), p != min(g)) for g in groups.values() if len(g) > 1 for p in g)


def test_whole_table(spark, sf):
    rows = [(r["doc_id"], r["text"]) for r in pq.read_table(f"{sf}/documents.parquet").to_pylist()]
    got = paragraphs.repeated_paragraphs(spark.read.parquet(f"{sf}/documents.parquet")).collect()
    assert sorted(tuple(r) for r in got) == brute(rows)


def test_cases(spark):
    long = " ".join(f"w{i}" for i in range(60))
    rows = [(1, long), (2, long.upper() + "\nother line"), (3, long + " tail"), (4, None), (5, ""), (6, "a b\n\n a  b"), (7, "x " * 30000)]
    docs = spark.createDataFrame([(i, t, 0) for i, t in rows], "doc_id long, text string, para int")
    got = paragraphs.repeated_paragraphs(docs).collect()
    assert sorted(tuple(r) for r in got) == brute(rows)
    assert paragraphs.repeated_paragraphs(docs.limit(0)).collect() == []


def test_without_ids(spark):
    long = [f"w{i}" for i in range(60)]
    near = " ".join([*long[:59], "x"])
    docs = spark.createDataFrame([(None, " ".join(long)), (None, near + "\nalone"), (4, "alone"), (4, " ".join(long)), (4, "other text")], "doc_id long, text string")
    got = {(r.id, r.para, r.lead_id, r.lead_para, r.removed) for r in paragraphs.repeated_paragraphs(docs).collect()}
    assert got == {(None, 0, None, 0, False), (4, 0, None, 0, True), (None, 1, None, 1, False), (4, 0, None, 1, True)}
