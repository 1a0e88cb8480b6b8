"""The near-duplicate stage of the pipeline against all pairs at Jaccard 0.8 or more."""

import itertools

import pyarrow.parquet as pq


def survivors(rows):
    """Places of ``rows`` (id, text) that stay: the first of each component by (id is null, id)."""
    words = [tuple((t or "").encode().lower().split()) for _, t in rows]
    sets = [{w[i : i + 5] for i in range(max(1, len(w) - 4))} for w in words]
    lead = list(range(len(rows)))

    def root(i):
        while lead[i] != i:
            i = lead[i]
        return i

    having, pairs = {}, 0
    for i, s in enumerate(sets):
        for g in s:
            having.setdefault(g, []).append(i)
    for i, j in {p for ids in having.values() for p in itertools.combinations(ids, 2)}:
        if 5 * len(sets[i] & sets[j]) >= 4 * len(sets[i] | sets[j]):
            pairs += sets[i] != sets[j]
            lead[root(i)] = root(j)
    groups = {}
    for i in range(len(rows)):
        groups.setdefault(root(i), []).append(i)
    return [min(g, key=lambda i: (rows[i][0] is None, rows[i][0] or 0)) for g in groups.values()], pairs


def test_all_pairs(spark):
    import corpus_pipeline as cp

    path = "/root/testdata/sf0.01/documents.parquet"
    rows = [(r["doc_id"], r["text"]) for r in pq.read_table(path, columns=["doc_id", "text"]).to_pylist()]
    stay, pairs = survivors(rows)
    got = sorted(r.doc_id for r in cp.distinct_documents(spark, spark.read.parquet(path), "").select("doc_id").collect())
    assert pairs >= 5 and got == sorted(rows[i][0] for i in stay)


def test_ids(spark):
    import corpus_pipeline as cp

    long = [f"w{i}" for i in range(100)]
    near, far = [*long], [*long]
    near[50], far[30], far[60], far[80] = "x", "x", "y", "z"  # 91 of 101 shingles shared; 81 of 111
    rows = [(7, " ".join(long)), (7, "another text"), (None, " ".join(near)), (None, "lonely"), (None, "lonely"), (3, " ".join(far)), (9, ""), (10, None), (7, "another text"), (12, "ANOTHER  text")]
    docs = spark.createDataFrame([(i, t, k) for k, (i, t) in enumerate(rows)], "doc_id long, text string, n_chars int")
    got = cp.distinct_documents(spark, docs, "")
    assert got.columns == docs.columns
    assert sorted((str(r.doc_id), r.text) for r in got.collect()) == sorted([("7", rows[0][1]), ("7", "another text"), ("None", "lonely"), ("3", rows[5][1]), ("9", "")])
