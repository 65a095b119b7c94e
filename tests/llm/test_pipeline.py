"""The pipeline against plain Python over the smallest tables."""

import re

from conftest import SF, same
from test_text_operators import base_spans

import corpus_pipeline
from cellscrub.llm import merge_dropout, quality_hosts
from cellscrub.llm.queries import QUERIES, SQL


def test_stages_by_brute_force(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    rows = {r.doc_id: r.text for r in docs.collect()}
    stats = {i: quality_hosts.text_stats(t.encode()) for i, t in rows.items()}
    good = [i for i, s in stats.items() if s[0] >= 10 and 100 * s[4] <= 20 * s[0]]
    shingles = []
    for i in good:
        w = rows[i].lower().split()
        shingles.append({tuple(w[j : j + 5]) for j in range(max(1, len(w) - 4))})
    single = _first(good, shingles)
    cut = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
    grams = {tuple(b[j : j + 10]) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect() for b in [cut(r.text)] for j in range(len(b) - 9)}
    clean = [i for i in single if not any(tuple(w[j : j + 10]) in grams for w in [cut(rows[i])] for j in range(len(w) - 9))]
    out = corpus_pipeline.run(spark, SF)
    got = {r.doc_id: r for r in merge_dropout.decode_documents(out).collect()}
    assert sorted(got) == sorted(clean) and out.columns == [*docs.columns, "piece_ids"]
    assert all(r.decoded == r.text for r in got.values())
    for i in clean:
        spans = base_spans(rows[i])
        if not spans and "token" not in rows[i]:
            assert got[i].text == rows[i]
        for kind, a, b in spans:
            assert rows[i][a:b] not in got[i].text or kind == "ip"


def _first(ids, sets):
    """Ids that are the smallest of their component."""
    parent = {i: i for i in ids}

    def root(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for x, (i, a) in enumerate(zip(ids, sets)):
        for j, b in list(zip(ids, sets))[:x]:
            if 100 * len(a & b) >= 80 * len(a | b):
                p, q = root(i), root(j)
                parent[max(p, q)] = min(p, q)
    return [i for i in ids if root(i) == i]


def test_queries_against_sql(spark):
    for name, sql in SQL.items():
        same(QUERIES[name](spark, SF), sql)
