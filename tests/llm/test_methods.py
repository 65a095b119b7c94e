"""The operators' methods: parses, folds, votes, verdicts and groups against plain versions, and odd tables."""

import random
import re

import numpy as np
import pytest
from conftest import SF
from pyspark.sql import functions as F

from cellscrub.llm import chat_events, deobfuscation, jaccard_join, merge_dropout, pii_votes, quality_hosts, relative_dedup, sharding, winnowing


def longest_by_hand(sequences, copies):
    places = [(i, p) for i, s in enumerate(sequences) for p in range(len(s))]
    out = []
    for i, p in places:
        best = len(sequences[i]) - p if copies[i] > 1 else 0
        for j, q in places:
            if (i, p) != (j, q):
                n = 0
                while p + n < len(sequences[i]) and q + n < len(sequences[j]) and sequences[i][p + n] == sequences[j][q + n]:
                    n += 1
                best = max(best, n)
        out.append(best)
    return out


def test_factors_are_the_longest_matches():
    rng = random.Random(3)
    for _ in range(60):
        sequences = [[rng.randrange(3) for _ in range(rng.randint(1, 9))] for _ in range(rng.randint(1, 6))]
        copies = [rng.choice((1, 1, 1, 2)) for _ in sequences]
        flat = np.array([x for s in sequences for x in s], np.uint64)
        got = relative_dedup.longest_elsewhere(flat, np.array([len(s) for s in sequences]), np.array(copies)).tolist()
        assert got == longest_by_hand(sequences, copies)


def test_the_parse_is_greedy_and_covers_what_stands_elsewhere():
    assert relative_dedup.greedy_factors([0, 3, 2, 1, 0, 1, 2, 0]) == [(1, 3), (5, 1), (6, 2)]
    rng = random.Random(4)
    for _ in range(50):
        sequences = [[rng.randrange(4) for _ in range(rng.randint(1, 8))] for _ in range(4)]
        longest = longest_by_hand(sequences, [1] * 4)
        every = [x for s in sequences for x in s]
        at = 0
        for s in sequences:
            covered = {p for a, n in relative_dedup.greedy_factors(longest[at : at + len(s)]) for p in range(a, a + n)}
            assert covered == {p for p, x in enumerate(s) if every.count(x) > 1}
            at += len(s)


def test_a_log_with_every_kind_of_event_folds_to_its_table(spark):
    table = spark.createDataFrame([(c, t, "user" if t % 2 else "assistant", f"text {c} {t} <&>" * (t % 3)) for c in range(12) for t in range(5)], "conv_id long, turn long, role string, text string")
    log = chat_events.table_events(table)
    assert {r.op for r in log.select("op").distinct().collect()} == {"delta", "edit", "regenerate", "delete"}
    got = {(r.conv_id, r.message.turn): (r.role, r.text) for r in chat_events.fold_events(log.orderBy(F.rand(1))).collect()}
    assert got == {(r.conv_id, r.turn): (r.role, r.text) for r in table.collect()}
    assert chat_events.fold_events(chat_events.table_events(table.limit(0))).count() == 0


def test_events_of_one_number(spark):
    rows = [(1, 1, 5, "delta", "b"), (1, 1, 5, "edit", "a"), (1, 2, None, "delta", "early"), (1, 2, 0, "edit", "x"), (1, 3, None, "delta", "y"), (1, 3, None, "regenerate", "x"), (1, 4, 2, "delete", None), (1, 4, 2, "delta", "back")]
    log = spark.createDataFrame([(c, m, s, o, "user", t) for c, m, s, o, t in rows], "conv_id long, message long, seq long, op string, role string, text string")
    assert {r.message: r.text for r in chat_events.fold_events(log).collect()} == {1: "ab", 2: "x", 3: "xy", 4: "back"}


def test_hosts_are_judged_by_rule_and_evidence(spark):
    good = " ".join(f"w{i}" for i in range(30))
    rows = [(f"fine{i % 4}", good) for i in range(200)] + [("short", "one two")] * 60 + [("short", good)] * 5 + [("small", "one two"), ("small", good)] + [("half", "one two")] * 10 + [("half", "word " * 30)] * 10 + [("half", good)] * 20
    df = spark.createDataFrame([(i, t, h) for i, (h, t) in enumerate(rows)], "doc_id long, text string, source string")
    got = {r.host: r for r in quality_hosts.host_verdicts(quality_hosts.document_stats(df)).collect()}
    assert [h for h, r in got.items() if r.host_rejected] == ["short"]  # one of two documents, or two rules at a quarter each, are not enough
    assert got["half"].too_short_failures == got["half"].too_repetitive_failures == 10
    kept = quality_hosts.judge(df).filter("host = 'short' AND NOT base_failed")
    assert kept.count() == 5 and kept.filter("kept").count() == 0


def test_candidates_get_mixed_votes_and_planted_secrets_are_found(spark):
    docs = spark.read.parquet("/root/testdata/sf0.1/documents.parquet").select("doc_id", "text")
    spans = pii_votes.with_votes(pii_votes.candidate_spans(docs)).filter(~F.col("kind").isin(*pii_votes.BASE_KINDS))
    assert spans.select(*pii_votes.LABELERS).distinct().count() >= 4
    found = pii_votes.detect(docs).filter("kind = 'secret'").join(docs, "doc_id").select("doc_id", F.expr("substring(text, start + 1, end - start)").alias("s")).collect()
    planted = {(r.doc_id, m[1]) for r in docs.collect() for m in re.finditer(r"(?:password=|token = \")([0-9a-f]{16,})", r.text or "")}
    got = {(r.doc_id, r.s) for r in found}
    assert len(planted) > 100 and len(got & planted) >= 0.95 * len(planted) and len(got & planted) >= 0.95 * len(got)


def test_overlaps_never_vote(spark):
    docs = spark.createDataFrame([(1, "call +1 (017) 555-7713 or 017-555-7713"), (2, "key a" + "_" * 70 + "1234567 x")], "doc_id long, text string")
    spans = {(r.doc_id, r.kind, r.match) for r in pii_votes.candidate_spans(docs).collect()}
    assert (1, "phone", "+1 (017) 555-7713") in spans and (1, "local_number", "017-555-7713") in spans and (2, "secret", "a" + "_" * 70 + "1234567") in spans
    assert len([s for s in spans if s[0] == 1]) == 2


def brute_components(sets):
    parent = list(range(len(sets)))

    def root(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i, a in enumerate(sets):
        for j in range(i):
            if a and sets[j] and 100 * len(a & sets[j]) >= 80 * len(a | sets[j]):
                parent[max(root(i), root(j))] = min(root(i), root(j))
    return [root(i) for i in range(len(sets))]


@pytest.mark.parametrize("budget", [60, 400, 1_000_000])
def test_chunked_groups_lose_no_link(spark, budget):
    rng = random.Random(9)
    base = [f"w{i}" for i in range(40)]
    texts = []
    for i in range(120):  # two families of near copies that share a passage, and strangers
        words = list(base) if i % 3 else base[:15] + [f"v{j}" for j in range(25)]
        for _ in range(rng.randint(0, 2)):
            words[rng.randrange(16, 40)] = f"x{rng.randrange(500)}"
        if i % 10 == 0:
            words = base[:12] + [f"y{i}_{j}" for j in range(rng.randint(1, 40))]
        texts.append(" ".join(words))
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    sets = [{tuple(w[j : j + 5]) for j in range(len(w) - 4)} for w in (t.split() for t in texts)]
    got = {r.doc_id: r.component_id for r in jaccard_join.components(docs, group_budget=budget).collect()}
    assert [got[i] for i in range(len(texts))] == brute_components(sets)


def test_stages_on_odd_tables(spark):
    """Nulls in every column, empty and repeated rows, and column names that the operators use themselves."""
    text = " ".join(f"w{i}" for i in range(40)) + " me@mail.example.com"
    extra = ["__id", "__key", "__host", "__spans", "__loser", "__n", "__doc", "__hash", "__own", "__place", "__repeat", "piece_ids"]
    rows = [(1, text, "a"), (1, text, "a"), (2, text, None), (3, None, "a"), (4, "", "b"), (None, text + " more", "b"), (5, "short", "b"), (None, None, None)]
    docs = spark.createDataFrame([(*r, *[f"{c}{i}" for c in extra]) for i, r in enumerate(rows)], "doc_id long, text string, source string, " + ", ".join(f"{c} string" for c in extra))
    benchmark = spark.createDataFrame([("q", "w1 w2 w3 w4 w5 w6 w7 w8 w9 w10"), (None, None)], "item_id string, text string")
    stages = {
        "quality": (lambda d: quality_hosts.filter_documents(d), 4),
        "near": (lambda d: jaccard_join.keep_representatives(d), 6),
        "leaks": (lambda d: winnowing.clean_documents(d, benchmark), 4),
        "private": (lambda d: pii_votes.mask_documents(d), 8),
        "pieces": (lambda d: merge_dropout.encode_documents(d), 8),
    }
    for name, (stage, rows_kept) in stages.items():
        got = stage(docs)
        assert sorted(got.columns) == sorted(docs.columns), name
        assert got.count() == rows_kept, name
        none = stage(docs.limit(0))
        assert none.count() == 0 and sorted(none.columns) == sorted(docs.columns), name
    masked = pii_votes.mask_documents(docs).filter("doc_id = 1").select("text", "__spans").collect()
    assert all(r.text.endswith("[EMAIL]") and r["__spans"].startswith("__spans") for r in masked)


def test_written_shards_hold_repeated_ids_once(spark, tmp_path):
    docs = spark.createDataFrame([(i // 2, "x" * (i % 7)) for i in range(40)], "doc_id long, text string")
    out = sharding.write_shards(docs, str(tmp_path / "s"))
    assert sorted((r.doc_id, r.text) for r in out.collect()) == sorted((r.doc_id, r.text) for r in docs.collect())


def test_viterbi_is_the_best_of_all_paths():
    rng = np.random.default_rng(5)
    m = deobfuscation.CharacterModel(np.log(rng.dirichlet(np.full(27, 0.3), (27, 27)) + 1e-6).astype(np.float32))

    def every(text, i, state, cost, out):
        if i == len(text):
            yield cost + (m.trigrams[state[0], state[1], 0] if state[1] else 0.0), out
            return
        for o, c in m.options(text, i):
            if o == -1:
                yield from every(text, i + 1, state, cost - c, out)
            elif o == 0:
                yield from every(text, i + 1, (0, 0), cost - c + (m.trigrams[state[0], state[1], 0] if state[1] else 0.0), out + " ")
            else:
                yield from every(text, i + 1, (state[1], o), cost - c + m.trigrams[state[0], state[1], o], out + chr(96 + o))

    for text in ["a1", "b00k!", "l|ll", "1d1*t", "a.b-c", "s+*p", "aaab", "x9|!1", "*a*"]:
        paths = sorted(every(text, 0, (0, 0), 0.0, ""), key=lambda p: -p[0])
        assert m.restore(text.encode()) == paths[0][1].encode().split() or paths[1][0] > paths[0][0] - 1e-4, text


def test_more_disguises():
    lexicon = {b"idiot": 3.0, b"stupid": 3.0, b"ass": 3.0}
    counts = np.ones(27**3)
    d = deobfuscation.Detector(lexicon, deobfuscation.CharacterModel.mixture(counts, [w for w in lexicon] * 50, 0.9))
    for text in [b"you 1d10+ there", b"an a$$ here", b"so stuupid it is", b"i  d  i  o  t", b"s.t..u.p.i.d", b"id*ot!"]:
        assert d.features(text)[1] == 1.0, text
    for text in [b"all letters been good", b"a 1 2 3 4 b", b"look at 10.0.0.1 now", b""]:
        assert d.features(text)[1] == 0.0, text
