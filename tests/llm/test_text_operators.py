import hashlib
import random
import re
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from cellscrub.llm import chat_events, deobfuscation, hidden_markov, jaccard_join, merge_dropout, pii_votes, quality_hosts, relative_dedup, sharding, winnowing

SCHEMA = "doc_id long, text string, lang string, source string, n_words long, `end` int"


def corpus(seed=1, n=60):
    """Small documents with copies, near copies, shared passages, personal data, nulls and blanks."""
    rng = random.Random(seed)
    words = ["".join(rng.choice("abcdeinorst") for _ in range(rng.randint(2, 7))) for _ in range(400)]
    text = lambda k: " ".join(rng.choice(words) for _ in range(k))
    passage = text(60)
    rows = []
    for i in range(n):
        t = text(rng.randint(1, 120))
        if i % 7 == 1:
            t += "\n" + passage + "\n" + text(5)
        if i % 5 == 2 and rows:
            t = rows[rng.randrange(len(rows))][1] or t
        if i % 5 == 3 and rows and rows[-1][1]:
            cut = rows[-1][1].split(" ")
            cut[len(cut) // 2] = "CHANGED"
            t = " ".join(cut)
        if i % 6 == 0:
            t += " mail me.27@mail6.example.com or +1 (301) 555-0346, from 10.0.0.255 with 4539 5787 6362 1486 and token = \"ede43f42c939b6405768150e0411590525cf889e\""
        rows.append((i, t, "en", f"h{i % 3}", 0, 0))
    return rows + [(900, None, None, None, None, None), (901, "", "en", "h1", 1, 1), (902, " \t\n", "en", "h1", 1, 1), (903, "short one", "en", "h0", 1, 1), rows[0], (None, "no id " + passage, "en", "h0", 0, 0)]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(corpus(), SCHEMA).repartition(3).cache()


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


# 1


def test_pieces_match_the_library_without_dropout_and_decode_with_it():
    import sentencepiece

    model = open(merge_dropout.DEFAULT_MODEL, "rb").read()
    sp = sentencepiece.SentencePieceProcessor(model_proto=model)
    exact, loose = merge_dropout.Codec(model, 0.0), merge_dropout.Codec(model, 0.3)
    rng = random.Random(2)
    texts = ["".join(rng.choice(" ab\n▁éthe ningß漢😀.") for _ in range(rng.randint(0, 60))) for _ in range(300)] + ["a" * 3000, "▁"]
    for t in texts:
        assert exact.decode(exact.encode(t)) == t == loose.decode(loose.encode(t, 7))
        if "▁" not in t:
            assert np.frombuffer(exact.encode(t), exact.code).tolist() == sp.encode(t)
    units = [(" " + "".join(rng.choice("abthening") for _ in range(rng.randint(1, 20))), v) for v in range(4) for _ in range(200)]
    assert loose.segment_many(units) == [np.array(loose.segment(u, v), loose.code).tobytes() for u, v in units]
    word = " thenanother"
    assert len({loose.segment_many([(word, v)])[0] for v in range(30)}) > 3
    again = merge_dropout.Codec(model, 0.3)
    assert [again.encode(t, 3) for t in texts[:50]] == [loose.encode(t, 3) for t in texts[:50]]


def test_every_occurrence_draws_its_own_skips():
    model = open(merge_dropout.DEFAULT_MODEL, "rb").read()
    codec = merge_dropout.Codec(model, 0.1)
    text = "another thing happened yesterday"
    copies = codec.encode_many([text] * 3000, list(range(3000)))
    assert len(set(copies)) > 100 and copies == merge_dropout.Codec(model, 0.1).encode_many([text] * 3000, list(range(3000)))
    word = "yesterday"
    whole = merge_dropout.Codec(model, 0.0).encode(word)
    keys = np.random.default_rng(1).integers(0, 2**63, 4000).astype(np.uint64)
    within = codec.segment_many([(" " + word, int(k)) for k in keys])
    assert len(set(within)) > 20
    # the share without any skip is that of independent draws, one a candidate of the undisturbed agenda
    _, candidates = codec._segment(" " + word, iter(()))
    untouched = codec._gaps(keys, 0) >= candidates
    assert abs(untouched.mean() - 0.9**candidates) < 0.04 and all(w == whole for w, u in zip(within, untouched) if u)
    # repeats within one text do not step through a fixed cycle
    line = np.frombuffer(codec.encode(" ".join([word] * 400), 5), codec.code).tobytes()
    assert line != codec.encode(" ".join([word] * 400), 6) and codec.decode(line) == " ".join([word] * 400)
    # a tree that is pruned all the time gives the same
    small = merge_dropout.Codec(model, 0.1, cache_bound=20)
    assert [small.encode(text, i) for i in range(300)] == copies[:300]


def test_pieces_table(docs, empty):
    out = merge_dropout.decode_documents(merge_dropout.encode_documents(docs))
    assert out.filter("NOT (decoded <=> text)").count() == 0 and out.count() == docs.count()
    assert merge_dropout.encode_documents(empty).count() == 0
    one = merge_dropout.encode_documents(docs.filter("doc_id = 903")).select(merge_dropout.unpack_ids(F.col("piece_ids")).alias("ids")).first()
    assert len(one.ids) > 1


# 2


def test_chat_folds_edits_and_regenerations(spark):
    log = [
        (1, 0, "delta", 0, "user", "Hel"), (1, 1, "delta", 0, "user", "lo <|end|> &lt;"),
        (1, 2, "delta", 1, "assistant", "bad"), (1, 3, "regenerate", 1, "assistant", "go"), (1, 4, "delta", 1, "assistant", "od"),
        (1, 5, "delta", 2, "user", "x"), (1, 6, "edit", 2, "user", "y"), (1, 7, "delta", 3, "user", "gone"), (1, 8, "delete", 3, None, None), (2, 0, "delta", 0, "assistant", None),
    ]
    df = spark.createDataFrame(log, "conv_id long, seq long, op string, message long, role string, text string")
    got = {r.conv_id: r for r in chat_events.read_back(chat_events.render(chat_events.fold_events(df))).collect()}
    assert [(t.role, t.text) for t in got[1].turns] == [("user", "Hello <|end|> &lt;"), ("assistant", "good"), ("user", "y")] and got[1].loss_text == "good"
    assert [(t.role, t.text) for t in got[2].turns] == [("assistant", "")] and got[2].loss_text == ""


def test_chat_ties_and_nulls(spark):
    rows = [(1, 0, "user", "b"), (1, 0, "user", "a"), (1, 0, "user", "a"), (1, None, None, None)]
    turns = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    back = chat_events.read_back(chat_events.render(chat_events.fold_events(chat_events.table_events(turns)))).first()
    assert [(t.role, t.text) for t in back.turns] == [("", ""), ("user", "a"), ("user", "a"), ("user", "b")]


# 3


def test_quality_statistics_by_hand(docs, empty):
    def brute(t):
        w = re.findall(r"[^\x20\x09-\x0D]+", t or "")
        lines, seen, dup = (t or "").split("\n"), set(), 0
        for x in lines:
            if re.search(r"[^\x20\x09-\x0D]", x):
                dup += x in seen
                seen.add(x)
        grams = [tuple(w[i : i + 5]) for i in range(len(w) - 4)]
        c = Counter(grams)
        rep = {i + j for i, g in enumerate(grams) if c[g] > 1 for j in range(5)}
        return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t or "")), dup, len(rep)

    for t in [r[1] for r in corpus()] + ["é é é é é é é é", "a b\na b\n\n#", "x " * 30, "a b c d e"]:
        assert quality_hosts.text_stats(t.encode() if t is not None else None) == brute(t), t
    out = quality_hosts.judge(docs)
    assert out.count() == docs.count() and out.filter("kept AND base_failed").count() == 0
    assert quality_hosts.judge(empty).count() == 0 and quality_hosts.filter_documents(empty).count() == 0
    kept = quality_hosts.filter_documents(docs)
    assert kept.columns == docs.columns and kept.count() == out.filter("kept").count()


def test_bad_hosts_lose_their_documents(spark):
    rows = [(i, "word " * 40 if i % 2 else " ".join(f"w{j}" for j in range(40)), "bad" if i < 100 and (i % 2 or i < 20) else "good") for i in range(400)]
    df = spark.createDataFrame([(i, "x" if h == "bad" and i > 20 else t, h) for i, t, h in rows], "doc_id long, text string, source string")
    got = quality_hosts.judge(df)
    assert got.filter("host = 'bad' AND kept").count() == 0 and got.filter("host = 'good' AND kept").count() > 0


# 4

PATTERNS = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}


def base_spans(t):
    def ok(kind, m):
        d = re.sub(r"[^0-9]", "", m)
        if kind == "ip":
            return all(int(x) <= 255 for x in m.split("."))
        if kind == "phone":
            return 8 <= len(d) <= 15
        if kind == "card":
            s = sum(int(c) if i % 2 == 0 else sum(divmod(2 * int(c), 10)) for i, c in enumerate(reversed(d)))
            return 16 <= len(d) <= 19 and s % 10 == 0
        return True

    return [(k, m.start(), m.end()) for k, p in PATTERNS.items() for m in re.finditer(p, t or "") if ok(k, m.group())]


def test_personal_data_against_plain_patterns(spark, docs, empty):
    rng = random.Random(5)
    odd = ["".join(rng.choice("0123456789.@+- ()ab%_é") for _ in range(rng.randint(0, 60))) for _ in range(400)] + ["a@b.c_d@e.f", "1.2.3.4.5.6.7.8", "1" * 5000, "1 " * 3000, "+1 (301) 555-0346 4539578763621486", "😀 x@y.zz", "0004.1.1.1 256.1.1.1"]
    df = spark.createDataFrame([(i, t) for i, t in enumerate(odd)], "doc_id long, text string").unionByName(docs.filter("doc_id IS NOT NULL").select((docs.doc_id + 10000).alias("doc_id"), "text"))
    got = {(r.doc_id, r.text_key): [(s.kind, s.start, s.end) for s in r.spans if s.k <= 4] for r in pii_votes.document_spans(df).collect()}
    for r in df.select("doc_id", "text", F.expr("xxhash64(coalesce(text, ''))").alias("k")).distinct().collect():
        assert got.get((r.doc_id, r.k), []) == base_spans(r.text), r.text
    masked = pii_votes.mask_documents(docs)
    assert masked.columns == docs.columns and masked.count() == docs.count()
    text = masked.filter("doc_id = 0").first().text
    assert "[EMAIL]" in text and "[CARD]" in text and "[SECRET]" in text and "4539" not in text
    assert pii_votes.mask_documents(empty).count() == 0


def test_labelers_reliability():
    patterns = [((1, 1, 1, 1), 50.0), ((1, 0, 0, 1), 20.0), ((-1, -1, -1, -1), 60.0), ((0, 0, 0, -1), 40.0), ((-1, 1, 0, -1), 2.0)]
    prior, tables, chance = pii_votes.estimate_reliability(patterns)
    assert chance[1, 1, 1, 1] > 0.9 > 0.1 > chance[-1, -1, -1, -1] and all(t[1][0] > t[1][1] for t in tables)
    assert pii_votes.estimate_reliability([])[2] == {}


# 5


def test_shards_are_gapless_and_even(docs, empty):
    rows = sharding.assign_shards(docs).collect()
    assert len(rows) == docs.count()
    by: dict[int, list] = {}
    for r in rows:
        by.setdefault(r.shard, []).append(r)
    total, largest = sum(r.size for r in rows), max(r.size for r in rows)
    assert all(sorted(r.slot for r in x) == list(range(len(x))) for x in by.values())
    assert all(abs(sum(r.size for r in x) - total / 8) <= largest for x in by.values())
    texts = {r.doc_id: r.text or "" for r in docs.collect()}
    assert all(r.text_crc32 == zlib.crc32(texts[r.doc_id].encode()) and r.size == len(texts[r.doc_id].encode()) + 1 for r in rows)
    order = [r.doc_id for r in sorted(rows, key=lambda r: (r.shard, r.slot)) if r.doc_id is not None]
    assert order == sorted(order) and sharding.assign_shards(empty).count() == 0


# 6


def test_repeated_windows_by_brute_force(docs, empty):
    rows = docs.select("doc_id", "text").collect()
    words = [re.findall(r"[^\x20\x09-\x0D]+", r.text or "") for r in rows]
    count = Counter(tuple(w[i : i + 35]) for w in words for i in range(len(w) - 34))
    want = []
    for r, w in zip(rows, words):
        gone = {i + j for i in range(len(w) - 34) if count[tuple(w[i : i + 35])] > 1 for j in range(35)}
        want.append((r.doc_id, len(w), len(gone), hashlib.sha256(" ".join(x for i, x in enumerate(w) if i not in gone).encode()).hexdigest()))
    got = [(r.doc_id, r.n_words, r.n_removed, r.kept_sha256) for r in relative_dedup.duplicate_factors(docs).collect()]
    assert sorted(got, key=str) == sorted(want, key=str) and any(w[2] for w in want)
    # with a bitmap so small that all anchors look repeated, the result is the same
    tiny = [(r.doc_id, r.n_words, r.n_removed, r.kept_sha256) for r in relative_dedup.duplicate_factors(docs, bitmap_bits=11).collect()]
    assert sorted(tiny, key=str) == sorted(want, key=str) and relative_dedup.duplicate_factors(empty).count() == 0


# 7


def test_forward_recursion_and_scores(docs, empty):
    rng = np.random.default_rng(0)
    m = hidden_markov.Model(rng.dirichlet(np.ones(3)), rng.dirichlet(np.ones(3), 3), rng.dirichlet(np.ones(6), 3))
    sequences = [rng.integers(0, 6, n).astype(np.uint16) for n in (1, 2, 5, 30, 17, 64, 200)]

    def plain(s):
        a, logs = m.start * m.emit[:, s[0]], 0.0
        for t in range(len(s)):
            a = (a @ m.move) * m.emit[:, s[t]] if t else a
            logs += np.log10(a.sum())
            a = a / a.sum()
        return logs

    assert np.allclose(hidden_markov.log_likelihoods(sequences, m, 16), [plain(s) for s in sequences])
    whole = [np.zeros(3), np.zeros((3, 3)), np.zeros((6, 3))]  # plain Baum-Welch over uncut sequences
    for q in sequences:
        a, b = np.zeros((len(q), 3)), np.ones((len(q), 3))
        for t in range(len(q)):
            a[t] = ((a[t - 1] @ m.move) if t else m.start) * m.emit[:, q[t]]
            a[t] /= a[t].sum()
        for t in range(len(q) - 2, -1, -1):
            b[t] = m.move @ (m.emit[:, q[t + 1]] * b[t + 1])
            b[t] /= b[t].sum()
        g = a * b / (a * b).sum(1, keepdims=True)
        whole[0] += g[0]
        for t in range(len(q)):
            whole[2][q[t]] += g[t]
            if t:
                xi = a[t - 1][:, None] * m.move * (m.emit[:, q[t]] * b[t])[None, :]
                whole[1] += xi / xi.sum()
    for block in (7, 16, 1000):
        start, move, emit, logs = hidden_markov.expected_counts(sequences, m, block)
        assert np.allclose(start, whole[0]) and np.allclose(move, whole[1]) and np.allclose(emit, whole[2]) and np.isclose(logs, sum(map(plain, sequences)))
    out = hidden_markov.score_documents(docs, emitted_words=50, lookup_words=120, shared_classes=40).collect()
    counts: Counter = Counter()
    for r in docs.collect():
        if not hidden_markov.held_out(r.doc_id):
            counts.update([*(r.text or "").lower().split(), None])
    n, v = sum(counts.values()), len(counts)
    texts = {r.doc_id: r.text for r in docs.collect()}
    for r in out:
        tokens = [*(texts[r.doc_id] or "").lower().split(), None]
        assert (r.n_tokens, r.n_known, r.train_tokens) == (len(tokens), sum(t in counts for t in tokens), n)
        assert abs(r.base_score - sum(np.log10((counts[t] + 0.1) / (n + 0.1 * (v + 1))) for t in tokens)) < 1e-6
    assert hidden_markov.score_documents(empty).count() == 0


def test_model_sums_to_one_over_the_vocabulary():
    counts = {b"a": 5.0, b"b": 3.0, b"c": 1.0, b"d": 1.0}
    masses = np.full(2, 0.1)
    for w in (b"b", b"c", b"d"):
        masses[hidden_markov.shared_class(w, 2)] += counts[w] + 0.1
    v = hidden_markov.Vocabulary([b"a", b"b"], np.array([5.0, 3.0]), 14, 5, 4, 1, masses)
    shares = v.class_shares()
    assert np.isclose(shares.sum(), 1) and v.codes().tolist() == [3, 1 + hidden_markov.shared_class(b"b", 2)]
    within = [(counts[w] + 0.1) / masses[hidden_markov.shared_class(w, 2)] for w in (b"b", b"c", b"d")] + [0.1 / m for m in masses]
    assert np.isclose(sum(within), 2)  # the words and the unseen type of both classes


def test_held_out_text_is_likelier_than_under_the_base(spark):
    out = hidden_markov.score_documents(spark.read.parquet("/root/testdata/sf0.01/documents.parquet")).filter("held_out")
    r = out.agg(F.sum("score").alias("s"), F.sum("base_score").alias("b"), F.sum("n_tokens").alias("n")).first()
    print("held out, log10 a token:", r.s / r.n, r.b / r.n)
    assert r.s / r.n > r.b / r.n + 0.1


# 8


def test_benchmark_hits_by_brute_force(spark, docs, empty):
    texts = [r.text for r in docs.filter("text IS NOT NULL").collect()]
    cut = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
    long = [t for t in texts if len(cut(t)) > 40]
    items = [("b1", " ".join(cut(long[0])[5:30])), ("b2", "Short One"), ("b3", None), ("b4", ", ".join(cut(long[1])[3:13])), ("b5", "absent words here")]
    bench = spark.createDataFrame(items, "item_id string, text string")
    for limit in (winnowing.BROADCAST_LIMIT, 0):
        hits = winnowing.hits(docs, bench, broadcast_limit=limit).collect()
        want = set()
        for r in docs.collect():
            w = cut(r.text)
            for i, t in items:
                b = cut(t)
                k = min(10, len(b))
                if k:
                    grams = {tuple(b[j : j + k]) for j in range(len(b) - k + 1)}
                    want |= {(r.doc_id, p + 1, k, i) for p in range(len(w) - k + 1) if tuple(w[p : p + k]) in grams}
        assert {(h.doc_id, h.place, h.width, h.item_id) for h in hits} == want and want
    out = winnowing.contamination(docs, bench)
    assert out.count() == docs.count() and out.filter("contaminated").count() == docs.count() - winnowing.clean_documents(docs, bench).count()
    none = spark.createDataFrame([], "item_id string, text string")
    assert winnowing.contamination(docs, none).filter("contaminated").count() == 0 and winnowing.contamination(empty, bench).count() == 0


# 9


def test_disguises_are_undone():
    words = [b"idiot", b"moron", b"stupid", b"loser", b"worthless", b"trash"]
    model = deobfuscation.CharacterModel.mixture(np.zeros(27**3), words)
    for place, word in ((b"1d10t", b"idiot"), (b"i d i o t", b"idiot"), (b"m0r0n", b"moron"), (b"$tup1d", b"stupid"), (b"looooser", b"loser"), (b"w0rthl3ss", b"worthless"), (b"tr@sh", b"trash"), (b"l.o.s.e.r", b"loser")):
        found = deobfuscation.disguised(b"the " + place + b" and that.")
        assert any(word in model.restore(p) for p in found), (place, found)
    assert deobfuscation.disguised(b"plain words, nothing else. A b") == []


def test_toxic_documents_are_found(spark, empty):
    rng = random.Random(3)
    common = ["".join(rng.choice("aeinorst") for _ in range(5)) for _ in range(80)]
    bad = ["idiot", "moron", "stupid", "loser"]
    rows = []
    for i in range(400):
        words = [rng.choice(common) for _ in range(40)]
        toxic = i % 4 == 0
        if toxic:
            words[7], words[20] = rng.choice(bad), rng.choice(["1d10t", "m0r0n"]) if i % 8 else rng.choice(bad)
        rows.append((i, " ".join(words), int(toxic)))
    docs = spark.createDataFrame([(i, t) for i, t, _ in rows] + [(900, None), (None, "x")], "doc_id long, text string")
    labels = spark.createDataFrame([(i, y) for i, _, y in rows], "doc_id long, toxic int")
    got = {r.doc_id: r for r in deobfuscation.score_documents(docs, labels).collect()}
    assert sum(got[i].predicted == y for i, _, y in rows if got[i].held_out) >= 0.95 * sum(got[i].held_out for i, _, _ in rows)
    assert 0 <= got[900].score < 0.5 and got[None].held_out
    assert deobfuscation.score_documents(docs, labels.limit(0)).filter("predicted = 1").count() == 0


# 10


def components(sets):
    """Smallest member by links of all pairs."""
    least = list(range(len(sets)))
    for _ in sets:
        for i, a in enumerate(sets):
            for j, b in enumerate(sets):
                if a and b and 100 * len(a & b) >= 80 * len(a | b):
                    least[i] = min(least[i], least[j])
    return least


def test_set_links_by_brute_force():
    rng = random.Random(4)
    for trial in range(40):
        sets = []
        for _ in range(25):
            if sets and rng.random() < 0.7:
                base = set(rng.choice(sets))
                for _ in range(rng.randint(0, 4)):
                    base.discard(rng.choice(sorted(base)) if base else 0)
                    base.add(rng.randrange(1000))
            else:
                base = set(rng.sample(range(1000), rng.randint(1, 30)))
            sets.append(base)
        sets.sort(key=len)
        df = Counter(x for s in sets for x in s)
        ordered = [sorted(s, key=lambda x: (df[x], x)) for s in sets]
        roots = jaccard_join.link_sets(ordered, [len(s) - jaccard_join._least_overlap(len(s), 80) + 1 for s in ordered])
        want = components(sets)
        assert len({*zip(roots, want)}) == len(set(roots)) == len(set(want)), trial


def test_join_by_brute_force(docs, empty):
    rows = docs.collect()
    sets = []
    for r in rows:
        w = (r.text or "").lower().split()
        sets.append({tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set())
    least = components(sets)
    ids = lambda i: min((rows[j].doc_id for j in range(len(rows)) if least[j] == least[i] and rows[j].doc_id is not None and sets[i]), default=rows[i].doc_id)
    want = sorted(((r.doc_id, len(sets[i]), ids(i) if sets[i] else r.doc_id) for i, r in enumerate(rows)), key=str)
    got = sorted(((r.doc_id, r.n_shingles, r.component_id) for r in jaccard_join.components(docs).collect()), key=str)
    assert got == want
    kept = jaccard_join.keep_representatives(docs)
    assert kept.columns == docs.columns and len({r.doc_id for r in kept.collect()}) == kept.count()
    assert jaccard_join.components(empty).count() == 0 and jaccard_join.keep_representatives(empty).count() == 0


def test_connected_components(spark):
    edges = [(b"%03d" % (i + 1), b"%03d" % i) for i in range(40)] + [(b"900", b"901")]
    got = {bytes(r.node): bytes(r.head) for r in jaccard_join.connected(spark.createDataFrame(edges, "a binary, b binary")).collect()}
    assert got == {b"%03d" % i: b"000" for i in range(1, 41)} | {b"901": b"900"}
