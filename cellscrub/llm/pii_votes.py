"""Personal data by weak supervision, with built-in functions only.

Four exact kinds (email, ip, card, phone) are always reported. Further candidates (secrets, local phone numbers and
national ids, account numbers) that do not overlap an exact span get votes from a regex, a gazetteer, a context and a shape
labeler, each of which may say yes, no or nothing. The votes are counted by pattern, a table of 81 rows at most, from
which expectation-maximisation estimates every labeler's reliability and each pattern's probability; exact spans take no
part in it. These soft labels train a logistic span classifier on bucketed features, which then decides each candidate as
a column expression.

Span positions come from the lengths of the text between matches, summed over a document's matches, so nothing depends
on the text's length but the scan. The patterns are written so that matching is linear: a match can only start where a
run of its characters starts or where the last match ended, which is where the plain pattern would start too.

Defined results: a null text is empty; repeated rows (same id and text) get equal results; a null id is an id; an empty
table gives an empty result; with no candidate the classifier keeps its prior; other columns are ignored, and kept by
`mask_documents`.
"""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from cellscrub.llm.common import fresh, materialize, read_table

BASE_KINDS = ("email", "ip", "card", "phone")
ADDED_KINDS = ("secret", "local_number", "account")
KINDS = BASE_KINDS + ADDED_KINDS
CONTEXT = 32
MAYBE = "[0-9@]"

PATTERNS = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:\G|(?<![0-9]))[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
    "secret": r"(?<![A-Za-z0-9_-])(?=[A-Za-z_-]*+[0-9])[A-Za-z0-9_-]{16,}+",
    "local_number": r"(?<![0-9A-Za-z.+-])(?:[0-9]{3}-[0-9]{2}-[0-9]{4}|\(?[0-9]{3}\)?[\x20.-][0-9]{3}[.-][0-9]{4})(?![0-9A-Za-z-])",
    "account": r"(?<![0-9A-Za-z.+_-])[0-9]{9,34}+(?![0-9A-Za-z_-])",
}
BYTE_PART = r"^0*(?:[0-9]{1,2}|1[0-9]{2}|2[0-4][0-9]|25[0-5])(?:\.0*(?:[0-9]{1,2}|1[0-9]{2}|2[0-4][0-9]|25[0-5])){3}$"
KEY_WORDS = ("token", "key", "secret", "password", "passwd", "pwd", "bearer", "auth", "credential", "ssn", "social", "tel", "phone", "call", "fax", "mobile", "account", "acct", "iban")
OTHER_WORDS = ("version", "license", "isbn", "page", "chapter", "figure", "section", "table", "http", "www", "commit", "sha")
LABELERS = ("v_regex", "v_gazetteer", "v_context", "v_shape")
FEATURES = ("f_kind", "f_length", "f_digits", "f_before", "f_word")


def _digits(c: Column) -> Column:
    return F.regexp_replace(c, "[^0-9]", "")


def _luhn(digits: Column) -> Column:
    places = F.transform(F.filter(F.split(F.reverse(digits), ""), lambda d: d != ""), lambda d, i: F.when(i % 2 == 0, d.cast("int")).when(d.cast("int") > 4, 2 * d.cast("int") - 9).otherwise(2 * d.cast("int")))
    return F.aggregate(places, F.lit(0), lambda a, d: a + d) % 10 == 0


def _valid() -> Column:
    """Whether a match of a base kind holds; candidates of the added kinds always do."""
    digits = _digits(F.col("match"))
    size = F.length(digits)
    return (
        F.when(F.col("kind") == "ip", F.col("match").rlike(BYTE_PART))
        .when(F.col("kind") == "card", size.between(16, 19) & _luhn(digits))
        .when(F.col("kind") == "phone", size.between(8, 15))
        .when(F.col("kind") == "secret", F.col("match").rlike("[A-Za-z]") & F.col("match").rlike("[0-9]"))
        .otherwise(F.lit(True))
    )


def candidate_spans(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, text_key, kind, start, end (code points, end exclusive), match, before, after; only matches are shuffled."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    slim = docs.select(F.col(id_col).cast("long").alias("doc_id"), text.alias("t")).filter(F.col("t").rlike(MAYBE))
    found = slim.select("doc_id", F.xxhash64("t").alias("text_key"), "t")
    gaps = {k: F.split("t", PATTERNS[k], -1) for k in KINDS}
    hints = {"email": F.contains(F.col("t"), F.lit("@")), "phone": F.contains(F.col("t"), F.lit("+"))}
    empty = F.array().cast("array<string>")
    for kind in KINDS:
        hint = hints.get(kind, F.lit(True))
        found = found.withColumn(f"m_{kind}", F.when(hint, F.regexp_extract_all("t", F.lit(PATTERNS[kind]), F.lit(0))).otherwise(empty))
    some = reduce(lambda a, b: a | b, (F.size(f"m_{k}") > 0 for k in KINDS))
    found = found.filter(some).withColumn("row", F.monotonically_increasing_id())
    for kind in KINDS:
        found = found.withColumn(f"g_{kind}", F.when(F.size(f"m_{kind}") > 0, gaps[kind]).otherwise(empty))
    parts = []
    for kind in KINDS:
        lean = F.transform(f"g_{kind}", lambda g: F.struct(F.length(g).alias("gap"), F.right(g, F.lit(CONTEXT)).alias("before"), F.left(g, F.lit(2)).alias("first")))
        found = found.withColumn(f"g_{kind}", lean)
        parts.append(_joined(kind))
    rows = found.select("row", "doc_id", "text_key", F.explode(F.flatten(F.array(*parts))).alias("s")).select("row", "doc_id", "text_key", "s.*")
    so_far = Window.partitionBy("row", "kind").orderBy("i").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    end = F.sum(F.col("gap") + F.length("match")).over(so_far)
    placed = rows.withColumn("end", end.cast("long")).withColumn("start", F.col("end") - F.length("match"))
    return _clear(placed.filter(_valid()))


def _clear(spans: DataFrame) -> DataFrame:
    """spans of each (doc_id, text_key) once, without candidates that overlap an exact span of the document."""
    every = spans.groupBy("doc_id", "text_key").agg(F.collect_set(F.struct("kind", "start", "end", "match", "before", "after")).alias("every"))
    exact = F.filter("every", lambda s: s["kind"].isin(*BASE_KINDS))
    free = F.filter("every", lambda s: ~s["kind"].isin(*BASE_KINDS) & ~F.exists("exact", lambda b: (b["start"] < s["end"]) & (s["start"] < b["end"])))
    return every.withColumn("exact", exact).select("doc_id", "text_key", F.explode(F.concat("exact", free)).alias("s")).select("doc_id", "text_key", "s.*")


def _joined(kind: str) -> Column:
    return F.transform(f"m_{kind}", lambda m, i: F.struct(F.lit(kind).alias("kind"), i.alias("i"), F.get(f"g_{kind}", i)["gap"].alias("gap"), m.alias("match"), F.get(f"g_{kind}", i)["before"].alias("before"), F.get(f"g_{kind}", i + 1)["first"].alias("after")))


def _vote(yes: Column, no: Column) -> Column:
    return F.when(yes, 1).when(no, -1).otherwise(0)


def with_votes(spans: DataFrame) -> DataFrame:
    """spans with the labelers' votes (1, 0, -1) and the classifier's features."""
    near = lambda words: F.col("before").rlike(r"(?i)(?:^|[^A-Za-z])(?:" + "|".join(words) + r")s?[^A-Za-z0-9]{0,6}$")
    n_digits, size = F.length(_digits(F.col("match"))), F.length("match")
    share = n_digits / size
    hexadecimal = F.col("match").rlike(r"^(?:[0-9a-f]{24,}|[0-9A-F]{24,})$") | F.col("match").rlike(r"^(?:sk|pk|ghp|gho|xox[bp]|AKIA)[A-Za-z0-9_-]{12,}$")
    plain = F.col("match").rlike(r"^[A-Za-z_-]+[0-9]{1,4}$")
    quoted = F.col("before").rlike(r"[=:]\s?[\"']?$") | F.col("before").rlike(r"[\"']$") & F.col("after").rlike(r"^[\"']")
    inside = F.col("before").rlike(r"[A-Za-z/._-]$") | F.col("after").rlike(r"^[/_]")
    kind = F.col("kind")
    digits = _digits(F.col("match"))
    round_number = digits.rlike(r"^(?:19|20)[0-9]{6}(?:[0-9]{4}(?:[0-9]{2})?)?$") | digits.rlike(r"0{6}$")
    return (
        spans.withColumn("v_regex", F.when(kind == "secret", _vote(hexadecimal, plain)).when(kind == "local_number", 1).otherwise(_vote(F.lit(False), round_number)))
        .withColumn("v_gazetteer", _vote(near(KEY_WORDS), near(OTHER_WORDS)))
        .withColumn("v_context", _vote(quoted, inside | (kind == "account") & F.col("before").rlike(r"[a-z]\s$")))
        .withColumn("v_shape", F.when(kind == "secret", _vote(share.between(0.2, 0.95) & (n_digits >= 4), share < 0.1)).when(kind == "account", _vote(_luhn(digits), ~_luhn(digits))).otherwise(0))
        .withColumn("f_kind", F.array_position(F.array(*[F.lit(k) for k in KINDS]), F.col("kind")).cast("int") - 1)
        .withColumn("f_length", F.when(size < 20, 0).when(size < 28, 1).when(size < 48, 2).otherwise(3))
        .withColumn("f_digits", F.when(share < 0.1, 0).when(share < 0.3, 1).when(share < 0.8, 2).otherwise(3))
        .withColumn("f_before", F.when(quoted, 2).when(inside, 1).otherwise(0))
        .withColumn("f_word", F.when(near(KEY_WORDS), 2).when(near(OTHER_WORDS), 1).otherwise(0))
    )


def estimate_reliability(patterns: list[tuple[tuple[int, ...], float]], rounds: int = 60) -> tuple[float, list[dict[int, tuple[float, float]]], dict[tuple[int, ...], float]]:
    """Two-class expectation-maximisation over vote patterns: the prior, for each labeler and vote its probability under
    either class, and each pattern's probability of being personal. Starts from the share of agreeing votes."""
    labelers = len(patterns[0][0]) if patterns else len(LABELERS)
    chance = {v: (1 + sum(x > 0 for x in v)) / (2 + sum(x != 0 for x in v)) for v, _ in patterns}
    prior, tables = 0.5, [{-1: (0.1, 0.4), 0: (0.3, 0.4), 1: (0.6, 0.2)} for _ in range(labelers)]
    for _ in range(rounds if patterns else 0):
        total = sum(n for _, n in patterns)
        yes = sum(n * chance[v] for v, n in patterns)
        prior = (yes + 1) / (total + 2)
        tables = []
        for i in range(labelers):
            table = {}
            for vote in (-1, 0, 1):
                a = sum(n * chance[v] for v, n in patterns if v[i] == vote)
                b = sum(n * (1 - chance[v]) for v, n in patterns if v[i] == vote)
                # a weak pull towards labelers that are right more often than not keeps the classes from swapping
                pull = {-1: (0.5, 2.0), 0: (1.0, 1.0), 1: (2.0, 0.5)}[vote]
                table[vote] = ((a + pull[0]) / (yes + 3.5), (b + pull[1]) / (total - yes + 3.5))
            tables.append(table)
        for v, _ in patterns:
            score = math.log(prior / (1 - prior)) + sum(math.log(tables[i][x][0] / tables[i][x][1]) for i, x in enumerate(v))
            chance[v] = 1 / (1 + math.exp(-max(-40.0, min(40.0, score))))
    return prior, tables, chance


def train_span_classifier(rows: list[tuple[tuple[int, ...], float, float]], rounds: int = 200, rate: float = 0.5, decay: float = 1e-3) -> tuple[float, list[dict[int, float]]]:
    """Logistic weights of bucketed features from (features, weight, soft label), by full gradient steps."""
    total = sum(w for _, w, _ in rows)
    bias, weights = 0.0, [{} for _ in FEATURES]
    for f, _, _ in rows:
        for i, x in enumerate(f):
            weights[i].setdefault(x, 0.0)
    for _ in range(rounds if total else 0):
        grad_b, grads = 0.0, [dict.fromkeys(w, 0.0) for w in weights]
        for f, w, y in rows:
            p = 1 / (1 + math.exp(-max(-40.0, min(40.0, bias + sum(weights[i][x] for i, x in enumerate(f))))))
            d = w * (y - p) / total
            grad_b += d
            for i, x in enumerate(f):
                grads[i][x] += d
        bias += rate * grad_b
        for i in range(len(weights)):
            for x in weights[i]:
                weights[i][x] += rate * 4 * grads[i][x] - decay * weights[i][x]
    return bias, weights


def detect(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", threshold: float = 0.5) -> DataFrame:
    """doc_id, text_key, kind, start, end, probability: exact spans and accepted candidates. What reaches the driver is
    counts by vote pattern and feature bucket."""
    spans = materialize(with_votes(candidate_spans(docs, id_col, text_col)), "pii-spans")
    base = F.col("kind").isin(*BASE_KINDS)
    counts = [(tuple(r[c] for c in LABELERS), tuple(r[c] for c in FEATURES), float(r["n"])) for r in spans.filter(~base).groupBy(*LABELERS, *FEATURES).agg(F.count("*").alias("n")).collect()]
    by_votes: dict[tuple[int, ...], float] = {}
    for v, _, n in counts:
        by_votes[v] = by_votes.get(v, 0.0) + n
    _, _, chance = estimate_reliability(sorted(by_votes.items()))
    bias, weights = train_span_classifier([(f, n, chance[v]) for v, f, n in sorted(counts)])
    score = F.lit(bias)
    for name, table in zip(FEATURES, weights):
        for value, weight in sorted(table.items()):
            score = score + F.when(F.col(name) == value, weight).otherwise(0.0)
    return spans.select("doc_id", "text_key", "kind", "start", "end", F.when(base, 1.0).otherwise(1 / (1 + F.exp(-score))).alias("probability")).filter(F.col("probability") >= threshold)


def document_spans(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, text_key, spans array<struct<k, start, end, kind>> by kind as listed, then start; documents with spans."""
    order = F.array_position(F.array(*[F.lit(k) for k in KINDS]), F.col("kind")).cast("int").alias("k")
    return detect(docs, id_col, text_col).groupBy("doc_id", "text_key").agg(F.array_sort(F.collect_list(F.struct(order, "start", "end", "kind"))).alias("spans"))


def _with_spans(docs: DataFrame, id_col: str, text_col: str, keep: list) -> tuple[DataFrame, str]:
    """docs with their spans, and that column's name, which clashes with none of theirs."""
    own, key, spans, doc, hashed = (fresh(docs, f"__{n}") for n in ("own", "key", "spans", "doc", "hash"))
    found = materialize(document_spans(docs, id_col, text_col), "pii-documents").select(F.col("doc_id").alias(own), F.col("text_key").alias(key), F.col("spans").alias(spans))
    rows = docs.select(*keep, F.col(id_col).cast("long").alias(doc), F.xxhash64(F.coalesce(F.col(text_col).cast("string"), F.lit(""))).alias(hashed))
    return rows.join(found, F.col(doc).eqNullSafe(F.col(own)) & (F.col(hashed) == F.col(key)), "left"), spans


def mask_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs, all columns and rows, with every span of the text replaced by its kind in brackets.

    Rows without a digit or an at sign pass unchanged; only the others meet their spans in a join.
    """
    some = F.coalesce(F.col(text_col).rlike(MAYBE), F.lit(False))
    both, spans = _with_spans(docs.filter(some), id_col, text_col, [F.col(f"`{c}`") for c in docs.columns])
    order = F.array_sort(F.transform(spans, lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"), s["kind"].alias("kind"))))
    text = F.col(text_col)
    start = F.struct(F.lit(0).cast("long").alias("at"), F.array().cast("array<string>").alias("parts"))
    step = lambda a, s: F.when(s["start"] >= a["at"], F.struct(s["end"].alias("at"), F.concat(a["parts"], F.array(F.substring(text, (a["at"] + 1).cast("int"), (s["start"] - a["at"]).cast("int")), F.concat(F.lit("["), F.upper(s["kind"]), F.lit("]")))).alias("parts"))).otherwise(F.struct(F.greatest(a["at"], s["end"]).alias("at"), a["parts"].alias("parts")))
    masked = F.aggregate(order, start, step, lambda a: F.concat(F.array_join(a["parts"], ""), F.substring(text, (a["at"] + 1).cast("int"), F.length(text))))
    done = both.select(*[F.when(F.col(spans).isNull(), text).otherwise(masked).alias(c) if c == text_col else F.col(f"`{c}`") for c in docs.columns])
    return docs.filter(~some).unionByName(done)


def pii_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    both, found = _with_spans(docs.select("doc_id", "text"), "doc_id", "text", ["doc_id"])
    spans = F.coalesce(found, F.array().cast("array<struct<k: int, start: bigint, end: bigint, kind: string>>"))
    written = lambda a: F.array_join(F.transform(a, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")
    count = lambda k: F.size(F.filter(spans, lambda s: s["kind"] == k)).cast("long").alias(f"n_{k}")
    exact = F.filter(spans, lambda s: s["k"] <= len(BASE_KINDS))
    return both.select("doc_id", *[count(k) for k in KINDS], F.size(spans).cast("long").alias("n_spans"), F.sha2(F.encode(written(exact), "utf-8"), 256).alias("base_sha256"), written(spans).alias("spans"))
