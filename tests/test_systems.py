import pytest
from conftest import SF

from cellscrub.operators import fd, measure
from cellscrub.plans import effectiveness as E
from cellscrub.session import materialize
from cellscrub.systems import column_imputer, corrector_ensemble, factor, fd_majority, record_prompt, rule_workflow, signature_detector, staged
from cellscrub.systems.base import apply_best, records

RULES = [fd.Dependency(("postcode",), "locality"), fd.Dependency(("locality",), "country"), fd.Dependency(("country",), "country_code")]


@pytest.fixture(scope="module")
def sample(spark):
    return E.make_sample(materialize(E.classified_cells(spark, SF), "c"), 300, 0.2, fds=RULES)


@pytest.mark.parametrize("name,least", [("signature_detector", 0.7), ("factor", 0.4), ("record_prompt", 0.7), ("flag_all", 0.3)])
def test_detectors(sample, name, least):
    assert measure.detection(sample.cells, E.DETECTORS[name](sample)).first().f1 >= least


@pytest.mark.parametrize("name,least", [("corrector_ensemble", 0.25), ("record_prompt", 0.3), ("fd_majority", 0.1)])
def test_correctors(sample, name, least):
    assert measure.correction(sample.cells, E.CORRECTORS[name](sample)).first().f1 >= least


def test_labels_are_bounded(sample):
    labels = sample.labels(3)
    assert len({r["_id"] for r in labels.draw(50)}) == 3 and len(labels.asked) == 3


def test_dependencies_hold_after_repair(spark, sample):
    done = fd_majority.repaired(sample.dirty, [fd.Dependency(("country",), "country_code")])
    assert fd.holds(done.dropna(subset=["country"]), ["country"], "country_code").first().holds


def test_nothing_to_repair_without_errors(spark, sample):
    clean = records(sample.pairs.select("_id", *[sample.pairs[f"c_{a}"].alias(f"d_{a}") for a in E.ATTRS]))
    assert fd_majority.correct(clean, RULES).count() == 0


def test_attributes_outside_every_rule_stay(sample):
    got = fd_majority.correct(sample.dirty, RULES)
    assert got.filter("attr IN ('name', 'house_number', 'road', 'postcode')").count() == 0


def test_recall_by_rate_and_precision(spark):
    """More errors, better precision of a fixed detector: the class balance effect."""
    cells = materialize(E.classified_cells(spark, SF), "c")
    p = [measure.detection(s.cells, E.DETECTORS["flag_all"](s)).first().f1 for s in (E.make_sample(cells, 300, r, fds=[]) for r in (0.05, 0.2))]
    assert p[0] < p[1]


def test_prompts_are_deduplicated_and_bad_json_is_counted(spark, sample):
    twice = sample.dirty.union(sample.dirty)
    cost = record_prompt.cost(twice, record_prompt.RulebookCompleter(failing=10)).first()
    assert cost.calls <= 2 * sample.dirty.count() and cost.bad_json > 0


def test_ladder_changes_one_thing_at_a_time():
    steps = rule_workflow.ladder()
    assert [s.sampling for s in steps] == ["coreset", "full", "full", "full"] and [s.max_lhs for s in steps] == [3, 3, 2, 2] and steps[3].single_max < steps[2].single_max


def test_clusters_and_choice():
    weighted = {"000": 10, "001": 5, "110": 2, "111": 1}
    got = signature_detector.clusters(weighted, 2)
    assert got["000"] == got["001"] != got["110"] == got["111"]
    assert signature_detector.choose_tuples({"a": {"x": 0, "y": 0}, "b": {"x": 1, "y": 1}, "c": {"x": 0, "y": 1}}, 2) == ["a", "b"]


def test_one_pass_repair_equals_plain_counting(spark, sample):
    """Two rules for one right side, taken from the same state: most support wins, then the largest value; a blank left
    side proposes nothing."""
    from collections import Counter

    rules = [fd.Dependency(("postcode",), "region"), fd.Dependency(("locality", "country"), "region"), fd.Dependency(("postcode",), "locality")]
    rows = [r.asDict() for r in sample.dirty.collect()]
    wanted = {r["_id"]: {"region": [], "locality": []} for r in rows}
    for rule in rules:
        known = [r for r in rows if all(r[a] is not None for a in rule.lhs)]
        counts = Counter((tuple(r[a] for a in rule.lhs), r[rule.rhs]) for r in known if r[rule.rhs] is not None)
        best = {}
        for (key, v), n in counts.items():
            if key not in best or (-n, v) < best[key]:
                best[key] = (-n, v)
        for r in known:
            if (key := tuple(r[a] for a in rule.lhs)) in best:
                n, v = best[key]
                wanted[r["_id"]][rule.rhs].append((-n, v))
    got = apply_best(sample.dirty, rules, fd_majority.best_values(sample.dirty, rules)).collect()
    assert len(got) == len(rows)
    before = {r["_id"]: r for r in rows}
    for r in got:
        for a, offers in wanted[r._id].items():
            assert r[a] == (max(offers)[1] if offers else before[r._id][a])


def _joins(df):
    return df._jdf.queryExecution().optimizedPlan().toString().count("Join ")


def test_violations_take_one_pass_for_all_rules(sample):
    """The plan does not grow with the rules, and the cells are those of plain counting."""
    from collections import Counter, defaultdict

    rules = [fd.Dependency(lhs, rhs) for lhs, rhs in ((("postcode",), "region"), (("postcode",), "locality"), (("locality", "country"), "region"), (("locality",), "country"), (("country",), "country_code"), (("road",), "locality"))]
    for found in (factor.violating, signature_detector.violating_minority):
        assert _joins(found(sample.dirty, rules)) == _joins(found(sample.dirty, rules[:1]))
    wrong, minor = set(), {}
    for rule in rules:
        groups = defaultdict(Counter)
        known = [r for r in sample.dirty.collect() if all(r[a] is not None for a in (*rule.lhs, rule.rhs))]
        for r in known:
            groups[tuple(r[a] for a in rule.lhs)][r[rule.rhs]] += 1
        for r in known:
            if len(counts := groups[tuple(r[a] for a in rule.lhs)]) > 1:
                wrong.add((r._id, rule.rhs))
                minor[r._id, rule.rhs] = minor.get((r._id, rule.rhs), False) or counts[r[rule.rhs]] < max(counts.values())
    assert wrong and {tuple(r) for r in factor.violating(sample.dirty, rules).collect()} == wrong
    assert {(r._id, r.attr): r.minor for r in signature_detector.violating_minority(sample.dirty, rules).collect()} == minor


def test_sources_of_candidates_are_planned_once(sample, monkeypatch):
    """What is planned at once stays small, as the driver holds it for every system under way."""
    joins = []
    for module in (factor, corrector_ensemble):
        monkeypatch.setattr(module, "materialize", lambda df, label: (joins.append(_joins(df)), materialize(df, label))[1])
    joins.append(_joins(factor.candidates(sample.dirty, sample.errors, RULES)))
    joins.append(_joins(corrector_ensemble.proposals(sample.dirty, sample.errors, sample.labels().draw())))
    assert max(joins) <= 6


def test_poi_by_category_runs_one_system_at_a_time(spark, sample, monkeypatch):
    import threading

    from cellscrub import queries

    who = []
    monkeypatch.setattr(queries, "SYSTEMS", {"detect": ("flag_missing", "flag_all"), "correct": ("column_mode",)})
    monkeypatch.setattr(queries, "_poi_sample", lambda *a: sample)
    monkeypatch.setattr(queries, "materialize", lambda df, label: (who.append(threading.get_ident()), materialize(df, label))[1])
    assert queries.QUERIES["poi_by_category"](spark, SF).count() > 0 and set(who) == {threading.get_ident()}


def test_factor_fits_on_columns_not_on_rows(sample, monkeypatch):
    """The weights of plain rows, without the driver making one Python object a candidate."""
    import numpy as np

    made = []
    monkeypatch.setattr(factor, "candidates", lambda *a, f=factor.candidates, **b: (made.append(materialize(f(*a, **b), "seen")), made[-1])[1])
    with monkeypatch.context() as m:
        m.setattr(type(sample.dirty), "collect", lambda *a: pytest.fail("rows came to the driver"))
        got = factor.fit(sample.dirty, factor.detect(sample.dirty, RULES), RULES)
    shown = {(r._id, r.attr): r.x for r in made[0].selectExpr("_id", "attr", "pmod(xxhash64(_id, attr), 2) AS x").distinct().collect()}
    groups = {}
    for r in made[0].collect():
        groups.setdefault((r._id, r.attr), []).append(([r[f] * (shown[r._id, r.attr] if f == "own_value" else 1) for f in factor.FEATURES], r.v == r.own))
    data = [(np.array([x for x, _ in g]), np.array([y for _, y in g])) for g in groups.values() if any(y for _, y in g) and len(g) > 1]
    w = np.zeros(len(factor.FEATURES))
    for _ in range(20):
        p = [np.exp(x @ w - (x @ w).max()) for x, _ in data]
        w = w + 0.3 * sum(x[y].sum(0) - (q / q.sum()) @ x for (x, y), q in zip(data, p)) / len(data)
    assert len(data) > 10 and np.allclose(got, w)


def test_no_rules_change_nothing(sample):
    assert fd_majority.correct(sample.dirty, []).count() == 0
    assert rule_workflow._violations(sample.dirty, [], rule_workflow.Config())["dependency"] == 0


def test_imputer_learns_a_column_from_the_others():
    truth = [{"_id": f"{i:02}", "attr": a, "dirty": v, "clean": v} for i in range(20) for a, v in (("country", "NO" if i % 2 else "SE"), ("locality", "Oslo" if i % 2 else "Lund"), ("region", None if i % 3 else "x"))]
    model = column_imputer.fit(truth, "country")
    scores = {v: model.bias + model.weigh("locality", v) for v in ("Oslo", "Lund")}
    assert model.values == ["NO", "SE"] and scores["Oslo"].argmax() == 0 and scores["Lund"].argmax() == 1
    assert column_imputer.fit(truth, "road").values == [] and column_imputer.fit([], "road").values == []
    assert column_imputer.fit([t | {"clean": "SE"} for t in truth], "country").values == ["SE"]


def test_imputer_answers_every_cell(spark, sample):
    got = column_imputer.predict(sample.dirty, sample.labels())
    assert got.count() == 8 * sample.dirty.count() and got.filter("score < 0 OR score > 1 OR score IS NULL").count() == 0
    assert column_imputer.predict(sample.dirty.limit(0), sample.labels()).count() == 0
    blank = sample.dirty.selectExpr("_id", *[f"CAST(NULL AS STRING) AS {a}" for a in E.ATTRS])
    assert column_imputer.predict(blank, sample.labels()).filter("value IS NOT NULL").count() == 0


def test_poi_by_category_learns_and_repairs_once_for_both_tasks(spark, sample, monkeypatch):
    """Every system that serves both tasks, and factor's rules, run once a slice; the scores are those of the systems by themselves."""
    from cellscrub import queries
    from cellscrub.systems import factor

    runs = []
    for module, name in ((fd_majority, "repaired"), (rule_workflow, "repaired"), (factor, "cooccurrence")):
        monkeypatch.setattr(module, name, lambda *a, f=getattr(module, name), m=module, **b: (runs.append(m), f(*a, **b))[1])
    monkeypatch.setattr(queries, "SYSTEMS", {"detect": ("fd_majority", "rule_workflow", "factor"), "correct": ("factor", "fd_majority", "rule_workflow")})
    monkeypatch.setattr(queries, "_poi_sample", lambda *a: sample)
    got = {(r.slice, r.task, r.system, r.category): (r.n_true, r.tp, r.score) for r in queries.QUERIES["poi_by_category"](spark, SF).collect()}
    assert sorted(m.__name__ for m in runs) == sorted(2 * [m.__name__ for m in (fd_majority, rule_workflow, factor)])
    for task, table, score in (("detect", E.DETECTORS, measure.recall_by_category), ("correct", E.CORRECTORS, measure.f1_by_category)):
        for name in ("fd_majority", "rule_workflow", "factor"):
            want = {r.category: (r.n_true, r.tp, r[-1]) for r in score(sample.cells, table[name](sample)).collect()}
            for kind in ("library", "shopping_center"):
                assert {k[3]: v for k, v in got.items() if k[:3] == (kind, task, name)} == want


def test_simple_rules_take_known_values_only(spark):
    values = ["Main Road"] * 3 + ["MAIN ROAD", "Main-Road", "Main Road.", "&#77;ain Road", "OTHER"]
    rows = [(str(i), *[v if a == "road" else None for a in E.ATTRS]) for i, v in enumerate(values)]
    dirty = spark.createDataFrame(rows, ", ".join(f"{c} string" for c in ("_id", *E.ATTRS)))
    cells = dirty.selectExpr("_id", "'road' AS attr").filter("_id > 2")
    assert sorted((r._id, r.repair) for r in staged.simple_rules(dirty, cells).collect()) == [(str(i), "Main Road") for i in range(3, 7)]


def test_stages_repair_each_cell_once(sample):
    got = staged.correct(sample.dirty, sample.errors, sample.fds, sample.labels())
    counts = {r.stage: r["count"] for r in got.groupBy("stage").count().collect()}
    assert counts["rules"] > 0 and set(counts) <= {"rules", "dependencies", "ensemble", "prompt"}
    assert got.select("_id", "attr").distinct().count() == got.count()
    assert got.join(sample.errors, ["_id", "attr"], "left_anti").count() == 0
