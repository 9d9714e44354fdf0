"""Worked cases and invariants of the method."""

import hashlib
from collections import Counter
from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from lakeadapt.baselines import methods
from lakeadapt.functions.draws import draw
from lakeadapt.functions.features import WIDTH, encode, gram_buckets, packed_array, row_of, vector_of, vectors_of
from lakeadapt.functions.vectors import phi
from lakeadapt.operators import cost, gap, head, metrics, process, typesets, weak
from lakeadapt.operators.judge import ClientJudge, KnowledgeJudge, NoisyJudge, Proposal, prompt_text
from lakeadapt.operators.adapt import ArrayLake, Config, SparkLake, adapt, drawn
from lakeadapt.operators.process import GroundTruth, knowledge_base
from lakeadapt.operators.typer import Typer, contrastive, fit, gradients, realign, score, softmax
from lakeadapt.sources import catalog
from lakeadapt.sources.store import RunStore
from lakeadapt.workloads.checks import EXAMPLE


def toy(n=240, types=6, width=12, seed=0):
    rng = np.random.default_rng(seed)
    centres = rng.normal(0, 2, (types, width))
    y = rng.integers(0, types, n)
    x = centres[y] + rng.normal(0, 1, (n, width))
    ids = [f"t{k // 3}#{k % 3}" for k in range(n)]
    split = ["test" if (k // 3) % 10 == 0 else "valid" if (k // 3) % 10 == 1 else "train" for k in range(n)]
    return ids, [i.split("#")[0] for i in ids], split, x, [f"s{k}" for k in y], tuple(f"s{k}" for k in range(types))


CFG = Config(iterations=4, budget=80, warm_tables=4, batch=10, probe=20, kmeans_rounds=3, patience=10)


def lake_and_start(seed=0):
    ids, tables, split, x, y, types = toy(seed=seed)
    return ArrayLake(ids, tables, split, x, y), Typer.new(types, x.shape[1], 1)


def test_phi_is_the_softmax_maximum_and_stable(spark):
    cases = [[1.0, 2.0, 3.0], [5.0, 5.0], [1000.0, 999.0], [-1e6, -1e6 - 1], [0.3]]
    got = spark.createDataFrame([(c,) for c in cases], "v array<double>").select(phi("v")).collect()
    for c, (g,) in zip(cases, got):
        assert g == pytest.approx(softmax(np.array([c])).max())


def test_gradient_by_finite_difference():
    rng = np.random.default_rng(1)
    t = Typer.new(("a", "b", "c"), 5, 1, hidden=4)
    x, y = rng.normal(size=(7, 5)), np.array([0, 1, 2, 0, 1, 2, 2])
    grads = gradients(t, x, y)
    for name, w in t.weights().items():
        for at in [(0,) * w.ndim, tuple(s - 1 for s in w.shape)]:
            keep, eps = w[at], 1e-6
            w[at] = keep + eps
            up = t.loss(x, y)
            w[at] = keep - eps
            down = t.loss(x, y)
            w[at] = keep
            assert grads[name][at] == pytest.approx((up - down) / 2 / eps, abs=1e-6)


def test_fit_lowers_the_loss_and_leaves_the_start_alone():
    _, _, _, x, y, types = toy()
    t = Typer.new(types, x.shape[1], 1)
    before = t.w1.copy()
    out = fit(t, x, t.encode_types(y), epochs=5)
    assert out.loss(x, t.encode_types(y)) < t.loss(x, t.encode_types(y)) / 2
    assert np.array_equal(before, t.w1)


def test_contrastive_pulls_views_together():
    rng = np.random.default_rng(0)
    a = rng.normal(size=(128, 10))
    b = a + rng.normal(0, 0.3, a.shape)
    t = Typer.new(("x",), 10, 1)

    def margin(t):
        ha, hb = (t.hidden(v) / np.linalg.norm(t.hidden(v), axis=1, keepdims=True) for v in (a, b))
        s = ha @ hb.T
        return np.diag(s).mean() - (s.sum() - np.trace(s)) / (128 * 127)

    assert margin(contrastive(t, a, b, epochs=5)) > margin(t)


def test_realign_copies_shared_columns_and_keeps_the_encoder():
    s = Typer.new(("a", "b", "c"), 6, 1)
    t = realign(s, ("b", "x", "c"), 5)
    assert np.array_equal(t.w1, s.w1) and np.array_equal(t.w2[:, 0], s.w2[:, 1]) and np.array_equal(t.w2[:, 2], s.w2[:, 2])
    assert np.array_equal(realign(s, s.types, 9).w2, s.w2)
    apart = realign(s, ("p", "q"), 5)
    assert np.array_equal(apart.w2, realign(s, ("p", "q"), 5, transplant=False).w2)


def test_relational_realign_matches_counts(spark):
    h = spark.createDataFrame([(t, [1.0, 2.0]) for t in ("a", "b", "c")], "type_name string, w array<double>")
    out = {r["type_name"]: r for r in head.realign(h, typesets.typeset(spark, ["b", "c", "x", "y"]), 2, 1).collect()}
    assert out["b"]["copied"] and out["b"]["w"] == [1.0, 2.0] and not out["x"]["copied"] and len(out["y"]["w"]) == 2
    assert head.realign_report(h, typesets.typeset(spark, ["b", "c", "x", "y"])).head() == (2, 2, 1)


def test_draws_are_md5_and_agree_with_python(spark):
    got = {r[0]: r[1] for r in spark.createDataFrame([("a",), ("b#1",)], "i string").select("i", draw("seed", "i")).collect()}
    assert got == {i: int(hashlib.md5(f"seed:{i}".encode()).hexdigest()[:8], 16) for i in ("a", "b#1")}
    assert drawn(["x", "y", "z"], 2, "s") == drawn(["z", "y", "x"], 2, "s")


def test_worked_example(spark):
    cols = spark.createDataFrame(list(EXAMPLE), "column_id string, cells array<string>, type_name string, pred string")
    got = {r["column_id"]: r["decision"] for r in gap.knowledge_judge(cols).collect()}
    assert got == {"c1": "no", "c2": "no", "c3": "unknown", "c4": "yes"}


def test_answers_outside_the_closed_set_are_unknown(spark):
    texts = ["Yes.", " no", "I don't know", "perhaps", "", None, "NO, it is not", "yesterday"]
    got = [r[0] for r in spark.createDataFrame([(t,) for t in texts], "t string").select(gap.parse_answer("t")).collect()]
    assert got == ["yes", "no", "unknown", "unknown", "unknown", "unknown", "no", "unknown"]


def test_client_judge_redacts_and_parses(spark):
    cols = spark.createDataFrame([("c1", ["bob@example.com", "10.0.0.1"], "mail")], "column_id string, cells array<string>, pred string")
    ask = lambda prompts: ["no" if "bob" not in p and "<mail>" in p and "<ip>" in p else "yes" for p in prompts]
    assert gap.client_judge(cols, ask, ["mail", "name"], 1).head()["decision"] == "no"


def test_gate_limits(spark):
    df = spark.createDataFrame([("a", 0.2), ("b", 0.9), ("c", 1.0)], "column_id string, phi double")
    assert gap.gate(df, 0.0).count() == 0 and gap.gate(df, 1.1).count() == 3 and gap.gate(df, 0.9).count() == 1


def test_batches_are_disjoint_and_within_budget():
    lake, start = lake_and_start()
    out = adapt(lake, start, CFG)
    bought = [i for _, s, i in out.trace if s in ("batch", "residual")]
    probes = [i for _, s, i in out.trace if s == "probe"]
    assert len(bought) == len(set(bought)) == out.spent <= CFG.budget
    assert len(probes) == len(set(probes))
    assert set(bought) <= set(lake.train)


def test_every_batch_comes_from_weak_clusters_and_one_cluster_is_the_lake():
    lake, start = lake_and_start()
    flagged = lake.train[:3]
    whole = lake.from_weak(start, flagged, set(), 10**6, 1, CFG, "x")
    assert set(whole) == set(lake.train)
    some = lake.from_weak(start, flagged, set(), 10**6, 8, CFG, "x")
    assert set(flagged) <= set(some) < set(lake.train)


def test_yes_judge_buys_nothing_and_no_judge_is_the_variant_without():
    lake, start = lake_and_start()
    quiet = adapt(lake, start, replace(CFG, judge="yes", residual=False))
    assert not [1 for l, s, _ in quiet.trace if s == "batch" and l > 0]
    a, b = adapt(lake, start, replace(CFG, judge="no")), adapt(lake, start, replace(CFG, judge="none"))
    assert [x for x in a.trace if x[1] == "batch"] == [x for x in b.trace if x[1] == "batch"]
    assert b.judge_calls == 0 < a.judge_calls


def test_judge_changes_only_which_columns_are_bought():
    lake, start = lake_and_start()
    out = adapt(lake, start, replace(CFG, judge_accuracy=0.0))
    assert set(out.typer.types) == set(start.types)  # nothing outside the set can be said


def test_same_seed_same_trace_other_seed_other_trace():
    lake, start = lake_and_start()
    assert adapt(lake, start, CFG).trace == adapt(lake, start, CFG).trace != adapt(lake, start, replace(CFG, seed=2)).trace


def test_early_stop_keeps_the_best():
    lake, start = lake_and_start()
    out = adapt(lake, start, replace(CFG, iterations=30, budget=10**6, patience=2, residual=False))
    losses = [h["loss"] for h in out.history]
    touched = {i for _, s, i in out.trace if s in ("probe", "batch")}
    assert out.history[-1]["alpha"] >= 2 or set(lake.train) <= touched
    assert out.typer.loss(*lake.valid(out.typer)) == pytest.approx(min(losses))


def test_selectors_spaces_and_empty_pools():
    lake, start = lake_and_start()
    for change in ({"selector": "random"}, {"space": "logits"}, {"replay": False}, {"judge": "yes", "on_empty": "random"}, {"judge": "yes", "on_empty": "stop"}):
        out = adapt(lake, start, replace(CFG, **change))
        assert out.spent <= CFG.budget


def test_sufficient_and_exhausted_lakes_halt():
    lake, start = lake_and_start()
    assert adapt(lake, start, replace(CFG, residual=False), sufficient=lambda loss: True).iterations == 1
    out = adapt(lake, start, replace(CFG, iterations=500, budget=10**6, probe=100, patience=10**6, residual=False))
    assert out.iterations < 500


def columns_of(spark):
    ids, tables, split, x, y, types = toy()
    rows = [(i, t, s, [float(v) for v in f], name) for i, t, s, f, name in zip(ids, tables, split, x, y)]
    return spark.createDataFrame(rows, "column_id string, table_id string, split string, features array<double>, type_name string")


def test_spark_and_array_lakes_choose_alike(spark):
    lake, start = lake_and_start()
    cfg = replace(CFG, iterations=2)
    a, b = adapt(lake, start, cfg), adapt(SparkLake(columns_of(spark).repartition(3)), start, cfg)
    assert sorted(a.trace) == sorted(b.trace)
    assert np.allclose(a.typer.w2, b.typer.w2, atol=1e-6)


def test_resume_goes_on_where_it_stopped(spark):
    lake, start = lake_and_start()
    store = RunStore.new(spark)
    whole = adapt(lake, start, CFG)
    adapt(lake, start, replace(CFG, iterations=2, residual=False), store)
    again = adapt(lake, start, CFG, store)
    assert again.spent == whole.spent and np.allclose(again.typer.w2, whole.typer.w2) and again.trace == whole.trace
    assert store.trace().where("stage = 'batch'").count() >= 4


class Sealed(ArrayLake):
    """A lake that opens the type of a column only to the process, once it is paid."""

    def __init__(self, lake, cells):
        self.__dict__.update(lake.__dict__)
        self._cells, self.held = [cells[i] for i in lake.at], []

    def truth(self, ids):
        raise AssertionError("the loop looked at a type")

    def labelled(self, ids, t):
        raise AssertionError("the loop looked at a type")


def test_a_lake_without_truth_needs_only_a_judge_and_a_process():
    lake, start = lake_and_start()
    cells = {i: [lake.y[k], "x"] for i, k in lake.at.items()}
    paid = []

    class Paid:
        def label(self, ids):
            paid.extend(ids)
            return {i: lake.y[lake.at[i]] for i in ids if lake.at[i] % 7}  # cannot name some

    asked = []

    def ask(prompts):
        asked.extend(prompts)
        return ["Yes." if p.split("Values: ")[1].split(";")[0] == p.split("Proposed: ")[1] else "no" for p in prompts]

    out = adapt(Sealed(lake, cells), start, CFG, judge=ClientJudge(ask, start.types), process=Paid())
    bought = [i for _, stage, i in out.trace if stage in ("batch", "residual")]
    assert sorted(paid) == sorted(bought) and out.spent == len(paid) <= CFG.budget and len(asked) == out.judge_calls > 0
    assert all(np.isfinite(h["loss"]) for h in out.history)
    with pytest.raises(AssertionError):
        adapt(Sealed(lake, cells), start, CFG)


def test_judges(spark):
    rows = [("c1", ["Supplier#1"], "vendor_name"), ("c2", ["https://a/x", None], "web_address"), ("c3", ["zq-77"], "product_name"), ("c4", [], "order_date"), ("c5", ["AFRICA"], "order_date"), ("c6", ["0.05"], "tax_rate")]
    table_ = gap.knowledge_judge(spark.createDataFrame(rows, "column_id string, cells array<string>, pred string"))
    mine = KnowledgeJudge().answer([Proposal(i, tuple(c for c in cells if c is not None), label) for i, cells, label in rows if i != "c2"])
    assert [r["decision"] for r in table_.orderBy("column_id").collect() if r["column_id"] != "c2"] == mine == ["yes", "unknown", "no", "no", "yes"]
    asked = [Proposal(f"c{k}", (), "a") for k in range(2000)]
    truth = lambda ids: {i: "a" for i in ids}
    one, two = (NoisyJudge(truth, seed=s).answer(asked) for s in (1, 2))
    assert one != two and abs(one.count("yes") / 2000 - 0.8) < 0.03 and one == NoisyJudge(truth, seed=1).answer(asked)
    assert prompt_text(("b", "a"), ["mail me@x.org", "y" * 500], "a").split("Values: ")[1] == f"mail <mail>; {'y' * 200}\nProposed: a"


def test_processes_and_the_account():
    cells = {"c1": ["http://x", "a@b"], "c2": ["12", "13"], "c3": ["1,5"], "c4": ["Rome", "Oslo", "x"], "c5": []}
    own = lambda ids: {i: cells[i] for i in ids}
    assert process.Heuristic(own).label(list(cells)) == {"c1": "web_address", "c2": "record_key", "c3": "money_amount", "c4": "name"}
    assert process.Dictionary(own, {"Rome": "town", "Oslo": "town", "12": "number"}).label(list(cells)) == {"c4": "town", "c2": "number"}
    account = process.Account(process.Heuristic(own), 3)
    account.buy(["c1", "c5"])
    assert account.left == 1
    with pytest.raises(ValueError):
        account.buy(["c2", "c3"])


def test_many_labels_are_fitted_in_spark(spark):
    lake, start = lake_and_start()
    cfg = replace(CFG, iterations=1, local_labels=5, residual=False)
    out = adapt(SparkLake(columns_of(spark)), start, cfg)
    assert out.history[0]["loss"] < SparkLake(columns_of(spark)).loss(start) == pytest.approx(start.loss(*lake.valid(start)))


def test_score_is_one_arrow_pass_that_equals_numpy(spark):
    _, start = lake_and_start()
    cols = columns_of(spark)
    rows = {r["column_id"]: r for r in score(cols, start).collect()}
    x = np.array([r["features"] for r in cols.orderBy("column_id").collect()])
    best, conf = start.predict(x)
    for (i, r), b, c in zip(sorted(rows.items()), best, conf):
        assert r["pred"] == start.types[b] and r["phi"] == pytest.approx(c)


def test_stop_trace_needs_strict_improvement(spark):
    losses = spark.createDataFrame([(1, 0.5), (2, 0.5), (3, 0.4), (4, 0.4), (5, 0.4)], "iter int, loss double")
    got = [(r["alpha"], r["stopped"]) for r in weak.stop_trace(losses, 2).orderBy("iter").collect()]
    assert got == [(0, False), (1, False), (0, False), (1, False), (2, True)]


def test_ledger_refuses_beyond_the_budget(spark):
    rows = weak.ledger(spark.createDataFrame([(0, 6), (1, 6), (2, 6)], "iter long, size long"), 10).orderBy("iter").collect()
    assert [(r["paid"], r["left"]) for r in rows] == [(6, 4), (4, 0), (0, 0)]


def test_processes(spark):
    truth = spark.createDataFrame([(f"c{k}", "t") for k in range(9)], "column_id string, type_name string")
    p = GroundTruth(truth, 5)
    assert p.label(truth.limit(3)).count() == 3 and p.label(truth).count() == 2 and p.left == 0
    cols = spark.createDataFrame([("c", ["x", "y", "q"])], "column_id string, cells array<string>")
    words = spark.createDataFrame([("x", "letter"), ("y", "letter"), ("q", "rare")], "value string, type_name string")
    assert knowledge_base(cols, words).head()["label"] == "letter"


def test_f1_by_hand(spark):
    rows = spark.createDataFrame([("a", "a"), ("a", "b"), ("b", "b"), ("c", "z")], "type_name string, pred string")
    got = {r["type_name"]: (r["tp"], r["fp"], r["fn"], r["f1"]) for r in metrics.per_type(rows).collect()}
    assert got == {"a": (1, 0, 1, 0.666667), "b": (1, 1, 0, 0.666667), "c": (0, 0, 1, 0.0), "z": (0, 1, 0, 0.0)}
    known = typesets.typeset(spark, ["a", "b", "c"])
    assert metrics.ood_rate(rows, known).head()["ood_rate"] == 0.25
    assert metrics.ma_f1(metrics.per_type(rows), known).head()["n_types"] == 3
    assert metrics.ma_f1(metrics.per_type(rows), typesets.typeset(spark, ["a", "b", "c", "d"]), "typeset").head()["n_types"] == 4


def test_silhouettes_agree_in_sign(spark):
    rng = np.random.default_rng(0)
    rows = [(str(k), k % 2, [float(v) for v in rng.normal(8 * (k % 2), 1, 4)]) for k in range(40)]
    df = spark.createDataFrame(rows, "column_id string, cluster int, hidden array<double>")
    assert metrics.silhouette_exact(df).head()["silhouette"] > 0.6 and metrics.silhouette_fast(df) > 0.6


def test_cost_closed_forms():
    w = cost.Work(7, 20, 5, 3, 11, 4, 6, 100, 8, 2)
    assert w.replay_exact() == 3 * sum(20 + 5 * l for l in range(1, 8)) and w.replay_lower() == 3 * sum(20 + 5 * (l - 1) for l in range(1, 8))
    assert w.replay_bound(100) is None and w.replay_bound(140) == 7 * 140 * 3
    assert cost.prompt_dollars(78) == pytest.approx(0.00047) and cost.prompt_dollars(275) == pytest.approx(0.0015)


def test_fusion_refuses_a_missing_type():
    x = np.eye(4)
    with pytest.raises(methods.MissingTypeError):
        methods.feature_fusion([x, x], ["a", "a", "b", "b"], ("a", "b", "c"), [0, 1, 2, 3], 1)
    assert methods.feature_fusion([x], ["a", "a", "b", "b"], ("a", "b", "c"), [0, 1, 2, 3], 1, strict=False).types == ("a", "b", "c")


def test_prompted_answers_come_from_cells_and_generators_err_less_with_more_labels():
    types = tuple(catalog.TX1.target)
    cells = [["https://a.example/x"], ["AFRICA", "asia"], ["Customer#1"], ["12.50"], []] * 20
    for strength in methods.ANNOTATORS:
        said = methods.direct_label(cells, types, strength)
        assert said == methods.direct_label(cells[:5], types, strength) * 20 and said[4] == "empty"
    shares = [np.mean([a not in types for a in methods.direct_label(cells, types, m)]) for m in methods.ANNOTATORS]
    assert max(shares) > 0.3
    truth = [types[k % len(types)] for k in range(400)]
    rng = np.random.default_rng(0)
    x = rng.normal(size=(400, 6))
    far = [sum(a.startswith("unlisted") for a in methods.nearest_label(x, list(range(n)), truth, list(range(200, 400)), 0.9)) for n in (5, 50, 200)]
    assert far[0] > far[1] > far[2]


@pytest.mark.parametrize("cells", [[], [None], [""], ["x" * 100_000], ["é漢字🙂", "\x00"], ['{"a": [1, {"b": null}]}'], ["1e400", "nan", "-0"]])
def test_any_cells_give_a_finite_vector(cells):
    v = vector_of(cells)
    assert v.shape == (WIDTH,) and np.isfinite(v).all()


def test_encoder_sees_values_only(spark):
    a = spark.createDataFrame([("t#0", "t", ["1", "2"])], "column_id string, source_table string, cells array<string>")
    b = spark.createDataFrame([("other#9", "elsewhere", ["1", "2"])], a.schema)
    assert encode(a).head()["features"] == encode(b).head()["features"]


def test_transfers_have_the_three_regimes():
    sizes = {t.name: (len(t.source), len(t.target), len(set(t.source) & set(t.target))) for t in catalog.TRANSFERS}
    assert sizes["TX1"][2] == sizes["TX1"][0] < sizes["TX1"][1] and sizes["TX3"][1] == 27
    assert 0 < sizes["TX2"][2] < 8 and 0 < sizes["TX3"][2] < sizes["TX3"][0]


def test_distributed_training_is_full_batch_adam(spark):
    from lakeadapt.operators.typer import Adam, fit_distributed

    _, start = lake_and_start()
    cols = columns_of(spark).where("split = 'train'")
    rows = cols.collect()
    x, y = np.array([r["features"] for r in rows]), start.encode_types([r["type_name"] for r in rows])
    want, adam = start.copy(), Adam(2e-2)
    for _ in range(3):
        adam.update(want.weights(), gradients(want, x, y))
    got = fit_distributed(cols.repartition(3), start, steps=3)
    assert all(np.allclose(a, b, atol=1e-9) for a, b in zip(got.weights().values(), want.weights().values()))


def test_blocks_train_on_every_column_alike(spark):
    from lakeadapt.operators.typer import blocked, fit_blocks, fit_to_plateau, train_blocks

    lake, start = lake_and_start()
    cols = columns_of(spark)
    rows = cols.orderBy("column_id").collect()
    x, y = np.array([r["features"] for r in rows]), start.encode_types([r["type_name"] for r in rows])
    whole = fit_to_plateau(start, x, y, most=6)
    one = fit_blocks(cols.repartition(3), start, most=6)
    assert all(np.allclose(a, b, atol=1e-9) for a, b in zip(one.weights().values(), whole.weights().values()))
    # many blocks: each column is in one of them, the mean is weighted by columns, and the result is about as good
    parts = {}
    for r in blocked(cols, start.types, 30).collect():
        parts.setdefault(r["block"], []).append(r["column_id"])
    assert len(parts) == 8 and sorted(i for ids in parts.values() for i in ids) == sorted(r["column_id"] for r in rows) and all(ids == sorted(ids) for ids in parts.values())
    place = {r["column_id"]: k for k, r in enumerate(rows)}
    own = [(len(ids), fit(start, x[[place[i] for i in ids]], y[[place[i] for i in ids]], epochs=1).w1) for ids in parts.values()]
    mean, loss = train_blocks(blocked(cols, start.types, 30), start, lambda m, b: fit(m, b["features"], b["y"], epochs=1))
    assert np.allclose(mean.w1, sum(n * w for n, w in own) / len(rows)) and loss == pytest.approx(start.loss(x, y))
    many = fit_blocks(cols, start, most=20, size=30)
    assert (many.predict(x)[0] == y).mean() > (whole.predict(x)[0] == y).mean() - 0.05


def test_source_typer_has_no_switch_by_size(spark, monkeypatch):
    from pyspark.sql.classic.dataframe import DataFrame as Classic

    from lakeadapt.operators.typer import fit_to_plateau
    from lakeadapt.plans import queries_learned

    rng, types = np.random.default_rng(7), catalog.TX1.source[:3]
    x = rng.normal(size=(4200, WIDTH)).astype(np.float32)
    y = rng.integers(0, 3, len(x))
    x[:, :3] += np.eye(3, dtype=np.float32)[y] * 4
    rows = spark.createDataFrame([(f"c{k:04d}", types[c], v.tobytes()) for k, (c, v) in enumerate(zip(y, x))], "column_id string, type_name string, features binary")
    monkeypatch.setattr(Classic, "limit", lambda *a: pytest.fail("some columns train first"))
    got = queries_learned.source_typer(rows)
    fresh = Typer.new(catalog.TX1.source, WIDTH, 1)
    alone = fit_to_plateau(fresh, x.astype(np.float64), fresh.encode_types([types[c] for c in y]), most=12)
    assert got.loss(x, fresh.encode_types([types[c] for c in y])) < 2 * alone.loss(x, fresh.encode_types([types[c] for c in y])) + 0.01


def whole_equals_uncut(spark, monkeypatch, name, runs):
    """sf0.001 has fewer tables of a kind than LAKE_TABLES: there the drawn lake is whole, and both ways must agree. With fewer
    drawn ones, the whole way must not change."""
    from lakeadapt.workloads import grid

    sf, seen = "/root/testdata/sf0.001", ("transfer", "method", "budget", "n_labels", "judge_calls", "iterations")
    order = lambda rows: sorted(rows, key=lambda r: tuple(r[c] for c in seen[:3]))
    alone = order(grid.execute(grid.arrays(spark, sf), r) for r in runs)
    monkeypatch.setattr(grid, "LAKE_TABLES", 1)
    monkeypatch.setattr(grid, "_arrays", lambda *a: pytest.fail("the experiment ran on drawn tables"))
    got = order(r.asDict() for r in grid._batch(spark, sf, runs).collect())
    assert name in grid.WHOLE and [[r[c] for c in seen] for r in got] == [[r[c] for c in seen] for r in alone]
    for r, want in zip(got, alone):
        assert (r["sw_f1"], r["ma_f1"], r["ood"]) == pytest.approx((want["sw_f1"], want["ma_f1"], want["ood"]), abs=1e-6), r


def test_replay_experiment_runs_on_whole_lakes(spark, monkeypatch):
    from lakeadapt.workloads import experiments

    whole_equals_uncut(spark, monkeypatch, "V13", experiments.low("V13", "TX1", ("full_J", "no_replay_J"), (5,)) + [experiments.Run("V13", "TX1", "full_J", "low0", iterations=2)])


def test_transplant_experiment_runs_on_whole_lakes(spark, monkeypatch):
    from lakeadapt.workloads import experiments

    whole_equals_uncut(spark, monkeypatch, "W11", experiments.runs("W11"))


def test_word_experiment_runs_on_whole_lakes(spark, monkeypatch):
    from lakeadapt.workloads import experiments

    runs = [experiments.Run("W14", "TX1", "weak_judge_W", "low", iterations=2), experiments.Run("W14", "TX1", "plain_W", "low", iterations=2, labels=90)]
    whole_equals_uncut(spark, monkeypatch, "W14", runs + experiments.high("W14", "TX1", ("weak_judge_W",), (0.05, 0.25)))


def test_blocks_of_labels_are_trained_on_as_on_the_driver(spark):
    lake, start = lake_and_start()
    labels = {i: lake.y[lake.at[i]] for i in lake.train}
    here = lake.fit(start, labels, replace(CFG, epochs=3), 5)
    there = SparkLake(columns_of(spark)).fit(start, labels, replace(CFG, epochs=3, local_labels=len(labels) - 1), 5)
    x, y = lake.labelled(lake.train, start)
    assert there.loss(x, y) < 0.75 * start.loss(x, y) and here.loss(x, y) < start.loss(x, y)
    assert all(np.isfinite(w).all() for w in there.weights().values())


def test_grams_are_whole_characters(spark):
    cells = ["a🙂b\n🙂c", "xy", "z", "", "ab" * 30_000]
    cols = spark.createDataFrame([("t#0", cells)], "column_id string, cells array<string>")
    for n in (2, 3):
        want = Counter(int(hashlib.md5(c[i : i + n].encode()).hexdigest()[:8], 16) % 256 for c in cells for i in range(len(c) - n + 1))
        assert {r["bucket"]: r["n"] for r in gram_buckets(cols, n, 256).collect()} == dict(want)


def test_arrays_never_hold_vectors_as_python_numbers(spark, monkeypatch):
    """Through toPandas the vectors of an experiment took 1.3 GB of the driver at sf0.1."""
    from pyspark.sql.classic.dataframe import DataFrame as Classic

    from lakeadapt.workloads import grid

    rows = spark.createDataFrame([("b", [3.0, 4.0]), ("a", [1.0, 2.0])], "column_id string, v array<float>")
    assert grid.vectors(rows, "v").tolist() == [[1.0, 2.0], [3.0, 4.0]] and grid.vectors(rows, "v").dtype == np.float32
    monkeypatch.setattr(Classic, "toPandas", lambda self: pytest.fail("a lake went through toPandas"))
    grid._arrays.cache_clear()
    a = grid.arrays(spark, "/root/testdata/sf0.001")
    assert a.ids == sorted(a.ids) and all(len(v) == len(a.ids) for v in a.parts.values())


def test_documents_as_units_leave_their_texts_in_spark(spark, monkeypatch):
    from pyspark.sql.classic.dataframe import DataFrame as Classic

    from lakeadapt.workloads import checks

    monkeypatch.setattr(Classic, "toPandas", lambda self: pytest.fail("texts went through toPandas"))
    assert checks.documents_as_units(spark, "/root/testdata/sf0.001").head()["n_types"] > 0


def test_nearest_rows_meet_as_blocks(spark, monkeypatch):
    from pyspark.ml.feature import BucketedRandomProjectionLSHModel as Model

    from lakeadapt.operators import joins

    monkeypatch.setattr(Model, "approxSimilarityJoin", lambda *a, **k: pytest.fail("pairs are listed bucket by bucket"))
    monkeypatch.setattr(joins, "BLOCK", 64)
    x = np.random.default_rng(4).normal(size=(300, 8))
    x[50:60] = x[40]
    rows = spark.createDataFrame([(i, i % 3, v.tolist()) for i, v in enumerate(x)] + [(500, 1, None)], "vec_id long, label int, hidden array<double>")
    exact = joins.knn(rows.where("vec_id % 20 = 0"), rows, 5)
    assert "NestedLoop" not in exact._jdf.queryExecution().toString() and "Cartesian" not in exact._jdf.queryExecution().toString()
    u = x / np.linalg.norm(x, axis=1)[:, None]
    want = {(q, int(i), k + 1, int(i) % 3) for q in range(0, 300, 20) for k, i in enumerate([i for i in np.lexsort((np.arange(300), -(u @ u[q]).round(9))) if i != q][:5])}
    assert {(r["query"], r["found"], r["k"], r["label"]) for r in exact.collect()} == want
    near = joins.knn_lsh(rows.where("vec_id % 20 = 0"), rows, 5, bucket=1e9, most=3.0)
    far = {(q, int(i), k + 1) for q in range(0, 300, 20) for k, i in enumerate([i for i in np.lexsort((np.arange(300), ((x - x[q]) ** 2).sum(1).round(12))) if i != q][:5]) if ((x[i] - x[q]) ** 2).sum() < 9}
    assert len({(r["query"], r["found"], r["k"]) for r in near.collect()} & far) >= 0.5 * len(far)  # those on the other side of every projection are not near
    assert {(r["query"], r["found"]) for r in near.collect()} <= {(q, i) for q in range(0, 300, 20) for i in range(300) if i != q}


def test_exact_silhouette_has_no_limit_of_rows(spark):
    x = np.random.default_rng(5).normal(size=(90, 3)) + 3 * (np.arange(90) % 3)[:, None]
    d, c = np.linalg.norm(x[:, None] - x[None], axis=2), np.arange(90) % 3
    mean = lambda i, k: d[i, (c == k) & (np.arange(90) != i)].mean()
    want = np.mean([(min(mean(i, k) for k in range(3) if k != c[i]) - mean(i, c[i])) / max(min(mean(i, k) for k in range(3) if k != c[i]), mean(i, c[i])) for i in range(90)])
    small = spark.createDataFrame([(str(i), int(k), v.tolist()) for i, (k, v) in enumerate(zip(c, x))], "column_id string, cluster int, hidden array<double>")
    got = metrics.silhouette_exact(small).head()
    assert got["silhouette"] == pytest.approx(want, abs=2e-6) and got["n"] == 90
    many = spark.range(20_050).select(F.col("id").cast("string").alias("column_id"), (F.col("id") % 2).alias("cluster"), F.array((F.col("id") % 2) * 9.0, F.rand(3)).alias("hidden"))
    assert metrics.silhouette_exact(many).head()["n"] == 20_050


#: Queries that made their data up until they were moved onto a given table.
READING = [
    "avg_gain",
    "budget_grid",
    "budget_ledger",
    "early_stop_trace",
    "labels_to_target",
    "overhead_cost",
    "prompt_cost",
    "realign_random",
    "replay_cost",
    "sql_recursive",
    "type_granularity",
]


@pytest.mark.parametrize("name", READING)
def test_query_reads_a_given_table(spark, name):
    from lakeadapt.plans import registered

    assert registered().queries[name](spark, "/root/testdata/sf0.001").inputFiles()


def test_columns_encoded_together_equal_each_alone(spark):
    rng = np.random.default_rng(3)
    odd = [[], [None], [""], ["", ""], ["a"], ["é漢字🙂", None, "\x00"], ["1e400", "nan", "-0", "inf", "x"], ["x" * 100_000], ["1,5", "1_0", " 7 "], ["\ud800"]]
    columns = odd + [[str(x)[: rng.integers(0, 9)] for x in rng.normal(0, 1000, rng.integers(0, 12))] for _ in range(300)]
    alone = np.array([vector_of(c) for c in columns])
    assert (vectors_of(columns) == alone).all() and vectors_of([]).shape == (0, WIDTH)
    df = spark.createDataFrame([(f"c{k:03d}", c) for k, c in enumerate(columns) if "\ud800" not in c] + [("d", None)], "column_id string, cells array<string>")
    plain, packed = encode(df).orderBy("column_id").collect(), encode(df, packed=True).orderBy("column_id").collect()
    assert [list(row_of(r["features"])) for r in packed] == [r["features"] for r in plain]


def packed_columns(spark):
    ids, tables, split, x, y, types = toy()
    packed = packed_array(x.astype(np.float32)).to_pylist()
    return spark.createDataFrame(list(zip(ids, tables, split, packed, y)), "column_id string, table_id string, split string, features binary, type_name string")


def test_packed_features_adapt_alike(spark):
    ids, tables, split, x, y, types = toy()
    start = lake_and_start()[1]
    for space in ("hidden", "logits"):
        cfg = replace(CFG, iterations=2, space=space)
        a = adapt(ArrayLake(ids, tables, split, x.astype(np.float32).astype(float), y), start, cfg)
        b = adapt(SparkLake(packed_columns(spark).repartition(3)), start, cfg)
        assert sorted(a.trace) == sorted(b.trace) and np.allclose(a.typer.w2, b.typer.w2, atol=1e-6)


def test_a_probe_is_gated_without_another_pass_and_vectors_are_computed_once(spark):
    lake, start = SparkLake(packed_columns(spark)), lake_and_start()[1]
    probed = lake.fresh(set(), 20, "p")
    columns, train, lake.columns, lake.train = lake.columns, lake.train, None, None
    gated = lake.gate(start, probed, 2.0)
    assert [i for i, _ in gated] == probed and lake.fit(start, dict(gated), CFG, 1).w1.shape == start.w1.shape
    lake.columns, lake.train = columns, train
    made, space = [], lake._space
    lake._space = lambda *x: made.append(space(*x)) or made[-1]
    assert len(lake.from_weak(start, probed, set(probed), 5, 4, CFG, "b")) == 5
    assert len(made) == 1 and not made[0].storageLevel.useMemory  # for all rounds, and given back


def test_source_columns_that_nobody_reads_are_not_made(spark):
    from lakeadapt.sources import lake

    sf, groups = "/root/testdata/sf0.001", tuple(g for g in catalog.GROUPS if g.name in ("supplier", "pages"))
    every, some = lake.build(spark, sf, groups), lake.build(spark, sf, groups, ("supplier",))
    wanted = every.where("lake = 'target' OR source_table = 'supplier'")
    assert sorted(map(str, some.collect())) == sorted(map(str, wanted.collect())) and 0 < some.count() < every.count()
