import numpy as np
import pytest
from pyspark.sql import functions as F

from driftview.functions import features as fx
from driftview.functions import vectors
from driftview.learn.model import Model
from driftview.learn.sgd import SgdTrainer
from driftview.operators import store
from driftview.operators.band import HolderPair
from driftview.operators.measures import diff_with_exact
from driftview.operators.store import choose_buffer, full_bytes, hybrid_bytes
from driftview.operators.view import ClassificationView, Options, gather
from driftview.plans import replay, workloads
from driftview.plans.declare import create_view, parse_definition, run_statement
from driftview.session import materialize, shared_path
from driftview.sources import view_source
from driftview.streaming.attach import attach_stream

TRAINER = SgdTrainer("hinge", 2.0, 0.01)


@pytest.fixture(scope="module")
def small(spark):
    rng = np.random.default_rng(2)
    x = rng.normal(size=(400, 3))
    y = np.where(x @ [1.0, -2.0, 0.5] + 0.2 >= 0, 1, -1)
    entities = materialize(spark.createDataFrame([(k, f.tolist()) for k, f in enumerate(x)], "id long, f array<double>"), "small")
    batch = [(k, x[k], int(y[k])) for k in range(80)]
    return entities, batch


def start(small, **options):
    entities, batch = small
    warm = TRAINER.fit([(f, y) for _, f, y in batch[:40]], 3)
    view = ClassificationView(entities, TRAINER, 3, Options(buckets=4, **options), warm)
    view.examples = batch[:40]
    return view, batch[40:]


def exactly(view):
    assert diff_with_exact(view.view(), view.exact()).count() == 0


@pytest.mark.parametrize("options", [{}, {"band": "pairwise"}, {"arch": "memory"}, {"arch": "hybrid"}, {"pair": HolderPair.for_norm("l1")}, {"layout": "slim", "refine": True}, {"policy": "lazy"}, {"policy": "lazy", "band": "current"}, {"policy": "lazy", "arch": "hybrid"}, {"alpha": None, "sigma": 0.5}, {"clock": "seconds"}], ids=str)
def test_every_round_equals_a_full_relabel(small, options):
    view, rest = start(small, **options)
    for k in range(0, 40, 8):
        view.update(rest[k : k + 8])
        if view.options.policy == "lazy":
            assert view.count_members(1) == view.exact().where("class = 1").count()
        exactly(view)
    ids = view.entities.select("id").limit(50)
    assert view.label_of_many(ids).select("id", "class").exceptAll(view.exact()).count() == 0
    assert view.label_of(5) == view.exact().where("id = 5").first()["class"] and view.label_of(10**9) is None
    history = view.round_history()
    assert view.explain_band().agg(F.sum("n_rows")).first()[0] == 400
    assert history.count() == len(view.history) and view.published()["round"] == view.round
    if view.options.policy == "eager" and view.options.clock == "rows":
        assert all(s.cost <= view.n / view.options.sigma for s in view.history)


def test_current_band_is_refused_for_eager_views():
    with pytest.raises(ValueError):
        Options(band="current")


def test_entities_arrive_leave_and_change(small, spark):
    view, rest = start(small)
    view.update(rest[:10])
    big = spark.createDataFrame([(1000, [30.0, -20.0, 5.0]), (1001, [0.0, 0.0, 0.0])], "id long, f array<double>")
    view.add_entities(big)
    exactly(view)
    view.update(rest[10:20])
    exactly(view)
    view.delete_entities(spark.createDataFrame([(3,), (1000,)], "id long"))
    exactly(view)
    assert view.view().where("id in (3, 1000)").count() == 0
    view.update_entities(spark.createDataFrame([(7, [-9.0, 9.0, 0.0])], "id long, f array<double>"))
    exactly(view)
    view.update(rest[20:30])
    exactly(view)


@pytest.mark.parametrize("options", [{}, {"policy": "lazy"}, {"arch": "memory"}, {"policy": "lazy", "arch": "hybrid"}, {"pair": HolderPair.for_norm("l1")}, {"layout": "slim"}], ids=str)
def test_unusable_rows_are_set_aside(small, spark, options):
    entities, batch = small
    nan, inf = float("nan"), float("inf")
    odd = spark.createDataFrame([(900, [nan, 0.0, 0.0]), (901, [1.0, inf, 0.0]), (902, [1.0, None, 0.0]), (903, None), (904, [1.0]), (None, [1.0, 1.0, 1.0]), (905, [1.0, 2.0, 3.0])], "id long, f array<double>")
    view, rest = start((entities.unionByName(odd), batch), **options)
    assert {r["id"] for r in view.refused(odd).collect()} == {900, 901, 902, 903, 904, None}
    view.update(rest[:10])
    view.add_entities(odd.select((F.col("id") + 50).alias("id"), "f"))
    view.update(rest[10:20])
    exactly(view)
    ids = {r["id"] for r in view.view().collect()}
    assert ids == {*range(400), 905, 955}
    assert all(np.isfinite(view.bounds)) and view.label_of(900) is None and view.label_of(955) is not None


@pytest.mark.parametrize("options", [{}, {"policy": "lazy"}, {"arch": "memory", "policy": "lazy"}, {"layout": "slim", "policy": "lazy"}, {"band": "pairwise"}], ids=str)
def test_the_name_follows_every_change(small, spark, options):
    view, rest = start(small, **options)
    view.name = f"named_{abs(hash(str(options)))}"
    vector = "id long, f array<double>"

    def follows(n):
        rows = spark.table(view.name)
        assert rows.count() == n and diff_with_exact(rows, view.exact()).count() == 0

    view.update(rest[:10])
    follows(400)
    view.delete_entities(spark.createDataFrame([(3,), (5,), (None,)], "id long"))
    follows(398)
    view.add_entities(spark.createDataFrame([(700, [9.0, -9.0, 9.0])], vector))
    follows(399)
    view.update(rest[10:20])
    follows(399)
    view.add_entities(spark.createDataFrame([(3, [-9.0, 9.0, -9.0])], vector))  # deleted before
    follows(400)
    assert view.label_of(3) == view.exact().where("id = 3").first()["class"] and view.label_of(5) is None
    view.add_entities(spark.createDataFrame([(7, [8.0, 0.0, 0.0])], vector))  # there already
    follows(400)
    with pytest.raises(ValueError):
        view.add_entities(spark.createDataFrame([(800, [1.0, 1.0, 1.0]), (800, [2.0, 1.0, 1.0])], vector))
    view.update(rest[20:30])
    follows(400)


def test_a_look_up_opens_few_files(small):
    view, rest = start(small)
    view.update(rest[:4])
    plan = view.store.read().where("id = 7")._jdf.queryExecution().executedPlan().toString()
    assert "EqualTo(id,7)" in plan
    assert [view.label_of(k) for k in range(0, 400, 41)] == [r["class"] for r in view.exact().where("id % 41 = 0").orderBy("id").collect()]


def test_equal_margins_are_dealt_to_several_tasks(spark):
    rows = spark.range(300_000).select("id", F.array(F.lit(1.0), F.col("id") / 3e5).alias("f"))
    view = ClassificationView(rows, TRAINER, 2, Options(buckets=4))  # a cold start: all margins are 0
    assert view.n == 300_000
    assert view.store.read().select(F.input_file_name()).distinct().count() > 1


@pytest.mark.parametrize("limit", [10, 10**5])
def test_the_buffer_holds_the_nearest(small, monkeypatch, limit):
    monkeypatch.setattr(store, "SORTED_BUFFER", limit)
    view, rest = start(small, arch="hybrid", buffer_share=0.1)
    view.update(rest[:4])
    for low, high in ((0.0, 0.0), (-0.3, 0.4), (-50.0, 50.0)):
        got = {r["id"] for r in choose_buffer(view.store, low, high, 40).collect()}
        rows = sorted((max(r["eps"] - high, 0.0) if r["eps"] >= high else max(low - r["eps"], 0.0), r["id"]) for r in view.store.read().collect())
        assert got == {k for _, k in rows[:40]}


def test_deleted_and_relabelled_examples_mean_training_anew(small):
    view, rest = start(small)
    view.update(rest)
    view.delete_examples(range(0, 80, 3))
    view.relabel({1: -1, 2: 1})
    kept = [(k, f, {1: -1, 2: 1}.get(k, y)) for k, f, y in small[1] if k % 3]
    m = TRAINER.fit([(f, y) for _, f, y in kept], 3)
    assert np.allclose(m.w, view.model.w) and m.b == pytest.approx(view.model.b)
    exactly(view)


def test_cold_start_and_hyperplane(small):
    entities, batch = small
    view = ClassificationView(entities, TRAINER, 3, Options(buckets=4))
    assert view.view().where("class = 1").count() == 400  # all margins are 0
    view.update(batch[:5])
    exactly(view)


def test_reads_open_only_what_they_need(small):
    view, rest = start(small)
    view.update(rest[:2])
    low, high = view.bounds
    assert low < high
    plan = view.all_members(1)._jdf.queryExecution().executedPlan().toString()
    base = [line for line in plan.splitlines() if "FileScan" in line and "base" in line]
    assert base and all("PartitionFilters" in line and "eps_bucket" in line for line in base)
    assert all("f:array" not in line.split("ReadSchema")[1] for line in base)
    assert "GreaterThanOrEqual(eps" in plan
    negative = view.view().where("class = -1")._jdf.queryExecution().optimizedPlan().toString()
    assert negative.count("eps_bucket") < view.view()._jdf.queryExecution().optimizedPlan().toString().count("eps_bucket")


def test_sandwich_and_uncertain(small):
    view, rest = start(small, policy="lazy")
    view.update(rest[:6])
    exact = {r["id"] for r in view.exact().where("class = 1").collect()}
    sure, may = ({r["id"] for r in s.collect()} for s in view.sandwich(1))
    assert sure <= exact <= may
    near = view.most_uncertain(5).collect()
    assert [abs(r["eps"]) for r in near] == sorted(abs(r["eps"]) for r in near) and len(near) == 5


def test_views_over_sparse_text(spark, data):
    w = workloads.text_language(spark, data, 7, dim=1 << 12)
    w.warm, w.measured = 40, 20
    entities = materialize(w.entities, "text")
    view = ClassificationView.create(entities, w.examples().limit(40), w.trainer, w.dim, Options(buckets=4), name="text_view")
    view.add_examples(w.examples().orderBy(F.desc("id")).limit(20))
    exactly(view)
    assert spark.table("text_view").count() == entities.count()


def test_declared_view_and_its_errors(spark, small):
    entities, batch = small
    rows = entities.select("id", F.col("f")[0].alias("a"), F.col("f")[1].alias("b"), F.col("f")[2].alias("c"))
    rows.createOrReplaceTempView("things")
    spark.createDataFrame([(k, "yes" if y > 0 else "no") for k, _, y in batch], "id long, kind string").createOrReplaceTempView("marks")
    spark.createDataFrame([("yes",), ("no",)], "kind string").createOrReplaceTempView("kinds")
    text = "DEFINE MODEL VIEW good OVER things KEY id LABELS kinds(kind) EXAMPLES marks(id, kind) FEATURES dense_columns(a, b, c) POLICY lazy"
    view = run_statement(spark, text)
    assert spark.sql("SELECT count(*) AS n FROM good").first()["n"] == 400
    exactly(view)
    assert parse_definition(text + " ").policy == "lazy" and parse_definition(text).positional == ("a", "b", "c")
    for bad in (text.replace("KEY id", "KEY nope"), text.replace("marks(id, kind)", "marks(id, nope)"), text.replace("FEATURES dense", "FEATURES sense")):
        with pytest.raises(ValueError):
            create_view(spark, parse_definition(bad))
    with pytest.raises(ValueError):
        parse_definition("SELECT 1")
    spark.createDataFrame([("yes",), ("other",)], "kind string").createOrReplaceTempView("kinds")
    with pytest.raises(ValueError):
        run_statement(spark, text)


def test_duplicate_ids_are_refused(spark):
    twice = spark.createDataFrame([(1, [1.0]), (1, [2.0])], "id long, f array<double>")
    with pytest.raises(ValueError):
        ClassificationView.create(twice, spark.createDataFrame([(1, 1)], "id long, label int"), TRAINER, 1)


def test_data_source_reads_the_published_round(spark, small):
    view, rest = start(small)
    view.update(rest[:6])
    view_source.register(spark)
    rows = spark.read.format("modelview").load(view.path)
    assert rows.select("id", "class").exceptAll(view.view()).count() == 0 and rows.count() == 400
    assert {r["id"] for r in rows.where("class = 1").collect()} == {r["id"] for r in view.all_members(1).collect()}
    assert rows.where("id = 3").count() == 1


def test_streams_of_examples_and_entities(spark, small):
    view, rest = start(small)
    path = shared_path(spark, "in")
    spark.createDataFrame([(k, y) for k, _, y in rest[:10]], "id long, label int").coalesce(1).write.parquet(path)
    stream = spark.readStream.schema("id long, label int").parquet(path)
    attach_stream(view, stream, "examples", shared_path(spark, "cp")).awaitTermination()
    exactly(view)
    before = view.round
    # a batch that is sent again, as after a failure, changes nothing
    attach_stream(view, stream, "examples", shared_path(spark, "cp2")).awaitTermination()
    assert view.round == before
    more = shared_path(spark, "more")
    spark.createDataFrame([(2000, [1.0, 1.0, 1.0])], "id long, f array<double>").write.parquet(more)
    view.last_batch = -1
    attach_stream(view, spark.readStream.schema("id long, f array<double>").parquet(more), "entities", shared_path(spark, "cp3")).awaitTermination()
    assert view.label_of(2000) is not None
    exactly(view)


def test_replay_agrees_with_the_view_and_the_family(small):
    entities, batch = small
    models = [TRAINER.fit([(f, y) for _, f, y in batch[:40]], 3)]
    for _, f, y in batch[40:52]:
        models.append(TRAINER.step(models[-1], f, y))
    largest = vectors.max_norm(entities, 2)
    family = replay.costs_of(replay.cost_family(entities, models, largest), len(models))
    for s in (0, 5):
        assert [b.n_band for b in replay.band_counts(entities, models, s, largest, HolderPair())] == [int(c) for c in family[s][s:]]
    rows = replay.replay_rounds(entities, models, lambda _, a, c: a >= c, largest, 400)
    view, rest = start(small, slack=False)
    for k in range(12):
        view.update(rest[k : k + 1])
    assert [(s.round, s.stored, s.n_band, s.reclustered) for s in view.history] == [(r[0], r[1], r[4], r[7]) for r in rows]


def test_memory_formulas():
    assert hybrid_bytes(582_000, 0, 4, 1) == 6_984_000 and hybrid_bytes(124_000, 0, 4, 1) == 1_488_000
    assert hybrid_bytes(100, 10, 8, 32) == 10 * 40 + 1600 and full_bytes(100, 8, 32) == 4000


def test_gather_orders_by_id(spark, small):
    got = gather(small[0], spark.createDataFrame([(9, 1), (2, -1)], "id long, label int"))
    assert [(k, y) for k, _, y in got] == [(2, -1), (9, 1)]


def test_scores_and_norms_agree_for_dense_and_sparse(spark):
    w = np.array([0.5, -1.0, 2.0])
    dense = spark.createDataFrame([(1, [1.0, 2.0, 3.0]), (2, [0.0, 0.0, 0.0])], "id long, f array<double>")
    sparse = dense.select("id", F.struct(F.array(*map(F.lit, range(3))).alias("idx"), F.col("f").alias("val")).alias("f"))
    for df in (dense, sparse):
        rows = df.select(vectors.score(df, Model(w, 0.25)).alias("e"), *[vectors.vector_norm(df, q).alias(f"n{k}") for k, q in enumerate((1, 2, float("inf"), 3))]).collect()
        assert [r["e"] for r in rows] == [4.25, -0.25]
        assert [rows[0][f"n{k}"] for k in range(4)] == pytest.approx([6, 14**0.5, 3, 36 ** (1 / 3)])
    wide = spark.createDataFrame([(1, [1.0] * 200)], "id long, f array<double>")
    assert wide.select(vectors.score(wide, Model(np.ones(200), 1.0))).first()[0] == 199


def test_feature_functions(spark):
    docs = spark.createDataFrame([(1, "The cat the hat", "x"), (2, None, None), (3, "cat", "y")], "id long, text string, kind string")
    tf = {r["id"]: r["f"] for r in fx.TermFrequency("text", 1 << 10, "l1").transform(docs, "id").collect()}
    assert sorted(tf[1]["val"]) == [0.25, 0.25, 0.5] and tf[2]["val"] == [] and sum(tf[3]["val"]) == 1
    assert tf[1]["idx"] == sorted(tf[1]["idx"])
    l2 = fx.TermFrequency("text", 1 << 10, "l2").transform(docs, "id").where("id = 1").first()["f"]["val"]
    assert sum(v * v for v in l2) == pytest.approx(1)
    idf = fx.TfIdf("text", 1 << 10).fit(docs)
    again = fx.TfIdf("text", 1 << 10).fit(docs.where("id < 3")).update(docs.where("id = 3"))
    assert again.n_docs == 3 and (idf.frequencies == again.frequencies).all()
    assert idf.transform(docs, "id").where("id = 1").first()["f"]["val"]
    hot = {r["id"]: r["f"] for r in fx.OneHot(("kind",), 64).transform(docs, "id").collect()}
    assert hot[2]["idx"] == [] and hot[1]["val"] == [1.0]
    both = fx.Concat((fx.OneHot(("kind",), 64), fx.TermFrequency("text", 32, None)))
    row = both.transform(docs, "id").where("id = 3").first()["f"]
    assert both.dim == 96 and max(row["idx"]) >= 64
    dense = spark.createDataFrame([(1, 2.0, 3.0)], "id long, a double, b double")
    poly = fx.Polynomial2(fx.DenseColumns(("a", "b")))
    assert poly.transform(dense, "id").first()["f"] == [2, 3, 4, 6, 9] and poly.dim == 5
    rff = fx.RandomFourier(fx.DenseColumns(("a", "b")), 2000, 0.1)
    f = np.array(rff.transform(dense, "id").first()["f"])
    assert f @ f == pytest.approx(1, abs=0.1)
    fx.register_feature("mine", lambda: fx.DenseColumns(("a",)))
    assert fx.get_feature("mine").dim == 1
