"""Golden values, properties and brute force of the linking engine."""

import random
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from slicelink.functions import sqlfuncs, templates, tokens
from slicelink.plans import catalog as C
from slicelink.operators import relational
from slicelink.plans import cost, examples, experiments, groups, linkers, linking, metrics, slicing, sqlgen, train, workload
from slicelink.plans import queries as linking_queries
from slicelink.sources import readers
from slicelink.streaming import online


@pytest.fixture(scope="module")
def base(spark, sf):
    return C.base(spark, sf).cache()


@pytest.fixture(scope="module")
def ordered(base):
    return groups.order(base).cache()


@pytest.fixture(scope="module")
def question(spark):
    return spark.createDataFrame([(1, "main", "number of orders per customer segment", ["customer", "orders"], "SELECT 1", "easy", "t", "train")], workload.QA)


def sums(slices):
    return [r.slice_tokens for r in slices.orderBy("slice_id").collect()]


@pytest.mark.parametrize("cap, want", [(100, [84, 93, 98, 39]), (84, [27, 74, 76, 82, 55]), (50, [27, 57, 49, 44, 43, 39, 42, 13]), (200, [199, 115]), (315, [314])])
def test_packing_golden(ordered, cap, want):
    got = slicing.pack(ordered, cap)
    assert sums(got) == want
    assert [r.oversize for r in got.orderBy("slice_id").collect()] == [n >= cap for n in want]


def test_packing_options(ordered, base):
    with pytest.raises(ValueError):
        slicing.pack(ordered, 50, oversize="error")
    assert slicing.check(slicing.pack(ordered, 60, method="ffd"), base).first()[3:] == (0, 0, 0)
    grouped = slicing.pack(ordered, 1000, boundary="group")
    assert grouped.count() == 3
    parts = slicing.split_columns(base.where("table_name = 'lineitem'"), 40).collect()
    assert sum(len(p["columns"]) for p in parts) == 11 and len(parts) > 1


def test_cap_for(ordered):
    sizes = [r.n_tokens for r in ordered.orderBy("pos").collect()]
    assert [slicing.cap_for(sizes, m) for m in (7, 5, 4, 2, 1)] == [(58, 7), (77, 5), (85, 4), (166, 2), (315, 1)]


def test_orders_are_permutations(base):
    for how in ("canonical", "fk_bfs", "size_desc", "seeded_shuffle"):
        assert sorted(r.pos for r in groups.order(base, how).collect()) == list(range(1, 15))


@pytest.mark.parametrize("seed, cap", [(1, 50), (2, 100), (3, 121)])
def test_distributed_packing_equals_sequential(spark, seed, cap):
    r = random.Random(seed)
    sizes = [r.choice([0, 1, 2, 3, 8, 40, 120]) for _ in range(900)]
    df = spark.createDataFrame(list(enumerate(sizes)), "pos long, n_tokens long")
    got = [x.slice_id for x in slicing.pack_distributed(df, cap, 97).orderBy("pos").collect()]
    want, k, total = [], 0, 0
    for n in sizes:
        if not k or total + n >= cap:
            k, total = k + 1, n
        else:
            total += n
        want.append(k)
    assert got == want
    assert slicing.pack_distributed(df.limit(0), cap).count() == 0


def test_groups_by_joins(base):
    a = sorted(map(tuple, groups.correlate(base).collect()))
    assert a == sorted(map(tuple, groups.correlate(base, driver_tables=0).collect())) and len(a) == 9


@pytest.mark.parametrize("kw, rows", [({}, 6), ({"balance": "none"}, 4), ({"emission": "per_table"}, 10), ({"balance": "weight"}, 4)])
def test_examples_golden(question, ordered, base, kw, rows):
    assert examples.sliced(question, slicing.pack(ordered, 100), base, **kw).count() == rows


def test_history_window_agrees(question, ordered):
    st = examples.steps(question, slicing.pack(ordered, 100)).select("qid", F.inline("steps"))
    both = slicing.window_history(st.withColumnRenamed("history", "h")).collect()
    assert all(r.h == r.history for r in both)


def test_no_exchange_of_questions_before_texts(spark, question, ordered):
    made = slicing.pack(ordered, 100)
    plan = examples.steps(question, spark.createDataFrame(made.collect(), made.schema))._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("Join") == 1


def test_measures_golden(spark):
    gold = spark.createDataFrame([(i, ["a", "b"]) for i in range(4)], "qid int, gold_tables array<string>")
    pred = spark.createDataFrame([(0, ["a", "b"]), (1, ["a", "b", "c"]), (2, ["a"]), (3, [])], "qid int, pred_tables array<string>")
    r = metrics.link_scores(pred, gold).first()
    assert (r.tot_acc, r.filt_acc, r.avg_prec, r.avg_rec) == (25.0, 50.0, 66.6667, 62.5)


def test_memory_fit():
    m = cost.MemoryModel.fit(cost.MEMORY_POINTS[1])
    assert round(m.base, 1) == 19517.6 and round(2 * m.per_token, 2) == 23.76


def test_perfect_oracle(spark, base):
    qa = workload.qa_frame(spark, workload.make_qa([(t, t) for t in C.TABLES], 30, "main"))
    r = metrics.link_scores(linkers.NoisyOracle(1, 0, 0).predict(qa, base), qa).first()
    assert (r.tot_acc, r.filt_acc, r.avg_prec, r.avg_rec) == (100.0,) * 4


def test_order_of_slices_does_not_matter_without_history(spark, base):
    qa = workload.qa_frame(spark, workload.make_qa([(t, t) for t in C.TABLES], 20, "main"))
    one = linkers.LexicalLinker(0.3, 0.0)
    a, b = ({r.qid: r.pred_tables for r in linking.infer_sliced(one, qa, slicing.pack(groups.order(base, how), 100), base).collect()} for how in ("canonical", "size_desc"))
    assert a == b


def test_rounds_follow_answers(spark, base, ordered, question):
    sl = slicing.pack(ordered, 100)
    said = linkers.ExternalLinker(lambda xs: ["customer, nonsense" if "customer(" in x else "orders" if "orders(" in x else templates.NONE for x in xs])
    r = linking.infer_rounds(said.answer, question, sl, base).first()
    assert r.pred_tables == ["customer", "orders"] and r.n_calls == 4


@pytest.fixture(scope="module")
def small(spark, base, ordered):
    """Sixty questions over the base tables, and a shelf of their slices."""
    qa = workload.qa_frame(spark, workload.make_qa([(t, t) for t in C.TABLES], 60, "main"))
    return qa.cache(), linking.Shelf.of(base, slicing.pack(ordered, 100))


def plain_features(shelf, words, k, past):
    """The features of one question's prompt, word by word."""
    weight, q = lambda w: shelf.weight.get(w, 1.0), set(words)
    total, names = sum(map(weight, q)) or 1.0, shelf.slices[k]
    known = set().union(*shelf.short.values(), *shelf.long.values())
    seen, told = set().union(*(shelf.long[h] for h in past)), set().union(*(shelf.short[h] for h in past))
    whole = {t: shelf.short[t] <= q for t in names}
    overlap = {t: sum(weight(w) for w in q & shelf.short[t]) / total for t in names}
    best = max(overlap.values())
    return [
        [overlap[t], sum(weight(w) for w in q & shelf.long[t]) / total, len(q & shelf.short[t]) / len(shelf.short[t]), whole[t], whole[t] and any(whole[u] and shelf.short[t] < shelf.short[u] for u in names),
         len(told & shelf.short[t]) / len(shelf.short[t]), any(h in shelf.keys[t] for h in past), sum(weight(w) for w in q & seen & known) / total, min(len(past), 4) / 4, k / len(shelf.slices), overlap[t] / best if best else 0.0]
        for t in names
    ]


def test_features_of_many_questions_equal_plain_ones(small):
    qa, shelf = small
    rows = linking.questions_of(qa).collect()
    bench = shelf.bench([r.words for r in rows], 1 << 12)
    gold = bench.gold([r.gold_tables for r in rows])
    for k in range(len(shelf.slices)):
        past = gold * (bench.slice_of < k)
        x = bench.prompts(k, past).x
        for i, r in enumerate(rows):
            before = [t for s in shelf.slices[:k] for t in s if t in r.gold_tables]
            assert np.allclose(x[i], np.array(plain_features(shelf, r.words, k, before), float))


def test_lessons_are_the_examples(spark, small, base, ordered):
    """Prompts, labels and weights of the matrix form are those of the example builder."""
    qa, shelf = small
    rows = linking.questions_of(qa).collect()
    bench = shelf.bench([r.words for r in rows], 64)
    for history, kw in ((True, {}), (False, {"history": "none", "balance": "weight"})):
        made = Counter()
        for prompt, y, weight in bench.lessons(bench.gold([r.gold_tables for r in rows]), history):
            k = int(bench.slice_of[prompt.here[0]]) + 1
            for i, w, target, past in zip(prompt.some, weight, y, prompt.past, strict=True):
                made[rows[i].qid, k, w, tuple(sorted(bench.names[j] for j, v in zip(prompt.here, target, strict=True) if v)), tuple(sorted(bench.names[j] for j in np.flatnonzero(past)))] += 1
        want = Counter((r.qid, r.slice_id, r.weight, () if r.assistant == templates.NONE else tuple(sorted(r.assistant.split(", "))), tuple(sorted(r.history))) for r in examples.sliced(qa, slicing.pack(ordered, 100), base, **kw).collect())
        assert made == want


@pytest.mark.parametrize("one", [linkers.PairLogit(), linkers.LowRankText(linkers.LowRankConfig(rank=3, dim=64))])
def test_gradients_equal_differences(small, one):
    qa, shelf = small
    rows = linking.questions_of(qa).limit(12).collect()
    bench = shelf.bench([r.words for r in rows], 64)
    gold = bench.gold([r.gold_tables for r in rows])

    def loss(at=None):
        at = one.start(bench) if at is None else at
        return sum(one.learn(p, y, w, at) for p, y, w in bench.lessons(gold, True))

    at = one.start(bench)
    loss(at)
    grads = one.rows(bench, at)
    fields = [("g", "w")] if isinstance(one, linkers.PairLogit) else [("t", "tuned"), ("a", "a"), ("b", "b")]
    for name, attr in fields:
        value = getattr(one, attr)
        for row, v in [(r, v) for (n, r), v in grads.items() if n == name][:6]:
            for j in (0, len(v) - 1):
                spot = (j,) if value.ndim == 1 else (row, j)
                keep, sides = value[spot], []
                for e in (1e-5, -1e-5):
                    value[spot] = keep + e
                    sides.append(loss())
                value[spot] = keep
                assert abs((sides[0] - sides[1]) / 2e-5 - v[j]) < 1e-3 * max(1, abs(v[j]))


@pytest.mark.parametrize("direct", [64, 0])
def test_training_lowers_loss_and_links(small, monkeypatch, direct):
    qa, shelf = small
    monkeypatch.setattr(train, "DIRECT", max(direct, 1))
    few = qa.repartition(3) if not direct else qa
    one, losses = train.fit(linkers.LowRankText(linkers.LowRankConfig(rank=4, dim=256)), few, shelf, True, 1, 8)
    assert losses[-1] < losses[0]
    two, falls = train.fit(linkers.PairLogit(), few, shelf, True)
    assert falls[-1] < 0.3 * falls[0]
    r = metrics.link_scores(linking.infer(two, qa, shelf), qa).first()
    assert r.n == 60 and r.filt_acc > 60


def test_all_methods_and_gates_at_a_small_scale(spark, sf):
    rows = {(r.dataset, r.method, r.model): r for r in experiments.methods(spark, sf, scale=0.03).collect()}
    assert len(rows) == 24
    status = lambda d, m: [rows[d, m, x].status for x in experiments.MODELS]
    assert status(1, "full_schema") == ["OOM", "OOM", "CONTEXT_EXCEEDED"] and status(2, "full_schema") == ["OK", "OK", "CONTEXT_EXCEEDED"]
    assert status(1, "untrained") == ["OK", "OK", "CONTEXT_EXCEEDED"] and status(1, "slice_wise") == ["OK"] * 3
    assert [rows[1, "slice_wise", x].calls for x in experiments.MODELS] == [8, 8, 11]
    for r in rows.values():
        assert r.status == "OK" and r.n == {1: 11, 2: 5}[r.dataset] and r.tot_acc <= r.filt_acc <= r.avg_rec + 1e-9 or r.status != "OK" and r.tot_acc is None


def test_execution_and_guard(spark, sf):
    C.register_fleet(spark, sf, [("region", "region", "true"), ("nation", "nation", "true")])
    pairs = [(1, "SELECT count(*) FROM region", "SELECT count(1) AS n FROM region"), (2, "SELECT 3", "SELECT count(*) FROM region"), (3, "DROP TABLE region", "SELECT 1"), (4, "SELECT nope FROM region", "SELECT 1"), (5, "SELECT r_name FROM region ORDER BY r_name DESC", "SELECT r_name FROM region ORDER BY r_name")]
    got = metrics.execution_matches(spark, pairs)
    assert [(q, ok) for q, ok, _ in got] == [(1, 1), (2, 0), (3, 0), (4, 0), (5, 0)] and got[2][2] == "INVALID"
    assert metrics.plan_match(spark, "SELECT r_name FROM region WHERE r_regionkey > 1 AND r_name > 'A'", "SELECT r_name FROM region WHERE r_name > 'A' AND r_regionkey > 1")


def test_skeletons_fill_given_tables():
    base = {"orders": "orders", "orders_f_p1": "orders", "customer": "customer"}
    assert sqlgen.fill("SELECT count(*) FROM orders JOIN customer ON orders.o_custkey = customer.c_custkey", ["orders", "customer"], ["orders_f_p1", "customer"], {"order"}, base) == "SELECT count(*) FROM orders_f_p1 JOIN customer ON orders_f_p1.o_custkey = customer.c_custkey"
    assert sqlgen.fill("SELECT 1 FROM orders", ["orders"], ["customer"], set(), base) is None


def test_fleet_sizes_and_gate(spark, sf):
    assert len(C.fleet_names(254)) == 254 and len({n for n, _, _ in C.shard_list()}) == len(C.shard_list())
    assert C.type_name(C.footers(spark, sf, ["orders"])["orders"]["o_orderdate"].dataType) == "timestamp"
    report = spark.createDataFrame([("full_schema", 8000), ("sliced", 1600)], "variant string, max_tokens int")
    assert [r.status for r in cost.gate(report, experiments.memory(1), 1, 80_000, 100_000).orderBy("variant").collect()] == ["OOM", "OK"]


def test_sql_functions(spark):
    sqlfuncs.register(spark)
    assert spark.sql("SELECT token_count('a_b(c int)') AS n, link_f1(array('a'), array('a', 'b')) AS f").first()[:] == (7, 2 / 3)
    assert [r.slice_id for r in spark.sql("SELECT * FROM pack_slices(array('a', 'b', 'c'), array(5, 5, 5), 11)").collect()] == [1, 1, 2]


def test_bpe_counts_fall_with_vocabulary(base):
    small, large = tokens.train_bpe(base, "text", 20), tokens.train_bpe(base, "text", 200)
    text = base.first().text
    assert small.count(text) >= large.count(text) > 0


def test_ddl_source(spark, tmp_path):
    (tmp_path / "a.sql").write_text("CREATE TABLE a (id INT, v DECIMAL(10, 2), PRIMARY KEY (id));\nCREATE TABLE b (id INT, a_id INT, FOREIGN KEY (a_id) REFERENCES a (id));")
    rows = {r.table_name: r for r in readers.read_ddl(spark, str(tmp_path)).collect()}
    assert [c.name for c in rows["a"]["columns"]] == ["id", "v"] and rows["b"].fks[0].ref_table == "a"


def test_bad_records_and_runs(spark, tmp_path):
    (tmp_path / "x.csv").write_text("a,b\n1,2\nx,3\n")
    got = readers.read_any(spark, str(tmp_path / "x.csv"), "csv", "a int, b int").collect()
    assert len(got) == 2 and got[1]["_corrupt_record"] == "x,3"
    for _ in range(2):
        readers.write_run(spark.range(3), str(tmp_path / "runs"), "r1")
    assert spark.read.parquet(str(tmp_path / "runs")).count() == 3


def test_reslicer_equals_full_pack():
    r = random.Random(4)
    tables = [(f"t{i:02}", r.randint(1, 30)) for i in range(40)]
    live = online.Reslicer(tables, 60)
    for change in ([("t20", 50)], [("t05", None)], [("t39x", 7)], [("t00", 59)]):
        live.apply(change)
        assert live.slices == online.Reslicer(live.tables, 60).slices


def test_stateful_stream(spark, sf):
    got = online.stream_link_stateful(spark, "/root/testdata/sf0.01")
    assert got.where("NOT complete").count() == 0


@pytest.mark.parametrize("width", [1, 7, 50])
def test_range_join_at_fractional_bounds(spark, width):
    points = spark.createDataFrame([(i, i * 0.3 - 5) for i in range(400)], "i int, at double")
    ranges = [(49.5, 50.5), (50.0, 50.0), (0.0, 50.0), (-3.2, 0.1), (99.9, 100.0), (20.0, 19.0), (50.0, 100.0)]
    got = relational.range_join(points, spark.createDataFrame(ranges, "lo double, hi double"), "at", "lo", "hi", width)
    assert sorted((r.i, r.lo, r.hi) for r in got.collect()) == sorted((i, lo, hi) for i in range(400) for lo, hi in ranges if lo <= i * 0.3 - 5 < hi)


def test_short_and_odd_passages_are_linked(spark, tmp_path):
    text = "one alpha beta gamma delta epsilon\tzeta eta\n theta iota"
    passages = ["alpha", "lph", "alpha beta", "alpha beta gamma", "alpha beta gamma delta", "beta gamma delta epsilon\tzeta", "pha beta gamma delta epsilon\tzeta et", "alpha beta gamma delta epsilon zeta", " theta", "eta\n theta iota", "nowhere to be found at all", "", "one alpha beta gamma delta epsilon\tzeta eta\n theta iota", "gamma beta"]
    spark.createDataFrame(list(enumerate(passages)), "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    docs = [(1, text), (2, "xalphax"), (3, None), (4, ""), (5, "alpha beta gamma"), (5, text)]
    spark.createDataFrame(docs, "doc_id long, text string").write.parquet(str(tmp_path / "documents.parquet"))
    got = sorted((r.item_id, r.doc_id) for r in linking_queries.passage_link(spark, str(tmp_path)).collect())
    assert got == sorted((i, d) for i, p in enumerate(passages) for d, t in docs if p and t and p in t)


def test_dense_blocks(spark):
    r = np.random.default_rng(3)
    v = r.integers(-3, 4, (90, 4)).astype(float) + 0.5  # many ties
    df = spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(v)], "vec_id long, embedding array<double>")
    n = v / np.linalg.norm(v, axis=1, keepdims=True)
    s = np.round(n @ n.T, 6)
    want = sorted((q, int(j), k + 1) for q in range(0, 90, 7) for k, j in enumerate([j for j in np.lexsort((np.arange(90), -s[q])) if j != q][:5]))
    for block in (8, 4096):
        got = linkers.DenseLinker(5, block).nearest(df.where("vec_id % 7 = 0"), df)
        assert sorted((x.query_id, x.vec_id, x["rank"]) for x in got.collect()) == want


def test_ordered_results_are_told_apart_without_collecting(spark):
    rows = spark.range(0, 1000, 1, 7).select((F.col("id") * 7919 % 1009).alias("x"))
    assert metrics.digest(rows.orderBy("x"), True) == metrics.digest(rows.repartition(3).orderBy("x"), True) != metrics.digest(rows.orderBy(F.desc("x")), True)
    assert metrics.digest(rows) == metrics.digest(rows.orderBy("x"))


@pytest.mark.parametrize("seed, cap, fan", [(1, 50, 3), (2, 121, 2), (5, 7, 4)])
def test_packing_in_a_tree_of_blocks(spark, seed, cap, fan):
    r = random.Random(seed)
    sizes = [r.choice([0, 0, 1, 2, 3, 8, 40, 120]) for _ in range(700)]
    df = spark.createDataFrame([(i + 1000, n) for i, n in enumerate(sizes)], "pos long, n_tokens long")
    got = [x.slice_id for x in slicing.pack_distributed(df, cap, 23, fan).orderBy("pos").collect()]
    want, k, total = [], 0, 0
    for n in sizes:
        if not k or total + n >= cap:
            k, total = k + 1, n
        else:
            total += n
        want.append(k)
    assert got == want


def test_summaries_of_two_blocks():
    r = random.Random(8)
    for _ in range(300):
        cap = r.randint(2, 40)
        one, two = ([r.randint(0, 30) for _ in range(r.randint(0, 12))] for _ in range(2))
        both = slicing._then(slicing._summary(np.array(one, np.int64), cap), slicing._summary(np.array(two, np.int64), cap))
        whole = slicing._summary(np.array(one + two, np.int64), cap)
        assert all(slicing._answer(both, c) == slicing._answer(whole, c) for c in range(cap + 1))


def test_reslicer_in_the_order_of_groups_and_after_a_restart(spark, tmp_path):
    r = random.Random(4)
    tables = [(f"t{i:02}", r.randint(1, 30), None if i % 3 else f"t{i - i % 9:02}") for i in range(40)]
    live = online.Reslicer(tables, 60)
    assert [t for s in live.slices for t in s] == sorted((t for t, *_ in tables), key=lambda t: (int(t[1:]) % 3 > 0, f"t{int(t[1:]) - int(t[1:]) % 9:02}" if int(t[1:]) % 3 == 0 else "", t))
    for change in ([("t20", 50)], [("t05", None)], [("t39x", 7, "t00")], [("t00", 59)], [("zz", None)], [("t12", 9, None)]):
        live.apply(change)
        assert live.slices == online.Reslicer([(t, *live.of[t]) for t in live.of], 60).slices
    src, out = str(tmp_path / "changes"), str(tmp_path / "slices")
    spark.createDataFrame([("t07", 3, None), ("new", 29, "t09")], "table_name string, n_tokens int, lead string").write.parquet(src)
    online.reslice(online.read_stream(spark, src, "table_name string, n_tokens int, lead string", 100), live, out).awaitTermination()
    again = online.Reslicer.latest(spark, out, 60)
    assert (again.slices, again.version) == (live.slices, live.version)


def test_late_turns_get_their_own_history(spark, tmp_path):
    path, kind = str(tmp_path / "turns"), "conv_id long, turn long, role string, at timestamp"
    for k, rows in enumerate([[(1, 1, "system"), (1, 3, "assistant"), (2, 1, "user")], [(1, 2, "user"), (1, 4, "user")]]):
        spark.createDataFrame(rows, "conv_id long, turn long, role string").withColumn("at", F.timestamp_seconds(F.col("turn") + 1_000_000_000)).coalesce(1).write.mode("append").parquet(path)
        __import__("time").sleep(1.1)
    got = {(r.conv_id, r.turn): r.before for r in online.drain(online.converse(online.read_stream(spark, path, kind))).collect()}
    assert got == {(1, 1): "", (1, 3): "system", (2, 1): "", (1, 2): "system", (1, 4): "system,user,assistant"}


def test_explain_link_and_bucketed_plan(spark, sf):
    sqlfuncs.register(spark)
    got = spark.sql("SELECT * FROM explain_link('number of orders by market segment', array('orders(o_key int)', 'customer(c_market string)'))").collect()
    assert sorted(map(tuple, got)) == [("customer", "market", False), ("orders", "order", True)]
    assert "Exchange" not in relational.bucketed_aggregate(spark, sf)._jdf.queryExecution().executedPlan().toString()
