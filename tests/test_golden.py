"""Hand-computed values, published aggregates and invariants of the library proper."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from tablemill.operators import agent as A
from tablemill.operators import corpus as C
from tablemill.operators import encoder as E
from tablemill.operators import factory as X
from tablemill.operators import metrics as M
from tablemill.operators import tables as T
from tablemill.plans import tables as table_plans
from tablemill.plans.registry import Tables


@pytest.fixture(scope="module")
def t(spark):
    return Tables(spark, "/root/testdata/sf0.001")


# --- measures ----------------------------------------------------------------


def test_published_gains_and_wins(spark):
    s = M.scores_frame(spark).cache()
    gain = lambda ours: {r.system: (r.gain, r.n_rows) for r in M.improvement(s, ours, [5, 6]).collect()}
    assert gain("P7")["G3"] == (35.20, 23) and gain("P72")["G3"] == (49.32, 20)
    assert gain("P7")["G4"][0] == 39.55 and gain("P72")["T1"][0] == 126.92
    assert [M.wins(s, x).first().wins for x in ("P7", "P72")] == [17, 18]


def test_micro_f1(spark):
    mk = lambda rows: spark.createDataFrame(rows, "sample_id int, label string")
    got = M.micro_f1(mk([(1, "a"), (2, "b"), (3, "c")]), mk([(1, "a"), (2, "b"), (3, "d")])).first()
    assert (got.tp, got.fp, got.fn) == (2, 1, 1) and abs(got.f1 - 2 / 3) < 1e-6


def test_mean_ap(spark):
    ranked = spark.createDataFrame([("q", i, i) for i in (1, 2, 3)], "query_id string, item int, rank int")
    rel = spark.createDataFrame([("q", 1), ("q", 3), ("z", 9)], "query_id string, item int")
    got = M.mean_ap(ranked, rel).first()
    assert got.queries == 2 and abs(got.map - (1 + 2 / 3) / 2 / 2) < 1e-6


def test_text_scores(spark):
    pair = lambda a, b: spark.createDataFrame([(1, a.split(), b.split())], "sample_id int, pred array<string>, gold array<string>")
    assert M.bleu(pair("a b c d e", "a b c d e")).first().bleu == 100
    assert M.bleu(pair("a b", "c d")).first().bleu == 0
    assert M.rouge_l(pair("a b c d", "a c d e")).first().rouge_l == 75
    assert M.sentence_bleu(pair("a b c d e", "a b c d e")).first().bleu == 100
    rng = np.random.default_rng(0)
    rows = [(i, [str(x) for x in rng.integers(0, 4, 7)], [str(x) for x in rng.integers(0, 4, 9)]) for i in range(20)]

    def lcs(a, b):
        d = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
        for i, x in enumerate(a):
            for j, y in enumerate(b):
                d[i + 1][j + 1] = d[i][j] + 1 if x == y else max(d[i][j + 1], d[i + 1][j])
        return d[-1][-1]

    got = spark.createDataFrame(rows, "i int, a array<string>, b array<string>").select("i", M.lcs(F.col("a"), F.col("b")).alias("l")).collect()
    assert {r.i: r.l for r in got} == {i: lcs(a, b) for i, a, b in rows}


def test_pass_at_k(spark):
    runs = spark.createDataFrame([("p", i < 2) for i in range(5)] + [("q", False)] * 5 + [("r", True)], "problem string, ok boolean")
    assert abs(M.pass_at_k(runs, 1).first().pass_at_k - (2 / 5 + 0 + 1) / 3) < 1e-6
    three = 1 - math.comb(3, 3) / math.comb(5, 3)
    assert abs(M.pass_at_k(runs, 3).first().pass_at_k - (three + 0 + 1) / 3) < 1e-6


def test_execution_accuracy(spark):
    mk = lambda rows: spark.createDataFrame(rows, "sample_id int, row_hash string")
    gold = mk([(1, "a"), (1, "a"), (2, "b"), (3, "c")])
    got = M.exec_acc(mk([(1, "a"), (1, "a"), (2, "b"), (2, "b")]), gold).first()
    assert (got.samples, got.correct) == (3, 1)


# --- corpus ------------------------------------------------------------------


def test_packing_is_whole_and_lossless(spark, t):
    for ctx in (64, 512):
        size = {r.doc_id: r.n for r in t.documents.select("doc_id", F.size(F.regexp_extract_all("text", F.lit(r"\S+"), F.lit(0))).alias("n")).where("n > 0").collect()}
        for packs, key in ((C.concat_cut(t.documents, ctx), ["pack_id"]), (C.by_length(t.documents, ctx), ["shard", "pack"])):
            rows = packs.collect()
            used, whole = {}, {}
            for r in rows:
                used[tuple(r[k] for k in key)] = used.get(tuple(r[k] for k in key), 0) + r["to"] - r["from"]
                whole[r.doc_id] = whole.get(r.doc_id, 0) + r["to"] - r["from"]
            assert max(used.values()) <= ctx and whole == size
        cut = {d for d, n in size.items() if n <= ctx} & {r[0] for r in C.by_length(t.documents, ctx).groupBy("doc_id").count().where("count > 1").collect()}
        assert not cut


def test_masks_fall_with_the_threshold(t):
    scored = C.excess(t.documents, t.labels).cache()
    kept = [C.selective_loss(C.masked(scored, x)).agg(F.sum("n_kept")).first()[0] for x in (0.2, 0.6, 0.9)]
    assert kept[0] >= kept[1] >= kept[2]


def test_registry_has_54_tags():
    from tablemill.functions.text import lines, tokens  # noqa: F401

    names = C.tag_columns(F.col("text"), F.col("ws"), F.col("ls"))
    assert len(names) == 48


def test_near_groups(spark):
    base = " ".join(f"w{i}" for i in range(100))
    rows = [(5, base), (3, base), (8, base + " extra"), (9, " ".join(f"v{i}" for i in range(100))), (10, None), (11, "")]
    got = {r.doc_id: r.class_id for r in C.near_groups(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {3: 3, 5: 3, 8: 3, 9: 9, 10: 10, 11: 10}


def test_components_of_a_long_chain(spark):
    links = spark.createDataFrame([(i, i + 1) for i in range(40)] + [(100, 101)], "x long, y long")
    got = {r.node: r.root for r in C.components(links).collect()}
    assert all(got[i] == 0 for i in range(41)) and got[101] == 100


# --- tables ------------------------------------------------------------------


def cells(spark, rows):
    return spark.createDataFrame(rows, "table_id string, row_id long, col_id int, col_name string, value string")


def boundary(spark):
    rows = []
    for r in range(10):
        rows += [("b", r, 0, "k", str(r)), ("b", r, 1, "x30", None if r < 3 else "v"), ("b", r, 2, "x40", None if 2 < r < 7 else "v"), ("b", r, 3, "len100", "y" * 100), ("b", r, 4, "len101", "y" * (101 if r == 0 else 1))]
    rows += [("four", r, c, f"c{c}", str(r)) for r in range(4) for c in range(2)] + [("five", r, c, f"c{c}", str(r)) for r in range(5) for c in range(2)] + [("one", r, 0, "c0", str(r)) for r in range(9)]
    return cells(spark, rows)


def test_cleaning_limits(spark):
    kept, ledger = T.clean(boundary(spark))
    assert {(r.table_id, r.object_id, r.rule) for r in ledger.collect()} == {("b", "x40", "sparse_column"), ("b", "len101", "long_content"), ("b", "0", "sparse_row"), ("b", "1", "sparse_row"), ("b", "2", "sparse_row"), ("four", "four", "small_table"), ("one", "one", "small_table")}
    again, more = T.clean(kept)
    assert more.count() == 0 and again.count() == kept.count()


def test_transpose_twice_is_identity(spark):
    c = cells(spark, [("t", r, k, f"c{k}", f"{r}-{k}") for r in range(4) for k in range(3)])
    twice = T.transpose(T.transpose(c))
    assert {(r.row_id, r.col_id, r.value) for r in twice.collect()} == {(r, k, f"{r}-{k}") for r in range(4) for k in range(3)}


def test_anonymise_is_one_to_one(t):
    c = table_plans.small_cells(t)
    out, mapping = T.anonymise(c)
    for k in ("header", "value"):
        m = mapping.where(F.col("kind") == k)
        assert m.count() == m.select("table_id", "old").distinct().count()
    assert out.count() == c.count()
    count = lambda df: sorted(r["count"] for r in df.groupBy("table_id", "col_id", "value").count().collect())
    assert count(out) == count(c)


def test_text_forms(t):
    got = {f: {r.table_id: r.text for r in T.serialise(table_plans.small_cells(t), f).collect()} for f in T.FORMATS}
    assert got["csv"]["region"].splitlines()[0] == "r_regionkey,r_name"
    assert got["markdown"]["region"].splitlines()[1] == "|---|---|"
    assert len(T.combos()) >= 20 and all(len(x) == 2 for x in got.values())


# --- encoder -----------------------------------------------------------------


def test_attention_has_no_order():
    rng = np.random.default_rng(0)
    e = rng.normal(size=(6, 5, 64))
    rows, cols = rng.permutation(6), rng.permutation(5)
    out = E.encode_grid(e, 2)
    assert np.allclose(E.encode_grid(e[rows][:, cols], 2), out[rows][:, cols])
    assert not np.allclose(E.encode_grid(e[rows], 2, positions=True), E.encode_grid(e, 2, positions=True)[rows])


def test_attention_against_loops():
    rng = np.random.default_rng(1)
    x, w = rng.normal(size=(3, 8)), E.weights(8, 1, 3)[0]
    q, k, v = (x @ w[c] for c in "qkv")
    mixed = np.zeros((3, 8))
    for h in range(2):
        s = slice(4 * h, 4 * h + 4)
        for i in range(3):
            p = np.exp([q[i, s] @ k[j, s] / 2 for j in range(3)])
            mixed[i, s] = (p / p.sum()) @ v[:, s]
    y = E.layer_norm(x + mixed @ w["o"])
    assert np.allclose(E.attend(x, w, heads=2), E.layer_norm(y + np.maximum(y @ w["up"], 0) @ w["down"]))


def test_adapter_merges(spark):
    rng = np.random.default_rng(2)
    x, w = rng.normal(size=(50, 64)), E.adapter_weights(64)
    whole = E.adapter_state(x, w)
    merged = E.merge_states(E.merge_states(E.adapter_state(x[:7], w), E.adapter_state(x[7:30], w)), E.adapter_state(x[30:], w))
    assert all(np.allclose(a, b) for a, b in zip(whole, merged))
    df = spark.createDataFrame([("t", 0, v.tolist()) for v in x], "table_id string, col_id int, vec array<double>").repartition(3)
    got = np.array(E.adapter_columns(df).first().vecs)
    assert np.allclose(got, (whole[2] / whole[1][:, None]) @ w["out"])


def test_contrast_of_two_columns(spark):
    rows = [("t", c, s, [1.0, 0.0] if c else [0.0, 1.0], 0) for c in (0, 1) for s in (0, 1)]
    got = E.contrast_loss(spark.createDataFrame(rows, "table_id string, col_id int, snap int, vec array<double>, batch int"), 0.5).collect()
    want = -math.log(math.exp(2) / (math.exp(2) + 2))
    assert len(got) == 4 and all(abs(r.loss - want) < 1e-9 for r in got)


def test_gradient_of_the_head():
    rng = np.random.default_rng(3)
    x, plus, w = rng.normal(size=(6, 4)), np.array([1, 0, 3, 2, 5, 4]), np.eye(4) + 0.1 * rng.normal(size=(4, 4))
    loss, grad = E.batch_gradient(x, plus, w, 0.3)
    for i, j in ((0, 0), (1, 3), (2, 1)):
        step = np.zeros((4, 4))
        step[i, j] = 1e-5
        numeric = (E.batch_gradient(x, plus, w + step, 0.3)[0] - E.batch_gradient(x, plus, w - step, 0.3)[0]) / 2e-5
        assert abs(numeric - grad[i, j]) < 1e-4 * max(1, abs(numeric))


def test_splice_puts_vectors_in_slots(spark):
    p = spark.createDataFrame([("t", "a <vec> x\nb <vec> y")], "table_id string, prompt string")
    v = spark.createDataFrame([("t", 0, [[1.0]]), ("t", 1, [[2.0]])], "table_id string, col_id int, vecs array<array<double>>")
    parts = E.splice(p, v).first().parts
    assert [q.kind for q in parts] == ["mark", "text", "vec", "text", "vec", "text", "mark"] and parts[4].vec == [[2.0]]


# --- factory and agent -------------------------------------------------------


def test_statements_are_admitted_with_care():
    good = ["SELECT 1", "with a as (select 1) select * from a", "select 'drop table x' as s", "values (1)"]
    bad = ["DROP TABLE x", "select 1; select 2", "insert into t values (1)", "-- only a comment", "create view v as select 1"]
    assert all(map(X.admissible, good)) and not any(map(X.admissible, bad))


def test_sql_errors_have_classes(spark, t):
    got = {r.sample_id: r.error_class for r in X.run_sql(spark, [("a", "SELECT r_name FROM region"), ("b", "SELECT nope FROM region"), ("c", "SELEC 1"), ("d", "SELECT (1 FROM region"), ("e", "SELECT cast('x' AS int) FROM region"), ("f", "SELECT 1 FROM region WHERE 1 = 0")], {"region": t.region}).collect()}
    assert got == {"a": "ok", "b": "field_mismatch", "c": "refused", "d": "syntax", "e": "type_error", "f": "empty"}


def test_programs_are_limited(spark):
    rows = [("ok", "print(6 * 7)"), ("loop", "while True: pass"), ("file", "open('/tmp/tablemill-test', 'w').write('x' * 10)"), ("key", "{}['a']"), ("memory", "x = 'a' * (1 << 34)"), ("syntax", "print((1")]
    got = {r.sample_id: (r.status, r.error_class, r.output) for r in X.run_python(spark.createDataFrame(rows, "sample_id string, code string"), seconds=1).collect()}
    assert got["ok"] == ("ok", "ok", "42\n") and got["loop"][1] == "timeout" and got["key"][1] == "field_mismatch" and got["syntax"][1] == "syntax"
    assert got["file"][0] == "error" and got["memory"][0] == "error"


def test_funnel_only_shrinks(spark, t):
    kept = [r.kept for r in M.funnel(X.staged(X.drafts(X.questions(spark)), {n: getattr(t, n) for n in X.SEMANTIC})).orderBy("step").collect()]
    assert kept == sorted(kept, reverse=True) and kept[-1] > 0


def test_loop_repairs(spark, t):
    runs = A.loop(spark, ("q", "What is the average total price of orders? o_totalprice"), {"orders": t.orders}).collect()
    assert runs[-1].status == "ok" and len(runs) <= 3


def test_dsl_refuses(t):
    with pytest.raises(ValueError):
        A.Dsl.parse("from orders | drop all")
    with pytest.raises(ValueError):
        A.Dsl.parse("from orders | keep 1 = 1; delete from x")
    assert A.Dsl.compile("from region | keep r_regionkey > 2 | show r_name", lambda n: getattr(t, n)).count() == 2


def test_dag_order():
    d = A.Dag({"c": None, "b": None, "a": None}, [("a", "b"), ("b", "c")])
    assert d.order() == ["a", "b", "c"]
    with pytest.raises(ValueError):
        A.Dag({"a": None, "b": None}, [("a", "b"), ("b", "a")]).order()


def test_prompts_and_rows_round_trip(t):
    back = X.parse_receipts(X.receipts(t.orders, t.lineitem))
    assert back.count() == t.lineitem.join(t.orders, F.col("l_orderkey") == F.col("o_orderkey")).count()
    assert X.prompts(X.questions(t.spark)).where(F.col("prompt").contains("{")).count() == 0


def test_sql_results_are_taken_whole(spark):
    """More rows than 200: all are counted, the hash is free of order and sees every row."""
    orders = spark.read.parquet("/root/testdata/sf0.001/orders.parquet")
    some = "SELECT o_orderkey, CASE WHEN o_orderkey > 9 THEN o_totalprice / 3.0e0 END FROM orders"
    statements = [("plain", some), ("turned", f"{some} ORDER BY o_orderkey DESC"), ("less", f"{some} WHERE o_orderkey < (SELECT max(o_orderkey) FROM orders)"), ("other", some.replace("> 9", "> 10"))]
    got = {r.sample_id: r for r in X.run_sql(spark, statements, {"orders": orders}).collect()}
    assert got["plain"].n_rows == orders.count() > 200 and got["less"].n_rows == got["plain"].n_rows - 1
    assert got["plain"].rows_hash == got["turned"].rows_hash
    assert len({got[k].rows_hash for k in ("plain", "less", "other")}) == 3
