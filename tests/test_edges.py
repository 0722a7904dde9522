"""Nulls, empty texts, repeated rows, empty tables and marks in values, for the operators of the library proper; and values of queries that SQL cannot give."""

import csv
import io
import json
import math
import xml.etree.ElementTree as ElementTree

import pytest
from pyspark.sql import functions as F

from tablemill.operators import agent as A
from tablemill.operators import corpus as C
from tablemill.operators import encoder as E
from tablemill.operators import factory as X
from tablemill.operators import metrics as M
from tablemill.operators import tables as T
from tablemill.plans import catalogue

TEXT = "one two three four five six seven eight nine ten"
ROWS = [(1, TEXT), (2, TEXT), (2, TEXT), (3, None), (4, ""), (5, "   \n\t"), (6, "x" * 50_000), (7, TEXT + " and more words in a row " * 400)]


@pytest.fixture(scope="module", params=["edge", "none"])
def docs(request, spark):
    return spark.createDataFrame(ROWS if request.param == "edge" else [], "doc_id long, text string")


def ids(df):
    return {r.doc_id for r in df.select("doc_id").collect()}


@pytest.mark.parametrize("fn", [C.basic_tags, C.all_tags, C.decide, C.web_rules, C.near_groups], ids=lambda f: f.__name__)
def test_every_document_is_answered(docs, fn):
    assert ids(fn(docs)) == ids(docs)


@pytest.mark.parametrize("fn", [C.exact, C.repeated_lines, C.concat_cut, C.by_length, lambda d: C.decontaminate(d, d.withColumnRenamed("doc_id", "item_id")), lambda d: C.keyword_hits(d, ["one"]), A.chunks], ids=str)
def test_nothing_breaks(docs, fn):
    assert fn(docs).count() >= 0


@pytest.mark.parametrize("fn", [C.excess, C.excess_in_context], ids=lambda f: f.__name__)
def test_losses_of_awkward_texts(spark, docs, fn):
    labels = spark.createDataFrame([(1, 1, 0), (1, 1, 0), (9, 1, 0)], "doc_id long, quality int, toxic int")
    got = fn(docs, labels).collect()
    assert all(r.excess is not None and r.loss_cur > -1e-9 for r in got)


def test_near_groups_of_chains_and_strangers(spark):
    """A text, its variants, and variants that are alike only through it: one class; other texts stay alone."""
    words = [f"w{i}" for i in range(60)]
    change = lambda at: " ".join("z" if i == at else w for i, w in enumerate(words))
    rows = [(i, change(i)) for i in range(10, 50, 3)] + [(100, " ".join(words)), (200, " ".join(f"v{i}" for i in range(60)))]
    got = {r.doc_id: r.class_id for r in C.near_groups(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert {c for d, c in got.items() if d <= 100} == {10} and got[200] == 200


# --- marks in names and values -----------------------------------------------

MARKED = [("t", 0, 0, "a|b", 'he said "x", <b> & \\ end'), ("t", 0, 1, 'c"d', "p;q=r|s"), ("t", 1, 0, "a|b", None), ("t", 1, 1, 'c"d', "two words over the sixteen places of a column")]


@pytest.fixture(scope="module")
def marked(spark):
    return spark.createDataFrame(MARKED, "table_id string, row_id long, col_id int, col_name string, value string")


def test_forms_can_be_read_back(marked):
    text = {f: T.serialise(marked, f).first().text for f in T.FORMATS}
    want = [{'a|b': MARKED[0][4], 'c"d': MARKED[1][4]}, {'a|b': "", 'c"d': MARKED[3][4]}]
    assert json.loads(text["json"]) == want
    assert list(csv.DictReader(io.StringIO(text["csv"]))) == want
    rows = ElementTree.fromstring(text["xml"])
    assert [[c.text or "" for c in row] for row in rows] == [list(w.values()) for w in want]
    cells = ElementTree.fromstring(text["html"])
    assert [[c.text or "" for c in row] for row in cells] == [list(want[0]), *[list(w.values()) for w in want]]
    assert all(len([1 for a, b in zip(" " + line, line) if b == "|" and a != "\\"]) == 3 for line in text["markdown"].split("\n") if "---" not in line)
    assert MARKED[3][4] in text["text"]


def test_all_kinds_are_anonymised(spark):
    cells = spark.createDataFrame([("t", i, 0, "name", f"person {i}") for i in range(50)], "table_id string, row_id long, col_id int, col_name string, value string")
    out, mapping = T.anonymise(cells)
    assert out.where("value like 'person%'").count() == 0 and mapping.where("kind = 'value'").count() == 50
    assert T.anonymise(cells, max_kinds=20)[0].where("value like 'person%'").count() == 50


def test_plan_follows_the_grid(spark):
    plain = spark.createDataFrame([("t", 0, 0, 1, 1, "a", True), ("t", 1, 0, 1, 1, "1", False)], "table_id string, r int, c int, rowspan int, colspan int, value string, is_header boolean")
    assert [s["step"] for s in json.loads(T.plan_of(plain))] == ["flatten_headers"]
    merged = plain.withColumn("colspan", F.when(F.col("r") == 0, 2).otherwise(1))
    assert [s["step"] for s in json.loads(T.plan_of(merged))] == ["unmerge", "flatten_headers"]


# --- executors and tools ------------------------------------------------------


def test_outputs_are_whole(spark, tmp_path):
    rows = [("long", "print('y' * 100_000)"), ("flood", "while True: print('z' * 1_000_000)"), ("exit", "import sys; sys.exit(3)")]
    got = {r.sample_id: r for r in X.run_python(spark.createDataFrame(rows, "sample_id string, code string"), seconds=5, output_mb=4).collect()}
    assert got["long"].output == "y" * 100_000 + "\n" and got["long"].status == "ok"
    assert got["flood"].error_class == "output" and got["exit"].status == "error"


def test_whole_results_are_compared(spark):
    """Two results that differ in one of 5000 rows differ."""
    region = spark.read.parquet("/root/testdata/sf0.001/region.parquet")
    one = "SELECT id FROM range(5000)"
    got = {r.sample_id: (r.n_rows, r.rows_hash) for r in X.run_sql(spark, [("a", one), ("b", one + " ORDER BY id DESC"), ("c", one.replace("id FROM", "CASE WHEN id = 4999 THEN 0 ELSE id END AS id FROM"))], {"region": region}).collect()}
    assert got["a"] == got["b"] and got["a"][0] == 5000 and got["a"] != got["c"]


def test_join_paths():
    assert [t for t, _ in A.join_path(["lineitem", "nation"])] in (["lineitem", "orders", "customer", "nation"], ["lineitem", "supplier", "nation"])
    assert "JOIN orders ON l_orderkey = o_orderkey" in A.compose("What is the total revenue per orderpriority?", ["lineitem", "orders"], A.TERMS)
    assert A.compose("How many rows?", ["part"], {}) == "SELECT count(*) AS answer FROM part"


def test_lcs_against_a_table(spark):
    import random

    random.seed(5)
    pairs = [([random.choice("abcd") for _ in range(random.randint(0, 30))], [random.choice("abcd") for _ in range(random.randint(0, 30))]) for _ in range(60)] + [(None, ["a"])]

    def plain(x, y):
        row = [0] * (len(y or []) + 1)
        for a in x or []:
            before = list(row)
            for j, b in enumerate(y or []):
                row[j + 1] = before[j] + 1 if a == b else max(before[j + 1], row[j])
        return row[-1]

    df = spark.createDataFrame([(i, a, b) for i, (a, b) in enumerate(pairs)], "i int, a array<string>, b array<string>")
    got = {r.i: r.n for r in df.select("i", M.lcs(F.col("a"), F.col("b")).alias("n")).collect()}
    assert got == {i: plain(a, b) for i, (a, b) in enumerate(pairs)}


# --- what the experiments must show -------------------------------------------


def rows_of(spark, name, sf="0.001"):
    return catalogue.QUERIES[name](spark, f"/root/testdata/sf{sf}").collect()


def test_normalising_and_asking_back_win(spark):
    for name, worse, better in (("w22", "raw", "normalised"), ("w23", "guessed", "asked_back")):
        total = {r.way: r.total for r in rows_of(spark, name)}
        assert total[better] == 100 > total[worse], name


def test_values_beat_schema_without_names(spark):
    f1 = {r.way: r.f1 for r in rows_of(spark, "x03_schema_or_values")}
    assert f1["values"] > f1["schema"]
    names = {r.headers: r.f1 for r in rows_of(spark, "x09_headers")}
    assert names["original"] > names["anonymised"] == f1["schema"]


def test_knowledge_helps(spark):
    acc = {r.knowledge: r.exec_acc for r in rows_of(spark, "w14")}
    assert acc[True] > acc[False]
    assert {r.exec_acc for n in ("w15", "w16") for r in rows_of(spark, n)} == {1.0}


def test_corpus_chain_only_shrinks(spark):
    got = sorted(rows_of(spark, "w27", "0.01"), key=lambda r: r.step)
    docs, tokens = [r.docs for r in got[:6]], [r.tokens for r in got[:6]]
    assert docs == sorted(docs, reverse=True) and tokens == sorted(tokens, reverse=True) and docs[2] < docs[1] < docs[0] and tokens[3] < tokens[2]
    stage = {r.stage: r for r in got}
    assert 0 < stage["selected"].tokens < stage["neutral"].tokens
    assert stage["packed"].tokens == stage["mixed"].tokens > 0


def test_fitting_lowers_the_loss(spark):
    loss = {(r.way, r.stage): r.loss for r in rows_of(spark, "enc_table_method")}
    assert all(loss[w, "after"] < loss[w, "before"] for w in ("adapter", "mean"))


def test_table_method_against_numpy(spark):
    """Snapshots through attention, adapter and loss in Spark against the same in arrays."""
    import numpy as np

    from tablemill.plans import encoder as P
    from tablemill.plans.registry import Tables

    t = Tables(spark, "/root/testdata/sf0.001")
    cells = E.embed(P.snapshot_cells(t, 16)).toPandas()
    w, vecs = E.adapter_weights(E.D), {}
    for (table, snap), part in cells.groupby(["table_id", "snap"]):
        grid, _, cols = E.grid_of(part)
        out = E.encode_grid(grid)
        for j, c in enumerate(cols):
            top, total, acc = E.adapter_state(out[:, j], w)
            vecs[table, snap, c] = ((acc / total[:, None]) @ w["out"]).mean(0)
    got = {(r.table_id, r.snap, r.col_id): np.array(r.vec) for r in P.encoded_columns(t).collect()}
    assert got.keys() == vecs.keys() and all(np.allclose(got[k], vecs[k], atol=1e-6) for k in vecs)


def test_vectors_of_values_are_not_broadcast(spark):
    """However small the values are, their vectors do not pass the driver."""
    cells = spark.sql("SELECT * FROM VALUES ('a', 1L, 0, 'c', 'x'), ('a', 2L, 0, 'c', NULL) AS t(table_id, row_id, col_id, col_name, value)")
    out = E.embed(cells)
    assert "Broadcast" not in out._jdf.queryExecution().executedPlan().toString()
    assert {r.row_id: any(r.vec) for r in out.collect()} == {1: True, 2: False}


def test_counted_cells_have_the_same_profile(spark):
    """Equal cells counted together give the profile and, apart from their number, the anonymised cells of all cells."""
    rows = [("a", r, c, f"h{c}", v) for r in range(40) for c, v in enumerate([str(r % 3), None if r % 4 == 0 else "x" + str(r % 5), "n/a" if r % 2 else "2024-01-01", str(r / 4)])]
    cells = spark.createDataFrame(rows, "table_id string, row_id long, col_id int, col_name string, value string")
    few = T.counted(cells)
    assert few.count() == 3 + 5 + 1 + 2 + 40 and few.agg(F.sum("n")).first()[0] == len(rows)
    assert sorted(T.profile(few).collect()) == sorted(T.profile(cells).collect())
    got = {r.col_name: (r.n, r.n_missing, r.n_distinct, r.dtype, r.is_key) for r in T.profile(cells).collect()}
    assert got == {"h0": (40, 0, 3, "long", False), "h1": (40, 10, 5, "string", False), "h2": (40, 20, 2, "timestamp", False), "h3": (40, 0, 40, "double", True)}
    names = ["table_id", "col_name", "value"]
    assert sorted(T.anonymise(few)[0].select(*names).collect(), key=str) == sorted(T.anonymise(cells)[0].select(*names).distinct().collect(), key=str)


def test_losses_are_equal_to_the_last_bit(spark):
    """The order of tokens by excess hangs on the last bit, so logarithms are the C library's."""
    counts = spark.range(1, 3001).select(F.concat(F.lit("t"), "id").alias("token"), F.col("id").alias("n"))
    got = {r.token: (r.loss_cur, r.loss_ref) for r in C.losses(counts, counts.where("n % 2 = 0")).collect()}
    c, r, v = 3000 * 3001 / 2, 1500 * 1501, 3000
    assert got == {f"t{n}": (-math.log((n + 1) / (c + v)), -math.log(((n if n % 2 == 0 else 0) + 1) / (r + v))) for n in range(1, 3001)}


def test_schema_items_hold_values_of_the_tables(spark, small):
    """What is searched is read from the tables, so a question in words of a value finds its column."""
    docs = A.value_docs(spark, lambda name: spark.read.parquet(f"{small}/{name}.parquet"))
    text = {r.item_id: r.text for r in docs.collect()}
    kinds = sorted(r[0] for r in spark.read.parquet(f"{small}/customer.parquet").select("c_mktsegment").distinct().collect())
    keys = spark.read.parquet(f"{small}/orders.parquet").agg(F.min("o_orderkey"), F.max("o_orderkey")).first()
    assert text["customer.c_mktsegment"].endswith(" ".join(kinds)) and text["orders.o_orderkey"].endswith(f"{keys[0]} to {keys[1]}")
    assert set(text) == {r.item_id for r in A.schema_docs(spark).collect()}
    found = A.embed_search(spark.createDataFrame([("q", f"customers of {kinds[0]}")], "query_id string, query string"), docs)
    assert "customer.c_mktsegment" in {r.item_id for r in found.collect()}


def test_systems_are_measured_on_rows(spark):
    rows = spark.createDataFrame([("a", True, True), ("a", False, True), (None, True, False), ("b", True, None)], "k string, said boolean, gold boolean")
    got = {tuple(r) for r in M.measured(rows, {"s": F.col("said"), "yes": F.lit(True)}, F.col("gold"), {1: F.col("k")}).collect()}
    assert got == {(1, "a", "s", 50.0), (1, "a", "yes", 100.0), (1, "none", "s", 0.0), (1, "none", "yes", 0.0)}


def test_each_pack_has_a_step(spark):
    docs = spark.createDataFrame([(1, "a b c"), (2, None), (3, "d e f g")], "doc_id long, text string")
    got = C.cosine_schedule(C.concat_cut(docs, 2)).orderBy("step").collect()
    assert [(r.step, r.tokens) for r in got] == [(0, 2), (1, 2), (2, 2), (3, 1)] and got[0].lr == 3e-5 and got[1].lr == 3e-5 > got[2].lr > got[3].lr > 0
