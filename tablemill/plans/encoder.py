"""Queries of the table encoder."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from tablemill.functions import det
from tablemill.operators import encoder as E
from tablemill.operators import tables as T
from tablemill.plans.registry import query
from tablemill.plans.tables import SMALL_SQL, small_cells

HASH_SQL = """g AS (SELECT value, md5(substr(p, i::BIGINT, 3)) AS h FROM (SELECT value, '^' || value || '$' AS p, unnest(range(1, greatest(length(value), 1) + 1)) AS i FROM vals)),
b AS (SELECT value, (('0x' || substr(h, 1, 8))::BIGINT % 64)::INT AS dim, CASE WHEN ('0x' || substr(h, 9, 1))::INT % 2 = 0 THEN 1.0 ELSE -1.0 END AS s FROM g),
s AS (SELECT value, dim, sum(s)::DOUBLE AS x FROM b GROUP BY 1, 2), nn AS (SELECT value, sqrt(sum(x * x)) AS n FROM s GROUP BY 1),
v AS (SELECT value, dim, x / n AS x FROM s JOIN nn USING (value) WHERE n > 0 AND x <> 0)"""


@query("enc_cell_vectors", f"WITH vals AS (SELECT DISTINCT p_name AS value FROM part), {HASH_SQL} SELECT value, dim, round(x, 6) AS x FROM v")
def enc_cell_vectors(t):
    v = t.part.select(F.col("p_name").alias("value")).distinct().select("value", F.posexplode(E.hashed(F.col("value"))).alias("dim", "x"))
    return v.where("x <> 0").select("value", "dim", F.round("x", 6).alias("x"))


SNAP_SQL = f"""r AS (SELECT c_nationkey::VARCHAR AS table_id, c_custkey AS row_id, c_name, c_acctbal, c_mktsegment, row_number() OVER (PARTITION BY c_nationkey ORDER BY {det.sql_text("'snap'", 'c_custkey')}, c_custkey) AS r, count(*) OVER (PARTITION BY c_nationkey) AS m FROM customer),
snaps AS (SELECT *, (r > least(32, m // 2))::INT AS snap FROM r WHERE r <= 2 * least(32, m // 2))"""


def customer_snapshots(t, rows=32):
    c = t.customer.select(F.col("c_nationkey").cast("string").alias("table_id"), F.col("c_custkey").alias("row_id"), "c_name", "c_acctbal", "c_mktsegment")
    return E.snapshots(c, "table_id", "row_id", rows)


def snapshot_cells(t, rows=32):
    s = customer_snapshots(t, rows)
    cells = F.array(*[F.struct(F.lit(i).alias("col_id"), F.lit(n).alias("col_name"), F.col(n).cast("string").alias("value")) for i, n in enumerate(["c_name", "c_acctbal", "c_mktsegment"])])
    return s.select("table_id", "snap", "row_id", F.inline(cells))


@query("enc_snapshots", f"WITH {SNAP_SQL} SELECT table_id, row_id, snap FROM snaps")
def enc_snapshots(t):
    return customer_snapshots(t).select("table_id", "row_id", "snap")


POOL_SQL = SMALL_SQL + f""", vals AS (SELECT DISTINCT value FROM cells), {HASH_SQL}, n AS (SELECT table_id, col_id, count(*) AS n FROM cells GROUP BY 1, 2)
SELECT table_id, col_id, dim, round(sum(x) / any_value(n.n), 6) AS x FROM cells JOIN v USING (value) JOIN n USING (table_id, col_id) GROUP BY 1, 2, 3 HAVING abs(sum(x)) > 1e-9"""


@query("enc_pool_mean", POOL_SQL)
def enc_pool_mean(t):
    p = E.pool(E.embed(small_cells(t)), "mean")
    return p.select("table_id", "col_id", F.posexplode("vec").alias("dim", "x")).where("abs(x) > 1e-9").select("table_id", "col_id", "dim", F.round("x", 6).alias("x"))


@query("enc_attention")
def enc_attention(t):
    """Encoded cells of customer snapshots: one row a cell with the first entries of its vector."""
    out = E.encode(E.embed(snapshot_cells(t, 16)), layers=1)
    return out.select("table_id", "snap", "row_id", "col_id", F.round(F.col("vec")[0], 4).alias("x0"), F.round(F.col("vec")[1], 4).alias("x1"))


@query("enc_adapter")
def enc_adapter(t):
    """Column vectors of all customer columns; rows are merged as softmax states, none is sampled."""
    cells = E.embed(T.melt(t.customer, "customer", "c_custkey"))
    out = E.adapter_columns(cells)
    return out.select("table_id", "col_id", F.size("vecs").alias("k"), F.round(F.col("vecs")[0][0], 4).alias("x00"), F.round(F.col("vecs")[3][63], 4).alias("x363"))


LOSS_SQL = f"""
WITH h AS (SELECT label AS col_id, ({det.sql_unit("'snap'", "vec_id")} < 0.5)::INT AS snap, embedding FROM embeddings),
u AS (SELECT col_id, snap, unnest(range(64)) AS d, unnest(list_transform(embedding, lambda x: x::DOUBLE)) AS x FROM h),
p AS (SELECT col_id, snap, d, avg(x) AS x FROM u GROUP BY 1, 2, 3),
s AS (SELECT a.col_id, a.snap, b.col_id AS other, b.snap AS osnap, sum(a.x * b.x) / 0.07 AS s, a.col_id = b.col_id AS pos FROM p a JOIN p b ON a.d = b.d AND NOT (a.col_id = b.col_id AND a.snap = b.snap) GROUP BY 1, 2, 3, 4),
m AS (SELECT col_id, snap, max(s) AS top FROM s GROUP BY 1, 2)
SELECT col_id, snap, round(any_value(top) + ln(sum(exp(s - top))) - max(s) FILTER (WHERE pos), 4) AS loss FROM s JOIN m USING (col_id, snap) GROUP BY 1, 2"""


@query("enc_contrastive_loss", LOSS_SQL)
def enc_contrastive_loss(t):
    """Ten labels stand for ten columns; each one's vectors are dealt to two snapshots by hash and pooled."""
    cells = t.embeddings.select(F.when(det.unit("snap", F.col("vec_id")) < 0.5, "1").otherwise("0").alias("table_id"), F.col("label").alias("col_id"), F.transform("embedding", lambda x: x.cast("double")).alias("vec"))
    p = E.pool(cells).select(F.lit("t").alias("table_id"), "col_id", F.col("table_id").cast("int").alias("snap"), "vec", F.lit(0).alias("batch"))
    return E.contrast_loss(p).select("col_id", "snap", F.round("loss", 4).alias("loss"))


@query("enc_pool_max", POOL_SQL.replace("sum(x) / any_value(n.n)", "CASE WHEN count(*) < any_value(n.n) THEN greatest(max(x), 0) ELSE max(x) END").replace("HAVING abs(sum(x)) > 1e-9", "HAVING abs(CASE WHEN count(*) < any_value(n.n) THEN greatest(max(x), 0) ELSE max(x) END) > 1e-9"))
def enc_pool_max(t):
    p = E.pool(E.embed(small_cells(t)), "max")
    return p.select("table_id", "col_id", F.posexplode("vec").alias("dim", "x")).where("abs(x) > 1e-9").select("table_id", "col_id", "dim", F.round("x", 6).alias("x"))


def encoded_columns(t, rows=16, axes="both"):
    """(table_id, snap, col_id, vec): snapshots through attention and adapter; the mean of a column's k vectors."""
    out = E.encode(E.embed(snapshot_cells(t, rows)), axes=axes).withColumn("table_id", F.concat_ws("#", "table_id", F.col("snap").cast("string")))
    cols = E.adapter_columns(out)
    mean = F.transform(F.sequence(F.lit(0), F.lit(E.D - 1)), lambda i: F.aggregate(F.col("vecs"), F.lit(0.0), lambda a, v: a + F.get(v, i)) / F.size("vecs"))
    return cols.select(F.split("table_id", "#")[0].alias("table_id"), F.split("table_id", "#")[1].cast("int").alias("snap"), "col_id", mean.alias("vec"))


@query("enc_table_method")
def enc_table_method(t):
    """Cells, attention over both axes, adapter, contrastive loss, head: mean loss of customer columns before and after fitting, beside mean pooling."""
    from tablemill.functions.lineage import cut

    pooled = E.pool(E.embed(snapshot_cells(t, 16)).withColumn("table_id", F.concat_ws("#", "table_id", F.col("snap").cast("string"))))
    pooled = pooled.select(F.split("table_id", "#")[0].alias("table_id"), F.split("table_id", "#")[1].cast("int").alias("snap"), "col_id", "vec")
    out = []
    for way, vecs in (("adapter", encoded_columns(t)), ("mean", pooled)):
        _, history = E.fit_head(cut(E.batches(vecs, 256)), steps=8)
        out += [(way, "before", round(history[0], 4)), (way, "after", round(history[-1], 4))]
    return t.spark.createDataFrame(out, "way string, stage string, loss double")


@query("enc_splice", SMALL_SQL + "SELECT table_id, 2 * count(DISTINCT col_id)::BIGINT + 3 AS parts, count(DISTINCT col_id)::BIGINT AS vectors FROM cells GROUP BY 1")
def enc_splice(t):
    """Prompts of whole tables with their column vectors in the slots: parts and vectors of each."""
    cells = small_cells(t)
    vecs = E.adapter_columns(E.embed(cells))
    return E.splice(E.hybrid_prompt(cells, T.profile(cells)), vecs).select("table_id", F.size("parts").cast("long").alias("parts"), F.size(F.filter("parts", lambda p: p["kind"] == "vec")).cast("long").alias("vectors"))


@query("enc_train_plans", "SELECT * FROM (VALUES ('encoder_only', 'encoder', TRUE, 'table'), ('encoder_only', 'adapter', TRUE, 'table'), ('encoder_only', 'decoder', FALSE, 'table'), ('decoder_only', 'encoder', FALSE, 'text'), ('decoder_only', 'adapter', FALSE, 'text'), ('decoder_only', 'decoder', TRUE, 'text'), ('joint', 'encoder', TRUE, 'table'), ('joint', 'adapter', TRUE, 'table'), ('joint', 'decoder', TRUE, 'table')) v(plan, part, trained, route)")
def enc_train_plans(t):
    return E.train_plans(t.spark)


@query("enc_head_fit")
def enc_head_fit(t):
    """The contrastive loss at every second step of fitting a linear head on pooled customer columns."""
    pooled = E.embed(snapshot_cells(t)).withColumn("table_id", F.concat_ws("#", "table_id", F.col("snap").cast("string")))
    vecs = E.pool(pooled).select(F.split("table_id", "#")[0].alias("table_id"), F.split("table_id", "#")[1].cast("int").alias("snap"), "col_id", "vec")
    _, history = E.fit_head(E.batches(vecs, 256), steps=6)
    return t.spark.createDataFrame([(i, round(x, 4)) for i, x in enumerate(history) if i % 2 == 0], "step int, loss double")


PROFILE_SQL = """prof AS (SELECT table_id, col_id, col_name, CASE WHEN regexp_matches(any_value(value), '^[0-9]+$') THEN 'long' ELSE 'string' END AS dtype, count(DISTINCT value) = count(*) AS is_key FROM cells GROUP BY 1, 2, 3)"""


@query("enc_hybrid_prompt", SMALL_SQL + f""", {PROFILE_SQL}, r AS (SELECT *, row_number() OVER (PARTITION BY table_id, col_id ORDER BY md5(value), value) AS r FROM (SELECT DISTINCT table_id, col_id, value FROM cells)),
v AS (SELECT table_id, col_id, string_agg(value, ', ' ORDER BY r) AS vals FROM r WHERE r <= 3 GROUP BY 1, 2)
SELECT table_id, 'table ' || table_id || ', columns=[' || string_agg(table_id || '.' || col_name || '(<vec>|' || dtype || '|' || CASE WHEN is_key THEN 'key' ELSE '' END || ')|[' || vals || ']', ', ' ORDER BY col_id) || ']' AS prompt FROM prof JOIN v USING (table_id, col_id) GROUP BY 1""")
def enc_hybrid_prompt(t):
    cells = small_cells(t)
    return E.hybrid_prompt(cells, T.profile(cells))


def _drawn(task, col="col_id"):
    return det.sql_unit("'align'", f"'{task}'", "table_id", "row_id", col) + " < 0.3"


def _instruction(task, col="col_id", row="row_id"):
    return f"(['{E.INSTRUCTIONS[task][0]}', '{E.INSTRUCTIONS[task][1]}'])[{det.sql_pick(2, chr(39) + 'instruction' + chr(39), chr(39) + task + chr(39), 'table_id', row, col)} + 1]"


ALIGN_SQL = {
    "column_prediction": f"SELECT 'column_prediction/' || table_id || '/' || row_id || '/' || col_id AS sample_id, {_instruction('column_prediction')} AS instruction, value AS input, col_name AS output FROM cells WHERE {_drawn('column_prediction')}",
    "cell_prediction": f"SELECT 'cell_prediction/' || table_id || '/' || row_id || '/' || col_id AS sample_id, {_instruction('cell_prediction')} AS instruction, col_name AS input, value AS output FROM cells WHERE {_drawn('cell_prediction')}",
    "question_generation": f"SELECT 'question_generation/' || c.table_id || '/' || c.row_id || '/' || c.col_id AS sample_id, {_instruction('question_generation').replace('table_id', 'c.table_id').replace('row_id', 'c.row_id').replace('col_id', 'c.col_id')} AS instruction, c.value AS input, 'What is the ' || c.col_name || ' of ' || c.table_id || ' ' || k.value || '?' AS output FROM cells c JOIN cells k ON c.table_id = k.table_id AND c.row_id = k.row_id AND k.col_id = 0 WHERE c.col_id > 0 AND {_drawn('question_generation').replace('table_id', 'c.table_id').replace('row_id', 'c.row_id').replace('col_id', 'c.col_id')}",
    "titling": f"SELECT 'titling/' || table_id || '/0/-1' AS sample_id, {_instruction('titling', '-1', '0')} AS instruction, col_name AS input, table_id || ' by ' || col_name AS output FROM (SELECT DISTINCT table_id, col_name FROM cells WHERE col_id = 0)",
    "row_summary": f"SELECT 'row_summary/' || table_id || '/' || row_id || '/-1' AS sample_id, {_instruction('row_summary', '-1')} AS instruction, table_id || ' row ' || row_id AS input, string_agg(col_name || ' is ' || value, ', ' ORDER BY col_id) AS output FROM cells WHERE {_drawn('row_summary', '-1')} GROUP BY table_id, row_id",
}
for _task, _name in (("column_prediction", "enc_column_prediction"), ("cell_prediction", "enc_cell_prediction"), ("question_generation", "enc_question_gen"), ("titling", "enc_titles"), ("row_summary", "enc_row_summary")):

    @query(_name, SMALL_SQL + ALIGN_SQL[_task])
    def enc_align(t, task=_task):
        return E.alignment(small_cells(t), task, 0.3)


@query("enc_nearest_columns", """
WITH c AS (SELECT label AS id, unnest(range(64)) AS d, unnest(list_transform(embedding, lambda x: x::DOUBLE)) AS x FROM embeddings), m AS (SELECT id, d, avg(x) AS x FROM c GROUP BY 1, 2),
s AS (SELECT a.id AS q, b.id AS vec_id, sum(a.x * b.x) AS s FROM m a JOIN m b ON a.d = b.d AND a.id <> b.id GROUP BY 1, 2)
SELECT q, vec_id, round(s, 4) AS score, rk FROM (SELECT *, row_number() OVER (PARTITION BY q ORDER BY round(s, 6) DESC, vec_id) AS rk FROM s) WHERE rk <= 3""")
def enc_nearest_columns(t):
    """Mean vectors of the ten labels as column vectors; the three nearest of each."""
    cells = t.embeddings.select(F.lit("e").alias("table_id"), F.col("label").alias("col_id"), F.transform("embedding", lambda x: x.cast("double")).alias("vec"))
    cols = E.pool(cells).select(F.col("col_id").cast("long").alias("vec_id"), F.col("vec").alias("embedding"))
    out = E.nearest(cols.select(F.col("vec_id").alias("q"), F.col("embedding").alias("query")), cols, 3)
    return out.select(F.col("q").cast("int").alias("q"), F.col("vec_id").cast("int").alias("vec_id"), F.round("score", 4).alias("score"), "rk")


@query("enc_token_cost", SMALL_SQL + r"SELECT table_id, sum(len(regexp_split_to_array(trim(value), '\s+')))::BIGINT AS text_tokens, count(DISTINCT col_id)::BIGINT * 4 AS vector_tokens FROM cells GROUP BY 1")
def enc_token_cost(t):
    return E.token_cost(small_cells(t))


@query("vec_knn_label", """
WITH s AS (SELECT a.vec_id, a.label, b.label AS pred, row_number() OVER (PARTITION BY a.vec_id ORDER BY round(list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda z: z[1]::DOUBLE * z[2]::DOUBLE)), 6) DESC, b.vec_id) AS rk
 FROM embeddings a JOIN embeddings b ON a.vec_id % 20 = 0 AND a.vec_id <> b.vec_id)
SELECT count(*)::BIGINT AS total, sum((label = pred)::INT)::BIGINT AS correct FROM s WHERE rk = 1""")
def vec_knn_label(t):
    """Column type by the nearest labelled vector, for every twentieth vector."""
    e = t.embeddings
    best = E.nearest(e.where("vec_id % 20 = 0").select(F.col("vec_id").alias("q"), F.col("embedding").alias("query")), e, 1)
    both = best.join(e.select(F.col("vec_id").alias("q"), F.col("label").alias("gold")), "q").join(e.select("vec_id", F.col("label").alias("pred")), "vec_id")
    return both.agg(F.count("*").alias("total"), F.sum((F.col("gold") == F.col("pred")).cast("int")).alias("correct"))


@query("enc_route", SMALL_SQL + ", s AS (SELECT DISTINCT table_id AS id, 1 AS n FROM cells UNION ALL SELECT doc_id::VARCHAR, 0 FROM documents) SELECT CASE WHEN n > 0 THEN 'table' ELSE 'text' END AS route, count(*)::BIGINT AS samples FROM s GROUP BY 1")
def enc_route(t):
    tables = small_cells(t).select("table_id").distinct().select(F.array("table_id").alias("table_ids"))
    texts = t.documents.select(F.expr("cast(array() as array<string>)").alias("table_ids"))
    return E.route(tables.unionByName(texts)).groupBy("route").agg(F.count("*").alias("samples"))
