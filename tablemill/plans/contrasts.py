"""Each baseline beside the method it is held against."""

from __future__ import annotations

from pyspark.sql import functions as F

from tablemill.functions.lineage import cut
from tablemill.operators import corpus as C
from tablemill.operators import encoder as E
from tablemill.operators import factory as X
from tablemill.operators import metrics as M
from tablemill.operators import tables as T
from tablemill.plans import encoder as encoder_plans
from tablemill.plans import workloads
from tablemill.plans.corpus import LM_SQL, MASKS
from tablemill.plans.encoder import SNAP_SQL
from tablemill.plans.factory import CHAIN_SQL
from tablemill.plans.registry import query


@query("x01_text_or_vectors", "SELECT size, 5 * count(*)::BIGINT AS least_words, 5 * 4 AS vectors FROM customer, (VALUES (10), (100), (1000)) v(size) WHERE c_custkey < size GROUP BY size")
def x01(t):
    """Words of a five-column table grow with its rows; its vectors do not."""
    out = None
    for size in (10, 100, 1000):
        c = E.token_cost(T.melt(t.customer.where(F.col("c_custkey") < size), "customer", "c_custkey"))
        row = c.select(F.lit(size).alias("size"), F.col("text_tokens").alias("least_words"), F.col("vector_tokens").cast("int").alias("vectors"))
        out = row if out is None else out.unionByName(row)
    return out


@query("x02_head_or_sample")
def x02(t):
    """Priorities seen in the first rows of each month against a drawn sample of as many."""
    from pyspark.sql import Window

    o = t.orders.withColumn("m", F.date_format("o_orderdate", "yyyy-MM"))
    from tablemill.functions import det

    seen = lambda name, order: o.withColumn("r", F.row_number().over(Window.partitionBy("m").orderBy(*order))).where("r <= 8").groupBy("m").agg(F.countDistinct("o_orderpriority").alias("k")).agg(F.lit(name).alias("way"), F.round(F.avg("k"), 4).alias("seen"))
    return seen("first_rows", ["o_orderdate", "o_orderkey"]).unionByName(seen("sample", [det.text("x2", F.col("o_orderkey"))]))


def by_schema(shown):
    """Rule predictor that sees a column's name and one of its values."""
    name, value = F.lower("col_name"), F.lower(F.coalesce("shown", F.lit("")))
    label = F.when(name.rlike("key$"), "key").when(name.rlike("date"), "date").when(name.rlike("price|bal"), "money").when(name.rlike("size|quantity"), "quantity").when(name.rlike("_name$") & ~name.rlike("^p_"), "name").when(name.rlike("segment|brand|type|status|priority"), "category")
    label = label.when(value.rlike(r"^[0-9]{4}-[0-9]{2}"), "date").when(value.rlike(r"^-?[0-9]+\.[0-9]+"), "money").when(value.rlike("^-?[0-9]+"), "quantity").otherwise("text")
    return shown.withColumn("label", label)


def header_scores(t, headers=("original", "anonymised"), ways=("schema", "values")):
    """(headers, way, f1): column types by schema and the first value, and by a profile of all values, under real and anonymised names.

    Equal cells are counted together before anything else; all that follows depends on distinct values, their counts and first rows.
    """
    cells = cut(T.counted(workloads.star_cells(t)))
    renamed, mapping = T.anonymise(cells)
    gold = t.spark.createDataFrame([(n, c, s) for n in workloads.STARS for c, s in X.SEMANTIC[n].items()], "table_id string, col_name string, label string")
    heads = mapping.where("kind = 'header'").select("table_id", F.col("old").alias("col_name"), "new")
    sides = {"original": lambda: (cells, gold), "anonymised": lambda: (cut(renamed), gold.join(heads, ["table_id", "col_name"]).select("table_id", F.col("new").alias("col_name"), "label"))}
    out = []
    for header in headers:
        some, truth = sides[header]()
        found = {"schema": lambda: by_schema(some.groupBy("table_id", "col_name").agg(F.min_by("value", "row_id").alias("shown"))), "values": lambda: workloads.guess_type(T.profile(some))}
        keyed = lambda df: cut(df.select(F.concat_ws(".", "table_id", "col_name").alias("sample_id"), "label"))
        truth = keyed(truth)
        for way in ways:
            out.append(M.micro_f1(keyed(found[way]()), truth).select(F.lit(header).alias("headers"), F.lit(way).alias("way"), "*"))
    return C.union_all(out)


@query("x03_schema_or_values")
def x03(t):
    """Under anonymised headers the profile of values beats the schema with a few of them."""
    return header_scores(t, headers=("anonymised",))


@query("x09_headers")
def x09(t):
    """Original against anonymised headers, for the predictor that reads names."""
    return header_scores(t, ways=("schema",))


@query("x11_single_turn", CHAIN_SQL + ", k AS (SELECT chain_id, min(turn) FILTER (WHERE failed) AS cut FROM ch GROUP BY 1) SELECT 'single' AS way, turn, (count(*) FILTER (WHERE NOT failed AND NOT contains(query, 'their')))::BIGINT AS answered FROM ch GROUP BY 2 UNION ALL SELECT 'chained', turn, (count(*) FILTER (WHERE cut IS NULL OR turn < cut))::BIGINT FROM ch JOIN k USING (chain_id) GROUP BY 2")
def x11(t):
    """Questions answered on their own and with the turns before: 'their' points to the filter of the first turn."""
    turns = cut(X.chains(t.orders, t.lineitem))
    alone = turns.groupBy(F.lit("single").alias("way"), "turn").agg(F.count_if(~F.col("failed") & ~F.col("query").contains("their")).alias("answered"))
    held = X.truncate(turns).groupBy("turn").agg(F.count("*").alias("answered"))
    chained = turns.select("turn").distinct().join(held, "turn", "left").select(F.lit("chained").alias("way"), "turn", F.coalesce("answered", F.lit(0)).alias("answered"))
    return alone.unionByName(chained)


X15_SQL = f"""WITH {SNAP_SQL}, m AS (SELECT table_id, snap, count(*) AS m FROM snaps GROUP BY ALL)
SELECT way, CASE way WHEN 'rows' THEN sum(3) WHEN 'columns' THEN sum(m) ELSE sum(3 * m) END::BIGINT AS changed, sum(3 * m)::BIGINT AS cells FROM m, (VALUES ('rows'), ('columns'), ('both')) v(way) GROUP BY way""".replace("least(32", "least(8")


@query("x15_single_axis", X15_SQL)
def x15(t):
    """Cells whose vectors change when the first cell of each snapshot is emptied: along one axis only its row or its column, along both all."""
    cells = cut(E.embed(encoder_plans.snapshot_cells(t, 8)))
    first = cells.groupBy("table_id", "snap").agg(F.min("row_id").alias("row_id")).withColumn("col_id", F.lit(0))
    spot = F.col("hit").isNotNull()
    other = cut(cells.join(first.withColumn("hit", F.lit(1)), ["table_id", "snap", "row_id", "col_id"], "left").withColumn("vec", F.when(spot, F.array_repeat(F.lit(0.0), E.D)).otherwise(F.col("vec"))).drop("hit"))
    out = []
    for axes in ("rows", "columns", "both"):
        key = ["table_id", "snap", "row_id", "col_id"]
        a, b = E.encode(cells, 1, axes=axes), E.encode(other, 1, axes=axes).withColumnRenamed("vec", "new")
        far = F.exists(F.zip_with("vec", "new", lambda x, y: F.abs(x - y)), lambda d: d > 1e-9)
        out.append(a.join(b, key).agg(F.lit(axes).alias("way"), F.count_if(far).alias("changed"), F.count("*").alias("cells")))
    return C.union_all(out)


@query("x04_token_choice", " UNION ALL ".join(f"SELECT * FROM (WITH {LM_SQL}, y AS (SELECT *, {MASKS[m]} AS keep FROM x WINDOW d AS (PARTITION BY doc_id)) SELECT '{m}' AS mode, sum(n) FILTER (WHERE keep)::BIGINT AS kept, round(sum(n * excess) FILTER (WHERE keep) / sum(n) FILTER (WHERE keep), 6) AS mean_excess FROM y)" for m in MASKS))
def x04(t):
    """Mean excess loss of the kept tokens: chosen, at random, or all."""
    scored = cut(C.excess(t.documents, t.labels))
    kept = F.when(F.col("keep"), F.col("n"))
    return C.union_all([C.masked(scored, mode=m).agg(F.lit(m).alias("mode"), F.sum(kept).alias("kept"), F.round(F.sum(kept * F.col("excess")) / F.sum(kept), 6).alias("mean_excess")) for m in MASKS])


@query("x08_real_or_vague_names")
def x08(t):
    """Key errors of a predictor that copies names from the question: with real field names and with vague ones."""
    d = X.questions(t.spark).where("table_id = 'part' and class = 'computation'").orderBy("sample_id").collect()
    vague = {r.sample_id: r.query for r in X.questions(t.spark).where("table_id = 'part'").select("sample_id", X.blur_names(F.col("query"), F.col("table_id"), F.col("col")).alias("query")).collect()}

    def copied(question, col):
        return f"SELECT sum({col if col in question else col.split('_', 1)[1]}) FROM part"

    out = None
    for name, texts in (("real", {r.sample_id: r.query for r in d}), ("vague", vague)):
        runs = X.run_sql(t.spark, [(r.sample_id, copied(texts[r.sample_id], r.col)) for r in d], {"part": t.part})
        row = runs.agg(F.lit(name).alias("names"), F.count("*").alias("n"), F.round(F.avg((F.col("error_class") == "field_mismatch").cast("int")), 6).alias("key_error_rate"))
        out = row if out is None else out.unionByName(row)
    return out


@query("x12_prompt_shapes", f"SELECT 'one' AS way, 1::BIGINT AS shapes UNION ALL SELECT 'many', {len(X.PROMPTS)}")
def x12(t):
    """Distinct prompt openings with one template and with all."""
    q = X.questions(t.spark)
    opening = lambda p: F.regexp_replace(F.replace(F.replace(p, F.col("table_id"), F.lit("T")), F.col("query"), F.lit("Q")), "x^", "")
    def shapes(name, templates):
        p = X.prompts(q, templates).join(q.select("sample_id", "table_id", "query"), "sample_id")
        return p.agg(F.lit(name).alias("way"), F.countDistinct(opening(F.replace("prompt", F.col("query"), F.lit("Q")))).alias("shapes"))

    return shapes("one", X.PROMPTS[:1]).unionByName(shapes("many", None))


@query("x16_pool_or_adapter")
def x16(t):
    """Distance between the vectors of two columns of a table by mean pooling and by the adapter (unit length each), over all tables."""
    cells = cut(E.embed(encoder_plans.snapshot_cells(t, 16)).where("snap = 0"))
    mean = F.transform(F.sequence(F.lit(0), F.lit(E.D - 1)), lambda i: F.aggregate(F.col("vecs"), F.lit(0.0), lambda a, v: a + F.get(v, i)))

    def gap(way, vecs):
        norm = F.sqrt(F.aggregate("vec", F.lit(0.0), lambda a, x: a + x * x))
        unit = cut(vecs.withColumn("norm", norm).where("norm > 0").select("table_id", "col_id", F.transform("vec", lambda x: x / F.col("norm")).alias("vec")))
        a, b = unit.alias("a"), unit.alias("b")
        far = F.sqrt(F.aggregate(F.zip_with("a.vec", "b.vec", lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x))
        return a.join(b, (F.col("a.table_id") == F.col("b.table_id")) & (F.col("a.col_id") < F.col("b.col_id"))).agg(F.lit(way).alias("way"), F.count("*").alias("pairs"), F.round(F.avg(far), 4).alias("gap"))

    return gap("mean", E.pool(cells)).unionByName(gap("adapter", E.adapter_columns(cells).select("table_id", "col_id", mean.alias("vec"))))
