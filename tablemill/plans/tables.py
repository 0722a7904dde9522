"""Queries of table collection, cleaning, normalisation and text forms."""

from __future__ import annotations

from pyspark.sql import functions as F

from tablemill.functions import det
from tablemill.operators import tables as T
from tablemill.plans.registry import query

MISS = "(value IS NULL OR lower(trim(value)) IN ('', 'nan', 'null', 'none', 'n/a'))"

SLICE_COLS = ["o_orderkey", "o_custkey", "o_totalprice", "o_orderpriority", "blank", "O_CUSTKEY", "note", "o_orderstatus", "echo"]


def slices(t):
    """``orders`` cut by month, with planted faults; see the oracle text for each."""
    o = t.orders.withColumn("table_id", F.concat(F.lit("orders-"), F.date_format("o_orderdate", "yyyy-MM")))
    key = F.col("o_orderkey")
    low = det.unit("sparse", F.col("table_id")) < 0.3
    first = o.groupBy("table_id").agg(F.min("o_orderkey").alias("first_key"))
    o = o.join(first, "table_id")
    bad_row = det.unit("row", key) < 0.05
    wide = o.select(
        "table_id", key.alias("row_id"), key.cast("string").alias("o_orderkey"),
        F.when(~bad_row, F.col("o_custkey").cast("string")).alias("c1"),
        F.when(~bad_row, F.col("o_totalprice").cast("string")).alias("c2"),
        F.when(~bad_row, F.col("o_orderpriority")).alias("c3"),
        F.lit("___").alias("c4"), F.col("o_custkey").cast("string").alias("c5"),
        F.when(det.unit("note", key) < 0.002, F.repeat(F.lit("x"), 120)).otherwise("short").alias("c6"),
        F.when(det.unit("hole", key) < F.when(low, 0.5).otherwise(0.05), None).otherwise(F.col("o_orderstatus")).alias("c7"),
        F.when(key == F.col("first_key"), "echo").otherwise("v").alias("c8"),
    )
    names = ["o_orderkey", *[f"c{i}" for i in range(1, 9)]]
    cells = F.array(*[F.struct(F.lit(i).alias("col_id"), F.lit(n).alias("col_name"), F.col(c).alias("value")) for i, (n, c) in enumerate(zip(SLICE_COLS, names))])
    return wide.select("table_id", "row_id", F.inline(cells))


_U = det.sql_unit
_CELLS = [
    "o_orderkey::VARCHAR", "CASE WHEN NOT bad THEN o_custkey::VARCHAR END", "CASE WHEN NOT bad THEN o_totalprice::VARCHAR END", "CASE WHEN NOT bad THEN o_orderpriority END",
    "'___'", "o_custkey::VARCHAR", f"CASE WHEN {_U(chr(39) + 'note' + chr(39), 'o_orderkey')} < 0.002 THEN repeat('x', 120) ELSE 'short' END",
    f"CASE WHEN {_U(chr(39) + 'hole' + chr(39), 'o_orderkey')} < CASE WHEN low THEN 0.5 ELSE 0.05 END THEN NULL ELSE o_orderstatus END", "CASE WHEN o_orderkey = first_key THEN 'echo' ELSE 'v' END",
]
SLICES_SQL = (
    f"WITH o1 AS (SELECT *, 'orders-' || strftime(o_orderdate, '%Y-%m') AS table_id FROM orders), "
    f"o2 AS (SELECT *, min(o_orderkey) OVER (PARTITION BY table_id) AS first_key, {_U(chr(39) + 'sparse' + chr(39), 'table_id')} < 0.3 AS low, {_U(chr(39) + 'row' + chr(39), 'o_orderkey')} < 0.05 AS bad FROM o1), "
    "cells AS (" + " UNION ALL ".join(f"SELECT table_id, o_orderkey AS row_id, {i} AS col_id, '{n}' AS col_name, {e} AS value FROM o2" for i, (n, e) in enumerate(zip(SLICE_COLS, _CELLS))) + "), "
    f"cf AS (SELECT table_id, col_id, col_name, nth, first, blank, max_len, share, CASE WHEN nth > 1 THEN 'duplicate_name' WHEN first = col_name THEN 'header_echo' WHEN blank THEN 'underscore_only' WHEN max_len > 100 THEN 'long_content' WHEN share > 0.3 THEN 'sparse_column' END AS rule FROM "
    f"(SELECT *, row_number() OVER (PARTITION BY table_id, lower(col_name) ORDER BY col_id) AS nth FROM (SELECT table_id, col_id, col_name, arg_min(value, row_id) AS first, bool_and(regexp_matches(coalesce(value, ''), '^[_\\-\\s]*$')) AS blank, max(length(value)) AS max_len, avg({MISS}::INT) AS share FROM cells GROUP BY 1, 2, 3))), "
    "f AS (SELECT table_id, col_id, col_name, rule, round(CASE rule WHEN 'duplicate_name' THEN nth WHEN 'long_content' THEN max_len WHEN 'sparse_column' THEN share ELSE 1 END, 6)::DOUBLE AS measured FROM cf WHERE rule IS NOT NULL), "
    "k1 AS (SELECT c.* FROM cells c ANTI JOIN f USING (table_id, col_id)), "
    f"rf AS (SELECT * FROM (SELECT table_id, row_id, round(avg({MISS}::INT), 6) AS measured FROM k1 GROUP BY 1, 2) WHERE measured > 0.3), "
    "k2 AS (SELECT k.* FROM k1 k ANTI JOIN rf USING (table_id, row_id)), "
    "sm AS (SELECT * FROM (SELECT table_id, count(DISTINCT row_id)::BIGINT AS n_rows, count(DISTINCT col_id)::BIGINT AS n_cols FROM k2 GROUP BY 1) WHERE n_rows < 5 OR n_cols < 2) "
)


@query("tab_catalog", "SELECT 'customer' AS name, count(*)::BIGINT AS n_rows, 5 AS n_cols FROM customer UNION ALL SELECT 'orders', count(*), 6 FROM orders UNION ALL SELECT 'part', count(*), 6 FROM part UNION ALL SELECT 'supplier', count(*), 4 FROM supplier UNION ALL SELECT 'nation', count(*), 3 FROM nation UNION ALL SELECT 'region', count(*), 2 FROM region")
def tab_catalog(t):
    out = None
    for name in ("customer", "orders", "part", "supplier", "nation", "region"):
        df = getattr(t, name)
        row = df.agg(F.count("*").alias("n_rows")).select(F.lit(name).alias("name"), "n_rows", F.lit(len(df.columns)).alias("n_cols"))
        out = row if out is None else out.unionByName(row)
    return out


@query("tab_slices", SLICES_SQL + "SELECT table_id, count(DISTINCT row_id)::BIGINT AS n_rows, count(*)::BIGINT AS n_cells, count(value)::BIGINT AS n_values FROM cells GROUP BY 1")
def tab_slices(t):
    return slices(t).groupBy("table_id").agg(F.countDistinct("row_id").alias("n_rows"), F.count("*").alias("n_cells"), F.count("value").alias("n_values"))


for _name, _rules in (("tab_dup_columns", ["duplicate_name"]), ("tab_underscore", ["underscore_only"]), ("tab_long_columns", ["long_content"]), ("tab_header_echo", ["header_echo"])):

    @query(_name, SLICES_SQL + f"SELECT table_id, col_id, col_name, rule, measured FROM f WHERE rule = '{_rules[0]}'")
    def tab_rule(t, rules=_rules):
        return T.column_faults(slices(t)).where(F.col("rule").isin(rules))


@query("tab_sparse", SLICES_SQL + "SELECT table_id, 'column' AS object, col_name AS object_id, measured FROM f WHERE rule = 'sparse_column' UNION ALL SELECT table_id, 'row', row_id::VARCHAR, measured FROM rf")
def tab_sparse(t):
    _, ledger = T.clean(slices(t))
    return ledger.where("rule in ('sparse_column', 'sparse_row')").select("table_id", "object", "object_id", "measured")


@query("tab_small", SLICES_SQL + "SELECT table_id, n_rows, n_cols FROM sm")
def tab_small(t):
    cells = slices(t)
    cols = T.column_faults(cells)
    kept = cells.join(cols, ["table_id", "col_id"], "left_anti")
    return T.small_tables(kept.join(T.row_faults(kept), ["table_id", "row_id"], "left_anti"))


@query("tab_clean_pipeline", SLICES_SQL + "SELECT rule, count(*)::BIGINT AS n FROM (SELECT rule FROM f UNION ALL SELECT 'sparse_row' FROM rf UNION ALL SELECT 'small_table' FROM sm UNION ALL SELECT 'kept_cells' FROM k2 ANTI JOIN sm USING (table_id)) GROUP BY 1")
def tab_clean_pipeline(t):
    kept, ledger = T.clean(slices(t))
    return ledger.select("rule").unionByName(kept.select(F.lit("kept_cells").alias("rule"))).groupBy("rule").agg(F.count("*").alias("n"))


HORIZ_SQL = """
WITH s AS (SELECT *, c_custkey // 8 AS block, (c_custkey % 8 + 1)::BIGINT AS i FROM customer),
h AS (SELECT 'across-' || block AS table_id, 0 AS row_id, i AS col_id, c_name AS value FROM s UNION ALL SELECT 'across-' || block, 1, i, c_acctbal::VARCHAR FROM s UNION ALL SELECT 'across-' || block, 2, i, c_mktsegment FROM s
 UNION ALL SELECT DISTINCT 'across-' || block, v.k, 0, v.n FROM s, (VALUES (0, 'name'), (1, 'balance'), (2, 'segment')) v(k, n)
 UNION ALL SELECT 'down-' || block, i, 0, c_name FROM s UNION ALL SELECT 'down-' || block, i, 1, c_acctbal::VARCHAR FROM s UNION ALL SELECT 'down-' || block, i, 2, c_mktsegment FROM s),
k AS (SELECT *, CASE WHEN regexp_matches(value, '^-?[0-9]+(\\.[0-9]+)?([eE][-+]?[0-9]+)?$') THEN 'number' WHEN regexp_matches(value, '^[0-9]{4}-[0-9]{2}-[0-9]{2}') THEN 'timestamp' ELSE 'string' END AS k FROM h),
br AS (SELECT table_id, sum(same)::BIGINT AS uniform_rows, count(*)::BIGINT AS n_rows FROM (SELECT table_id, row_id, (count(DISTINCT k) = 1)::INT AS same FROM k WHERE col_id > 0 GROUP BY 1, 2) GROUP BY 1),
bc AS (SELECT table_id, sum(same)::BIGINT AS uniform_cols, count(*)::BIGINT AS n_cols FROM (SELECT table_id, col_id, (count(DISTINCT k) = 1)::INT AS same FROM k GROUP BY 1, 2) GROUP BY 1),
f AS (SELECT table_id, bool_and(k = 'string') AND count(DISTINCT value) = count(*) AS names_first FROM k WHERE col_id = 0 GROUP BY 1)
SELECT table_id, uniform_rows, n_rows, uniform_cols, n_cols, names_first AND uniform_rows / n_rows > uniform_cols / n_cols AS horizontal FROM br JOIN bc USING (table_id) JOIN f USING (table_id)"""


def across_and_down(t):
    """All customers in tables of eight, once with attributes across and once down."""
    s = t.customer.withColumn("i", F.expr("c_custkey % 8 + 1")).withColumn("block", F.expr("cast(c_custkey div 8 AS string)"))
    attrs = [("name", "c_name"), ("balance", "c_acctbal"), ("segment", "c_mktsegment")]
    cell = lambda r, c, v: F.struct(r.cast("long").alias("row_id"), c.cast("int").alias("col_id"), v.cast("string").alias("value"))
    down = s.select(F.concat(F.lit("down-"), F.col("block")).alias("table_id"), F.inline(F.array(*[cell(F.col("i"), F.lit(k), F.col(c)) for k, (_, c) in enumerate(attrs)])))
    across = s.select(F.concat(F.lit("across-"), F.col("block")).alias("table_id"), F.inline(F.array(*[cell(F.lit(k), F.col("i"), F.col(c)) for k, (_, c) in enumerate(attrs)])))
    names = across.select("table_id").distinct().select("table_id", F.inline(F.array(*[cell(F.lit(k), F.lit(0), F.lit(n)) for k, (n, _) in enumerate(attrs)])))
    return down.unionByName(across).unionByName(names).withColumn("col_name", F.concat(F.lit("c"), F.col("col_id").cast("string")))


@query("tab_horizontal", HORIZ_SQL)
def tab_horizontal(t):
    return T.horizontal(across_and_down(t))


GRID_SQL = """
WITH base AS (SELECT r_name, n_name, year(o_orderdate)::INT AS y, round(sum(o_totalprice))::BIGINT AS v FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1, 2, 3),
nat AS (SELECT DISTINCT r_name, n_name FROM base), ncol AS (SELECT *, row_number() OVER (ORDER BY r_name, n_name)::INT AS c FROM nat), yr AS (SELECT y, (row_number() OVER (ORDER BY y) + 1)::INT AS r FROM (SELECT DISTINCT y FROM base)),
grid AS (SELECT 'revenue' AS table_id, 0 AS r, min(c) AS c, 1 AS rowspan, count(*)::INT AS colspan, r_name AS value, TRUE AS is_header FROM ncol GROUP BY r_name
 UNION ALL SELECT 'revenue', 1, c, 1, 1, n_name, TRUE FROM ncol UNION ALL SELECT 'revenue', 0, 0, 2, 1, 'year', TRUE
 UNION ALL SELECT 'revenue', r, 0, 1, 1, y::VARCHAR, FALSE FROM yr UNION ALL SELECT 'revenue', r, c, 1, 1, v::VARCHAR, FALSE FROM base JOIN ncol USING (r_name, n_name) JOIN yr USING (y)),
un AS (SELECT table_id, unnest(range(r, r + rowspan)) AS r, c, colspan, value, is_header FROM grid),
uc AS (SELECT table_id, r, unnest(range(c, c + colspan)) AS c, value, is_header FROM un),
hd AS (SELECT table_id, c, string_agg(value, ' / ' ORDER BY r) AS col_name FROM uc WHERE is_header GROUP BY 1, 2),
fl AS (SELECT u.table_id, u.r::BIGINT AS row_id, u.c::INT AS col_id, col_name, value FROM uc u JOIN hd USING (table_id, c) WHERE NOT is_header)
"""


def grid(t):
    """Revenue by year under nation under region: merged headers as in a spreadsheet. Labels are few; values come from one aggregate."""
    from pyspark.sql import Window

    both = t.orders.join(t.customer, F.col("o_custkey") == F.col("c_custkey")).join(t.nation, F.col("c_nationkey") == F.col("n_nationkey")).join(t.region, F.col("n_regionkey") == F.col("r_regionkey"))
    base = both.groupBy("r_name", "n_name", F.year("o_orderdate").alias("y")).agg(F.round(F.sum("o_totalprice")).cast("long").alias("v"))
    cols = base.select("r_name", "n_name").distinct().withColumn("c", F.row_number().over(Window.orderBy("r_name", "n_name")))
    years = base.select("y").distinct().withColumn("r", F.row_number().over(Window.orderBy("y")) + 1)
    cell = lambda r, c, span, v, h, rs=1: [F.lit("revenue").alias("table_id"), F.lit(r).alias("r") if isinstance(r, int) else r.cast("int").alias("r"), F.lit(c).alias("c") if isinstance(c, int) else c.cast("int").alias("c"), F.lit(rs).alias("rowspan"), F.lit(span).alias("colspan") if isinstance(span, int) else span.cast("int").alias("colspan"), v.cast("string").alias("value"), F.lit(h).alias("is_header")]
    top = cols.groupBy("r_name").agg(F.min("c").alias("c"), F.count("*").alias("k"))
    out = top.select(*cell(0, F.col("c"), F.col("k"), F.col("r_name"), True))
    out = out.unionByName(cols.select(*cell(1, F.col("c"), 1, F.col("n_name"), True))).unionByName(t.spark.range(1).select(*cell(0, 0, 1, F.lit("year"), True, 2)))
    out = out.unionByName(years.select(*cell(F.col("r"), 0, 1, F.col("y"), False)))
    return out.unionByName(base.join(cols, ["r_name", "n_name"]).join(years, "y").select(*cell(F.col("r"), F.col("c"), 1, F.col("v"), False)))


@query("tab_regularity", GRID_SQL + "SELECT table_id, bool_or(rowspan > 1 OR colspan > 1) AS merged, count(DISTINCT r) FILTER (WHERE is_header)::BIGINT AS header_rows, FALSE AS regular FROM grid GROUP BY 1")
def tab_regularity(t):
    return T.regularity(grid(t))


@query("tab_unmerge", GRID_SQL + "SELECT table_id, r::INT AS r, c::INT AS c, value, is_header FROM uc")
def tab_unmerge(t):
    return T.unmerge(grid(t))


@query("tab_flatten_headers", GRID_SQL + "SELECT * FROM fl")
def tab_flatten_headers(t):
    return T.flatten_headers(T.unmerge(grid(t)))


@query("tab_plan_replay", GRID_SQL + "SELECT * FROM fl")
def tab_plan_replay(t):
    g = grid(t)
    return T.replay(g, T.plan_of(g))


@query("tab_normalise_names", r"SELECT p_partkey, regexp_replace(regexp_replace(lower(trim('  ' || p_brand || ' / ' || p_type || '!')), '[^a-z0-9]+', '_', 'g'), '^_+|_+$', '', 'g') AS name, replace('1,234.50', ',', '') AS number, 'true' AS flag, NULL::VARCHAR AS gap FROM part")
def tab_normalise_names(t):
    return t.part.select("p_partkey", T.normalise_name(F.concat(F.lit("  "), "p_brand", F.lit(" / "), "p_type", F.lit("!"))).alias("name"), T.normalise_value(F.lit(" 1,234.50")).alias("number"), T.normalise_value(F.lit("Yes ")).alias("flag"), T.normalise_value(F.lit("N/A")).alias("gap"))


@query("tab_impute", SLICES_SQL + "SELECT table_id, row_id, coalesce(value, m) AS value FROM (SELECT table_id, row_id, value, (SELECT arg_max(v, n * 1000 - ascii(v)) FROM (SELECT value AS v, count(*) AS n FROM cells i WHERE i.table_id = cells.table_id AND i.col_id = 7 AND value IS NOT NULL GROUP BY 1)) AS m FROM cells WHERE col_id = 7)")
def tab_impute(t):
    col = slices(t).where("col_id = 7").select("table_id", "row_id", "value")
    return T.impute(col, "value", "mode", ["table_id"])


def small_cells(t):
    """``nation`` and ``region`` as cells, for text forms."""
    return T.melt(t.nation, "nation", "n_nationkey").unionByName(T.melt(t.region, "region", "r_regionkey"))


SMALL_SQL = """WITH cells AS (SELECT 'nation' AS table_id, n_nationkey::BIGINT AS row_id, 0 AS col_id, 'n_nationkey' AS col_name, n_nationkey::VARCHAR AS value FROM nation UNION ALL SELECT 'nation', n_nationkey, 1, 'n_name', n_name FROM nation UNION ALL SELECT 'nation', n_nationkey, 2, 'n_regionkey', n_regionkey::VARCHAR FROM nation
 UNION ALL SELECT 'region', r_regionkey, 0, 'r_regionkey', r_regionkey::VARCHAR FROM region UNION ALL SELECT 'region', r_regionkey, 1, 'r_name', r_name FROM region) """

_SER = {
    "html": ("'<table>'", "'<tr>' || string_agg('<th>' || col_name || '</th>', '' ORDER BY col_id) || '</tr>'", "'<tr>' || string_agg('<td>' || value || '</td>', '' ORDER BY col_id) || '</tr>'", "''", "'</table>'"),
    "xml": ("'<table>'", None, "'<row>' || string_agg('<' || col_name || '>' || value || '</' || col_name || '>', '' ORDER BY col_id) || '</row>'", "''", "'</table>'"),
    "markdown": ("''", "'| ' || string_agg(col_name, ' | ' ORDER BY col_id) || ' |'", "'| ' || string_agg(value, ' | ' ORDER BY col_id) || ' |'", "chr(10)", "''"),
    "json": ("'['", None, """'{' || string_agg('"' || col_name || '":"' || value || '"', ',' ORDER BY col_id) || '}'""", "','", "']'"),
    "csv": ("''", "string_agg(col_name, ',' ORDER BY col_id)", """string_agg('"' || value || '"', ',' ORDER BY col_id)""", "chr(10)", "''"),
    "text": ("''", "string_agg(rpad(col_name, greatest(16, length(col_name))::INT, ' '), ' ' ORDER BY col_id)", "string_agg(rpad(value, greatest(16, length(value))::INT, ' '), ' ' ORDER BY col_id)", "chr(10)", "''"),
    "key_value": ("''", None, "string_agg(col_name || '=' || value, '; ' ORDER BY col_id)", "chr(10)", "''"),
    "pipe": ("''", "string_agg(col_name, '|' ORDER BY col_id)", "string_agg(value, '|' ORDER BY col_id)", "chr(10)", "''"),
}
for _fmt, (_a, _h, _l, _s, _e) in _SER.items():
    _rule = " || chr(10) || regexp_replace(head, '[^|]+', '---', 'g')" if _fmt == "markdown" else ""
    _top = f"(SELECT any_value(head){_rule.replace('head', 'any_value(head)')} || {_s} FROM h WHERE h.table_id = l.table_id)" if _h else "''"
    _head = f"h AS (SELECT table_id, row_id, {_h} AS head FROM cells GROUP BY 1, 2), " if _h else ""

    @query(f"fac_serialise_{_fmt}", SMALL_SQL + f", {_head}l AS (SELECT table_id, row_id, {_l} AS line FROM cells GROUP BY 1, 2) SELECT table_id, {_a} || {_top} || string_agg(line, {_s} ORDER BY row_id) || {_e} AS text FROM l GROUP BY table_id")
    def fac_serialise(t, fmt=_fmt):
        return T.serialise(small_cells(t), fmt)


@query("fac_table_info_combos", "SELECT count(*)::BIGINT AS n FROM range(8), range(2) b(x), range(2) c(y)")
def fac_table_info_combos(t):
    return t.spark.createDataFrame(T.combos(), "fmt string, described boolean, listed boolean").agg(F.count("*").alias("n"))


ANON_SQL = SMALL_SQL + """, h AS (SELECT table_id, col_id, col_name, 'col_' || row_number() OVER (PARTITION BY table_id ORDER BY md5(col_name), col_name) AS new FROM (SELECT DISTINCT table_id, col_id, col_name FROM cells)),
few AS (SELECT table_id, col_id FROM cells WHERE NOT regexp_matches(value, '^-?[0-9.]+$') GROUP BY 1, 2),
v AS (SELECT table_id, col_id, value, 'val_' || row_number() OVER (PARTITION BY table_id, col_id ORDER BY md5(value), value) AS nv FROM (SELECT DISTINCT table_id, col_id, value FROM cells SEMI JOIN few USING (table_id, col_id)))
SELECT c.table_id, c.row_id, c.col_id, h.new AS col_name, coalesce(v.nv, c.value) AS value FROM cells c JOIN h USING (table_id, col_id) LEFT JOIN v ON v.table_id = c.table_id AND v.col_id = c.col_id AND v.value = c.value"""


@query("fac_anonymise", ANON_SQL)
def fac_anonymise(t):
    return T.anonymise(small_cells(t))[0]


@query("enc_cells", "SELECT 'customer' AS table_id, c_custkey AS row_id, v.col_id, v.col_name, v.value FROM customer, LATERAL (VALUES (0, 'c_custkey', c_custkey::VARCHAR), (1, 'c_name', c_name), (2, 'c_nationkey', c_nationkey::VARCHAR), (3, 'c_acctbal', c_acctbal::VARCHAR), (4, 'c_mktsegment', c_mktsegment)) v(col_id, col_name, value)")
def enc_cells(t):
    return T.melt(t.customer, "customer", "c_custkey")


@query("enc_profile", """
WITH cells AS (SELECT c_custkey AS row_id, v.* FROM customer, LATERAL (VALUES (0, 'c_custkey', c_custkey::VARCHAR, 'long'), (1, 'c_name', c_name, 'string'), (2, 'c_nationkey', c_nationkey::VARCHAR, 'long'), (3, 'c_acctbal', c_acctbal::VARCHAR, 'double'), (4, 'c_mktsegment', c_mktsegment, 'string')) v(col_id, col_name, value, dtype))
SELECT 'customer' AS table_id, col_id, col_name, dtype, count(*)::BIGINT AS n, 0::BIGINT AS n_missing, count(DISTINCT value)::BIGINT AS n_distinct, max(length(value))::INT AS max_len, count(DISTINCT value) = count(*) AS is_key FROM cells GROUP BY col_id, col_name, dtype""")
def enc_profile(t):
    return T.profile(T.melt(t.customer, "customer", "c_custkey"))


@query("agt_fk_inclusion", """
WITH v AS (SELECT DISTINCT 'nation' AS table_id, 'n_regionkey' AS col_name, n_regionkey::VARCHAR AS value FROM nation UNION SELECT 'nation', 'n_nationkey', n_nationkey::VARCHAR FROM nation UNION SELECT 'region', 'r_regionkey', r_regionkey::VARCHAR FROM region
 UNION SELECT 'customer', 'c_custkey', c_custkey::VARCHAR FROM customer UNION SELECT 'customer', 'c_nationkey', c_nationkey::VARCHAR FROM customer UNION SELECT 'orders', 'o_custkey', o_custkey::VARCHAR FROM orders),
n AS (SELECT table_id, col_name, count(*) AS n FROM v GROUP BY 1, 2)
SELECT a.table_id, a.col_name, b.table_id AS in_table, b.col_name AS in_col, round(count(*)::DOUBLE / any_value(n.n), 6) AS containment FROM v a JOIN v b ON a.value = b.value AND a.table_id <> b.table_id JOIN n ON n.table_id = a.table_id AND n.col_name = a.col_name GROUP BY 1, 2, 3, 4""")
def agt_fk_inclusion(t):
    picks = [(t.nation, "nation", "n_nationkey", ["n_regionkey", "n_nationkey"]), (t.region, "region", "r_regionkey", ["r_regionkey"]), (t.customer, "customer", "c_custkey", ["c_custkey", "c_nationkey"]), (t.orders, "orders", "o_orderkey", ["o_custkey"])]
    out = None
    for df, name, key, cols in picks:
        cells = T.melt(df, name, key, cols)
        out = cells if out is None else out.unionByName(cells)
    return T.inclusions(out)
