"""Collections of tables in long cell form: melting, profiles, cleaning rules, normalisation, imputation, text forms.

``cells`` = (table_id, row_id, col_id, col_name, value); a missing value is null, empty, or one of ``MISSING``.
"""

from __future__ import annotations

import json

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

MISSING = ["", "nan", "null", "none", "n/a"]


def melt(df: DataFrame, table_id: Column | str, key: str, columns: list[str] | None = None) -> DataFrame:
    """Wide rows as cells; one narrow pass."""
    columns = columns or df.columns
    table = F.lit(table_id) if isinstance(table_id, str) else table_id
    cells = F.array(*[F.struct(F.lit(i).alias("col_id"), F.lit(c).alias("col_name"), F.col(c).cast("string").alias("value")) for i, c in enumerate(columns)])
    return df.select(table.alias("table_id"), F.col(key).cast("long").alias("row_id"), F.inline(cells))


def missing(value: Column) -> Column:
    return value.isNull() | F.lower(F.trim(value)).isin(MISSING)


def kind(value: Column) -> Column:
    """long, double, timestamp, boolean or string; null for a missing value."""
    return (
        F.when(missing(value), None)
        .when(value.try_cast("long").isNotNull() & value.rlike("^-?[0-9]+$"), "long")
        .when(value.rlike(r"^-?[0-9]+(\.[0-9]+)?([eE][-+]?[0-9]+)?$"), "double")
        .when(value.rlike(r"^[0-9]{4}-[0-9]{2}-[0-9]{2}"), "timestamp")
        .when(F.lower(value).isin("true", "false"), "boolean")
        .otherwise("string")
    )


def counted(cells: DataFrame) -> DataFrame:
    """Cells of equal value in a column as one: ``n`` of them, ``row_id`` of the first. ``n`` of cells already counted is added up."""
    n = F.sum("n") if "n" in cells.columns else F.count("*")
    return cells.groupBy("table_id", "col_id", "col_name", "value").agg(n.alias("n"), F.min("row_id").alias("row_id"))


def profile(cells: DataFrame) -> DataFrame:
    """One row a column: counts, lengths, first value, type by majority of kinds, key candidate. Each distinct value is looked at once."""
    v, n = F.col("value"), F.col("n")
    those = lambda which: F.sum(F.when(which, n).otherwise(0))
    counts = [those(F.col("k") == name).alias(f"k_{name}") for name in ("long", "double", "timestamp", "boolean", "string")]
    p = counted(cells).withColumn("k", kind(v)).groupBy("table_id", "col_id", "col_name").agg(F.sum("n").alias("n"), those(F.col("k").isNull()).alias("n_missing"), F.count("value").alias("n_distinct"), F.max(F.length(v)).alias("max_len"), *counts)
    dtype = F.when(F.col("n") == F.col("n_missing"), "string").when(F.col("k_string") > 0, "string").when((F.col("k_boolean") > 0) & (F.col("k_long") + F.col("k_double") + F.col("k_timestamp") == 0), "boolean").when((F.col("k_timestamp") > 0) & (F.col("k_long") + F.col("k_double") == 0), "timestamp").when(F.col("k_double") > 0, "double").when(F.col("k_long") > 0, "long").otherwise("string")
    return p.select("table_id", "col_id", "col_name", dtype.alias("dtype"), "n", "n_missing", "n_distinct", "max_len", ((F.col("n_missing") == 0) & (F.col("n_distinct") == F.col("n"))).alias("is_key"))


# --- cleaning rules ----------------------------------------------------------


def column_faults(cells: DataFrame, long_limit: int = 100, sparse_limit: float = 0.3) -> DataFrame:
    """(table_id, col_id, col_name, rule, measured): the first rule each column breaks; one profile pass for all rules."""
    v = F.col("value")
    p = cells.groupBy("table_id", "col_id", "col_name").agg(
        F.min_by("value", "row_id").alias("first"), F.bool_and(F.coalesce(v, F.lit("")).rlike(r"^[_\-\s]*$")).alias("blank"),
        F.max(F.length(v)).alias("max_len"), F.avg(missing(v).cast("double")).alias("share"),
    )
    w = Window.partitionBy("table_id", F.lower("col_name")).orderBy("col_id")
    p = p.withColumn("nth", F.row_number().over(w))
    rule = F.when(F.col("nth") > 1, "duplicate_name").when(F.col("first") == F.col("col_name"), "header_echo").when(F.col("blank"), "underscore_only").when(F.col("max_len") > long_limit, "long_content").when(F.col("share") > sparse_limit, "sparse_column")
    measured = F.when(rule == "duplicate_name", F.col("nth")).when(rule == "long_content", F.col("max_len")).when(rule == "sparse_column", F.col("share")).otherwise(1.0).cast("double")
    return p.select("table_id", "col_id", "col_name", rule.alias("rule"), F.round(measured, 6).alias("measured")).where("rule is not null")


def row_faults(cells: DataFrame, limit: float = 0.3) -> DataFrame:
    """(table_id, row_id, measured): rows with more than ``limit`` missing."""
    return cells.groupBy("table_id", "row_id").agg(F.round(F.avg(missing(F.col("value")).cast("double")), 6).alias("measured")).where(F.col("measured") > limit)


def small_tables(cells: DataFrame, min_rows: int = 5, min_cols: int = 2) -> DataFrame:
    return cells.groupBy("table_id").agg(F.countDistinct("row_id").alias("n_rows"), F.countDistinct("col_id").alias("n_cols")).where((F.col("n_rows") < min_rows) | (F.col("n_cols") < min_cols))


def clean(cells: DataFrame) -> tuple[DataFrame, DataFrame]:
    """All rules in their fixed order: the surviving cells, and the ledger of what went and why."""
    cols = column_faults(cells)
    kept = cells.join(cols.select("table_id", "col_id"), ["table_id", "col_id"], "left_anti")
    rows = row_faults(kept)
    kept = kept.join(rows.select("table_id", "row_id"), ["table_id", "row_id"], "left_anti")
    small = small_tables(kept)
    kept = kept.join(small.select("table_id"), "table_id", "left_anti")
    ledger = (
        cols.select("table_id", F.lit("column").alias("object"), F.col("col_name").alias("object_id"), "rule", "measured")
        .unionByName(rows.select("table_id", F.lit("row").alias("object"), F.col("row_id").cast("string").alias("object_id"), F.lit("sparse_row").alias("rule"), "measured"))
        .unionByName(small.select("table_id", F.lit("table").alias("object"), F.col("table_id").alias("object_id"), F.lit("small_table").alias("rule"), F.col("n_rows").cast("double").alias("measured")))
    )
    return kept, ledger


def horizontal(cells: DataFrame) -> DataFrame:
    """Tables whose attributes run down the first column: more rows than columns hold one kind of value."""
    k = cells.withColumn("k", F.when(kind(F.col("value")).isin("long", "double"), "number").otherwise(kind(F.col("value")))).where("k is not null")
    body = k.where("col_id > 0")
    by_row = body.groupBy("table_id", "row_id").agg((F.countDistinct("k") == 1).cast("int").alias("same")).groupBy("table_id").agg(F.sum("same").alias("uniform_rows"), F.count("*").alias("n_rows"))
    by_col = k.groupBy("table_id", "col_id").agg((F.countDistinct("k") == 1).cast("int").alias("same")).groupBy("table_id").agg(F.sum("same").alias("uniform_cols"), F.count("*").alias("n_cols"))
    first = k.where("col_id = 0").groupBy("table_id").agg((F.bool_and(F.col("k") == "string") & (F.countDistinct("value") == F.count("*"))).alias("names_first"))
    both = by_row.join(by_col, "table_id").join(first, "table_id")
    return both.select("table_id", "uniform_rows", "n_rows", "uniform_cols", "n_cols", (F.col("names_first") & (F.col("uniform_rows") / F.col("n_rows") > F.col("uniform_cols") / F.col("n_cols"))).alias("horizontal"))


def transpose(cells: DataFrame) -> DataFrame:
    """Swap rows and columns of whole tables, counted from 0; column names are given up."""
    order = cells.withColumn("r", F.dense_rank().over(Window.partitionBy("table_id").orderBy("row_id")) - 1)
    return order.select("table_id", F.col("col_id").cast("long").alias("row_id"), F.col("r").cast("int").alias("col_id"), F.concat(F.lit("c"), F.col("r").cast("string")).alias("col_name"), "value")


def normalise_name(name: Column) -> Column:
    return F.regexp_replace(F.regexp_replace(F.lower(F.trim(name)), "[^a-z0-9]+", "_"), "^_+|_+$", "")


def normalise_value(value: Column) -> Column:
    """Outer blanks and thousands separators out, missing marks to null, flags in one spelling."""
    v = F.regexp_replace(F.trim(value), r"\s+", " ")
    return F.when(missing(v), None).when(v.rlike(r"^-?[0-9]{1,3}(,[0-9]{3})+(\.[0-9]+)?$"), F.replace(v, F.lit(","), F.lit(""))).when(F.lower(v).isin("yes", "true", "y"), "true").when(F.lower(v).isin("no", "false", "n"), "false").otherwise(v)


def impute(df: DataFrame, column: str, how: str = "mean", by: list[str] | None = None, order: list[str] | None = None) -> DataFrame:
    """Fill gaps by the group's mean, median or mode, or by the last value in order."""
    by, c = by or [], F.col(column)
    if how == "ffill":
        w = Window.partitionBy(*by).orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
        return df.withColumn(column, F.last(c, ignorenulls=True).over(w))
    agg = {"mean": F.avg(c), "median": F.percentile(c, 0.5), "mode": F.mode(c, True)}[how]
    stats = df.groupBy(*by).agg(agg.alias("_fill"))
    joined = df.join(stats, by) if by else df.crossJoin(F.broadcast(stats))
    return joined.withColumn(column, F.coalesce(c, F.col("_fill"))).drop("_fill")


# --- irregular grids ---------------------------------------------------------


def unmerge(grid: DataFrame) -> DataFrame:
    """(table_id, r, c, value, is_header): every cell of a span gets the value of its anchor."""
    rows = grid.withColumn("r", F.explode(F.sequence(F.col("r"), F.col("r") + F.col("rowspan") - 1)))
    return rows.withColumn("c", F.explode(F.sequence(F.col("c"), F.col("c") + F.col("colspan") - 1))).select("table_id", "r", "c", "value", "is_header")


def flatten_headers(cells: DataFrame, sep: str = " / ") -> DataFrame:
    """Body cells with one name a column: its header levels joined from the top."""
    heads = cells.where("is_header").groupBy("table_id", "c").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("r", "value"))), lambda x: x["value"]), sep).alias("col_name"))
    return cells.where("not is_header").join(heads, ["table_id", "c"]).select("table_id", F.col("r").cast("long").alias("row_id"), F.col("c").alias("col_id"), "col_name", "value")


def plan_of(grid: DataFrame, sep: str = " / ") -> str:
    """The steps that turn the tables of a grid into cells, as JSON, from what they are: spans are
    unmerged if any is there, and names come from one header row or from several joined.
    The plan applies to later states of the tables too."""
    seen = regularity(grid).agg(F.max("merged").alias("merged"), F.max("header_rows").alias("levels")).first()
    steps = [{"step": "unmerge"}] if seen.merged else []
    return json.dumps([*steps, {"step": "flatten_headers", "sep": sep if (seen.levels or 0) > 1 else ""}])


def replay(grid: DataFrame, plan: str) -> DataFrame:
    steps = {"unmerge": lambda df, **_: unmerge(df), "flatten_headers": lambda df, sep: flatten_headers(df, sep)}
    for s in json.loads(plan):
        grid = steps[s.pop("step")](grid, **s)
    return grid


def regularity(grid: DataFrame) -> DataFrame:
    """Regular tables have one header row and no spans."""
    return grid.groupBy("table_id").agg(F.max((F.col("rowspan") > 1) | (F.col("colspan") > 1)).alias("merged"), F.countDistinct(F.when(F.col("is_header"), F.col("r"))).alias("header_rows")).select("table_id", "merged", "header_rows", (~F.col("merged") & (F.col("header_rows") == 1)).alias("regular"))


# --- text forms --------------------------------------------------------------


def serialise(cells: DataFrame, fmt: str) -> DataFrame:
    """(table_id, text) in html, xml, markdown, text, json, csv, pipe or key=value form."""
    rows = cells.groupBy("table_id", "row_id").agg(F.array_sort(F.collect_list(F.struct("col_id", "col_name", F.coalesce("value", F.lit("")).alias("value")))).alias("cs"))

    def each(fn, sep):
        return F.array_join(F.transform("cs", fn), sep)

    def swapped(text, *pairs):
        for old, new in pairs:
            text = F.replace(text, F.lit(old), F.lit(new))
        return text

    padded = lambda x: F.rpad(x, F.greatest(F.lit(16), F.length(x)), " ")  # noqa: E731  (a longer value is not cut)
    # What the marks of a form mean elsewhere is escaped in names and values.
    marked = lambda x: swapped(x, ("&", "&amp;"), ("<", "&lt;"), (">", "&gt;"))
    barred = lambda x: swapped(x, ("\\", "\\\\"), ("|", "\\|"), ("\n", " "))
    tag = lambda x: F.regexp_replace(F.regexp_replace(x, r"[^\pL\pN_.-]", "_"), r"^(?![\pL_])", "_")
    told = lambda x: F.to_json(F.array(x)).substr(F.lit(2), F.length(F.to_json(F.array(x))) - 2)
    listed = lambda x: swapped(x, ("\\", "\\\\"), (";", "\\;"), ("=", "\\="), ("\n", "\\n"))
    quoted = lambda x: F.concat(F.lit('"'), F.replace(x, F.lit('"'), F.lit('""')), F.lit('"'))
    value, pair = (lambda c: barred(c["value"])), (lambda c: F.concat(listed(c["col_name"]), F.lit("="), listed(c["value"])))
    quote = lambda c: quoted(c["value"])
    head_of = lambda c: F.when(c["col_name"].rlike('[",\n]'), quoted(c["col_name"])).otherwise(c["col_name"])
    name = lambda c: barred(c["col_name"])
    forms = {
        "html": ("<table>", each(lambda c: F.concat(F.lit("<th>"), marked(c["col_name"]), F.lit("</th>")), ""), each(lambda c: F.concat(F.lit("<td>"), marked(c["value"]), F.lit("</td>")), ""), "<tr>", "</tr>", "", "</table>"),
        "xml": ("<table>", None, each(lambda c: F.concat(F.lit("<"), tag(c["col_name"]), F.lit(">"), marked(c["value"]), F.lit("</"), tag(c["col_name"]), F.lit(">")), ""), "<row>", "</row>", "", "</table>"),
        "markdown": ("", each(name, " | "), each(value, " | "), "| ", " |", "\n", ""),
        "text": ("", each(lambda c: padded(c["col_name"]), " "), each(lambda c: padded(c["value"]), " "), "", "", "\n", ""),
        "json": ("[", None, each(lambda c: F.concat(told(c["col_name"]), F.lit(":"), told(c["value"])), ","), "{", "}", ",", "]"),
        "csv": ("", each(head_of, ","), each(quote, ","), "", "", "\n", ""),
        "pipe": ("", each(name, "|"), each(value, "|"), "", "", "\n", ""),
        "key_value": ("", None, each(pair, "; "), "", "", "\n", ""),
    }
    start, head, body, a, b, sep, end = forms[fmt]
    shown = rows.select("table_id", "row_id", F.concat(F.lit(a), body, F.lit(b)).alias("line"), (F.concat(F.lit(a), head, F.lit(b)) if head is not None else F.lit(None).cast("string")).alias("head"))
    text = shown.groupBy("table_id").agg(F.first("head").alias("head"), F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("row_id", "line"))), lambda x: x["line"]), sep).alias("lines"))
    rule = F.concat(F.lit("\n"), F.regexp_replace("head", "[^|]+", "---")) if fmt == "markdown" else F.lit("")
    top = F.when(F.col("head").isNotNull(), F.concat("head", rule, F.lit(sep))).otherwise("")
    return text.select("table_id", F.concat(F.lit(start), top, "lines", F.lit(end)).alias("text"))


FORMATS = ["html", "xml", "markdown", "text", "json", "csv", "pipe", "key_value"]


def combos() -> list[tuple[str, bool, bool]]:
    """Text form with or without field descriptions, with or without listed values."""
    return [(f, d, v) for f in FORMATS for d in (False, True) for v in (False, True)]


# --- augmentation ------------------------------------------------------------


def anonymise(cells: DataFrame, max_kinds: int | None = None) -> tuple[DataFrame, DataFrame]:
    """Headers become ``col_i``, text values ``val_j`` (of columns with up to ``max_kinds`` kinds, if given); the mapping is one to one inside each table."""
    heads = cells.select("table_id", "col_id", "col_name").distinct().withColumn("new", F.concat(F.lit("col_"), F.row_number().over(Window.partitionBy("table_id").orderBy(F.md5("col_name"), "col_name")).cast("string")))
    values = cells.select("table_id", "col_id", "value").where("value is not null").distinct()
    texts = values.groupBy("table_id", "col_id").agg(F.count_if(kind(F.col("value")) == "string").alias("k")).where((F.col("k") > 0) & (F.lit(max_kinds is None) | (F.col("k") <= F.lit(max_kinds or 0))))
    kinds = values.join(texts.select("table_id", "col_id"), ["table_id", "col_id"], "left_semi")
    vals = kinds.withColumn("new_value", F.concat(F.lit("val_"), F.row_number().over(Window.partitionBy("table_id", "col_id").orderBy(F.md5("value"), "value")).cast("string")))
    named = {"col_name": F.col("new").alias("col_name"), "value": F.coalesce("new_value", "value").alias("value")}
    out = cells.join(heads.drop("col_name"), ["table_id", "col_id"]).join(vals, ["table_id", "col_id", "value"], "left").select(*[named.get(c, F.col(c)) for c in cells.columns])
    mapping = heads.select("table_id", F.lit("header").alias("kind"), F.col("col_name").alias("old"), "new").unionByName(vals.select("table_id", F.lit("value").alias("kind"), F.col("value").alias("old"), F.col("new_value").alias("new")))
    return out, mapping


def inclusions(cells: DataFrame) -> DataFrame:
    """Share of a column's distinct values found in each other column; values are hashed and joined once."""
    vals = cells.where(~missing(F.col("value"))).select("table_id", "col_name", "value").distinct()
    size = vals.groupBy("table_id", "col_name").agg(F.count("*").alias("n"))
    at = vals.groupBy("value").agg(F.collect_list(F.struct("table_id", "col_name")).alias("cols"))
    pairs = at.select(F.explode("cols").alias("a"), "cols").select("a", F.explode("cols").alias("b")).where("a.table_id <> b.table_id").groupBy("a", "b").agg(F.count("*").alias("both"))
    return pairs.select(F.col("a.table_id").alias("table_id"), F.col("a.col_name").alias("col_name"), F.col("b.table_id").alias("in_table"), F.col("b.col_name").alias("in_col"), "both").join(size, ["table_id", "col_name"]).select("table_id", "col_name", "in_table", "in_col", F.round(F.col("both") / F.col("n"), 6).alias("containment"))
