"""Irregular tables as sources: table markup in HTML, and a Python data source for grids with spans."""

from __future__ import annotations

import json
from html.parser import HTMLParser

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

GRID = "table_id string, r int, c int, rowspan int, colspan int, value string, is_header boolean"


class TableParser(HTMLParser):
    """Cells of all tables in a page, placed around the spans above and to the left."""

    def __init__(self):
        super().__init__()
        self.tables: list[list[tuple]] = []
        self.cell: dict | None = None

    def handle_starttag(self, tag, attrs):
        a = dict(attrs)
        if tag == "table":
            self.tables.append([])
            self.row, self.taken = -1, set()
        elif tag == "tr" and self.tables:
            self.row, self.col = int(a["data-r"]) if str(a.get("data-r", "")).isdigit() else self.row + 1, 0
        elif tag in ("td", "th") and self.tables:
            if str(a.get("data-c", "")).isdigit():  # a table with holes says where its cells are
                self.col = int(a["data-c"])
            while (self.row, self.col) in self.taken:
                self.col += 1
            span = lambda k: int(a[k]) if str(a.get(k, "")).isdigit() and int(a[k]) > 0 else 1
            self.cell = {"r": self.row, "c": self.col, "rs": span("rowspan"), "cs": span("colspan"), "h": tag == "th", "text": []}
            self.taken |= {(self.row + i, self.col + j) for i in range(self.cell["rs"]) for j in range(self.cell["cs"])}

    def handle_data(self, data):
        if self.cell is not None:
            self.cell["text"].append(data)

    def handle_endtag(self, tag):
        if tag in ("td", "th") and self.cell is not None:
            x, self.cell = self.cell, None
            self.tables[-1].append((x["r"], x["c"], x["rs"], x["cs"], " ".join("".join(x["text"]).split()), x["h"]))


def from_html(pages: DataFrame, key: str, html: str) -> DataFrame:
    """Grid cells of every table in a column of pages; a page's n-th table is ``key#n``."""

    def run(frames):
        for pdf in frames:
            rows = []
            for k, text in zip(pdf[key], pdf[html]):
                p = TableParser()
                p.feed(text or "")
                p.close()
                rows += [(f"{k}#{i}", *c) for i, t in enumerate(p.tables) for c in t]
            yield pd.DataFrame(rows, columns=["table_id", "r", "c", "rowspan", "colspan", "value", "is_header"])

    return pages.select(key, html).mapInPandas(run, GRID)


def to_html(grid: DataFrame) -> DataFrame:
    """(table_id, html): a grid as table markup with its spans; cells carry their place, as a grid may have holes."""
    from pyspark.sql import functions as F

    tag = F.when(F.col("is_header"), "th").otherwise("td")
    attr = lambda name: F.when(F.col(name) > 1, F.concat(F.lit(f' {name}="'), F.col(name).cast("string"), F.lit('"'))).otherwise("")
    cell = F.concat(F.lit("<"), tag, F.lit(' data-c="'), F.col("c").cast("string"), F.lit('"'), attr("rowspan"), attr("colspan"), F.lit(">"), F.coalesce("value", F.lit("")), F.lit("</"), tag, F.lit(">"))
    rows = grid.withColumn("cell", cell).groupBy("table_id", "r").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("c", "cell"))), lambda x: x["cell"]), "").alias("cells"))
    lines = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("r", "cells"))), lambda x: F.concat(F.lit('<tr data-r="'), x["r"].cast("string"), F.lit('">'), x["cells"], F.lit("</tr>"))), "")
    return rows.groupBy("table_id").agg(F.concat(F.lit("<table>"), lines, F.lit("</table>")).alias("html"))


class GridSource(DataSource):
    """``spark.read.format("grid").option("grids", json)``: small irregular tables given inline, one partition each.

    The option is a JSON object of table name to rows; a cell is a text, null, or
    ``{"v": text, "rs": rows, "cs": columns, "h": true}``.
    """

    @classmethod
    def name(cls):
        return "grid"

    def schema(self):
        return GRID

    def reader(self, schema):
        return GridReader(self.options.get("grids", "{}"))


class GridReader(DataSourceReader):
    def __init__(self, text: str):
        self.grids = json.loads(text)

    def partitions(self):
        return [InputPartition(k) for k in sorted(self.grids)] or [InputPartition(None)]

    def read(self, partition):
        for r, row in enumerate(self.grids.get(partition.value, [])):
            for c, cell in enumerate(row):
                if cell is not None:
                    d = cell if isinstance(cell, dict) else {"v": cell}
                    yield (partition.value, r, c, int(d.get("rs", 1)), int(d.get("cs", 1)), d.get("v"), bool(d.get("h", False)))
