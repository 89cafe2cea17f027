"""Tables of HTML pages as raw cells: an Arrow pass over html.parser, tolerant of broken markup."""

from __future__ import annotations

import re
from collections.abc import Iterator
from html.parser import HTMLParser

import pyarrow as pa
from pyspark.sql import DataFrame

CELLS = "array<struct<r:int,c:int,rs:int,cs:int,text:string,is_th:boolean>>"
#: The HTML standard's bound of a colspan. A rowspan ends with its group of rows at the latest, so it needs none; 0 means just that.
MOST_COLUMNS = 1000


class TableParser(HTMLParser):
    """Collects tables; nested ones go into their cell's text, or stand alone with nested="split"."""

    def __init__(self, nested: str = "text"):
        super().__init__(convert_charrefs=True)
        self.nested, self.done, self.open, self.skip = nested, [], [], 0

    def handle_starttag(self, tag, attrs):
        if tag in ("script", "style"):
            self.skip += 1
        if tag == "table":
            if self.open and self.nested == "text":
                self.open[-1]["depth"] += 1
            else:
                self.open.append({"depth": 0, "rows": [], "groups": [], "group": 0, "caption": "", "cell": None, "in_caption": False})
        if not self.open or self.open[-1]["depth"]:
            return
        now = self.open[-1]
        if tag == "caption":
            now["in_caption"] = True
        elif tag in ("thead", "tbody", "tfoot"):
            self.end_cell(now)
            now["group"] += 1
        elif tag == "tr":
            self.end_cell(now)
            self.begin_row(now)
        elif tag in ("td", "th"):
            self.end_cell(now)
            if not now["rows"] or now["groups"][-1] != now["group"]:
                self.begin_row(now)
            held = dict(attrs)
            now["cell"] = [self.span(held.get("rowspan"), 0), min(MOST_COLUMNS, self.span(held.get("colspan"), 1)), [], tag == "th"]
        elif tag == "br" and now["cell"]:
            now["cell"][2].append(" ")

    @staticmethod
    def span(text: str | None, least: int) -> int:
        """The number a span begins with, at least `least`; 1 where there is none. No table has more than so many rows."""
        digits = re.match(r"\s*\+?(\d{1,9})", text or "")
        return max(least, int(digits[1])) if digits else 1

    @staticmethod
    def begin_row(now):
        now["rows"].append([])
        now["groups"].append(now["group"])

    @staticmethod
    def end_cell(now):
        if now["cell"]:
            now["rows"][-1].append(now["cell"])
            now["cell"] = None

    def handle_endtag(self, tag):
        if tag in ("script", "style"):
            self.skip = max(0, self.skip - 1)
        if not self.open:
            return
        now = self.open[-1]
        if tag == "table":
            if now["depth"]:
                now["depth"] -= 1
            else:
                self.end_cell(now)
                self.done.append(self.open.pop())
        elif not now["depth"]:
            if tag == "caption":
                now["in_caption"] = False
            elif tag in ("td", "th", "tr"):
                self.end_cell(now)
            elif tag in ("thead", "tbody", "tfoot"):
                self.end_cell(now)
                now["group"] += 1

    def handle_data(self, data):
        if self.skip or not self.open:
            return
        now = self.open[-1]
        if now["in_caption"]:
            now["caption"] += data
        elif now["cell"]:
            now["cell"][2].append(data)

    def tables(self, html: str) -> list[tuple[str, list[dict]]]:
        self.feed(html)
        self.close()
        while self.open:  # a table left open ends with the page
            self.end_cell(self.open[-1])
            self.done.append(self.open.pop())
        out = []
        for found in self.done:
            cells = []
            ends = {g: r + 1 for r, g in enumerate(found["groups"])}  # where each group of rows ends
            covered: dict[int, int] = {}  # column: the row up to which a cell above covers it
            for r, row in enumerate(found["rows"]):
                c = 0
                for rs, cs, parts, head in row:
                    while covered.get(c, 0) > r:
                        c += 1
                    left = ends[found["groups"][r]] - r
                    rs = min(rs, left) if rs else left
                    for j in range(cs):
                        covered[c + j] = max(covered.get(c + j, 0), r + rs)
                    cells.append({"r": r, "c": c, "rs": rs, "cs": cs, "text": " ".join("".join(parts).split()), "is_th": head})
                    c += cs
            out.append((" ".join(found["caption"].split()), cells))
        return out


def extract_tables(pages: DataFrame, nested: str = "text") -> DataFrame:
    """(doc_id, table_id, caption, cells) of all tables of (page_id, url, html). A page without tables gives no row."""
    arrow = pa.list_(pa.struct([("r", pa.int32()), ("c", pa.int32()), ("rs", pa.int32()), ("cs", pa.int32()), ("text", pa.string()), ("is_th", pa.bool_())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            docs, ids, captions, cells = [], [], [], []
            for url, html in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                if html and "<table" in html.lower():
                    for k, (caption, found) in enumerate(TableParser(nested).tables(html)):
                        docs.append(url)
                        ids.append(f"{url}#{k}")
                        captions.append(caption)
                        cells.append(found)
            yield pa.RecordBatch.from_arrays([pa.array(docs, pa.string()), pa.array(ids, pa.string()), pa.array(captions, pa.string()), pa.array(cells, arrow)], ["doc_id", "table_id", "caption", "cells"])

    return pages.select("url", "html").mapInArrow(run, f"doc_id string, table_id string, caption string, cells {CELLS}")
