"""Workbooks (.xlsx) as cells: values, number formats and styled runs, read with the standard library alone.

A workbook is a zip of XML parts. A row of the result is a non-blank cell under its sheet's header row; runs
of a styled text come out in the same HTML-like syntax that `richtext` reads. One file is one task's work.
"""

from __future__ import annotations

import io
import posixpath
import re
import zipfile
from collections.abc import Iterator
from xml.etree import ElementTree
from xml.sax.saxutils import escape

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sheetgraph.operators.cells import CELL_COLUMNS
from sheetgraph.session import prepare

SCHEMA = "sheet_id string, row_id string, col string, style_key string, kind string, s string, n double, b boolean, format_class string, rich string"
MAIN = "{http://schemas.openxmlformats.org/spreadsheetml/2006/main}"
LINK = "{http://schemas.openxmlformats.org/officeDocument/2006/relationships}id"
# The file format's own numbers of date and of date-time formats
DATES, DATETIMES = frozenset((14, 15, 16, 17)), frozenset((18, 19, 20, 21, 22, 45, 46, 47))
# end of fixed values


class Unreadable(ValueError):
    """A file that is no workbook."""


def format_class(number: int, code: str | None) -> str | None:
    """date, datetime, bool or None of a number format."""
    if code is None:
        return "date" if number in DATES else "datetime" if number in DATETIMES else None
    if re.fullmatch(r'"(yes|ja|true|wahr)";.*"(no|nein|false|falsch)".*', code, re.I):
        return "bool"
    plain = re.sub(r'"[^"]*"|\[[^\]]*\]|\\.', "", code).lower()
    if re.search("[hs]", plain):
        return "datetime"
    return "date" if re.search("[yd]", plain) else None


def _text(item) -> tuple[str, str | None]:
    """Plain text of a string item, and its styled form where a run has a style."""
    runs = item.findall(f"{MAIN}r")
    if not runs:
        return "".join(t.text or "" for t in item.iter(f"{MAIN}t")), None
    plain, rich, styled = [], [], False
    for run in runs:
        t = "".join(x.text or "" for x in run.findall(f"{MAIN}t"))
        shown, style = escape(t), run.find(f"{MAIN}rPr")
        for tag in ("strike", "u", "i", "b") if style is not None else ():
            mark = style.find(MAIN + tag)
            if mark is not None and mark.get("val") not in ("0", "false", "none"):
                shown, styled = f"<{tag}>{shown}</{tag}>", True
        color = style.find(f"{MAIN}color") if style is not None else None
        rgb = color.get("rgb") if color is not None else None
        if rgb and rgb[-6:] != "000000":
            shown, styled = f'<font color="#{rgb[-6:].lower()}">{shown}</font>', True
        plain.append(t)
        rich.append(shown)
    return "".join(plain), "".join(rich) if styled else None


def _column(reference: str) -> int:
    out = 0
    for c in re.match("[A-Z]+", reference).group():
        out = out * 26 + ord(c) - 64
    return out


def read(name: str, content: bytes) -> Iterator[tuple]:
    """The cells of every sheet; Unreadable where the bytes are no workbook."""
    try:
        with zipfile.ZipFile(io.BytesIO(content)) as z:
            names = set(z.namelist())

            def part(path: str):
                return ElementTree.fromstring(z.read(path)) if path in names else None

            book, links = part("xl/workbook.xml"), part("xl/_rels/workbook.xml.rels")
            if book is None or links is None:
                raise Unreadable(f"{name}: no workbook part")
            targets = {r.get("Id"): posixpath.normpath(posixpath.join("xl", r.get("Target"))) if r.get("Target")[0] != "/" else r.get("Target")[1:] for r in links}
            shared = part("xl/sharedStrings.xml")
            strings = [] if shared is None else [_text(x) for x in shared.findall(f"{MAIN}si")]
            styles = part("xl/styles.xml")
            classes: list[str | None] = [None]
            if styles is not None:
                codes = {int(f.get("numFmtId")): f.get("formatCode") for f in styles.iter(f"{MAIN}numFmt")}
                classes = [format_class(int(x.get("numFmtId", 0)), codes.get(int(x.get("numFmtId", 0)))) for x in styles.findall(f"{MAIN}cellXfs/{MAIN}xf")] or classes
            sheets = [(s.get("name"), part(targets[s.get(LINK)])) for s in book.iter(f"{MAIN}sheet") if targets.get(s.get(LINK)) in names]
    except (zipfile.BadZipFile, ElementTree.ParseError, KeyError, EOFError) as e:
        raise Unreadable(f"{name}: {e}") from e
    for title, sheet in sheets:
        header: dict[int, str] = {}
        for row in sheet.iter(f"{MAIN}row"):
            for c in row.findall(f"{MAIN}c"):
                at, kind, v = _column(c.get("r")), c.get("t", "n"), c.find(f"{MAIN}v")
                plain, rich = (None, None)
                if kind == "s" and v is not None:
                    plain, rich = strings[int(v.text)]
                elif kind == "inlineStr":
                    plain, rich = _text(c.find(f"{MAIN}is"))
                elif kind == "str" and v is not None:
                    plain = v.text
                if not header or row.get("r") == "1":
                    header[at] = plain if plain is not None else (v.text if v is not None else "")
                    continue
                if at not in header or (v is None and not plain):
                    continue
                n = b = fmt = None
                if kind == "b":
                    b = v.text == "1"
                elif kind == "n" and v is not None:
                    n, style = float(v.text), int(c.get("s", 0))
                    fmt = classes[style] if style < len(classes) else None
                    if fmt == "bool":
                        n, b, fmt = None, n != 0, None
                if n is None and b is None and not plain:
                    continue
                yield f"{name}/{title}", row.get("r"), header[at], None, "B" if b is not None else "N" if n is not None else "S", plain, n, b, fmt, rich


def cells(spark: SparkSession, path: str, skip_unreadable: bool = False) -> DataFrame:
    """Cells of all workbooks under a path, sheets named file/sheet."""
    prepare(spark)
    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.xlsx").option("recursiveFileLookup", "true").load(path)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds = (pa.string(),) * 6 + (pa.float64(), pa.bool_(), pa.string(), pa.string())
        for batch in batches:
            for file, content in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                try:
                    rows = list(read(posixpath.basename(file), content))
                except Unreadable:
                    if not skip_unreadable:
                        raise
                    continue
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], names=list(CELL_COLUMNS))

    return files.select("path", "content").mapInArrow(run, SCHEMA)


def funnel(spark: SparkSession, path: str) -> DataFrame:
    """Files listed, fetched (not empty), parseable, and kept: a header without blanks or repeats, and a cell under it."""
    prepare(spark)
    files = spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(path)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for file, content in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                parsed = kept = False
                try:
                    rows = list(read(posixpath.basename(file), content)) if content else []
                    parsed = bool(content)
                    kept = bool(rows) and all(r[2] and r[2].strip() for r in rows) and len({(r[0], r[1], r[2]) for r in rows}) == len(rows)
                except Unreadable:
                    parsed = False
                out.append((bool(content), parsed, kept))
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.bool_()) for c in zip(*out)], names=["fetched", "parsed", "kept"])

    each = files.select("path", "content").mapInArrow(run, "fetched boolean, parsed boolean, kept boolean")
    listed = F.lit(len(files.inputFiles())).cast("long")  # the reader leaves out files without a byte
    return each.agg(*[F.count_if(c).alias(c) for c in ("fetched", "parsed", "kept")]).select(listed.alias("listed"), "fetched", "parsed", "kept")


def write(sheets: dict[str, list[list]]) -> bytes:
    """A workbook of small sheets: text, styled text in tags, numbers, booleans, (number, format code)."""
    from sheetgraph.sources.markup import runs_xml

    codes = sorted({v[1] for rows in sheets.values() for row in rows for v in row if isinstance(v, tuple)})
    out = io.BytesIO()
    space = 'xmlns="http://schemas.openxmlformats.org/spreadsheetml/2006/main"'
    with zipfile.ZipFile(out, "w", zipfile.ZIP_DEFLATED) as z:
        names = list(sheets)
        z.writestr("xl/workbook.xml", f'<workbook {space} xmlns:r="{LINK[1:-3]}"><sheets>' + "".join(f'<sheet name="{escape(n)}" sheetId="{k}" r:id="r{k}"/>' for k, n in enumerate(names, 1)) + "</sheets></workbook>")
        z.writestr("xl/_rels/workbook.xml.rels", "<Relationships>" + "".join(f'<Relationship Id="r{k}" Target="worksheets/sheet{k}.xml"/>' for k in range(1, len(names) + 1)) + "</Relationships>")
        formats = "".join(f"<numFmt numFmtId=\"{164 + k}\" formatCode=\"{escape(c, {chr(34): '&quot;'})}\"/>" for k, c in enumerate(codes))
        z.writestr("xl/styles.xml", f'<styleSheet {space}><numFmts>{formats}</numFmts><cellXfs><xf numFmtId="0"/>' + "".join(f'<xf numFmtId="{164 + k}"/>' for k in range(len(codes))) + "</cellXfs></styleSheet>")

        def cell(r: int, c: int, v) -> str:
            ref, k = "", c
            while k:
                k, rest = divmod(k - 1, 26)
                ref = chr(65 + rest) + ref
            at = f'r="{ref}{r}"'
            if v is None or v == "":
                return ""
            if isinstance(v, bool):
                return f'<c {at} t="b"><v>{int(v)}</v></c>'
            if isinstance(v, tuple):
                return f'<c {at} s="{1 + codes.index(v[1])}"><v>{v[0]!r}</v></c>'
            if isinstance(v, str):
                return f'<c {at} t="inlineStr"><is>{runs_xml(v)}</is></c>'
            return f"<c {at}><v>{v!r}</v></c>"

        for k, n in enumerate(names, 1):
            rows = "".join(f'<row r="{r}">' + "".join(cell(r, c, v) for c, v in enumerate(row, 1)) + "</row>" for r, row in enumerate(sheets[n], 1))
            z.writestr(f"xl/worksheets/sheet{k}.xml", f"<worksheet {space}><sheetData>{rows}</sheetData></worksheet>")
    return out.getvalue()
