"""Line rules and licence notices on made texts, against plain Python and SQL."""

from __future__ import annotations

import re

import duckdb
import pandas as pd
from pyspark.sql import functions as F

from motif_spark.llm import license, quality, sql

PROSE = "This is a plain sentence of enough words to be kept here, and it goes on."
MENUS = ["Home", "About us", "Products", "News and events"]


def passes(lines: list[str], i: int) -> bool:
    """One line's verdict, written anew."""
    words = [re.findall(r"[^\x20\x09-\x0D]+", x) for x in lines]
    marks = [sum(c in quality.MARKS for c in x) for x in lines]
    short = [0 < len(w) <= 4 and not m for w, m in zip(words, marks)]
    n, x = len(words[i]), lines[i]
    if not n:
        return True
    first = last = i
    while first > 0 and short[first - 1]:
        first -= 1
    while last + 1 < len(lines) and short[last + 1]:
        last += 1
    if short[i] and last - first + 1 >= 4:
        return False
    if n <= 6 and not marks[i] and (i < 3 or i >= len(lines) - 3) and re.search(quality.MENU, x):
        return False
    symbols = sum(c in quality.SYMBOLS for c in x)
    if n >= 8 and not marks[i] or marks[i] + symbols > max(4.0, n * 0.75) or sum(c in "|•›»" for c in x) > n * 0.2:
        return False
    return n > 14 or not re.search(quality.BOILERPLATE, x)


TEXTS = [
    "\n".join([PROSE, *MENUS, PROSE]),
    "\n".join([PROSE, *MENUS[:3], PROSE]),
    "\n".join([PROSE, *MENUS[:2], "", *MENUS[2:], PROSE]),
    "\n".join([*MENUS, PROSE, PROSE]),
    "\n".join(["Kontakt", PROSE, PROSE, "Impressum"]),
    "\n".join([PROSE, PROSE, PROSE, PROSE, "Kontakt to be kept", PROSE, PROSE, PROSE, PROSE]),
    "\n".join([PROSE, "Tous droits réservés", "Datenschutzerklärung", "Leer más", PROSE, PROSE]),
    "\n".join([PROSE, "One.", "Two.", "Three.", "Four.", "Five.", PROSE]),
    "\n".join(["short", "lines", "only", "here"] * 40),
    "a | b | c | d\n" + PROSE,
    "", None, "\n\n\n", PROSE,
]


def frame(spark):
    return spark.createDataFrame([(i, x) for i, x in enumerate(TEXTS)], "doc_id long, text string")


def test_line_verdicts(spark):
    for r in quality.assess(frame(spark)).collect():
        lines = (TEXTS[r.doc_id] or "").split("\n")
        failed = [i for i in range(len(lines)) if not passes(lines, i)]
        assert r.n_failed_lines == len(failed), (r.doc_id, failed)
        assert r.clean_text == ("\n".join(x for i, x in enumerate(lines) if i not in failed) if failed else TEXTS[r.doc_id] or "")


def test_sql_of_made_lines_and_notices(spark):
    notices = [text for _, text, _ in license.NOTICES]
    texts = TEXTS + notices + [f"Some words before. {n.capitalize()} and after" for n in notices] + [n.replace("4 0", "3 1").replace("version 2 0", "version 1 1") for n in notices]
    df = spark.createDataFrame([(i, x) for i, x in enumerate(texts)], "doc_id long, text string")
    con = duckdb.connect()
    con.register("documents", pd.DataFrame({"doc_id": range(len(texts)), "text": texts}))
    for found, statement in ((quality.assess(df).drop("lost", "clean_text"), sql.QUALITY), (license.scan(df), sql.LICENSE)):
        a, b = found.toPandas(), con.sql(statement).df()
        cols = sorted(a.columns)
        key = lambda t: sorted(tuple(str(round(float(v), 6)) if isinstance(v, float) else str(v) for v in r) for r in t[cols].astype(object).where(t[cols].notna(), None).itertuples(index=False))
        norm = lambda t: t.assign(**{c: t[c].astype("float64") for c in cols if t[c].dtype.kind in "if"})
        assert key(norm(a)) == key(norm(b))


def test_every_notice_is_named(spark):
    rows = [(i, text) for i, (_, text, _) in enumerate(license.NOTICES)]
    got = {r.doc_id: r for r in license.scan(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    for i, (label, text, phrase) in enumerate(license.NOTICES):
        assert got[i].score == 1.0
        assert (label in got[i].labels.split(",")) == (f" {phrase} " in f" {text} ")
    other = spark.createDataFrame([(1, "Licensed under CC BY-NC 3.0"), (2, "Licensed under the GNU General Public Licence, a text")], "doc_id long, text string")
    labels = {r.doc_id: r.labels for r in license.scan(other).collect()}
    assert labels[1] == "cc-by-nc" and labels[2] == ""
