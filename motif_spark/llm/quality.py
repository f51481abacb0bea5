"""Line-first quality rules, in DataFrame functions only.

Lines are judged one by one (punctuation, navigation, boilerplate); failing lines go, and a document
that loses too large a share of its text, or keeps too few words, is rejected.

A line is navigation if separators stand between too many of its words, if it is one of a run of short lines
without sentence marks (a menu written downwards), or if it is a short line with a menu word at the top or the
bottom of the text. Boilerplate phrases and menu words are those of four languages.

Defined cases: a null or empty text has no words and is rejected; lines without a word are neutral, stay, and end
a run; rows are judged alone, so repeated rows get equal verdicts; a very long text is judged as any other, and
one long line as one line; a word count at a limit passes; columns of the input whose names clash with result
columns are not carried.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import words

SYMBOLS = "#*$%&|<>"
MIN_WORDS = 10
MAX_REPEAT_PERCENT = 20
WINDOW = 5
#: A line of this many words or more needs a sentence mark.
LONG_LINE = 8
#: More marks for each word than this is no prose.
MARKS_PER_WORD = 0.75
BARS_PER_WORD = 0.2
#: A boilerplate phrase fails only short lines.
SHORT_LINE = 14
MAX_LOST = 0.3
#: So many consecutive lines of at most so many words and no sentence mark are a menu.
RUN_LINES, RUN_WORDS = 4, 4
#: A menu word fails a line of at most so many words among so many first or last lines.
EDGE_LINES, EDGE_WORDS = 3, 6
# Sentence marks, phrases of boilerplate and words of menus in English, French, German and Spanish.
MARKS = ".!?:;,…\"'»”)。！？"
BOILERPLATE = (
    r"(?i)\b(cookies? policy|privacy policy|terms of (service|use)|all rights reserved|enable javascript|click here|sign up|log ?in|subscribe (now|to)|back to top|skip to content|read more"
    r"|tous droits r.serv.s|politique de confidentialit|conditions d.utilisation|en savoir plus|lire la suite"
    r"|alle rechte vorbehalten|datenschutzerkl.rung|nutzungsbedingungen|mehr erfahren|weiterlesen"
    r"|todos los derechos reservados|pol.tica de privacidad|t.rminos de uso|leer m.s)"
)
MENU = r"(?i)(^|[^a-z])(home|about us|contact( us)?|site ?map|menu|accueil|plan du site|startseite|impressum|kontakt|inicio|aviso legal|mapa del sitio|contacto)([^a-z]|$)"


def _strip(text: Column, chars: str) -> Column:
    return F.length(text) - F.length(F.translate(text, chars, ""))


def _window_hashes(w: Column) -> Column:
    """One hash for each window of five consecutive words, in order."""
    n = F.size(w)
    places = F.when(n >= WINDOW, F.sequence(F.lit(0), n - WINDOW)).otherwise(F.array().cast("array<int>"))
    return F.transform(places, lambda i: F.xxhash64(*[F.get(w, i + k) for k in range(WINDOW)]))


def with_repeat_words(df: DataFrame) -> DataFrame:
    """n_repeat_words from the column words: words inside windows found twice or more.

    Only texts with a repeated hash sort (hash, place) pairs, so no text costs more than n log n.
    """
    none = F.array().cast("array<struct<h:bigint,i:int>>")
    df = df.withColumn("_h", _window_hashes(F.col("_w")))
    pairs = F.sort_array(F.transform("_h", lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
    df = df.withColumn("_p", F.when(F.size(F.array_distinct("_h")) < F.size("_h"), pairs).otherwise(none))
    places = F.sort_array(F.transform(F.filter("_p", lambda p, j: _same(p, j - 1) | _same(p, j + 1)), lambda p: p["i"]))
    add = lambda a, p: F.struct((a["n"] + p + WINDOW - F.greatest(a["end"], p)).alias("n"), (p + WINDOW).alias("end"))
    start = F.struct(F.lit(0).alias("n"), F.lit(0).alias("end"))
    return df.withColumn("n_repeat_words", F.aggregate(places, start, add, lambda a: a["n"].cast("long"))).drop("_h", "_p")


def _same(p: Column, j: Column) -> Column:
    return F.coalesce(p["h"] == F.get("_p", j)["h"], F.lit(False))


def line_passes(line: Column, n: Column, marks: Column, in_run: Column, at_edge: Column) -> Column:
    """Verdict on one line of n words and so many marks; true for lines without a word."""
    bars, symbols = _strip(line, "|•›»"), _strip(line, SYMBOLS)
    punctuation = ((n < LONG_LINE) | (marks > 0)) & (marks + symbols <= F.greatest(F.lit(4.0), n * MARKS_PER_WORD))
    menu = (n <= EDGE_WORDS) & (marks == 0) & at_edge & line.rlike(MENU)
    navigation = (bars <= n * BARS_PER_WORD) & ~in_run & ~menu
    boilerplate = (n > SHORT_LINE) | ~line.rlike(BOILERPLATE)
    return (n == 0) | (punctuation & navigation & boilerplate)


def _in_run(lines: str, j: Column, i: Column) -> Column:
    """Whether line i is short and one of RUN_LINES such lines in a row."""
    short = lambda d: F.coalesce(F.get(lines, i + d)["short"], F.lit(False)) if d else F.lit(True)
    runs = F.lit(False)
    for first in range(1 - RUN_LINES, 1):
        whole = F.lit(True)
        for d in range(first, first + RUN_LINES):
            whole = whole & short(d)
        runs = runs | whole
    return j["short"] & runs


def assess(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: counts, base verdict, the method's verdict, and the text that passing lines leave.

    Columns: doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, kept,
    n_failed_lines, lost (share of word characters in failed lines), clean_text.
    """
    df = docs.select(F.col(id_col).alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("_t"))
    df = df.withColumns({"_w": words(F.col("_t")), "_lines": F.split("_t", "\n")})
    df = with_repeat_words(df.withColumns({"n_words": F.size("_w").cast("long"), "n_symbols": _strip(F.col("_t"), SYMBOLS).cast("long")}))
    dense = lambda line: F.length(F.translate(line, " \t\n\v\f\r", ""))
    counted = F.transform("_lines", lambda x: F.struct(x.alias("x"), F.size(words(x)).alias("n"), _strip(x, MARKS).alias("marks")))
    df = df.withColumn("_counted", F.transform(counted, lambda j: j.withField("short", (j["n"] > 0) & (j["n"] <= RUN_WORDS) & (j["marks"] == 0))))
    edge = lambda i: (i < EDGE_LINES) | (i >= F.size("_counted") - EDGE_LINES)
    passes = lambda j, i: line_passes(j["x"], j["n"], j["marks"], _in_run("_counted", j, i), edge(i))
    df = df.withColumn("_judged", F.transform("_counted", lambda j, i: F.struct(j["x"].alias("x"), dense(j["x"]).alias("c"), passes(j, i).alias("ok"))))
    full = F.transform(F.filter("_judged", lambda j: j["c"] > 0), lambda j: j["x"])
    total = lambda ok: F.aggregate(F.filter("_judged", lambda j: j["ok"] if ok else F.lit(True)), F.lit(0).cast("long"), lambda a, j: a + j["c"])
    df = df.withColumns({"_full": full, "word_chars": total(False), "_left": total(True), "n_failed_lines": F.size(F.filter("_judged", lambda j: ~j["ok"])).cast("long")})
    df = df.withColumns({
        "n_dup_lines": (F.size("_full") - F.size(F.array_distinct("_full"))).cast("long"),
        "base_failed": (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > MAX_REPEAT_PERCENT * F.col("n_words")),
        "lost": F.when(F.col("word_chars") > 0, 1 - F.col("_left") / F.col("word_chars")).otherwise(1.0),
        "clean_text": F.when(F.col("n_failed_lines") == 0, F.col("_t")).otherwise(F.array_join(F.transform(F.filter("_judged", lambda j: j["ok"]), lambda j: j["x"]), "\n")),
    })
    kept = ~F.col("base_failed") & (F.col("lost") <= MAX_LOST) & (F.size(words(F.col("clean_text"))) >= MIN_WORDS)
    out = F.struct("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", kept.alias("kept"), "n_failed_lines", "lost", "clean_text")
    # A filter on these columns would be pushed below the array expressions and repeat them for each element; one
    # on what an outer generator makes stays above it.
    return df.select(F.explode_outer(F.array(out)).alias("_r")).select("_r.*")


def keep_documents(docs: DataFrame) -> DataFrame:
    """The documents that pass, with their clean text; the columns stay those of the input."""
    held = F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_row")
    judged = assess(docs.select(held, "text"), "_row").filter("kept")
    r = lambda c: F.col("doc_id")[c]
    new = {"text": F.col("clean_text"), "n_chars": F.length("clean_text").cast("long")}
    return judged.select(*[new[c].alias(c) if c in new else r(c).alias(c) for c in docs.columns])
