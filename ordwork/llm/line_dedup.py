"""Line deduplication by overlapping windows of three lines.

Non-blank lines (trimmed of spaces, tabs and carriage returns) are numbered in each document and every three
consecutive ones form a window, named by 128 hash bits. A window that also stands earlier (smaller id,
or same document and smaller line number) is a later occurrence; the lines under all later occurrences are merged
and go, blank lines and everything else stays.

All of it is DataFrame functions. First occurrences come from a partial aggregate, so a window that a third
of all documents share costs one row a task in the shuffle; only windows that do repeat are joined back, and that join may
be split by adaptive execution as one side has a row per window.

Defined results: rows with a null id or null text pass unchanged, as do texts of fewer than three non-blank
lines; rows that share an id but not the text are documents of their own, in the order of a hash of the text; rows that share both
are one document, none of them earlier than the other, and lose the same lines; an empty table gives
an empty table; columns that are not used pass through; `n_lines` and `n_removed` replace columns of those names.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ordwork.llm.common import Scratch, let, without

WINDOW = 3
BLANKS = " \t\r"


def lines_of(text):
    return F.split(text, "\n", -1)


def bare(line):
    return F.trim(line, F.lit(BLANKS))


def filled_lines(text):
    """Array of (i, line): the non-blank lines, trimmed, with their places among all lines."""
    numbered = F.transform(lines_of(text), lambda x, i: F.struct(i.alias("i"), bare(x).alias("line")))
    return F.filter(numbered, lambda x: x["line"] != "")


def windows(docs: DataFrame, text: str, key: str) -> DataFrame:
    """(id, t, at, h1, h2): a row for each window; t is a hash of the text, at holds the places of its lines among all lines of the text."""
    width = WINDOW

    def of(lines):
        last = F.size(lines) - width
        inside = lambda j: F.slice(lines, j + 1, width)
        name = lambda j: F.array_join(inside(j)["line"], "\n")
        made = F.transform(F.sequence(F.lit(0), last), lambda j: F.struct(inside(j)["i"].alias("at"), F.xxhash64(name(j)).alias("h1"), F.xxhash64(F.lit(1), name(j)).alias("h2")))
        return F.when(last >= 0, made)

    rows = docs.where(F.col(key).isNotNull() & F.col(text).isNotNull()).select(F.col(key).alias("id"), F.xxhash64(text).alias("t"), F.explode(let(filled_lines(F.col(text)), of)).alias("w"))
    return rows.select("id", "t", "w.at", "w.h1", "w.h2")


def repeated_lines(docs: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """(id, t, gone): for each document with later occurrences, the places of the lines that they cover."""
    rows = windows(docs, text, key)
    first = F.min(F.struct("id", "t", F.col("at")[0].alias("at"))).alias("first")
    firsts = rows.groupBy("h1", "h2").agg(first, F.count("*").alias("n")).where("n > 1").select("h1", "h2", "first")
    firsts = Scratch(docs.sparkSession, "lines").save(firsts, "repeated")
    later = rows.join(firsts, ["h1", "h2"]).where(F.struct("id", "t", F.col("at")[0].alias("at")) > F.col("first"))
    return later.select("id", "t", F.explode("at").alias("at")).groupBy("id", "t").agg(F.collect_set("at").alias("gone"))


def dedup_lines(docs: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """docs with the text that is left, n_lines (non-blank lines before) and n_removed."""
    base = without(docs, "n_lines", "n_removed")
    gone = repeated_lines(base, text, key).select(F.col("id").alias("__id"), F.col("t").alias("__t"), F.col("gone").alias("__gone"))
    joined = base.join(gone, (F.col(key) == F.col("__id")) & (F.xxhash64(text) == F.col("__t")), "left")

    def kept(lines):
        rest = F.array_except(F.sequence(F.lit(0), F.size(lines) - 1), F.col("__gone"))
        return F.array_join(F.transform(rest, lambda i: lines[i]), "\n")

    new = F.when(F.col("__gone").isNotNull(), let(lines_of(F.col(text)), kept)).otherwise(F.col(text))
    n_lines = F.when(F.col(text).isNull(), 0).otherwise(F.size(filled_lines(F.col(text))))
    n_removed = F.when(F.col("__gone").isNull(), 0).otherwise(F.size("__gone"))
    return joined.select(*[new.alias(c) if c == text else F.col(f"`{c}`") for c in base.columns], n_lines.cast("long").alias("n_lines"), n_removed.cast("long").alias("n_removed"))
