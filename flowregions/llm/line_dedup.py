"""Line dedup by winnowing over line hashes.

The lines of a document that are not blank are hashed after normalising, once; all else works on these
hashes. Of every ``run`` lines in a row the least hash is a fingerprint (the last of equal ones), so a
repeated run of that length always has a fingerprint in common with its earlier copy, at the same place
of the run. Fingerprints that stand at one position only are dropped. Around each of the others the match
is extended left and right to the windows that it is the minimum of; positions with equal windows are
joined to the earliest of them (smallest id, then line), and neighbouring windows that follow the same
earlier document in step grow into one maximal run. Deletions are taken from these runs: their lines go, save
those that belong to the first occurrence itself where the two overlap.

Two independent 64-bit hashes of a line, and of a window, stand for the text. All of it is DataFrame work:
a common line or passage only adds to minima, it is never paired, and hot ones do not meet in one task.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from flowregions.llm.common import cut, hot_join, table

RUN = 3
#: Words that make a run of fewer lines a passage of its own, for callers that ask for it.
WORDS = 50
#: Documents whose deletions may be broadcast when the text is put together again, and lines deleted in them.
BROADCAST_DOCS, BROADCAST_LINES = 100_000, 1_000_000


def lines(text: Column) -> Column:
    return F.split(F.coalesce(text, F.lit("")), "\n")


def normal(line: Column) -> Column:
    """Lower case, runs of blanks as one, none at the ends."""
    return F.trim(F.regexp_replace(F.lower(line), r"[\x00-\x20]+", " "))


def hashed(docs: DataFrame, id_col: str, text_col: str, words: int | None = None) -> DataFrame:
    """(id, n, h, g, c): numbers, both hashes and words of a document's lines that are not blank; written once."""
    rows = docs.select(docs[id_col].alias("id"), docs[text_col].alias("text")).filter("id is not null and text is not null")
    rows = rows.select("id", F.filter(F.transform(lines(F.col("text")), lambda x, i: F.struct(i.alias("n"), normal(x).alias("x"))), lambda s: s["x"] != "").alias("all"))
    count = (lambda x: F.lit(0)) if words is None else (lambda x: F.size(F.split(x, " ")))  # noqa: ARG005
    each = lambda make: F.transform("all", lambda s: make(s))
    rows = rows.select("id", each(lambda s: s["n"]).alias("n"), each(lambda s: F.xxhash64(s["x"])).alias("h"), each(lambda s: F.xxhash64(F.lit("second"), s["x"])).alias("g"), each(lambda s: count(s["x"])).alias("c"))
    return table(rows.filter(F.size("n") > 0))


def windows(found: DataFrame, run: int, words: int | None = None) -> DataFrame:
    """(id, at, len, place, print, content, more, numbers): each window of ``found`` lines, its length, the place and hash of its fingerprint, both hashes of its content and its line numbers.

    Windows have ``run`` lines; with ``words`` also fewer, where these have so many words.
    """
    spans = lambda k: F.when(F.size("h") >= k, F.transform(F.sequence(F.lit(0), F.size("h") - k), lambda at: F.struct(at.alias("at"), F.lit(k).alias("len")))).otherwise(F.array().cast("array<struct<at:int,len:int>>"))
    many = lambda k: F.filter(spans(k), lambda s: F.aggregate(F.slice("c", s["at"] + 1, k), F.lit(0), lambda a, x: a + x) >= words)
    kinds = [spans(run)] + ([] if words is None else [many(k) for k in range(1, run)])
    rows = found.select("id", "n", "h", "g", F.explode(F.concat(*kinds)).alias("w")).select("id", "n", "h", "g", "w.at", "w.len")
    part = lambda c: F.slice(c, F.col("at") + 1, F.col("len"))
    least = F.array_min(F.transform(part("h"), lambda x, i: F.struct(x.alias("h"), (-i).alias("i"))))
    rows = rows.withColumn("least", least)
    return rows.select("id", "at", "len", (F.col("at") - F.col("least.i")).alias("place"), F.col("least.h").alias("print"), F.xxhash64(part("h")).alias("content"), F.xxhash64(part("g")).alias("more"), part("n").alias("numbers"))


def repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", run: int = RUN, words: int | None = None) -> DataFrame:
    """(id, at, len, numbers, first struct<id, at>): windows that stood somewhere earlier, with their earliest position; ``at`` counts lines that are not blank."""
    found = hashed(docs, id_col, text_col, words)
    total = found.agg(F.sum(F.size("n"))).first()[0] or 0
    every = windows(found, run, words)
    place = F.struct("id", "place")
    prints = every.groupBy("print", "len").agg(F.min(place).alias("low"), F.max(place).alias("high"), F.count("*").alias("many")).filter("low != high").select("print", "len", "many")
    near = cut(hot_join(every, prints, ["print", "len"], total, ["id", "at"]).select("id", "at", "len", "content", "more", "numbers"))
    here = F.struct("id", "at")
    first = near.groupBy("content", "more", "len").agg(F.min(here).alias("first"), F.max(here).alias("last"), F.count("*").alias("many")).filter("first != last").drop("last")
    joined = hot_join(near, first, ["content", "more", "len"], total, ["id", "at"])
    return joined.filter((F.col("id") != F.col("first.id")) | (F.col("at") != F.col("first.at"))).select("id", "at", "len", "numbers", "first")


def grown(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", run: int = RUN, words: int | None = None) -> DataFrame:
    """(id, at, len, first_id, first_at, gone): maximal repeated runs, in lines that are not blank: windows that keep step with one earlier document, grown together.

    ``gone`` has the line numbers of the run, save those that belong to the first occurrence where the two overlap.
    """
    rows = repeats(docs, id_col, text_col, run, words)
    overlap = F.when(F.col("id") == F.col("first.id"), F.greatest(F.lit(0), F.col("first.at") + F.col("len") - F.col("at"))).otherwise(0)
    rows = rows.select("id", "at", (F.col("at") + F.col("len")).alias("stop"), F.col("first.id").alias("first_id"), (F.col("at") - F.col("first.at")).alias("shift"), F.slice("numbers", overlap + 1, F.col("len")).alias("own"))
    step = Window.partitionBy("id", "first_id", "shift").orderBy("at", "stop")
    before = F.max("stop").over(step.rowsBetween(Window.unboundedPreceding, -1))
    begins = rows.withColumn("new", F.coalesce((F.col("at") > before).cast("int"), F.lit(1)))
    island = begins.withColumn("island", F.sum("new").over(step.rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    whole = island.groupBy("id", "first_id", "shift", "island").agg(F.min("at").alias("at"), F.max("stop").alias("stop"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("own")))).alias("gone"))
    return whole.select("id", "at", (F.col("stop") - F.col("at")).alias("len"), "first_id", (F.col("at") - F.col("shift")).alias("first_at"), "gone")


def runs(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", run: int = RUN, words: int | None = None) -> DataFrame:
    """(id, at, len, first_id, first_at): the maximal repeated runs."""
    return grown(docs, id_col, text_col, run, words).drop("gone")


def deletions(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", run: int = RUN, words: int | None = None) -> DataFrame:
    """(id, gone): the numbers (from 0) of the lines to delete, of documents that lose some: those of their maximal repeated runs."""
    gone = grown(docs, id_col, text_col, run, words).select("id", F.explode("gone").alias("n"))
    return cut(gone.groupBy("id").agg(F.array_sort(F.collect_set("n")).alias("gone")))


def deduplicate(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", run: int = RUN, words: int | None = None) -> DataFrame:
    """All columns of every row, ``text`` without later repeated runs, and ``n_lines`` and ``n_removed``.

    A document without repeats keeps its text unchanged, blank lines and all. Null and empty texts
    stay as they are and have no lines; rows without an id pass unchanged; rows with one id count as
    one document. Runs shorter than ``run`` lines stay, but with ``words`` those of so many words or
    more go too; the first occurrence of a line always stays (ties of equal lines in one document: the
    earlier one). A document that is all repeats keeps its blank lines only. Very long texts are whole
    arrays of hashes in one row. An empty table gives no rows. Columns of ``docs`` that are named n_lines
    or n_removed give way to the results; all other names are kept apart.
    """
    found = deletions(docs, id_col, text_col, run, words)
    size = found.agg(F.count("*"), F.sum(F.size("gone"))).first()
    found = found.select(F.col("id").alias("_id"), F.col("gone").alias("_gone"))
    if size[0] <= BROADCAST_DOCS and (size[1] or 0) <= BROADCAST_LINES:
        found = F.broadcast(found)
    names = [c for c in docs.columns if c not in ("n_lines", "n_removed")]
    rows = docs.select(F.struct(*[docs[c] for c in names]).alias("_row"), docs[id_col].alias("_key")).join(found, F.col("_key") == F.col("_id"), "left")
    text = F.col("_row")[text_col]
    kept = F.array_except(F.sequence(F.lit(0), F.size("_lines") - 1), F.col("_gone"))
    whole = F.when(F.col("_gone").isNull(), text).otherwise(F.array_join(F.transform(kept, lambda i: F.get("_lines", i)), "\n"))
    rows = rows.withColumn("_lines", lines(text))
    out = [whole.alias(c) if c == text_col else F.col("_row")[c].alias(c) for c in names]
    return rows.select(*out, F.when(F.coalesce(text, F.lit("")) == "", 0).otherwise(F.size("_lines")).alias("n_lines"), F.coalesce(F.size("_gone"), F.lit(0)).alias("n_removed"))
