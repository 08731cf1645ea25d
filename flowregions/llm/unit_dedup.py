"""Substring dedup by hashing lines, sentences and stretches of words.

Units are a text's lines (a paragraph is a run of them), inside long lines its sentences, and, so that
passages set into the middle of a sentence are met too, stretches of words whose ends the words
themselves decide: an end is a pair of words whose hash is the least within REACH pairs on either side, a
unit reaches over two such stretches. Equal passages have equal ends, wherever they stand. A unit's digest
is taken after normalising (lower case, blanks as one); of all units with one digest in the corpus the
earliest (smallest id, then offset) stays, the rest are repeats. Repeats that touch or overlap make one
span; spans of LEAST_WORDS words or more go, with their original offsets kept. Shorter ones (a greeting,
the name of a licence) stay: short lines recur without being copied.

A task already drops what repeats among its own units, so a common unit reaches the shuffle once for
each batch and not once for each occurrence.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from flowregions.llm.common import give_back, text_batches
from flowregions.llm.set_join import mix

#: The shortest units that count, in words; a short one may repeat by chance.
LINE_WORDS, SENTENCE_WORDS = 3, 8
#: The shortest repeated span that is removed, in words.
LEAST_WORDS = 20
#: Pairs of words on either side that an end of a stretch is least among.
REACH = 4
#: Units of a batch, and words whose hashes a task keeps.
BATCH, KEPT_WORDS = 200_000, 150_000

_SENTENCE = re.compile(r"[^.!?]+[.!?]*")
_LINE = re.compile(r"[^\n]+")
_WORD = re.compile(r"\S+")


def units(text: str | None, line_words: int = LINE_WORDS, sentence_words: int = SENTENCE_WORDS) -> Iterator[tuple[int, int, int]]:
    """(start, end, digest) of the units of a text; offsets in characters, blanks at the ends left out."""
    for line in _LINE.finditer(text or ""):
        body, start = line.group(), line.start()
        words = body.lower().split()
        if len(words) >= line_words:
            yield _unit(body, start, words)
        if len(words) > sentence_words:
            for part in _SENTENCE.finditer(body):
                if part.end() - part.start() < len(body):
                    words = part.group().lower().split()
                    if len(words) >= sentence_words:
                        yield _unit(part.group(), start + part.start(), words)
    yield from stretches(text)


class _Codes(dict):
    """Word -> 64-bit digest."""

    def __missing__(self, word: str) -> int:
        if len(self) >= KEPT_WORDS:
            self.clear()
        code = self[word] = int.from_bytes(hashlib.blake2b(word.encode("utf-8", "replace"), digest_size=8).digest(), "little")
        return code


_CODES = _Codes()


def stretches(text: str | None, reach: int = REACH) -> Iterator[tuple[int, int, int]]:
    """(start, end, digest) of units of two neighbouring stretches of words."""
    words = (text or "").lower().split()
    n = len(words) - 1
    if n < 4 * reach:
        return
    codes = np.fromiter(map(_CODES.__getitem__, words), dtype=np.uint64, count=n + 1)
    pair = mix(codes[:-1] * np.uint64(0x9E3779B97F4A7C15) + codes[1:])
    inner = pair[reach : n - reach]
    least = np.ones(len(inner), dtype=bool)
    for k in range(1, reach + 1):
        least &= (inner < pair[reach - k : n - reach - k]) & (inner <= pair[reach + k : n - reach + k])
    ends = np.flatnonzero(least) + reach + 1  # the word behind the pair's first
    if len(ends) < 3:
        return
    spans = [m.span() for m in _WORD.finditer(text)]
    for a, b in zip(ends[:-2].tolist(), ends[2:].tolist(), strict=True):
        yield spans[a][0], spans[b - 1][1], int.from_bytes(hashlib.blake2b(codes[a:b].tobytes(), digest_size=8).digest(), "little", signed=True)


def _unit(body: str, start: int, words: list[str]) -> tuple[int, int, int]:
    digest = int.from_bytes(hashlib.blake2b(" ".join(words).encode("utf-8", "replace"), digest_size=8).digest(), "little", signed=True)
    return start + len(body) - len(body.lstrip()), start + len(body.rstrip()), digest


def repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", line_words: int = LINE_WORDS, sentence_words: int = SENTENCE_WORDS) -> DataFrame:
    """(id, spans array<struct<start, end>>) of documents with repeated units: the units' places, in order."""
    import pyarrow as pa

    text_batches(docs.sparkSession)
    schema = "digest long, id long, start int, stop int, known boolean"
    names = [f.split()[0] for f in schema.split(", ")]
    texts = docs.select(docs[id_col].cast("long").alias("id"), docs[text_col].alias("text")).filter("id is not null and text is not null")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        first: dict[int, tuple[int, int, int]] = {}
        gone: list[tuple] = []

        def rows() -> pa.RecordBatch:
            out = [(d, *u, False) for d, u in first.items()] + gone
            first.clear()
            gone.clear()
            types = (pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.bool_())
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True) if out else [[]] * 5, types, strict=True)], names)

        for batch in batches:
            for ident, text in zip(batch.column("id").to_pylist(), batch.column("text").to_pylist(), strict=True):
                for start, stop, digest in units(text, line_words, sentence_words):
                    new = (ident, start, stop)
                    old = first.setdefault(digest, new)
                    if old[:2] != new[:2]:
                        first[digest] = min(old, new)
                        lost = max(old, new)
                        # any key will do for a unit that is known to go: its own place spreads them
                        gone.append((hash((lost[0], lost[1])), *lost, True))
                if len(first) + len(gone) >= BATCH:
                    yield rows()
        yield rows()
        _CODES.clear()
        give_back()

    found = texts.mapInArrow(run, schema)
    here = F.when(~F.col("known"), F.struct("id", "start"))
    ranked = found.withColumn("first", F.min(here).over(Window.partitionBy("digest")))
    lost = ranked.filter(F.col("known") | (F.struct("id", "start") != F.col("first"))).select("id", "start", "stop").distinct()
    return lost.groupBy("id").agg(F.array_sort(F.collect_list(F.struct("start", F.col("stop").alias("end")))).alias("spans"))


def merged(text: str, spans: list, least_words: int = LEAST_WORDS) -> list[tuple[int, int]]:
    """Spans in order of their start, grown together over overlaps and blanks, without those of fewer words than ``least_words``."""
    out: list[list[int]] = []
    for s in spans:
        if out and (s["start"] <= out[-1][1] or not text[out[-1][1] : s["start"]].strip()):
            out[-1][1] = max(out[-1][1], s["end"])
        else:
            out.append([s["start"], s["end"]])
    return [(a, b) for a, b in out if len(text[a:b].split()) >= least_words]


def deduplicate(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", least_words: int = LEAST_WORDS, **how) -> DataFrame:
    """(id, text, n_removed, spans) of every row: the text without its repeated spans, their number, and their offsets (characters) in the original text.

    Null texts stay null, empty texts empty, with no spans. Rows without an id pass unchanged; rows
    with one id and one text count as one document, and of equal units within one text the first stays.
    Very long texts are whole rows. An empty table gives no rows. No other column is read or returned, so
    names cannot clash.
    """
    import pyarrow as pa

    found = repeats(docs, id_col, text_col, **how).select(F.col("id").alias("_id"), "spans")
    rows = docs.select(docs[id_col].cast("long").alias("id"), docs[text_col].cast("string").alias("text"))
    rows = rows.join(found, F.col("id") == F.col("_id"), "left").select("id", "text", "spans")
    schema = "id long, text string, n_removed int, spans array<struct<start:int,end:int>>"

    def cut_out(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts, n, kept = batch.column("text").to_pylist(), [], []
            spans = batch.column("spans").to_pylist()
            for k, (text, some) in enumerate(zip(texts, spans, strict=True)):
                some = merged(text, some, least_words) if some and text is not None else []
                n.append(len(some))
                kept.append([{"start": a, "end": b} for a, b in some])
                at, out = 0, []
                for a, b in some:
                    out.append(text[at:a])
                    at = b
                if some:
                    texts[k] = "".join([*out, text[at:]])
            span = pa.list_(pa.struct([pa.field("start", pa.int32()), pa.field("end", pa.int32())]))
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(texts, pa.string()), pa.array(n, pa.int32()), pa.array(kept, span)], ["id", "text", "n_removed", "spans"])

    return rows.mapInArrow(cut_out, schema).withColumnRenamed("id", id_col).withColumnRenamed("text", text_col)
