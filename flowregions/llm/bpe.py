"""BPE encoding by backtracking over longest token matches, and decoding by an offset table.

A chain of tokens is the merge result of its string exactly when every token is the merge result of
its own string and every neighbouring pair is the merge result of the joined pair. So the encoder
walks the word from the left, takes the longest token (Aho-Corasick finds all tokens of the word in
one pass), accepts it only when the pair with the token before is compatible, and otherwise tries the
next shorter one or steps back. A position that failed once is never entered again: the time is
linear in the word.

Symbols: a byte is the character of its number; the last byte of a word is that character plus 256,
as word ends have symbols of their own in the vocabulary.
"""

from __future__ import annotations

import hashlib
import json
import unicodedata
from collections.abc import Iterator
from functools import lru_cache
from struct import pack

import numpy as np
from pyspark.sql import DataFrame

from flowregions.llm.common import give_back, text_batches

WORD_END = "</w>"
#: Chunks and words that a task keeps, and the longest that is kept.
CHUNKS, WORDS, CHUNK_CHARS = 250_000, 300_000, 48
#: Up to here, letters and their cases are the same in all Unicode versions.
LATIN = "\u024f"
#: Pairs kept in the compatibility table.
PAIRS = 1_000_000
#: Texts are encoded in slices of this many documents, so that few ids are in memory at once.
SLICE = 256


@lru_cache(maxsize=1)
def byte_symbols() -> dict[str, int]:
    """The printable character that byte-level vocabularies write for each byte -> the byte: printable Latin-1 stays itself, the rest follows from 256 up in order of the byte."""
    plain = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b]
    hidden = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(hidden)}


class Encoder:
    """One tokenizer file of the kind "byte-level BPE with word ends". ``spec`` is its JSON text."""

    def __init__(self, spec: str):
        import ahocorasick
        import regex
        import tokenizers
        import tokenizers.normalizers
        import tokenizers.pre_tokenizers

        spec = json.loads(spec)
        model = spec["model"]
        vocab, byte_of = model["vocab"], byte_symbols()
        self.form: dict[int, str] = {}
        for text, i in vocab.items():
            body, ends = (text[: -len(WORD_END)], True) if text.endswith(WORD_END) else (text, False)
            if len(body) == 1:
                self.form[i] = chr(byte_of[body] + 256 * ends)
        self.unit = {s: i for i, s in self.form.items()}
        self.merge: dict[tuple[int, int], tuple[int, int]] = {}
        for rank, pair in enumerate(model["merges"]):
            left, right = pair if isinstance(pair, list) else pair.split(" ")
            a, b, c = vocab[left], vocab[right], vocab[left + right]
            self.form[c] = self.form[a] + self.form[b]
            self.merge.setdefault((a, b), (rank, c))
        self.own: dict[int, bool] = {}
        self.fits: dict[tuple[int, int], bool] = {}
        self.finder = ahocorasick.Automaton()
        for i, s in self.form.items():
            self.finder.add_word(s, (len(s), i))
        self.finder.make_automaton()
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.split_special = regex.compile("(" + "|".join(map(regex.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        pattern = next(p for p in spec["pre_tokenizer"]["pretokenizers"] if p["type"] == "Split")["pattern"]["Regex"]
        self.words = regex.compile(pattern).findall
        self.normal = tokenizers.normalizers.Sequence([tokenizers.normalizers.NFC(), tokenizers.normalizers.Lowercase()]).normalize_str
        self.cut = tokenizers.pre_tokenizers.Split(tokenizers.Regex(pattern), "removed", invert=True).pre_tokenize_str
        self.space = regex.compile(r"\s+", regex.V1).split
        shown = {i: t for t, i in vocab.items()} | {i: t for t, i in self.special.items()}
        pieces = [(shown.get(i, "") + " ").encode() for i in range(max(shown) + 1)]
        self.offsets = np.concatenate([[0], np.cumsum([len(p) for p in pieces])]).astype(np.int64)
        self.letters = np.frombuffer(b"".join(pieces), dtype=np.uint8)
        self.cache: dict[str, bytes] = {}
        self.known: dict[str, bytes] = {}

    def merged(self, ids: list[int]) -> list[int]:
        """The plain merge loop, for the short strings of one token or one pair."""
        ids = list(ids)
        while len(ids) > 1:
            rank, at = min((self.merge.get(p, (1 << 60, 0))[0], k) for k, p in enumerate(zip(ids, ids[1:], strict=False)))
            if rank == 1 << 60:
                break
            ids[at : at + 2] = [self.merge[ids[at], ids[at + 1]][1]]
        return ids

    def whole(self, i: int) -> bool:
        """Whether merging the token's own symbols gives the token."""
        if (known := self.own.get(i)) is None:
            known = self.own[i] = self.merged([self.unit[s] for s in self.form[i]]) == [i]
        return known

    def pair(self, a: int, b: int) -> bool:
        """Whether a and b may stand side by side, from the table."""
        if (known := self.fits.get((a, b))) is None:
            if len(self.fits) > PAIRS:
                self.fits.clear()
            known = self.fits[a, b] = self.merged([self.unit[s] for s in self.form[a] + self.form[b]]) == [a, b]
        return known

    def word(self, symbols: str) -> list[int]:
        """The longest matches from the left, where all their pairs are compatible; else the way back."""
        chain = [i for _, (_, i) in self.finder.iter_long(symbols)]
        own, fits, before = self.own, self.fits, None
        for i in chain:
            if not (own.get(i) or self.whole(i)) or before is not None and not (fits[before, i] if (before, i) in fits else self.pair(before, i)):
                return self.backtracked(symbols)
            before = i
        return chain

    def backtracked(self, symbols: str) -> list[int]:
        n = len(symbols)
        starts: list[list[tuple[int, int]]] = [[] for _ in range(n)]
        for end, (size, i) in self.finder.iter(symbols):
            starts[end + 1 - size].append((size, i))  # ends come in order, so sizes do
        failed = bytearray(n + 1)
        chain: list[int] = []
        begins: list[int] = []
        left: list[int] = []  # matches not tried yet at each step of the chain
        at, untried = 0, len(starts[0]) if n else 0
        while at < n:
            found = False
            while untried:
                untried -= 1
                size, i = starts[at][untried]
                if not failed[at + size] and self.whole(i) and (not chain or self.pair(chain[-1], i)):
                    found = True
                    break
            if found:
                chain.append(i)
                begins.append(at)
                left.append(untried)
                at += size
                untried = len(starts[at]) if at < n else 0
            else:
                failed[at] = 1
                if not chain:
                    raise ValueError("the vocabulary lacks a byte")
                chain.pop()
                at, untried = begins.pop(), left.pop()
        return chain

    def chunk(self, text: str) -> bytes:
        """Ids of a text without white space, little-endian."""
        if not text or max(text) <= LATIN:
            words = self.words(unicodedata.normalize("NFC", text).lower())
        else:  # which characters are letters, and their lower case, depend on the Unicode version: the tokenizer's own tables decide
            words = [w for w, _ in self.cut(self.normal(text))]
        known, out = self.known, []
        for word in words:
            if (got := known.get(word)) is None:
                raw = word if word.isascii() else word.encode("utf-8", "surrogatepass").decode("latin-1")
                ids = self.word(raw[:-1] + chr(ord(raw[-1]) + 256))
                got = pack(f"<{len(ids)}I", *ids)
                if len(word) <= CHUNK_CHARS:
                    if len(known) >= WORDS:
                        known.clear()
                    known[word] = got
            out.append(got)
        return out[0] if len(out) == 1 else b"".join(out)

    def part(self, text: str) -> list[bytes]:
        pieces = self.space(text) if any(c in text for c in "\x1c\x1d\x1e\x1f") else text.split()
        cache, out = self.cache, []
        for p in pieces:
            if (got := cache.get(p)) is None:
                got = self.chunk(p)
                if len(p) <= CHUNK_CHARS:
                    if len(cache) >= CHUNKS:
                        cache.clear()
                    cache[p] = got
            out.append(got)
        return out

    def encode(self, text: str | None) -> np.ndarray:
        """Ids of a whole text; null is an empty text."""
        if not text:
            return np.zeros(0, dtype="<u4")
        if self.split_special is None or "<|" not in text and not any(s in text for s in self.special):
            return np.frombuffer(b"".join(self.part(text)), dtype="<u4")
        out: list[bytes] = []
        for k, piece in enumerate(self.split_special.split(text)):
            out += [np.array([self.special[piece]], dtype="<u4").tobytes()] if k % 2 else self.part(piece)
        return np.frombuffer(b"".join(out), dtype="<u4")

    def decode(self, ids: np.ndarray) -> bytes:
        """The tokens' text with a blank between, in UTF-8: one gather through the offset table."""
        ids = np.asarray(ids, dtype=np.int64)
        if not len(ids):
            return b""
        begin = self.offsets[ids]
        size = self.offsets[ids + 1] - begin
        ends = np.cumsum(size)
        where = np.arange(ends[-1]) + np.repeat(begin - (ends - size), size)
        return self.letters[where].tobytes()[:-1]


_ENCODERS: dict[str, Encoder] = {}


def encoder(spec: str, key: str) -> Encoder:
    """The task's encoder; a tenth of a second to build."""
    if key not in _ENCODERS:
        _ENCODERS.clear()
        _ENCODERS[key] = Encoder(spec)
    return _ENCODERS[key]


def _spec(docs: DataFrame, tokenizer: str):
    """The tokenizer file (a few MB, whatever the corpus) as a broadcast, so that executors need not see its path."""
    with open(tokenizer, encoding="utf-8") as f:
        text = f.read()
    return docs.sparkSession.sparkContext.broadcast((text, hashlib.sha256(text.encode()).hexdigest()))


def _mapped(docs: DataFrame, tokenizer: str, id_col: str, in_col: str, schema: str, make) -> DataFrame:
    import pyarrow as pa
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import StructType

    spec = _spec(docs, tokenizer)
    text_batches(docs.sparkSession)
    frame = docs.select(docs[id_col].alias("id"), docs[in_col].alias("value"))
    names = to_arrow_schema(StructType.fromDDL(f"{id_col} {frame.schema['id'].dataType.simpleString()}, {schema}"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = encoder(*spec.value)
        for batch in batches:
            for k in range(0, batch.num_rows, SLICE):
                part = batch.slice(k, SLICE)
                rows = [make(coder, x) for x in part.column(1).to_pylist()]
                columns = [pa.array([r[c] for r in rows], type=names.field(c + 1).type) for c in range(len(names) - 1)]
                yield pa.RecordBatch.from_arrays([part.column(0).cast(names.field(0).type), *columns], schema=names)
        del coder
        _ENCODERS.clear()  # tasks of other operators follow in this worker
        give_back()

    return frame.mapInArrow(run, StructType.fromDDL(f"{id_col} {frame.schema['id'].dataType.simpleString()}, {schema}"))


def encode(docs: DataFrame, tokenizer: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, ids array<long>) of every row: whole texts, null as empty. Repeated rows stay repeated; other columns are not read."""
    return _mapped(docs, tokenizer, id_col, text_col, "ids array<long>", lambda coder, text: (coder.encode(text).astype(np.int64),))


def decode(encoded: DataFrame, tokenizer: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """(id, text) of rows with ids; null ids give an empty text. An id outside the vocabulary is an error."""
    return _mapped(encoded, tokenizer, id_col, ids_col, "text string", lambda coder, ids: (coder.decode(np.array(ids or [], dtype=np.int64)).decode("utf-8", "replace"),))


def round_trip(docs: DataFrame, tokenizer: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Encodes and decodes every row in one pass over the texts: (id, n_tokens, ids_sha256, decoded_sha256).

    No shuffle: work follows the scan's splits, memory one slice of texts. Null and empty texts have
    0 tokens and the digests of nothing. Repeated rows stay repeated, rows without an id are encoded like
    others; very long texts are whole, in time linear in their length. An empty table gives no rows. No other
    column is read or returned, so names cannot clash.
    """

    def make(coder: Encoder, text: str | None) -> tuple[int, str, str]:
        ids = coder.encode(text)
        return len(ids), hashlib.sha256(ids.tobytes()).hexdigest(), hashlib.sha256(coder.decode(ids)).hexdigest()

    return _mapped(docs, tokenizer, id_col, text_col, "n_tokens long, ids_sha256 string, decoded_sha256 string", make)
