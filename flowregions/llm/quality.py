"""Quality classifier: attention-based multiple-instance learning.

A document is a bag of passages of 64 words. Every passage of the whole text is encoded by what it says,
the sum of learned embeddings of its words and pairs of words (hashed into BUCKETS), and by the shapes of
its words (case, marks, repetition, lengths); a hidden layer turns both into a representation, gated
attention weighs the representations, and the document's score is a logistic function of the weighted one.
Labels exist for documents only: the attention learns which passages decide. Embeddings, hidden layer and
attention are fitted together.

Encoding works on whole batches of texts as byte arrays; nothing is done word by word in Python.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from flowregions.llm.common import give_back, text_batches

PASSAGE = 64
#: Labelled documents of each class that the model is fitted on, at most: those with the smallest hashes of their ids.
SAMPLE = 3_000
HIDDEN, GATE, EPOCHS, RATE, SEED = 24, 12, 20, 0.02, 11
#: Hash buckets of words and pairs of words, numbers an embedding has, and its part of the rate and of the weights' decay.
BUCKETS, EMBEDDED, SLOW, DECAY = 1 << 13, 8, 0.2, 1e-3
THRESHOLD = 0.7
#: Texts are encoded together up to so many letters: encoding takes about 70 bytes a letter.
CHUNK = 200_000

NAMES = ("upper", "lower", "digit", "marks", "other_marks", "pipes", "lines", "word_bytes", "upper_words", "marked_words", "same_as_last", "same_as_before_last", "distinct", "longest_repeat", "words", "short", "after", "empty")
D = len(NAMES)


def _class_table() -> np.ndarray:
    """For each byte: 0 blank, 1 upper case, 2 lower case or other letter, 3 digit, 4 sentence mark, 5 any other mark."""
    out = np.full(256, 5, dtype=np.uint8)
    for b in range(256):
        c = chr(b)
        out[b] = 0 if b <= 32 else 2 if b >= 128 or c.islower() else 1 if c.isupper() else 3 if c.isdigit() else 4 if c in ".,;:?'" else 5
    return out


CLASS = _class_table()


def buckets(codes: np.ndarray) -> np.ndarray:
    return ((codes * np.uint64(0xD1342543DE82EF95)) >> np.uint64(64 - BUCKETS.bit_length() + 1)).astype(np.uint16)


def encode(texts: list[str | None], passage: int = PASSAGE) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(shapes of all passages, number of passages of each text, buckets of words and pairs of words, number of these of each passage). A text without words is one empty passage."""
    raw = [(t or "").encode("utf-8", "replace") for t in texts]
    data = np.frombuffer(b"\n".join(raw) + b"\n", dtype=np.uint8)
    ends = np.cumsum([len(r) + 1 for r in raw])
    kind = CLASS[data]
    lead = np.flatnonzero(data[:-1] == 0xC3)  # letters of Latin-1: the byte behind tells the case
    lead = lead[(data[lead + 1] >= 0x80) & (data[lead + 1] <= 0x9E)]
    kind[lead] = 1
    small = data.copy()
    small[(data >= 65) & (data <= 90)] += 32
    small[lead + 1] += 32
    solid = kind != 0
    edge = np.diff(solid.astype(np.int8), prepend=0)
    begin, stop = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
    n_words = np.bincount(np.searchsorted(ends, begin, side="right"), minlength=len(raw))
    n_pass = np.maximum(1, -(-n_words // passage))
    out = np.zeros((int(n_pass.sum()), D))
    first_pass = np.cumsum(n_pass) - n_pass
    out[first_pass[n_words == 0], -1] = 1
    if not len(begin):
        return out, n_pass, np.zeros(0, dtype=np.uint16), np.zeros(len(out), dtype=np.int64)
    size = stop - begin
    word_of = np.repeat(np.arange(len(raw)), n_words)
    nth = np.arange(len(begin)) - np.repeat(np.cumsum(n_words) - n_words, n_words)
    group = first_pass[word_of] + nth // passage
    starts = np.flatnonzero(np.diff(group, prepend=-1))
    rows = group[starts]
    counts = np.diff(np.append(starts, len(group)))

    def per_word(flag: np.ndarray) -> np.ndarray:
        total = np.concatenate([[0], np.cumsum(flag, dtype=np.int64)])
        return total[stop] - total[begin]

    def per_passage(x: np.ndarray) -> np.ndarray:
        return np.add.reduceat(x.astype(np.float64), starts)

    upper, lower, digit, mark, odd = (per_word(kind == k) for k in (1, 2, 3, 4, 5))
    chars = per_passage(size)
    breaks = np.concatenate([[0], np.cumsum(data == 10, dtype=np.int64)])
    # a word's hash: sum of its bytes, in lower case, times odd powers of the place, in 64 bits
    place = np.arange(len(data)) - np.repeat(begin, np.diff(np.append(begin, len(data)))) if begin[0] == 0 else np.concatenate([np.zeros(begin[0], dtype=np.int64), np.arange(begin[0], len(data)) - np.repeat(begin, np.diff(np.append(begin, len(data))))])
    power = (np.uint64(0x9E3779B97F4A7C15) ** np.arange(1, 65, dtype=np.uint64))[place & 63]
    mixed = np.where(solid, small, 0).astype(np.uint64) * power
    summed = np.concatenate([np.zeros(1, dtype=np.uint64), np.cumsum(mixed, dtype=np.uint64)])
    code = summed[stop] - summed[begin]
    same1, same2 = np.zeros(len(code), dtype=bool), np.zeros(len(code), dtype=bool)
    same1[1:] = (code[1:] == code[:-1]) & (word_of[1:] == word_of[:-1])
    same2[2:] = (code[2:] == code[:-2]) & (word_of[2:] == word_of[:-2])
    order = np.lexsort((code, group))
    g, c = group[order], code[order]
    new = np.ones(len(c), dtype=bool)
    new[1:] = (g[1:] != g[:-1]) | (c[1:] != c[:-1])
    distinct = np.add.reduceat(new.astype(np.float64), starts)
    runs = np.diff(np.append(np.flatnonzero(new), len(new)))
    most = np.maximum.reduceat(runs, np.concatenate([[0], np.cumsum(distinct).astype(np.int64)[:-1]]))
    out[rows, 0] = per_passage(upper) / chars
    out[rows, 1] = per_passage(lower) / chars
    out[rows, 2] = per_passage(digit) / chars
    out[rows, 3] = per_passage(mark) / counts
    out[rows, 4] = per_passage(odd) / counts
    out[rows, 5] = per_passage((odd > 0) & (size == 1)) / counts
    out[rows, 6] = (breaks[stop[np.append(starts[1:], len(group)) - 1]] - breaks[begin[starts]]) / counts
    out[rows, 7] = chars / counts / 8
    out[rows, 8] = per_passage((upper >= 2) & (lower == 0)) / counts
    out[rows, 9] = per_passage((odd > 0) & (size > 1)) / counts
    out[rows, 10] = per_passage(same1) / counts
    out[rows, 11] = per_passage(same2) / counts
    out[rows, 12] = distinct / counts
    out[rows, 13] = most / counts
    out[rows, 14] = counts / passage
    out[rows, 15] = per_passage(size <= 3) / counts
    out[rows, 16] = (nth[starts] > 0).astype(float)
    last = np.concatenate([np.zeros(1, dtype=np.uint64), code[:-1]])
    last[nth == 0] = 0
    tokens = np.stack([buckets(code), buckets(code + last * np.uint64(0x9E3779B97F4A7C15))], axis=1).ravel()
    n_tokens = np.zeros(len(out), dtype=np.int64)
    n_tokens[rows] = 2 * counts
    return out, n_pass, tokens, n_tokens


@dataclass
class Model:
    mean: np.ndarray
    scale: np.ndarray
    w: dict[str, np.ndarray]

    def score(self, x: np.ndarray, bags: np.ndarray, tokens: np.ndarray, n_tokens: np.ndarray) -> np.ndarray:
        return forward(self.w, (x - self.mean) / self.scale, bags, tokens, n_tokens)[0]


def embedded(table: np.ndarray, tokens: np.ndarray, n_tokens: np.ndarray) -> np.ndarray:
    """Each passage's sum of its tokens' embeddings, over the root of their number."""
    out = np.zeros((len(n_tokens), table.shape[1]))
    some = np.flatnonzero(n_tokens)
    if len(some):
        start = (np.cumsum(n_tokens) - n_tokens)[some]
        out[some] = np.add.reduceat(table[tokens], start, axis=0) / np.sqrt(n_tokens[some])[:, None]
    return out


def forward(w: dict[str, np.ndarray], x: np.ndarray, bags: np.ndarray, tokens: np.ndarray, n_tokens: np.ndarray):
    """Scores of bags whose passages stand one after another; bags: their sizes."""
    start = np.cumsum(bags) - bags
    x = np.hstack([x, embedded(w["e"], tokens, n_tokens)])
    h = np.tanh(x @ w["w1"] + w["b1"])
    v, u = np.tanh(h @ w["v"]), 1 / (1 + np.exp(-(h @ w["u"])))
    a = (v * u) @ w["a"]
    e = np.exp(a - np.repeat(np.maximum.reduceat(a, start), bags))
    e /= np.repeat(np.add.reduceat(e, start), bags)
    z = np.add.reduceat(e[:, None] * h, start)
    p = 1 / (1 + np.exp(-np.clip(z @ w["c"] + w["c0"], -30, 30)))
    return p, x, h, v, u, e, z


def stretches(first: np.ndarray, size: np.ndarray) -> np.ndarray:
    """The numbers first[k] .. first[k] + size[k] - 1, one k after another."""
    return np.repeat(first - (np.cumsum(size) - size), size) + np.arange(size.sum())


def fit(x: np.ndarray, bags: np.ndarray, y: np.ndarray, tokens: np.ndarray | None = None, n_tokens: np.ndarray | None = None, seed: int = SEED, epochs: int = EPOCHS) -> Model:
    """Gradient descent (Adam) on the mean log loss with both classes of equal weight."""
    rng = np.random.default_rng(seed)
    tokens, n_tokens = (np.zeros(0, dtype=np.uint16), np.zeros(len(x), dtype=np.int64)) if tokens is None else (tokens, n_tokens)
    mean, scale = x.mean(axis=0), x.std(axis=0) + 1e-3
    x = (x - mean) / scale
    w = {"w1": rng.normal(0, 0.3, (D + EMBEDDED, HIDDEN)), "b1": np.zeros(HIDDEN), "v": rng.normal(0, 0.3, (HIDDEN, GATE)), "u": rng.normal(0, 0.3, (HIDDEN, GATE)), "a": rng.normal(0, 0.3, GATE), "c": rng.normal(0, 0.3, HIDDEN), "c0": np.zeros(1), "e": np.zeros((BUCKETS, EMBEDDED))}
    m, s = {k: np.zeros_like(p) for k, p in w.items()}, {k: np.zeros_like(p) for k, p in w.items()}
    weight = np.where(y == 1, 0.5 / max(1, (y == 1).sum()), 0.5 / max(1, (y == 0).sum()))
    first, first_token = np.cumsum(bags) - bags, np.cumsum(n_tokens) - n_tokens
    step = 0
    for _ in range(epochs):
        for some in np.array_split(rng.permutation(len(bags)), max(1, len(bags) // 256)):
            b = bags[some]
            at = stretches(first[some], b)
            n = n_tokens[at]
            mine = tokens[stretches(first_token[at], n)]
            p, xs, h, v, u, e, z = forward(w, x[at], b, mine, n)
            start = np.cumsum(b) - b
            d = (p - y[some]) * weight[some] / weight[some].sum()
            dz = d[:, None] * w["c"]
            g = {"c": z.T @ d, "c0": np.array([d.sum()])}
            dzr = np.repeat(dz, b, axis=0)
            de = (dzr * h).sum(axis=1)
            da = e * (de - np.repeat(np.add.reduceat(e * de, start), b))
            g["a"] = (v * u).T @ da
            dv, du = da[:, None] * w["a"] * u * (1 - v * v), da[:, None] * w["a"] * v * u * (1 - u)
            g["v"], g["u"] = h.T @ dv, h.T @ du
            dh = (e[:, None] * dzr + dv @ w["v"].T + du @ w["u"].T) * (1 - h * h)
            g["w1"], g["b1"] = xs.T @ dh, dh.sum(axis=0)
            each = (dh @ w["w1"][D:].T) / np.sqrt(np.maximum(n, 1))[:, None]
            g["e"] = np.stack([np.bincount(mine, weights=np.repeat(each[:, k], n), minlength=BUCKETS) for k in range(EMBEDDED)], axis=1)
            step += 1
            for k in w:
                grad = g[k] + (DECAY if k == "e" else 1e-4) * w[k]
                m[k] = 0.9 * m[k] + 0.1 * grad
                s[k] = 0.99 * s[k] + 0.01 * grad * grad
                w[k] = w[k] - RATE * (SLOW if k == "e" else 1.0) * (m[k] / (1 - 0.9**step)) / (np.sqrt(s[k] / (1 - 0.99**step)) + 1e-8)
    w["e"] = w["e"].astype(np.float32)
    return Model(mean, scale, w)


def held_out(ident: Column) -> Column:
    """Rows whose labels the model never sees: crc32 of the id as text leaves 2 modulo 4."""
    return F.coalesce(F.crc32(ident.cast("string").cast("binary")) % 4 == 2, F.lit(False))


def _sliced(texts: list[str | None]) -> Iterator[slice]:
    begin = size = 0
    for k, t in enumerate(texts):
        if size and size + len(t or "") > CHUNK:
            yield slice(begin, k)
            begin, size = k, 0
        size += len(t or "")
    if begin < len(texts):
        yield slice(begin, len(texts))


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", sample: int = SAMPLE) -> Model | None:
    """The model fitted on at most 2 * ``sample`` labelled documents that are not held out; None without both classes.

    ``sample`` bounds the labelled rows, each takes part with all its passages. Only their encodings come to the
    driver: about 4 bytes a word. Of rows with one id the least text stands for it, of labels with one id the least.
    """
    import pyarrow as pa

    text_batches(docs.sparkSession)
    known = labels.select(labels[id_col].alias("id"), labels["quality"].cast("int").alias("y")).filter("id is not null and y in (0, 1)")
    known = known.groupBy("id").agg(F.min("y").alias("y")).filter(~held_out(F.col("id")))
    parts = [known.filter(F.col("y") == k).orderBy(F.xxhash64("id", F.lit(SEED)), "id").limit(sample) for k in (0, 1)]
    chosen = parts[0].unionByName(parts[1])
    rows = docs.select(docs[id_col].alias("id"), docs[text_col].alias("text")).join(F.broadcast(chosen), "id")
    rows = rows.groupBy("id", "y").agg(F.min("text").alias("text"))

    def passages(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column("text").to_pylist()
            for part in _sliced(texts):
                x, n, tokens, n_tokens = encode(texts[part])
                ends = np.cumsum(n)
                words = np.concatenate([[0], np.cumsum(n_tokens)])
                out = ([x[b - k : b].astype("<f4").tobytes() for b, k in zip(ends, n, strict=True)], [tokens[words[b - k] : words[b]].astype("<u2").tobytes() for b, k in zip(ends, n, strict=True)], [n_tokens[b - k : b].astype("<u2").tobytes() for b, k in zip(ends, n, strict=True)])
                yield pa.RecordBatch.from_pydict({"id": batch.column("id").slice(part.start, len(n)).cast(pa.int64()), "y": batch.column("y").slice(part.start, len(n)).cast(pa.int32()), **{c: pa.array(o, pa.binary()) for c, o in zip(("x", "t", "nt"), out, strict=True)}})
        give_back()

    got = sorted((r["id"], r["y"], bytes(r["x"]), bytes(r["t"]), bytes(r["nt"])) for r in rows.select(F.col("id").cast("long").alias("id"), "text", "y").mapInArrow(passages, "id long, y int, x binary, t binary, nt binary").collect())
    y = np.array([r[1] for r in got], dtype=float)
    if not 0 < y.sum() < len(y):
        return None
    xs = [np.frombuffer(r[2], dtype="<f4").reshape(-1, D).astype(float) for r in got]
    tokens, n_tokens = (np.frombuffer(b"".join(r[c] for r in got), dtype="<u2") for c in (3, 4))
    return fit(np.concatenate(xs), np.array([len(x) for x in xs]), y, tokens, n_tokens.astype(np.int64))


def scores(docs: DataFrame, model: Model | None, id_col: str = "doc_id", text_col: str = "text", keep: tuple[str, ...] = ()) -> DataFrame:
    """The columns ``keep`` and ``score`` of every row, from the whole text alone.

    Null and empty texts are one passage without words. Without a model (no labels of both classes)
    every score is 1: nothing is known against a document. Repeated rows stay repeated.
    """
    import pyarrow as pa
    from pyspark.sql.types import DoubleType, StructField, StructType

    keep = keep or (id_col,)
    # by place, so that columns named like the score do not clash
    frame = docs.select(*[docs[c].alias(f"c{i}") for i, c in enumerate(keep)], docs[text_col].alias("_text"))
    if model is None:
        return frame.select(*[F.col(f"c{i}").alias(c) for i, c in enumerate(keep)], F.lit(1.0).alias("score"))
    sent = docs.sparkSession.sparkContext.broadcast(model)
    text_batches(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column("_text").to_pylist()
            for part in _sliced(texts):
                x, n, tokens, n_tokens = encode(texts[part])
                p = sent.value.score(x, n, tokens, n_tokens)
                yield pa.RecordBatch.from_arrays([*(batch.column(i).slice(part.start, len(p)) for i in range(len(keep))), pa.array(p, pa.float64())], names=[f"c{i}" for i in range(len(keep))] + ["score"])
        give_back()

    schema = StructType([StructField(f"c{i}", frame.schema[f"c{i}"].dataType) for i in range(len(keep))] + [StructField("score", DoubleType())])
    return frame.mapInArrow(run, schema).toDF(*keep, "score")


def classify(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """(id, held_out, score, predicted) of every row, from its whole text alone.

    Null and empty texts are one passage without words and get a score like others; so do rows without an id,
    which count as not held out. Repeated rows stay repeated and score alike. Very long texts are encoded by
    themselves. Without labels of both classes every score is 1; an empty table gives no rows. No other column is
    read or returned, so names cannot clash.
    """
    scored = scores(docs, train(docs, labels, id_col, text_col), id_col, text_col)
    return scored.select(id_col, held_out(F.col(id_col)).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))
