"""Exact Jaccard join of documents on word shingles, by partitioning the universe of shingles.

Pigeonhole. Two sets of sizes a and b at the threshold differ in at most H = floor((1-t)/(1+t) (a+b))
shingles. The universe is cut into m segments by hash, m fixed per size band (powers of two), so each
difference spoils one segment. A set with more than H non-empty segments therefore shares at least
(non-empty - H) whole segments with every partner, and with all its segments put in one global
order, rarest first, it shares one of its first H + 1 (frequent segments get allocation 0, the rarest
allocation 1). A set with too few non-empty segments gets allocation 2 on all: it is also indexed by
the one-deletion neighbourhoods of its segments, among other such sets. A set near the upper end of
its band is posted in the next band's segments too.

1. Each task hashes its documents and packs segment signatures into buckets; equal sets of one
   document or more are one class, keyed by the digest of the set.
2. Each bucket counts its signatures; those of one class alone are dropped.
3. Each class keeps its rarest shared signatures, or drops out when too few are shared.
4. In every signature's group all classes are compared with a centre (exact, on the sets). Where
   that leaves a group unconnected, the classes outside the main component are compared with all of
   their cluster, in blocks.
5. Components of the links.

The number of buckets grows with the text. Signatures that are frequent in a small sample (in 1 % of it) bypass
the buckets; the sample steers work only, results do not depend on it. A signature that is less frequent than that
and yet in many documents makes its bucket larger by one entry for each task and class it is in. Allocation is by
frequency: at the registered density every set has more segments than a partner can spoil, so allocations 0 and 1
suffice, and the one-deletion neighbourhoods serve sets whose shingles fall into few segments only.
Hashes of shingles and digests have 64 bits.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from flowregions.llm.common import cut, give_back, hot_join, table, text_batches

WIDTH, NUMERATOR, DENOMINATOR = 5, 75, 100
#: Segments for each shingle of the largest set of a band; bands below TOKENS have a segment for each shingle.
DENSITY, TOKENS = 0.4, 64
#: Signatures packed together by a task, letters behind one bucket, classes compared together by a task.
FLUSH, BUCKET_LETTERS, COMPARED = 200_000, 10_000_000, 2_000
#: A bucket's signatures are sorted and counted in so many slices, as sorting takes several times the memory of what is sorted.
SLICES = 8
#: Classes of a block that is compared with another.
BLOCK = 600
#: Sampled documents, and the number of them a signature must be in to bypass the buckets.
SAMPLE, OFTEN = 1_500, 15
#: Ids that may be broadcast (8 bytes each).
BROADCAST_IDS = 1_000_000
KEPT_WORDS = 150_000

U = np.uint64


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (splitmix)."""
    x = (x ^ (x >> U(30))) * U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U(27))) * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


class Words(dict):
    """Word -> 64-bit digest; kept for a task, up to KEPT_WORDS."""

    def __missing__(self, word: bytes) -> int:
        if len(self) >= KEPT_WORDS:
            self.clear()
        code = self[word] = int.from_bytes(hashlib.blake2b(word, digest_size=8).digest(), "little")
        return code


_WORDS = Words()


def shingles(text: str | None, width: int = WIDTH) -> np.ndarray:
    """The sorted distinct hashes of a whole text's shingles: words between blanks, A-Z in lower case; a shorter text is one shingle, a text without words none."""
    words = (text or "").encode("utf-8", "replace").lower().split()
    if not words:
        return np.zeros(0, dtype=U)
    codes = np.fromiter(map(_WORDS.__getitem__, words), dtype=U, count=len(words))
    n = max(1, len(codes) - width + 1)
    total = np.zeros(n, dtype=U)
    factor = 0x9E3779B97F4A7C15
    for k in range(min(width, len(codes))):
        total += codes[k : k + n] * U(factor)
        factor = factor * 0xD1342543DE82EF95 % 2**64 | 1
    return np.unique(mix(total + U(min(width, len(codes)))))


def digest(hashes: np.ndarray) -> int:
    return int.from_bytes(hashlib.blake2b(hashes.tobytes(), digest_size=8).digest(), "little", signed=True)


def differences(a: int, b: int, num: int, den: int) -> int:
    return (den - num) * (a + b) // (den + num)


def signatures(hashes: np.ndarray, num: int = NUMERATOR, den: int = DENOMINATOR, density: float = DENSITY, tokens: int = TOKENS) -> Iterator[tuple[int, int, np.ndarray]]:
    """(scheme, how many signatures a partner must share at least, signatures) for each band the set is posted in.

    Where that number would be below 1, the set's partners may share no whole segment; then another
    scheme (numbered from 64) has its segments' one-deletion neighbourhoods.
    """
    s = len(hashes)
    band = s.bit_length() - 1
    largest = s * den // num
    for scheme in (band, band + 1) if largest >= 1 << (band + 1) else (band,):
        most = min(largest, (2 << band) - 1) if scheme == band else largest
        h = differences(s, most, num, den)
        top = 2 << scheme
        if top <= tokens:
            yield scheme, max(1, s - h), mix(hashes + U(scheme + 1))
            continue
        m = int(np.ceil(density * top))
        own = U((scheme + 1) * 0xC2B2AE3D27D4EB4F % 2**64)
        segment = ((hashes >> U(32)) * U(m)) >> U(32)
        start = np.flatnonzero(np.diff(segment, prepend=U(m)))
        base = segment[start] * U(0x9E3779B97F4A7C15) + own
        inner = mix(hashes)
        total = np.add.reduceat(inner, start)
        yield scheme, max(1, len(start) - h), mix(total + base)
        if len(start) <= h:
            count = np.diff(np.append(start, s))
            empty = np.setdiff1d(np.arange(m, dtype=U), segment[start]) * U(0x9E3779B97F4A7C15) + own
            around = np.concatenate([total + base, np.repeat(total + base, count) - inner, empty])
            yield scheme + 64, 1, np.unique(mix(around + U(64)))


def bucket_of(codes: np.ndarray, buckets: int) -> np.ndarray:
    return (((codes >> U(32)) * U(buckets)) >> U(32)).astype(np.int64)


def name_of(codes: np.ndarray, bucket: np.ndarray | int) -> np.ndarray:
    """One number of the bucket and the low 48 bits, which is what stays of a signature. Two signatures of one name only cost a comparison."""
    return (codes & U(0xFFFFFFFFFFFF)) ^ mix(np.atleast_1d(np.asarray(bucket)).astype(U) + U(1))


def six(codes: np.ndarray) -> bytes:
    return np.ascontiguousarray(codes.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :6]).tobytes()


def unsix(data: bytes) -> np.ndarray:
    out = np.zeros((len(data) // 6, 8), dtype=np.uint8)
    out[:, :6] = np.frombuffer(data, dtype=np.uint8).reshape(-1, 6)
    return out.view("<u8").ravel()


def runs(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and lengths of the runs of equal rows."""
    start = np.flatnonzero(np.any(np.diff(x, axis=0) != 0, axis=1)) + 1 if x.ndim > 1 else np.flatnonzero(np.diff(x)) + 1
    start = np.concatenate([[0], start]).astype(np.int64)
    return start, np.diff(np.append(start, len(x)))


#: Rows between the steps: what they hold, for which bucket, and arrays as bytes. RECORDS (class, scheme,
#: size, shared signatures needed), POSTINGS (signatures by class), DOCS (id, size, class), SHARED (signatures with their counts).
RECORDS, POSTINGS, DOCS, SHARED = 0, 1, 2, 3
PACKED = "kind int, part int, x binary, y binary, z binary, w binary"
ROWS = "kind int, a long, b long, c long, d long"


def _packed(rows: list[tuple]):
    import pyarrow as pa

    columns = list(zip(*rows, strict=True)) if rows else [[]] * 6
    types = (pa.int32(), pa.int32(), pa.binary(), pa.binary(), pa.binary(), pa.binary())
    return [pa.array(c, t) for c, t in zip(columns, types, strict=True)], [f.split()[0] for f in PACKED.split(", ")]


def _joined(column, kind: str) -> np.ndarray:
    return np.frombuffer(b"".join(x for x in column.to_pylist() if x), dtype=kind)


class Packer:
    """Collects a task's documents and packs their signatures by bucket."""

    def __init__(self, buckets: int, often: np.ndarray, how: dict):
        self.buckets, self.often, self.how, self.turn = buckets, often, how, 0
        self.clear()

    def clear(self) -> None:
        self.docs, self.records, self.codes, self.seen, self.size = [], [], [], set(), 0

    def add(self, ident: int | None, hashes: np.ndarray) -> None:
        key = digest(hashes) if len(hashes) else 0
        self.docs.append((ident, len(hashes), key))
        if ident is None or not len(hashes) or key in self.seen:
            return
        self.seen.add(key)
        for scheme, need, codes in signatures(hashes, **self.how):
            self.records.append((key, scheme, len(hashes), need))
            self.codes.append(codes)
            self.size += len(codes)

    def rows(self) -> Iterator[tuple]:
        if not self.docs:
            return
        self.turn += 1
        ident = np.array([d[0] if d[0] is not None else np.iinfo(np.int64).min for d in self.docs], dtype="<i8")
        yield DOCS, (hash(tuple(ident[:8].tolist())) + self.turn) % self.buckets, ident.tobytes(), np.array([d[1] for d in self.docs], dtype="<i8").tobytes(), np.array([d[2] for d in self.docs], dtype="<i8").tobytes(), None
        if not self.records:
            return
        records = np.array(self.records, dtype=np.int64)
        home = bucket_of(records[:, 0].view(U), self.buckets)
        order = np.argsort(home, kind="stable")
        for some in np.split(order, np.flatnonzero(np.diff(home[order])) + 1):
            yield RECORDS, int(home[some[0]]), *(records[some, c].astype("<i8").tobytes() for c in range(4))
        codes, of = np.concatenate(self.codes), np.repeat(np.arange(len(records)), [len(c) for c in self.codes])
        if len(self.often):
            at = np.minimum(np.searchsorted(self.often[0], codes), len(self.often[0]) - 1)
            hot = self.often[0][at] == codes
            if hot.any():
                yield from shared_rows(records[of[hot], 0], records[of[hot], 1], self.often[1][at[hot]].astype(np.int64) + 2**31, name_of(codes[hot], bucket_of(codes[hot], self.buckets)), self.buckets)
                codes, of = codes[~hot], of[~hot]
        if not len(codes):
            return
        bucket = bucket_of(codes, self.buckets)
        order = np.argsort(bucket, kind="stable")
        bucket, codes, of = bucket[order], codes[order], of[order]
        start, size = runs(bucket)
        for a, n in zip(start, size, strict=True):
            r, length = runs(of[a : a + n])
            mine = records[of[a : a + n][r]]
            yield POSTINGS, int(bucket[a]), mine[:, 0].astype("<i8").tobytes(), mine[:, 1].astype(np.uint8).tobytes(), length.astype("<u4").tobytes(), six(codes[a : a + n])


def shared_rows(key: np.ndarray, scheme: np.ndarray, count: np.ndarray, name: np.ndarray, buckets: int) -> Iterator[tuple]:
    """Rows of kind SHARED, by the classes' buckets."""
    home = bucket_of(key.view(U), buckets)
    order = np.lexsort((scheme, key, home))
    key, scheme, count, name, home = key[order], scheme[order], count[order], name[order], home[order]
    start, size = runs(home)
    for a, n in zip(start, size, strict=True):
        r, length = runs(np.stack([key[a : a + n], scheme[a : a + n]], axis=1))
        head = np.stack([key[a : a + n][r], scheme[a : a + n][r], length], axis=1).astype("<i8")
        yield SHARED, int(home[a]), head.tobytes(), count[a : a + n].astype("<u4").tobytes(), name[a : a + n].astype("<u8").tobytes(), None


def count_bucket(tab, buckets: int) -> Iterator[tuple]:
    """Step 2 of one bucket: signatures of two classes or more."""
    bucket = tab.column("part")[0].as_py()
    run_key, run_scheme, length = _joined(tab.column("x"), "<i8"), _joined(tab.column("y"), np.uint8), _joined(tab.column("z"), "<u4")
    codes = np.concatenate([unsix(x) for x in tab.column("w").to_pylist()])
    of = np.repeat(np.arange(len(run_key), dtype=np.int32), length)
    slice_ = ((codes & U(0xFFFFFFFF)) * U(SLICES) >> U(32)).astype(np.uint8)
    for k in range(SLICES):
        mine = slice_ == k
        yield from count_slice(codes[mine], of[mine], run_key, run_scheme, bucket, buckets)


def count_slice(codes: np.ndarray, of: np.ndarray, run_key: np.ndarray, run_scheme: np.ndarray, bucket: int, buckets: int) -> Iterator[tuple]:
    """Of some signatures of a bucket, with all that equal them, those of two classes or more."""
    if not len(codes):
        return
    order = np.argsort(codes, kind="stable")
    codes, of = codes[order], of[order]
    start, size = runs(codes)
    keep = np.repeat(size > 1, size)
    codes, key, scheme = codes[keep], run_key[of[keep]], run_scheme[of[keep]].astype(np.int64)
    order = np.lexsort((key, codes))
    codes, key, scheme = codes[order], key[order], scheme[order]
    once = np.ones(len(codes), dtype=bool)
    once[1:] = (codes[1:] != codes[:-1]) | (key[1:] != key[:-1])
    codes, key, scheme = codes[once], key[once], scheme[once]
    if not len(codes):
        return
    start, size = runs(codes)
    count = np.repeat(size, size)
    keep = count > 1
    if keep.any():
        yield from shared_rows(key[keep], scheme[keep], np.minimum(count[keep], 2**31 - 1), name_of(codes[keep], bucket), buckets)


def choose(tab) -> tuple[np.ndarray, ...]:
    """Step 3 of one bucket of classes: (kind, a, b, c, d) rows: documents, and the rarest shared signatures of classes that can have a partner."""
    kind = tab.column("kind").to_numpy()
    out = []
    some = tab.filter(kind == DOCS)
    if some.num_rows:
        ident, size, key = (_joined(some.column(c), "<i8") for c in "xyz")
        out.append((np.full(len(ident), DOCS), ident, size, key, np.zeros(len(ident), dtype=np.int64)))
    some, more = tab.filter(kind == RECORDS), tab.filter(kind == SHARED)
    if some.num_rows and more.num_rows:
        records = np.unique(np.stack([_joined(some.column(c), "<i8") for c in "xyzw"], axis=1), axis=0)
        head = _joined(more.column("x"), "<i8").reshape(-1, 3)
        count, name = _joined(more.column("y"), "<u4").astype(np.int64), _joined(more.column("z"), "<u8")
        pair = np.concatenate([records[:, :2], head[:, :2]])
        _, ident = np.unique(pair, axis=0, return_inverse=True)
        ident = ident.ravel()
        row_of = np.zeros(ident.max() + 1, dtype=np.int64)
        row_of[ident[: len(records)]] = np.arange(len(records))
        of = np.repeat(row_of[ident[len(records) :]], head[:, 2])
        order = np.lexsort((name, count, of))
        of, count, name = of[order], count[order], name[order]
        once = np.ones(len(of), dtype=bool)  # a class met in several tasks may bring a frequent signature several times
        once[1:] = (of[1:] != of[:-1]) | (name[1:] != name[:-1])
        of, count, name = of[once], count[once], name[once]
        start, size = runs(of)
        rank = np.arange(len(of)) - np.repeat(start, size)
        need = records[of, 3]
        keep = rank <= np.repeat(size, size) - need
        weight = np.repeat(size, size)
        if keep.any():
            out.append((np.full(keep.sum(), SHARED), name[keep].view(np.int64), records[of[keep], 0], records[of[keep], 2], weight[keep]))
    return tuple(np.concatenate([o[c] for o in out]) for c in range(5)) if out else tuple(np.zeros(0, dtype=np.int64) for _ in range(5))


def _frequent(texts: DataFrame, how: dict) -> np.ndarray:
    """Signatures of OFTEN or more of SAMPLE documents, sorted, and their counts: at most a few 10,000."""
    import pyarrow as pa

    chosen = texts.select("id").filter("id is not null").orderBy(F.xxhash64("id", F.lit(5)), "id").limit(SAMPLE).dropDuplicates()

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for text in batch.column("text").to_pylist():
                hashes = shingles(text, how["width"])
                if len(hashes):
                    codes = np.concatenate([c for _, _, c in signatures(hashes, **{k: v for k, v in how.items() if k != "width"})])
                    yield pa.RecordBatch.from_pydict({"code": pa.array(codes.view(np.int64))})

    rows = texts.join(F.broadcast(chosen), "id").select("text").mapInArrow(sign, "code long").groupBy("code").count().filter(F.col("count") >= OFTEN).collect()
    rows = sorted((int(np.int64(r[0]).view(U)), r[1]) for r in rows)
    return (np.array([r[0] for r in rows], dtype=U), np.array([r[1] for r in rows], dtype=np.int64)) if rows else ()


def candidates(texts: DataFrame, how: dict) -> DataFrame:
    """Steps 1 to 3: ROWS from (id, text), written to the shared folder."""
    import pyarrow as pa

    text_batches(texts.sparkSession)
    letters = texts.agg(F.sum(F.length("text"))).first()[0] or 0
    buckets = int(max(16, -(-letters // BUCKET_LETTERS)))
    often = texts.sparkSession.sparkContext.broadcast(_frequent(texts, how))
    width, rest = how["width"], {k: v for k, v in how.items() if k != "width"}

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        packer = Packer(buckets, often.value, rest)
        for batch in batches:
            for ident, text in zip(batch.column("id").to_pylist(), batch.column("text").to_pylist(), strict=True):
                packer.add(ident, shingles(text, width))
                if packer.size >= FLUSH or len(packer.docs) >= 20_000:
                    yield pa.RecordBatch.from_arrays(*_packed(list(packer.rows())))
                    packer.clear()
        yield pa.RecordBatch.from_arrays(*_packed(list(packer.rows())))
        packer.clear()
        _WORDS.clear()
        give_back()

    def count(tab: pa.Table) -> pa.Table:
        if tab.column("kind")[0].as_py() != POSTINGS:
            return tab
        columns, names = _packed(list(count_bucket(tab, buckets)))
        give_back()
        return pa.table(columns, names=names)

    def pick(tab: pa.Table) -> pa.Table:
        kind, *rest = choose(tab)
        return pa.table({"kind": pa.array(kind, pa.int32()), **{n: pa.array(x, pa.int64()) for n, x in zip("abcd", rest, strict=True)}})

    packed = texts.mapInArrow(pack, PACKED)
    counted = packed.groupBy("kind", "part").applyInArrow(count, PACKED)
    return table(counted.groupBy("part").applyInArrow(pick, ROWS))


def hashed_sets(keys: DataFrame, low: DataFrame, texts: DataFrame, how: dict) -> DataFrame:
    """(key, hashes) of the classes ``keys``, hashed anew from one document of each and written once."""
    import pyarrow as pa

    width = how["width"]
    ids = cut(keys.join(low, "key").select("id"))
    if ids.count() <= BROADCAST_IDS:
        ids = F.broadcast(ids)

    def hashed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(0, batch.num_rows, 128):
                sets = [shingles(t, width) for t in batch.column("text").slice(k, 128).to_pylist()]
                yield pa.RecordBatch.from_pydict({"key": pa.array([digest(s) for s in sets], pa.int64()), "hashes": pa.array([s.tobytes() for s in sets], pa.binary())})
        _WORDS.clear()
        give_back()

    return table(texts.join(ids, "id").select("text").mapInArrow(hashed, "key long, hashes binary"))


def compare(edges: DataFrame, sets: DataFrame, how: dict) -> DataFrame:
    """The links among ``edges`` (a, b: classes): pairs whose sets reach the threshold exactly.

    Many pairs of few classes are compared in one task; a frequent ``a`` is dealt to several.
    """
    import pyarrow as pa

    num, den = how["num"], how["den"]
    degree = edges.groupBy("a").agg(F.count("*").alias("many")).withColumn("degree", F.col("many"))
    total = edges.count()
    groups = max(1, -(-total // COMPARED))
    salt = F.pmod(F.xxhash64("b"), F.ceil(F.col("degree") / (COMPARED // 4)))
    dealt = hot_join(edges.select("a", "b"), degree, ["a"], total, ["b"]).withColumn("grp", F.pmod(F.xxhash64("a", salt), F.lit(groups))).select("a", "b", "grp")
    left = dealt.join(sets, F.col("b") == F.col("key")).select("grp", "a", "b", "hashes")
    right = dealt.select("grp", "a").distinct().join(sets, F.col("a") == F.col("key")).select(F.col("grp").alias("of"), F.col("a").alias("centre"), F.col("hashes").alias("whole"))

    def check(pairs: pa.Table, centres: pa.Table) -> pa.Table:
        of = dict(zip(centres.column("centre").to_pylist(), centres.column("whole").to_pylist(), strict=True))
        found = set()
        for a, b, x in zip(pairs.column("a").to_pylist(), pairs.column("b").to_pylist(), pairs.column("hashes").to_pylist(), strict=True):
            if a in of:
                p, q = np.frombuffer(of[a], dtype=U), np.frombuffer(x, dtype=U)
                if len(p) > len(q):
                    p, q = q, p
                at = np.searchsorted(q, p)
                at[at == len(q)] = 0
                both = int((q[at] == p).sum())
                if den * both >= num * (len(p) + len(q) - both):
                    found.add((a, b))
        found = sorted(found)
        return pa.table({"a": pa.array([f[0] for f in found], pa.int64()), "b": pa.array([f[1] for f in found], pa.int64())})

    return cut(left.groupBy("grp").cogroup(right.groupBy("of")).applyInArrow(check, "a long, b long"))


def common(xs: list[np.ndarray], ys: list[np.ndarray]) -> np.ndarray:
    """Sizes of all intersections of two lists of sets, by matrix products over slices of their common hashes."""
    out = np.zeros((len(xs), len(ys)), dtype=np.float32)
    x, y = np.concatenate(xs), np.concatenate(ys)
    shared = np.intersect1d(x, y)
    if not len(shared):
        return out.astype(np.int64)
    parts = []
    for values, sets in ((x, xs), (y, ys)):
        at = np.minimum(np.searchsorted(shared, values), len(shared) - 1)
        hit = shared[at] == values
        row = np.repeat(np.arange(len(sets)), [len(s) for s in sets])[hit]
        order = np.argsort(at[hit], kind="stable")
        parts.append((row[order], at[hit][order]))
    for begin in range(0, len(shared), 4096):
        dense = []
        for (row, col), sets in zip(parts, (xs, ys), strict=True):
            a, b = np.searchsorted(col, [begin, begin + 4096])
            m = np.zeros((len(sets), 4096), dtype=np.float32)
            m[row[a:b], col[a:b] - begin] = 1
            dense.append(m)
        out += dense[0] @ dense[1].T
    return out.astype(np.int64)


def compare_blocks(members: DataFrame, sets: DataFrame, how: dict) -> DataFrame:
    """Links (a, b) between labels, from members (cluster, key, label): all classes that are not of their cluster's main label against all of the cluster.

    Blocks of at most BLOCK classes meet in a task, as matrix products; nothing is sent on but which labels are linked.
    """
    import pyarrow as pa

    num, den = how["num"], how["den"]
    each = members.groupBy("cluster", "label").agg(F.count("*").alias("n"))
    main = cut(each.groupBy("cluster").agg(F.max(F.struct("n", F.col("label").alias("l"))).alias("m"), F.sum("n").alias("all"), F.count("*").alias("labels")).filter("labels > 1").select("cluster", F.col("m.l").alias("main"), F.col("all").alias("n_all"), (F.col("all") - F.col("m.n")).alias("n_out")))
    total = main.agg(F.sum("n_all")).first()[0]
    if not total:
        return members.sparkSession.createDataFrame([], "a long, b long")
    groups = max(1, -(-total // BLOCK))
    across, down = F.ceil(F.col("n_all") / BLOCK).cast("int"), F.ceil(F.col("n_out") / BLOCK).cast("int")
    rows = members.join(main, "cluster").join(sets, "key").withColumn("i", F.pmod(F.xxhash64("key", F.lit(3)), down).cast("int")).withColumn("j", F.pmod(F.xxhash64("key", F.lit(4)), across).cast("int"))
    # clusters of one block share tasks; the blocks of a large one are dealt to tasks of their own
    task = F.pmod(F.xxhash64("cluster", "i", "j"), F.lit(groups * 4))
    out = rows.filter("label != main").withColumn("j", F.explode(F.sequence(F.lit(0), across - 1))).select(task.alias("task"), "cluster", "i", "j", "label", "hashes")
    all_ = rows.withColumn("i", F.explode(F.sequence(F.lit(0), down - 1))).select(task.alias("task_"), F.col("cluster").alias("cluster_"), F.col("i").alias("i_"), F.col("j").alias("j_"), F.col("label").alias("label_"), F.col("hashes").alias("hashes_"))

    def blocks(tab: pa.Table, end: str) -> dict:
        found: dict = {}
        for *at, label, x in zip(*(tab.column(c + end).to_pylist() for c in ("cluster", "i", "j", "label", "hashes")), strict=True):
            found.setdefault(tuple(at), []).append((label, np.frombuffer(x, dtype=U)))
        return found

    def check(left: pa.Table, right: pa.Table) -> pa.Table:
        found = set()
        there = blocks(right, "_")
        for at, xs in blocks(left, "").items():
            ys = there.get(at, ())
            if ys:
                both = common([x for _, x in xs], [y for _, y in ys])
                sizes = np.array([len(x) for _, x in xs])[:, None] + np.array([len(y) for _, y in ys])[None, :]
                a, b = np.array([p for p, _ in xs]), np.array([p for p, _ in ys])
                i, j = np.nonzero((den * both >= num * (sizes - both)) & (a[:, None] != b[None, :]))
                if len(i):
                    found |= set(map(tuple, np.unique(np.stack([a[i], b[j]], axis=1), axis=0).tolist()))
        found = sorted(found)
        return pa.table({"a": pa.array([f[0] for f in found], pa.int64()), "b": pa.array([f[1] for f in found], pa.int64())})

    return cut(out.groupBy("task").cogroup(all_.groupBy("task_")).applyInArrow(check, "a long, b long").distinct())


def components(links: DataFrame, nodes: DataFrame) -> DataFrame:
    """(key, label): the smallest label reachable by links, from (key, label) nodes and (a, b) links between keys.

    Each round takes the least label around and then the label's own label, so long chains take a
    logarithmic number of rounds; each round is checkpointed.
    """
    both = links.select("a", "b").union(links.select(F.col("b").alias("a"), F.col("a").alias("b")))
    now = nodes
    while True:
        near = both.join(now, F.col("b") == F.col("key")).groupBy("a").agg(F.min("label").alias("near"))
        step = now.join(near, F.col("key") == F.col("a"), "left").select("key", F.col("label").alias("old"), F.least("label", F.coalesce("near", "label")).alias("label"))
        # labels are ids of nodes as well: a node's label is replaced by the least label its holder got
        holder = step.filter(F.col("label") != F.col("old")).groupBy(F.col("old").alias("was")).agg(F.min("label").alias("to"))
        new = cut(step.join(holder, F.col("label") == F.col("was"), "left").select("key", "old", F.least("label", F.coalesce("to", "label")).alias("label")))
        if new.filter(F.col("label") != F.col("old")).isEmpty():
            return new.select("key", "label")
        now = new.select("key", "label")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = WIDTH, num: int = NUMERATOR, den: int = DENOMINATOR, density: float = DENSITY, tokens: int = TOKENS) -> DataFrame:
    """(id, n_shingles, component_id) of every row.

    Rows link when den * intersection >= num * union of their shingle sets; component_id is the
    smallest id reachable. Null and empty texts have no shingles and link with nothing; rows without
    an id link with nothing and get a null component; repeated rows are linked copies and stay
    repeated. Of very long texts all shingles count. No other column is read or returned, so names cannot
    clash. An empty table gives no rows.
    """
    how = {"width": width, "num": num, "den": den, "density": density, "tokens": tokens}
    texts = docs.select(docs[id_col].cast("long").alias("id"), docs[text_col].alias("text"))
    rows = candidates(texts, how)
    none = F.lit(-(2**63))
    listed = rows.filter(F.col("kind") == DOCS).select(F.when(F.col("a") != none, F.col("a")).alias("id"), F.col("b").alias("n"), F.col("c").alias("key"))
    low = listed.filter("n > 0 and id is not null").groupBy("key").agg(F.min("id").alias("id"))
    posts = rows.filter(F.col("kind") == SHARED).select(F.col("a").alias("sig"), F.col("b").alias("key"), F.col("c").alias("n"), F.col("d").alias("weight"))
    fits = lambda n, m: den * F.least(n, m) >= num * F.greatest(n, m)

    centre = posts.groupBy("sig").agg(F.max(F.struct("weight", "key", "n")).alias("centre"), F.count("*").alias("many")).filter("many > 1").select("sig", F.col("centre.key").alias("a"), F.col("centre.n").alias("an"), "many")
    total = posts.count()
    star = cut(hot_join(posts, centre, ["sig"], total, ["key"]).filter(F.col("key") != F.col("a")).select("a", "an", F.col("key").alias("b"), "n").distinct())
    ends = cut(star.select(F.col("a").alias("key")).union(star.select(F.col("b").alias("key"))).distinct().join(low, "key").select("key", F.col("id").alias("label")))
    sets = hashed_sets(ends.select("key"), low, texts, how)
    labels = components(compare(star.filter(fits(F.col("n"), F.col("an"))).select("a", "b"), sets, how), ends)

    # groups of one signature whose classes are not all connected by now: their clusters are compared in blocks
    told = posts.join(labels, "key")
    open_ = told.groupBy("sig").agg(F.min("label").alias("least"), F.max("label").alias("most"), F.min("key").alias("a"), F.count("*").alias("many")).filter("least < most").select("sig", "a", "many")
    around = cut(hot_join(told.select("sig", "key", "label"), open_, ["sig"], total, ["key"]))
    if not around.isEmpty():
        near = cut(around.filter(F.col("key") != F.col("a")).select("a", F.col("key").alias("b")).distinct())
        nodes = cut(around.select("key", "label").distinct())
        clusters = components(near, nodes.join(low, "key").select("key", F.col("id").alias("label"))).withColumnRenamed("label", "cluster")
        links = compare_blocks(nodes.join(clusters, "key").select("cluster", "key", "label"), sets, how)
        joined = components(links, cut(links.select(F.col("a").alias("key")).union(links.select(F.col("b").alias("key"))).distinct().withColumn("label", F.col("key"))))
        labels = labels.join(joined.select(F.col("key").alias("label"), F.col("label").alias("to")), "label", "left").select("key", F.coalesce("to", "label").alias("label"))
    moved = labels.join(low, "key").filter("label != id").select("key", "label")
    whole = low.join(moved, "key", "left").select("key", F.coalesce("label", "id").alias("component_id"))
    linked = F.when(F.col("n") > 0, F.col("key"))
    joined = listed.withColumn("of", linked).join(whole.withColumnRenamed("key", "k"), F.col("of") == F.col("k"), "left")
    component = F.when(F.col("id").isNull(), F.lit(None)).otherwise(F.coalesce("component_id", "id"))
    return joined.select(F.col("id").alias(id_col), F.col("n").alias("n_shingles"), component.alias("component_id"))
