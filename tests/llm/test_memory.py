"""What a task holds beyond its batch: two workers share what an executor's heap leaves."""

import random
import tracemalloc

import pyarrow as pa

from flowregions.llm import quality, set_join


def peak_of(work) -> float:
    """MB that ``work`` takes at most beyond what there was."""
    tracemalloc.start()
    work()
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    return most / 1e6


def texts(n: int, words: int) -> list[str]:
    draw = random.Random(3)
    return [" ".join(f"w{draw.randrange(20_000)}" for _ in range(words)) for _ in range(n)]


def test_encoding_a_batch_of_texts():
    batch = texts(600, 300)

    def work():
        for part in quality._sliced(batch):
            quality.encode(batch[part])

    assert peak_of(work) < 30  # a fifth of a batch at a time; 1 MB at a time took 77


def test_counting_a_bucket():
    packer, rows = set_join.Packer(1, (), {}), []
    for k, text in enumerate(texts(600, 400)):
        packer.add(k, set_join.shingles(text))
        packer.add(10_000 + k, set_join.shingles(text + " end"))
    rows = [r for r in packer.rows() if r[0] == set_join.POSTINGS]
    tab = pa.table(*[set_join._packed(rows)[0]], names=set_join._packed([])[1])
    many = sum(len(r[5]) for r in rows) // 6
    found = []
    assert peak_of(lambda: found.extend(set_join.count_bucket(tab, 1))) < 50e-6 * many
    # both classes of a pair keep their common signatures, each counted twice
    counts = [c for r in found for c in memoryview(r[3]).cast("I")]
    assert len(counts) > 0.9 * many and set(counts) == {2}
