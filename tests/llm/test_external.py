"""Shards larger than the memory budget, and verification of repeats."""

import random

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from probgraph.llm import induced_sort, passages, substring_dedup, suffix_dedup
from probgraph.llm.external import Column, Pool, Queue


def test_queue_keeps_order(tmp_path):
    rng = np.random.default_rng(1)
    for budget in (2000, 1 << 22):
        with Pool(budget, str(tmp_path)) as pool:
            q, want, n = Queue(pool), [], 0
            for _ in range(60):
                k = rng.integers(0, 40, int(rng.integers(1, 90)))
                q.push(k, np.arange(n, n + len(k)), k)
                want += [(int(x), n + i) for i, x in enumerate(k)]
                n += len(k)
            got = [(int(r[0, i]), int(r[1, i])) for r in q.drain(50) for i in range(r.shape[1])]
            assert got == sorted(want)
    assert not list(tmp_path.iterdir())


def test_text_of_many_times_the_budget(tmp_path):
    """A text of ten times the budget is sorted as in memory, and what is held stays within the budget and a block."""
    rng = np.random.default_rng(2)
    base = rng.integers(0, 60, 4000)
    text = np.concatenate([base[i : i + 900] for i in rng.integers(0, 3000, 20)])
    want = induced_sort.suffix_arrays(text, 50)
    budget = text.nbytes // 10
    with Pool(budget, str(tmp_path)) as pool:
        line = Column(pool, np.int64)
        line.append(text + 1)
        line.append(np.zeros(1, np.int64))
        got = list(induced_sort.external_arrays(line.seal(), 50, pool, 64).chunks(1000))
        assert pool.spilled > 10 * budget and pool.peak <= 2 * budget
    assert np.array_equal(np.concatenate([g[0] for g in got]), want[0]) and np.array_equal(np.concatenate([g[1] for g in got]), want[1])


def test_shards_beyond_memory(spark, tmp_path):
    """Parts of one minimizer, blocks and pools of any size give the same windows."""
    r = random.Random(8)
    vocab = [f"w{i}" for i in range(50)]
    shared = [" ".join(r.choices(vocab, k=80)) for _ in range(4)]
    docs = [(i, " ".join([" ".join(r.choices(vocab, k=r.randint(0, 60))), r.choice(shared)[r.randint(0, 40) :], " ".join(r.choices(vocab, k=20))])) for i in range(60)]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    rows = passages.segments(df).coalesce(1).sortWithinPartitions("h", "digest").toArrow()

    def windows(f, budget, part):
        out = set()
        with Pool(budget, str(tmp_path)) as pool:
            c = passages.Contents(pool)
            for table, goes_on in passages.shards(iter(rows.to_batches(7)), part):
                c.add(table, goes_on)
                if not goes_on and len(c):
                    for b in f(c.seal()):
                        out |= {(d, lo) for d, s, e in zip(*[b.column(i).to_pylist() for i in (0, 2, 3)]) for lo in range(s, e - 49)}
                    c = passages.Contents(pool)
        return out

    want = windows(suffix_dedup.repeated, 1 << 28, 1 << 24)
    assert want and want == windows(suffix_dedup.repeated, 4000, 300)
    for block in (1 << 21, 400):
        assert want == windows(lambda c, block=block: substring_dedup.repeated(c, block), 4000, 300)


def test_repeats_are_verified(spark):
    """Of a claimed repeat whose words differ in one place, the parts of 50 words that agree stay."""
    a = [f"a{i}" for i in range(130)]
    b = a[:60] + ["other"] + a[61:]
    df = spark.createDataFrame([(1, " ".join(a)), (2, " ".join(b)), (3, " ".join(a[:55]))], "doc_id long, text string").withColumn("shift", F.lit("clash"))
    from probgraph.llm.text import Codes, words

    key = [passages.text_key(words(" ".join(x), Codes())) for x in (a, b, a[:55])]
    spans = spark.createDataFrame([(2, key[1], 0, 80, 1, key[0], 0), (2, key[1], 70, 130, 1, key[0], 70), (3, key[2], 0, 55, 1, key[0], 0)], "doc long, text_key long, lo int, hi int, first_doc long, first_key long, first_lo int")
    assert {(r.doc, r.lo, r.hi) for r in passages.verified(spans, df).collect()} == {(2, 0, 60), (2, 61, 130), (3, 0, 55)}
    assert isinstance(spans.toArrow(), pa.Table)
