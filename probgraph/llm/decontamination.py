"""Operator 8: benchmark decontamination by edit distance.

A benchmark item of n words leaks into a text if some run of the text's words is within floor(``max_edit`` x n) word edits of it.

1. Lossless seeds: of the d + 1 pieces an item is cut into, d edits leave one untouched, so only places that hold a piece's first words
   verbatim can match. One rolling hash over every text, looked up in a bit table, finds them.
2. Around each seed, windows of the item's size at every shift up to d are embedded by the CGK random walk: at each of 3n steps the current word is written and the
   pointer moves on by a random bit of (step, word), which turns edit distance into Hamming distance. Bit sampling of the
   embedding, repeated with new walks, gives LSH keys; a window meets the items of its size that share a key. The number of repetitions comes from the collision
   rate measured on items with d random edits, for a recall of ``recall``.
3. Candidates are verified by the exact edit distance of the item to the best run of words around the window.

The benchmark's seeds and keys go to the tasks as a broadcast of bounded size: ``slice_items`` items at a time, as many passes as that takes.
Nothing is shuffled. Null or empty texts and items match nothing; items of up to 9 words have to occur unchanged; repeated rows give repeated results,
equal items are each reported."""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from probgraph.llm.text import Codes, grams, mix, words

MAX_EDIT, RECALL, SAMPLED, SLICE = 0.1, 0.98, 3, 20_000
_LONGEST_SEED = 8
#: Texts that are laid end to end at a time, to bound a task's memory.
ROWS = 1000
_TABLE = 22


def cgk_keys(rows: np.ndarray, seed: int, sampled: int = SAMPLED) -> np.ndarray:
    """Bit-sampling keys of word matrices (rows x n, zero padded) under the walk that ``seed`` names."""
    n = rows.shape[1]
    rng = np.random.default_rng((seed, n))
    at = set(rng.choice(3 * n, size=min(sampled, 3 * n), replace=False).tolist())
    salt = rng.integers(1, 2**63, size=3 * n, dtype=np.uint64)
    padded = np.concatenate([rows, np.zeros((len(rows), 1), np.uint64)], axis=1)
    pointer = np.zeros(len(rows), np.int64)
    line = np.arange(len(rows))
    key = np.full(len(rows), np.uint64(seed * 2 + 1))
    for step in range(max(at) + 1):
        word = padded[line, pointer]
        if step in at:
            key = mix(key + word)
        pointer = np.minimum(pointer + (mix(word + salt[step]) & np.uint64(1)).astype(np.int64), n)
    return key


def edited(item: np.ndarray, d: int, rng: np.random.Generator) -> np.ndarray:
    """An item with d random word edits, cut or padded to its size."""
    out = item.tolist()
    for _ in range(d):
        kind, at = rng.integers(3), int(rng.integers(len(out)))
        new = int(rng.integers(1, 2**62))
        if kind == 0:
            out[at] = new
        elif kind == 1:
            out.insert(at, new)
        elif len(out) > 1:
            del out[at]
    row = np.zeros(len(item), np.uint64)
    row[: min(len(out), len(row))] = np.array(out[: len(row)], np.uint64)
    return row


def repetitions(items: np.ndarray, d: int, recall: float, most: int = 256) -> int:
    """Walks needed for the recall, from the measured collision rate of items with d edits."""
    if d == 0:
        return 1
    rng = np.random.default_rng(7)
    base = np.repeat(items, max(1, 64 // len(items)), axis=0)[:256]
    other = np.stack([edited(r, d, rng) for r in base])
    missed, reps = np.ones(len(base), bool), 0
    while reps < most and missed.mean() > (1 - recall) / 2:
        missed &= cgk_keys(base, reps) != cgk_keys(other, reps)
        reps += 1
    return reps


def best_run(item: np.ndarray, text: np.ndarray) -> tuple[int, int, int]:
    """(edits, start, end) of the run of ``text`` nearest to ``item``; the shortest prefix wins ties."""
    m, n = len(item), len(text)
    cost = np.zeros(n + 1, np.int64)
    start = np.arange(n + 1)
    for i in range(1, m + 1):
        same = (text != item[i - 1]).astype(np.int64)
        new = np.empty(n + 1, np.int64)
        origin = np.empty(n + 1, np.int64)
        diag, up = cost[:-1] + same, cost[1:] + 1
        new[0], origin[0] = i, 0
        new[1:] = np.minimum(diag, up)
        origin[1:] = np.where(diag <= up, start[:-1], start[1:])
        # insertions run along the row: running minimum of (value - index)
        lead = new - np.arange(n + 1)
        low = np.minimum.accumulate(lead)
        source = np.maximum.accumulate(np.where(lead == low, np.arange(n + 1), -1))
        better = low < lead
        new = np.where(better, low + np.arange(n + 1), new)
        origin = np.where(better, origin[source], origin)
        cost, start = new, origin
    end = int(np.argmin(cost))
    return int(cost[end]), int(start[end]), end


class Index:
    """Seeds and LSH keys of some items."""

    def __init__(self, items: list[tuple[int, str]], max_edit: float = MAX_EDIT, recall: float = RECALL):
        codes = Codes()
        self.items = [(i, w) for i, t in items if len(w := words(t, codes))]
        self.d = [int(max_edit * len(w) + 1e-9) for _, w in self.items]
        seeds: dict[int, dict[int, set]] = defaultdict(lambda: defaultdict(set))  # size of the seed: hash: {(item size, offset, d)}
        by_size = defaultdict(list)
        for at, (_, w) in enumerate(self.items):
            d, n = self.d[at], len(w)
            by_size[n].append(at)
            k = min(_LONGEST_SEED, n // (d + 1))
            for piece in range(d + 1):
                o = piece * n // (d + 1)
                seeds[k][int(grams(w[o : o + k], k)[0])].add((n, o, d))
        self.seeds = {k: {h: sorted(v) for h, v in s.items()} for k, s in seeds.items()}
        self.tables = {}
        for k, s in self.seeds.items():
            table = np.zeros(1 << _TABLE, bool)
            table[np.fromiter(s, np.uint64, len(s)) >> np.uint64(64 - _TABLE)] = True
            self.tables[k] = table
        self.keys: dict[int, list[dict[int, list[int]]]] = {}
        for n, ats in by_size.items():
            rows = np.stack([self.items[a][1] for a in ats])
            reps = repetitions(rows, self.d[ats[0]], recall)
            self.keys[n] = []
            for r in range(reps):
                table: dict[int, list[int]] = defaultdict(list)
                for a, key in zip(ats, cgk_keys(rows, r).tolist()):
                    table[key].append(a)
                self.keys[n].append(dict(table))

    def leaks(self, texts: list[np.ndarray]) -> list[tuple[int, int, int, int, int]]:
        """(position in ``texts``, item_id, start_word, end_word, edits) of the leaks in the texts' words.

        The texts are laid end to end, so that each step of a walk works on the windows of all of them."""
        size = np.array([len(t) for t in texts], np.int64)
        if not size.sum():
            return []
        begin = np.concatenate([[0], np.cumsum(size + 1)])
        line = np.zeros(int(begin[-1]), np.uint64)  # 0 between texts: no word has that code
        for t, at in zip(texts, begin):
            line[at : at + len(t)] = t
        windows: dict[int, list[np.ndarray]] = defaultdict(list)  # size: starts
        for k, table in self.tables.items():
            h = grams(line, k)
            for x in np.flatnonzero(table[h >> np.uint64(64 - _TABLE)]).tolist():
                for n, o, d in self.seeds[k].get(int(h[x]), ()):
                    doc = int(np.searchsorted(begin, x, "right")) - 1
                    windows[n].append(np.arange(max(int(begin[doc]), x - o - d), max(int(begin[doc]), min(x - o + d, int(begin[doc] + size[doc]) - 1)) + 1))
        pairs = set()
        for n, starts in windows.items():
            at = np.unique(np.concatenate(starts))
            end = begin[1:][np.searchsorted(begin, at, "right") - 1] - 1
            inside = at[:, None] + np.arange(n)[None, :]
            rows = np.where(inside < end[:, None], line[np.minimum(inside, len(line) - 1)], np.uint64(0))
            for r, table in enumerate(self.keys[n]):
                for x, key in zip(at.tolist(), cgk_keys(rows, r).tolist()):
                    for a in table.get(key, ()):
                        pairs.add((a, x))
        out, last = set(), {}
        for a, x in sorted(pairs):
            if x < last.get(a, -1):
                continue
            doc = int(np.searchsorted(begin, x, "right")) - 1
            d, w = self.d[a], self.items[a][1]
            lo, hi = max(int(begin[doc]), x - d), min(int(begin[doc] + size[doc]), x + len(w) + 2 * d + 1)
            edits, s, e = best_run(w, line[lo:hi])
            if edits <= d:
                first = lo - int(begin[doc])
                out.add((doc, self.items[a][0], first + s, first + e, edits))
                last[a] = lo + e
        return sorted(out)


def _slices(benchmark: DataFrame, size: int) -> Iterator[list[tuple[int, str]]]:
    part = []
    for r in benchmark.select("item_id", "text").filter("text is not null and item_id is not null").toLocalIterator():
        part.append((r[0], r[1]))
        if len(part) == size:
            yield part
            part = []
    if part:
        yield part


def contamination(docs: DataFrame, benchmark: DataFrame, max_edit: float = MAX_EDIT, recall: float = RECALL, slice_items: int = SLICE) -> DataFrame:
    """(doc_id, item_id, start_word, end_word, edits) of every leak."""
    sc = docs.sparkSession.sparkContext
    kind = docs.schema["doc_id"].dataType.simpleString()
    schema = f"doc_id {kind}, item_id long, start_word int, end_word int, edits int"

    def found(shared):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            codes = Codes()
            for b in (x.slice(at, ROWS) for x in batches for at in range(0, x.num_rows, ROWS)):
                out = shared.value.leaks([words(t.as_py(), codes) for t in b.column(1)])
                row, *cols = list(zip(*out)) if out else [(), (), (), (), ()]
                yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(row, pa.int64())), pa.array(cols[0], pa.int64()), *[pa.array(c, pa.int32()) for c in cols[1:]]], names=["doc_id", "item_id", "start_word", "end_word", "edits"])

        return docs.select("doc_id", "text").filter("text is not null").mapInArrow(run, schema)

    parts = [found(sc.broadcast(Index(s, max_edit, recall))) for s in _slices(benchmark, slice_items)]
    return reduce(DataFrame.unionByName, parts) if parts else docs.sparkSession.createDataFrame([], schema)


def clean(docs: DataFrame, benchmark: DataFrame, max_edit: float = MAX_EDIT, recall: float = RECALL, slice_items: int = SLICE) -> DataFrame:
    """The rows of ``docs`` in which no item leaks, columns unchanged."""
    import pandas as pd
    from pyspark.sql import types as T

    for s in _slices(benchmark, slice_items):
        shared = docs.sparkSession.sparkContext.broadcast(Index(s, max_edit, recall))

        def leaking(parts: Iterator[pd.Series], shared=shared) -> Iterator[pd.Series]:
            codes = Codes()
            for texts in parts:
                hit = np.zeros(len(texts), bool)
                for at in range(0, len(texts), ROWS):
                    hit[[at + x[0] for x in shared.value.leaks([words(t, codes) for t in texts[at : at + ROWS]])]] = True
                yield pd.Series(hit)

        udf = F.pandas_udf(leaking, T.BooleanType(), F.PandasUDFType.SCALAR_ITER)
        docs = docs.filter(~udf(F.coalesce("text", F.lit(""))))
    return docs
