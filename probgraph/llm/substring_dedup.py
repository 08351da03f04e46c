"""Operator 6: substring dedup by relative Lempel-Ziv parsing.

The reference is all text that comes before, in order of (doc_id, text hash, place). It is cut in blocks by the minimizer of its windows (see
:mod:`probgraph.llm.passages`), and a text's segments go to every block that could hold a factor of 50 words of them: those
of their own minimizers. A block is indexed by a suffix array with common prefixes. Segments are parsed from left to right: from where a phrase ends, the
longest factor is sought that begins earlier in the reference, compared word by word (16 bits here, 64 bits before a span is reported). Factors of ``length`` words and more are duplicate spans. A
repeat that greedy phrases cut apart lies across the boundary between two of them, so each window across a boundary is looked up as well: none is lost.

Segments of a minimizer beyond ``BLOCK`` symbols are several reference blocks; each is indexed together with each later one, and all factors of both count.

Null, empty and shorter texts have no factors. Rows equal in doc_id and text are one text and no reference for each other.
A text is its own reference for what it said before. Empty tables, very long texts, ties and further columns: see :mod:`probgraph.llm.passages`."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from probgraph.llm.external import Pool
from probgraph.llm.induced_sort import _doubling, _Ranges
from probgraph.llm.passages import LENGTH, PART, Contents, found, joined, named, shards
from probgraph.runtime import lean, shared_dir

#: Symbols of a reference block.
BLOCK = 2 << 20
BUDGET = 256 << 20
#: Places of a block whose neighbours are looked up at a time.
STEP = 1 << 15


class Block:
    """An indexed reference: texts end to end, each ended by a number of its own."""

    def __init__(self, text: np.ndarray, cap: int):
        self.text = text
        order, prefix = _doubling(text, cap)
        n = len(text)
        ranges = _Ranges(prefix.astype(np.min_scalar_type(cap)))
        self.length, self.source = np.zeros(n, np.int64), np.full(n, -1)
        for order_, at in ((order, 1), (order[::-1], -1)):
            near = self._earlier(order_)
            every = np.flatnonzero(near >= 0)
            for has in (every[x : x + STEP] for x in range(0, len(every), STEP)):
                i, j = has, near[has]
                p, q = order_[i], order_[j]
                if at < 0:
                    i, j = n - 1 - j, n - 1 - i  # in the array's own direction
                long = ranges.least(j + 1, i)
                better = long > self.length[p]
                self.length[p[better]], self.source[p[better]] = long[better], q[better]

    @staticmethod
    def _earlier(order: np.ndarray) -> np.ndarray:
        """For each place of the array the nearest one before it whose text begins earlier; -1 if there is none."""
        up = np.arange(-1, len(order) - 1)
        live = np.flatnonzero(up >= 0)
        while len(live):
            live = live[order[up[live]] > order[live]]
            up[live] = up[up[live]]
            live = live[up[live] >= 0]
        return up


def phrases(longest: np.ndarray, begin: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(start, length) of the greedy phrases of texts begin..end - 1, all texts a phrase at a time. A word without a factor is a phrase of its own."""
    starts, sizes, at, stop = [], [], begin, end
    while len(at):
        size = np.maximum(1, np.minimum(longest[at], stop - at))
        starts.append(at)
        sizes.append(size)
        at = at + size
        live = at < stop
        at, stop = at[live], stop[live]
    return (np.concatenate(starts), np.concatenate(sizes)) if starts else (np.zeros(0, np.int64),) * 2


def factored(text: np.ndarray, begin: np.ndarray, size: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """(windows, the earlier ones that they repeat) of a block's texts: those in long factors, and those across boundaries of phrases."""
    block = Block(text, int(size.max()))
    start, long = phrases(block.length, begin, begin + size)
    wide = long >= length
    many = long[wide] - length + 1
    inside = np.repeat(start[wide] - np.cumsum(many) + many, many) + np.arange(int(many.sum()))
    # windows that hold a boundary: they begin in a phrase and end in a later one
    text_of = np.searchsorted(begin, start, "right") - 1
    low = np.maximum(begin[text_of], start - length + 1)
    many = start - low
    across = np.unique(np.repeat(low - np.cumsum(many) + many, many) + np.arange(int(many.sum())))
    across = across[block.length[across] >= length]
    source = np.full(len(text), -1)
    source[across] = block.source[across]
    source[inside] = np.repeat(block.source[start[wide]] - start[wide], long[wide] - length + 1) + inside
    at = np.flatnonzero(source >= 0)
    return at, source[at]


def repeated(contents: Contents, block: int = BLOCK) -> Iterator[pa.RecordBatch]:
    """Rows of ``OCCURRENCES``."""
    c, length = contents, contents.length
    yield from c.again()  # a segment that occurs again is a factor as a whole
    order = np.argsort(c.rank)
    size = c.n + length - 1
    part = np.cumsum(size[order] + 1) // block
    parts = np.split(order, np.flatnonzero(np.diff(part)) + 1)

    def lay(which: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        n = size[which]
        head = np.concatenate([[0], np.cumsum(n + 1)])
        text = np.empty(int(head[-1]), np.int64)
        text[head[1:] - 1] = (1 << 20) + np.arange(len(which))
        step = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
        text[np.repeat(head[:-1], n) + step] = c.words.take(np.repeat(c.begin[which], n) + step)
        return text, head[:-1]

    for i in range(len(parts)):
        for j in range(i, len(parts)):
            if i == j and len(parts) > i + 1:
                continue  # a block is indexed with itself wherever it meets a later one
            which = parts[i] if i == j else np.concatenate([parts[i], parts[j]])
            text, begin = lay(which)
            at, source = factored(text, begin, size[which], length)
            of, from_ = np.searchsorted(begin, at, "right") - 1, np.searchsorted(begin, source, "right") - 1
            off, there = at - begin[of], source - begin[from_]
            if len(at):
                yield c.spans(*joined(which[of], off, which[from_], there - off))


def factor_spans(docs: DataFrame, length: int = LENGTH, part: int = PART, block: int = BLOCK, budget: int = BUDGET) -> DataFrame:
    """(doc, text_key, lo, hi, first_doc) of the long factors, merged per text."""
    place = shared_dir(docs.sparkSession) + "/scratch"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lean()
        with Pool(budget, place) as pool:
            contents = Contents(pool, length)
            for rows, goes_on in shards(batches, part):
                contents.add(rows, goes_on)
                if not goes_on and len(contents):
                    yield from repeated(contents.seal(), block)
                    contents.words.drop()
                    contents.places.drop()
                    contents = Contents(pool, length)

    return found(docs, run, length)


def substring_dedup(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """(doc_id, start_word, end_word, n_words, first_doc_id): spans that are long factors of earlier text; first_doc_id is the lowest id of their references."""
    return named(factor_spans(docs, length))
