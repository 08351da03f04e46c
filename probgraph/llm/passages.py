"""Repeated passages of at least ``LENGTH`` words: how texts are cut so that equal passages meet in one task, and how what is found there is verified.

Every window of LENGTH words is represented by its minimizer, the run of ``SEED`` words in it with the least hash (the leftmost of
equal ones), which depends on the window's words alone. Consecutive windows with one minimizer form a segment, sent by
the minimizer's hash: equal windows, in whatever texts, always meet, and each window is sent exactly once. Segments of equal words are sent once
for all their occurrences in a batch of texts, 20 bytes each, so a passage that every text holds costs a task little more than its places.

A segment carries 16 bits a word, by which the operators find repeats. Segments that are equal as a whole are told by a 64-bit digest of their words. Before anything else is reported or cut, each repeat is
verified against the 64-bit codes of both texts' words (:func:`verified`); of a repeat that fails, the runs of LENGTH and more words that do agree stay.

A text is known by its doc_id and the hash of its words; rows equal in both are one text. Shorter texts have no window. Null text is empty,
a null doc_id counts as the lowest. Further columns aren't read, so that their names can't clash. An empty table has no passages. Very long texts are cut piece by piece. Of equal
windows the first in order of (doc_id, text hash, place) is the original."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from probgraph.llm.external import Column, Pool
from probgraph.llm.text import Codes, grams, mix, words
from probgraph.runtime import cut, lean, small, stage

LENGTH, SEED = 50, 8
NULL_DOC = -(2**63)
SCHEMA = "h long, digest long, n_windows int, symbols binary, places binary"
#: An occurrence of a segment: which text, and its first window.
PLACE = np.dtype([("doc", "<i8"), ("key", "<i8"), ("lo", "<i4")])
#: Bytes of rows that a task reads before it works on them (whole groups of one minimizer; larger groups go in parts).
PART = 24 << 20
_PIECE = 1 << 20
_BASE = 0x9E3779B97F4A7C15 | 1
_BACK = pow(_BASE, -1, 1 << 64)


def cuts(code: np.ndarray, length: int = LENGTH, seed: int = SEED) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(minimizer hash, first window, number of windows) of the segments of a text's words."""
    if len(code) < length:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64)
    if len(code) > _PIECE:  # positions share a 64-bit key with the hash: very long texts go piece by piece
        parts = [cuts(code[at : at + _PIECE], length, seed) for at in range(0, len(code) - length + 1, _PIECE - length + 1)]
        ats = range(0, len(code) - length + 1, _PIECE - length + 1)
        return np.concatenate([p[0] for p in parts]), np.concatenate([p[1] + at for p, at in zip(parts, ats)]), np.concatenate([p[2] for p in parts])
    h = grams(code, seed)
    key = (h >> np.uint64(20) << np.uint64(20)) | np.arange(len(h), dtype=np.uint64)
    wide, size = length - seed + 1, 1
    low = key
    while 2 * size <= wide:
        low = np.minimum(low[:-size], low[size:])
        size *= 2
    if size < wide:
        low = np.minimum(low[: len(low) - (wide - size)], low[wide - size :])
    start = np.flatnonzero(np.append(True, low[1:] != low[:-1]))
    at = (low[start] & np.uint64(_PIECE - 1)).astype(np.int64)
    return h[at], start, np.diff(np.append(start, len(low)))


def symbols(code: np.ndarray) -> np.ndarray:
    return (mix(code) >> np.uint64(48)).astype(np.uint16)


def text_key(code: np.ndarray) -> int:
    return xxhash.xxh3_64_intdigest(code.tobytes()) - (1 << 63)


def _powers(base: int, n: int) -> np.ndarray:
    out = np.full(n + 1, np.uint64(base))
    out[0] = 1
    return np.cumprod(out, dtype=np.uint64)


def segments(docs: DataFrame, length: int = LENGTH, seed: int = SEED) -> DataFrame:
    """Segments of all texts, ``SCHEMA``; equal ones of a batch are one row with several places."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lean()
        codes = Codes()
        for b in batches:
            for part in range(0, b.num_rows, 500):
                hs, los, ns, bodies, owner, known, base = [], [], [], [], [], [], 0
                for doc, text in zip(b.column(0)[part : part + 500].to_pylist(), b.column(1)[part : part + 500].to_pylist()):
                    code = words(text, codes)
                    h, lo, n = cuts(code, length, seed)
                    if not len(h):
                        continue
                    hs.append(h)
                    los.append(lo + base)
                    ns.append(n)
                    bodies.append(code)
                    owner.append(np.full(len(h), len(known)))
                    known.append((doc, text_key(code), base))
                    base += len(code)
                if not hs:
                    continue
                h, at, n, body, own = (np.concatenate(x) for x in (hs, los, ns, bodies, owner))
                end = at + n + length - 1
                # a segment's digest: its part of a power sum over all words, shifted to the front
                sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(mix(body) * _powers(_BASE, len(body))[:-1], dtype=np.uint64)])
                digest = mix((sums[end] - sums[at]) * _powers(_BACK, len(body))[at] + n.astype(np.uint64))
                docs_, keys, starts = (np.array(x, np.int64)[own] for x in zip(*known))
                order = np.lexsort((digest, h))
                h, digest = h[order], digest[order]
                first = np.flatnonzero(np.append(True, (h[1:] != h[:-1]) | (digest[1:] != digest[:-1])))
                places = np.empty(len(order), PLACE)
                places["doc"], places["key"], places["lo"] = docs_[order], keys[order], (at - starts)[order]
                at, n = at[order[first]], n[order[first]]
                size = n + length - 1
                text = symbols(body)[np.repeat(at - np.cumsum(np.append(0, size[:-1])), size) + np.arange(int(size.sum()))]
                binary = lambda ends, raw: pa.Array.from_buffers(pa.binary(), len(ends), [None, pa.py_buffer(np.append(0, ends).astype(np.int32)), pa.py_buffer(raw)])
                yield pa.RecordBatch.from_arrays(
                    [pa.array(h[first].view(np.int64)), pa.array(digest[first].view(np.int64)), pa.array(n.astype(np.int32)), binary(np.cumsum(size) * 2, text), binary(np.append(first[1:], len(h)) * PLACE.itemsize, places)],
                    names=["h", "digest", "n_windows", "symbols", "places"],
                )

    rows = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(NULL_DOC)).alias("doc"), F.col("text").cast("string")).filter("text is not null")
    return rows.mapInArrow(run, SCHEMA)


def shards(batches: Iterator[pa.RecordBatch], part: int = PART) -> Iterator[tuple[pa.Table, bool]]:
    """(rows, whether their last minimizer goes on) of rows in order of (h, digest). No segment's rows are parted."""
    held, size = [], 0
    for b in batches:
        if not b.num_rows:
            continue
        held.append(b)
        size += b.nbytes
        if size < part:
            continue
        t = pa.Table.from_batches(held).combine_chunks()
        h, digest = t.column("h").to_numpy(), t.column("digest").to_numpy()
        whole = np.flatnonzero(h[1:] != h[:-1])
        at = int((whole if len(whole) else np.flatnonzero(digest[1:] != digest[:-1]))[-1:].sum()) + 1 if len(whole) or (digest[1:] != digest[:-1]).any() else 0
        if not at:
            held = t.to_batches()
            continue
        yield t.slice(0, at), not len(whole)
        held = t.slice(at).to_batches()
        size = sum(x.nbytes for x in held) if len(whole) else 0
    if held:
        yield pa.Table.from_batches(held), False


def _binary(column: pa.ChunkedArray) -> list[tuple[np.ndarray, np.ndarray]]:
    """(offsets, bytes) of each chunk."""
    out = []
    for c in column.chunks:
        ends = np.frombuffer(c.buffers()[1], np.int32)[c.offset : c.offset + len(c) + 1].astype(np.int64)
        out.append((ends, np.frombuffer(c.buffers()[2], np.uint8) if c.buffers()[2] is not None else np.zeros(0, np.uint8)))
    return out


def _gather(column: pa.ChunkedArray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(bytes of the rows end to end, size of each)."""
    parts, sizes, base = [], [], 0
    for ends, raw in _binary(column):
        k = len(ends) - 1
        here = rows[np.searchsorted(rows, base) : np.searchsorted(rows, base + k)] - base
        size = ends[here + 1] - ends[here]
        parts.append(raw[np.repeat(ends[here] - np.cumsum(np.append(0, size[:-1]))[: len(here)], size) + np.arange(int(size.sum()))])
        sizes.append(size)
        base += k
    return np.concatenate(parts), np.concatenate(sizes)


class Contents:
    """The distinct segments of some minimizers, and where they occur. Words and places are columns of a pool; of a segment itself about 60 bytes are in memory."""

    def __init__(self, pool: Pool, length: int = LENGTH):
        self.pool, self.length = pool, length
        self.words = Column(pool, np.int32)  # 16-bit words + 2, a 1 after each segment
        self.places = Column(pool, PLACE)
        self.parts: list[tuple[np.ndarray, ...]] = []

    def add(self, rows: pa.Table, goes_on: bool = False) -> None:
        h, digest, n = (rows.column(c).to_numpy() for c in ("h", "digest", "n_windows"))
        count = np.concatenate([np.diff(ends) for ends, _ in _binary(rows.column("places"))]) // PLACE.itemsize
        group = np.flatnonzero(np.append(True, h[1:] != h[:-1]))
        size = np.diff(np.append(group, len(h)))
        keep = np.repeat(np.add.reduceat(count, group), size) > 1
        if goes_on or self.parts and h[0] == self.parts[-1][-1][-1]:
            keep |= (h == h[-1]) & goes_on | (h == h[0]) & bool(self.parts and h[0] == self.parts[-1][-1][-1])
        at = np.flatnonzero(keep)
        if not len(at):
            return
        h, digest, n, count = h[at], digest[at], n[at].astype(np.int64), count[at]
        first = np.flatnonzero(np.append(True, (h[1:] != h[:-1]) | (digest[1:] != digest[:-1])))
        raw, _ = _gather(rows.column("places"), at)
        places = raw.view(PLACE)
        count = np.add.reduceat(count, first)
        which = np.repeat(np.arange(len(first)), count)
        order = np.lexsort((places["lo"], places["key"], places["doc"], which))
        places = places[order]
        raw, size = _gather(rows.column("symbols"), at[first])
        size //= 2
        text = np.ones(int(size.sum()) + len(size), np.int32)
        head = np.concatenate([[0], np.cumsum(size + 1)])
        text[np.repeat(head[:-1] - np.cumsum(np.append(0, size[:-1])), size) + np.arange(int(size.sum()))] = raw.view(np.uint16).astype(np.int32) + 2
        least = places[np.concatenate([[0], np.cumsum(count)[:-1]])]
        self.parts.append((head[:-1] + len(self.words), n[first], count, len(self.places) + np.cumsum(count) - count, least["doc"], least["key"], least["lo"].astype(np.int64), h[first]))
        self.words.append(text)
        self.places.append(places)

    def seal(self) -> Contents:
        self.begin, self.n, self.count, self.at, self.doc, self.key, self.lo, _ = (np.concatenate(x) for x in zip(*self.parts))
        order = np.lexsort((self.lo, self.key, self.doc))
        #: Order of the segments' first occurrences: of equal windows the one in the segment of least rank is the first.
        self.rank = np.empty(len(order), np.int64)
        self.rank[order] = np.arange(len(order))
        self.words.seal()
        self.places.seal()
        return self

    def __len__(self) -> int:
        return sum(len(p[0]) for p in self.parts)

    def of(self, position: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(segment, place in it) of places in the text."""
        which = np.searchsorted(self.begin, position, "right") - 1
        return which, position - self.begin[which]

    def again(self, batch: int = 200_000) -> Iterator[pa.RecordBatch]:
        """Rows of ``OCCURRENCES``: segments that occurred before as a whole, which the digest of their words tells for sure."""
        many = np.flatnonzero(self.count > 1)
        ends = np.cumsum(self.count[many])
        at = 0
        while at < len(many):
            to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + batch)))
            w, at = many[at:to], to
            count = self.count[w] - 1  # the first one stays
            each = np.repeat(w, count)
            p = self.places.take(np.repeat(self.at[w] + 1 - np.cumsum(count) + count, count) + np.arange(int(count.sum())))
            # rows that are the same text occur at the same place
            keep = (p["doc"] != self.doc[each]) | (p["key"] != self.key[each]) | (p["lo"] != self.lo[each])
            p, each = p[keep], each[keep]
            yield self._rows(p["doc"], p["key"], p["lo"], p["lo"] + self.n[each] + self.length - 1, self.doc[each], self.key[each], self.lo[each], True)

    def spans(self, which: np.ndarray, lo: np.ndarray, hi: np.ndarray, source: np.ndarray, shift: np.ndarray) -> pa.RecordBatch:
        """Rows of ``OCCURRENCES``: windows lo..hi - 1 of segments, where these occur first, repeat windows lo + shift.. of the first occurrence of ``source``; that itself is no repeat."""
        keep = (which != source) | (shift != 0)
        w, lo, hi, s, shift = which[keep], lo[keep], hi[keep], source[keep], shift[keep]
        begin = self.lo[w] + lo
        return self._rows(self.doc[w], self.key[w], begin, begin + hi - lo + self.length - 1, self.doc[s], self.key[s], self.lo[s] + lo + shift, False)

    @staticmethod
    def _rows(doc, key, lo, hi, first_doc, first_key, first_lo, sure: bool) -> pa.RecordBatch:
        cols = [np.ascontiguousarray(c, t) for c, t in ((doc, np.int64), (key, np.int64), (lo, np.int32), (hi, np.int32), (first_doc, np.int64), (first_key, np.int64), (first_lo, np.int32))]
        return pa.RecordBatch.from_arrays([*map(pa.array, cols), pa.array(np.full(len(cols[0]), sure))], names=NAMES)


def joined(which: np.ndarray, off: np.ndarray, source: np.ndarray, shift: np.ndarray) -> tuple[np.ndarray, ...]:
    """Runs (which, lo, hi, source, shift) of windows in order that go on in the same source."""
    new = np.append(True, (which[1:] != which[:-1]) | (off[1:] != off[:-1] + 1) | (source[1:] != source[:-1]) | (shift[1:] != shift[:-1]))
    at = np.flatnonzero(new)
    return which[at], off[at], off[np.append(at[1:], len(off)) - 1] + 1, source[at], shift[at]


OCCURRENCES = "doc long, text_key long, lo int, hi int, first_doc long, first_key long, first_lo int, sure boolean"
NAMES = [x.split()[0] for x in OCCURRENCES.split(", ")]


def found(docs: DataFrame, run, length: int = LENGTH) -> DataFrame:
    """Verified, merged spans (doc, text_key, lo, hi, first_doc) that ``run`` finds in the segments, by minimizer. run: rows of ``SCHEMA`` in order to ``OCCURRENCES``."""
    rows = segments(docs, length).repartition("h").sortWithinPartitions("h", "digest")
    spans = stage(rows.mapInArrow(run, OCCURRENCES))
    own = ["doc", "text_key", "lo", "hi", "first_doc"]
    return merged(spans.filter("sure").select(*own).unionByName(verified(spans.filter("not sure").drop("sure"), docs, length).select(*own)))


def _asked(docs: DataFrame, ranges: DataFrame, whole: bool) -> DataFrame:
    """(doc, text_key, lo, hi, got) of ranges of words of the texts: their 64-bit hash, or the words' codes themselves."""
    ask = ranges.groupBy("doc").agg(F.collect_list(F.struct("text_key", "lo", "hi")).alias("ask"))
    texts = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(NULL_DOC)).alias("doc"), F.col("text").cast("string")).filter("text is not null")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lean()
        codes = Codes()
        for b in (x.slice(at, 500) for x in batches for at in range(0, x.num_rows, 500)):
            docs_, keys, los, his, got = [], [], [], [], []
            ask = b.column(2)
            ends, flat = ask.offsets.to_pylist(), ask.values
            key, lo, hi = (flat.field(i).to_numpy() for i in range(3))
            for i, (doc, text) in enumerate(zip(b.column(0).to_pylist(), b.column(1))):
                code = words(text.as_py(), codes)
                k = text_key(code)
                for j in range(ends[i], ends[i + 1]):
                    if key[j] == k:
                        part = code[lo[j] : hi[j]].tobytes()
                        docs_.append(doc)
                        keys.append(k)
                        los.append(lo[j])
                        his.append(hi[j])
                        got.append(part if whole else xxhash.xxh3_64_intdigest(part) - (1 << 63))
            yield pa.RecordBatch.from_arrays([pa.array(docs_, pa.int64()), pa.array(keys, pa.int64()), pa.array(los, pa.int32()), pa.array(his, pa.int32()), pa.array(got, pa.binary() if whole else pa.int64())], names=["doc", "text_key", "lo", "hi", "got"])

    # rows that are one text answer alike
    return texts.join(ask, "doc").select("doc", "text", "ask").mapInArrow(run, f"doc long, text_key long, lo int, hi int, got {'binary' if whole else 'long'}").dropDuplicates(["doc", "text_key", "lo", "hi"])


def verified(spans: DataFrame, docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """The spans (doc, text_key, lo, hi, first_doc) whose words are those of their first occurrence, by 64 bits a word.

    Pieces of one repeat are put together first, so that each repeat is asked once of either text. Of a span that fails the parts of ``length`` and more words that agree stay."""
    by = Window.partitionBy("doc", "text_key").orderBy("first_doc", "first_key", "shift", "lo")
    same = (F.lag("first_doc").over(by) == F.col("first_doc")) & (F.lag("first_key").over(by) == F.col("first_key")) & (F.lag("shift").over(by) == F.col("shift")) & (F.lag("hi").over(by) >= F.col("lo"))
    runs = spans.withColumn("shift", F.col("first_lo") - F.col("lo")).withColumn("new", F.when(same, 0).otherwise(1))
    runs = runs.withColumn("run", F.sum("new").over(by.rowsBetween(Window.unboundedPreceding, 0)))
    runs = runs.groupBy("doc", "text_key", "run").agg(F.first("first_doc").alias("first_doc"), F.first("first_key").alias("first_key"), F.first("shift").alias("shift"), F.min("lo").alias("lo"), F.max("hi").alias("hi"))
    runs = stage(runs.select("doc", "text_key", "lo", "hi", "first_doc", "first_key", "shift"))
    own = ["doc", "text_key", "lo", "hi"]

    def sides(of: DataFrame, whole: bool) -> DataFrame:
        there = of.select(F.col("first_doc").alias("doc"), F.col("first_key").alias("text_key"), (F.col("lo") + F.col("shift")).alias("lo"), (F.col("hi") + F.col("shift")).alias("hi"))
        got = stage(_asked(docs, of.select(*own).unionByName(there).distinct(), whole))
        far = got.select(F.col("doc").alias("first_doc"), F.col("text_key").alias("first_key"), F.col("lo").alias("first_lo"), (F.col("hi") - F.col("lo")).alias("long"), F.col("got").alias("theirs"))
        return of.withColumn("first_lo", F.col("lo") + F.col("shift")).withColumn("long", F.col("hi") - F.col("lo")).join(got, own).join(far, ["first_doc", "first_key", "first_lo", "long"])

    both = sides(runs, False)
    good = both.filter("got = theirs").select(*own, "first_doc")
    bad = cut(both.filter("got <> theirs").select(*own, "first_doc", "first_key", "shift"))
    if bad.isEmpty():
        return good

    def agree(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lean()
        for b in batches:
            out = []
            for doc, key, lo, first, x, y in zip(*[c.to_pylist() for c in b.columns]):
                same = np.frombuffer(x, np.uint64) == np.frombuffer(y, np.uint64)
                edge = np.flatnonzero(np.diff(np.concatenate([[0], same.astype(np.int8), [0]])))
                out += [(doc, key, lo + int(s), lo + int(e), first) for s, e in zip(edge[::2], edge[1::2]) if e - s >= length]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], t) for i, t in enumerate((pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int64()))], names=[*own, "first_doc"])

    mended = sides(bad, True).select("doc", "text_key", "lo", "first_doc", "got", "theirs").mapInArrow(agree, "doc long, text_key long, lo int, hi int, first_doc long")
    return good.unionByName(mended)


def merged(spans: DataFrame) -> DataFrame:
    """Overlapping or touching spans of a text become one: (doc, text_key, lo, hi, first_doc); of several earlier texts the lowest id."""
    spans = spans.groupBy("doc", "text_key", "lo").agg(F.max("hi").alias("hi"), F.min("first_doc").alias("first_doc"))
    by = Window.partitionBy("doc", "text_key").orderBy("lo")
    reach = F.max("hi").over(by.rowsBetween(Window.unboundedPreceding, -1))
    island = F.sum(F.when(F.col("lo") <= reach, 0).otherwise(1)).over(by.rowsBetween(Window.unboundedPreceding, 0))
    return spans.withColumn("island", island).groupBy("doc", "text_key", "island").agg(F.min("lo").alias("lo"), F.max("hi").alias("hi"), F.min("first_doc").alias("first_doc")).drop("island")


def named(spans: DataFrame) -> DataFrame:
    """Merged spans as a result: (doc_id, start_word, end_word, n_words, first_doc_id)."""
    back = lambda c: F.when(F.col(c) != NULL_DOC, F.col(c))
    return spans.select(back("doc").alias("doc_id"), F.col("lo").alias("start_word"), F.col("hi").alias("end_word"), (F.col("hi") - F.col("lo")).alias("n_words"), back("first_doc").alias("first_doc_id"))
