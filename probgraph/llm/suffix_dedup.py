"""Operator 4: suffix-array dedup. Passages of at least 50 words that occurred before, found by external induced sorting.

Segments of all texts (see :mod:`probgraph.llm.passages`) are grouped by the hash of their minimizer. In a task, the distinct segments of some minimizers are
laid end to end as a string of 16-bit words, whose suffix and common-prefix arrays are built by :mod:`probgraph.llm.induced_sort`. Windows between neighbours that share 50 words
and more are one window: the suffix order alone decides. Of equal windows the first in order of (doc_id, text hash, place) stays, the others are
duplicates; they are verified against the texts, by 64 bits a word, and spans are merged per text.

Text, places, names, pending and sorted suffixes of a shard are blocks of one pool: what passes ``budget`` bytes is in files under ``spark.checkpoint.dir``, on any
file system that pyarrow opens. In memory are the rows read at a time (``part`` bytes), about 60 bytes for each distinct segment, and the windows of one class of equals.

Null, empty and shorter texts have no passages. Rows equal in doc_id and text are one text and no copies of each other. A text that repeats itself loses all
but the first occurrence. Empty tables, very long texts, ties and further columns: see :mod:`probgraph.llm.passages`; :func:`without` keeps all columns, whatever their names."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from probgraph.llm import induced_sort, passages
from probgraph.llm.external import Column, Pool, Queue
from probgraph.llm.passages import LENGTH, NULL_DOC, PART, Contents, found, joined, named, shards
from probgraph.llm.text import Codes, words
from probgraph.runtime import cut as cut_, lean
from probgraph.runtime import fresh, shared_dir, small, stage

BUDGET = 256 << 20


def repeated(contents: Contents) -> Iterator[pa.RecordBatch]:
    """Rows of ``OCCURRENCES``."""
    c, length, pool = contents, contents.length, contents.pool
    yield from c.again()
    step = induced_sort.live_block(pool)
    text = Column(pool, np.int32)
    for x in c.words.chunks():
        text.append(x)
    text.append(np.zeros(1, np.int32))
    order = induced_sort.external_arrays(text.seal(), length, pool)
    text.drop()
    place = Queue(pool)  # windows that occur again, by place: (place, first window)

    def classes(position: np.ndarray, run: np.ndarray) -> None:
        """Complete runs of equal windows, in order of run."""
        which, off = c.of(position)
        window = off < c.n[which]  # suffixes that begin after the last window of their segment are none
        position, run, which, off = position[window], run[window], which[window], off[window]
        if not len(run):
            return
        start = np.flatnonzero(np.append(True, run[1:] != run[:-1]))
        size = np.diff(np.append(start, len(run)))
        first = np.minimum.reduceat(c.rank[which] << 32 | off, start)
        again = np.repeat(size > 1, size)
        place.push(position[again], np.repeat(first, size)[again], np.zeros(int(again.sum()), np.int64))

    held, total = [], 0
    for position, prefix in order.chunks(step):
        run = total + np.cumsum(prefix < length)
        total = int(run[-1])
        held.append((position, run))
        if run[0] == total and held[0][1][0] == total:
            continue  # the run goes on
        position, run = (np.concatenate(x) for x in zip(*held))
        done = int(np.searchsorted(run, total))
        classes(position[:done], run[:done])
        held = [(position[done:], run[done:])]
    order.drop()
    if held:
        classes(*(np.concatenate(x) for x in zip(*held)))
    by_rank = np.argsort(c.rank)
    for rows in place.drain():
        which, off = c.of(rows[0])
        yield c.spans(*joined(which, off, by_rank[rows[1] >> 32], (rows[1] & 0xFFFFFFFF) - off))


def duplicate_spans(docs: DataFrame, length: int = LENGTH, budget: int = BUDGET, part: int = PART) -> DataFrame:
    """(doc, text_key, lo, hi, first_doc) of passages that occurred before, merged per text."""
    place = shared_dir(docs.sparkSession) + "/scratch"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lean()
        with Pool(budget, place) as pool:
            contents = Contents(pool, length)
            for rows, goes_on in shards(batches, part):
                contents.add(rows, goes_on)
                if not goes_on and len(contents):
                    yield from repeated(contents.seal())
                    contents.words.drop()
                    contents.places.drop()
                    contents = Contents(pool, length)

    return found(docs, run, length)


def suffix_dedup(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """(doc_id, start_word, end_word, n_words, first_doc_id) of every duplicate span."""
    return named(duplicate_spans(docs, length))


def without(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """The rows of ``docs`` with duplicate spans cut out of the text and ``n_chars`` (where there is such a column) brought up to date.

    A text that loses all its words is dropped; other texts are unchanged, those without words too."""
    import pandas as pd
    from pyspark.sql import types as T

    columns = docs.columns
    spans = fresh(docs, "dup_spans")
    found = stage(duplicate_spans(docs, length)).groupBy("doc", "text_key").agg(F.array_sort(F.collect_list(F.struct("lo", "hi"))).alias("parts"))
    # one row a document id: its texts' spans by text key
    doc = fresh(docs, "dup_doc")
    found = small(cut_(found.groupBy(F.col("doc").alias(doc)).agg(F.collect_list(F.struct("text_key", "parts")).alias(spans))))

    def cut(parts: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.Series]:
        codes = Codes()
        for texts, found_ in parts:
            yield pd.Series([_cut(t, f, codes) for t, f in zip(texts, found_)], dtype=object)

    udf = F.pandas_udf(cut, T.StringType(), F.PandasUDFType.SCALAR_ITER)
    marked = docs.withColumn(doc, F.coalesce(F.col("doc_id").cast("long"), F.lit(NULL_DOC))).join(found, doc, "left")
    sure = marked.filter(F.col(spans).isNull() | F.col("text").isNull())
    new = fresh(docs, "dup_text")
    # only texts with spans go through Python
    rest = marked.filter(F.col(spans).isNotNull() & F.col("text").isNotNull()).withColumn(new, udf(F.col("text"), F.col(spans))).filter(F.col(new).isNotNull())
    if "n_chars" in columns:
        rest = rest.withColumn("n_chars", F.when(F.col(new) == F.col("text"), F.col("n_chars")).otherwise(F.length(new).cast(docs.schema["n_chars"].dataType)))
    return sure.select(columns).unionByName(rest.withColumn("text", F.col(new)).select(columns))


def _cut(text: str | None, found, codes: Codes) -> str | None:
    """The text without the spans found for its key; None if no word is left."""
    if text is None or found is None or len(found) == 0:
        return text
    code = words(text, codes)
    key = passages.text_key(code)
    parts = [p for f in found if f["text_key"] == key for p in f["parts"]]
    if not parts:
        return text
    from probgraph.llm.text import spans

    at = spans(text, codes)
    if sum(p["hi"] - p["lo"] for p in parts) >= len(at):
        return None
    out, done = [], 0
    for p in parts:
        out.append(text[done : at[p["lo"]][0]])
        done = at[p["hi"] - 1][1]
    out.append(text[done:])
    return "".join(out)
