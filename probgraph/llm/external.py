"""Arrays and a priority queue larger than memory: blocks in a pool of bounded size, the rest in files of a scratch folder.

A :class:`Pool` holds blocks up to ``budget`` bytes; the least recently used ones are written to ``uri``, on any file system that
pyarrow can open, and read again when they are asked for. A block never changes, so it is written once at most. Without ``uri`` everything stays in
memory. :class:`Column` is an array of blocks, :class:`Queue` a priority queue of sorted runs of blocks."""

from __future__ import annotations

import uuid
from collections import OrderedDict
from collections.abc import Iterator

import numpy as np


class Pool:
    def __init__(self, budget: int, uri: str | None = None):
        self.budget, self.uri = budget, uri
        self.live: OrderedDict[int, np.ndarray] = OrderedDict()
        self.saved: dict[int, tuple[np.dtype, tuple[int, ...]]] = {}
        self.used = self.peak = self.made = self.spilled = 0
        self.fs = self.path = None

    def _open(self) -> None:
        from pyarrow import fs

        self.fs, base = fs.FileSystem.from_uri(self.uri)
        self.path = f"{base.rstrip('/')}/pool-{uuid.uuid4().hex}"
        self.fs.create_dir(self.path, recursive=True)

    def _trim(self) -> None:
        while self.used > self.budget and len(self.live) > 1 and self.uri:
            i, x = self.live.popitem(last=False)
            self.used -= x.nbytes
            if i not in self.saved:
                if self.fs is None:
                    self._open()
                with self.fs.open_output_stream(f"{self.path}/{i}") as f:
                    f.write(np.ascontiguousarray(x))
                self.saved[i] = (x.dtype, x.shape)
                self.spilled += x.nbytes

    def _keep(self, i: int, x: np.ndarray) -> None:
        self.live[i] = x
        self.used += x.nbytes
        self._trim()
        self.peak = max(self.peak, self.used)

    def put(self, x: np.ndarray) -> int:
        self.made += 1
        self._keep(self.made, x)
        return self.made

    def get(self, i: int) -> np.ndarray:
        if (x := self.live.get(i)) is not None:
            self.live.move_to_end(i)
            return x
        dtype, shape = self.saved[i]
        with self.fs.open_input_stream(f"{self.path}/{i}") as f:
            x = np.frombuffer(f.read(), dtype).reshape(shape)
        self._keep(i, x)
        return x

    def drop(self, i: int) -> None:
        if (x := self.live.pop(i, None)) is not None:
            self.used -= x.nbytes
        if self.saved.pop(i, None) is not None:
            self.fs.delete_file(f"{self.path}/{i}")

    def close(self) -> None:
        self.live.clear()
        if self.fs is not None:
            self.fs.delete_dir(self.path)
            self.fs = None

    def __enter__(self) -> Pool:
        return self

    def __exit__(self, *_) -> None:
        self.close()


class Column:
    """An array that is appended to, sealed, and then read."""

    def __init__(self, pool: Pool, dtype=np.int64):
        self.pool, self.dtype = pool, np.dtype(dtype)
        self.block = max(64, pool.budget // 32 // self.dtype.itemsize)
        self.ids: list[int] = []
        self.tail: list[np.ndarray] = []
        self.n = self.waiting = 0

    def append(self, x: np.ndarray) -> None:
        self.tail.append(np.asarray(x, self.dtype))
        self.n += len(x)
        self.waiting += len(x)
        if self.waiting >= self.block:
            self._flush(self.block)

    def _flush(self, least: int) -> None:
        t = np.concatenate(self.tail) if self.tail else np.zeros(0, self.dtype)
        at = 0
        while len(t) - at >= least and at < len(t):
            self.ids.append(self.pool.put(t[at : at + self.block].copy()))
            at += self.block
        self.tail, self.waiting = [t[at:]] if at < len(t) else [], max(0, len(t) - at)

    def seal(self) -> Column:
        self._flush(1)
        return self

    def __len__(self) -> int:
        return self.n

    def slice(self, a: int, b: int) -> np.ndarray:
        a, b = max(a, 0), min(b, self.n)
        if a >= b:
            return np.zeros(0, self.dtype)
        parts = [self.pool.get(self.ids[k])[max(0, a - k * self.block) : b - k * self.block] for k in range(a // self.block, (b - 1) // self.block + 1)]
        return parts[0] if len(parts) == 1 else np.concatenate(parts)

    def take(self, at: np.ndarray) -> np.ndarray:
        if len(self.ids) == 1:
            return self.pool.get(self.ids[0])[at]
        out = np.empty(at.shape, self.dtype)
        which = at // self.block
        for k in np.unique(which).tolist():
            here = which == k
            out[here] = self.pool.get(self.ids[k])[at[here] - k * self.block]
        return out

    def chunks(self, size: int | None = None) -> Iterator[np.ndarray]:
        size = size or self.block
        for at in range(0, self.n, size):
            yield self.slice(at, at + size)

    def drop(self) -> None:
        for i in self.ids:
            self.pool.drop(i)
        self.ids, self.tail, self.n = [], [], 0


class _Run:
    """Blocks of rows (key, a, b) in order of key, read from the front."""

    def __init__(self, ids: list[int], rows: int):
        self.ids, self.rows, self.at = ids, rows, 0  # at: within the first block


class Queue:
    """Priority queue of (key, a, b): by key, then by time of insertion.

    Insertions are sorted runs; neighbouring small ones are merged, and all of them when there are over ``MOST``."""

    MOST = 24

    def __init__(self, pool: Pool):
        self.pool = pool
        self.block = max(64, pool.budget // 64 // 24)
        self.runs: list[_Run] = []

    def __bool__(self) -> bool:
        return bool(self.runs)

    def _run(self, rows: np.ndarray) -> _Run:
        return _Run([self.pool.put(np.ascontiguousarray(rows[:, at : at + self.block])) for at in range(0, rows.shape[1], self.block)], rows.shape[1])

    def _front(self, run: _Run) -> np.ndarray:
        return self.pool.get(run.ids[0])[:, run.at :]

    def _skip(self, run: _Run, rows: int) -> None:
        run.at += rows
        run.rows -= rows
        if run.at >= self.pool.get(run.ids[0]).shape[1]:
            self.pool.drop(run.ids.pop(0))
            run.at = 0

    def push(self, key: np.ndarray, a: np.ndarray, b: np.ndarray) -> None:
        if not len(key):
            return
        rows = np.stack([key, a, b]).astype(np.int64, copy=False)
        if len(key) > 1 and (key[1:] < key[:-1]).any():
            rows = rows[:, np.argsort(key, kind="stable")]
        self.runs.append(self._run(rows))
        while len(self.runs) > 1 and 2 * self.runs[-1].rows >= self.runs[-2].rows and len(self.runs[-1].ids) == len(self.runs[-2].ids) == 1 and self.runs[-1].rows + self.runs[-2].rows <= self.block:
            new, old = self.runs.pop(), self.runs.pop()
            both = np.concatenate([self._front(old), self._front(new)], axis=1)
            for i in old.ids + new.ids:
                self.pool.drop(i)
            self.runs.append(self._run(both[:, np.argsort(both[0], kind="stable")]))
        if len(self.runs) > self.MOST:
            ids, total = [], 0
            while self.runs:
                got = self._run(self.next(self.block))
                ids += got.ids
                total += got.rows
            self.runs = [_Run(ids, total)]

    def least(self) -> int:
        return min(int(self._front(r)[0, 0]) for r in self.runs)

    def window(self, limit: int) -> tuple[np.ndarray, float]:
        """(rows, bound): all rows of keys under ``bound``, in order; not taken out. None may be under it."""
        bound, parts = np.inf, []
        for r in self.runs:
            part = self._front(r)[:, :limit]
            if part.shape[1] < r.rows:
                bound = min(bound, part[0, -1])
            parts.append(part)
        parts = [p if bound == np.inf else p[:, : np.searchsorted(p[0], bound)] for p in parts]
        rows = parts[0] if len(parts) == 1 else np.concatenate(parts, axis=1) if parts else np.zeros((3, 0), np.int64)
        return (rows[:, np.argsort(rows[0], kind="stable")] if len(parts) > 1 else rows), bound

    def skip_under(self, bound: float) -> None:
        """Take out what a window showed under ``bound``."""
        for r in self.runs:
            while r.rows and (k := int(np.searchsorted(self._front(r)[0], bound))):
                self._skip(r, k)
                if r.rows and r.at:
                    break
        self.runs = [r for r in self.runs if r.rows]

    def piece(self, key: int, limit: int) -> np.ndarray:
        """Takes out the rows of a key that were inserted first, as many as are at hand; no columns if there are none."""
        for r in self.runs:
            front = self._front(r)
            if front[0, 0] == key:
                got = front[:, : min(limit, int(np.searchsorted(front[0], key, "right")))]
                self._skip(r, got.shape[1])
                self.runs = [r for r in self.runs if r.rows]
                return got
        return np.zeros((3, 0), np.int64)

    def next(self, limit: int) -> np.ndarray:
        """Takes out some of the first rows, in order."""
        rows, bound = self.window(limit)
        if not rows.shape[1]:
            return self.piece(self.least(), limit)
        self.skip_under(bound)
        return rows

    def drain(self, limit: int | None = None) -> Iterator[np.ndarray]:
        while self.runs:
            yield self.next(limit or self.block)
