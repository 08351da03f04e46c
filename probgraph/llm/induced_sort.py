"""Suffix and common-prefix arrays by external induced sorting.

Suffixes are split into those smaller (L) and larger (S) than their successor. The leftmost S suffixes of each run are sorted by recursion on
the string of their substrings' names; all others are induced from them in two scans, left to right for L and right to left
for S. A scan's pending suffixes sit in a disk-backed priority queue, ordered by (first symbol, time of insertion), whose tuples carry the
position and the common prefix with the suffix before it. The common prefix of two neighbours is 1 + the least common prefix between their successors, a
range minimum over the scan since the last insertion for that symbol; across symbols it is 0.

The scan takes as many symbols at a time as induce nothing among themselves (about the square root of what is pending), or a piece of a single symbol's list, and
handles them as arrays. Text, names, sorted seeds, pending and finished suffixes are all blocks of one pool: what passes its budget is on disk, at every level of the recursion.

Prefix values stop at ``cap``. Strings of at most ``base`` symbols end the recursion by doubling."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

from probgraph.llm.external import Column, Pool, Queue

BASE = 1 << 14


def _common(text: Column, a: np.ndarray, b: np.ndarray, known: np.ndarray, cap: int) -> np.ndarray:
    """Common prefixes of suffix pairs, at least ``known`` of which agree, up to cap. The text ends with a symbol that is nowhere else."""
    out = np.minimum(known, cap).astype(np.int64)
    live, n, step = np.flatnonzero(out < cap), len(text), np.arange(8)
    while len(live):
        x, y = (a[live] + out[live])[:, None] + step, (b[live] + out[live])[:, None] + step
        same = (text.take(np.minimum(x, n - 1)) == text.take(np.minimum(y, n - 1))) & (x < n) & (y < n)
        more = np.where(same.all(axis=1), 8, np.argmin(same, axis=1))
        out[live] += more
        live = live[(more == 8) & (out[live] < cap)]
    return np.minimum(out, cap)


class _Ranges:
    """Range minima of one block."""

    def __init__(self, values: np.ndarray):
        self.levels = [values]
        step = 1
        while 2 * step <= len(values):
            last = self.levels[-1]
            self.levels.append(np.minimum(last[:-step], last[step:]))
            step *= 2

    def least(self, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        """Minimum over lo..hi, both ends counted."""
        size = hi - lo + 1
        level = np.frexp(size)[1] - 1
        out = np.empty(len(lo), np.int64)
        for k in np.unique(level).tolist():
            at = level == k
            row = self.levels[k]
            out[at] = np.minimum(row[lo[at]], row[hi[at] - (1 << k) + 1])
        return out


class Sorted:
    """Suffixes in order: positions and prefixes with the one before, kept from last to first."""

    def __init__(self, position: Column, prefix: Column):
        self.position, self.prefix, self.n = position.seal(), prefix.seal(), len(position)

    def chunks(self, size: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        for end in range(self.n, 0, -size):
            lo = max(0, end - size)
            # a suffix's prefix with the one before it is stored with that one, as its prefix with the next
            yield self.position.slice(lo, end)[::-1], np.append(self.prefix.slice(lo + 1, end + 1), np.zeros(max(0, end + 1 - self.n), np.int64))[::-1]

    def drop(self) -> None:
        self.position.drop()
        self.prefix.drop()


class _Seeds:
    """A sorted stream (key, position, prefix) that a scan merges with its queue; keys don't fall."""

    def __init__(self, columns: list[Column], back: bool):
        self.columns, self.back, self.n, self.at = columns, back, len(columns[0]), 0

    def _rows(self, a: int, b: int) -> np.ndarray:
        if not self.back:
            return np.stack([c.slice(a, b) for c in self.columns])
        key, position, prefix = self.columns
        lo, hi = self.n - b, self.n - a
        shifted = np.append(prefix.slice(lo + 1, hi + 1), np.zeros(max(0, hi + 1 - self.n), np.int64))
        return np.stack([-key.slice(lo, hi)[::-1], position.slice(lo, hi)[::-1], shifted[::-1]])

    def window(self, limit: int) -> tuple[np.ndarray, float]:
        rows = self._rows(self.at, min(self.n, self.at + limit))
        if self.at + limit >= self.n:
            return rows, np.inf
        return rows[:, : np.searchsorted(rows[0], rows[0, -1])], rows[0, -1]

    def piece(self, key: int, limit: int) -> np.ndarray:
        rows = self._rows(self.at, min(self.n, self.at + limit))
        rows = rows[:, : np.searchsorted(rows[0], key, "right")]
        self.at += rows.shape[1]
        return rows

    def least(self) -> int:
        return int(self._rows(self.at, self.at + 1)[0, 0])

    def __bool__(self) -> bool:
        return self.at < self.n


class _Scan:
    """One inducing scan. sign -1 takes the symbols from last to first."""

    def __init__(self, text: Column, seeds: _Seeds, sign: int, cap: int, pool: Pool, put):
        self.text, self.seeds, self.sign, self.cap, self.put = text, seeds, sign, cap, put
        self.queue = Queue(pool)
        self.limit = int(min(self.queue.block, max(256, 4 * len(text) ** 0.5)))
        self.key: int | None = None  # of the last block's last suffix
        self.last = (-1, False)
        self.since: dict[int, tuple[int, int]] = {}  # within one symbol's pieces: queue: (least prefix in its block since, number of that block)
        self.blocks: list[int] = []

    def run(self) -> None:
        queue, seeds = self.queue, self.seeds
        while queue or seeds:
            q, q_bound = queue.window(self.limit)
            s, s_bound = seeds.window(self.limit)
            bound = min(q_bound, s_bound)
            q, s = q[:, : np.searchsorted(q[0], bound)], s[:, : np.searchsorted(s[0], bound)]
            rows, fixed = np.concatenate([q, s], axis=1), np.repeat([False, True], [q.shape[1], s.shape[1]])
            end = 0
            if rows.shape[1]:
                order = np.argsort(rows[0], kind="stable")
                rows, fixed = rows[:, order], fixed[order]
                to, live = self.targets(rows, fixed)
                own = live & (to == rows[0]) & (rows[0] != self.key)
                end = self.reach(rows, to, live & ~own)
                if own[:end].any():
                    rows, fixed = self.unrolled(rows[:, :end], fixed[:end], own[:end])
                    to, live = self.targets(rows, fixed)
                    live &= (to != rows[0]) | (rows[0] == self.key)
                    end = self.reach(rows, to, live)
            if end:
                bound = rows[0, end - 1] + 1
                queue.skip_under(bound)
                seeds.at += int(np.count_nonzero(fixed[:end]))
                self.block(rows[:, :end], fixed[:end], to[:end], live[:end], True)
                continue
            key = min(x.least() for x in (queue, seeds) if x)
            rows = queue.piece(key, self.limit) if queue else q
            if done := not rows.shape[1]:
                rows = seeds.piece(key, self.limit)
            fixed = np.full(rows.shape[1], done)
            self.block(rows, fixed, *self.targets(rows, fixed), False)

    @staticmethod
    def reach(rows: np.ndarray, to: np.ndarray, live: np.ndarray) -> int:
        """How many suffixes of whole symbols can be taken so that none induces one of a symbol that is at hand."""
        low = np.minimum.accumulate(np.where(live, to, np.iinfo(np.int64).max))
        fine = np.flatnonzero(np.append(rows[0, 1:] != rows[0, :-1], True) & (low > rows[0]))
        return int(fine[-1]) + 1 if len(fine) else 0

    def unrolled(self, rows: np.ndarray, fixed: np.ndarray, own: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """With all that suffixes induce for their own symbol c: after those that begin with one c come those with two, and so on, each time in the same order."""
        found, levels, seqs = [rows], [np.zeros(rows.shape[1], np.int64)], [np.arange(rows.shape[1])]
        cur, least, level = np.arange(rows.shape[1]), rows[2], 1
        keep = own
        while keep.any():
            if not keep.all():
                # the least prefix since the suffix before that is still there
                at = np.flatnonzero(keep)
                least = np.minimum.reduceat(least[: at[-1] + 1], np.append(0, at[:-1] + 1))
                cur = cur[at]
            key, position = rows[0, cur], rows[1, cur] - level
            prefix = np.minimum(np.where(np.append(True, key[1:] != key[:-1]), level, least + level), self.cap)
            found.append(np.stack([key, position, prefix]))
            levels.append(np.full(len(cur), level))
            seqs.append(cur)
            keep = (position > 0) & (self.sign * self.text.take(np.maximum(position - 1, 0)) == key)
            level += 1
        rows, seq = np.concatenate(found, axis=1), np.concatenate(seqs)
        fixed = np.append(fixed, np.zeros(rows.shape[1] - len(fixed), bool))
        order = np.lexsort((seq, np.concatenate(levels), fixed, rows[0]))
        return rows[:, order], fixed[order]

    def targets(self, rows: np.ndarray, fixed: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Key of the suffix before each one, and whether it is of the scan's kind."""
        before = rows[1] - 1
        to = self.sign * self.text.take(np.maximum(before, 0)).astype(np.int64)
        return to, (before >= 0) & ((to > rows[0]) | (to == rows[0]) & ~fixed)

    def block(self, rows: np.ndarray, fixed: np.ndarray, to: np.ndarray, live: np.ndarray, whole: bool) -> None:
        """Take suffixes in order, and queue those that they induce. whole: nothing of these symbols comes later."""
        key, position, prefix = rows
        n = len(key)
        opens = np.append(key[0] != self.key, key[1:] != key[:-1])
        prefix = np.where(opens, 0, prefix)
        before, was_fixed = np.append(self.last[0], position[:-1]), np.append(self.last[1], fixed[:-1])
        meets = np.flatnonzero(fixed & ~was_fixed & ~opens)
        if len(meets):
            prefix[meets] = _common(self.text, before[meets], position[meets], np.ones(len(meets), np.int64), self.cap)
        if opens[0]:
            self.since.clear()
            self.blocks.clear()
        self.put(key, position, prefix, fixed)
        at = np.flatnonzero(live)
        if len(at):
            goal = to[at]
            order = np.argsort(goal, kind="stable")
            at, goal = at[order], goal[order]
            first = np.append(True, goal[1:] != goal[:-1])
            got = np.ones(len(at), np.int64)
            inner = np.flatnonzero(~first)
            if len(inner):
                got[inner] = 1 + _Ranges(prefix).least(at[inner - 1] + 1, at[inner])
            starts = np.flatnonzero(first)
            if self.since:
                ahead = np.minimum.accumulate(prefix)
                gaps = np.minimum.accumulate(np.array(self.blocks[::-1]))
                for s, c in zip(starts.tolist(), goal[starts].tolist()):
                    if c in self.since:
                        v, b = self.since[c]
                        gap = len(self.blocks) - b - 1
                        got[s] = 1 + min(v, int(ahead[at[s]]), int(gaps[gap - 1]) if gap else self.cap)
            self.queue.push(goal, position[at] - 1, np.minimum(got, self.cap))
            if not whole:
                behind = np.minimum.accumulate(np.append(prefix, self.cap)[::-1])[::-1]
                ends = np.append(starts[1:], len(at)) - 1
                self.since.update(zip(goal[ends].tolist(), zip(behind[at[ends] + 1].tolist(), [len(self.blocks)] * len(ends))))
        self.blocks.append(int(prefix.min()))
        self.key, self.last = int(key[-1]), (int(position[n - 1]), bool(fixed[n - 1]))


def _doubling(text: np.ndarray, cap: int) -> tuple[np.ndarray, np.ndarray]:
    """Base case: suffix array and prefixes (up to cap) of a short string of integers."""
    n = len(text)
    narrow = np.int32 if n < 1 << 30 else np.int64  # the ranks of all levels are most of the memory
    rank = np.unique(text, return_inverse=True)[1].astype(narrow)
    levels, step = [rank], 1
    sa = np.argsort(rank, kind="stable").astype(narrow)
    while rank.max() + 1 < n:
        key = rank.astype(np.int64)
        key *= n + 1
        key[:-step] += rank[step:]
        key[:-step] += 1
        sa = np.argsort(key).astype(narrow)  # equal keys stay equal in rank, so their order doesn't matter before the last round
        key = key[sa]
        rank = np.empty(n, narrow)
        rank[sa[0]] = 0
        rank[sa[1:]] = np.cumsum(key[1:] != key[:-1], dtype=narrow)
        del key
        step *= 2
        levels.append(rank)
    a, b = sa[:-1].copy(), sa[1:].copy()
    out = np.zeros(n, np.int64)
    total = np.zeros(n - 1, narrow)
    for level in range(len(levels) - 1, -1, -1):
        if (1 << level) > 2 * cap:
            continue
        ok = (a < n) & (b < n)
        ok[ok] = levels[level][a[ok]] == levels[level][b[ok]]
        total[ok] += 1 << level
        a[ok] += 1 << level
        b[ok] += 1 << level
    out[1:] = np.minimum(total, cap)
    return sa.astype(np.int64), out


def _leftmost(text: Column, pool: Pool) -> tuple[Column, Column]:
    """(leftmost S positions in order, kind of each position from last to first: 1 for S)."""
    n, kinds, back = len(text), Column(pool, np.uint8), Column(pool)
    kinds.append(np.ones(1, np.uint8))
    after = True  # kind of the position after the chunk
    for end in range(n - 1, 0, -text.block):
        lo = max(0, end - text.block)
        x = text.slice(lo, end + 1)
        change = x[:-1] != x[1:]
        at = np.minimum.accumulate(np.where(change, np.arange(len(change)), len(change))[::-1])[::-1]
        up = np.append(x[:-1] < x[1:], after)
        kind = up[at]
        both = np.append(kind, after)
        back.append((np.flatnonzero(both[1:] & ~both[:-1]) + lo + 1)[::-1])
        kinds.append(kind[::-1])
        after = bool(kind[0])
    back.seal()
    out = Column(pool)
    for end in range(len(back), 0, -back.block):
        out.append(back.slice(max(0, end - back.block), end)[::-1])
    back.drop()
    return out.seal(), kinds.seal()


def _names(text: Column, lms: Column, kinds: Column, top: int, pool: Pool) -> tuple[Queue, bool]:
    """(queue of (order-preserving name, number, 0) of the substrings between neighbouring leftmost S positions, both ends counted; whether all names differ)."""
    n, m = len(text), len(lms)
    unit = 2 * (top + 2) + 2
    per = max(1, int((62 - np.log2(m + 1)) // np.log2(unit)))
    named, same = Queue(pool), False

    def key(rank: np.ndarray, which: np.ndarray, at: int) -> np.ndarray:
        begin = lms.take(which)
        end = np.where(which + 1 < m, lms.take(np.minimum(which + 1, m - 1)), n - 1)
        out = rank.copy()
        for j in range(at, at + per):
            x = np.minimum(begin + j, n - 1)
            code = np.where(begin + j <= end, 2 * (text.take(x).astype(np.int64) + 1) + kinds.take(n - 1 - x), 0)
            out = out * unit + code
        return out

    def size(which: np.ndarray) -> np.ndarray:
        return np.where(which + 1 < m, lms.take(np.minimum(which + 1, m - 1)), n - 1) - lms.take(which) + 1

    live, step = Queue(pool), live_block(pool)
    for a in range(0, m, step):
        which = np.arange(a, min(m, a + step))
        live.push(key(np.zeros(len(which), np.int64), which, 0), which, np.zeros(len(which), np.int64))
    at = 0
    while live:
        at += per
        more = Queue(pool)
        last = (None, None, 0)  # key, old rank, new rank
        opened, passed = 0, 0  # rows of the old rank before, rows of the old rank so far
        for rows in live.drain():
            k, which, old = rows
            # a name is where its group starts within the old one
            new_old = np.append(old[0] != last[1], old[1:] != old[:-1])
            new = np.append(k[0] != last[0], k[1:] != k[:-1])
            index = np.arange(len(k))
            begin = np.maximum.accumulate(np.where(new_old, index, -passed if not new_old[0] else 0))
            group = np.maximum.accumulate(np.where(new, index, -1))
            rank = np.where(group >= 0, old + group - begin, last[2])
            tied = ~new | np.append(~new[1:], False)
            tied |= k == k[-1] if bool(live) else False  # the group may go on
            tied |= ~new[0] & (group < 0)
            go = tied & (size(which) > at)
            same |= bool((~new & ~go).any())
            named.push(rank[~go], which[~go], np.zeros(int((~go).sum()), np.int64))
            more.push(key(rank[go], which[go], at), which[go], rank[go])
            passed = len(k) - int(begin[-1])
            last = (int(k[-1]), int(old[-1]), int(rank[-1]))
        live = more
    return named, not same


def live_block(pool: Pool) -> int:
    return max(64, pool.budget // 64 // 24)


def external_arrays(text: Column, cap: int, pool: Pool, base: int = BASE) -> Sorted:
    """Suffix order of a text of integers over 0 that ends with its only 0; that suffix is left out. Two texts are never held at once in memory beyond the pool's budget."""
    n, step = len(text), live_block(pool)
    top = max((int(x.max()) for x in text.chunks()), default=0)
    lms, kinds = _leftmost(text, pool)
    m = len(lms)
    named, distinct = _names(text, lms, kinds, top, pool)
    kinds.drop()

    def by_name() -> Iterator[tuple[np.ndarray, np.ndarray]]:
        if distinct:
            for rows in named.drain():
                yield rows[1], np.zeros(rows.shape[1], np.int64)
            return
        placed = Queue(pool)
        for rows in named.drain():
            placed.push(rows[1], rows[0], rows[2])
        reduced = Column(pool)
        for rows in placed.drain():
            reduced.append(rows[1] + 1)
        reduced.seal()
        if m <= base:
            order, shared = _doubling(reduced.slice(0, m), cap)
            reduced.drop()
            yield order, shared
            return
        # the recursion's text ends as this one does
        ended = Column(pool)
        for x in reduced.chunks():
            ended.append(x)
        reduced.drop()
        ended.append(np.zeros(1, np.int64))
        found = external_arrays(ended.seal(), cap, pool, base)
        ended.drop()
        yield from found.chunks(step)
        found.drop()

    seeds = [Column(pool) for _ in range(3)]
    last = -1
    for order, shared in by_name():
        position = lms.take(order)
        before = np.append(last, position[:-1])
        # names in common, in symbols: the distance to the first different name
        known = lms.take(np.minimum(order + shared, m - 1)) - position
        prefix = np.zeros(len(order), np.int64)
        real = before >= 0
        prefix[real] = _common(text, before[real], position[real], known[real], cap)
        for c, x in zip(seeds, (text.take(position), position, prefix)):
            c.append(x)
        last = int(position[-1])
    lms.drop()
    larger = [Column(pool) for _ in range(3)]

    def put_larger(key, position, prefix, fixed) -> None:
        own = ~fixed
        # the prefix with the L suffix before: none where a symbol starts
        for c, x in zip(larger, (key[own], position[own], prefix[own])):
            c.append(x)

    for c in seeds:
        c.seal()
    _Scan(text, _Seeds(seeds, False), 1, cap, pool, put_larger).run()
    for c in seeds:
        c.drop()
    out = Column(pool), Column(pool)

    def put(key, position, prefix, fixed) -> None:
        out[0].append(position)
        out[1].append(prefix)

    _Scan(text, _Seeds([c.seal() for c in larger], True), -1, cap, pool, put).run()
    for c in larger:
        c.drop()
    # going down, a prefix is with the next larger suffix
    return Sorted(*out)


def suffix_arrays(text: np.ndarray, cap: int = 1 << 30, budget: int = 256 << 20, folder: str | None = None, base: int = BASE) -> tuple[np.ndarray, np.ndarray]:
    """(suffix array, common prefix of each suffix with the one before it, at most cap) of integers from 0; a suffix that ends is smaller. For texts whose result fits in memory."""
    if not len(text):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    with Pool(budget, folder) as pool:
        line = Column(pool, np.int64)
        for at in range(0, len(text), line.block):
            line.append(np.asarray(text[at : at + line.block], np.int64) + 1)
        line.append(np.zeros(1, np.int64))
        found = list(external_arrays(line.seal(), cap, pool, base).chunks(1 << 20))
        return np.concatenate([f[0] for f in found]), np.concatenate([f[1] for f in found])
