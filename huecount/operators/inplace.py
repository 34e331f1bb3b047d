"""Four-cycles of bare edges on flat graphs, summed where they start. Every task reads the lists of neighbours as they are written
and takes its share of the starts, some at a time: no candidate becomes a row of a join, and none is moved."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from huecount.operators.graph import MOST_NEAR, id_of

#: Candidates that a task looks at together, if one start has no more; rows that leave it together.
LOT, ROWS = 1 << 17, 1 << 17
#: Ids below this are looked up in a table, others by halving.
LOW_ID = 1 << 25


def fits(ctx) -> bool:
    """Whether tasks may take starts in place: on flat graphs. A count of one start is at most twice the square of the arcs, which both
    a long and a double hold."""
    return 0 < ctx.coloring.k <= 16 and ctx.graph.flat_parts() > 0 and ctx.graph.work()["arcs"] <= MOST_NEAR


def _spread(start: np.ndarray, size: np.ndarray) -> np.ndarray:
    """start[0], start[0] + 1, ... (size[0] of them), then those of start[1], and so on."""
    before = np.cumsum(size) - size
    return np.repeat(start - before, size) + np.arange(int(size.sum()))


class _Lists:
    """Vertices by their place in the order, their colours in every trial, and their neighbours' places."""

    def __init__(self, batches: Iterator[pa.RecordBatch]):
        keys, hues, deals, sizes, near, self.part = [], [], [], [], [], None
        for b in batches:
            if not b.num_rows:
                continue
            self.part = b.column("part")[0].as_py()
            keys.append(b.column("tail").to_numpy())
            hues.append(b.column("hues").flatten().to_numpy().astype(np.int64))
            deals.append(b.column("deal").to_numpy())
            sizes.append(np.diff(b.column("near").offsets.to_numpy()).astype(np.int64))
            near.append(b.column("near").flatten().to_numpy())
        if self.part is None:
            return
        key, size = np.concatenate(keys), np.concatenate(sizes)
        order, self.sorted = np.argsort(key), {}
        self.key, self.size, self.start = key[order], size[order], (np.cumsum(size) - size)[order]
        self.deal = np.concatenate(deals)[order]
        self.hues = np.concatenate(hues).reshape(len(key), -1)[order].T.copy()
        low = (1 << 40) - 1
        if int((self.key & low).max()) < LOW_ID:
            at = np.zeros(int((self.key & low).max()) + 1, np.int32)
            at[self.key & low] = np.arange(len(key), dtype=np.int32)
            self.near = np.concatenate([at[x & low] for x in near])
        else:
            self.near = np.concatenate([np.searchsorted(self.key, x).astype(np.int32) for x in near])

    def by_colour(self, trial: int, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Neighbours of every vertex in the order of their colours, where those of each colour begin, and how many they are."""
        if trial not in self.sorted:
            of = np.repeat(np.arange(len(self.key)), self.size)
            near = self.near[_spread(self.start, self.size)]
            cell = of * k + self.hues[trial][near]
            many = np.bincount(cell, minlength=len(self.key) * k)
            self.sorted = {trial: (near[np.argsort(cell, kind="stable")], (np.cumsum(many) - many).reshape(-1, k), many.reshape(-1, k))}
        return self.sorted[trial]

    def lots(self, parts: int, side: int | None) -> Iterator[np.ndarray]:
        """This part's starts, in lots of about as many candidates."""
        own = np.arange(self.part, len(self.key), parts)
        own = own if side is None else own[(self.key[own] & 1) == side]
        if len(own):
            of = np.repeat(np.arange(len(own)), self.size[own])
            found = np.bincount(of, weights=self.size[self.near[_spread(self.start[own], self.size[own])]], minlength=len(own))
            yield from np.split(own, np.flatnonzero(np.diff(np.cumsum(found) // LOT)) + 1)


def _arcs(g: _Lists, own: np.ndarray, high: bool) -> tuple[np.ndarray, np.ndarray]:
    """Arcs from some starts: the start's place among own, and the other end."""
    hi, mid = np.repeat(np.arange(len(own)), g.size[own]), g.near[_spread(g.start[own], g.size[own])].astype(np.int64)
    below = mid < own[hi] if high else slice(None)
    return hi[below], mid[below]


def _halves(g: _Lists, own: np.ndarray, high: bool | str, k: int) -> Iterator[tuple]:
    """high: True if the start is to be the highest, "end" if the end is. For each trial: the paths start, mid, end from some starts that have three colours, as hi (the start's place among own), mid and of (which
    arc it goes over), end; then the distinct pairs of ends as hi * vertices + end, and how many paths of each colour in the middle they have."""
    n, (hi, mid) = len(g.key), _arcs(g, own, high is True)
    of = np.repeat(np.arange(len(mid)), g.size[mid])
    end = g.near[_spread(g.start[mid], g.size[mid])].astype(np.int64)
    if high:
        far = end > np.maximum(own[hi], mid)[of] if high == "end" else end < own[hi[of]]
        of, end = of[far], end[far]
    for trial, hue in enumerate(g.hues):
        first, second, third = hue[own][hi], hue[mid], hue[end]
        ok = (third != second[of]) & (third != first[of]) & (first != second)[of]
        arc, w = of[ok], end[ok]
        if not len(w):
            continue
        pair, c = hi[arc] * n + w, second[arc]
        told = np.sort(pair * k + c)
        at = np.flatnonzero(np.concatenate(([True], told[1:] != told[:-1])))
        many, told = np.diff(np.append(at, len(told))), told[at]
        new = np.concatenate(([True], told[1:] // k != told[:-1] // k))
        table = np.zeros((int(new.sum()), k), np.int64)
        table[np.cumsum(new) - 1, told % k] = many
        yield trial, hue, hi, mid, arc, w, pair, told[new] // k, table


def _met(g: _Lists, own: np.ndarray, high: bool, k: int, keep_tail: bool) -> Iterator[tuple]:
    """Both halves of a cycle are paths of three: two of them with the same ends and other colours in the middle."""
    for trial, hue, _, _, _, _, _, ends, table in _halves(g, own, high, k):
        hi, w = np.divmod(ends, len(g.key))
        for s in range(k):
            for t in range(s + 1, k):
                cnt = 2 * table[:, s] * table[:, t]
                if keep_tail:
                    at = np.flatnonzero(cnt)
                    a, b, cnt, colour = own[hi[at]], w[at], cnt[at], hue[w[at]]
                else:
                    cnt = np.bincount(hi * k + hue[w], weights=cnt, minlength=1).astype(np.int64)
                    at = np.flatnonzero(cnt)
                    a = b = own[at // k]
                    cnt, colour = cnt[at], at % k
                yield trial, a, b, (1 << s | 1 << t) | np.left_shift(1, hue[a]) | np.left_shift(1, colour), cnt


def _closed(g: _Lists, own: np.ndarray, high: bool, k: int, keep_tail: bool) -> Iterator[tuple]:
    """Cycles by one of their arcs: an arc and one step more is a path of three, which meets the other ones with the same ends."""
    for trial, hue, hi, mid, arc, w, pair, ends, table in _halves(g, own, high, k):
        row, cell = np.searchsorted(ends, pair), arc * k + hue[w]
        cnt = np.stack([np.bincount(cell, weights=table[row, c], minlength=len(mid) * k).astype(np.int64).reshape(-1, k) for c in range(k)], axis=2)
        cnt[np.arange(len(mid)), :, hue[mid]] = 0
        for s in range(k):
            for t in range(s + 1, k):
                both = cnt[:, s, t] + cnt[:, t, s]
                at = np.flatnonzero(both)
                a, b = own[hi[at]], mid[at]
                yield trial, a, b, (1 << s | 1 << t) | np.left_shift(1, hue[a]) | np.left_shift(1, hue[b]), both[at]


def _grouped(code: np.ndarray, weight: np.ndarray, space: int) -> tuple[np.ndarray, np.ndarray]:
    """The codes that occur, below space, and the sums of their weights, none of them 0."""
    if space <= 8 * len(code):
        sums = np.bincount(code, weights=weight, minlength=1).astype(np.int64)
        return (at := np.flatnonzero(sums)), sums[at]
    order = np.argsort(code)
    code = code[order]
    at = np.flatnonzero(np.concatenate((np.ones(min(1, len(code)), bool), code[1:] != code[:-1])))
    return code[at], np.add.reduceat(weight[order], at) if len(at) else weight[:0]


def _longer(g: _Lists, own: np.ndarray, high: bool, k: int, keep_tail: bool) -> Iterator[tuple]:
    """Paths of four, one step beyond paths of three: neighbours of a colour are taken out only if it is free."""
    n = len(g.key)
    for trial, hue, _, _, _, _, _, ends, table in _halves(g, own, high, k):
        near, first, many = g.by_colour(trial, k)
        row, c = np.nonzero(table)
        hi, y = ends[row] // n, ends[row] % n
        base = 1 << c | np.left_shift(1, hue[own[hi]]) | np.left_shift(1, hue[y])
        parts = [(at, d) for d in range(k) if len(at := np.flatnonzero(base >> d & 1 == 0))]
        at, d = np.concatenate([x for x, _ in parts]), np.concatenate([np.full(len(x), d) for x, d in parts])
        size = many[y[at], d]
        at, d, size = at[size > 0], d[size > 0], size[size > 0]
        sigs, of = np.unique(base[at] | np.left_shift(1, d), return_inverse=True)
        for i in range(len(sigs)):  # one set of colours after the other
            own_at, d_i, size_i = at[of == i], d[of == i], size[of == i]
            w = near[_spread(first[y[own_at], d_i], size_i)]
            code, cnt = _grouped(np.repeat(hi[own_at] * n, size_i) + w, np.repeat(table[row[own_at], c[own_at]], size_i), len(own) * n)
            yield trial, own[code // n], code % n, np.full(len(code), sigs[i]), cnt


def _dealt(ctx, deal: int = 1) -> DataFrame:
    """part, tail, near, hues (colours in every trial), deal (the part out of so many that rows of this start would lie in): all lists for every part."""
    g = ctx.graph
    parts = 4 * g.spark.sparkContext.defaultParallelism
    hues = F.array(*[ctx.coloring.color(id_of(F.col("tail")), F.lit(t)).cast("tinyint") for t in range(ctx.coloring.trials)])
    lists = g.lists().select("tail", "near", hues.alias("hues"), F.pmod(F.hash("tail"), F.lit(deal)).alias("deal")).coalesce(1)
    # A product of partitions: each task reads the lists for itself, nothing is gathered or moved.
    return lists.crossJoin(g.spark.range(0, parts, 1, parts).select(F.col("id").alias("part")).hint("shuffle_replicate_nl"))


def _rows(ctx, high: bool | str, kind: Callable, keep_tail: bool = False) -> DataFrame:
    """trial, h, tail, sig, cnt (not summed)."""
    k, side, parts = ctx.coloring.k, ctx.side, 4 * ctx.graph.spark.sparkContext.defaultParallelism
    schema = pa.schema([("trial", pa.int32()), ("h", pa.int64()), ("tail", pa.int64()), ("sig", pa.int64()), ("cnt", pa.int64())])

    def out(some: list[tuple]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in zip(*some, strict=True)], schema=schema)

    def share(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lists, some, n = _Lists(batches), [], 0
        for own in lists.lots(parts, side) if lists.part is not None else ():
            for trial, a, b, sig, cnt in kind(lists, own, high, k, keep_tail):
                some.append((np.full(len(a), trial, np.int32), lists.key[a], lists.key[b], sig, cnt))
                n += len(a)
                if n >= ROWS:
                    yield out(some)
                    some, n = [], 0
        if n:
            yield out(some)

    return _dealt(ctx).mapInArrow(share, "trial int, h long, tail long, sig long, cnt long")


def met(ctx, high: bool, keep_tail: bool) -> DataFrame:
    """Pairs of paths of three with the same ends, by their start, by both ends if the tail is kept."""
    return _rows(ctx, high, _met, keep_tail)


def closed(ctx, high: bool | str = False) -> DataFrame:
    """Cycles by one of their arcs, h to tail. high: those whose highest vertex is h (True) or the one opposite to h ("end")."""
    return _rows(ctx, high, _closed)


def longer(ctx) -> DataFrame:
    """Paths of four, by their ends, summed."""
    return _rows(ctx, False, _longer)


STEPS = ("seed", "extend", "merge")


def loads(ctx, high: bool) -> DataFrame:
    """step, part, candidates, kept of the steps of ``met``, as joins of rows dealt by their start would have them."""
    k, deal, parts = ctx.coloring.k, ctx.graph.flat_parts(ctx.coloring.trials, "high" if high else "plain"), 4 * ctx.graph.spark.sparkContext.defaultParallelism

    def share(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        g = _Lists(batches)
        if g.part is None:
            return
        told = np.zeros((len(STEPS), 2, deal), np.int64)

        def tell(step: int, kept: int, starts: np.ndarray, many: np.ndarray | None = None) -> None:
            told[step, kept] += np.bincount(g.deal[starts], weights=many, minlength=deal).astype(np.int64)

        for own in g.lots(parts, None):
            hi, mid = _arcs(g, own, high)
            for hue in g.hues:
                ok = hue[own[hi]] != hue[mid]
                tell(0, 0, own[hi])
                tell(0, 1, own[hi[ok]])
                tell(1, 0, own[hi[ok]], g.size[mid[ok]])
            for _, _, hi_, _, arc, _, _, ends, table in _halves(g, own, high, k):
                tell(1, 1, own[hi_[arc]])
                found = (table > 0).sum(axis=1)
                tell(2, 0, own[ends // len(g.key)], found * found)
                tell(2, 1, own[ends // len(g.key)], found * (found - 1))
        step, part = np.nonzero(told[:, 0])
        yield pa.RecordBatch.from_arrays([pa.array([STEPS[x] for x in step], pa.string()), pa.array(part.astype(np.int32)), pa.array(told[step, 0, part]), pa.array(told[step, 1, part])], names=["step", "part", "candidates", "kept"])

    rows = _dealt(ctx, deal).mapInArrow(share, "step string, part int, candidates long, kept long")
    return rows.groupBy("step", "part").agg(F.sum("candidates").alias("candidates"), F.sum("kept").alias("kept"))
