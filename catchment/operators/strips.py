"""Sweeps inside strips of the x axis: what needs counts, or every pair of every slab, without moving a label.

Squares (columns tile, xl, xh, yl, yh, n, more) are dealt to the strips that they reach, by cuts at sides of each tile. A task
holds the y order of one strip's squares as arrays and takes the strip's events in order, so an event costs a slice
of them. What leaves a strip are its counts, or its rows batch by batch; labels are never shuffled.

``label_totals`` deals a square only to the groups of strips that hold one of its sides. Of the squares that span a
group, which would be dealt to all groups, it gets a profile along y, worked out in ranges of y from all squares at once.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Sides of a strip, about.
EVENTS = 1024
#: Rows of a batch that leaves a strip.
ROWS = 1 << 16


def cuts_of(squares: DataFrame, events: int = EVENTS) -> dict[int, np.ndarray]:
    """Interior cuts by tile, each at a side of a square; tiles of few events have none. One number for ``events`` sides."""
    sides = squares.select("tile", F.explode(F.array("xl", "xh")).alias("x"))
    large = {r["tile"]: r["c"] for r in sides.groupBy("tile").agg(F.count("*").alias("c")).filter(F.col("c") > events).collect()}
    if not large:
        return {}
    most = -(-max(large.values()) // events)
    at = [i / most for i in range(1, most)]
    rows = sides.join(F.broadcast(squares.sparkSession.createDataFrame([(t,) for t in large], "tile long")), "tile")
    found = rows.groupBy("tile").agg(F.percentile_approx("x", at, max(10_000, 20 * most)).alias("cuts")).collect()
    every = {t: max(1, most // -(-c // events)) for t, c in large.items()}
    return {r["tile"]: np.unique(np.array(r["cuts"][every[r["tile"]] - 1 :: every[r["tile"]]], np.int64)) for r in found}


def _strip_of(cuts: dict[int, np.ndarray], tile: np.ndarray, x: np.ndarray) -> np.ndarray:
    """The strip of each x in its tile."""
    out = np.zeros(len(tile), np.int64)
    for t in np.unique(tile).tolist():
        if t in cuts:
            own = tile == t
            out[own] = np.searchsorted(cuts[t], x[own], side="right")
    return out


def _deal(cuts: dict[int, np.ndarray], columns: int):
    """Rows once for each strip that they reach with their closed x range, the strip as last column."""

    def run(batches):
        for batch in batches:
            tile, xl, xh = (batch.column(i).to_numpy() for i in range(3))
            first, last = _strip_of(cuts, tile, xl), _strip_of(cuts, tile, xh)
            times = last - first + 1
            begin = np.cumsum(times) - times
            for lo in range(0, len(tile), 4096):
                part = slice(lo, lo + 4096)
                row = np.repeat(np.arange(len(tile))[part], times[part])
                strip = first[row] + np.arange(begin[lo], begin[lo] + len(row)) - begin[row]
                yield pa.RecordBatch.from_arrays([batch.column(i).take(pa.array(row)) for i in range(columns)] + [pa.array(strip)], names=[*batch.schema.names, "strip"])

    return run


def _by_strip(cuts: dict[int, np.ndarray], work, numbered: bool = False):
    """Hand over each strip's squares as arrays (rows are sorted by tile and strip), with the range of its events.

    ``numbered`` work, on one tile, gets the strip's number in place of the tile's.
    """

    def whole(tile: int, strip: int, held: list):
        own = cuts.get(tile, np.empty(0, np.int64))
        lo = int(own[strip - 1]) if strip else None
        hi = int(own[strip]) if strip < len(own) else None
        columns = [np.concatenate([b.column(i).to_numpy() for b in held]) for i in range(1, held[0].num_columns - 1)]
        return work(strip if numbered else tile, columns, lo, hi)

    def run(batches):
        key, held = None, []
        for batch in batches:
            tile, strip = batch.column(0).to_numpy(), batch.column(batch.num_columns - 1).to_numpy()
            turns = (np.flatnonzero((tile[1:] != tile[:-1]) | (strip[1:] != strip[:-1])) + 1).tolist()
            for a, b in zip([0, *turns], [*turns, len(tile)]):
                if a == b:
                    continue
                now = (int(tile[a]), int(strip[a]))
                if held and now != key:
                    yield from whole(*key, held)
                    held = []
                key = now
                held.append(batch.slice(a, b - a))
        if held:
            yield from whole(*key, held)

    return run


def in_strips(squares: DataFrame, work, schema: str, events: int = EVENTS, more: tuple[str, ...] = (), numbered: bool = False) -> DataFrame:
    """What ``work(tile, [xl, xh, yl, yh, n, more], first event, end of events)`` yields for every strip, as batches of ``schema``."""
    rows = squares if "tile" in squares.columns else squares.withColumn("tile", F.lit(0))
    rows = rows.select(*[F.col(c).cast("long") for c in ("tile", "xl", "xh", "yl", "yh", "n", *more)])
    cuts = cuts_of(rows, events)
    kind = ", ".join(f"{c} long" for c in (*rows.columns, "strip"))
    dealt = rows.mapInArrow(_deal(cuts, len(rows.columns)), kind)
    parts = max(2 * rows.sparkSession.sparkContext.defaultParallelism, min(1024, sum(map(len, cuts.values())) // 4))
    placed = dealt.repartition(parts, "tile", "strip").sortWithinPartitions("tile", "strip")
    return placed.mapInArrow(_by_strip(cuts, work, numbered), schema)


def _turns(xl, xh, lo, hi):
    """The strip's events in order: x of each, where its rows begin, and the rows (square, +1 at its left or -1 at its right side)."""
    inside = lambda x: np.flatnonzero((x >= lo if lo is not None else x == x) & (x < hi if hi is not None else x == x))
    left, right = inside(xl), inside(xh)
    x = np.concatenate([xl[left], xh[right]])
    order = np.argsort(x, kind="stable")
    x, at = np.unique(x[order], return_index=True)
    return x, [*at.tolist(), len(order)], np.concatenate([left, right])[order].tolist(), np.repeat([1, -1], [len(left), len(right)])[order].tolist()


def _merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Closed spans, touching ones as one."""
    if len(spans) == 1:
        return spans
    out: list[list[int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1][1] = max(b, out[-1][1])
        else:
            out.append([a, b])
    return [(a, b) for a, b in out]


class _Status:
    """The y order of a strip's squares: sides 0.., gap g below side g (gap 0 is below all), and what is alive.

    ``sides[i]`` counts the live squares with a side at ys[i], ``depth[g]`` is the sum of a measure over gap g.
    """

    def __init__(self, columns, lo):
        xl, _, yl, yh, *measures = columns
        self.ys, at = np.unique(np.concatenate([yl, yh]), return_inverse=True)
        self.a, self.b = at[: len(yl)], at[len(yl) :]
        live = np.flatnonzero(xl < lo) if lo is not None else np.empty(0, np.int64)
        size = len(self.ys)
        self.lower, self.upper = np.bincount(self.a[live], minlength=size), np.bincount(self.b[live], minlength=size)
        self.sides = self.lower + self.upper
        self.depths = []
        for m in measures:
            turn = np.zeros(size + 2, np.int64)
            np.add.at(turn, self.a[live] + 1, m[live])
            np.add.at(turn, self.b[live] + 1, -m[live])
            self.depths.append(np.cumsum(turn)[: size + 1])
        self.measures = measures
        self.al, self.bl, self.ml = self.a.tolist(), self.b.tolist(), [m.tolist() for m in measures]

    def turn(self, k: int, sign: int) -> None:
        a, b = self.al[k], self.bl[k]
        self.lower[a] += sign
        self.upper[b] += sign
        self.sides[a] += sign
        self.sides[b] += sign
        for depth, m in zip(self.depths, self.ml):
            depth[a + 1 : b + 1] += sign * m[k]

    def turn_all(self, who: np.ndarray, signs: np.ndarray) -> None:
        """``turn`` of many squares at once."""
        a, b = self.a[who], self.b[who]
        for counts, at in ((self.lower, a), (self.upper, b), (self.sides, a), (self.sides, b)):
            np.add.at(counts, at, signs)
        for depth, m in zip(self.depths, self.measures):
            turn = np.zeros(len(depth) + 1, np.int64)
            np.add.at(turn, a + 1, signs * m[who])
            np.add.at(turn, b + 1, -signs * m[who])
            depth += np.cumsum(turn)[: len(depth)]


def _heats(tile, columns, lo, hi):
    """Of one strip by heat: pairs in changed intervals (k), pairs of all slabs (k_all), and the parts of the plane's faces less
    their links over borders (chi: the faces' number less that of their holes), parts outside every pair included."""
    status = _Status(columns, lo)
    depth, sides = status.depths[0], status.sides
    x, at, who, sign = _turns(columns[0], columns[1], lo, hi)
    live = 2 * (int(status.lower.sum()))
    m = len(x)
    seen = {"k": [], "k_all": [], "chi": []}
    start = np.concatenate([[0], depth[1:][sides > 0]])
    seen["k_all"].append((start, m))
    closed = 0
    for i in range(m):
        rows = range(at[i], at[i + 1])
        spans = _merged([(status.al[who[r]], status.bl[who[r]]) for r in rows])
        for a, b in spans:
            seen["k_all"].append((depth[a + 1 : b + 2][sides[a : b + 1] > 0], i - m))
        for r in rows:
            status.turn(who[r], sign[r])
            live += 2 * sign[r]
        closed += 2 if live else 1
        for a, b in spans:
            now = depth[a + 1 : b + 2][sides[a : b + 1] > 0]
            seen["k"].append((now[:-1], 1))
            seen["k_all"].append((now, m - i))
            seen["chi"].append((now, 1))
            seen["chi"].append((depth[b + 1 : b + 2].copy(), -1))
    sums = {}
    for name, parts in seen.items():
        if parts:
            keys, weights = np.concatenate([p for p, _ in parts]), np.repeat([w for _, w in parts], [len(p) for p, _ in parts])
            found, which = np.unique(keys, return_inverse=True)
            total = np.zeros(len(found), np.int64)
            np.add.at(total, which, weights)
            sums[name] = dict(zip(found.tolist(), total.tolist()))
        else:
            sums[name] = {}
    sums["k_all"][0] = sums["k_all"].get(0, 0) - closed
    if lo is None:
        sums["chi"][0] = sums["chi"].get(0, 0) + 1
    keys = sorted(set().union(*sums.values()))
    yield pa.RecordBatch.from_arrays([pa.array([tile] * len(keys), pa.int64()), pa.array(keys, pa.int64()), *[pa.array([sums[s].get(h, 0) for h in keys], pa.int64()) for s in ("k", "k_all", "chi")]], names=["tile", "heat", "k", "k_all", "chi"])


def heat_counts(squares: DataFrame, events: int = EVENTS) -> DataFrame:
    """(heat, k, k_all, chi): labels of the changed-interval sweep, of the full-slab sweep, and faces less their holes, by heat."""
    found = in_strips(squares, _heats, "tile long, heat long, k long, k_all long, chi long", events)
    return found.groupBy("heat").agg(*[F.sum(c).alias(c) for c in ("k", "k_all", "chi")])


#: Strips of a group, at least and at most; in between, the largest tile has about ``GROUPS`` groups.
FEW, MANY, GROUPS = 4, 64, 64


def _deal_ends(cuts: dict[int, np.ndarray]):
    """Squares (kind 0) once for each group that holds one of their sides."""

    def run(batches):
        for batch in batches:
            tile, xl, xh = (batch.column(i).to_numpy() for i in range(3))
            first, last = _strip_of(cuts, tile, xl), _strip_of(cuts, tile, xh)
            again = np.flatnonzero(last > first)
            row = pa.array(np.concatenate([np.arange(len(tile)), again]))
            whole = batch.take(row)
            kind = pa.array(np.zeros(len(row), np.int64))
            yield pa.RecordBatch.from_arrays([whole.column(0), kind, *whole.columns[1:], pa.array(np.concatenate([first, last[again]]))], names=PLACED)

    return run


#: Columns of what a group gets: a to e are xl, xh, yl, yh, n of a square (kind 0), or a row of the profile (see ``_profiles``).
PLACED = ["tile", "kind", "a", "b", "c", "d", "e", "strip"]


def _deal_sides(cuts: dict[int, np.ndarray], heights: dict[int, np.ndarray]):
    """Lower and upper sides of squares by ranges of y: (tile, y, groups of the left and right side, n or -n, range)."""

    def run(batches):
        for batch in batches:
            tile, xl, xh, yl, yh, n = (batch.column(i).to_numpy() for i in range(6))
            span = (_strip_of(cuts, tile, xl) << 32) + _strip_of(cuts, tile, xh)
            tile, y = np.concatenate([tile, tile]), np.concatenate([yl, yh])
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in (tile, y, np.concatenate([span, span]), np.concatenate([n, -n]), _strip_of(heights, tile, y))], names=["tile", "y", "span", "turn", "strip"])

    return run


def _profiles(cuts: dict[int, np.ndarray]):
    """Of one range of y: for every group what the squares that span it have there, between sides of the group's own squares.

    A row of kind 2 for each own y: whether a side of a spanning square lies there (b), how many distinct ones lie above it, before the
    next own y (c), and the greatest depth there (d). A row of kind 1 for what lies below the first own y: c, d, and how much the
    depth grows over the range (e). Depths are relative to the depth at the range's upper end.
    """

    def work(tile, columns, lo, hi):
        y, span, turn = columns
        first, last = span >> 32, span & 0xFFFFFFFF
        ys, rank = np.unique(y, return_inverse=True)
        size = len(ys)
        held, count = [], 0
        for g in range(len(cuts[tile]) + 1):
            still = np.flatnonzero((first < g) & (g < last))
            at = np.flatnonzero(np.bincount(rank[(first == g) | (last == g)], minlength=size))
            if not len(still) and not len(at):
                continue
            there = np.bincount(rank[still], minlength=size) > 0
            # sums of integers, exact in doubles below 2^53
            depth = np.cumsum(np.bincount(rank[still], weights=turn[still], minlength=size).astype(np.int64))
            depth, grown = depth - depth[-1], depth[-1]
            seen = np.concatenate([[0], np.cumsum(there)])
            begin = int(at[0]) if len(at) else size
            lead = (1, ys[0], 0, seen[begin], max(-grown, depth[:begin].max(initial=-grown)), grown)
            above = seen[np.append(at[1:], size)] - seen[at + 1] if len(at) else at
            best = np.maximum.reduceat(depth, at) if len(at) else at
            rows = [np.full(len(at), 2), ys[at], there[at], above, best, np.zeros(len(at))]
            rows = [np.concatenate([[v], c]).astype(np.int64) for v, c in zip(lead, rows)]
            held.append([np.full(len(rows[0]), tile), *rows, np.full(len(rows[0]), g)])
            count += len(rows[0])
            if count >= ROWS:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*held)], names=PLACED)
                held, count = [], 0
        if count:
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*held)], names=PLACED)

    return work


def _strip_totals(columns, lo, hi, own, ys, there, above, depth_above):
    """Of one strip, of whose squares ``own`` have a side in it: how many pairs its changed intervals hold, and the greatest heat of one.

    Only own squares' sides stand in the y order; of the others, alive throughout, it is known for each y of ``ys``
    whether a side lies there, how many distinct ones lie above it before the next y, and the greatest depth there.
    """
    moving = [c[own] for c in columns]
    status = _Status(moving, lo)
    x, at, who, sign = _turns(moving[0], moving[1], lo, hi)
    sides, depth = status.sides, status.depths[0]
    place = np.searchsorted(ys, status.ys)
    depth[1:] += np.maximum.reduceat(depth_above, place)
    passed, more = np.concatenate([[0], np.cumsum(there)]), np.concatenate([[0], np.cumsum(above)])
    between = passed[place[1:]] - passed[place[:-1] + 1] + more[place[1:]] - more[place[:-1]]
    within = np.concatenate([[0], np.cumsum(between)])
    sides += there[place]
    k, best = 0, 0
    for i in range(len(x)):
        rows = range(at[i], at[i + 1])
        if len(rows) > 32:
            status.turn_all(np.array(who[at[i] : at[i + 1]]), np.array(sign[at[i] : at[i + 1]]))
        else:
            for r in rows:
                status.turn(who[r], sign[r])
        for a, b in _merged([(status.al[who[r]], status.bl[who[r]]) for r in rows]):
            met = np.count_nonzero(sides[a : b + 1]) + int(within[b] - within[a])
            if met > 1:
                k += met - 1
                # every gap between the ends; what lies outside a pair has no greater depth
                best = max(best, int(depth[a + 1 : b + 1].max()))
    return k, best


def _totals(events: int):
    """Of one group, strip by strip: pairs in changed intervals and the greatest heat."""

    def work(tile, columns, lo, hi):
        kind = columns[0]
        squares = xl, xh, yl, yh, n = [c[kind == 0] for c in columns[1:]]
        if not len(xl):
            return
        ys, at = np.unique(np.concatenate([yl, yh]), return_inverse=True)
        a, b = at[: len(yl)], at[len(yl) :]
        there, above, top = np.zeros(len(ys), bool), np.zeros(len(ys), np.int64), np.zeros(len(ys), np.int64)
        if len(xl) < len(kind):
            profile = [c[kind != 0] for c in columns]
            order = np.lexsort(profile[:2])
            kinds, _, sides, counts, best, grown = (c[order] for c in profile)
            begin = np.flatnonzero(kinds == 2)
            there, above, top = sides[begin] > 0, np.add.reduceat(counts, begin), np.maximum.reduceat(best + np.cumsum(grown), begin)
        x = np.sort(np.concatenate([v[(v >= lo if lo is not None else v == v) & (v < hi if hi is not None else v == v)] for v in (xl, xh)]))
        inner = np.unique(x[events::events]).tolist()
        k, best = 0, 0
        for left, right in zip([lo, *inner], [*inner, hi]):
            inside = lambda v: (v >= left if left is not None else v == v) & (v < right if right is not None else v == v)  # noqa: B023, E731
            own = inside(xl) | inside(xh)
            if not own.any():
                continue
            # nothing is alive before the first event or after the last one
            still = ~own & (xl < left) & (xh >= right) if left is not None and right is not None else np.zeros(len(xl), bool)
            low, high = a[still], b[still]
            lower, upper = np.bincount(low, minlength=len(ys)), np.bincount(high, minlength=len(ys))
            # sums of integers, exact in doubles below 2^53
            turn = np.bincount(low, weights=n[still], minlength=len(ys)) - np.bincount(high, weights=n[still], minlength=len(ys))
            found = _strip_totals(squares, left, right, own, ys, there | (lower + upper > 0), above, top + np.cumsum(turn.astype(np.int64)))
            k, best = k + found[0], max(best, found[1])
        yield pa.RecordBatch.from_arrays([pa.array([v], pa.int64()) for v in (tile, k, best)], names=["tile", "labels", "max_heat"])

    return work


def label_totals(squares: DataFrame, events: int = EVENTS, group: int | None = None) -> DataFrame:
    """(tile, labels, max_heat) of the changed-interval sweep of every tile, no label made; ``group`` is the sides of a group.

    What is shuffled grows with the squares, not with the strips that they span: a square goes to at most two groups, its
    sides to a range of y each, and a profile has at most a row for each side of a group's squares and one for each range.
    """
    rows = squares.select(*[F.col(c).cast("long") for c in ("tile", "xl", "xh", "yl", "yh", "n")])
    if group is None:
        largest = rows.groupBy("tile").agg(F.count("*").alias("c")).agg(F.max("c")).first()[0] or 0
        group = events * min(MANY, max(FEW, 2 * largest // (events * GROUPS)))
    cuts = cuts_of(rows, group)
    kind = ", ".join(f"{c} long" for c in PLACED)
    parts = max(2 * rows.sparkSession.sparkContext.defaultParallelism, min(1024, 2 * sum(map(len, cuts.values()))))
    dealt = rows.mapInArrow(_deal_ends(cuts), kind)
    if cuts:
        heights = cuts_of(rows.select("tile", F.col("yl").alias("xl"), F.col("yh").alias("xh")), group)
        large = rows.join(F.broadcast(rows.sparkSession.createDataFrame([(t,) for t in cuts], "tile long")), "tile")
        sides = large.mapInArrow(_deal_sides(cuts, heights), "tile long, y long, span long, turn long, strip long")
        ranges = sides.repartition(parts, "tile", "strip").sortWithinPartitions("tile", "strip")
        dealt = dealt.unionByName(ranges.mapInArrow(_by_strip(heights, _profiles(cuts)), kind))
    placed = dealt.repartition(parts, "tile", "strip").sortWithinPartitions("tile", "strip")
    found = placed.mapInArrow(_by_strip(cuts, _totals(events)), "tile long, labels long, max_heat long")
    return found.groupBy("tile").agg(F.sum("labels").alias("labels"), F.max("max_heat").alias("max_heat"))


def _status_rows(tile, columns, lo, hi):
    """Of one strip: a row for every event after which squares are alive, from their sides in order (y, lower ones first)."""
    status = _Status(columns, lo)
    x, at, who, sign = _turns(columns[0], columns[1], lo, hi)
    rows = [[] for _ in range(5)]
    for i in range(len(x)):
        for r in range(at[i], at[i + 1]):
            status.turn(who[r], sign[r])
        there = np.flatnonzero(status.sides)
        if not len(there):
            continue
        low, both = status.lower[there], status.sides[there]
        high, before = both - low, np.cumsum(both) - both
        # positions from before + 1 on: first those of lower sides, then those of upper ones
        signed = low * before + low * (low + 1) // 2 - high * (before + low) - high * (high + 1) // 2
        for column, value in zip(rows, (int(x[i]), int(both.sum()), int(status.ys[there[0]]), int(status.ys[there[-1]]), int(signed.sum()))):
            column.append(value)
    yield pa.RecordBatch.from_arrays([pa.array(r, pa.int64()) for r in rows], names=["x", "elements", "lowest", "highest", "signed_pos"])


def status_summary(squares: DataFrame, events: int = EVENTS) -> DataFrame:
    """(x, elements, lowest, highest, signed_pos) of the line status after every event but the last: how many sides, the ends, and
    positions of lower sides less those of upper ones. No status is written out."""
    return in_strips(squares, _status_rows, "x long, elements long, lowest long, highest long, signed_pos long", events)


def _pairs(measures: int, box):
    x0, x1, y0, y1 = box or (None,) * 4
    names = ["x0", "x1", "y0", "y1", *[f"m{i}" for i in range(measures)]]

    def work(tile, columns, lo, hi):
        status = _Status([*columns[:4], *columns[5:]], lo)
        x, at, who, sign = _turns(columns[0], columns[1], lo, hi)
        held, count = [], 0
        for i in range(len(x)):
            for r in range(at[i], at[i + 1]):
                status.turn(who[r], sign[r])
            ends = (int(x[i]), int(x[i + 1]) if i + 1 < len(x) else hi)
            if ends[1] is None or box and (ends[0] >= x1 or ends[1] <= x0):
                continue
            there = np.flatnonzero(status.sides)
            y = status.ys[there]
            low, high, gap = y[:-1], y[1:], there[:-1] + 1
            if box:
                met = (low < y1) & (high > y0)
                low, high, gap, ends = np.maximum(low[met], y0), np.minimum(high[met], y1), gap[met], (max(ends[0], x0), min(ends[1], x1))
            held.append([np.full(len(low), ends[0]), np.full(len(low), ends[1]), low, high, *[d[gap] for d in status.depths]])
            count += len(low)
            if count >= ROWS:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*held)], names=names)
                held, count = [], 0
        if count:
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*held)], names=names)

    return work


def surface_pairs(squares: DataFrame, measures: tuple[str, ...] = ("n",), box: tuple[int, int, int, int] | None = None, events: int = EVENTS) -> DataFrame:
    """(x0, x1, y0, y1, measures) of the full-slab sweep of one tile, every pair of every slab, clipped to the open box if one
    is given; rows leave the task that makes them, and none is made outside the box."""
    kind = ", ".join(f"{c} long" for c in ("x0", "x1", "y0", "y1", *[f"m{i}" for i in range(len(measures))]))
    if box:
        # a slab that meets the box begins at or before its right side, its squares reach its left side
        squares = squares.filter((F.col("xl") <= box[1]) & (F.col("xh") >= box[0]))
    more = tuple(f"_{m}" for m in measures)
    found = in_strips(squares.withColumns({f"_{m}": F.col(m) for m in measures}), _pairs(len(measures), box), kind, events, more)
    return found.withColumnsRenamed({f"m{i}": m for i, m in enumerate(measures)})


#: Ids and slab borders of a batch of runs that leaves a strip, about.
HELD = 1 << 19


def _steps(status: _Status, events):
    """A run is a pair over the slabs in which neither its sides nor its set change. For every event (at first None, for what is
    there before the strip): the lower sides of the runs that end, those of the runs that begin, the upper side of the pair above
    each side (-1: none), and above which sides the set has changed."""
    _, at, who, sign = events
    size = len(status.ys)
    top, same = np.full(size, -1, np.int64), np.zeros(size, bool)

    def now(changed):
        nonlocal top
        there = np.flatnonzero(status.sides)
        new = np.full(size, -1, np.int64)
        new[there[:-1]] = there[1:]
        other = (new != top) | changed
        ended, begun = np.flatnonzero(other & (top >= 0)), np.flatnonzero(other & (new >= 0))
        top = new
        return ended, begun, new, changed

    yield None, *now(same)
    for i in range(len(at) - 1):
        changed = same.copy()
        for r in range(at[i], at[i + 1]):
            status.turn(who[r], sign[r])
            changed[status.al[who[r]] : status.bl[who[r]]] = True
        yield i, *now(changed)


def _sets(number, columns, lo, hi):
    """Of one strip, its squares one for each member: the runs with their sets and the borders of their slabs."""
    order = np.argsort(columns[5], kind="stable")
    xl, xh, yl, yh, _, oid = (c[order] for c in columns)
    status = _Status([xl, xh, yl, yh], lo)
    events = x, at, who, sign = _turns(xl, xh, lo, hi)
    marks = x if hi is None else np.append(x, hi)
    live = xl < lo if lo is not None else np.zeros(len(xl), bool)
    begun: dict[int, tuple[int, int, np.ndarray]] = {}
    held: list[tuple] = []
    amount = 0

    def batch():
        low, high, members, borders = zip(*held)
        listed = lambda parts: pa.ListArray.from_arrays(pa.array(np.cumsum([0, *map(len, parts)]), pa.int32()), pa.array(np.concatenate(parts)))
        return pa.RecordBatch.from_arrays([pa.array(status.ys[list(low)]), pa.array(status.ys[list(high)]), listed(members), listed(borders)], names=["y0", "y1", "rnn", "xs"])

    def end(p, i):
        q, start, members = begun.pop(p)
        if i > start:
            held.append((p, q, members, marks[start : i + 1]))
            return len(members) + i + 1 - start
        return 0

    for i, ended, opened, top, _ in _steps(status, events):
        for p in ended.tolist():
            amount += end(p, i)
            if amount >= HELD:
                yield batch()
                held.clear()
                amount = 0
        for r in range(at[i], at[i + 1]) if i is not None else ():
            live[who[r]] = sign[r] > 0
        there = np.flatnonzero(live)
        a, b, ids = status.a[there], status.b[there], oid[there]
        part = max(1, (1 << 22) // max(1, len(there)))
        for first in range(0, len(opened), part):
            some = opened[first : first + part]
            pair, which = np.nonzero((a <= some[:, None]) & (b > some[:, None]))
            found, stops = ids[which], np.cumsum(np.bincount(pair, minlength=len(some))).tolist()
            for p, q, lo_, hi_ in zip(some.tolist(), top[some].tolist(), [0, *stops], stops):
                begun[p] = q, i or 0, found[lo_:hi_].copy()
    for p in list(begun):
        amount += end(p, len(marks) - 1)
        if amount >= HELD:
            yield batch()
            held.clear()
            amount = 0
    if held:
        yield batch()


def surface_set_runs(squares: DataFrame, events: int = EVENTS) -> DataFrame:
    """(y0, y1, rnn, xs) of one tile: pairs of the full-slab sweep with their sets, one row for all slabs of a strip in a row in which
    the pair stays; xs are these slabs' borders."""
    each = squares.select("xl", "xh", "yl", "yh", F.lit(1).alias("n"), F.explode("members").alias("oid"))
    return in_strips(each, _sets, "y0 long, y1 long, rnn array<long>, xs array<long>", events, ("oid",))


def slabs_of(runs: DataFrame) -> DataFrame:
    """The runs' rows slab by slab: x0 and x1 in place of xs."""
    kept = [c for c in runs.columns if c != "xs"]
    each = runs.select(*kept, "xs", F.posexplode("xs").alias("_at", "x0")).filter("_at + 1 < size(xs)")
    return each.select("x0", F.expr("xs[_at + 1]").alias("x1"), *kept)


def _faces(number, columns, lo, hi):
    """Of one strip: the parts that its faces have in it (kind 0: node, the least slab rectangle, and the heat that an enclosure query of
    that rectangle's centre finds among the strip's squares), and the nodes of the pairs at its left (1) and right border (2)."""
    xl, xh, yl, yh, n = columns
    status = _Status(columns[:4], lo)
    events = x, *_ = _turns(xl, xh, lo, hi)
    marks = (x if hi is None else np.append(x, hi)).tolist()
    # run 0 is the exterior
    up, start, low, high = [0], [0], [0], [0]
    own = np.zeros(len(status.ys) + 1, np.int64)

    def root(u):
        while up[u] != u:
            up[u] = u = up[up[u]]
        return u

    left, spans = range(0), {}
    for i, ended, opened, top, changed in _steps(status, events):
        fresh = np.arange(len(up), len(up) + len(opened))
        now = own.copy()
        for p in ended.tolist():
            now[p + 1 : spans.pop(p) + 1] = 0
        for p, q, k in zip(opened.tolist(), top[opened].tolist(), fresh.tolist()):
            now[p + 1 : q + 1] = k
            spans[p] = q
        up += fresh.tolist()
        start += [i or 0] * len(opened)
        low += opened.tolist()
        high += top[opened].tolist()
        if i is None:
            left = range(1, len(up))
        else:
            kept = (now != own) & ~np.concatenate([[False], changed])
            for u, v in set(zip(own[kept].tolist(), now[kept].tolist())):
                u, v = root(u), root(v)
                up[max(u, v)] = min(u, v)
            if i == 0:
                # what ends at the border has no slab here
                gone = set(left) - set(np.unique(now).tolist())
        own = now
    gone = gone if len(x) else set(left)
    roots = [root(u) for u in range(len(up))]
    name = lambda u: (number + 1 << 32) + roots[u] if roots[u] else -1
    best: dict[int, tuple] = {}
    for u in range(1, len(up)):
        if roots[u] and u not in gone and start[u] + 1 < len(marks):
            place = (start[u], low[u], high[u])
            if roots[u] not in best or place < best[roots[u]]:
                best[roots[u]] = place
    nodes, places = list(best), np.array(list(best.values()), np.int64).reshape(-1, 3)
    at, ys = np.array(marks, np.int64), status.ys
    x0, y0, y1 = at[places[:, 0]], ys[places[:, 1]], ys[places[:, 2]]
    x1 = at[places[:, 0] + 1]
    heat = np.zeros(len(nodes), np.int64)
    part = max(1, (1 << 22) // max(1, len(xl)))
    for first in range(0, len(nodes), part):
        s = slice(first, first + part)
        qx, qy = (x0 + x1)[s, None], (y0 + y1)[s, None]
        heat[s] = ((2 * xl < qx) & (qx < 2 * xh) & (2 * yl < qy) & (qy < 2 * yh)) @ n
    names = ["kind", "node", "x0", "y0", "x1", "y1", "n"]
    rows = lambda kind, node, *c: pa.RecordBatch.from_arrays([pa.array(np.full(len(node), kind)), pa.array(node, pa.int64()), *[pa.array(v, pa.int64()) for v in c]], names=names)
    yield rows(0, [name(u) for u in nodes], x0, y0, x1, y1, heat)
    right = sorted(set(own.tolist()) - {0}) if hi is not None else []
    for kind, some, border in ((1, list(left), lo), (2, right, hi)):
        if some:
            one = np.full(len(some), border)
            yield rows(kind, [name(u) for u in some], one, ys[[low[u] for u in some]], one, ys[[high[u] for u in some]], np.zeros(len(some), np.int64))


def face_parts(squares: DataFrame, events: int = EVENTS) -> DataFrame:
    """(kind, node, x0, y0, x1, y1, n) of one tile, see ``_faces``: pairs of kinds 1 and 2 with equal x0, y0 are one; node -1 is the exterior."""
    return in_strips(squares, _faces, "kind long, node long, x0 long, y0 long, x1 long, y1 long, n long", events, numbered=True)
