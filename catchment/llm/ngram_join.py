"""N-gram Jaccard self-join, size-aware: fixed-size subsets for light sets, inverted lists for heavy ones.

A text's set holds its distinct word shingles (64-bit hashes stand for them and for whole sets).
Equal sets form one class; links are sought between classes, so copies cost one row each.

* Light classes (set size up to a boundary) enumerate every subset of the size that a partner of
  each possible size needs. Sharing such a subset is the link itself: no check follows.
* Heavy classes put the rarest part of their set into inverted lists: as two linked sets overlap
  in all but a fifth of either, each must show a common element there. Light classes near the
  boundary stand in the lists too. Length and position bounds cut what is checked, exact overlap
  decides.
* The boundary is the size at which the rows that enumeration makes outgrow the cost of list
  entries, summed over the size histogram of the corpus.

Long lists are never paired out. First each list is checked against one pivot for each size
band, the member with the fewest rare elements (in a group of near copies, what they are copies of); components of those links are formed, and only pairs of list members that still lie in
different components are checked after that, cell by cell.

``n_links`` counts every text that links with a text, its copies too. Links lie inside components, so the classes of a
component are dealt into cells and every pair of cells is one piece of work that gives each class one number:
overlaps are counted through the elements that two cells share, common ones as products of 0/1 matrices, and no pair
becomes a row. That is quadratic in the different texts of one component, as the count itself is; ``links=False`` leaves it out.

Results for odd input: null or blank text has no shingles and its own id as component; a null id
keeps its row, takes part in no link and has a null component; rows with one id and several texts
are separate texts that report the same id; columns other than id and text are ignored.
"""

from __future__ import annotations

from itertools import combinations
from math import comb

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import U, bitmap_bits, by_bytes, column_bytes, id_slots, in_batches, lean, materialize, mix, release, shrink_driver, signed, slices, slot_hit, without_ids, word_hashes

_ROLL = [U(0x9FB21C651E98DF25), U(0xD6E8FEB86659FD93), U(0xA0761D6478BD642F), U(0xE7037ED1A0B428DB), U(0x8EBC6AF09C88C6E3)]


def shingle_sets(texts: list, width: int = 5):
    """Sorted distinct shingle hashes of each text (None for null, empty for no words)."""
    for lo, hi in slices([len(t or b"") for t in texts], 1 << 20):
        part = [None if t is None else t.lower().split() for t in texts[lo:hi]]
        hashes = word_hashes(b" ".join(b" ".join(w) for w in part if w))
        at = 0
        rolled = None
        if len(hashes) >= width:
            rolled = np.zeros(len(hashes) - width + 1, np.uint64)
            for k in range(width):
                rolled += hashes[k : k + len(rolled)] * (_ROLL[k % 5] + U(2 * (k // 5)))
            rolled = mix(rolled)
        for w in part:
            if w is None:
                yield None
                continue
            n = len(w)
            if n >= width:
                yield np.unique(rolled[at : at + n - width + 1])
            elif n:
                mult = np.array([_ROLL[k % 5] + U(2 * (k // 5)) for k in range(n)], np.uint64)
                yield mix(mix(np.array([(hashes[at : at + n] * mult).sum(dtype=np.uint64) + U(n)], np.uint64)))
            else:
                yield np.empty(0, np.uint64)
            at += n


def set_key(tokens: np.ndarray) -> int:
    return int(signed(mix(mix(tokens ^ U(0x5851F42D4C957F2D)).sum(dtype=np.uint64, keepdims=True) + U(len(tokens))))[0])


def need(a: int, b: int, num: int, den: int) -> int:
    """Least overlap of two sets of these sizes that reaches num/den."""
    return -(-num * (a + b) // (num + den))


def subset_sizes(n: int, num: int, den: int) -> list[int]:
    """The subset sizes that a set of n elements enumerates, one for each overlap that some partner needs."""
    partners = range(-(-num * n // den), den * n // num + 1)
    return sorted({c for b in partners if b and (c := need(n, b, num, den)) <= min(n, b)})


def boundary(histogram: dict[int, int], num: int, den: int, entry_cost: float, largest: int) -> int:
    """The light/heavy boundary of least cost: rows enumerated below it, list entries (weighed) from its zone on."""
    best, at = None, 0
    for b in range(0, largest + 1):
        cost = sum(c * sum(comb(n, k) for k in subset_sizes(n, num, den)) for n, c in histogram.items() if 0 < n <= b)
        cost += sum(c * entry_cost * (n - -(-num * n // den) + 1) for n, c in histogram.items() if n * den >= num * (b + 1))
        if best is None or cost < best:
            best, at = cost, b
    return at


class Repeats:
    """Which tokens come again among those of a task, and how often, in bounded memory.

    A bitmap marks what has been seen; only tokens that meet their mark are kept, so a token seen once costs a bit.
    A mark is two bits; one met by chance makes a token that came once count as two, which only steers the order of a set's elements.
    """

    def __init__(self, bits: int = 27, held: int = 1 << 19, table: int = 1 << 20):
        self.shift, self.room, self.held_room, self.table_room = U(64 - bits), 1 << (bits - 3), held, table
        self.marks = np.zeros(1 << (bits - 3), np.uint8)
        self.marked = self.size = 0
        self.held: list[np.ndarray] = []
        self.tokens, self.counts = np.empty(0, np.uint64), np.empty(0, np.int64)

    def add(self, tokens: np.ndarray):
        """Take a set's tokens; gives (tokens, counts) when the table is full, else None."""
        if self.marked > self.room:
            self.marks[:] = 0
            self.marked = 0
        at = np.concatenate((mix(tokens) >> self.shift, mix(tokens ^ U(0x2545F4914F6CDD1D)) >> self.shift))
        word, bit = (at >> U(3)).astype(np.int64), np.uint8(1) << (at & U(7)).astype(np.uint8)
        known = ((self.marks[word] & bit) != 0).reshape(2, -1).all(axis=0)
        np.bitwise_or.at(self.marks, word, bit)
        self.marked += len(tokens)
        again = tokens[known]
        if len(again):
            self.held.append(again)
            self.size += len(again)
        if self.size > self.held_room:
            self._fold()
            if len(self.tokens) > self.table_room:
                return self.flush()
        return None

    def _fold(self) -> None:
        fresh, counts = np.unique(np.concatenate([np.empty(0, np.uint64), *self.held]), return_counts=True)
        self.held, self.size = [], 0
        every, back = np.unique(np.concatenate((self.tokens, fresh)), return_inverse=True)
        self.counts = np.bincount(back, np.concatenate((self.counts, counts)), len(every)).astype(np.int64)
        self.tokens = every

    def flush(self) -> tuple[np.ndarray, np.ndarray]:
        self._fold()
        out = self.tokens, self.counts + 1
        self.tokens, self.counts = np.empty(0, np.uint64), np.empty(0, np.int64)
        return out


def _signatures(width: int):
    schema = pa.schema([("doc_id", pa.int64()), ("n", pa.int64()), ("ckey", pa.int64()), ("token", pa.int64()), ("cnt", pa.int64())])

    def told(found):
        for lo in range(0, len(found[0]), 1 << 16):
            tokens, counts = found[0][lo : lo + (1 << 16)], found[1][lo : lo + (1 << 16)]
            none = pa.nulls(len(tokens), pa.int64())
            yield pa.RecordBatch.from_arrays([none, none, none, pa.array(signed(tokens)), pa.array(counts)], schema=schema)

    @lean()
    def run(batches):
        repeats = Repeats()
        for batch in by_bytes(batches, 1):
            ns, keys = [], []
            for s in shingle_sets(column_bytes(batch.column(1)), width):
                n = 0 if s is None else len(s)
                ns.append(n)
                keys.append(set_key(s) if n else None)
                if n and (full := repeats.add(s)):
                    yield from told(full)
            none = pa.nulls(len(ns), pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(ns, pa.int64()), pa.array(keys, pa.int64()), none, none], schema=schema)
        yield from told(repeats.flush())

    return run


def _entries(width: int, num: int, den: int, light: int, frequent: tuple[np.ndarray, np.ndarray]):
    """List entries (kind 0) and subsets (kind = their size) of each class, once for each partition."""
    names = ("kind", "key", "ckey", "n", "doc_id", "pos", "odd")
    schema = pa.schema([(x, pa.int64() if x in ("key", "ckey", "doc_id") else pa.int32()) for x in names])
    tokens, weight = frequent

    @lean()
    def run(batches):
        seen = set()
        for batch in by_bytes(batches, 1):
            ids = batch.column(0).to_pylist()
            kinds, keys, heads, poss = [], [], [], []
            for doc, s in zip(ids, shingle_sets(column_bytes(batch.column(1)), width)):
                if doc is None or s is None or not len(s):
                    continue
                ckey, n = set_key(s), len(s)
                if ckey in seen:
                    continue
                seen.add(ckey)
                if n <= light:
                    marked = mix(s)
                    for c in subset_sizes(n, num, den):
                        picks = np.array(list(combinations(range(n), c)))
                        found = mix(marked[picks].sum(axis=1, dtype=np.uint64) + U(c))
                        kinds.append(np.full(len(found), c, np.int32))
                        keys.append(found)
                        poss.append(np.zeros(len(found), np.int32))
                        heads.append((ckey, n, doc, len(found), 0))
                if n * den >= num * (light + 1):
                    rare, odd = s, n
                    if len(tokens):
                        at = np.minimum(np.searchsorted(tokens, s), len(tokens) - 1)
                        load = np.where(tokens[at] == s, weight[at], 0)
                        rare, odd = s[np.lexsort((s, load))], int((load == 0).sum())
                    k = n - -(-num * n // den) + 1
                    kinds.append(np.zeros(k, np.int32))
                    keys.append(rare[:k])
                    poss.append(np.arange(k, dtype=np.int32))
                    heads.append((ckey, n, doc, k, odd))
            if kinds:
                reps = np.array([h[3] for h in heads])
                spread = lambda i, t: pa.array(np.repeat(np.array([h[i] for h in heads], t), reps))
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(kinds)), pa.array(signed(np.concatenate(keys))), spread(0, np.int64), spread(1, np.int32), spread(2, np.int64), pa.array(np.concatenate(poss)), spread(4, np.int32)], schema=schema)

    return run


def _set_rows(width: int):
    schema = pa.schema([("doc_id", pa.int64()), ("ckey", pa.int64()), ("tokens", pa.list_(pa.int64()))])

    @lean()
    def run(batches):
        for batch in by_bytes(batches, 1):
            ids, keys, sets = [], [], []
            for doc, s in zip(batch.column(0).to_pylist(), shingle_sets(column_bytes(batch.column(1)), width)):
                if s is not None and len(s):
                    ids.append(doc)
                    keys.append(set_key(s))
                    sets.append(s)
            if ids:
                offsets = np.concatenate(([0], np.cumsum([len(s) for s in sets])))
                values = pa.ListArray.from_arrays(pa.array(offsets.astype(np.int32)), pa.array(signed(np.concatenate(sets))))
                yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(keys, pa.int64()), values], schema=schema)

    return run


def _near(texts: DataFrame, ids: DataFrame) -> DataFrame:
    """The rows of ``texts`` whose id is in ``ids``, and few others, without moving a text: the join after it decides."""
    bits = bitmap_bits(ids.count())
    return slot_hit(texts, id_slots(ids, bits), bits).filter("_hit").select("doc_id", "text")


def block_links(a: list[np.ndarray], b: list[np.ndarray] | None, num: int, den: int) -> np.ndarray:
    """The link matrix of sets a and b (None: a with itself, without its diagonal), by exact overlaps.

    An element in few sets of both sides is counted pair by pair, one in many by a matrix product.
    """
    within, b = b is None, a if b is None else b
    shape = len(a), len(b)
    flat = [np.concatenate(x) for x in (a, b)]
    rows = [np.repeat(np.arange(len(x)), [len(s) for s in x]) for x in (a, b)]
    every, back = np.unique(np.concatenate(flat), return_inverse=True)
    of = back[: len(flat[0])], back[len(flat[0]) :]
    counts = [np.bincount(x, minlength=len(every)) for x in of]
    shared = (counts[0] > (1 if within else 0)) & (counts[1] > 0)
    work = counts[0] * counts[1]
    common = shared & (work > max(64, shape[0] * shape[1] // 100))
    overlap = np.zeros(shape, np.float32)
    at = np.flatnonzero(common)
    place = np.full(len(every), -1)
    for lo in range(0, len(at), 512):
        some = at[lo : lo + 512]
        place[some] = np.arange(len(some))
        sides = []
        for x, r, n in zip(of, rows, shape):
            pick = place[x] >= 0
            m = np.zeros((n, len(some)), np.float32)
            m[r[pick], place[x[pick]]] = 1
            sides.append(m)
        overlap += sides[0] @ sides[1].T
        place[some] = -1
    few = np.flatnonzero(shared & ~common)
    if len(few):
        order = [np.argsort(x, kind="stable") for x in of]
        starts = [np.concatenate(([0], np.cumsum(c))) for c in counts]
        cuts = np.concatenate(([0], np.cumsum(work[few])))
        lo = 0
        while lo < len(few):
            hi = max(lo + 1, int(np.searchsorted(cuts, cuts[lo] + (1 << 21), side="right")) - 1)
            t = few[lo:hi]
            turn = np.repeat(t, work[t])
            step = np.arange(len(turn)) - np.repeat(cuts[lo:hi] - cuts[lo], work[t])
            left = rows[0][order[0][starts[0][turn] + step // counts[1][turn]]]
            right = rows[1][order[1][starts[1][turn] + step % counts[1][turn]]]
            overlap += np.bincount(left * shape[1] + right, minlength=shape[0] * shape[1]).reshape(shape)
            lo = hi
    sizes = [np.array([len(s) for s in x], np.float64) for x in (a, b)]
    link = (overlap > 0) & (den * overlap.astype(np.float64) >= num * (sizes[0][:, None] + sizes[1][None, :] - overlap))
    if within:
        np.fill_diagonal(link, False)
    return link


def _count_links(num: int, den: int):
    """From rows (label, i, j, own, ckey, copies, tokens) in the order of (label, i, j): (ckey, links) for each of them."""
    schema = pa.schema([("ckey", pa.int64()), ("links", pa.int64())])

    def told(rows):
        key = rows[0][0]
        sides = [[r for r in rows if r[1] == own] for own in key[1:]]
        if key[1] == key[2]:
            link = block_links([r[4] for r in sides[0]], None, num, den)
            found = [(sides[0], link, sides[0])]
        elif sides[0] and sides[1]:
            link = block_links(*[[r[4] for r in side] for side in sides], num, den)
            found = [(sides[0], link, sides[1]), (sides[1], link.T, sides[0])]
        else:
            return
        for mine, link, theirs in found:
            links = link @ np.array([r[3] for r in theirs], np.int64)
            yield pa.RecordBatch.from_arrays([pa.array([r[2] for r in mine], pa.int64()), pa.array(links, pa.int64())], schema=schema)

    @lean()
    def run(batches):
        held = []
        for batch in batches:
            keys = list(zip(*(batch.column(c).to_pylist() for c in range(3))))
            own, ckey, copies = (batch.column(c).to_pylist() for c in (3, 4, 5))
            lists = batch.column(6)
            values, ends = lists.values.to_numpy(), lists.offsets.to_numpy()
            for i, key in enumerate(keys):
                if held and held[0][0] != key:
                    yield from told(held)
                    held = []
                held.append((key, own[i], ckey[i], copies[i], values[ends[i] : ends[i + 1]].copy()))
        if held:
            yield from told(held)

    return run


def link_counts(texts: DataFrame, classes: DataFrame, width: int, num: int, den: int, members: int = 2048, elements: int = 1 << 19) -> DataFrame:
    """(ckey, links): with how many texts of other classes each class links. ``classes``: ckey, label, least, copies, n.

    A component of two classes is its one link; larger ones are counted cell by cell.
    """
    groups = classes.groupBy("label").agg(F.count("*").alias("k"), F.sum("n").alias("size"), F.sum("copies").alias("all"))
    placed = classes.join(groups.filter("k > 1"), "label")
    two = placed.filter("k = 2").select("ckey", (F.col("all") - F.col("copies")).alias("links"))
    many = materialize(placed.filter("k > 2").withColumn("cells", F.expr(f"cast(greatest(ceil(k / {members}D), ceil(size / {elements}D)) as int)")).select("label", "ckey", F.col("least").alias("doc_id"), "copies", "cells"), "members")
    sets = _near(texts, many.select("doc_id")).mapInArrow(_set_rows(width), "doc_id long, ckey long, tokens array<long>").dropDuplicates(["doc_id", "ckey"])
    rows = many.join(sets, ["ckey", "doc_id"]).withColumn("own", F.expr("cast(pmod(xxhash64(ckey), cells) as int)"))
    rows = rows.withColumn("other", F.explode(F.expr("sequence(0, cells - 1)"))).select("label", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "own", "ckey", "copies", "tokens")
    counted = rows.repartition("label", "i", "j").sortWithinPartitions("label", "i", "j").mapInArrow(_count_links(num, den), "ckey long, links long")
    return two.unionByName(counted).groupBy("ckey").agg(F.sum("links").alias("links"))


def _overlap_bound(num: int, den: int):
    """A pair's needed overlap, and the conditions on sizes and list positions that it can be reached."""
    required = F.expr(f"cast(ceil({num} * (a_n + b_n) / cast({num + den} as double) - 1e-9) as int)")
    sizes = (F.col("a_n") * den >= F.col("b_n") * num) & (F.col("b_n") * den >= F.col("a_n") * num)
    places = F.lit(1) + F.least(F.col("a_n") - F.col("a_pos") - 1, F.col("b_n") - F.col("b_pos") - 1) >= required
    return required, sizes, places


def set_bitmap(tokens: np.ndarray) -> np.ndarray:
    """A set's bitmap in 64-bit words, a power of two of them and at least four bits an element; its halves laid over
    each other are the bitmap of half the size."""
    bits = 1 << max(6, (4 * len(tokens) - 1).bit_length())
    marks = np.zeros(bits, bool)
    marks[(mix(tokens ^ U(0xA5A35625E9D1F4B7)) & U(bits - 1)).astype(np.int64)] = True
    return np.packbits(marks, bitorder="little").view("<i8")


def _bitmaps(width: int):
    schema = pa.schema([("doc_id", pa.int64()), ("ckey", pa.int64()), ("n", pa.int64()), ("marks", pa.list_(pa.int64()))])

    @lean()
    def run(batches):
        for batch in by_bytes(batches, 1):
            found = [(doc, set_key(s), len(s), set_bitmap(s)) for doc, s in zip(batch.column(0).to_pylist(), shingle_sets(column_bytes(batch.column(1)), width)) if s is not None and len(s)]
            if found:
                ids, keys, sizes, marks = zip(*found)
                offsets = np.concatenate(([0], np.cumsum([len(m) for m in marks]))).astype(np.int32)
                yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(keys, pa.int64()), pa.array(sizes, pa.int64()), pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate(marks)))], schema=schema)

    return run


def _checked(texts: DataFrame, pairs: DataFrame, width: int, num: int, den: int) -> DataFrame:
    """Those of the candidate pairs (a, a_doc, b, b_doc) whose sets overlap enough, as (u, v).

    First bitmaps of a sixteenth of the sets' size meet: where two differ in a bit, an element lies in one set only, so
    they bound the overlap from above. Sets move only for the pairs that the bound leaves.
    """
    marks = _near(texts, pairs.select(F.explode(F.array("a_doc", "b_doc")).alias("doc_id"))).mapInArrow(_bitmaps(width), "doc_id long, ckey long, n long, marks array<long>")
    side = lambda p: marks.select(F.col("doc_id").alias(f"{p}_doc"), F.col("ckey").alias(p), F.col("n").alias(f"{p}_n"), F.col("marks").alias(f"{p}_marks"))
    # sizes differ by a quarter at most, so bitmaps by a factor of two at most
    folded = lambda mine, other: F.expr(f"if(size({mine}) > size({other}), zip_with(slice({mine}, 1, size({mine}) div 2), slice({mine}, size({mine}) div 2 + 1, size({mine}) div 2), (p, q) -> p | q), {mine})")
    met = pairs.join(side("a"), ["a", "a_doc"]).join(side("b"), ["b", "b_doc"]).withColumns({"x": folded("a_marks", "b_marks"), "y": folded("b_marks", "a_marks")})
    apart = F.expr("aggregate(zip_with(x, y, (p, q) -> bit_count(p ^ q)), 0, (s, v) -> s + v)")
    left = materialize(met.filter((num + den) * (F.col("a_n") + F.col("b_n") - apart) >= 2 * num * (F.col("a_n") + F.col("b_n"))).select("a", "a_doc", "b", "b_doc").distinct(), "pairs")
    sets = lambda p: _near(texts, left.select(F.col(f"{p}_doc").alias("doc_id"))).mapInArrow(_set_rows(width), "doc_id long, ckey long, tokens array<long>").select(F.col("doc_id").alias(f"{p}_doc"), F.col("ckey").alias(p), F.col("tokens").alias(f"{p}_set"))
    both = left.join(sets("a"), ["a", "a_doc"]).join(sets("b"), ["b", "b_doc"])
    shared = F.size(F.array_intersect("a_set", "b_set"))
    return both.filter(den * shared >= num * (F.size("a_set") + F.size("b_set") - shared)).select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct()


def components(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """(node, label) of every node that has a link; the label is the least node of its component.

    Alternating star contractions: each round joins the edges with one row a node (a hot node's edges
    can be split by the engine), and is written to the shared folder. Links and labels stay distributed.
    """

    def mark(df):
        r = df.agg(F.count("*"), F.sum(F.xxhash64("u", "v").bitwiseAND(0xFFFFFFFF))).first()
        return r[0], r[1]

    now = materialize(edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).filter("u != v").distinct(), "edges")
    state = mark(now)
    for _ in range(rounds):
        if not state[0]:
            break
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        wide = both.join(low, "u").filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        low2 = wide.groupBy("u").agg(F.min("v").alias("m"))
        tight = wide.join(low2, "u").filter("v != m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        after = materialize(tight.unionByName(low2.select("u", F.col("m").alias("v"))).distinct(), "edges")
        release(now)
        shrink_driver(edges.sparkSession)
        seen, state, now = state, mark(after), after
        if seen == state:
            break
    else:
        raise RuntimeError("the components did not settle")
    return now.select(F.col("u").alias("node"), F.col("v").alias("label")).unionByName(now.select(F.col("v").alias("node"), F.col("v").alias("label")).distinct())


def jaccard_join(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 5, num: int = 80, den: int = 100, entry_cost: float = 12.0, largest_light: int = 12, frequent_tokens: int = 1 << 20, cell: int = 2048, links: bool = True) -> DataFrame:
    """One row a document: doc_id, n_shingles, component_id, n_links, is_light.

    Two texts link when den * overlap >= num * union. ``frequent_tokens`` bounds the table of the
    most frequent shingles (12 bytes each) that goes to every task; it only steers the order of a set's elements (any
    order gives the same links). ``cell`` is the block of a long list that one join key holds.
    """
    texts = in_batches(docs).select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    signed_rows = materialize(texts.mapInArrow(_signatures(width), "doc_id long, n long, ckey long, token long, cnt long"), "signatures")
    marks = signed_rows.filter("token is null").select("doc_id", "n", "ckey")
    top = signed_rows.filter("token is not null").groupBy("token").agg(F.sum("cnt").alias("cnt")).orderBy(F.desc("cnt"), "token").limit(frequent_tokens).toArrow()
    tokens, counts = top.column(0).to_numpy().view(np.uint64), np.minimum(top.column(1).to_numpy(), 1 << 30).astype(np.int32)
    order = np.argsort(tokens)
    frequent = (tokens[order], counts[order])
    del top, tokens, counts, order
    near_light = -(-den * (largest_light + 1) // num)
    histogram = {r[0]: r[1] for r in marks.filter(f"n between 1 and {near_light}").groupBy("n").agg(F.countDistinct("ckey")).collect()}
    light = boundary(histogram, num, den, entry_cost, largest_light)

    rows = texts.mapInArrow(_entries(width, num, den, light, frequent), "kind int, key long, ckey long, n int, doc_id long, pos int, odd int").repartition("kind", "key")
    rows = rows.groupBy("kind", "key", "ckey").agg(F.min("n").alias("n"), F.min("doc_id").alias("doc"), F.min("pos").alias("pos"), F.min("odd").alias("odd"))
    lists, bands = Window.partitionBy("kind", "key"), Window.partitionBy("kind", "key", "band")
    rows = rows.withColumn("cnt", F.count("*").over(lists)).filter("cnt > 1")
    rows = rows.withColumn("band", F.when(F.col("kind") > 0, 0).otherwise(F.floor(F.log(F.col("n").cast("double")) / F.log(F.lit(den / num)))))
    rows = materialize(rows.withColumn("pivot", F.min(F.struct("odd", "n", "ckey", "doc", "pos")).over(bands)).drop("odd"), "lists")
    shrink_driver(docs.sparkSession)

    required, sizes, places = _overlap_bound(num, den)
    stars = rows.filter("ckey != pivot.ckey").select("kind", F.col("ckey").alias("a"), F.col("n").alias("a_n"), F.col("doc").alias("a_doc"), F.col("pos").alias("a_pos"), F.col("pivot.ckey").alias("b"), F.col("pivot.n").alias("b_n"), F.col("pivot.doc").alias("b_doc"), F.col("pivot.pos").alias("b_pos"))
    direct = stars.filter((F.col("kind") > 0) & (required <= F.col("kind"))).select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v"))
    first = stars.filter((F.col("kind") == 0) & sizes & places).groupBy("a", "b").agg(F.min("a_doc").alias("a_doc"), F.min("b_doc").alias("b_doc"))
    first = materialize(first, "pairs")
    edges = materialize(direct.unionByName(_checked(texts, first, width, num, den)).distinct(), "links")
    shrink_driver(docs.sparkSession)
    known = components(edges)

    inside = rows.filter("kind = 0 and cnt > 1").join(known.withColumnRenamed("node", "ckey"), "ckey", "left").withColumn("label", F.coalesce("label", "ckey"))
    inside = inside.withColumn("lo", F.min("label").over(Window.partitionBy("key"))).withColumn("hi", F.max("label").over(Window.partitionBy("key"))).filter("lo != hi")
    inside = inside.withColumn("cells", F.expr(f"cast(ceil(cnt / {cell}D) as int)")).withColumn("own", F.expr("cast(pmod(ckey, cells) as int)"))
    inside = inside.withColumn("other", F.explode(F.expr("sequence(0, cells - 1)"))).withColumn("i", F.least("own", "other")).withColumn("j", F.greatest("own", "other"))
    side = lambda p: inside.select("key", "i", "j", *[F.col(c).alias(f"{p}_{c}") for c in ("ckey", "n", "doc", "pos", "label", "own")], F.col("pivot.ckey").alias(f"{p}_pivot"))
    rest = side("a").join(side("b"), ["key", "i", "j"]).filter("a_ckey < b_ckey and a_label != b_label and a_pivot != b_ckey and b_pivot != a_ckey and (a_own != b_own or i = j)").filter(sizes & places)
    rest = materialize(rest.groupBy(F.col("a_ckey").alias("a"), F.col("b_ckey").alias("b")).agg(F.min("a_doc").alias("a_doc"), F.min("b_doc").alias("b_doc")), "pairs")
    shrink_driver(docs.sparkSession)
    if rest.limit(1).count():
        more = materialize(_checked(texts, rest, width, num, den), "links")
        edges = edges.unionByName(more)
        known = components(edges)
    release(first, rest, rows)

    classes = marks.filter("ckey is not null and doc_id is not null").groupBy("ckey").agg(F.min("doc_id").alias("least"), F.count("*").alias("copies"), F.min("n").alias("n"))
    classes = materialize(classes.join(known.withColumnRenamed("node", "ckey"), "ckey", "left").withColumn("label", F.coalesce("label", "ckey")), "classes")
    shrink_driver(docs.sparkSession)
    owners = classes.groupBy("label").agg(F.min("least").alias("component_id"))
    told = classes.join(owners, "label")
    if links:
        told = told.join(link_counts(texts, classes, width, num, den), "ckey", "left")
    else:
        told = told.withColumn("links", F.lit(None).cast("long"))
    told = told.select("ckey", "component_id", (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n_links"))
    out = marks.join(told, "ckey", "left")
    named = F.col("doc_id").isNotNull()
    shown = F.when(named, F.coalesce("n_links", F.lit(0))).cast("long") if links else F.lit(None).cast("long")
    return out.select("doc_id", F.col("n").alias("n_shingles"), F.when(named, F.coalesce("component_id", "doc_id")).alias("component_id"), shown.alias("n_links"), F.col("n").between(1, light).alias("is_light"))


def keep_one(docs: DataFrame, id_col: str = "doc_id", **options) -> DataFrame:
    """The documents with the least id of their component, all columns as they were; rows with a null id stay."""
    found = materialize(jaccard_join(docs, id_col=id_col, links=False, **options).filter("doc_id != component_id").select(F.col("doc_id").alias(id_col)).distinct(), "copies")
    shrink_driver(docs.sparkSession)
    return without_ids(docs, found, column=id_col)


def op2_ngram_jaccard_join(spark, sf_dir: str) -> DataFrame:
    """doc_id, n_shingles, component_id and n_links of every document."""
    return jaccard_join(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")).select("doc_id", "n_shingles", "component_id", "n_links")


SQL = {
    "op2_ngram_jaccard_join": """
WITH RECURSIVE words AS (
  SELECT doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
grams AS (
  SELECT DISTINCT doc_id, unnest(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')]
    ELSE list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' ')) END) AS g FROM words),
sizes AS (SELECT doc_id, count(*) AS n FROM grams GROUP BY doc_id),
shared AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS o FROM grams a JOIN grams b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2),
links AS (
  SELECT x, y FROM shared JOIN sizes s ON s.doc_id = x JOIN sizes t ON t.doc_id = y WHERE 100 * o >= 80 * (s.n + t.n - o)),
both_ways AS (SELECT x, y FROM links UNION ALL SELECT y, x FROM links),
reach AS (SELECT doc_id AS x, doc_id AS y FROM documents UNION SELECT r.x, b.y FROM reach r JOIN both_ways b ON r.y = b.x),
least AS (SELECT x, min(y) AS component_id FROM reach GROUP BY x),
degree AS (SELECT x, count(*) AS n_links FROM both_ways GROUP BY x)
SELECT d.doc_id, coalesce(n, 0)::BIGINT AS n_shingles, component_id, coalesce(n_links, 0)::BIGINT AS n_links
FROM documents d LEFT JOIN sizes s ON s.doc_id = d.doc_id JOIN least l ON l.x = d.doc_id LEFT JOIN degree g ON g.x = d.doc_id
""",
}
