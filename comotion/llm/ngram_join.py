"""N-gram Jaccard join (operator 5): exact near-duplicate classes by T-occurrence search.

A document's set is its distinct 5-word shingles (64-bit hashes of the lower-cased words). Two documents link when
100 * intersection >= 80 * union; a class is a connected component of links.

1. Equal sets collapse to one representative.
2. Each set emits its ``floor(0.2 n) + K`` shingles of least hash, with K about a tenth of n. Linked sets share at least
   min(K_x, K_y) of them, so a set of which too few are shared with anybody is linked to nobody.
3. Of the shared shingles that are left, a set with c of them that must share k keeps the c - k + 1 rarest, by the number
   of sets that hold them: two linked sets have one of these in common. Passages that many unlike documents hold are
   frequent and drop out here.
4. What remains falls into cells: connected components of "shares a kept shingle". Links never leave a cell.
5. Within a cell (cut into blocks of bounded size, and pairs of blocks) inverted lists answer one query for each set:
   short lists are merged in a heap, long ones are probed by bisection for those that the short ones left alive
   (DivideSkip), those that reach the required overlap are verified exactly. Found sets join the query's class and leave
   the index, so that a large group of near copies costs about one query.
6. Links become classes.

No step gathers a shingle that many documents hold: each run of texts sends it twice at most to where its holders meet.

Defined results: null or empty texts, and texts without words, have no shingles and link with nothing (their class is
their own doc_id); fewer than five words are one shingle; repeated rows are copies of each other; a set is known by its
own hash, so that one doc_id may carry several texts, and a null doc_id any; a class of null ids has no component_id; an
empty table gives no rows.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from comotion.components import connected, cut
from comotion.llm.common import doc_text, record, slices, text_bytes

SHINGLE = 5
#: Shingles of one block: what a task holds of a cell, about 30 bytes each, twice where two blocks meet.
BLOCK = 1_000_000
#: Emitted shingles among which a task looks for shared ones before it sends them on.
_RUN = 1_000_000
#: Text bytes that are shingled at a time.
_SLICE = 1 << 20
#: Stands for a null doc_id, after all others.
NOBODY = (1 << 63) - 1
#: Lists that the heap hands out for one merge.
_WAYS = 64
#: Weight of list length when the number of long lists is chosen.
MU = 0.01

_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_BASE = np.uint64(0x9E3779B97F4A7C15 | 1)


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(29))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(32))


def _powers(n: int) -> np.ndarray:
    if len(_powers.known) < n:
        _powers.known = np.cumprod(np.full(max(n, 1 << 16), _BASE, np.uint64))
    return _powers.known[:n]


_powers.known = np.zeros(0, np.uint64)


def word_hashes(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hash of every word of a byte array, and where each starts. A hash depends on the word's bytes alone."""
    gap = _SPACE[data]
    edge = np.diff(np.concatenate(([True], gap, [True])).astype(np.int8))
    start, end = np.flatnonzero(edge == -1), np.flatnonzero(edge == 1)
    if not len(start):
        return np.zeros(0, np.uint64), start
    length = end - start
    low = _LOWER[data].astype(np.uint64) + np.uint64(1)
    out = np.zeros(len(start), np.uint64)
    powers = _powers(int(length.max()))
    # place by place for the usual lengths, and one by one for the few very long words
    order = np.argsort(-length, kind="stable")
    sizes = length[order]
    wide = min(int(sizes[0]), 64)
    for k in range(wide):
        own = order[: np.searchsorted(-sizes, -k, side="left")]
        out[own] += low[start[own] + k] * powers[k]
    for i in order[: np.searchsorted(-sizes, -wide, side="left")]:
        out[i] += (low[start[i] + wide : end[i]] * powers[wide : length[i]]).sum(dtype=np.uint64)
    return _mix(out ^ length.astype(np.uint64)), start


def shingle_sets(column: pa.Array) -> list[np.ndarray]:
    """Sorted distinct shingle hashes of every text of a string column."""
    data, offsets = text_bytes(column)
    # texts lie end to end: a gap between them keeps words apart
    n = len(offsets) - 1
    apart = np.full(len(data) + n, 32, np.uint8)
    sizes = np.diff(offsets)
    apart[np.arange(len(data)) + np.repeat(np.arange(n), sizes)] = data
    words, start = word_hashes(apart)
    first = np.searchsorted(start, offsets[:-1] + np.arange(n))
    last = np.searchsorted(start, offsets[1:] + np.arange(n) + 1)
    code = np.zeros(max(0, len(words) - SHINGLE + 1), np.uint64)
    for k in range(SHINGLE if len(code) else 0):
        code = (code + words[k : k + len(code)]) * _BASE
    code = _mix(code)
    out = []
    for a, b in zip(first.tolist(), last.tolist()):
        if b - a >= SHINGLE:
            out.append(np.unique(code[a : b - SHINGLE + 1]))
        elif b > a:
            own = np.array([b - a], np.uint64)
            for w in words[a:b]:
                own = (own + w) * _BASE
            out.append(_mix(own))
        else:
            out.append(np.zeros(0, np.uint64))
    return out


def set_key(own: np.ndarray) -> tuple[int, int]:
    """128 bits that name a set."""
    a = _mix(own + np.uint64(0x1234567)).sum(dtype=np.uint64)
    b = _mix(own ^ np.uint64(0xABCDEF0123456789)).sum(dtype=np.uint64)
    pair = _mix(np.array([a, b ^ np.uint64(len(own))]))
    return int(pair[0].astype(np.int64)), int(pair[1].astype(np.int64))


def spare(n: int) -> int:
    """Most shingles of a set of n that a linked set may lack."""
    return n // 5


def evidence(n: int) -> int:
    """K: emitted shingles that a linked set of any size shares at least, up to the smaller K of both."""
    return max(1, n // 10)


def emitted(own: np.ndarray) -> np.ndarray:
    """The first shingles by hash."""
    return own[: spare(len(own)) + evidence(len(own))]


def dealt(token: np.ndarray, key: np.ndarray) -> np.ndarray:
    """Where each (shingle, set) of a run of texts goes: 0 to meet the others of its shingle, 1 if it is known to be shared.

    A shingle that several sets of the run hold sends two of them to the meeting, which is enough for any other run to see it.
    """
    order = np.lexsort((key, token))
    same = token[order][1:] == token[order][:-1]
    place = np.zeros(len(order), np.int64)  # within its shingle
    if len(order):
        first = np.concatenate(([0], np.flatnonzero(~same) + 1))
        place = np.arange(len(order)) - np.repeat(first, np.diff(np.append(first, len(order))))
    out = np.zeros(len(order), np.int8)
    out[order] = place > 1
    return out


def _signed(x: np.ndarray) -> np.ndarray:
    return x.astype(np.uint64).view(np.int64)


# Search in one block ---------------------------------------------------------------------------------------------


class Index:
    """Inverted lists of the sets that still have no class."""

    def __init__(self, sets: list[np.ndarray]):
        self.sets = sets
        self.sizes = np.array([len(s) for s in sets], np.int64)
        self.alive = np.ones(len(sets), bool)
        self._build(np.arange(len(sets)))

    def _build(self, ids: np.ndarray) -> None:
        owner = np.repeat(ids.astype(np.int32), self.sizes[ids])
        token = np.concatenate([self.sets[i] for i in ids]) if len(ids) else np.zeros(0, np.uint64)
        order = np.argsort(token, kind="stable")
        token, self.owner = token[order], owner[order]
        del order, owner
        first = np.flatnonzero(np.concatenate(([True], token[1:] != token[:-1]))) if len(token) else np.zeros(0, np.int64)
        self.token, self.first = token[first], np.append(first, len(token))
        self.living = np.diff(self.first)  # live sets in each list
        self.built = len(ids)

    def remove(self, ids: np.ndarray) -> None:
        self.alive[ids] = False
        for i in ids:
            self.living[np.searchsorted(self.token, self.sets[i])] -= 1
        left = int(self.alive.sum())
        if left < 0.7 * self.built:
            self._build(np.flatnonzero(self.alive))

    def search(self, query: np.ndarray) -> np.ndarray:
        """Live sets linked to ``query``."""
        n = len(query)
        if not len(self.token):
            return np.zeros(0, np.int64)
        spot = np.minimum(np.searchsorted(self.token, query), len(self.token) - 1)
        spot = spot[(self.token[spot] == query) & (self.living[spot] > 0)]
        length = self.first[spot + 1] - self.first[spot]
        need = n - spare(n)  # a linked set shares that many at least
        if len(spot) < need:
            return np.zeros(0, np.int64)
        order = np.argsort(length, kind="stable")
        spot = spot[order]
        longest = int(length.max())
        n_long = min(need - 1, int(need / (MU * np.log2(longest + 1) + 1)), len(spot) - 1)
        lists = [self.owner[self.first[s] : self.first[s + 1]] for s in spot]
        short, long = lists[: len(lists) - n_long], lists[len(lists) - n_long :]
        found, count = merged_lists(short)
        able = (count >= need - n_long) & self.alive[found]
        found, count = found[able].astype(np.int64), count[able]
        # overlap needed with each very set: 100 o >= 80 (n + size - o)
        wanted = -(-80 * (n + self.sizes[found]) // 180)
        for k, x in enumerate(long):
            if not k % 16:
                able = count + (len(long) - k) >= wanted
                found, count, wanted = found[able], count[able], wanted[able]
                if not len(found):
                    break
            count += x[np.minimum(np.searchsorted(x, found), len(x) - 1)] == found
        return found[count >= wanted]


def merged_lists(lists: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Distinct ids of sorted lists and how many lists hold each. A heap hands out the shortest lists; each merge goes back into it."""
    heap = [(len(x), k) for k, x in enumerate(lists)]
    heapq.heapify(heap)
    lists = list(lists)
    while len(heap) > 1:
        taken = [lists[heapq.heappop(heap)[1]] for _ in range(min(_WAYS, len(heap)))]
        lists.append(np.sort(np.concatenate(taken), kind="stable"))  # merges runs
        heapq.heappush(heap, (len(lists[-1]), len(lists) - 1))
    whole = lists[heap[0][1]] if heap else np.zeros(0, np.int32)
    first = np.flatnonzero(np.concatenate(([True], whole[1:] != whole[:-1]))) if len(whole) else np.zeros(0, np.int64)
    return whole[first], np.diff(np.append(first, len(whole)))


def classes(sets: list[np.ndarray]) -> np.ndarray:
    """Least position of each set's class."""
    index, label = Index(sets), np.full(len(sets), -1, np.int64)
    for seed in range(len(sets)):
        if label[seed] >= 0:
            continue
        label[seed] = seed
        index.remove(np.array([seed]))
        queue = [seed]
        while queue:
            got = index.search(sets[queue.pop()])
            if len(got):
                label[got] = seed
                index.remove(got)
                queue += got.tolist()
    return label


# Distributed stages ----------------------------------------------------------------------------------------------


def _row_key() -> tuple[Column, Column]:
    """(d, h) of a row with columns doc_id and text; rows that share it are copies of each other."""
    return F.coalesce(F.col("doc_id").cast("long"), F.lit(NOBODY)).alias("d"), F.xxhash64(F.col("text").cast("string")).alias("h")


def keys(docs: DataFrame) -> DataFrame:
    """doc_id, n_shingles, the 128-bit name of the set and the hash of the text of every row."""
    out = pa.schema([("doc_id", pa.int64()), ("n_shingles", pa.int64()), ("hi", pa.int64()), ("lo", pa.int64()), ("h", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, _SLICE):
            sets = shingle_sets(b.column(1))
            names = [set_key(s) if len(s) else (0, 0) for s in sets]
            yield record(out, b.column(0), [len(s) for s in sets], *zip(*names), b.column(2))

    rows = doc_text(docs)
    return rows.select("doc_id", "text", _row_key()[1]).mapInArrow(run, "doc_id long, n_shingles long, hi long, lo long, h long")


def shared_shingles(docs: DataFrame) -> DataFrame:
    """Distinct (token, key) of emitted shingles that different sets hold, together by key."""
    out = pa.schema([("token", pa.int64()), ("key", pa.int64()), ("known", pa.int8())])

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()  # copies that this task has met already; a repeat costs time only
        parts: list[tuple[np.ndarray, np.ndarray]] = []

        def flush() -> pa.RecordBatch:
            token, key = map(np.concatenate, zip(*parts))
            parts.clear()
            return record(out, _signed(token), key, dealt(token, key))

        held = 0
        for b in slices(batches, _SLICE):
            for own in shingle_sets(b.column(0)):
                if not len(own) or (key := set_key(own)[0]) in seen:
                    continue
                seen.add(key)
                head = emitted(own)
                parts.append((head, np.full(len(head), key)))
                held += len(head)
            if held > _RUN:
                yield flush()
                held = 0
                if len(seen) > 500_000:  # between runs only: within a run each set counts once
                    seen.clear()
        if parts:
            yield flush()

    rows = docs.select(F.col("text").cast("string").alias("text")).mapInArrow(emit, "token long, key long, known byte")
    # those known to be shared are spread by key; the others meet by shingle
    meet = Window.partitionBy("token", F.when(F.col("known") == 1, F.col("key")).otherwise(F.lit(0)))
    seen = rows.select("token", "key", "known", F.min("key").over(meet).alias("_least"), F.max("key").over(meet).alias("_most"))
    shared = seen.filter((F.col("known") == 1) | (F.col("_least") != F.col("_most"))).select("token", "key")
    return cut(shared.repartition("key").dropDuplicates(["key", "token"]))


def cells(shared: DataFrame, sizes: DataFrame) -> DataFrame:
    """(hi, cell) of the sets that may be linked to another one. ``sizes`` has key and n."""
    # a partner may be a fifth smaller, and K with it
    need = F.greatest(F.lit(1), F.floor(F.floor(F.col("n") * 4 / 5) / 10)).alias("need")
    strong = cut(shared.groupBy("key").agg(F.count("*").alias("c")).join(sizes, "key").select("key", "c", need).filter("c >= need").drop("c"))
    held = shared.join(strong, "key")
    often = held.groupBy("token").agg(F.count("*").alias("df")).filter("df > 1")
    own = Window.partitionBy("key")
    ranked = held.join(often, "token").select("token", "key", "need", F.row_number().over(own.orderBy("df", "token")).alias("r"), F.count("*").over(own).alias("c"))
    rarest = cut(ranked.filter("c >= need and r <= c - need + 1").select("token", "key"))
    hubs = rarest.groupBy("token").agg(F.min("key").alias("hub"), F.max("key").alias("_most")).filter("hub <> _most").select("token", "hub")
    edges = rarest.join(hubs, "token").select("key", "hub")
    return connected(edges, "key", "hub").select(F.col("node").alias("hi"), F.col("component").alias("cell"))


def blocks(wanted: DataFrame) -> tuple[DataFrame, bool]:
    """(hi, best, cell, i, j): the pairs of blocks in which each set of a cell is compared, and whether any cell has several.

    A large cell is cut by size and then by hash; a block meets those of its own size band and of the next.
    """
    crowd = wanted.groupBy("cell").agg(F.count("*").alias("_m"), F.sum("n").alias("_n")).filter("_m > 1")
    placed = wanted.join(crowd, "cell")
    if not crowd.filter(F.col("_n") > BLOCK).count():
        return placed.select("hi", "best", "cell", F.lit(0).cast("long").alias("i"), F.lit(0).cast("long").alias("j")), False
    # linked sizes differ by 1.25 at most, so they lie in neighbouring bands
    band = F.when(F.col("_n") > BLOCK, F.floor(F.log(F.col("n")) / F.log(F.lit(1.26)))).otherwise(F.lit(0)).cast("long")
    placed = placed.withColumn("band", band)
    ways = placed.groupBy("cell", "band").agg(F.ceil(F.sum("n") / BLOCK).cast("long").alias("q"))
    placed = placed.join(ways, ["cell", "band"]).withColumn("block", F.col("band") * (1 << 32) + F.pmod(F.xxhash64("hi"), F.col("q")))
    here = placed.select("cell", "band", "block").distinct()
    there = here.select("cell", F.explode(F.array(F.col("band"), F.col("band") - 1)).alias("band"), F.col("block").alias("j"))
    meet = here.withColumnRenamed("block", "i").join(there, ["cell", "band"]).filter("i <= j")
    side = meet.select("cell", "i", "j", F.explode(F.array_distinct(F.array("i", "j"))).alias("block"))
    return placed.join(side, ["cell", "block"]).select("hi", "best", "cell", "i", "j"), True


def _classed(docs: DataFrame) -> DataFrame:
    """doc_id, n_shingles, h, component_id, and the key (best.d, best.h) of the row that stands for the class, for every row of ``docs``."""
    named = cut(keys(docs))
    reps = named.filter("n_shingles > 0").groupBy("hi", "lo").agg(F.min(F.struct(F.coalesce("doc_id", F.lit(NOBODY)).alias("d"), "h")).alias("best"), F.min("doc_id").alias("rep"), F.max("n_shingles").alias("n"))
    reps = cut(reps)
    near = cells(shared_shingles(docs), reps.groupBy(F.col("hi").alias("key")).agg(F.min("n").alias("n")))
    placed, many = blocks(cut(reps.join(near, "hi").select("hi", "best", "n", "cell")))
    spots = placed.groupBy("hi", "best.d", "best.h").agg(F.collect_list(F.struct("cell", "i", "j")).alias("spots"))
    texts = docs.select(F.col("text").cast("string").alias("text"), *_row_key())
    # rows that share a key are copies of each other: solve() keeps one
    read = texts.join(spots, ["d", "h"]).select("hi", "text", "spots")
    member = pa.schema([("hi", pa.int64()), ("tokens", pa.binary()), ("cell", pa.int64()), ("i", pa.int64()), ("j", pa.int64())])

    def reread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, _SLICE):
            lines = [
                (d, own.tobytes(), s["cell"], s["i"], s["j"])
                for d, own, spots in zip(b.column(0).to_pylist(), shingle_sets(b.column(1)), b.column(2).to_pylist())
                for s in spots
            ]
            yield record(member, *zip(*lines))

    members = read.mapInArrow(reread, "hi long, tokens binary, cell long, i long, j long")

    def solve(group: pa.Table) -> pa.Table:
        ids, first = np.unique(group.column("hi").to_numpy(), return_index=True)
        raw = group.column("tokens")
        sets = [np.frombuffer(raw[k].as_buffer(), np.uint64) for k in first.tolist()]  # views of the group's own memory
        label = classes(sets)
        moved = np.flatnonzero(label != np.arange(len(ids)))
        return pa.table({"a": ids[moved], "b": ids[label[moved]]}, schema=pa.schema([("a", pa.int64()), ("b", pa.int64())]))

    links = members.groupBy("cell", "i", "j").applyInArrow(solve, "a long, b long")
    if many:
        found = connected(links).select(F.col("node").alias("hi"), F.col("component").alias("root"))
    else:  # every class lies in one block, so its links are a star
        found = links.select(F.col("a").alias("hi"), F.col("b").alias("root"))
    roots = reps.join(found, "hi", "left").select("hi", "lo", "rep", "best", F.coalesce("root", "hi").alias("root"))
    first = roots.groupBy("root").agg(F.min("rep").alias("component_id"), F.min("best").alias("best"))
    roots = roots.select("hi", "lo", "root").join(first, "root").drop("root")
    return named.join(roots, ["hi", "lo"], "left").select("doc_id", "n_shingles", "h", F.coalesce("component_id", F.when(F.col("n_shingles") == 0, F.col("doc_id"))).alias("component_id"), "best")


def link_classes(docs: DataFrame) -> DataFrame:
    """doc_id, n_shingles, component_id for every row of ``docs``."""
    return _classed(docs).select("doc_id", "n_shingles", "component_id")


def keep_one(docs: DataFrame) -> DataFrame:
    """``docs``, all columns, with one row of each class: of the least doc_id, nulls last. Rows without words link with nothing and stay."""
    own = cut(_classed(docs).filter("n_shingles > 0").select(F.coalesce("doc_id", F.lit(NOBODY)).alias("d"), "h", "best"))
    chosen = (F.col("d") == F.col("best.d")) & (F.col("h") == F.col("best.h"))
    others = own.filter(~chosen).select("d", "h").distinct()
    repeated = cut(own.filter(chosen).groupBy("d", "h").agg(F.count("*").alias("_c")).filter("_c > 1").select("d", "h"))
    rows = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("row"), *_row_key())
    kept = rows.join(others.union(repeated), ["d", "h"], "left_anti").select("row.*")
    if repeated.isEmpty():
        return kept
    # rows with one key are copies of each other: any of them will do
    return kept.union(rows.join(repeated, ["d", "h"], "left_semi").dropDuplicates(["d", "h"]).select("row.*"))
