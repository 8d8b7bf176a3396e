"""Suffix-array dedup (operator 2): removes every byte that a long repeated string covers.

A string of ``least`` bytes that starts anywhere else too, in the same document or another, is a repeat; all bytes that
repeats cover go, in every copy. Texts are UTF-8 bytes; matches never cross documents.

1. Anchors: in each window of ``least`` bytes the piece of ``least // 4`` bytes with the least hash is an anchor, so equal
   windows have an anchor at the same place. Anchors whose piece occurs once in the corpus are dropped at once.
2. Anchors with equal bytes all around (from the piece's first place in a window to its last) are one context; a context
   that occurs twice makes all windows around its anchor repeats. Where a piece has one context only, that settles it.
3. The different contexts of a piece meet in one group. The group's suffixes (from the anchor on) form an enhanced suffix
   array; a stack scan of its common-prefix lengths gives the interval tree. In every interval the members that differ
   beyond it are compared on the left side: the repeat they share is maximal, and counts if its left extension, with the
   interval's common prefix, reaches ``least`` bytes. All members of an interval count, not only neighbours in the array.
4. Very large groups (more than ``LARGE`` contexts) are not gathered: their windows are hashed one by one and counted.

A second, shorter length can be judged in the same run: anchors then come from windows of the shorter length, contexts reach as
far as the longer one needs, and each interval counts for the longest of the two that it reaches. What repeats at the longer
length repeats at the shorter one too.

Texts cross a shuffle compressed. Rows are known by a 64-bit hash of doc_id and text.

Defined results: null and empty texts have no bytes and no spans; repeated rows are copies of each other; texts under
``least`` bytes keep everything; very long texts are processed in overlapping slices; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from comotion.components import cut
from comotion.llm.common import record, slices, squeezed, text_bytes, unsqueezed

LEAST = 400
#: Bytes of a passage of fifty words, of four letters and a gap each.
PASSAGE = 250
LARGE = 50_000
_SLICE = 1 << 20

_BASE = 0x9E3779B97F4A7C15 | 1
_MASK = (1 << 64) - 1
_INVERSE = pow(_BASE, -1, 1 << 64)
_HIGH = np.uint64(0xFFFFFFFF00000000)
_LOW = np.uint64(0xFFFFFFFF)


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(29))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(32))


class _Powers:
    up = down = np.ones(1, np.uint64)

    @classmethod
    def get(cls, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(cls.up) < n:
            for name, base in (("up", _BASE), ("down", _INVERSE)):
                powers = np.full(max(n, 1 << 16), base, np.uint64)
                powers[0] = 1
                setattr(cls, name, np.cumprod(powers))
        return cls.up[:n], cls.down[:n]


def _sums(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Prefix sums from which the hash of any range follows, and the factors that make it independent of the place."""
    up, down = _Powers.get(len(data) + 1)
    total = np.zeros(len(data) + 1, np.uint64)
    np.cumsum((data.astype(np.uint64) + np.uint64(1)) * up[: len(data)], out=total[1:])
    return total, down


def _least_in_windows(key: np.ndarray, width: int) -> np.ndarray:
    """Minimum of every ``width`` neighbours."""
    n = len(key) - width + 1
    pad = -len(key) % width
    rows = np.concatenate((key, np.full(pad, _MASK, np.uint64))).reshape(-1, width)
    ahead = np.minimum.accumulate(rows, axis=1).ravel()
    behind = np.minimum.accumulate(rows[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(behind[:n], ahead[width - 1 : width - 1 + n])


def gram_of(least: int) -> int:
    """Bytes of an anchor's piece."""
    return max(1, least // 4)


def anchors(data: np.ndarray, least: int, gram: int, far: int | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Positions of a document's anchors, the hash of each one's piece, and the hash of its context, which holds all windows of ``far`` bytes around it."""
    n, far = len(data), far or least
    if n < least:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64), np.zeros(0, np.uint64)
    out = []
    for lo in range(0, n - least + 1, _SLICE):
        hi = min(n - least + 1, lo + _SLICE)  # window starts of this slice
        a, z = max(0, lo - far), min(n, hi + 2 * far)
        total, down = _sums(data[a:z])
        grams = _mix((total[lo - a + gram : hi - a + least] - total[lo - a : hi - a + least - gram]) * down[lo - a : hi - a + least - gram])
        place = np.arange(len(grams), dtype=np.uint64)
        best = _least_in_windows((grams & _HIGH) | place, least - gram + 1)
        own = np.unique(best & _LOW).astype(np.int64)
        at = own + lo
        left, right = np.maximum(at - (far - gram), 0), np.minimum(at + far, n)
        around = (total[right - a] - total[left - a]) * down[left - a]
        shape = ((at - left) * (far + 1) + (right - at)).astype(np.uint64)
        out.append((at, grams[own], _mix(around ^ _mix(shape))))
    at, piece, around = map(np.concatenate, zip(*out))
    at, first = np.unique(at, return_index=True)
    return at, piece[first], around[first]


# Interval tree of one group --------------------------------------------------------------------------------------


def common(a: bytes, b: bytes) -> int:
    """Length of the common prefix."""
    m = min(len(a), len(b))
    if a[:m] == b[:m]:
        return m
    return int((np.frombuffer(a, np.uint8, m) != np.frombuffer(b, np.uint8, m)).argmax())


def prefix_intervals(lcp: list[int], least: int) -> Iterator[tuple[int, int, int]]:
    """(common prefix, first, last) of every interval of a suffix array, children before parents; ``lcp[i]`` belongs to neighbours i and i+1."""
    stack: list[tuple[int, int]] = []
    for i, value in enumerate([*lcp, -1]):
        start = i
        while stack and stack[-1][0] > value:
            length, start = stack.pop()
            yield length, start, i
        if value >= least and (not stack or stack[-1][0] < value):
            stack.append((value, start))


def diverse_reach(shared: list[int], label: list) -> list[int]:
    """For each member, in the order of the left sides, its longest left extension in common with a member of another label.

    ``shared`` are the common left bytes of neighbours.
    """
    out = []
    for steps, names in ((shared, label), (shared[::-1], label[::-1])):
        reach, one = [-1], -1
        for s, a, b in zip(steps, names, names[1:]):
            one = s if a != b else min(one, s)
            reach.append(one)
        out.append(reach)
    return list(map(max, out[0], reversed(out[1])))


def group_repeats(left: list[bytes], right: list[bytes], least: int, gram: int) -> list[list[tuple[int, int]]]:
    """For each context the ranges of left lengths j for which its window of j bytes before the anchor and ``least - j`` from it on occurs again in the group."""
    return [own for own, _ in repeats_of_two(left, right, least, least, gram)]


def repeats_of_two(left: list[bytes], right: list[bytes], least: int, short: int, gram: int) -> list[tuple[list[tuple[int, int]], list[tuple[int, int]]]]:
    """For each context the ranges of left lengths for windows of ``least`` bytes, then those for windows of ``short`` bytes that no repeat of ``least`` bytes covers.

    ``left`` holds the bytes before the anchor, nearest first. Members of an interval that go on with different bytes share
    a repeat that ends there; their common left extension, beyond which they differ too, is where it begins.
    """
    found: list[tuple[list, list]] = [([], []) for _ in left]
    order = sorted(range(len(right)), key=right.__getitem__)
    lcp = [common(right[a], right[b]) for a, b in zip(order, order[1:])]
    rank = {k: r for r, k in enumerate(sorted(range(len(left)), key=left.__getitem__))}
    for length, first, last in prefix_intervals(lcp, gram):
        own = sorted(order[first : last + 1], key=rank.__getitem__)
        shared = [common(left[a], left[b]) for a, b in zip(own, own[1:])]
        wanted, enough = max(0, least - length), max(0, short - length)
        if max(shared) < enough:
            continue
        label = [right[k][length : length + 1] or k for k in own]  # a text's end differs from everything
        for item, reach in zip(own, diverse_reach(shared, label)):
            if reach >= wanted:
                found[item][0].append((wanted, reach))
            elif reach >= enough:
                found[item][1].append((enough, reach))
    out = []
    for long, rest in found:
        long = merged(long)
        rest = [(lo, hi) for lo, hi in rest if not any(hi <= top and short - lo <= least - low for low, top in long)]
        out.append((long, merged(rest)))
    return out


def merged(ranges: list[tuple[int, int]], touch: int = 1) -> list[tuple[int, int]]:
    """Union of closed ranges."""
    out: list[tuple[int, int]] = []
    for lo, hi in sorted(ranges):
        if out and lo <= out[-1][1] + touch:
            out[-1] = (out[-1][0], max(out[-1][1], hi))
        else:
            out.append((lo, hi))
    return out


def repeat_groups(texts: list[bytes], least: int) -> list[tuple[int, list[tuple[int, int]]]]:
    """Maximal repeats of at least ``least`` bytes among a few texts: (length, all (text, position) occurrences).

    An interval is a maximal repeat when its members are preceded by more than one byte value (or by a text's start).
    """
    suffix = sorted((t[p:], k, p) for k, t in enumerate(texts) for p in range(len(t)))
    lcp = [common(a[0], b[0]) for a, b in zip(suffix, suffix[1:])]
    out = []
    for length, first, last in prefix_intervals(lcp, max(1, least)):
        before = {texts[k][p - 1] if p else -1 - i for i, (_, k, p) in enumerate(suffix[first : last + 1])}
        if len(before) > 1:
            out.append((length, sorted((k, p) for _, k, p in suffix[first : last + 1])))
    return sorted(out)


# Distributed stages ----------------------------------------------------------------------------------------------


def _text() -> Column:
    return F.coalesce(F.col("text").cast("string"), F.lit(""))


def _key() -> Column:
    return F.xxhash64(F.col("doc_id").cast("long"), _text())


def anchor_rows(docs: DataFrame, least: int, far: int | None = None) -> DataFrame:
    """(fp, ctx, key, pos) of every anchor."""
    out, gram = pa.schema([("fp", pa.int64()), ("ctx", pa.int64()), ("key", pa.int64()), ("pos", pa.int32())]), gram_of(least)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            data, offsets = text_bytes(b.column(1))
            keys = b.column(0).to_numpy()
            parts = []
            for k in np.flatnonzero(np.diff(offsets) >= least).tolist():
                at, piece, around = anchors(data[offsets[k] : offsets[k + 1]], least, gram, far)
                parts.append((piece.view(np.int64), around.view(np.int64), np.full(len(at), keys[k]), at))
            if parts:
                yield record(out, *map(np.concatenate, zip(*parts)))

    return docs.select(_key().alias("key"), _text().alias("text")).mapInArrow(run, "fp long, ctx long, key long, pos int")


def _contexts(docs: DataFrame, wanted: DataFrame, least: int, gram: int) -> DataFrame:
    """(fp, ctx, before, after) for the (key, pos, fp, ctx) of ``wanted``; ``before`` is reversed."""
    spots = wanted.groupBy("key").agg(F.collect_list(F.struct("fp", "ctx", "pos")).alias("spots"))
    read = docs.select(_key().alias("key"), squeezed(_text()).alias("text")).join(spots.hint("merge"), "key").select("spots", "text")  # a task has Python work on one side of the shuffle only
    out = pa.schema([("fp", pa.int64()), ("ctx", pa.int64()), ("before", pa.binary()), ("after", pa.binary())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, 1 << 19):
            rows = []
            for own, text in zip(b.column(0).to_pylist(), b.column(1)):
                raw = unsqueezed(text)
                rows += [(s["fp"], s["ctx"], raw[max(0, s["pos"] - least + gram) : s["pos"]][::-1], raw[s["pos"] : s["pos"] + least]) for s in own]
            yield record(out, *zip(*rows))

    return read.mapInArrow(run, "fp long, ctx long, before binary, after binary")


def _grouped(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[list, ...]]:
    """Columns of each run of equal ``fp``, across batches."""
    held: list[list] = []
    for b in batches:
        cols = [c.to_pylist() for c in b.columns]
        if not cols[0]:
            continue
        fp = np.array(cols[0])
        edges = [0, *(np.flatnonzero(fp[1:] != fp[:-1]) + 1).tolist(), len(fp)]
        for a, z in zip(edges, edges[1:]):
            part = [c[a:z] for c in cols]
            if held and held[0][0] == part[0][0]:
                for x, y in zip(held, part):
                    x += y
            else:
                if held:
                    yield tuple(held)
                held = part
    if held:
        yield tuple(held)


_RANGES = "fp long, ctx long, lo int, hi int, size int"
_RANGE_ARROW = pa.schema([("fp", pa.int64()), ("ctx", pa.int64()), ("lo", pa.int32()), ("hi", pa.int32()), ("size", pa.int32())])


def _solve(least: int, short: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    gram = gram_of(short)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows: list[tuple] = []
        for fp, ctx, before, after in _grouped(batches):
            if len(fp) == 2:  # both contexts are the only interval
                lcp, reach = common(after[0], after[1]), common(before[0], before[1])
                size = least if lcp + reach >= least else short
                if lcp >= gram and lcp + reach >= size:
                    rows += [(fp[0], c, max(0, size - lcp), reach, size) for c in ctx]
            elif len(fp) > 2:
                for c, own in zip(ctx, repeats_of_two(before, after, least, short, gram)):
                    rows += [(fp[0], c, lo, hi, size) for size, ranges in zip((least, short), own) for lo, hi in ranges]
            if len(rows) > 20_000:
                yield record(_RANGE_ARROW, *zip(*rows))
                rows = []
        if rows:
            yield record(_RANGE_ARROW, *zip(*rows))

    return run


def _by_windows(contexts: DataFrame, sizes: set[int]) -> DataFrame:
    """The same ranges for very large groups: every window of every context is hashed, and counted with partial sums."""
    out = pa.schema([("w", pa.int64()), ("fp", pa.int64()), ("ctx", pa.int64()), ("lo", pa.int32()), ("size", pa.int32())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for fp, ctx, before, after in zip(*(c.to_pylist() for c in b.columns)):
                total, down = _sums(np.frombuffer(before[::-1] + after, np.uint8))
                for size in sizes:
                    j = np.arange(max(0, size - len(after)), len(before) + 1)
                    if not len(j):
                        continue
                    start = len(before) - j
                    w = _mix((total[start + size] - total[start]) * down[start] ^ _mix(np.uint64(fp & _MASK) + (j * (1 << 32) + size).astype(np.uint64)))
                    yield record(out, w.view(np.int64), np.full(len(j), fp), np.full(len(j), ctx), j, np.full(len(j), size))

    rows = contexts.mapInArrow(run, "w long, fp long, ctx long, lo int, size int")
    twice = rows.groupBy("w").agg(F.count("*").alias("c")).filter("c > 1").select("w")
    return rows.join(twice, "w").select("fp", "ctx", "lo", F.col("lo").alias("hi"), "size")


def spans(docs: DataFrame, least: int = LEAST, short: int | None = None) -> DataFrame:
    """(key, spans) of rows with repeated bytes; spans are unmerged (start, end, size) that may reach over the text's ends, of windows of ``size`` bytes."""
    short = short or least
    if not 0 < short <= least:
        raise ValueError("the second length is the shorter one")
    gram = gram_of(short)
    whole = least - gram
    every = cut(anchor_rows(docs, short, least))
    # partial sums shrink copies before the shuffle; what occurs once goes before anything else is read
    pieces = every.groupBy("fp").agg(F.count("*").alias("n"), F.min("ctx").alias("least"), F.max("ctx").alias("most")).filter("n > 1")
    # a table of its own, so that Spark may split a piece that very many documents hold
    live = cut(every.join(cut(pieces.select("fp", (F.col("least") == F.col("most")).alias("one"))), "fp"))
    mixed = live.filter("not one").drop("one")
    contexts = cut(mixed.groupBy("fp", "ctx").agg(F.count("*").alias("c"), F.min(F.struct("key", "pos")).alias("at")))
    group = cut(contexts.groupBy("fp").agg(F.min("c").alias("least"), F.count("*").alias("m")).filter("least = 1").select("fp", "m"))
    wanted = cut(contexts.join(group, "fp").select("fp", "ctx", "at.*", "m"))
    most = wanted.agg(F.coalesce(F.max("m"), F.lit(0))).first()[0]
    held = _contexts(docs, wanted.filter(F.col("m") <= LARGE), least, gram)
    ranges = held.repartition("fp").sortWithinPartitions("fp").mapInArrow(_solve(least, short), _RANGES)
    if most > LARGE:
        ranges = ranges.union(_by_windows(_contexts(docs, wanted.filter(F.col("m") > LARGE), least, gram), {least, short}))
    full = contexts.filter("c > 1").select("fp", "ctx", F.lit(0).alias("lo"), F.lit(whole).alias("hi"), F.lit(least).alias("size"))
    span = lambda lo, hi, size: F.struct((F.col("pos") - hi).cast("int").alias("a"), (F.col("pos") - lo + size).cast("int").alias("z"), size.cast("int").alias("size")).alias("s")
    settled = live.filter("one").select("key", span(F.lit(0), F.lit(whole), F.lit(least)))
    found = mixed.join(full.union(ranges), ["fp", "ctx"]).select("key", span(F.col("lo"), F.col("hi"), F.col("size")))
    return settled.union(found).groupBy("key").agg(F.collect_set("s").alias("spans"))


def removed(n: int, own: list[dict] | None, least: int) -> list[tuple[int, int]]:
    """Maximal removed runs [a, z) of a text of n bytes: windows that leave the text don't count, nor those of a shorter length."""
    ranges = []
    for s in own or ():
        if s["size"] < least:
            continue
        first, last = max(0, s["a"]), min(n - least, s["z"] - least)
        if first <= last:
            ranges.append((first, last + least))
    return merged(ranges, 0)


def _with_spans(docs: DataFrame, keep: list[str], least: int, short: int | None = None) -> DataFrame:
    """_row (the columns ``keep``), the compressed text and the spans of every row of ``docs``."""
    right = spans(docs, least, short).select(F.col("key").alias("_id"), F.col("spans").alias("_spans"))
    row = F.struct(*(F.col(f"`{c}`") for c in keep)).alias("_row")
    left = docs.select(row, _key().alias("_key"), squeezed(F.col("text").cast("string")).alias("text"))
    return left.join(right.hint("merge"), F.col("_key") == F.col("_id"), "left").select("_row", "text", "_spans")


def strip(docs: DataFrame, least: int = LEAST, short: int | None = None) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 and the removed runs of every row of ``docs``.

    With ``short`` also n_passage_bytes and n_passages: bytes that repeats of ``short`` bytes and more cover, and their runs.
    """
    names = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, runs array<array<long>>"
    fields = [("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("n_removed", pa.int64()), ("n_spans", pa.int64()), ("kept_sha256", pa.string()), ("runs", pa.list_(pa.list_(pa.int64())))]
    if short:
        names += ", n_passage_bytes long, n_passages long"
        fields += [("n_passage_bytes", pa.int64()), ("n_passages", pa.int64())]
    out = pa.schema(fields)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, 1 << 20):
            rows = []
            for text, own in zip(b.column(1), b.column(2).to_pylist()):
                raw = unsqueezed(text) or b""
                gone = removed(len(raw), own, least)
                sha, at = hashlib.sha256(), 0
                for a, z in [*gone, (len(raw), len(raw))]:
                    sha.update(raw[at:a])
                    at = z
                size = lambda runs: sum(z - a for a, z in runs)
                row = (len(raw), size(gone), len(gone), sha.hexdigest(), [list(x) for x in gone])
                if short:
                    passages = removed(len(raw), own, short)
                    row += (size(passages), len(passages))
                rows.append(row)
            yield record(out, b.column(0), *zip(*rows))

    rows = _with_spans(docs, ["doc_id"], least, short).select(F.col("_row.doc_id").cast("long").alias("doc_id"), "text", "_spans")
    return rows.mapInArrow(run, names)


def whole_characters(raw: bytes, gone: list[tuple[int, int]]) -> str:
    """The text without the runs, less the bytes at their ends that would split a character."""
    inside = lambda i: i < len(raw) and raw[i] & 0xC0 == 0x80
    parts, at = [], 0
    for a, z in gone:
        while inside(a):
            a += 1
        while z > a and inside(z):
            z -= 1
        if z > a:
            parts.append(raw[at:a])
            at = z
    return b"".join([*parts, raw[at:]]).decode()


def rewrite(docs: DataFrame, least: int = LEAST) -> DataFrame:
    """``docs``, all columns, with repeated passages taken out of text (whole characters) and n_chars brought up to date."""

    def cleaned(columns: Iterator[tuple[pa.Array, pa.Array]]) -> Iterator[pa.Array]:
        for text, own in columns:
            out = []
            for b in slices(iter([pa.RecordBatch.from_arrays([text, own], names=["text", "own"])]), 1 << 20):
                for z, s in zip(b.column(0), b.column(1).to_pylist()):
                    raw = unsqueezed(z)
                    gone = removed(len(raw), s, least) if raw else []
                    out.append(None if raw is None else whole_characters(raw, gone) if gone else raw.decode())
            yield pa.array(out, pa.string())

    rest = [c for c in docs.columns if c != "text"]
    rows = _with_spans(docs, rest, least).select("_row", F.arrow_udf(cleaned, "string")("text", "_spans").alias("_new"))
    column = {c: F.col(f"_row.`{c}`") for c in rest}
    column["text"] = F.col("_new").cast(docs.schema["text"].dataType)
    if "n_chars" in column:
        column["n_chars"] = F.coalesce(F.length("_new"), column["n_chars"]).cast(docs.schema["n_chars"].dataType)
    return rows.select(*(column[c].alias(c) for c in docs.columns))
