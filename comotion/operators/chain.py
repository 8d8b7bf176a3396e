"""Chains clusters of consecutive units (ticks or partitions) into candidate groups.

Time is cut into blocks that are swept in parallel. A block yields what begins and ends inside it, the sets alive from its
first unit on with their last unit, and the sets alive at its end with their first. Joining neighbouring blocks only needs
the latter two, which are open candidates and not data. What joined blocks yield has the same form, so blocks are joined
level by level, many at a time in parallel.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from comotion.components import cut, cut_lists

_KINDS = "kind string, block long, first long, last long, members array<long>, u0 long, u1 long, nodes array<string>"
_ARROW = pa.schema([("kind", pa.string()), ("block", pa.int64()), ("first", pa.int64()), ("last", pa.int64()), ("members", pa.list_(pa.int64())), ("u0", pa.int64()), ("u1", pa.int64()), ("nodes", pa.list_(pa.string()))])
_OUT = "members array<long>, u0 long, u1 long, nodes array<string>"
_OUT_ARROW = pa.schema([("members", pa.list_(pa.int64())), ("u0", pa.int64()), ("u1", pa.int64()), ("nodes", pa.list_(pa.string()))])

#: Blocks that one task joins.
_FAN = 64

#: A set of members: a frozenset, or the bits of an int where it holds many of the numbers of its task (``_Classes.set``).
Members = frozenset | int
State = dict[Members, tuple[int, frozenset]]  # members: first unit, nodes passed

#: Bytes of lists of members that one batch of a result holds.
_BATCH_BYTES = 8 << 20


def _numbers(v: Members) -> Iterable[int]:
    if not isinstance(v, int):
        return v
    return np.flatnonzero(np.unpackbits(np.frombuffer(v.to_bytes((v.bit_length() + 7) // 8, "little"), np.uint8), bitorder="little")).tolist()


def _size(v: Members) -> int:
    return v.bit_count() if isinstance(v, int) else len(v)


def _has(v: Members, x: int) -> bool:
    return bool(v >> x & 1) if isinstance(v, int) else x in v


def _both(v: Members, w: Members, many: int) -> Members:
    """Intersection; an int holds ``many`` members at least, so that equal sets are equal keys."""
    if isinstance(v, int) and isinstance(w, int):
        both = v & w
        return both if both.bit_count() >= many else frozenset(_numbers(both))
    if isinstance(v, int):
        v, w = w, v
    if isinstance(w, int):
        bits = w.to_bytes((w.bit_length() + 7) // 8, "little")
        return frozenset(x for x in v if x >> 3 < len(bits) and bits[x >> 3] >> (x & 7) & 1)
    return v & w


def _within(v: Members, w: Members) -> bool:
    """Whether ``w`` holds all of ``v``."""
    if isinstance(v, int):
        return isinstance(w, int) and v & w == v
    return len(_both(v, w, 0)) == len(v) if isinstance(w, int) else v <= w


def _put(state: State, members: Members, start: int, nodes: frozenset) -> None:
    if old := state.get(members):
        start, nodes = min(start, old[0]), nodes | old[1]
    state[members] = (start, nodes)


def _holders(sets: Iterable[Members]) -> dict[int | None, list[Members]]:
    """The sets that hold each member; those of many members stand under None."""
    out: dict[int | None, list[Members]] = {}
    for v in sets:
        for x in (None,) if isinstance(v, int) else v:
            out.setdefault(x, []).append(v)
    return out


def _touching(holders: dict[int | None, list[Members]], c: Members) -> set[Members]:
    """The sets that may share a member with ``c``; only those are intersected."""
    return {v for x in (_numbers(c) if len(holders) > (None in holders) else ()) for v in holders.get(x, ())}.union(holders.get(None, ()))


def undominated(state: State) -> State:
    """Without sets of which a larger one has been alive as long."""
    out: State = {}
    by_member: dict[int, list[Members]] = {}
    many: list[Members] = []
    for v in sorted(state, key=lambda v: -_size(v)):
        start, n = state[v][0], _size(v)
        if any(out[w][0] <= start and _size(w) > n and _within(v, w) for w in many):
            continue
        if isinstance(v, int):
            many.append(v)
        else:
            probe = min((by_member.get(x, []) for x in v), key=len)
            if any(v < w and out[w][0] <= start for w in probe):
                continue
            for x in v:
                by_member.setdefault(x, []).append(v)
        out[v] = state[v]
    return out


class _Classes:
    """Ids that lie in the same sets of a group stand as one class; ``sets`` are the groups' member lists as class numbers.

    A list of at least ``many`` classes is held as an int: a bit takes a few hundredths of the room of an entry of a frozenset.
    """

    def __init__(self, members: pa.ChunkedArray):
        lists = members.combine_chunks()
        lists = lists if isinstance(lists, pa.Array) else pa.concat_arrays(lists.chunks)
        ids, lengths = lists.flatten().to_numpy(zero_copy_only=False), lists.value_lengths().to_numpy(zero_copy_only=False)
        inside = np.repeat(np.arange(len(lengths), dtype=np.int32), lengths)
        order = np.argsort(ids, kind="stable")  # of lists that are sorted themselves: runs are merged, sets stay in order
        ids, inside = ids[order], inside[order]
        cuts = np.append(np.flatnonzero(np.concatenate(([True], ids[1:] != ids[:-1])))[: len(ids)], len(ids))
        number: dict[bytes, int] = {}
        own: list[list[int]] = []
        where: list[np.ndarray] = []
        for lo, hi in zip(cuts, cuts[1:]):
            k = number.setdefault(inside[lo:hi].tobytes(), len(own))
            if k == len(own):
                own.append([])
                where.append(inside[lo:hi])
            own[k].append(ids[lo])
        self.own = [np.array(c, np.int64) for c in own]
        self.weight = [len(c) for c in own]
        self.sets: list[list[int]] = [[] for _ in lengths]
        for k, at in enumerate(where):
            for s in at.tolist():
                self.sets[s].append(k)
        self.many = max(_MANY, len(self.own) // 256)
        self._ends = np.cumsum(self.weight, dtype=np.int64)
        self._ids = np.concatenate(self.own) if self.own else np.zeros(0, np.int64)

    def set(self, classes: list[int]) -> Members:
        if len(classes) < self.many:
            return frozenset(classes)
        bits = np.zeros(max(classes) + 1, np.uint8)
        bits[classes] = 1
        return int.from_bytes(np.packbits(bits, bitorder="little").tobytes(), "little")

    def ids(self, classes: Members) -> np.ndarray:
        k = np.fromiter(_numbers(classes), np.int64)
        n = np.asarray(self.weight, np.int64)[k]
        return np.sort(self._ids[np.arange(n.sum()) + np.repeat(self._ends[k] - np.cumsum(n), n)])


#: Least classes of a set that is held as an int.
_MANY = 64


def _reaches(v: Members, m: int, weight: list[int] | None) -> bool:
    return _size(v) >= m or (weight is not None and sum(weight[x] for x in _numbers(v)) >= m)


def sweep(units: list[tuple[int, list[tuple[str, Members]]]], m: int, dominance: bool, track: bool, end: int, weight: list[int] | None = None, many: int = 0, least: int = 1) -> tuple[list, State]:
    """Closed chains (members, first, last, nodes) and the sets still alive at unit ``end``; ``weight`` is of members that are classes.

    Chains of fewer than ``least`` units are left out, except those from the first unit on.
    """
    state: State = {}
    closed: list = []
    before = None
    none = frozenset()
    kept = lambda start, stop: stop - start + 1 >= least or start == units[0][0]
    for unit, clusters in [*units, (end + 1, [])]:
        if unit == end + 1 and before == end:
            return closed, state
        if before is not None and unit != before + 1:
            closed += [(v, s, before, n) for v, (s, n) in state.items() if kept(s, before)]
            state = {}
        if unit == end + 1:
            break
        new: State = {}
        holders = _holders(state)
        for name, c in clusters:
            node = frozenset((name,)) if track else none
            for v in _touching(holders, c):
                both = _both(v, c, many)
                if _reaches(both, m, weight):
                    s, n = state[v]
                    _put(new, both, s, n | node)
            _put(new, c, unit, node)
        if dominance:
            new = undominated(new)
        for v, (s, n) in state.items():
            if (v not in new or new[v][0] > s) and kept(s, before):
                closed.append((v, s, before, n))
        state, before = new, unit
    return closed, {}


def sweep_printed(units: list[tuple[int, list[tuple[str, frozenset]]]], m: int, k: int) -> list:
    """The published bookkeeping: a cluster that extends a candidate starts none of its own, a shrinking candidate isn't reported."""
    state: dict[frozenset, int] = {}
    out, before = [], None
    for unit, clusters in units:
        if before is not None and unit != before + 1:
            out += [(v, s, before) for v, s in state.items() if before - s + 1 >= k]
            state = {}
        new: dict[frozenset, int] = {}
        used, extended = set(), set()
        for v, s in state.items():
            for name, c in clusters:
                both = v & c
                if len(both) >= m:
                    used.add(v)
                    extended.add(name)
                    new[both] = min(s, new.get(both, s))
        out += [(v, s, before) for v, s in state.items() if v not in used and before - s + 1 >= k]
        for name, c in clusters:
            if name not in extended:
                new.setdefault(c, unit)
        state, before = new, unit
    return out + [(v, s, before) for v, s in state.items() if before - s + 1 >= k]


def _units(group: pa.Table, classes: _Classes | None = None) -> list[tuple[int, list[tuple[str, Members]]]]:
    found: dict[int, list] = {}
    for t, cid, members in zip(group.column("t").to_pylist(), group.column("cid").to_pylist(), classes.sets if classes else group.column("members").to_pylist()):
        found.setdefault(t, []).append((f"{t}:{cid}", members))
    ordered = sorted((t, sorted(c, key=lambda x: (x[0], sorted(x[1])))) for t, c in found.items())
    return [(t, [(name, classes.set(own) if classes else frozenset(own)) for name, own in c]) for t, c in ordered]


def _batches(rows: Iterable[tuple], classes: _Classes, schema: pa.Schema) -> Iterator[pa.RecordBatch]:
    """Rows as batches of a few megabytes; their sets of classes become lists of ids only here."""
    at, held, size = schema.get_field_index("members"), [], 0
    for row in rows:
        row = (*row[:at], classes.ids(row[at]), *row[at + 1 :])
        held.append(row)
        size += row[at].nbytes + 100
        if size > _BATCH_BYTES:
            yield pa.RecordBatch.from_arrays([pa.array(list(c), f.type) for c, f in zip(zip(*held), schema)], schema=schema)
            held, size = [], 0
    if held:
        yield pa.RecordBatch.from_arrays([pa.array(list(c), f.type) for c, f in zip(zip(*held), schema)], schema=schema)


def _table(rows: list[tuple], schema: pa.Schema) -> pa.Table:
    return pa.table([list(c) for c in zip(*rows)] or [[] for _ in schema], schema=schema)


def chain(clusters: DataFrame, m: int, least_units: int, block: int = 64, dominance: bool = True, track: bool = False) -> DataFrame:
    """(members, u0, u1, nodes) of every chain of at least ``least_units`` units; ``nodes`` are 'unit:cluster' if tracked.

    The blocks are swept when this is called, and written; the last joining runs when the result is read.
    """

    def local(group: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = pa.Table.from_batches(group)
        classes = _Classes(table.column("members"))
        units = _units(table, classes)
        b = units[0][0] // block
        first, last = b * block, b * block + block - 1
        closed, alive = sweep(units, m, dominance, track, last, classes.weight, classes.many, least_units)
        rows = [("head" if s == first else "inner", b, first, last, v, s, z, sorted(n)) for v, s, z, n in closed if s == first or z - s + 1 >= least_units]
        rows += [("through" if s == first else "tail", b, first, last, v, s, last, sorted(n)) for v, (s, n) in alive.items()]
        yield from _batches(rows, classes, _ARROW)

    kept = ("members", "u0", "u1", "nodes")
    parts = cut_lists(clusters.groupBy(F.floor(F.col("t") / block).alias("_b")).applyInArrow(local, _KINDS))
    done, wide = parts.filter("kind = 'inner'").select(*kept), block
    lo, hi = parts.agg(F.min("first"), F.max("last")).first()
    # only sets that are open at a border meet: those of neighbouring blocks, then of blocks of blocks, until one task holds the rest
    while lo is not None and hi - lo >= wide * _FAN:
        wide *= _FAN
        joined = parts.filter("kind <> 'inner'").groupBy(F.floor(F.col("first") / wide).alias("_b"))
        parts = cut_lists(joined.applyInArrow(_merger(m, least_units, dominance, wide), _KINDS))
        done = done.unionByName(parts.filter("kind = 'inner'").select(*kept))
    rest = parts.filter("kind <> 'inner'").groupBy(F.lit(0).alias("_b")).applyInArrow(_merger(m, least_units, dominance, None), _KINDS)
    return done.unionByName(rest.select(*kept))


def _merger(m: int, least_units: int, dominance: bool, wide: int | None) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Joins the blocks of one group in order of time; ``wide`` is the length of the group's own block, none for the last level."""

    def join(group: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        blocks: dict[int, list] = {}
        table = pa.Table.from_batches(group)
        classes = _Classes(table.column("members"))
        for r, members in zip(table.drop_columns(["members"]).to_pylist(), classes.sets):
            r["members"] = classes.set(members)
            blocks.setdefault(r["first"], []).append(r)
        begin = min(blocks) // wide * wide if wide else None
        end = begin + wide - 1 if wide else None
        out: list = []
        state: State = {}
        last = None

        def close(members, start, stop, nodes):
            kind = "head" if start == begin else "inner"
            if kind == "head" or stop - start + 1 >= least_units:
                out.append((kind, begin or 0, begin or 0, end or 0, members, start, stop, sorted(nodes)))

        for first in sorted(blocks):
            if last is not None and first != last + 1:
                for v, (s, n) in state.items():
                    close(v, s, last, n)
                state = {}
            before, last, new = first - 1, blocks[first][0]["last"], {}
            heads = [(r["members"], r["u1"], frozenset(r["nodes"]), r["kind"]) for r in blocks[first] if r["kind"] in ("head", "through")]
            met = _holders({w for w, *_ in heads})
            ends: dict[frozenset, list] = {}
            for w, *rest in heads:
                ends.setdefault(w, []).append(rest)
            for v, (s, n) in state.items():
                whole = False
                for w in _touching(met, v):
                    both = _both(v, w, classes.many)
                    if not _reaches(both, m, classes.weight):
                        continue
                    whole |= both == v
                    for z, nodes, kind in ends[w]:
                        if kind == "through":
                            _put(new, both, s, n | nodes)
                        else:
                            close(both, s, z, n | nodes)
                if not whole:
                    close(v, s, before, n)
            for w, z, nodes, kind in heads:
                if kind == "through":
                    _put(new, w, first, nodes)
                else:
                    close(w, first, z, nodes)
            for r in blocks[first]:
                if r["kind"] == "tail":
                    _put(new, r["members"], r["u0"], frozenset(r["nodes"]))
            state = undominated(new) if dominance else new
        for v, (s, n) in state.items():
            if last != end:
                close(v, s, last, n)
            else:
                out.append(("through" if s == begin else "tail", begin, begin, end, v, s, last, sorted(n)))
        yield from _batches(out, classes, _ARROW)

    return join


def chain_printed(clusters: DataFrame, m: int, k: int) -> DataFrame:
    schema = pa.schema([("members", pa.list_(pa.int64())), ("u0", pa.int64()), ("u1", pa.int64())])

    def run(group: pa.Table) -> pa.Table:
        return _table([(sorted(v), s, z) for v, s, z in sweep_printed(_units(group), m, k)], schema)

    return clusters.groupBy(F.lit(0).alias("_all")).applyInArrow(run, "members array<long>, u0 long, u1 long")


def maximal(convoys: DataFrame) -> DataFrame:
    """Without groups that another one contains in members and interval."""
    c = cut_lists(convoys.select("members", "t_start", "t_end").distinct().withColumn("sid", F.monotonically_increasing_id()))
    small = c.select("sid", "t_start", "t_end", F.size("members").alias("n"), F.element_at("members", 1).alias("x"))  # any one member leads to all sets that hold it
    beaten = held(small, c)
    return c.join(beaten.hint("merge"), "sid", "left_anti").select("members", "t_start", "t_end", (F.col("t_end") - F.col("t_start") + 1).alias("lifetime"))


#: Members that are sent to all tasks; more of them are joined instead.
_FIRSTS = 100_000


def held(small: DataFrame, c: DataFrame, other: DataFrame | None = None) -> DataFrame:
    """(sid): groups of ``c`` that one of ``other`` holds in members and interval; without ``other`` strictly, of ``c`` itself.

    ``small`` has one member of each group of ``c``. Lists of members travel only with pairs that agree in interval and size: first
    with the largest partner of each group, which settles most, then with all the others of the groups that are left.
    """
    o = (c if other is None else other).withColumnsRenamed({"sid": "wid", "members": "w", "t_start": "ws", "t_end": "we"})
    large = o.select("wid", "ws", "we", F.size("w").alias("nw"), F.explode("w").alias("x"))
    firsts = small.select("x").distinct()
    if firsts.limit(_FIRSTS + 1).count() <= _FIRSTS:  # members that no group of ``c`` is sought by aren't shuffled
        large = large.join(firsts.hint("broadcast"), "x", "left_semi")
    within = (F.col("ws") <= F.col("t_start")) & (F.col("t_end") <= F.col("we")) & (F.col("n") <= F.col("nw"))
    strict = (F.col("nw") > F.col("n")) | (F.col("ws") < F.col("t_start")) | (F.col("t_end") < F.col("we"))
    pair = cut(small.join(large.hint("merge"), "x").filter(within if other is not None else within & strict).select("sid", "wid", "nw"))
    likely = pair.groupBy("sid").agg(F.max(F.struct("nw", "wid"))["wid"].alias("wid"))
    sure = cut(_holding(likely, c, o))
    rest = pair.join(sure, "sid", "left_anti").join(likely, ["sid", "wid"], "left_anti")
    return sure.union(_holding(rest, c, o).distinct())


def _holding(pair: DataFrame, c: DataFrame, o: DataFrame) -> DataFrame:
    """(sid) of the pairs (sid, wid) of which the second holds all members of the first.

    Lists of members take little room in a file and much in memory: the hints keep Spark from broadcasting them.
    """
    both = pair.join(c.select("sid", "members").hint("merge"), "sid").join(o.select("wid", "w").hint("merge"), "wid")
    return both.filter(F.size(F.array_except("members", "w")) == 0).select("sid")


def finish(convoys: DataFrame) -> DataFrame:
    """Hash-stable form: member ids as a comma-joined string."""
    return convoys.select(F.array_join(F.transform("members", lambda v: v.cast("string")), ",").alias("members"), F.size("members").cast("long").alias("n_members"), "t_start", "t_end", "lifetime")
