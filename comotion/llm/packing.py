"""Packing (operator 8): token sequences of one window, planned by non-negative least squares.

1. Every text becomes ids and an end id. Whole windows of a long document are sequences of their own; the rest of each
   document is one piece.
2. The histogram of piece lengths, in grid cells of ``GRID`` tokens rounded up, is small whatever the corpus. Shallow
   combinations (up to three distinct lengths, repeated) that fill the window are the columns of a least-squares problem;
   the non-negative solution says how often to use each. Counts are rounded down.
3. Cells that rounding leaves over are packed greedily, largest first, in batches.
4. Pieces get their rank within their cell (counts per hashed part, then prefix sums); rank ranges name sequence and place.

Only the histogram (at most window/grid rows) and the plan reach the driver.

Defined results: null and empty texts are one piece that holds just the end id; repeated rows are packed once each; equal
texts have equal ids; an empty table gives no rows; very long texts are cut into windows, each id in exactly one piece.
"""

from __future__ import annotations

import array
import os
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from comotion.llm.common import cut, doc_text, record, slices, small_table, text_bytes

WINDOW = 4096
GRID = 32
END_ID = 2
MEMO = 450_000
PLAIN = 1_000_000  # words of plain letters that a worker keeps, some 50 bytes each
PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long"
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
#: ASCII marks other than the apostrophe: after a letter the tokenizer splits before them.
_MARKS = "".join(chr(i) for i in range(33, 127) if not chr(i).isalnum() and chr(i) != "'")
_RUN = 2048  # new words in one call of the tokenizer
_GAP, _MARK = np.zeros(256, bool), np.zeros(256, bool)
_GAP[[32, *range(9, 14)]] = True
_MARK[list(_MARKS.encode())] = True
_PLAIN = "^[a-zÀ-ÖØ-öø-ÿ]+$"
#: Plain words known so far, their ids end to end, and where the ids of each begin and how many there are.
_NONE = (pa.array([], pa.large_string()), np.zeros(0, "<u4"), np.zeros(0, np.int64), np.zeros(0, np.int64))
_ENDING = 8  # marks at a word's end that are looked through


class Tokens:
    """Packed 32-bit little-endian ids of texts; memoises the parts between gaps, which never interact."""

    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = True  # their strings in a text are ordinary text
        self.memo: dict[str, bytes] = {"": b""}
        self.plain = _NONE
        vocabulary = self.tokenizer.get_vocab()
        self.closes = np.zeros(max(vocabulary.values()) + 1, bool)
        self.closes[[i for token, i in vocabulary.items() if token.endswith("</w>")]] = True

    def _one_by_one(self, parts: list[str]) -> None:
        for part, e in zip(parts, self.tokenizer.encode_batch_fast(parts, add_special_tokens=False)):
            self.memo[part] = array.array("I", e.ids).tobytes()

    def _learn(self, new: set[str]) -> None:
        memo, words, other, pairs = self.memo, {}, {}, []
        for part in new:
            core = part if part.isalpha() else part.rstrip(_MARKS)
            if not core.lower().isalpha():  # a letter whose lower case ends in a combining mark joins what follows
                other[part] = None
                continue
            if core is not part and len(core) < len(part):
                mark = part[len(core) :]
                pairs.append((part, core, mark))
                if mark not in memo:
                    other[mark] = None
            if core not in memo:
                words[core] = None
        if other:
            self._one_by_one(list(other))
        words = list(words)
        runs = [words[k : k + _RUN] for k in range(0, len(words), _RUN)]
        # a word of letters is one pre-token, which ends in the only id that closes a word
        for run, e in zip(runs, self.tokenizer.encode_batch_fast([" ".join(r) for r in runs], add_special_tokens=False)):
            ids = np.array(e.ids, "<u4")
            ends = (np.flatnonzero(self.closes[ids]) + 1) * 4
            if len(ends) != len(run):  # some letter becomes more than one pre-token
                self._one_by_one(run)
                continue
            raw, at = ids.tobytes(), 0
            for word, z in zip(run, ends.tolist()):
                memo[word] = raw[at:z]
                at = z
        for part, core, mark in pairs:
            memo[part] = memo[core] + memo[mark]

    def packed(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts of a string column, end to end, and the offsets of each text in them.

        ASCII capitals are lower-cased and gaps cut here already; the tokenizer would do both. Only distinct parts are looked
        up; those of plain letters, nearly all, are remembered in arrays and never become Python strings of their own.
        """
        coded, at = parts(*text_bytes(column))
        own = coded.dictionary
        known, pool, starts, sizes = self.plain
        spot = pc.fill_null(pc.index_in(own, value_set=known), -1).to_numpy()
        plain = (spot < 0) & pc.match_substring_regex(own, _PLAIN).to_numpy(zero_copy_only=False)
        if plain.any():
            new = own.filter(pa.array(plain))
            ids, size = self._encoded(new)
            spot = spot.copy()
            spot[plain] = np.arange(len(known), len(known) + len(new))
            known = pa.concat_arrays([known, new])
            starts = np.concatenate((starts, len(pool) + np.cumsum(size) - size))
            pool, sizes = np.concatenate((pool, ids)), np.concatenate((sizes, size))
            self.plain = (known, pool, starts, sizes) if len(known) <= PLAIN else _NONE
        odd = np.flatnonzero(spot < 0)
        words = own.take(pa.array(odd)).to_pylist()
        if len(self.memo) > MEMO:
            self.memo = {"": b""}
        if new := set(words).difference(self.memo):
            self._learn(new)
        rest = [self.memo[w] for w in words]
        start, size = np.zeros(len(own), np.int64), np.zeros(len(own), np.int64)
        size[odd] = np.fromiter(map(len, rest), np.int64, len(rest)) // 4
        start[odd] = len(pool) + np.cumsum(size[odd]) - size[odd]
        held = spot >= 0
        start[held], size[held] = starts[spot[held]], sizes[spot[held]]
        pool = np.concatenate((pool, np.frombuffer(b"".join(rest), "<u4")))
        codes = coded.indices.to_numpy()
        n = size[codes]
        ends = np.cumsum(n)
        spread = np.arange(ends[-1] if len(ends) else 0) + np.repeat(start[codes] - ends + n, n)
        return pool[spread], np.concatenate(([0], ends))[at]

    def _encoded(self, words: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids, end to end, and their numbers of words of letters: such a word is one pre-token, which ends in the only id that closes a word."""
        bounds = [*range(0, len(words), _RUN), len(words)]
        runs = pc.binary_join(pa.ListArray.from_arrays(bounds, words.cast(pa.string())), " ").to_pylist()
        pool, sizes = [], []
        for lo, hi, e in zip(bounds, bounds[1:], self.tokenizer.encode_batch_fast(runs, add_special_tokens=False)):
            ids = np.array(e.ids, "<u4")
            size = np.diff(np.flatnonzero(self.closes[ids]), prepend=-1)
            if len(size) != hi - lo:  # some letter becomes more than one pre-token
                each = self.tokenizer.encode_batch_fast(words[lo:hi].to_pylist(), add_special_tokens=False)
                ids, size = np.array([i for e in each for i in e.ids], "<u4"), np.array([len(e.ids) for e in each])
            pool.append(ids)
            sizes.append(size)
        return np.concatenate(pool), np.concatenate(sizes)


def parts(data: np.ndarray, offsets: np.ndarray) -> tuple[pa.DictionaryArray, np.ndarray]:
    """The parts of all texts, lower-cased in ASCII and encoded by a dictionary, and the number of parts before each text and in all.

    Parts end at gaps, and before marks that end a word after a letter of ``_PLAIN``: there the tokenizer splits too.
    """
    data = _LOWER[data]
    solid = ~_GAP[data]
    first = solid.copy()
    first[1:] &= ~solid[:-1]
    heads = offsets[:-1][np.diff(offsets) > 0]
    first[heads] = solid[heads]
    starts = np.flatnonzero(first)
    closed = np.concatenate((starts[1:], [len(data)])) if len(starts) else starts
    kept = np.zeros(len(data) + 1, np.int32)  # bytes before each place, without gaps
    np.cumsum(solid, out=kept[1:])
    last = starts + kept[closed] - kept[starts] - 1  # a part has no gap inside
    at, low = last, starts
    for _ in range(_ENDING):
        mark = _MARK[data[at]] & (at > low)
        at, low = at[mark] - 1, low[mark]
        if not len(at):
            break
        here = data[at]
        wide = (here >= 0x80) & (here != 0x97) & (here != 0xB7) & (at > low) & (data[np.maximum(at - 1, 0)] == 0xC3)
        first[at[((here >= 97) & (here <= 122)) | wide] + 1] = True
    starts = np.flatnonzero(first)
    own = pa.Array.from_buffers(pa.large_string(), len(starts), [None, pa.py_buffer(np.append(kept[starts], kept[-1]).astype(np.int64)), pa.py_buffer(data[solid])])
    return own.dictionary_encode(), np.searchsorted(starts, offsets)


@lru_cache(maxsize=1)
def tokens(path: str) -> Tokens:
    """One tokenizer for each worker process."""
    return Tokens(path)


def pieces(docs: DataFrame, path: str, window: int = WINDOW) -> DataFrame:
    """Windows and rests of every document."""
    out = pa.schema([(c.split()[0], pa.int64()) for c in PIECES.split(", ")])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t, end = tokens(path), END_ID.to_bytes(4, "little")
        for b in slices(batches, 8 << 20):
            ids, offsets = t.packed(b.column(1))
            rows = []
            for key, lo, hi in zip(b.column(0).to_pylist(), offsets.tolist(), offsets[1:].tolist()):
                raw = ids[lo:hi].tobytes() + end
                n = hi - lo + 1
                rows += [(key, s, min(window, n - s), zlib.crc32(raw[4 * s : 4 * (s + window)]), n) for s in range(0, n, window)]
            yield record(out, *zip(*rows))

    return doc_text(docs).mapInArrow(run, PIECES)


# Plan ------------------------------------------------------------------------------------------------------------


def combinations(cells: list[int], total: int) -> np.ndarray:
    """Columns over ``cells``: every repetition of one length, and all pairs and triples that fill ``total`` exactly."""
    at, found = {c: i for i, c in enumerate(cells)}, set()
    for a in cells:
        found.add(((a, total // a),))
        for n in range(1, total // a + 1):
            left = total - n * a
            for b in cells:
                if b >= a:
                    break
                if left and left % b == 0:
                    found.add(((a, n), (b, left // b)))
    for a in cells:
        for b in cells:
            if b >= a:
                break
            left = total - a - b
            for n in range(1, left // max(1, 1) + 1 if left > 0 else 0):
                c, rest = divmod(left, n)
                if not rest and c < b and c in at:
                    found.add(((a, 1), (b, 1), (c, n)))
    columns = np.zeros((len(cells), len(found)), np.float64)
    for j, combo in enumerate(sorted(found)):
        for c, n in combo:
            columns[at[c], j] += n
    return columns


def nnls(a: np.ndarray, b: np.ndarray, tolerance: float = 1e-9) -> np.ndarray:
    """min |ax - b| over x >= 0 by the active-set method."""
    n = a.shape[1]
    x, free = np.zeros(n), np.zeros(n, bool)
    scale = tolerance * max(1.0, np.abs(a.T @ b).max(initial=0.0))
    for _ in range(3 * a.shape[0] + 10):
        slope = a.T @ (b - a @ x)
        slope[free] = -np.inf
        j = int(slope.argmax())
        if slope[j] <= scale:
            break
        free[j] = True
        while True:
            own = np.flatnonzero(free)
            s = np.linalg.lstsq(a[:, own], b, rcond=None)[0]
            if s.min(initial=1.0) > 0:
                x[:] = 0
                x[own] = s
                break
            bad = s <= 0
            step = (x[own][bad] / np.maximum(x[own][bad] - s[bad], 1e-300)).min()
            x[own] += step * (s - x[own])
            drop = own[(x[own] <= 1e-9 * max(1.0, x.max())) & bad]
            if not len(drop):
                drop = own[bad][:1]
            free[drop] = False
            x[drop] = 0
            if not free.any():
                break
    return x


def plan(histogram: dict[int, int], total: int) -> list[tuple[dict[int, int], int]]:
    """[(cell: how many in a sequence), how many sequences] that place every piece of ``histogram`` (cell: count)."""
    left = {c: n for c, n in sorted(histogram.items()) if n}
    if not left:
        return []
    cells = list(left)
    columns = combinations(cells, total)
    counts = np.array([left[c] for c in cells], float)
    waste = (total - np.array(cells) @ columns) / total  # a little dearer than the fit, so that full combinations win
    fitted = np.vstack((columns / np.sqrt(np.maximum(counts, 1))[:, None], 0.05 * waste[None]))
    x = nnls(fitted, np.append(counts / np.sqrt(np.maximum(counts, 1)), 0.0))
    out = []
    for j in np.argsort(-x):
        if waste[j] > 0.03:  # greedy packing may find company for these
            continue
        own = {cells[i]: int(columns[i, j]) for i in np.flatnonzero(columns[:, j])}
        n = min([int(x[j] + 1e-6), *(left[c] // k for c, k in own.items())])
        if n <= 0:
            continue
        out.append((own, n))
        for c, k in own.items():
            left[c] -= n * k
    out += _greedy(left, total)
    # for a handful of pieces, rounding costs more than the fit gains
    return min(out, _greedy(dict(histogram), total), key=lambda p: sum(n for _, n in p))


def _greedy(left: dict[int, int], total: int) -> list[tuple[dict[int, int], int]]:
    """The largest cell first, then whatever fits best, as often as the counts allow."""
    out = []
    while any(left.values()):
        own, room = {}, total
        for c in sorted(left, reverse=True):
            k = min(left[c], room // c)
            if k:
                own[c] = k
                room -= k * c
        n = min(left[c] // k for c, k in own.items())
        out.append((own, n))
        for c, k in own.items():
            left[c] -= n * k
    return out


def pack(cut_pieces: DataFrame, window: int = WINDOW, grid: int = GRID) -> DataFrame:
    """``pieces`` with sequence_id and offset. Reads its input twice: pass a checkpointed frame."""
    spark = cut_pieces.sparkSession
    cell = F.ceil(F.col("length") / grid).cast("long")
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    part = F.pmod(F.xxhash64("doc_id", "start", "ids_crc32"), F.lit(parts))
    keyed = cut_pieces.select("*", cell.alias("_cell"), part.alias("_part"))
    counts = keyed.groupBy("_cell", "_part").agg(F.count("*").alias("_n"))
    # the table has a row for each cell and part; prefix sums run within a cell
    before = Window.partitionBy("_cell").orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    bases = counts.select("_cell", "_part", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_base"))
    histogram = {r._cell: r.n for r in counts.groupBy("_cell").agg(F.sum("_n").alias("n")).collect()}
    rows, first, used = [], 0, dict.fromkeys(histogram, 0)
    for own, n in plan(histogram, window // grid):
        slot = 0
        for c, k in sorted(own.items(), reverse=True):
            rows.append((c, used[c], used[c] + n * k, k, first, slot))
            used[c] += n * k
            slot += k
        first += n
    schema = "_cell long, _lo long, _hi long, _k long, _first long, _slot long"
    placed = small_table(spark, rows, schema)  # bounded by the number of cells, not by the corpus
    order = Window.partitionBy("_cell", "_part").orderBy("doc_id", "start", "ids_crc32")
    ranked = keyed.withColumn("_row", F.row_number().over(order) - 1).join(bases, ["_cell", "_part"])
    ranked = ranked.withColumn("_rank", F.col("_row") + F.col("_base")).drop("_row", "_base", "_part")
    hit = (F.col("_rank") >= F.col("_lo")) & (F.col("_rank") < F.col("_hi"))
    joined = ranked.join(F.broadcast(placed).withColumnRenamed("_cell", "_c"), (F.col("_cell") == F.col("_c")) & hit)
    turn = F.col("_rank") - F.col("_lo")
    spread = joined.select(
        *cut_pieces.columns,
        (F.col("_first") + F.floor(turn / F.col("_k"))).cast("long").alias("sequence_id"),
        (F.col("_slot") + turn % F.col("_k")).alias("_place"),
    )
    earlier = Window.partitionBy("sequence_id").orderBy("_place").rowsBetween(Window.unboundedPreceding, -1)
    return spread.select(*cut_pieces.columns, "sequence_id", F.coalesce(F.sum("length").over(earlier), F.lit(0)).cast("long").alias("offset"))


def pack_documents(docs: DataFrame, path: str, window: int = WINDOW, grid: int = GRID) -> DataFrame:
    return pack(cut(pieces(docs, path, window)), window, grid)
