"""N-gram Jaccard join: documents whose sets of five-word shingles have a Jaccard similarity of 0.8 or more.

Texts are shingled once; set size, a digest of 128 bits, a hashed bitmap and the sorted shingles are stored. Equal
digests are one set (two different sets among N share one with odds N*N / 2**129). Candidates are named by the first
half of the digest; a half that two sets share only causes additional tests.

Any two sets that link share a shingle among the first ``n - ceil(0.8 n) + 1`` of each in one common order. The order
puts last the shingles that recurred within a task's batches, by how often; it keeps tiles small, and any order is
right, so it may hold the ``MOST_ORDERED`` most frequent ones only. Prefix rows (shingle, node, size, place) are dealt by
shingle. Rows of a shingle known to be frequent are spread, as they pass through; a shingle that isn't among them holds
less than one row in ``MOST_ORDERED``, so no task gets a hot key.

* A tile of up to ``HOT_FROM`` sets makes its pairs whose sizes are within a band of 0.8 and whose remaining shingles
  could still reach the overlap.
* Larger tiles are cut by size band. Every set first meets the leader that it shares most tiles with; what these pairs
  link becomes one component. Then a tile's rows are those of its most frequent component and the others,
  each cut into blocks of about ``BLOCK_ROWS``; pairs of blocks of the same or neighbouring bands are compared by their
  bitmaps, unless both are of that component. Of the pairs that these don't rule out a round tests each component's
  nearest few; components grow, and rounds go on with ever more pairs until none was left out. So a group of near copies
  costs a few tests a member. Pairs of one component are not tested; ``Join.links`` tests those too and gives every link.

A pair is tested in two steps. Hashed bitmaps of at least four bits a shingle (at most 4096): every differing bit is a
shingle that is not shared, which bounds the overlap from above. What is left is decided by intersecting both sorted
shingle arrays exactly. Linked sets form components (alternating star contraction), and a component's id is its least
document id.

Null and empty texts, and texts of white space only, have no shingles and link with nothing. Texts of fewer than five
words have one. Repeated rows are equal sets. A row without id belongs to a component, but never names it. Extra
columns are never read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from privq.llm.common import WORD, small_batches, table, text_or_empty, tidy
from privq.sources.scratch import Scratch, materialize

WORDS = 5
#: Frequent shingles that the common order puts last.
MOST_ORDERED = 200_000
COMMON_FROM = 2
#: Sets of a tile from which it goes through leaders and blocks.
HOT_FROM = 32
#: Least common shingles of a set that tell which one of its tiles is responsible for a pair.
FIRST_SHINGLES = 16
#: Shingles among which recurrence is counted at a time.
RECUR_AMONG = 1_000_000
#: Bytes of texts that are shingled at a time.
SLICE_BYTES = 500_000
#: Longest bitmap, in words of 64 bits.
BITMAP_WORDS = 64
#: Bits of the set of wanted nodes: eight a node, up to this power of two.
MOST_SIEVE_BITS = 26
BLOCK_ROWS = 512
#: Rows of prefix shingles that a tile task should get, and rows of blocks.
TILE_ROWS = 150_000
DEALT_ROWS = 20_000
#: Pairs of a component that a pair of blocks may name in the first round, and how much more in each next one.
FIRST_NEAREST, MORE_NEAREST = 1, 64

_SPACES = np.zeros(256, bool)
_SPACES[[0x20, *range(0x09, 0x0E)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_rng = np.random.Generator(np.random.PCG64(2024))
_BYTE_CODE = _rng.integers(0, 1 << 63, 256, dtype=np.uint64)[_LOWER] * np.uint64(2) + np.uint64(1)
_PLACE_CODE = _rng.integers(0, 1 << 63, WORDS, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_BASE = np.uint64(0x9E3779B97F4A7C15)
_BACK = np.uint64(pow(int(_BASE), -1, 1 << 64))
_SECOND = np.uint64(0xD6E8FEB86659FD93)


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class Shingler:
    """Distinct shingle hashes of texts, from the bytes of an Arrow column, in slices of bounded size."""

    def __init__(self) -> None:
        self.up, self.back = np.ones(1, np.uint64), np.ones(1, np.uint64)

    def _powers(self, n: int) -> None:
        if len(self.up) < n + 1:
            n = max(n, SLICE_BYTES)
            self.up = np.cumprod(np.concatenate([[np.uint64(1)], np.full(n, _BASE)]))
            self.back = np.cumprod(np.concatenate([[np.uint64(1)], np.full(n, _BACK)]))

    def words(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Hashes of all words, and the first word of each text; text k is ``data[offsets[k]:offsets[k + 1]]``."""
        n = len(data)
        if not n:
            return np.zeros(0, np.uint64), np.zeros(len(offsets), np.int64)
        self._powers(n)
        solid = ~_SPACES[data]
        border = np.zeros(n + 1, bool)
        border[offsets] = True
        starts = np.flatnonzero(solid & (border[:-1] | np.concatenate([[True], ~solid[:-1]])))
        ends = np.flatnonzero(solid & (border[1:] | np.concatenate([~solid[1:], [True]]))) + 1
        total = np.empty(n + 1, np.uint64)
        total[0] = 0
        np.cumsum(_BYTE_CODE[data] * self.up[:n], out=total[1:])
        words = _mix((total[ends] - total[starts]) * self.back[starts] + (ends - starts).astype(np.uint64))
        return words, np.searchsorted(starts, offsets)

    def long_words(self, data: np.ndarray) -> np.ndarray:
        """Word hashes of one long text, from pieces that end at white space."""
        found, lo = [], 0
        while lo < len(data):
            hi, step = min(len(data), lo + SLICE_BYTES), SLICE_BYTES
            while hi < len(data):
                gaps = np.flatnonzero(_SPACES[data[hi - step : hi]])
                if len(gaps):
                    hi = hi - step + int(gaps[-1]) + 1
                    break
                hi = min(len(data), hi + step)
            found.append(self.words(data[lo:hi], np.array([0, hi - lo]))[0])
            lo = hi
        return np.concatenate([*found, np.zeros(0, np.uint64)])

    @staticmethod
    def shingles(words: np.ndarray, first: np.ndarray) -> list[np.ndarray]:
        """Sorted distinct shingle hashes of each text."""
        whole = np.zeros(max(0, len(words) - WORDS + 1), np.uint64)
        for k in range(WORDS):
            whole += words[k : k + len(whole)] * _PLACE_CODE[k]
        whole = _mix(whole + np.uint64(WORDS))
        out = []
        for lo, hi in zip(first[:-1].tolist(), first[1:].tolist(), strict=True):
            if hi - lo >= WORDS:
                own = np.sort(whole[lo : hi - WORDS + 1])
                out.append(own[np.concatenate([[True], own[1:] != own[:-1]])])
            elif hi > lo:
                short = (words[lo:hi] * _PLACE_CODE[: hi - lo]).sum(dtype=np.uint64) + np.uint64(hi - lo)
                out.append(_mix(np.array([short], np.uint64)))
            else:
                out.append(np.zeros(0, np.uint64))
        return out

    def sets_of(self, data: np.ndarray) -> np.ndarray:
        """Sorted distinct shingle hashes of one text."""
        words = self.long_words(data)
        return self.shingles(words, np.array([0, len(words)]))[0]

    def batch(self, texts: pa.Array) -> Iterator[tuple[int, list[np.ndarray]]]:
        """First row and sets of slices of about ``SLICE_BYTES``, or of one longer text."""
        texts = texts.cast(pa.large_binary())
        offsets = np.frombuffer(texts.buffers()[1], np.int64)[texts.offset : texts.offset + len(texts) + 1]
        data = np.frombuffer(texts.buffers()[2], np.uint8) if texts.buffers()[2] is not None else np.zeros(0, np.uint8)
        lo = 0
        while lo < len(texts):
            hi = max(lo + 1, int(np.searchsorted(offsets, offsets[lo] + SLICE_BYTES, "right")) - 1)
            hi = min(hi, len(texts))
            if hi == lo + 1 and offsets[hi] - offsets[lo] > SLICE_BYTES:
                yield lo, [self.sets_of(data[offsets[lo] : offsets[hi]])]
            else:
                yield lo, self.shingles(*self.words(data[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo]))
            lo = hi


def digest(own: np.ndarray) -> tuple[int, int]:
    """Both halves of a set's digest, as signed 64-bit numbers."""
    n = np.uint64(len(own))
    halves = np.array([_mix(own * _BASE).sum(dtype=np.uint64) + n, _mix((own ^ _SECOND) * _BACK).sum(dtype=np.uint64) ^ n], np.uint64)
    node, more = _mix(halves).view(np.int64).tolist()
    return node, more


def prefix_length(n: int) -> int:
    return n - (4 * n + 4) // 5 + 1


def bitmap(own: np.ndarray) -> bytes:
    """Hashed bitmap of a set: a power of two of words, with at least four bits a shingle while the longest allows."""
    words = min(BITMAP_WORDS, 1 << max(0, (-(-len(own) // 16) - 1).bit_length()))
    line = np.zeros(words * 64, np.uint8)
    line[(own >> np.uint64(40)) & np.uint64(words * 64 - 1)] = 1
    return np.packbits(line, bitorder="little").tobytes()


def fold(maps: list[bytes]) -> np.ndarray:
    """Bitmaps as rows of words, longer ones folded to the shortest."""
    words = min(len(m) for m in maps) // 8
    if all(len(m) == 8 * words for m in maps):
        return np.frombuffer(b"".join(maps), np.uint64).reshape(len(maps), words)
    out = np.empty((len(maps), words), np.uint64)
    for k, m in enumerate(maps):
        out[k] = np.bitwise_or.reduce(np.frombuffer(m, np.uint64).reshape(-1, words), axis=0)
    return out


SETS = "doc_id bigint, n bigint, node bigint, more bigint, row bigint, bits binary, shingles binary, is_shingle boolean"
_SETS = pa.schema([("doc_id", pa.int64()), ("n", pa.int64()), ("node", pa.int64()), ("more", pa.int64()), ("row", pa.int64()), ("bits", pa.binary()), ("shingles", pa.binary()), ("is_shingle", pa.bool_())])


def _set_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows of documents, with bitmap and shingles at the first of equal sets among some, and rows of shingles that recur
    within these (hash, times). ``row`` is a mixed number of the row, one to one."""
    shingler, context = Shingler(), TaskContext.get()
    count = (context.partitionId() if context else 0) << 33
    seen: set[tuple[int, int]] = set()
    fresh, held = [], 0
    for batch in batches:
        ids = batch.column(0)
        for at, sets in shingler.batch(batch.column(1)):
            nodes, more, bits, arrays = [], [], [], []
            for own in sets:
                name = digest(own)
                new = len(own) > 0 and name not in seen
                nodes.append(name[0])
                more.append(name[1])
                bits.append(bitmap(own) if new else None)
                arrays.append(own.tobytes() if new else None)
                if new:
                    seen.add(name)
                    fresh.append(own)
                    held += len(own)
            sizes = [len(own) for own in sets]
            rows = _mix(np.arange(count, count + len(sets), dtype=np.uint64)).view(np.int64)
            count += len(sets)
            yield pa.RecordBatch.from_arrays([ids.slice(at, len(sets)), pa.array(sizes, pa.int64()), pa.array(nodes, pa.int64()), pa.array(more, pa.int64()), pa.array(rows), pa.array(bits, pa.binary()), pa.array(arrays, pa.binary()), pa.array([False] * len(sets))], schema=_SETS)
            if held >= RECUR_AMONG:
                yield _recurring(fresh)
                fresh, held, seen = [], 0, set()
    yield _recurring(fresh)


def _recurring(sets: list[np.ndarray]) -> pa.RecordBatch:
    values, times = np.unique(np.concatenate([*sets, np.zeros(0, np.uint64)]), return_counts=True)
    often = times >= COMMON_FROM
    values, times = values[often].view(np.int64), times[often].astype(np.int64)
    columns = {"n": pa.array(times), "node": pa.array(values), "is_shingle": pa.array(np.ones(len(values), bool))}
    return pa.RecordBatch.from_arrays([columns.get(f.name, pa.nulls(len(values), f.type)) for f in _SETS], schema=_SETS)


class Order:
    """The common order: shingles that recur come last, by the logarithm of how often."""

    def __init__(self, values: np.ndarray, times: np.ndarray):
        order = np.argsort(values)
        self.values, self.rank = values[order], np.maximum(1, np.log2(times[order]).astype(np.int64))
        self.hot = times[order] >= HOT_FROM
        self.sieve = np.zeros(1 << 20, bool)
        self.sieve[(values >> np.uint64(44)).astype(np.int64)] = True

    def prefix(self, own: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """First shingles of a set in this order, and which of them are known to be frequent."""
        p = prefix_length(len(own))
        maybe = np.flatnonzero(self.sieve[(own >> np.uint64(44)).astype(np.int64)]) if len(self.values) else np.zeros(0, np.int64)
        if len(maybe):
            at = np.minimum(np.searchsorted(self.values, own[maybe]), len(self.values) - 1)
            hit = self.values[at] == own[maybe]
            if hit.any():
                rank, hot = np.zeros(len(own), np.int64), np.zeros(len(own), bool)
                rank[maybe[hit]], hot[maybe[hit]] = self.rank[at[hit]], self.hot[at[hit]]
                order = np.argsort(rank, kind="stable")[:p]
                return own[order], hot[order]
        return own[:p], np.zeros(p, bool)


#: ``size`` holds the set's size and the shingle's place (31 bits each), and is negative for frequent shingles.
PREFIX = "shingle bigint, node bigint, size bigint"


def _prefix_batches(order: Order):
    """Prefix rows of sets, from their stored arrays."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["shingle", "node", "size"]
        for batch in batches:
            parts, held = [], 0
            for node, blob in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                own = np.frombuffer(blob.as_buffer(), np.uint64)
                first, hot = order.prefix(own)
                parts.append((first.view(np.int64), node, len(own), hot))
                held += len(first)
                if held >= 50_000:
                    yield pa.RecordBatch.from_arrays(_prefix_rows(parts), names)
                    parts, held = [], 0
            if parts:
                yield pa.RecordBatch.from_arrays(_prefix_rows(parts), names)

    return run


def _prefix_rows(parts: list[tuple]) -> list[pa.Array]:
    counts = [len(p[0]) for p in parts]
    at = np.concatenate([np.arange(c) for c in counts])
    nodes, sizes = np.array([p[1] for p in parts], np.int64), np.array([p[2] for p in parts], np.int64)
    size = np.repeat(sizes, counts) << 31 | at
    return [pa.array(x) for x in (np.concatenate([p[0] for p in parts]), np.repeat(nodes, counts), np.where(np.concatenate([p[3] for p in parts]), -size, size))]


_ROWS = np.dtype([("shingle", "<i8"), ("node", "<i8"), ("n", "<i4"), ("at", "<i4")])


def tile_pairs(rows: np.ndarray) -> np.ndarray:
    """Pairs of nodes that share a shingle, are within the size band and could still overlap enough.

    ``rows`` are sorted by shingle and size, without repeats.
    """
    found = []
    left = np.arange(len(rows))
    step = 1
    while len(left):
        left = left[left + step < len(rows)]
        right = left + step
        n, m = rows["n"][left].astype(np.int64), rows["n"][right].astype(np.int64)
        near = (rows["shingle"][left] == rows["shingle"][right]) & (5 * n >= 4 * m)  # m >= n
        left, right, n, m = left[near], right[near], n[near], m[near]
        room = np.minimum(n - rows["at"][left], m - rows["at"][right])
        good = 9 * room >= 4 * (n + m)
        a, b = rows["node"][left[good]], rows["node"][right[good]]
        if len(a):
            found.append(np.stack([np.minimum(a, b), np.maximum(a, b)], axis=1))
        step += 1
    return np.unique(np.concatenate(found), axis=0) if found else np.zeros((0, 2), np.int64)


def _finished(rows: np.ndarray, hot_from: int) -> Iterator[pa.RecordBatch]:
    """Pairs of whole small tiles (x, y, no n); the rows of larger ones (shingle, node, n)."""
    if not len(rows):
        return
    cuts = np.flatnonzero(np.concatenate([[True], rows["shingle"][1:] != rows["shingle"][:-1], [True]]))
    large = np.repeat(np.diff(cuts) > hot_from, np.diff(cuts))
    if large.any():
        yield _hot(rows[large])
    pairs = tile_pairs(rows[~large])
    for lo in range(0, len(pairs), 50_000):
        part = pairs[lo : lo + 50_000]
        yield pa.RecordBatch.from_arrays([pa.array(part[:, 0].copy()), pa.array(part[:, 1].copy()), pa.nulls(len(part), pa.int32())], ["x", "y", "n"])


def _hot(rows: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(rows[c].copy()) for c in ("shingle", "node", "n")], ["x", "y", "n"])


def _tile_batches(hot_from: int):
    """Goes through rows sorted by shingle, size and node; holds one batch and one small tile."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, passing = np.empty(0, _ROWS), None
        for batch in batches:
            rows, size = np.empty(batch.num_rows, _ROWS), batch.column(2).to_numpy()
            rows["shingle"], rows["node"], known = batch.column(0).to_numpy(), batch.column(1).to_numpy(), size < 0
            rows["n"], rows["at"] = np.abs(size) >> 31, np.abs(size) & ((1 << 31) - 1)
            if passing is not None:
                known |= rows["shingle"] == passing
            if known.any():
                yield _hot(rows[known])
                rows = rows[~known]
            if not len(rows):
                continue
            passing = None
            rows = np.concatenate([held, rows])
            again = (rows["shingle"][1:] == rows["shingle"][:-1]) & (rows["node"][1:] == rows["node"][:-1])
            rows = rows[np.concatenate([[True], ~again])]
            cut = int(np.flatnonzero(np.concatenate([[True], rows["shingle"][1:] != rows["shingle"][:-1]]))[-1])
            yield from _finished(rows[:cut], hot_from)
            held = rows[cut:]
            if len(held) > hot_from:
                yield _hot(held)
                passing, held = held["shingle"][0], np.empty(0, _ROWS)
        yield from _finished(held, hot_from)

    return run


def bitmap_pairs(left: np.ndarray, right: np.ndarray, n: np.ndarray, m: np.ndarray, apart: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rows of left and right that are ``apart`` and could link (sizes within the band, few enough bits differ), and the
    share of bits that differ."""
    total = n[:, None].astype(np.int64) + m[None, :]
    x, y = np.nonzero(apart & (5 * np.minimum(n[:, None], m[None, :]) >= 4 * np.maximum(n[:, None], m[None, :])))
    differ, total = np.zeros(len(x), np.int64), total[x, y]
    for k in range(0, left.shape[1], 8):
        differ += np.bitwise_count(left[x, k : k + 8] ^ right[y, k : k + 8]).sum(axis=1, dtype=np.int64)
        could = 9 * differ <= total
        x, y, differ, total = x[could], y[could], differ[could], total[could]
    return x, y, differ / np.maximum(1, total)


def _nearest(pairs: np.ndarray, roots: np.ndarray, share: np.ndarray, most: int) -> np.ndarray:
    """Which pairs are among the ``most`` nearest of a root at either end."""
    keep = np.zeros(len(pairs), bool)
    for side in (0, 1):
        order = np.lexsort((pairs[:, 1], pairs[:, 0], share, roots[:, side]))
        own = roots[order, side]
        first = np.flatnonzero(np.concatenate([[True], own[1:] != own[:-1]]))
        place = np.arange(len(own)) - np.repeat(first, np.diff(np.append(first, len(own))))
        keep[order[place < most]] = True
    return keep


def least_common(x: np.ndarray, y: np.ndarray, shingle: np.ndarray) -> np.ndarray:
    """Whether ``shingle`` is responsible for a pair of sets with the given least common-tile shingles (ascending, padded
    with ``_NO_SHINGLE``).

    The least element of what both lists hold is the least that both sets have. Where the lists have nothing in common,
    every shingle of the pair is responsible.
    """
    out = np.zeros(len(x), bool)
    for lo in range(0, len(x), 20_000):
        a, b = x[lo : lo + 20_000], y[lo : lo + 20_000]
        both = np.where((a[:, :, None] == b[:, None, :]).any(axis=2), a, _NO_SHINGLE).min(axis=1)
        out[lo : lo + 20_000] = (both == _NO_SHINGLE) | (both == shingle[lo : lo + 20_000])
    return out


_NO_SHINGLE = np.int64((1 << 63) - 1)


def _block_batches(most: int | None):
    """Pairs of different roots between the sides of each group that bitmaps don't rule out, each at the one shingle that
    is responsible for it: all, or each root's ``most`` nearest, with a row of nulls where that left some out.

    Columns group, side (0 left, 1 right, 2 both), node, root, n, shingle, bits, firsts; sorted by group.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        for batch in batches:
            group = batch.column(0).to_numpy()
            if held and held[0].column(0)[0].as_py() == group[-1]:
                held.append(batch)
                continue
            last = int(np.searchsorted(group, group[-1], "left")) if len(group) else 0
            yield from _groups(pa.Table.from_batches([*held, batch.slice(0, last)]) if held or last else None, most)
            held = [batch.slice(last)] if last < batch.num_rows else []
        yield from _groups(pa.Table.from_batches(held) if held else None, most)

    return run


def _groups(rows: pa.Table | None, most: int | None) -> Iterator[pa.RecordBatch]:
    if rows is None or not rows.num_rows:
        return
    group, side, node, root, n, shingle = (rows.column(k).to_numpy() for k in range(6))
    maps, firsts = rows.column(6).to_pylist(), np.full((rows.num_rows, FIRST_SHINGLES), _NO_SHINGLE)
    for k, own in enumerate(rows.column(7).to_pylist()):
        firsts[k, : len(own)] = own
    cuts = np.flatnonzero(np.concatenate([[True], group[1:] != group[:-1], [True]]))
    found, left_out = [], False
    for lo, hi in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
        bits, own = fold(maps[lo:hi]), []
        first, second = np.flatnonzero(side[lo:hi] != 1), np.flatnonzero(side[lo:hi] != 0)
        for at in range(0, len(first), 128):
            part = first[at : at + 128]
            apart = root[lo + part][:, None] != root[lo + second][None, :]
            if not apart.any():
                continue
            x, y, share = bitmap_pairs(bits[part], bits[second], n[lo + part], n[lo + second], apart)
            p, q = lo + part[x], lo + second[y]
            here = (p != q) & least_common(firsts[p], firsts[q], shingle[p])
            p, q, share = p[here], q[here], share[here]
            p, q = np.where(node[p] < node[q], p, q), np.where(node[p] < node[q], q, p)
            own.append((np.stack([node[p], node[q]], axis=1), np.stack([root[p], root[q]], axis=1), share))
        if own:
            pairs, roots, share = (np.concatenate(c) for c in zip(*own, strict=True))
            if most is not None:
                keep = _nearest(pairs, roots, share, most)
                left_out |= not keep.all()
                pairs = pairs[keep]
            found.append(pairs)
    if left_out:
        yield pa.RecordBatch.from_arrays([pa.nulls(1, pa.int64()), pa.nulls(1, pa.int64())], ["a", "b"])
    pairs = np.unique(np.concatenate(found), axis=0) if found else np.zeros((0, 2), np.int64)
    for lo in range(0, len(pairs), 50_000):
        part = pairs[lo : lo + 50_000]
        yield pa.RecordBatch.from_arrays([pa.array(part[:, 0].copy()), pa.array(part[:, 1].copy())], ["a", "b"])


def _near_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Pairs whose bitmaps don't rule them out; sizes and bitmaps are the last four columns."""
    for batch in batches:
        n, m = (batch.column(k).to_numpy() for k in (6, 7))
        x, y = batch.column(8).to_pylist(), batch.column(9).to_pylist()
        keep = np.zeros(batch.num_rows, bool)
        width = np.array([min(len(p), len(q)) for p, q in zip(x, y, strict=True)], np.int64)
        for w in np.unique(width).tolist():
            at = np.flatnonzero(width == w)
            both = fold([b"\0" * w, *(x[k] for k in at.tolist()), *(y[k] for k in at.tolist())])[1:]
            differ = np.bitwise_count(both[: len(at)] ^ both[len(at) :]).sum(axis=1, dtype=np.int64)
            keep[at] = 9 * differ <= n[at] + m[at]
        yield batch.select(list(range(6))).filter(pa.array(keep))


def bit_set(names: DataFrame) -> tuple[bytes, int]:
    """The places of ``names``, one column of mixed numbers, in a bit set of a power of two of bits, and that power."""
    (name,) = names.columns
    bits = int(min(MOST_SIEVE_BITS, max(16, (8 * names.count()).bit_length())))
    place = F.call_function("shiftrightunsigned", F.col(name), F.lit(64 - bits))
    words = names.select(F.shiftright(place, 5).cast("int").alias("w"), F.call_function("shiftleft", F.lit(1).cast("long"), place.bitwiseAND(31).cast("int")).alias("m")).groupBy("w").agg(F.bit_or("m").alias("m")).toArrow()
    sieve = np.zeros(1 << (bits - 5), np.uint32)
    sieve[words.column("w").to_numpy()] = words.column("m").to_numpy().astype(np.uint32)
    return sieve.tobytes(), bits


def _in_sieve(mixed: pa.Array, taken: np.ndarray, bits: int) -> pa.Array:
    place = (mixed.to_numpy().view(np.uint64) >> np.uint64(64 - bits)).astype(np.int64)
    return pa.array((taken[place >> 3] >> (place & 7).astype(np.uint8) & 1).astype(bool))


def _sieved_batches(sieve: bytes, bits: int):
    """Rows whose first column, a mixed number, has its place in the bit set taken."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        taken = np.frombuffer(sieve, np.uint8)
        for batch in batches:
            yield batch.filter(_in_sieve(batch.column(0), taken, bits))

    return run


def _sieve_column(sieve: bytes, bits: int):
    """The same as a column: only the mixed numbers go to Python."""

    def run(mixed: pa.Array) -> pa.Array:
        return _in_sieve(mixed, np.frombuffer(sieve, np.uint8), bits)

    return F.arrow_udf(run, "boolean")


def _overlap_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        keep = []
        for x, y in zip(batch.column(4), batch.column(5), strict=True):
            x, y = (np.frombuffer(z.as_buffer(), np.uint64) for z in (x, y))
            merged = np.sort(np.concatenate([x, y]), kind="stable")
            both = int(np.count_nonzero(merged[1:] == merged[:-1]))
            keep.append(100 * both >= 80 * (len(x) + len(y) - both))
        yield batch.select([0, 1, 2, 3]).filter(pa.array(keep, pa.bool_()))


_PAIR = "a bigint, a_more bigint, b bigint, b_more bigint"
_NEAR = f"{_PAIR}, a_row bigint, b_row bigint"


class Join:
    """The join over one table of texts; every step that is read twice is written to the shared folder."""

    def __init__(self, docs: DataFrame, text: str = "text", id_column: str = "doc_id"):
        self.spark = docs.sparkSession
        self.steps = Scratch(self.spark)
        bodies = docs.select(docs[id_column].cast("long").alias("doc_id"), text_or_empty(text).cast("binary").alias("body"))
        with small_batches(self.spark):
            self.sets = self.steps.store(bodies.mapInArrow(tidy(_set_batches), SETS), "join-sets")
        self.profile = self.sets.where("not is_shingle").select("doc_id", "n", "node", "more")
        self.arrays = self.sets.where("shingles is not null")
        maps = self.arrays.groupBy("node", "more").agg(F.min(F.struct("row", "n", "bits")).alias("one")).select("node", "more", "one.*")
        self.maps = self.steps.store(maps, "join-maps")

    def order(self) -> Order:
        common = self.sets.where("is_shingle").groupBy("node").agg(F.sum("n").alias("times")).orderBy(F.desc("times"), "node").limit(MOST_ORDERED).toArrow()
        return Order(common.column("node").to_numpy().view(np.uint64), common.column("times").to_numpy())

    def _parts(self, rows: int, each: int) -> int:
        return int(max(int(self.spark.conf.get("spark.sql.shuffle.partitions")), rows // each + 1))

    def tiles(self) -> tuple[DataFrame, DataFrame]:
        """Candidate pairs (a, b) of small tiles, and rows (shingle, node, n, band) of the larger ones."""
        rows = int(self.maps.agg(F.coalesce(F.sum(F.col("n") / 5 + 1), F.lit(0))).first()[0])
        prefixes = self.arrays.select("node", "shingles").mapInArrow(tidy(_prefix_batches(self.order())), PREFIX)
        salt = F.when(F.col("size") < 0, F.pmod(F.xxhash64("node"), F.lit(1024))).otherwise(0)
        dealt = prefixes.repartition(self._parts(rows, TILE_ROWS), "shingle", salt).sortWithinPartitions("shingle", "size", "node")
        made = self.steps.store(dealt.mapInArrow(tidy(_tile_batches(HOT_FROM)), "x bigint, y bigint, n int"), "join-tiles")
        band = F.floor(F.log(F.col("n").cast("double")) / F.log(F.lit(1.26))).cast("int").alias("band")
        hot = made.where("n is not null").distinct().select(F.col("x").alias("shingle"), F.col("y").alias("node"), "n", band)
        hot = self.steps.store(hot, "join-hot")
        firsts = hot.groupBy("node").agg(F.slice(F.sort_array(F.collect_set("shingle")), 1, FIRST_SHINGLES).alias("firsts"))
        self.hot_maps = self.steps.store(self.sieved(self.maps.select("node", "bits"), hot.select("node").distinct()).join(firsts, "node"), "join-hot-maps")
        return made.where("n is null").select(F.col("x").alias("a"), F.col("y").alias("b")).distinct(), hot

    @staticmethod
    def rooted(hot: DataFrame, roots: DataFrame | None) -> DataFrame:
        """``hot`` with the component of each node: itself where there are no links."""
        if roots is None:
            return hot.withColumn("root", F.col("node"))
        return hot.join(roots.select("node", F.col("root.node").alias("root")).dropDuplicates(["node"]), "node", "left").withColumn("root", F.coalesce("root", "node"))

    def leader_pairs(self, hot: DataFrame) -> DataFrame:
        """Each node with the leader that it meets in most tiles of its own and the next smaller band."""
        leaders = hot.groupBy("shingle", "band").agg(F.min(F.struct(F.xxhash64("node").alias("key"), "node", "n")).alias("lead"))
        near = hot.withColumn("band", F.explode(F.array(F.col("band"), F.col("band") - 1)))
        met = near.join(leaders, ["shingle", "band"]).where("node <> lead.node and 5 * least(n, lead.n) >= 4 * greatest(n, lead.n)")
        often = met.groupBy("node", F.col("lead.node").alias("other")).agg(F.count(F.lit(1)).alias("k"))
        most = often.groupBy("node").agg(F.max(F.struct("k", "other")).alias("best"))
        return most.select(F.least("node", "best.other").alias("a"), F.greatest("node", "best.other").alias("b")).distinct()

    def block_pairs(self, hot: DataFrame, roots: DataFrame | None, most: int | None = None) -> DataFrame:
        """Pairs of different components within the larger tiles that bitmaps don't rule out: all, or the ``most`` nearest
        of each component in a pair of blocks, with a row of nulls if that left some out."""
        placed = self.steps.store(self.rooted(hot, roots), "join-rooted")
        by_root = placed.groupBy("shingle", "band", "root").agg(F.count(F.lit(1)).alias("k"))
        tiles = by_root.groupBy("shingle", "band").agg(F.max(F.struct("k", "root")).alias("main"), F.sum("k").alias("k"))
        pieces = F.array(F.struct(F.lit(0).alias("kind"), F.col("main.root").alias("of"), F.col("main.k").alias("k")), F.struct(F.lit(1).alias("kind"), F.lit(None).cast("long").alias("of"), (F.col("k") - F.col("main.k")).alias("k")))
        kinds = tiles.select("shingle", "band", F.inline(pieces)).where("k > 0").withColumn("blocks", F.ceil(F.col("k") / BLOCK_ROWS).cast("int"))
        kinds = self.steps.store(kinds, "join-kinds")
        x, y = (kinds.select("shingle", *[F.col(c).alias(f"{c}_{s}") for c in ("band", "kind", "of", "k", "blocks")]) for s in "xy")
        met = x.join(y, "shingle").where("((band_x = band_y and kind_x <= kind_y) or band_y = band_x + 1) and not coalesce(of_x = of_y, false)")
        same = (F.col("band_x") == F.col("band_y")) & (F.col("kind_x") == F.col("kind_y"))
        met = met.withColumn("i", F.explode(F.sequence(F.lit(0), F.col("blocks_x") - 1))).withColumn("j", F.explode(F.sequence(F.when(same, F.col("i")).otherwise(0), F.col("blocks_y") - 1)))
        met = self.steps.store(met.withColumn("group", F.xxhash64("shingle", "band_x", "kind_x", "i", "band_y", "kind_y", "j")), "join-blocks")
        alone = same & (F.col("i") == F.col("j"))
        left = met.select("shingle", F.col("band_x").alias("band"), F.col("kind_x").alias("kind"), F.col("i").alias("block"), "group", F.when(alone, 2).otherwise(0).alias("side"))
        right = met.where(~alone).select("shingle", F.col("band_y").alias("band"), F.col("kind_y").alias("kind"), F.col("j").alias("block"), "group", F.lit(1).alias("side"))
        rows = int(met.agg(F.coalesce(F.sum(F.col("k_x") / F.col("blocks_x") + F.col("k_y") / F.col("blocks_y")), F.lit(0))).first()[0])
        own = placed.join(kinds.where("kind = 0").select("shingle", "band", "of"), ["shingle", "band"]).withColumn("kind", F.when(F.col("root") == F.col("of"), 0).otherwise(1))
        own = own.join(kinds.select("shingle", "band", "kind", "blocks"), ["shingle", "band", "kind"]).withColumn("block", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int"))
        dealt = own.join(left.union(right), ["shingle", "band", "kind", "block"]).join(self.hot_maps, "node").select("group", "side", "node", "root", "n", "shingle", "bits", "firsts")
        dealt = dealt.repartition(self._parts(rows, DEALT_ROWS), "group").sortWithinPartitions("group")
        return dealt.mapInArrow(tidy(_block_batches(most)), "a bigint, b bigint").distinct()

    def sieved(self, rows: DataFrame, names: DataFrame) -> DataFrame:
        """``rows`` whose first column is among ``names`` (one column), and few others: a bit set keeps the rest from
        being shuffled."""
        return rows.mapInArrow(tidy(_sieved_batches(*bit_set(names))), rows.schema)

    def verified(self, pairs: DataFrame) -> DataFrame:
        """Of pairs of nodes (a, b), the pairs of sets that link, exactly."""
        maps = self.sieved(self.maps, pairs.select(F.explode(F.array("a", "b")).alias("node")))
        x, y = (maps.select(F.col("node").alias(s), *[F.col(c).alias(f"{s}_{c}") for c in ("more", "row", "n", "bits")]) for s in "ab")
        met = pairs.join(x, "a").join(y, "b").select("a", "a_more", "b", "b_more", "a_row", "b_row", "a_n", "b_n", "a_bits", "b_bits")
        near = self.steps.store(met.mapInArrow(tidy(_near_batches), _NEAR), "join-near")
        arrays = self.sieved(self.arrays.select("row", "shingles"), near.select(F.explode(F.array("a_row", "b_row")).alias("row")))
        x, y = (arrays.toDF(f"{s}_row", f"{s}_shingles") for s in "ab")
        met = near.join(x, "a_row").join(y, "b_row").select("a", "a_more", "b", "b_more", "a_shingles", "b_shingles")
        links = self.steps.store(met.mapInArrow(tidy(_overlap_batches), _PAIR), "join-links")
        return links.select(F.struct(F.col("a").alias("node"), F.col("a_more").alias("more")).alias("a"), F.struct(F.col("b").alias("node"), F.col("b_more").alias("more")).alias("b"))

    def classes(self) -> DataFrame:
        """doc_id, n_shingles, component_id; one row per input row."""
        with small_batches(self.spark):
            return self._classes()

    def _classes(self) -> DataFrame:
        pairs, hot = self.tiles()
        pairs = self.steps.store(pairs.union(self.leader_pairs(hot)).distinct(), "join-pairs")
        links = self.verified(pairs)
        roots = components(links, self.steps)
        most, left_out = FIRST_NEAREST, not hot.isEmpty()
        while left_out:
            found = self.steps.store(self.block_pairs(hot, roots, most), "join-pairs")
            left_out, most = not found.where("a is null").isEmpty(), most * MORE_NEAREST
            pairs, links, roots = self._joined(found.where("a is not null"), pairs, links, roots)
        placed = self._placed(roots)
        self.steps.clear()
        return placed.select("doc_id", "n_shingles", "component_id")

    def _joined(self, more: DataFrame, pairs: DataFrame, links: DataFrame, roots: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
        """Tested pairs, links and components after the pairs in ``more`` that were not tested yet."""
        more = self.steps.store(more.join(pairs, ["a", "b"], "left_anti"), "join-pairs")
        if more.isEmpty():
            return pairs, links, roots
        found, pairs = self.verified(more), pairs.union(more)
        if found.isEmpty():
            return pairs, links, roots
        return pairs, links.union(found), components(links.union(found), self.steps)

    def _placed(self, roots: DataFrame) -> DataFrame:
        """doc_id, n_shingles, component_id, id; stored apart from the steps."""
        own = self.profile.select("doc_id", "n", F.struct("node", "more").alias("id"))
        placed = materialize(own.join(roots.select(F.col("node").alias("node"), F.col("more"), "root"), (own["id.node"] == F.col("node")) & (own["id.more"] == F.col("more")), "left").select("doc_id", "n", "id", F.coalesce("root", "id").alias("root")), "join-placed")
        least = materialize(placed.where("n > 0").groupBy("root").agg(F.min("doc_id").alias("component_id")), "join-least")
        return placed.join(least, "root", "left").select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("n") == 0, F.col("doc_id")).otherwise(F.col("component_id")).alias("component_id"), "id")

    def links(self) -> DataFrame:
        """Every pair of different sets that link; pairs of one component are tested like all others."""
        pairs, hot = self.tiles()
        return self.verified(self.steps.store(pairs.union(self.block_pairs(hot, None)).distinct(), "join-pairs"))

    def classes_with_links(self) -> DataFrame:
        """doc_id, n_shingles, component_id, n_links (other rows that a row links with, its copies included)."""
        with small_batches(self.spark):
            return self._classes_with_links()

    def _classes_with_links(self) -> DataFrame:
        links = self.links()
        copies = self.profile.where("n > 0").groupBy(F.struct("node", "more").alias("id")).agg(F.count(F.lit(1)).alias("copies"))
        both = links.union(links.select("b", "a")).toDF("id", "other")
        near = both.join(copies.toDF("other", "copies"), "other").groupBy("id").agg(F.sum("copies").alias("near"))
        count = materialize(copies.join(near, "id", "left").select("id", (F.col("copies") - 1 + F.coalesce("near", F.lit(0))).alias("n_links")), "join-counts")
        placed = self._placed(components(links, self.steps)).join(count, "id", "left")
        self.steps.clear()
        return placed.select("doc_id", "n_shingles", "component_id", F.coalesce("n_links", F.lit(0)).alias("n_links"))


def components(links: DataFrame, steps: Scratch | None = None) -> DataFrame:
    """node (and more), root (least of its component) for every end of ``links``; ends are numbers or structs.

    Alternating star contraction: each end is tied to the least of its neighbours, first by larger ones, then by
    smaller ones, until all components are stars; the rounds grow with the logarithm of the size. Leasts come from aggregates
    with a join back, so that the many links of one end are never gathered.
    """
    steps = Scratch(links.sparkSession) if steps is None else steps
    edges = steps.store(links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct(), "star")
    while True:
        ends = edges.select(F.col("u").alias("x"), F.lit(1).alias("up")).union(edges.select("v", F.lit(0)))
        degrees = ends.groupBy("x").agg(F.sum("up").alias("up"), F.sum(1 - F.col("up")).alias("down"))
        if degrees.where("up > 1 or (up = 1 and down > 0)").isEmpty():  # all are stars
            named = ["u.node", "u.more"] if edges.schema["u"].dataType.typeName() == "struct" else [F.col("u").alias("node")]
            return edges.select(*named, F.col("v").alias("root"))
        both = edges.union(edges.select("v", "u"))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).union(least.select("u", F.col("m").alias("v")))
        edges = steps.store(small.where("u <> v").distinct(), "star")


def keep_one_of_each(docs: DataFrame) -> DataFrame:
    """One row of each component of ``docs``, with its own columns; documents without shingles all stay.

    Rows go or are compared by id. A bit set of these ids lets all other rows stay where they are; rows that it names are
    shuffled to their id, so what moves follows the rows that go, not the texts.
    """
    classes = materialize(Join(docs).classes(), "join-classes")
    stays, sets = F.bool_or(F.expr("doc_id is null or n_shingles = 0 or coalesce(doc_id = component_id, false)")), F.count_if(F.col("n_shingles") > 0)
    marked = classes.groupBy(F.col("doc_id").alias("__id")).agg(stays.alias("__stays"), (sets > 1).alias("__twice")).where("not __stays or __twice")
    marked = materialize(marked, "join-marked")
    named = _sieve_column(*bit_set(marked.select(F.xxhash64("__id").alias("__id"))))(F.xxhash64(docs["doc_id"].cast("long")))
    met = docs.where(named).join(marked, docs["doc_id"].cast("long").eqNullSafe(marked["__id"]), "left").where(F.coalesce("__stays", F.lit(True)))
    compared = F.coalesce("__twice", F.lit(False)) & F.regexp_like(text_or_empty(), F.lit(WORD))
    kept = docs.where(~named).unionByName(met.where(~compared).select(*docs.columns))
    if marked.where("__stays and __twice").isEmpty():
        return kept
    return kept.unionByName(met.where(compared).select(*docs.columns).dropDuplicates(["doc_id", "text"]))


def op5_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Shingle count and component of every document of ``documents``."""
    return Join(table(spark, sf_dir, "documents").select("doc_id", "text")).classes()


def op5_ngram_join_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Shingle count, component and number of links of every document of ``documents``."""
    return Join(table(spark, sf_dir, "documents").select("doc_id", "text")).classes_with_links()
