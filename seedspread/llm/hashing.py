"""Vectorised word splitting and hashing over the raw UTF-8 bytes of an Arrow string column.

One pass of array operations handles many documents, so no Python loop runs per word. All hashes are
64 bits wide and depend on nothing but the bytes, so tasks on any executor agree.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

PIECE_BYTES = 1 << 17
MAX_PIECE_TEXTS = 1 << 16
#: Bytes of one text that are split into words at once.
PART_BYTES = 1 << 24
#: Lower half of a digest.
DIGEST = 0xFFFFFFFF
#: Token groups by the upper 16 bits of a token, for rarity counts of a fixed size.
RANK_GROUPS = 1 << 16
_MASK = (1 << 64) - 1
_ODD = 0x9E3779B97F4A7C15


def _mix(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser on 64-bit words."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def seeds(n: int, seed: int) -> np.ndarray:
    """``n`` odd pseudo-random 64-bit constants."""
    base = (np.arange(1, n + 1, dtype=np.uint64) + np.uint64(seed * 1_000_003 & _MASK)) * np.uint64(_ODD)
    return _mix(base) | np.uint64(1)


SPACE_SEPARATORS = bytes([0x20, *range(0x09, 0x0E)])
_INVERSE = pow(_ODD, -1, 1 << 64)


class Splitter:
    """Splits pieces of text into words and hashes each word."""

    def __init__(self, separators: bytes = SPACE_SEPARATORS):
        marks = sorted(separators)
        self.ranges = [(x, x) for x in marks[:1]]
        for x in marks[1:]:
            if x == self.ranges[-1][1] + 1:
                self.ranges[-1] = (self.ranges[-1][0], x)
            else:
                self.ranges.append((x, x))
        self.power = np.ones(1, np.uint64)
        self.inverse = np.ones(1, np.uint64)

    def _scan(self, data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(is in a word, folded byte with 0 for separators), by whole-array comparisons."""
        inside = np.ones(len(data), bool)
        for lo, hi in self.ranges:
            inside &= (data - np.uint8(lo)) > np.uint8(hi - lo)
        folded = data + (((data - np.uint8(65)) < np.uint8(26)).view(np.uint8) << np.uint8(5))
        return inside, folded * inside.view(np.uint8)

    def _grow(self, n: int) -> None:
        if len(self.power) < n:
            steps = np.full(n, _ODD, np.uint64)
            back = np.full(n, _INVERSE, np.uint64)
            steps[0] = back[0] = 1
            self.power, self.inverse = np.multiply.accumulate(steps), np.multiply.accumulate(back)

    def _words(self, data: np.ndarray, cuts: np.ndarray):
        """(word starts, running weighted sums, is in a word)."""
        n = len(data)
        self._grow(n + 1)
        inside, folded = self._scan(data)
        first = np.empty(n, bool)
        first[0] = True
        np.logical_not(inside[:-1], out=first[1:])
        inner = cuts[1:-1]
        first[inner[inner < n]] = True
        first &= inside
        total = np.empty(n + 1, np.uint64)
        total[0] = 0
        np.cumsum(folded.astype(np.uint64) * self.power[:n], out=total[1:])
        return np.flatnonzero(first), total, inside

    def words(self, data: np.ndarray, cuts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(word hashes, index of the text each word is in). ``cuts``: offsets of the texts, n + 1 of them.

        A word's hash is the polynomial of its folded bytes, mixed; separators weigh nothing, so the sum up to
        the next word's start is the word's own. Long inputs go in parts that end at a separator, so the
        working arrays stay a bounded multiple of ``PART_BYTES`` whatever the length of a text.
        """
        if len(data) <= PART_BYTES:
            return self._part(data, cuts)
        found, lo = [], 0
        while lo < len(data):
            hi = self._boundary(data, lo + PART_BYTES)
            a, b = np.searchsorted(cuts, lo, side="right") - 1, np.searchsorted(cuts, hi, side="left")
            codes, of = self._part(data[lo:hi], np.clip(cuts[a : b + 1] - lo, 0, hi - lo))
            found.append((codes, of + a))
            lo = hi
        return np.concatenate([x[0] for x in found]), np.concatenate([x[1] for x in found])

    def _boundary(self, data: np.ndarray, at: int) -> int:
        """The first separator from ``at`` on, or the end."""
        for lo in range(at, len(data), PIECE_BYTES):
            inside, _ = self._scan(data[lo : lo + PIECE_BYTES])
            if not inside.all():
                return lo + int(np.argmin(inside))
        return len(data)

    def _part(self, data: np.ndarray, cuts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        if len(data) == 0:
            return np.empty(0, np.uint64), np.empty(0, np.int64)
        starts, total, _ = self._words(data, cuts)
        sums = np.diff(total[np.append(starts, len(data))])
        return _mix(sums * self.inverse[starts]), np.searchsorted(cuts, starts, side="right") - 1

    def words_and_prefixes(self, data: np.ndarray, cuts: np.ndarray, lengths: tuple[int, ...]) -> tuple[np.ndarray, np.ndarray]:
        """(hashes, texts) of all words and of their first ``lengths`` bytes, where a word is longer than that."""
        if len(data) == 0:
            return np.empty(0, np.uint64), np.empty(0, np.int64)
        starts, total, inside = self._words(data, cuts)
        bounds = np.append(starts, len(data))
        owner = np.searchsorted(cuts, starts, side="right") - 1
        stops = np.append(np.flatnonzero(~inside), len(data))
        ends = np.minimum(stops[np.searchsorted(stops, starts)], bounds[1:])
        out, of = [_mix(np.diff(total[bounds]) * self.inverse[starts])], [owner]
        for k in lengths:
            long = ends - starts > k
            at = starts[long]
            out.append(_mix((total[at + k] - total[at]) * self.inverse[at] + np.uint64(k)))
            of.append(owner[long])
        return np.concatenate(out), np.concatenate(of)


def pieces(column: pa.Array, limit: int = PIECE_BYTES) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, end row, bytes, offsets) of runs of texts of about ``limit`` bytes; nulls count as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    column = column.cast(pa.large_binary())
    n = len(column)
    if n == 0:
        return
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + n + 1]
    data = np.frombuffer(column.buffers()[2], np.uint8) if column.buffers()[2] is not None else np.empty(0, np.uint8)
    row = 0
    while row < n:
        end = max(row + 1, int(np.searchsorted(offsets, offsets[row] + limit, side="right")) - 1)
        end = min(end, n, row + MAX_PIECE_TEXTS)
        yield row, end, data[offsets[row] : offsets[end]], offsets[row : end + 1] - offsets[row]
        row = end


def shingles(hashes: np.ndarray, owner: np.ndarray, n_texts: int, width: int = 5, unique: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """(hashes of the distinct ``width``-word runs of each text, index of the text), sorted by text.

    A text of fewer words, but not none, gives its whole sequence as one run. Without ``unique`` repeats stay
    and the order is arbitrary.
    """
    factors = seeds(width, 77)
    count = np.bincount(owner, minlength=n_texts)
    first = np.concatenate([[0], np.cumsum(count)[:-1]])
    runs = np.empty(0, np.uint64)
    of = np.empty(0, np.int64)
    if len(hashes) >= width:
        m = len(hashes) - width + 1
        mixed = hashes[:m] * factors[0]
        for k in range(1, width):
            mixed = _mix(mixed) + hashes[k : m + k] * factors[k]
        good = owner[:m] == owner[width - 1 :]
        runs, of = _mix(mixed[good]), owner[:m][good]
    short = np.flatnonzero((count > 0) & (count < width))
    if len(short):
        whole = count[short].astype(np.uint64)
        for k in range(width - 1):
            more = np.flatnonzero(count[short] > k)
            whole[more] = _mix(whole[more]) + hashes[first[short[more]] + k] * factors[1]
        whole = _mix(whole)
        runs, of = np.concatenate([runs, whole]), np.concatenate([of, short])
    return distinct(runs, of) if unique else (runs, of)


def distinct(values: np.ndarray, of: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The distinct (text, value) pairs, sorted by text, then value.

    Values are sorted first and texts second by a counting sort, so a piece may hold at most 2^16 texts.
    """
    if len(values) == 0:
        return values, of
    order = np.argsort(values)
    order = order[np.argsort(of[order].astype(np.uint16), kind="stable")]
    values, of = values[order], of[order]
    new = np.empty(len(values), bool)
    new[0] = True
    np.not_equal(values[1:], values[:-1], out=new[1:])
    new[1:] |= of[1:] != of[:-1]
    return values[new], of[new]


def set_digest(values: np.ndarray, of: np.ndarray, n_texts: int) -> tuple[np.ndarray, np.ndarray]:
    """Two independent 64-bit sums over each text's set: equal sets give equal pairs."""
    one, two = np.zeros(n_texts, np.uint64), np.zeros(n_texts, np.uint64)
    if len(values):
        texts, at = np.unique(of, return_index=True)
        one[texts] = np.add.reduceat(_mix(values ^ np.uint64(0xA5A5)), at)
        two[texts] = np.add.reduceat(_mix(values * np.uint64(_ODD)), at)
    return one, two


def count_groups(pieces: Iterator[np.ndarray]) -> pa.RecordBatch:
    """``(group, n)`` of all token values of a task."""
    total = np.zeros(RANK_GROUPS, np.int64)
    for values in pieces:
        total += np.bincount((values >> np.uint64(48)).astype(np.int64), minlength=RANK_GROUPS)
    group = np.flatnonzero(total)
    return pa.RecordBatch.from_arrays([pa.array(group.astype(np.int32)), pa.array(total[group])], names=["group", "n"])


def prefixes(values: np.ndarray, of: np.ndarray, n: int, ranks: np.ndarray, percent: int) -> tuple[np.ndarray, pa.ListArray]:
    """(size of each set, its prefix tokens rarest first) for sorted distinct tokens."""
    size = np.bincount(of, minlength=n)
    order = np.argsort((of << 16) | ranks[(values >> np.uint64(48)).astype(np.int64)], kind="stable")
    take = np.where(size > 0, size - (-(-percent * size // 100)) + 1, 0)
    within = np.arange(len(of)) - np.repeat(np.cumsum(size) - size, size)
    tokens = values[order][within < np.repeat(take, size)].view(np.int64)
    offsets = np.concatenate([[0], np.cumsum(take)]).astype(np.int32)
    return size, pa.ListArray.from_arrays(pa.array(offsets), pa.array(tokens))


def line_name(number: np.ndarray, digest: np.ndarray) -> np.ndarray:
    """Line number and lower half of the digest: with doc_id, the name and the order of a line."""
    return (number.astype(np.int64) << 32) | (digest & np.uint64(DIGEST)).astype(np.int64)
