"""Near-duplicate vectors by randomised-rotation binary codes with stored correction factors.

A vector is scaled to unit length, rotated by a seeded random orthogonal matrix and reduced to the signs of
its coordinates; a short vector is padded with zeros to ``CODE_BITS`` first, so its code is longer than itself.
Beside the packed code stand the factor f = <code, rotated vector>, and the vector in four bits a coordinate:
a second rotation, rounded up or down by a seeded dither, so that the rounding has mean zero. For two vectors,
<code of one, four-bit form of the other> / f is an unbiased estimate of their inner product; its error has a
standard deviation of about sqrt((1 - f²) / (bits - 1) + step² / 4) / f. These packed columns are stored once,
and they alone go to the tables of buckets. Only pairs whose estimate plus ``Z`` deviations reaches the threshold
are recomputed: vectors are fetched for the rows of such pairs, and the exact value, in double precision, alone
makes a link.

Which pairs meet at all is decided by sign bits of further rotations, cut into tables of ``bits`` bits. At
cosine c a bit agrees with probability 1 - acos(c) / pi, so the number of tables follows from the wanted
chance, ``MISS``, that a pair exactly at the threshold shares no table; closer pairs are missed less. ``bits``
grows with the logarithm of the number of vectors, so buckets keep their size as data grow.

Equal vectors of a label are collapsed first. A pair counts in the first table it shares, so a row carries the
words of the tables up to its own and counts need no list of pairs: a bucket names its rows that need exact
values, then emits per vector one count and the smallest vector of its local component. Buckets above
``hot_bucket`` vectors are dealt in pairs of chunks to many tasks.

Cases: null, empty, zero or non-finite vectors, null labels and null ids link with nothing; vectors of
different length never meet; repeated rows link with each other; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seedspread.operators.components import connected_components
from seedspread.runtime import materialize

THRESHOLD, MISS, Z, HOT_BUCKET = 0.98, 2e-5, 5.0, 4096

#: Least length of a code in bits; vectors of more coordinates have a bit for each.
CODE_BITS = 256

#: Rows of a cell up to which its pairs are listed together with those of other cells.
SMALL_RUN = 16


def plan_tables(n: int, threshold: float = THRESHOLD, miss: float = MISS) -> tuple[int, int]:
    """(bits of a table, number of tables) for ``n`` vectors."""
    agree = 1 - math.acos(threshold) / math.pi
    bits = min(32, max(8, math.ceil(math.log2(n + 2))))
    return bits, math.ceil(math.log(miss) / math.log1p(-(agree**bits)))


def rotations(dim: int, n_bits: int, seed: int = 7) -> np.ndarray:
    """Enough stacked random orthogonal matrices for ``n_bits`` signs."""
    rng = np.random.default_rng([seed, dim])
    blocks = [np.linalg.qr(rng.standard_normal((dim, dim)))[0] for _ in range(math.ceil(n_bits / dim))]
    return np.concatenate(blocks)


def _matrix(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(lengths, row offsets, flat doubles) of a list column; nulls inside become NaN."""
    flat = column.flatten().cast(pa.float64())
    values = flat.fill_null(float("nan")).to_numpy(zero_copy_only=False)
    lengths = np.array(pa.compute.fill_null(pa.compute.list_value_length(column), 0), np.int64)
    return lengths, np.concatenate([[0], np.cumsum(lengths)[:-1]]) if len(lengths) else lengths, values


def encode(vectors: DataFrame) -> DataFrame:
    """``(vec_id, label, digest, unit)``: unit is the float64 vector's bytes, or null where it cannot link."""
    import pyarrow.compute  # noqa: F401  binds pa.compute

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import pyarrow.compute  # noqa: F401

        for batch in batches:
            ids, labels, column = batch.column(0), batch.column(1), batch.column(2)
            lengths, at, values = _matrix(column)
            usable = ~np.array(ids.is_null()) & ~np.array(labels.is_null()) & (lengths > 0)
            units, digests = [], []
            for k in range(len(lengths)):
                unit = mark = None
                if usable[k]:
                    v = values[at[k] : at[k] + lengths[k]]
                    if np.isfinite(v).all() and (norm := np.sqrt(v @ v)) > 0 and np.isfinite(norm):
                        unit = (v / norm).tobytes()
                        mark = hashlib.blake2b((v + 0.0).tobytes(), digest_size=16).digest()
                units.append(unit)
                digests.append(mark)
            yield pa.RecordBatch.from_arrays([ids, labels, pa.array(digests, pa.binary()), pa.array(units, pa.binary())], names=["vec_id", "label", "digest", "unit"])

    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("label").cast("string").alias("label"), F.col("embedding").cast("array<double>").alias("embedding"))
    return rows.mapInArrow(run, "vec_id long, label string, digest binary, unit binary")


class Coder:
    """Packed codes of unit vectors of one length, and estimates from them."""

    def __init__(self, dim: int, seed: int = 11):
        self.dim, self.bits = dim, max(CODE_BITS, dim)
        rng = np.random.default_rng([seed, dim])
        self.spin = np.linalg.qr(rng.standard_normal((self.bits, self.bits)))[0][:, :dim]
        self.smooth = np.linalg.qr(rng.standard_normal((dim, dim)))[0]
        self.dither = rng.random(dim)
        self.code_bytes, self.half_bytes = (self.bits + 7) // 8, (dim + 1) // 2

    def pack(self, x: np.ndarray) -> np.ndarray:
        """One row of bytes per vector: signs, four-bit coordinates, then factor, low and step as floats."""
        turned = x @ self.spin.T
        factor = np.abs(turned).sum(1) / math.sqrt(self.bits)
        smooth = x @ self.smooth.T
        low = smooth.min(1)
        step = np.maximum((smooth.max(1) - low) / 14, 1e-12)
        level = np.floor((smooth - low[:, None]) / step[:, None] + self.dither).clip(0, 15).astype(np.uint8)
        if self.dim % 2:
            level = np.concatenate([level, np.zeros((len(x), 1), np.uint8)], 1)
        numbers = np.stack([factor, low, step], 1).astype(np.float32)
        return np.concatenate([np.packbits(turned > 0, axis=1), level[:, ::2] << 4 | level[:, 1::2], numbers.view(np.uint8)], 1)

    def unpack(self, packed: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(codes over f, rotated four-bit forms, deviation of the estimate's first and second part squared, stacked)."""
        signs = np.unpackbits(packed[:, : self.code_bytes], axis=1, count=self.bits).astype(np.float32)
        half = packed[:, self.code_bytes : self.code_bytes + self.half_bytes]
        level = np.stack([half >> 4, half & 15], 2).reshape(len(packed), -1)[:, : self.dim]
        factor, low, step = np.ascontiguousarray(packed[:, self.code_bytes + self.half_bytes :]).view(np.float32).T
        rough = (low[:, None] + level * step[:, None]) @ self.smooth @ self.spin.T
        codes = (2 * signs - 1) / math.sqrt(self.bits) / factor[:, None]
        spread = np.maximum(1 - factor**2, 0) / factor**2 / (self.bits - 1)
        return codes, rough.astype(np.float32), np.stack([spread, 1 / factor, step / 2])

    def candidates(self, packed: np.ndarray, starts: np.ndarray, sizes: np.ndarray, threshold: float, z: float) -> tuple[np.ndarray, np.ndarray]:
        """Index pairs (i < j) inside runs of rows whose upper bound reaches the threshold.

        Pairs of small runs are listed for all runs of a size at once; larger runs go by blocks of a product."""
        codes, rough, (spread, inverse, noise) = self.unpack(packed)
        out_i, out_j = [np.empty(0, np.int64)], [np.empty(0, np.int64)]
        for size in np.unique(sizes[(sizes > 1) & (sizes <= SMALL_RUN)]):
            one, two = np.triu_indices(size, 1)
            at = starts[sizes == size][:, None]
            i, j = (at + one).ravel(), (at + two).ravel()
            for k in range(0, len(i), 16384):
                a, b = i[k : k + 16384], j[k : k + 16384]
                bound = np.einsum("ij,ij->i", codes[a], rough[b]) + z * np.sqrt(spread[a] + (inverse[a] * noise[b]) ** 2)
                out_i.append(a[bound >= threshold])
                out_j.append(b[bound >= threshold])
        for start, size in zip(starts[sizes > SMALL_RUN], sizes[sizes > SMALL_RUN], strict=True):
            end = start + size
            for lo in range(start, end, 1024):
                hi = min(lo + 1024, end)
                error = np.sqrt(spread[lo:hi, None] + (inverse[lo:hi, None] * noise[None, lo:end]) ** 2)
                i, j = np.nonzero(codes[lo:hi] @ rough[lo:end].T + z * error >= threshold)
                out_i.append(i[i < j] + lo)
                out_j.append(j[i < j] + lo)
        return np.concatenate(out_i), np.concatenate(out_j)


def table_keys(heads: DataFrame, bits: int, tables: int) -> DataFrame:
    """Heads with ``code``, the packed code, and ``words``, the sign bits of each table (four bytes a table)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        turns: dict[int, tuple[np.ndarray, Coder]] = {}
        weights = (1 << np.arange(bits)).astype(np.int64)
        for batch in batches:
            units = batch.column(3).to_pylist()
            codes: list = [None] * len(units)
            words = np.zeros((len(units), tables), ">u4")
            for size in {len(u) for u in units}:
                dim, mine = size // 8, [k for k, u in enumerate(units) if len(u) == size]
                if dim not in turns:
                    turns[dim] = rotations(dim, bits * tables)[: bits * tables], Coder(dim)
                turn, coder = turns[dim]
                x = np.frombuffer(b"".join(units[k] for k in mine), np.float64).reshape(-1, dim)
                words[mine] = ((x @ turn.T) > 0).reshape(len(mine), tables, bits) @ weights
                for k, row in zip(mine, coder.pack(x), strict=True):
                    codes[k] = row.tobytes()
            packed = pa.array([w.tobytes() for w in words], pa.binary())
            yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in range(4)), pa.array(codes, pa.binary()), packed], names=["rep", "label", "c", "unit", "code", "words"])

    return heads.select("rep", "label", "c", "unit").mapInArrow(run, "rep long, label string, c long, unit binary, code binary, words binary")


def _local_components(n: int, i: np.ndarray, j: np.ndarray, ids: np.ndarray) -> np.ndarray:
    """Smallest id of each row's component."""
    low = ids.copy()
    while True:
        before = low.copy()
        np.minimum.at(low, i, before[j])
        np.minimum.at(low, j, before[i])
        if np.array_equal(before, low):
            return low


def _cells(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.Table, np.ndarray]]:
    """Sorted rows in tables of whole ``(t, label, cell)`` groups, with the number of each row's group."""
    import pyarrow.compute as pc

    held: list[pa.Table] = []

    def whole(parts: list[pa.Table]) -> tuple[pa.Table, np.ndarray]:
        rows = pa.concat_tables(parts).combine_chunks()
        change = np.zeros(rows.num_rows, np.int64)
        for name in ("t", "label", "cell"):
            column = rows[name].combine_chunks()
            change[1:] |= np.array(pc.not_equal(column[1:], column[:-1]), bool)
        return rows, np.cumsum(change)

    for batch in batches:
        if batch.num_rows == 0:
            continue
        rows = pa.Table.from_batches([batch])
        last = np.ones(batch.num_rows, bool)
        for name in ("t", "label", "cell"):
            last &= np.array(pc.equal(rows[name], rows[name][-1]), bool)
        cut = int(np.flatnonzero(~last).max(initial=-1)) + 1
        ended = held and any(held[-1][n][-1].as_py() != rows[n][-1].as_py() for n in ("t", "label", "cell"))
        if cut or ended:
            yield whole([*held, rows.slice(0, cut)])
            held = []
        held.append(rows.slice(cut))
    if held:
        yield whole(held)


def _bytes(column: list, mine: np.ndarray, kind: type) -> np.ndarray:
    return np.frombuffer(b"".join(column[k] for k in mine), kind).reshape(len(mine), -1)


class CellPairs:
    """Pairs inside cells that their cell has to compute exactly."""

    def __init__(self, threshold: float, z: float):
        self.threshold, self.z, self.coders = threshold, z, {}

    def pairs(self, rows: pa.Table, cell: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(i, j) per table and vector length: bound reached, across the two sides, and no earlier table shared."""
        codes, words = rows["code"].to_pylist(), rows["words"].to_pylist()
        tables, dims, ids, side = (rows[n].to_numpy() for n in ("t", "dim", "rep", "side"))
        for t in np.unique(tables):
            for dim in np.unique(dims[tables == t]).tolist():
                mine = np.flatnonzero((tables == t) & (dims == dim))
                if dim not in self.coders:
                    self.coders[dim] = Coder(dim)
                _, starts, sizes = np.unique(cell[mine], return_index=True, return_counts=True)
                i, j = self.coders[dim].candidates(_bytes(codes, mine, np.uint8), starts, sizes, self.threshold, self.z)
                word = _bytes(words, mine, np.uint32)
                take = [np.empty(0, bool)]
                for k in range(0, len(i), 65536):  # blocks bound the memory of the comparison of words
                    a, b = i[k : k + 65536], j[k : k + 65536]
                    take.append((word[a, t] == word[b, t]) & ~(word[a, :t] == word[b, :t]).any(1))
                i, j = mine[i], mine[j]
                good = np.concatenate(take) & ((side[i] != side[j]) | (side[i] < 0)) & (ids[i] != ids[j])
                if good.any():
                    yield i[good], j[good]


def needed_rows(rows: DataFrame, threshold: float, z: float) -> DataFrame:
    """Sorted bucket rows → those that stand in a pair to be computed exactly, without code or vector."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        solver = CellPairs(threshold, z)
        for part, cell in _cells(batches):
            needed = np.zeros(part.num_rows, bool)
            for i, j in solver.pairs(part, cell):
                needed[i] = needed[j] = True
            yield from part.select(["t", "label", "cell", "rep", "side"]).filter(pa.array(needed)).to_batches()

    return rows.mapInArrow(run, "t int, label string, cell long, rep long, side long")


def bucket_links(rows: DataFrame, threshold: float, z: float) -> DataFrame:
    """Sorted rows with vectors → ``(v, linked, low, exact)``: copies linked first in this table, the smallest
    vector of the local component, and the pairs computed exactly (counted at one of their ends)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        solver = CellPairs(threshold, z)
        for part, cell in _cells(batches):
            ids, copies = part["rep"].to_numpy(), part["c"].to_numpy()
            units, n = part["unit"].to_pylist(), part.num_rows
            for i, j in solver.pairs(part, cell):
                sides, at = np.unique(np.concatenate([i, j]), return_inverse=True)
                x = _bytes(units, sides, np.float64)
                good = np.zeros(len(i), bool)
                for k in range(0, len(i), 65536):
                    a, b = x[at[: len(i)][k : k + 65536]], x[at[len(i) :][k : k + 65536]]
                    good[k : k + 65536] = np.einsum("ij,ij->i", a, b) >= threshold
                exact = np.bincount(i, minlength=n)
                i, j = i[good], j[good]
                linked = np.bincount(i, copies[j], n) + np.bincount(j, copies[i], n)
                low = _local_components(n, i, j, ids)
                touched = np.flatnonzero((linked > 0) | (exact > 0))
                columns = [ids[touched], linked[touched].astype(np.int64), low[touched], exact[touched].astype(np.int64)]
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=["v", "linked", "low", "exact"])

    return rows.mapInArrow(run, "v long, linked long, low long, exact long")


def near_vectors(vectors: DataFrame, threshold: float = THRESHOLD, z: float = Z, hot_bucket: int = HOT_BUCKET, counts: bool = False) -> DataFrame:
    """``vectors(vec_id, embedding, label)`` → ``(vec_id, n_links, component_id, kept)``, one row per row.

    With ``counts`` also ``n_exact``: pairs computed exactly for the row's class, each counted at one of its ends.
    """
    coded = materialize(encode(vectors), "vectors")
    usable = coded.filter("unit is not null")
    classes = usable.groupBy("label", "digest").agg(F.min("vec_id").alias("rep"), F.count("*").alias("c"))
    classes = materialize(classes, "classes")
    named = usable.withColumnRenamed("vec_id", "rep").dropDuplicates(["rep", "label", "digest"])
    heads = named.join(classes, ["label", "digest", "rep"])
    bits, tables = plan_tables(classes.count(), threshold)
    keyed = materialize(table_keys(heads, bits, tables), "keys")
    # only codes and the words of the tables so far go to the buckets, not the vectors
    dim = (F.octet_length("unit") / 8).cast("int")
    at = keyed.select("label", "rep", "code", "words", dim.alias("dim"), F.explode(F.sequence(F.lit(0), F.lit(tables - 1))).alias("t"))
    at = at.select("t", "label", "rep", "code", "dim", F.expr("substring(words, 4 * t + 1, 4)").alias("word"), F.expr("substring(words, 1, 4 * t + 4)").alias("words"))
    counts_of = at.groupBy("t", "label", "word").agg(F.count("*").alias("in_bucket")).filter("in_bucket > 1")
    met = at.join(counts_of, ["t", "label", "word"])
    chunks = F.ceil(F.col("in_bucket") / hot_bucket).cast("int")
    own = F.pmod(F.xxhash64("rep"), F.col("chunks")).cast("int")
    met = met.withColumn("chunks", chunks).withColumn("own", own)
    dealt = met.withColumn("with_", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)))
    # in a cell of two chunks only pairs across them count; a cell of one chunk counts all of its pairs
    cell = F.xxhash64("label", "word", F.least("own", "with_"), F.greatest("own", "with_"))
    side = F.when(F.col("own") == F.col("with_"), F.lit(-1)).otherwise(F.col("own"))
    rows = dealt.select("t", "label", cell.alias("cell"), "rep", "code", "words", "dim", side.cast("long").alias("side"))
    place = ["t", "label", "cell"]
    needed = materialize(needed_rows(rows.repartition(*place).sortWithinPartitions(*place), threshold, z), "needed")
    full = needed.join(keyed.select("rep", "label", "c", "unit", "code", "words", dim.alias("dim")), ["rep", "label"])
    full = full.withColumn("words", F.expr("substring(words, 1, 4 * t + 4)")).repartition(*place).sortWithinPartitions(*place)
    found = materialize(bucket_links(full, threshold, z), "links")
    edges = found.filter("v <> low").select(F.col("v").alias("a"), F.col("low").alias("b")).distinct()
    comps = connected_components(edges).withColumnRenamed("v", "rep")
    linked = found.groupBy(F.col("v").alias("rep")).agg(F.sum("linked").alias("linked"), F.sum("exact").alias("exact"))
    known = classes.join(linked, "rep", "left").join(comps, "rep", "left").select(
        "label", "digest", (F.col("c") - 1 + F.coalesce("linked", F.lit(0))).alias("links"), F.coalesce("component", "rep").alias("found"), F.coalesce("exact", F.lit(0)).alias("exact"))
    out = coded.join(known, ["label", "digest"], "left").select(
        "vec_id", F.coalesce("links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("found", "vec_id").alias("component_id"), *([F.coalesce("exact", F.lit(0)).alias("n_exact")] if counts else []))
    return out.withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))
