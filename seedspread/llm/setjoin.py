"""Candidates of an exact set-similarity join from ordered prefixes.

A set has one row per token of its prefix: the token (``cell``), the set's name in two longs (``doc``, ``tail``)
by which sets are ordered, and its size with the token's rank in the global order (``place``). Sets that share a
prefix token meet; the length filter and the positional filter thin the pairs, and what is left still needs
verification on the full sets. Cells above a limit are dealt in pairs of chunks, so no task holds a whole hot cell.

Rows without a ``team`` are read as sets whose lower half of ``tail`` is a digest: of the sets of a cell that
agree in it and in ``place``, equal sets in other words, the first one alone is compared.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from seedspread.llm.hashing import DIGEST, RANK_GROUPS
from seedspread.llm.sizes import few
from seedspread.runtime import materialize

#: Rows up to which groups are handled together.
SMALL = 24
#: Candidates that a task holds before it passes them on.
BATCH_ROWS = 500_000
BASE, MORE = ("cell", "doc", "tail", "place"), ("side", "open", "team")
FOUND = "kind int, a_doc long, a_tail long, b_doc long, b_tail long, place long"


def ranks_of(counted: DataFrame) -> np.ndarray:
    """Rarity rank of each of the ``RANK_GROUPS`` token groups from ``(group, n)`` rows, at most one per group and task."""
    total = np.zeros(RANK_GROUPS, np.int64)
    for r in counted.groupBy("group").agg(F.sum("n").alias("n")).collect():  # at most RANK_GROUPS rows
        total[r["group"]] = r["n"]
    ranks = np.empty(RANK_GROUPS, np.int64)
    ranks[np.lexsort((np.arange(RANK_GROUPS), total))] = np.arange(RANK_GROUPS)
    return ranks


def place(size: Column, rank: Column) -> Column:
    """Size of a set and rank of a token in one number."""
    return F.shiftleft(size.cast("long"), 32).bitwiseOR(rank.cast("long"))


def _met(percent: int, a: np.ndarray, b: np.ndarray, a_pos: np.ndarray, b_pos: np.ndarray) -> np.ndarray:
    """Length and positional filter for sets of sizes a and b whose first shared token stands at the given ranks."""
    good = 100 * np.minimum(a, b) >= percent * np.maximum(a, b)
    # at the first token two sets share, all they share stands from there on in both
    return good & (np.minimum(a - a_pos, b - b_pos) * (100 + percent) >= percent * (a + b))


def _candidates(percent: int, hot_group: int, every: bool, wide: bool):
    """Rows sorted by (cell, doc, tail) → kinds: 0 pair (earlier a, later b); 1 member b of cell ``a_doc`` in which a set has several candidates; 2 hot cell ``a_doc`` of ``place`` rows.

    ``wide`` rows also carry ``side`` (chunk, -1 for none), ``open`` and ``team`` (null: see above).
    ``every``: all candidates of open rows instead of the first one of each row. Sets of one team never meet.
    """

    def large(cell, doc, tail, place, side, open_, team):
        """One large group, in blocks of rows against all earlier ones."""
        n, pos = place >> 32, place & DIGEST
        for lo in range(0, len(doc), 512):
            hi = min(lo + 512, len(doc))
            good = _met(percent, n[:hi][None, :], n[lo:hi][:, None], pos[:hi][None, :], pos[lo:hi][:, None])
            good &= np.arange(hi)[None, :] < np.arange(lo, hi)[:, None]
            good &= team[:hi][None, :] != team[lo:hi][:, None]
            if wide:
                s = side[lo:hi][:, None]
                good &= (s < 0) | (s != side[:hi][None, :])
            if every:
                if wide:
                    good &= open_[lo:hi][:, None] > 0
                r, c = np.nonzero(good)
            else:
                count = good.sum(1)
                r = np.flatnonzero(count)
                c = good[r].argmax(1)
                if (count > 1).any():
                    yield 1, cell, cell * 0, doc, tail, place
            yield 0, doc[c], tail[c], doc[lo + r], tail[lo + r], place[lo + r]

    def small(group, before, cell, doc, tail, place, side, open_, team):
        """All groups of at most ``SMALL`` rows at once: each row against the one ``d`` before it, for every d."""
        n, pos = place >> 32, place & DIGEST
        count, first = np.zeros(len(doc), np.int64), np.zeros(len(doc), np.int64)
        for d in range(1, SMALL):
            later = np.flatnonzero(before >= d)
            if len(later) == 0:
                break
            early = later - d
            good = _met(percent, n[early], n[later], pos[early], pos[later]) & (team[early] != team[later])
            if wide:
                good &= (side[later] < 0) | (side[early] != side[later])
                if every:
                    good &= open_[later] > 0
            later, early = later[good], early[good]
            if every:
                yield 0, doc[early], tail[early], doc[later], tail[later], place[later]
            else:
                count[later] += 1
                first[later] = early
        if not every:
            rows = np.flatnonzero(count)
            yield 0, doc[first[rows]], tail[first[rows]], doc[rows], tail[rows], place[rows]
            held = (np.bincount(group[count > 1], minlength=group[-1] + 1 if len(group) else 0) > 0)[group]
            yield 1, cell[held], cell[held] * 0, doc[held], tail[held], place[held]

    def flush(cols):
        """All complete groups of ``cols``."""
        cell = cols[0]
        run = np.cumsum(np.concatenate([[0], (cell[1:] != cell[:-1]).astype(np.int64)]))
        keep = np.bincount(run)[run] > 1
        run, cols = run[keep], [c[keep] for c in cols]
        if not wide:
            # equal sets of a cell: the first alone stays
            order = np.lexsort((np.arange(len(run)), cols[3], cols[2] & DIGEST, run))
            r, t, p = run[order], cols[2][order] & DIGEST, cols[3][order]
            again = (r[1:] == r[:-1]) & (t[1:] == t[:-1]) & (p[1:] == p[:-1])
            only = np.sort(order[np.concatenate([[True], ~again])]) if len(order) else order
            run, cols = run[only], [c[only] for c in cols]
            team = np.arange(len(run))
            side = open_ = None
        else:
            side, open_, team = cols[4:]
        cell, doc, tail, place = cols[:4]
        at = np.flatnonzero(np.concatenate([[True], run[1:] != run[:-1]])) if len(run) else np.empty(0, np.int64)
        size = np.diff(np.append(at, len(run)))
        group = np.repeat(np.arange(len(at)), size)
        cut = lambda sel: (cell[sel], doc[sel], tail[sel], place[sel], None if side is None else side[sel], None if open_ is None else open_[sel], team[sel])
        few = (size[group] > 1) & (size[group] <= SMALL)
        none = np.empty(0, np.int64)
        out = [(0, none, none, none, none, none)]
        if few.any():
            out += small(group[few], (np.arange(len(cell)) - at[group])[few], *cut(few))
        for k in np.flatnonzero(size > SMALL):
            a, b = at[k], at[k] + size[k]
            if hot_group and b - a > hot_group:
                zero = np.zeros(1, np.int64)
                out.append((2, cell[a : a + 1], zero, zero, zero, np.array([b - a])))
                continue
            crowd = False
            for found in large(*cut(slice(a, b))):
                if found[0] == 0 or not crowd:
                    out.append(found)
                crowd |= found[0] == 1
                if sum(len(o[1]) for o in out) > BATCH_ROWS:
                    yield packed(out)
                    out = []
        if out:
            yield packed(out)

    def packed(out):
        kind = np.concatenate([np.full(len(o[1]), o[0], np.int32) for o in out])
        columns = [np.concatenate([o[j] for o in out]).astype(np.int64) for j in range(1, 6)]
        return pa.RecordBatch.from_arrays([pa.array(kind), *map(pa.array, columns)], names=["kind", "a_doc", "a_tail", "b_doc", "b_tail", "place"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list | None = None
        for batch in batches:
            if batch.num_rows == 0:
                continue
            cols = [batch.column(k).to_numpy(zero_copy_only=False) for k in range(7 if wide else 4)]
            if held is not None:
                cols = [np.concatenate([h, c]) for h, c in zip(held, cols, strict=True)]
            cut = int(np.searchsorted(cols[0], cols[0][-1], side="left"))
            if cut:
                yield from flush([c[:cut] for c in cols])
            held = [c[cut:] for c in cols]
        if held is not None:
            yield from flush(held)

    return run


def _dealt(rows: DataFrame, percent: int, hot_group: int, every: bool) -> DataFrame:
    wide = "team" in rows.columns
    cells = rows.select(*BASE, *(MORE if wide else ())).repartition("cell").sortWithinPartitions("cell", "doc", "tail")
    return cells.mapInArrow(_candidates(percent, hot_group, every, wide), FOUND)


def _chunked(rows: DataFrame, hot: DataFrame, hot_group: int) -> DataFrame:
    """Rows of hot cells dealt to pairs of chunks, so that no task holds a whole cell."""
    if "team" not in rows.columns:
        # equal sets of a hot cell first: the earliest of each stays
        alike = rows.join(hot.select("cell"), "cell").groupBy("cell", F.col("tail").bitwiseAND(F.lit(DIGEST)).alias("team"), "place").agg(F.min(F.struct("doc", "tail")).alias("first"))
        rows = alike.select("cell", "first.doc", "first.tail", "place", F.lit(-1).cast("long").alias("side"), F.lit(1).cast("long").alias("open"), F.xxhash64("team", "place").alias("team"))
    met = rows.join(hot, "cell").withColumn("chunks", F.ceil(2 * F.col("rows") / hot_group).cast("int")).withColumn("own", F.pmod(F.xxhash64("doc", "tail"), F.col("chunks")).cast("int"))
    dealt = met.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)))
    cell = F.xxhash64("cell", F.least("own", "other"), F.greatest("own", "other"))
    return dealt.select(cell.alias("cell"), "doc", "tail", "place", F.when(F.col("own") == F.col("other"), F.lit(-1)).otherwise(F.col("own")).cast("long").alias("side"), "open", "team")


def candidate_pairs(rows: DataFrame, percent: int, hot_group: int, every: bool) -> DataFrame:
    """Candidates of the sets whose prefix rows ``(cell, doc, tail, place)`` are given, with ``side`` -1, ``open`` and ``team`` where needed."""
    found = materialize(_dealt(rows, percent, hot_group, every), "candidates")
    hot = found.filter("kind = 2").select(F.col("a_doc").alias("cell"), F.col("place").alias("rows"))
    if not hot.isEmpty():
        found = found.filter("kind < 2").union(materialize(_dealt(_chunked(rows, few(hot), hot_group), percent, 0, every), "candidates"))
    return found


def pairs_of(found: DataFrame) -> DataFrame:
    """The distinct candidate pairs."""
    return found.filter("kind = 0").select("a_doc", "a_tail", "b_doc", "b_tail").distinct()


def members_of(found: DataFrame) -> DataFrame:
    """The distinct members of cells in which a set has more candidates than the one given."""
    return found.filter("kind = 1").select(F.col("a_doc").alias("cell"), F.col("b_doc").alias("doc"), F.col("b_tail").alias("tail"), "place").distinct()
