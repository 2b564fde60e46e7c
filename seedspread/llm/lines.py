"""Line dedup by an exact set-similarity join: later lines that match an earlier one are removed.

The tokens of a line are its distinct runs of five words (its whole word sequence where it has fewer). A line
goes when an earlier line, in order of doc_id and line number, has a Jaccard similarity of at least
``percent`` percent with it. Every line that holds a word takes part (``MIN_WORDS``).

Tokens are put in one global order, rarest first, by counts of lines over the whole corpus kept for 65,536 groups of
tokens; ties go by the token itself, so the order is total and the filters are exact however tokens share a
group. A line of n tokens can only match through its first ``n - ceil(t n) + 1`` tokens (prefix filter),
with lines of n t to n / t tokens (length filter), and only if the tokens left after the shared one could
still reach the needed overlap (positional filter). What is left is verified on the lines themselves.

Texts are read twice (counts with line digests, prefixes), so that prefixes are shuffled once, by token, and
never written. Equal token sets are found by their digests; a task passes on the prefix of the first of each
only, and the rest are dropped where a token's lines meet. A line then needs one earlier match, so each group
of lines that share a prefix token gives every line its first candidate only; lines for which none of those is
confirmed get their other candidates in a second pass. Groups above ``hot_group`` lines are dealt in pairs of
chunks.

Cases: null texts stay null and blank lines stay; rows with equal doc_id and text are one document; in rows of
one doc_id with different texts, equal lines of one number count as one line; a null doc_id comes first in the
order; an empty table gives an empty result; other columns are kept, whatever their names, and the count of
removed lines takes a free name (``n_removed``, with an underscore for each clash).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seedspread.llm import hashing, setjoin
from seedspread.llm.minhash import confirm
from seedspread.llm.sizes import few, small
from seedspread.llm.text import shielded
from seedspread.runtime import materialize, release

PERCENT, WIDTH, MIN_WORDS, HOT_GROUP = 75, 5, 1, 8192
#: Prefix tokens that a task gathers before it passes on the first line of each token set.
GATHERED = 1 << 21
NO_ID = -(1 << 63)


def _line_sets(texts: pa.Array, width: int, min_words: int, unique: bool = True) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """(row of each line, line number, token values, line of each token) of lines with enough words."""
    splitter = hashing.Splitter()
    for row, _, data, cuts in hashing.pieces(texts, hashing.PIECE_BYTES // 2):
        breaks = np.flatnonzero(data == 10)
        starts = np.unique(np.concatenate([cuts[:-1], breaks + 1]))
        starts = starts[starts < len(data)]
        if len(starts) == 0:
            continue
        codes, of = splitter.words(data, np.append(starts, len(data)))
        enough = np.bincount(of, minlength=len(starts)) >= min_words
        codes, of = codes[enough[of]], of[enough[of]]
        lines = np.flatnonzero(enough)
        place = np.cumsum(enough) - 1
        of = place[of]
        for lo in range(0, len(lines), hashing.MAX_PIECE_TEXTS):
            part = lines[lo : lo + hashing.MAX_PIECE_TEXTS]
            a, b = np.searchsorted(of, [lo, lo + len(part)])
            values, owner = hashing.shingles(codes[a:b], of[a:b] - lo, len(part), width, unique)
            doc = np.searchsorted(cuts, starts[part], side="right") - 1
            number = np.searchsorted(breaks, starts[part]) - np.searchsorted(breaks, cuts[doc])
            yield row + doc, number, values, owner


def line_sets(docs: DataFrame, width: int, min_words: int) -> DataFrame:
    """``docs(doc, th, text)`` → one row per compared line: its number, size and set digest.

    The same pass counts the lines' tokens: rows of size 0 hold a token group in ``doc`` and its count in ``tail``.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["doc", "th", "tail", "n", "d1", "d2"]
        total = np.zeros(hashing.RANK_GROUPS, np.int64)
        for batch in batches:
            for row, number, values, of in _line_sets(batch.column(2), width, min_words):
                total += np.bincount((values >> np.uint64(48)).astype(np.int64), minlength=hashing.RANK_GROUPS)
                one, two = hashing.set_digest(values, of, len(row))
                rows = pa.array(row)
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).take(rows), batch.column(1).take(rows), pa.array(hashing.line_name(number, one)), pa.array(np.bincount(of, minlength=len(row)).astype(np.int32)),
                     pa.array(one.view(np.int64)), pa.array(two.view(np.int64))],
                    names=names)
        group = np.flatnonzero(total)
        none = pa.array(np.zeros(len(group), np.int64))
        yield pa.RecordBatch.from_arrays([pa.array(group.astype(np.int64)), none, pa.array(total[group]), pa.array(np.zeros(len(group), np.int32)), none, none], names=names)

    return docs.mapInArrow(run, "doc long, th long, tail long, n int, d1 long, d2 long")


def token_ranks(sets: DataFrame) -> np.ndarray:
    """Rarity rank of each token group, from the counts that ``line_sets`` made over all lines."""
    return setjoin.ranks_of(sets.filter("n = 0").select(F.col("doc").cast("int").alias("group"), F.col("tail").alias("n")))


def line_prefixes(docs: DataFrame, ranks: np.ndarray, percent: int, width: int, min_words: int) -> DataFrame:
    """``docs(doc, text)`` → prefix rows ``(cell, doc, tail, place)`` of the first of each task's equal lines."""

    def firsts(parts):
        doc, tail, one, two, size, take, tokens = (np.concatenate(x) for x in zip(*parts, strict=True))
        order = np.lexsort((tail, doc, size, two, one))
        again = (one[order][1:] == one[order][:-1]) & (two[order][1:] == two[order][:-1]) & (size[order][1:] == size[order][:-1])
        only = np.zeros(len(doc), bool)
        only[order[np.concatenate([[True], ~again])]] = True
        line = np.repeat(np.arange(len(doc)), take)
        pos = np.arange(len(tokens)) - np.repeat(np.cumsum(take) - take, take)
        held = only[line]
        line, pos = line[held], pos[held]
        columns = [tokens[held], doc[line], tail[line], (size[line] << 32) | pos]
        return pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=["cell", "doc", "tail", "place"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts, gathered = [], 0
        for batch in batches:
            ids = batch.column(0).to_numpy(zero_copy_only=False)
            for row, number, values, of in _line_sets(batch.column(1), width, min_words):
                one, two = hashing.set_digest(values, of, len(row))
                size, tokens = hashing.prefixes(values, of, len(row), ranks, percent)
                take = np.diff(tokens.offsets.to_numpy(zero_copy_only=False)).astype(np.int64)
                parts.append((ids[row], hashing.line_name(number, one), one, two, size, take, tokens.values.to_numpy(zero_copy_only=False)))
                gathered += len(parts[-1][-1])
                if gathered > GATHERED:
                    yield firsts(parts)
                    parts, gathered = [], 0
        if parts:
            yield firsts(parts)

    return docs.mapInArrow(run, "cell long, doc long, tail long, place long")


def _line_texts(docs: DataFrame, spots: DataFrame, width: int) -> DataFrame:
    """``(node, text)`` of the lines named by ``spots(node, doc, tail)``."""
    by_doc = small(spots.groupBy("doc").agg(F.collect_list(F.struct("node", "tail")).alias("need")), "need")
    held = docs.join(by_doc, "doc").withColumn("lines", F.split("text", "\n", -1))
    line = lambda x: F.struct(x["node"].alias("node"), x["tail"].bitwiseAND(F.lit(hashing.DIGEST)).alias("digest"), F.get("lines", F.shiftright(x["tail"], 32).cast("int")).alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # rows of one doc_id may differ in text: the digest tells which line was meant
        splitter, seen = hashing.Splitter(), np.empty(0, np.int64)
        for batch in batches:
            meant = [np.empty(0, np.int64)]
            for row, end, data, cuts in hashing.pieces(batch.column(2)):
                values, of = hashing.shingles(*splitter.words(data, cuts), end - row, width)
                one, _ = hashing.set_digest(values, of, end - row)
                digest = batch.column(1).slice(row, end - row).to_numpy(zero_copy_only=False)
                meant.append(row + np.flatnonzero((one & np.uint64(hashing.DIGEST)).astype(np.int64) == digest))
            meant = np.concatenate(meant)
            # rows that repeat doc_id and text: one line of each is enough, and a few more do no harm
            nodes, at = np.unique(batch.column(0).to_numpy(zero_copy_only=False)[meant], return_index=True)
            new = ~np.isin(nodes, seen, assume_unique=True)
            seen = np.union1d(seen, nodes[new])
            yield batch.take(pa.array(meant[at[new]])).select(["node", "text"])

    return held.select(F.inline(F.transform("need", line))).mapInArrow(run, "node long, text string")


def _confirmed(pairs: DataFrame, docs: DataFrame, percent: int, width: int) -> DataFrame:
    """``(node)`` of the later lines of the candidate pairs that hold on the full lines."""
    ends = pairs.select(F.col("a_doc").alias("doc"), F.col("a_tail").alias("tail")).union(pairs.select("b_doc", "b_tail")).distinct()
    texts = materialize(_line_texts(docs, ends.select(_node("doc", "tail").alias("node"), "doc", "tail"), width), "line_texts")
    named = pairs.select(_node("a_doc", "a_tail").alias("a"), _node("b_doc", "b_tail").alias("b"))
    return few(confirm(named, texts, percent, width).select(F.col("b").alias("node")).distinct())


def _node(doc, tail):
    return F.xxhash64(doc, tail)


def repeated_lines(docs: DataFrame, percent: int = PERCENT, width: int = WIDTH, min_words: int = MIN_WORDS, hot_group: int = HOT_GROUP) -> DataFrame:
    """``(doc, th, gone)``: the numbers of the lines to remove from each document that has any; ``doc`` is doc_id, or ``NO_ID``, ``th`` xxhash64 of the text."""
    keyed = docs.select(_doc(), F.xxhash64("text").alias("th"), "text")
    sets = materialize(line_sets(keyed, width, min_words), "lines")
    ranks, lines = token_ranks(sets), sets.filter("n > 0")
    same = ["d1", "d2", "n"]
    found = setjoin.candidate_pairs(line_prefixes(keyed.select("doc", "text"), ranks, percent, width, min_words), percent, hot_group, False)
    first = materialize(setjoin.pairs_of(found), "pairs")
    matched = _confirmed(first, keyed, percent, width)
    members = setjoin.members_of(found).withColumn("node", _node("doc", "tail"))
    open_ = materialize(members.join(matched, "node", "left_anti"), "open")
    if not open_.isEmpty():
        wanted = few(open_.select("node").distinct().withColumn("open", F.lit(1).cast("long")))
        marked = members.join(few(open_.select("cell").distinct()), "cell", "left_semi").join(wanted, "node", "left")
        again = marked.select(*setjoin.BASE, F.lit(-1).cast("long").alias("side"), F.coalesce("open", F.lit(0).cast("long")).alias("open"), F.col("node").alias("team"))
        rest = setjoin.pairs_of(setjoin.candidate_pairs(again, percent, hot_group, True))
        rest = materialize(rest.join(first, rest.columns, "left_anti"), "pairs")
        matched = few(matched.union(_confirmed(rest, keyed, percent, width)).distinct())
    release(found)
    classes = lines.groupBy(*same).agg(F.min(F.struct("doc", "tail")).alias("first"))
    status = classes.withColumn("node", _node("first.doc", "first.tail")).join(matched.withColumn("hit", F.lit(True)), "node", "left").select(*same, "first", F.coalesce("hit", F.lit(False)).alias("hit"))
    gone = lines.join(status, same).filter(F.col("hit") | (F.struct("doc", "tail") != F.col("first")))
    return gone.groupBy("doc", "th").agg(F.collect_set(F.shiftright("tail", 32).cast("int")).alias("gone"))


def _doc():
    return F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID)).alias("doc")


@shielded
def dedup_lines(docs: DataFrame, **settings) -> DataFrame:
    """``docs`` with repeated lines cut from ``text``, plus their number as last column; every row and column stays."""
    gone = small(repeated_lines(docs, **settings), "gone")
    joined = docs.join(gone, (_doc() == F.col("doc")) & (F.xxhash64("text") == F.col("th")), "left")
    left = F.filter(F.split("text", "\n", -1), lambda line, i: ~F.array_contains("gone", i))
    cut = F.when(F.col("gone").isNull(), F.col("text")).otherwise(F.array_join(left, "\n"))
    return joined.withColumns({"text": cut, "n_removed": F.coalesce(F.size("gone"), F.lit(0)).cast("long")}).drop("doc", "th", "gone")
