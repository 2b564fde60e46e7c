"""MinHash near-duplicates by tensored banding, every link confirmed on full shingle sets.

Two small collections of minhash groups are computed per document, A (``groups`` groups of ``rows`` values)
and B (as many). Table (i, j) has the key (A_i, B_j), so ``groups``² tables of ``2 rows`` values each come
from ``2 groups rows`` minhashes instead of ``2 groups² rows``. With 18 groups of 3, a pair at Jaccard 0.75
misses all of A, or all of B, with probability (1 - 0.75³)^18 = 5e-5 each.

Documents meet by A_i: one row per document and group carries all of B, and the tables (i, 1..groups) are
formed inside the bucket of A_i, so no row per table is shuffled. Documents with equal shingle sets are
collapsed first into classes, numbered in the order of their smallest doc_id.

A bucket task ties each member of a table bucket to the smallest one, each tie once. Ties of similar sizes are
confirmed on the texts. Where confirmed links leave the documents tied to one hub in different components, the
hub's documents form a cell: those outside its largest component are compared with all others by counting
shared shingles, and only links leave the cell. Cells with much outside the largest component go through an
exact prefix join instead, so a large group that shares much, but not enough, never meets all against all.
Buckets of more than ``hot_bucket`` documents are formed by aggregates that combine on the map side.

Cases: texts that are null or without words have an empty set and no links; documents of fewer than five
words have one shingle, their whole sequence; rows that repeat link with one another; rows of one doc_id with
different texts are documents of their own (a group's id is still a doc_id); rows with a null doc_id take part
in nothing and keep a null component; an empty table gives an empty result; ``keep_one`` returns the columns
it was given, whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seedspread.llm import hashing, setjoin
from seedspread.llm.sizes import few
from seedspread.llm.text import shielded
from seedspread.operators.components import connected_components
from seedspread.runtime import materialize

GROUPS, ROWS = 18, 3
HOT_BUCKET = 20_000
HUB_SLICE = 256
#: Documents and shingles that one side of a comparison inside a cell may hold.
CELL_DOCS, CELL_SHINGLES = 1_500, 1_000_000
#: Rows of one prefix shingle that one task compares.
PREFIX_CELL = 8_192
FITS, CROWDED = 1, 2


def signatures(docs: DataFrame, groups: int = GROUPS, rows: int = ROWS, width: int = 5) -> DataFrame:
    """``(doc_id, th, n_shingles, d1, d2, a, b)``: hash of the text, set size, digest of the full set and both collections."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        splitter = hashing.Splitter()
        factor = (hashing.seeds(2 * groups * rows, 5) >> np.uint64(32)).astype(np.uint32) | np.uint32(1)
        shift = (hashing.seeds(2 * groups * rows, 9) >> np.uint64(20)).astype(np.uint32)
        tags = hashing.seeds(2 * groups, 13)
        for batch in batches:
            ids, th, texts = batch.column(0), batch.column(1), batch.column(2)
            for row, end, data, cuts in hashing.pieces(texts):
                n = end - row
                values, of = hashing.shingles(*splitter.words(data, cuts), n, width)
                one, two = hashing.set_digest(values, of, n)
                size = np.bincount(of, minlength=n)
                full = np.flatnonzero(size)
                starts = np.concatenate([[0], np.cumsum(size[full])[:-1]]) if len(full) else np.empty(0, np.int64)
                keys = np.zeros((n, 2 * groups), np.uint64)
                if len(full):
                    short = (values >> np.uint64(32)).astype(np.uint32)
                    for g in range(2 * groups):
                        mixed = np.full(len(full), tags[g], np.uint64)
                        for k in range(g * rows, (g + 1) * rows):
                            least = np.minimum.reduceat((short ^ shift[k]) * factor[k], starts)
                            mixed = hashing._mix(mixed + least)
                        keys[full, g] = mixed
                lists = lambda m, kind: pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * groups), pa.array(np.ascontiguousarray(m).view(kind).reshape(-1)))
                yield pa.RecordBatch.from_arrays(
                    [ids.slice(row, n), th.slice(row, n), pa.array(size.astype(np.int64)), pa.array(one.view(np.int64)), pa.array(two.view(np.int64)),
                     lists(keys[:, :groups], np.int64), lists((keys[:, groups:] >> np.uint64(32)).astype(np.uint32), np.int32)],
                    names=["doc_id", "th", "n_shingles", "d1", "d2", "a", "b"])

    return _keyed(docs).mapInArrow(run, "doc_id long, th long, n_shingles long, d1 long, d2 long, a array<long>, b array<int>")


def _keyed(docs: DataFrame) -> DataFrame:
    """``(doc_id, th, text)``: a row is known by its id and the hash of its text."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("th"), "text")


def _ties_in_buckets(groups: int, percent: int):
    """Rows sorted by (key, node) → ties (hub, node, flags): each member of a table bucket with its smallest, once per key.

    ``FITS``: the sizes allow a link. ``CROWDED``: some bucket of the tie has three members or more.
    """

    def emit(key, ids, sizes, b):
        run = np.cumsum(np.concatenate([[0], (key[1:] != key[:-1]).astype(np.int64)]))
        keep = np.bincount(run)[run] > 1
        run, ids, sizes, b = run[keep], ids[keep], sizes[keep], b[keep]
        if len(ids) == 0:
            return None
        lo, hi, flag = [], [], []
        for j in range(groups):
            code = (run.astype(np.uint64) << np.uint64(32)) | b[:, j].view(np.uint32).astype(np.uint64)
            order = np.argsort(code, kind="stable")
            code, who, size = code[order], ids[order], sizes[order]
            at = np.flatnonzero(np.concatenate([[True], code[1:] != code[:-1]]))
            count = np.diff(np.append(at, len(code)))
            first, hub_size = np.repeat(who[at], count), np.repeat(size[at], count)
            fits = 100 * np.minimum(size, hub_size) >= percent * np.maximum(size, hub_size)
            crowded = np.repeat(count > 2, count)
            tied = (first < who) & (fits | crowded)
            lo.append(first[tied])
            hi.append(who[tied])
            flag.append((fits * FITS + crowded * CROWDED)[tied])
        lo, hi, flag = np.concatenate(lo), np.concatenate(hi), np.concatenate(flag)
        order = np.lexsort((hi, lo))
        lo, hi, flag = lo[order], hi[order], flag[order]
        if len(lo) == 0:
            return None
        at = np.flatnonzero(np.concatenate([[True], (lo[1:] != lo[:-1]) | (hi[1:] != hi[:-1])]))
        flag = np.bitwise_or.reduceat(flag, at).astype(np.int32)
        return pa.RecordBatch.from_arrays([pa.array(lo[at]), pa.array(hi[at]), pa.array(flag)], names=["a", "b", "flags"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None
        for batch in batches:
            if batch.num_rows == 0:
                continue
            cols = [batch.column(k).to_numpy(zero_copy_only=False) for k in range(3)]
            lists = batch.column(3)
            cols.append(lists.flatten().to_numpy(zero_copy_only=False).reshape(-1, groups))
            if held is not None:
                cols = [np.concatenate([h, c]) for h, c in zip(held, cols, strict=True)]
            cut = int(np.searchsorted(cols[0], cols[0][-1], side="left"))
            if cut and (out := emit(*[c[:cut] for c in cols])) is not None:
                yield out
            held = [c[cut:] for c in cols]
        if held is not None and (out := emit(*held)) is not None:
            yield out

    return run


def bucket_ties(reps: DataFrame, groups: int, hot_bucket: int, percent: int) -> DataFrame:
    """``(a, b, flags)``: ties of the members of all table buckets with the smallest member, each tie once."""
    rows = reps.select(F.explode("a").alias("key"), "node", F.col("n_shingles").alias("n"), "b")
    hot = materialize(rows.groupBy("key").count().filter(F.col("count") > hot_bucket).select("key"), "hot")
    crowded = not hot.isEmpty()
    calm = rows.join(few(hot), "key", "left_anti") if crowded else rows
    dealt = calm.repartition("key").sortWithinPartitions("key", "node").select("key", "node", "n", "b")
    found = dealt.mapInArrow(_ties_in_buckets(groups, percent), "a long, b long, flags int")
    if crowded:
        tables = rows.join(few(hot), "key").select("node", "n", "key", F.posexplode("b").alias("j", "v")).select(F.xxhash64("key", "j", "v").alias("bucket"), "node", "n")
        heads = tables.groupBy("bucket").agg(F.min(F.struct("node", "n")).alias("hub"), F.count("*").alias("c")).filter("c > 1")
        inside = tables.join(heads, "bucket").filter("node > hub.node")
        fits = 100 * F.least("n", "hub.n") >= percent * F.greatest("n", "hub.n")
        flags = F.when(fits, FITS).otherwise(0) + F.when(F.col("c") > 2, CROWDED).otherwise(0)
        found = found.union(inside.select(F.col("hub.node").alias("a"), F.col("node").alias("b"), flags.cast("int").alias("flags")).filter("flags > 0"))
    return materialize(found.groupBy("a", "b").agg(F.bit_or("flags").alias("flags")), "ties")


def _verify(percent: int, width: int):
    """Rows sorted by (hub, slice, role): texts of a hub's pairs against the hub's own → confirmed (a, b)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        splitter = hashing.Splitter()
        hub, hub_set = None, None
        for batch in batches:
            a, role, ids = (batch.column(k).to_numpy(zero_copy_only=False) for k in range(3))
            lo, hi = [], []
            for row, end, data, cuts in hashing.pieces(batch.column(3)):
                values, of = hashing.shingles(*splitter.words(data, cuts), end - row, width)
                at = np.searchsorted(of, np.arange(end - row + 1))
                for k in range(end - row):
                    own = values[at[k] : at[k + 1]]
                    if role[row + k] == 0:
                        hub, hub_set = a[row + k], own
                    elif hub == a[row + k]:
                        place = np.searchsorted(hub_set, own)
                        place[place == len(hub_set)] = 0
                        both = int((hub_set[place] == own).sum()) if len(hub_set) else 0
                        if both and 100 * both >= percent * (len(own) + len(hub_set) - both):
                            lo.append(hub)
                            hi.append(ids[row + k])
            yield pa.RecordBatch.from_arrays([pa.array(np.array(lo, np.int64)), pa.array(np.array(hi, np.int64))], names=["a", "b"])

    return run


def confirm(pairs: DataFrame, texts: DataFrame, percent: int = 75, width: int = 5) -> DataFrame:
    """The pairs ``(a, b)`` whose full shingle sets meet the similarity; ``texts(node, text)``; a repeated row of it changes nothing.

    A hub's text travels once per slice of ``HUB_SLICE`` of its pairs, so one with many pairs is shared out.
    """
    fan = few(pairs.groupBy("a").agg(F.ceil(F.count("*") / HUB_SLICE).cast("int").alias("slices")).filter("slices > 1"))
    dealt = pairs.join(fan, "a", "left").withColumn("slices", F.coalesce("slices", F.lit(1)))
    side = dealt.select("a", F.pmod(F.xxhash64("b"), F.col("slices")).cast("int").alias("slice"), F.lit(1).alias("role"), F.col("b").alias("id"))
    hubs = side.groupBy("a", "slice").agg(F.lit(0).alias("role")).select("a", "slice", "role", F.col("a").alias("id"))
    need = side.union(hubs)
    texts = few(need).join(texts.withColumnRenamed("node", "id"), "id")
    dealt = texts.repartition("a", "slice").sortWithinPartitions("a", "slice", "role").select("a", "role", "id", "text")
    return dealt.mapInArrow(_verify(percent, width), "a long, b long").distinct()


def _links_in_cells(percent: int, width: int):
    """Rows ``(cell, node, team, main, text)`` sorted by cell → confirmed links across teams, one per pair of teams and cell.

    Shared shingles are counted through inverted lists, so no candidate pair is formed. Members of the cell's
    main team are only looked up, never looked from.
    """

    def solve(ids, team, main, sets):
        sizes = np.array([len(x) for x in sets])
        codes = np.concatenate(sets)
        owner = np.repeat(np.arange(len(ids)), sizes)
        order = np.argsort(codes, kind="stable")
        who = owner[order]
        new = np.concatenate([[True], codes[order][1:] != codes[order][:-1]])
        token = np.empty(len(codes), np.int64)
        token[order] = np.cumsum(new) - 1
        first = np.append(np.flatnonzero(new), len(codes))
        at = np.concatenate([[0], np.cumsum(sizes)])
        found = {}
        for x in np.flatnonzero(team != main):
            t = token[at[x] : at[x + 1]]
            lo, n = first[t], first[t + 1] - first[t]
            spots = np.repeat(lo - np.concatenate([[0], np.cumsum(n)[:-1]]), n) + np.arange(n.sum())
            both = np.bincount(who[spots], minlength=len(ids))
            good = (100 * both >= percent * (sizes[x] + sizes - both)) & (team != team[x])
            for y in np.flatnonzero(good):
                found.setdefault((min(team[x], team[y]), max(team[x], team[y])), (min(ids[x], ids[y]), max(ids[x], ids[y])))
        return list(found.values())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        splitter, held, cell = hashing.Splitter(), [], None

        def close():
            links = solve(*(np.array([h[k] for h in held]) for k in range(3)), [h[3] for h in held]) if len(held) > 1 else []
            return pa.RecordBatch.from_arrays([pa.array(np.array([x[k] for x in links], np.int64)) for k in (0, 1)], names=["a", "b"])

        for batch in batches:
            key, ids, team, main = (batch.column(k).to_numpy(zero_copy_only=False) for k in range(4))
            for row, end, data, cuts in hashing.pieces(batch.column(4)):
                values, of = hashing.shingles(*splitter.words(data, cuts), end - row, width)
                at = np.searchsorted(of, np.arange(end - row + 1))
                for k in range(end - row):
                    if cell is not None and key[row + k] != cell:
                        yield close()
                        held = []
                    cell = key[row + k]
                    held.append((ids[row + k], team[row + k], main[row + k], values[at[k] : at[k + 1]]))
        yield close()

    return run


def _document_prefixes(ranks: np.ndarray, percent: int, width: int):
    """Rows ``(node, text)`` → prefix rows of an exact set-similarity join."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        splitter = hashing.Splitter()
        for batch in batches:
            for row, end, data, cuts in hashing.pieces(batch.column(1)):
                values, of = hashing.shingles(*splitter.words(data, cuts), end - row, width)
                size, tokens = hashing.prefixes(values, of, end - row, ranks, percent)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(row, end - row), pa.array(size.astype(np.int64)), tokens], names=["node", "n", "prefix"])

    return run


def _token_counts(width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        splitter = hashing.Splitter()
        yield hashing.count_groups(
            hashing.shingles(*splitter.words(data, cuts), end - row, width)[0] for batch in batches for row, end, data, cuts in hashing.pieces(batch.column(1)))

    return run


def _by_prefixes(members: DataFrame, texts: DataFrame, percent: int, width: int) -> DataFrame:
    """Confirmed links across teams of ``members(node, team)`` by an exact prefix join, rarest shingles first.

    Each document's first candidate per shingle is confirmed first; teams that this joins need no other link.
    """
    teams = materialize(members.distinct(), "teams")
    held = materialize(texts.join(few(teams.select("node").distinct()), "node", "left_semi").select("node", "text"), "crowd")
    ranks = setjoin.ranks_of(held.mapInArrow(_token_counts(width), "group int, n long"))
    wide = held.mapInArrow(_document_prefixes(ranks, percent, width), "node long, n long, prefix array<long>").select("node", "n", F.posexplode("prefix").alias("pos", "cell"))
    rows = wide.select("cell", F.col("node").alias("doc"), F.lit(0).cast("long").alias("tail"), setjoin.place(F.col("n"), F.col("pos")).alias("place"), F.lit(-1).cast("long").alias("side"), F.lit(1).cast("long").alias("open"))
    rows = materialize(rows, "prefixes")
    links, asked = None, None
    for every in (False, True):
        dealt = rows.join(teams.withColumnRenamed("node", "doc"), "doc")
        pairs = setjoin.pairs_of(setjoin.candidate_pairs(dealt, percent, PREFIX_CELL, every)).select(F.col("a_doc").alias("a"), F.col("b_doc").alias("b"))
        pairs = materialize(pairs if asked is None else pairs.join(asked, ["a", "b"], "left_anti"), "pairs")
        found = materialize(confirm(pairs, held, percent, width), "links")
        links, asked = found if links is None else links.union(found), pairs
        ends = found.join(teams.withColumnRenamed("node", "a").withColumnRenamed("team", "x"), "a").join(teams.withColumnRenamed("node", "b").withColumnRenamed("team", "y"), "b")
        joined = connected_components(ends.select(F.col("x").alias("a"), F.col("y").alias("b"))).select(F.col("v").alias("team"), "component")
        teams = materialize(teams.join(joined, "team", "left").select("node", F.coalesce("component", "team").alias("team")), "teams")
    return links


def across_components(ties: DataFrame, comps: DataFrame, sizes: DataFrame, texts: DataFrame, percent: int, width: int, cell_docs: int = CELL_DOCS) -> DataFrame:
    """Confirmed links (a, b) between different components among documents tied to one hub.

    ``ties(a, b)`` of crowded buckets; ``comps(node, component)``, a node without a row is its own; ``sizes(node,
    n_shingles)``. Every candidate pair of a crowded bucket is tied to the same hub, so hubs whose documents are
    all in one component need nothing more, and any other pair meets in the hub's cell.
    """
    named = ties.join(comps.withColumnRenamed("node", "b"), "b", "left").select("a", F.col("b").alias("node"), F.coalesce("component", "b").alias("team"))
    hubs = ties.select("a").distinct().join(comps.withColumnRenamed("node", "a"), "a", "left").select("a", F.col("a").alias("node"), F.coalesce("component", "a").alias("team"))
    everyone = named.union(hubs)
    open_ = few(everyone.groupBy("a").agg(F.min("team").alias("lo"), F.max("team").alias("hi")).filter("lo <> hi").select("a"))
    members = materialize(everyone.join(open_, "a", "left_semi").join(few(sizes.join(few(everyone.select("node").distinct()), "node", "left_semi"), 200_000), "node"), "open")
    teams = members.groupBy("a", "team").agg(F.count("*").alias("docs"), F.sum("n_shingles").alias("load"))
    weight = F.greatest(F.col("docs") / cell_docs, F.col("load") / CELL_SHINGLES)
    cells = teams.groupBy("a").agg(F.max(F.struct(weight.alias("w"), F.col("team"))).alias("top"), F.sum(weight).alias("all"))
    cells = few(cells.select("a", F.col("top.team").alias("main"), F.ceil("top.w").cast("int").alias("chunks"), (F.col("all") - F.col("top.w") > 1).alias("crowd")))
    placed = members.join(cells, "a")
    calm = placed.filter("not crowd")
    own = F.pmod(F.xxhash64("node"), F.col("chunks")).cast("int")
    chunk = F.explode(F.when(F.col("team") == F.col("main"), F.array(own)).otherwise(F.sequence(F.lit(0), F.col("chunks") - 1)))
    rows = calm.withColumn("chunk", chunk).select(F.xxhash64("a", "chunk").alias("cell"), "node", "team", "main")
    held = rows.join(texts, "node").select("cell", "node", "team", "main", "text")
    links = held.repartition("cell").sortWithinPartitions("cell").mapInArrow(_links_in_cells(percent, width), "a long, b long")
    crowd = placed.filter("crowd").select("node", "team")
    if not crowd.isEmpty():
        links = links.union(_by_prefixes(crowd, texts, percent, width))
    return links.distinct()


def decided(docs: DataFrame, percent: int = 75, width: int = 5, groups: int = GROUPS, rows: int = ROWS, hot_bucket: int = HOT_BUCKET, cell_docs: int = CELL_DOCS) -> DataFrame:
    """``docs(doc_id, text)`` → ``(doc_id, th, n_shingles, component_id, kept)``, one row per row of ``docs``."""
    docs = docs.select("doc_id", "text")
    sigs = materialize(signatures(docs, groups, rows, width), "signatures")
    usable = sigs.filter("doc_id is not null and n_shingles > 0")
    same = ["d1", "d2", "n_shingles"]
    grouped = usable.groupBy(*same).agg(F.min(F.struct("doc_id", "th")).alias("first"))
    ordered = grouped.repartitionByRange("first", "d1", "d2").sortWithinPartitions("first", "d1", "d2")
    classes = materialize(ordered.select(*same, F.col("first.doc_id").alias("doc_id"), F.col("first.th").alias("th"), F.monotonically_increasing_id().alias("node")), "classes")
    reps = usable.join(classes, [*same, "doc_id", "th"]).select("node", "n_shingles", "a", "b")
    ties = bucket_ties(reps, groups, hot_bucket, percent)
    met = ties.select(F.col("a").alias("node")).union(ties.select(F.col("b").alias("node"))).distinct()
    wanted = few(classes.join(met, "node", "left_semi").select("node", "doc_id", "th"))
    texts = materialize(_keyed(docs).join(wanted, ["doc_id", "th"]).select("node", "text").dropDuplicates(["node"]), "texts")
    links = materialize(confirm(ties.filter(F.col("flags").bitwiseAND(FITS) > 0).select("a", "b"), texts, percent, width), "links")
    comps = materialize(connected_components(links).withColumnRenamed("v", "node"), "components")
    crowded = ties.filter(F.col("flags").bitwiseAND(CROWDED) > 0).select("a", "b")
    more = materialize(across_components(crowded, comps, classes.select("node", "n_shingles"), texts, percent, width, cell_docs), "links")
    if not more.isEmpty():
        comps = materialize(connected_components(links.union(more)).withColumnRenamed("v", "node"), "components")
    heads = classes.select(F.col("node").alias("component"), F.col("doc_id").alias("found"))
    named = classes.join(comps.join(heads, "component").select("node", "found"), "node", "left").select(*same, F.coalesce("found", "doc_id").alias("found"))
    component = F.when(F.col("n_shingles") > 0, F.when(F.col("doc_id").isNotNull(), F.col("found"))).otherwise(F.col("doc_id"))
    out = sigs.join(named, same, "left").select("doc_id", "th", "n_shingles", component.alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def near_duplicates(docs: DataFrame, **settings) -> DataFrame:
    """``docs(doc_id, text)`` → ``(doc_id, n_shingles, component_id, kept)``, one row per row of ``docs``."""
    return decided(docs, **settings).drop("th")


@shielded
def keep_one(docs: DataFrame, **settings) -> DataFrame:
    """``docs`` with the document of the smallest doc_id of each group of near duplicates; all columns as they were."""
    gone = few(decided(docs, **settings).filter("not kept").select(F.col("doc_id").alias("gone_id"), "th").distinct())
    return docs.join(gone, (F.col("doc_id").cast("long") == F.col("gone_id")) & (F.xxhash64("text") == F.col("th")), "left_anti")
