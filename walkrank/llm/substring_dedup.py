"""Exact dedup of repeated byte strings by blockwise suffix sorting with a difference cover.

A byte goes if a string of `length` (100) bytes that covers it also starts earlier: in an earlier document, or before
in the same one. Strings that start at a place are called windows here; they are judged on the input.

1. Every window has an anchor: of the strings of ANCHOR bytes in it the one of least hash, the first of equals. Equal
   windows have equal anchors at equal places, so windows of an anchor that occurs once are unique. Anchors are counted
   over all documents, which also counts the hot ones before anything is joined.
2. An occurrence of a repeated anchor has a context: the bytes of all windows that it is the anchor of. Of equal contexts
   (equal in anchor and in a 64-bit digest) the first stands for all; all windows of the others repeat its. No bytes are
   moved for this.
3. Different contexts of an anchor may share some windows. The contexts that stand for others go to blocks by anchor. In
   a block the windows are suffixes of a text of contexts and come in the order of their bytes: one bucket of suffixes at
   a time, cut by their first words and where a word is too frequent by the words behind it. Ties of HEAD bytes are
   resolved by a difference cover: its places in the text are ranked once by RANKED bytes, and for any two suffixes there
   is one way from both to places of the cover, whose ranks and the last bytes decide. So a bucket needs memory for
   BUCKET suffixes, whatever the block has. Equal neighbours in this order form groups, of which the first stays.
4. The windows of an anchor with more than HOT such contexts would not fit a block. They are sorted out by their whole
   bytes by Spark, which spills: the first of each is a grouped minimum.

Documents get the marked windows back and drop the bytes that they cover.

A null text is empty; a text of less than `length` bytes loses nothing. Very long texts are taken in overlapping parts.
A row is known by its doc_id and its text: rows that repeat both are one document and lose the same bytes; rows of one
doc_id and different texts are documents in the order of a hash of their texts. A null doc_id comes before all others.
Other columns are left out; an empty table gives an empty table.
"""

from __future__ import annotations

import hashlib
import math
from functools import cmp_to_key

import numpy as np
import pyarrow as pa
from numpy.lib.stride_tricks import as_strided
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

LENGTH, ANCHOR = 100, 24
#: Bytes of texts that are handled at once, and windows in a part of a longer text.
PART = 1 << 20
#: Contexts of a block, contexts of one anchor from which its windows are sorted by Spark, suffixes sorted at once.
BLOCK_CONTEXTS, HOT, BUCKET = 20_000, 20_000, 1 << 17
#: The period of a difference cover and its places: each difference of two remainders occurs among them.
PERIOD, COVER = 31, (1, 5, 11, 24, 25, 27)
#: Bytes compared before the cover is asked, and those that its places are ranked by. Ways to the cover take NEAREST bytes or more.
HEAD, RANKED, NEAREST = 40, 64, 4
#: A place in a text, how many places before it the first window starts, and how many the last, in one number.
SHIFT = 7
NO_ID = -(1 << 63)
#: What documents are known and ordered by.
KEY = ("doc_id", "tie")


def checked(length: int) -> int:
    """The head, the rank and the last words of a window overlap, and its anchor's way fits SHIFT bits."""
    if not NEAREST + PERIOD - 1 + RANKED <= length < ANCHOR + (1 << SHIFT):
        raise ValueError(f"strings of {length} bytes: {NEAREST + PERIOD - 1 + RANKED} to {ANCHOR + (1 << SHIFT) - 1} are possible")
    return length


def words8(text: np.ndarray) -> np.ndarray:
    """The 8 bytes at each place as a number in their order."""
    return as_strided(text, (len(text) - 7, 8), (1, 1)).copy().view(">u8").ravel().astype(np.uint64)


def anchors(text: np.ndarray, ends: np.ndarray, length: int = LENGTH) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of each anchor its place, hash, and the first and last place where a window of it starts.

    text: bytes of texts one after another; ends: where each ends. Windows don't cross these."""
    none = np.zeros(0, np.int64)
    n = len(text) - length + 1
    if n < 1:
        return none, none.view(np.uint64), none, none
    word = as_strided(text, (len(text) - 7, 8), (1, 1)).copy().view("<u8").ravel()
    m = len(text) - ANCHOR + 1
    h = word[:m] * np.uint64(0x9E3779B97F4A7C15)
    h ^= h >> np.uint64(29)
    h += word[8 : m + 8]
    h *= np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(32)
    h += word[16 : m + 16]
    h *= np.uint64(0x94D049BB133111EB)
    h ^= h >> np.uint64(31)
    # least hash, then first place, over the anchors of each window
    low = np.uint64((1 << 24) - 1)
    key = (h & ~low) | np.arange(m, dtype=np.uint64)
    span, width = length - ANCHOR + 1, 1
    best = key
    while 2 * width <= span:
        best = np.minimum(best[:-width], best[width:])
        width *= 2
    best = np.minimum(best[:n], best[span - width : span - width + n])
    at = (best & low).astype(np.int64)
    whole = np.ones(n, bool)
    for end in ends[:-1].tolist():
        whole[max(0, end - length + 1) : end] = False
    new = np.empty(n, bool)
    new[0] = True
    new[1:] = (at[1:] != at[:-1]) | (whole[1:] != whole[:-1])
    first = np.flatnonzero(new)
    last = np.append(first[1:], n) - 1
    first, last = first[whole[first]], last[whole[first]]
    return at[first], h[at[first]], first, last


def parts(texts: list[str], length: int = LENGTH):
    """Bytes handled at once: numbers of texts, where each text or part of one starts in them, places in the text, the bytes, ends."""
    held, size = [], 0

    def pack():
        data = b"".join(x for _, _, x in held)
        sizes = np.array([len(x) for _, _, x in held])
        ends = np.cumsum(sizes)
        return np.array([k for k, _, _ in held], np.int64), ends - sizes, np.array([o for _, o, _ in held], np.int64), data, ends

    for key, text in enumerate(texts):
        raw = text.encode()
        for at in range(0, max(len(raw) - length + 1, 0), PART):
            piece = raw[at : at + PART + length - 1]
            held.append((key, at, piece))
            size += len(piece)
            if size >= PART:
                yield pack()
                held, size = [], 0
    if held:
        yield pack()


def found_anchors(docs: DataFrame, contexts: bool, length: int) -> DataFrame:
    """All occurrences of anchors; with contexts also the document, place and the context's digest. docs: doc_id, tie, text."""
    kind, schema = common.arrow_schema("anchor long, context long, doc_id long, tie long, at long" if contexts else "anchor long")

    def run(batches):
        from xxhash import xxh3_64_intdigest

        for batch in batches:
            for low in range(0, batch.num_rows, 256):
                part = batch.slice(low, 256)
                keys = [part.column(k).to_numpy(zero_copy_only=False) for k in (0, 1)]
                for rows, starts, offsets, data, ends in parts(part.column(2).to_pylist(), length):
                    at, h, first, last = anchors(np.frombuffer(data, np.uint8), ends, length)
                    columns = [pa.array(h.view(np.int64))]
                    if contexts:
                        before, behind = at - first, at - last
                        seed = (before << SHIFT | behind).tolist()
                        view = memoryview(data)
                        digest = np.array([xxh3_64_intdigest(view[a : b + length], s) for a, b, s in zip(first.tolist(), last.tolist(), seed, strict=True)], np.uint64)
                        text = np.searchsorted(ends, at, "right")
                        place = at - starts[text] + offsets[text]
                        columns += [pa.array(digest.view(np.int64)), *(pa.array(k[rows[text]]) for k in keys), pa.array(place << 2 * SHIFT | before << SHIFT | behind)]
                    yield pa.RecordBatch.from_arrays(columns, schema=schema)

    return docs.mapInArrow(run, kind)


def windows_of(at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First and last start of the windows of an occurrence."""
    place, mask = at >> 2 * SHIFT, (1 << SHIFT) - 1
    return place - (at >> SHIFT & mask), place - (at & mask)


# a block of contexts


#: for two remainders the way, of NEAREST or more, that leads from both to places of the cover; from one alone to the next place
def _ways() -> np.ndarray:
    cover = {c % PERIOD for c in COVER}
    return np.array([[next(d for d in range(NEAREST, NEAREST + PERIOD) if (a + d) % PERIOD in cover and (b + d) % PERIOD in cover) for b in range(PERIOD)] for a in range(PERIOD)])


WAYS = _ways()


class Block:
    """The text of a block's contexts, its windows, and ranks of the cover's places."""

    def __init__(self, contexts: list[bytes], before: np.ndarray, length: int = LENGTH):
        sizes = np.array([len(x) for x in contexts])
        # each context starts where its anchor's place has the remainder 0, so windows that may be equal have equal remainders
        room = -(-(sizes + 2 * PERIOD) // PERIOD) * PERIOD
        lead = (-before) % PERIOD
        begin = np.cumsum(room) - room + lead
        self.text = np.zeros(int(room.sum()) + length + RANKED, np.uint8)
        inside = np.arange(int(sizes.sum())) - np.repeat(np.cumsum(sizes) - sizes, sizes)
        self.text[np.repeat(begin, sizes) + inside] = np.frombuffer(b"".join(contexts), np.uint8)
        n = sizes - length + 1
        self.owner = np.repeat(np.arange(len(contexts)), n)
        self.offset = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
        self.start = begin[self.owner] + self.offset
        self.word = words8(self.text)
        self.length = length
        # places of the cover that a window may be led to, in order of their bytes; the last place has all of them before the end
        cover = np.zeros(PERIOD, bool)
        cover[list(COVER)] = True
        reached = np.zeros(len(self.text) + 1, np.int64)
        np.add.at(reached, begin + NEAREST, 1)
        np.add.at(reached, begin + n + NEAREST + PERIOD - 1, -1)
        places = np.flatnonzero(np.cumsum(reached)[: len(self.text) - RANKED] > 0)
        places = places[cover[places % PERIOD]]
        keys = [self.word[places + k] for k in range(0, RANKED, 8)]
        order = np.lexsort(keys[::-1])
        same = np.ones(len(places), bool)
        for k in keys:
            same[1:] &= k[order][1:] == k[order][:-1]
        same[:1] = False
        self.rank, self.ranks = np.zeros(len(self.text), np.int64), len(places)
        self.rank[places[order]] = np.cumsum(~same)

    def buckets(self):
        """The suffixes bucket by bucket, in order: arrays of windows, and which are equal to the one before."""
        for windows in self.cut(np.arange(len(self.start)), 0):
            yield self.sorted(windows)

    def cut(self, windows: np.ndarray, depth: int):
        """Ranges of the suffixes of BUCKET at most, by their word at a depth; a word with more is cut by the next one."""
        if len(windows) <= BUCKET or 8 * depth == HEAD:
            yield windows
            return
        head = self.word[self.start[windows] + 8 * depth]
        order = np.argsort(head, kind="stable")
        ordered, at = head[order], 0
        while at < len(order):
            end = min(at + BUCKET, len(order))
            if end < len(order):
                cut = int(np.searchsorted(ordered, ordered[end], "left"))
                end = cut if cut > at else int(np.searchsorted(ordered, ordered[end], "right"))
            if end - at > BUCKET:
                yield from self.cut(windows[order[at:end]], depth + 1)
            else:
                yield windows[order[at:end]]
            at = end

    def sorted(self, windows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        start = self.start[windows]
        remainder = start % PERIOD
        head = [self.word[start + k] for k in range(0, HEAD, 8)]
        tail = [self.word[start + self.length - k] for k in (32, 24, 16, 8)]
        # one number has the remainder and the rank
        keys = [*head, remainder * (self.ranks + 1) + self.rank[start + WAYS[remainder, remainder]], *tail]
        order = np.lexsort(keys[::-1])
        same, tied = np.ones((2, len(order)), bool)
        for i, k in enumerate(keys):
            equal = k[order][1:] == k[order][:-1]
            same[1:] &= equal
            if i < len(head):
                tied[1:] &= equal
        same[:1] = tied[:1] = False
        return self.merged(windows, order, same, tied, start, remainder, tail)

    def merged(self, windows, order, same, tied, start, remainder, tail) -> tuple[np.ndarray, np.ndarray]:
        """Suffixes tied in the head come by remainder; those of several remainders are merged, by the way of each two."""
        group = np.cumsum(~tied)
        mixed = np.zeros(int(group[-1]) + 1 if len(group) else 1, bool)
        differ = tied[1:] & (remainder[order][1:] != remainder[order][:-1])
        mixed[group[1:][differ]] = True
        if not mixed.any():
            return windows[order], same
        ways, rank, places_of, remainders = WAYS.tolist(), *(memoryview(np.ascontiguousarray(x)) for x in (self.rank, start, remainder))
        tails = [memoryview(np.ascontiguousarray(t)) for t in tail]

        def compare(i: int, j: int) -> int:
            way = ways[remainders[i]][remainders[j]]
            x, y = rank[places_of[i] + way], rank[places_of[j] + way]
            if x == y:
                x, y = [t[i] for t in tails], [t[j] for t in tails]
            return (x > y) - (x < y)

        order, same = order.copy(), same.copy()
        at = np.flatnonzero(mixed[group])
        for places in np.split(at, np.flatnonzero(np.diff(group[at])) + 1):
            low, high = int(places[0]), int(places[-1]) + 1
            # of equal suffixes the first takes the others along
            firsts = np.flatnonzero(~same[low:high]) + low
            ends = np.append(firsts[1:], high)
            runs = sorted(range(len(firsts)), key=cmp_to_key(lambda a, b: compare(order[firsts[a]], order[firsts[b]])))
            moved = [order[firsts[k] : ends[k]] for k in runs]
            marks = [same[firsts[k] : ends[k]].copy() for k in runs]
            for k, (a, b) in enumerate(zip(runs[:-1], runs[1:], strict=True), 1):
                marks[k][0] = compare(order[firsts[a]], order[firsts[b]]) == 0
            marks[0][0] = False
            order[low:high], same[low:high] = np.concatenate(moved), np.concatenate(marks)
        return windows[order], same


def repeats(contexts: list[bytes], before: np.ndarray, docs: list[np.ndarray], places: np.ndarray, length: int = LENGTH) -> np.ndarray:
    """For each window of the contexts, in their order, whether an equal one comes earlier by document (its keys) and place."""
    block = Block(contexts, before, length)
    gone = np.zeros(len(block.start), bool)
    for windows, same in block.buckets():
        group = np.cumsum(~same)
        owner = block.owner[windows]
        keys = [*(k[owner] for k in docs), places[owner] + block.offset[windows]]
        order = np.lexsort([*keys[::-1], group])
        # a window at the first one's own place is the same occurrence
        first = np.flatnonzero(np.concatenate([[True], group[order][1:] != group[order][:-1]]))
        head = np.repeat(first, np.diff(np.append(first, len(order))))
        gone[windows[order]] = np.logical_or.reduce([k[order] != k[order][head] for k in keys])
    return gone


def marks(docs: DataFrame, length: int, block_contexts: int, hot: int) -> DataFrame:
    """docs: doc_id, tie, text. Of each document with repeated windows `whole`: the occurrences of anchors all of whose
    windows repeat unless they are in `own`: those that stand for others, with the windows that repeat."""
    # as a table, so that the join sees two plain exchanges and large partitions of it can be split
    repeated = common.written(found_anchors(docs, False, length).groupBy("anchor").count().where("count > 1").select("anchor"), "substring-repeated")
    held = common.written(found_anchors(docs, True, length).join(repeated.hint("shuffle_hash"), "anchor"), "substring-anchors")
    first = held.groupBy("anchor", "context").agg(F.min(F.struct(*KEY, "at")).alias("first"))
    first = common.written(first.select("anchor", "context", "first.doc_id", "first.tie", "first.at"), "substring-first")
    sizes = common.written(first.groupBy("anchor").agg(F.count("*").alias("n")).where("n > 1"), "substring-sizes")
    several = first.join(sizes, "anchor").select("anchor", *KEY, "at", "n")
    asked = several.groupBy(*KEY).agg(F.collect_list(F.struct("anchor", "at", "n")).alias("asked"))
    kind, schema = common.arrow_schema("anchor long, doc_id long, tie long, at long, n long, bytes binary")

    def cut(batches):
        for batch in batches:
            for low in range(0, batch.num_rows, 256):
                part = batch.slice(low, 256)
                rows = []
                for key, tie, text, wanted in zip(*(c.to_pylist() for c in part.columns), strict=True):
                    raw = text.encode()
                    begin, end = windows_of(np.array([x["at"] for x in wanted], np.int64))
                    rows += [(x["anchor"], key, tie, x["at"], x["n"], raw[a : b + length]) for x, a, b in zip(wanted, begin.tolist(), end.tolist(), strict=True)]
                for at in range(0, len(rows), 50_000):
                    yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows[at : at + 50_000], strict=True), schema, strict=True)], schema=schema)

    bytes_of = docs.join(asked.hint("shuffle_hash"), list(KEY)).select(*KEY, "text", "asked").mapInArrow(cut, kind)
    bytes_of = common.written(bytes_of, "substring-contexts")
    n = bytes_of.where(F.col("n") <= hot).count()
    blocks = max(1, math.ceil(n / block_contexts))
    out_kind, out_schema = common.arrow_schema("doc_id long, tie long, at long, windows array<int>")

    def one_block(table: pa.Table) -> pa.Table:
        keys, at = [table.column(k).to_numpy() for k in KEY], table.column("at").to_numpy()
        contexts = table.column("bytes").to_pylist()
        begin, _ = windows_of(at)
        before = (at >> 2 * SHIFT) - begin
        gone = repeats(contexts, before, keys, begin, length)
        sizes = np.array([len(x) - length + 1 for x in contexts])
        starts = np.repeat(begin, sizes) + np.arange(int(sizes.sum())) - np.repeat(np.cumsum(sizes) - sizes, sizes)
        ends = np.cumsum(np.add.reduceat(gone, np.cumsum(sizes) - sizes, dtype=np.int64))
        lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], ends]).astype(np.int32)), pa.array((starts - np.repeat(begin, sizes))[gone].astype(np.int32)))
        return pa.table([*(pa.array(k) for k in keys), pa.array(at), lists], schema=out_schema)

    sorted_ = bytes_of.where(F.col("n") <= hot).groupBy(F.pmod(F.xxhash64("anchor"), F.lit(blocks)).alias("block")).applyInArrow(one_block, out_kind)

    # windows of hot anchors, each on its own
    single_kind, single_schema = common.arrow_schema("window binary, doc_id long, tie long, at long, offset int")

    def singles(batches):
        for batch in batches:
            for low in range(0, batch.num_rows, 500):
                part, rows = batch.slice(low, 500), []
                for key, tie, at, raw in zip(*(part.column(k).to_pylist() for k in range(4)), strict=True):
                    rows += [(raw[k : k + length], key, tie, at, k) for k in range(len(raw) - length + 1)]
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), single_schema, strict=True)], schema=single_schema)

    single = bytes_of.where(F.col("n") > hot).select(*KEY, "at", "bytes").mapInArrow(singles, single_kind)
    single = single.withColumn("start", F.shiftright("at", 2 * SHIFT) - F.shiftright("at", SHIFT).bitwiseAND(F.lit((1 << SHIFT) - 1)) + F.col("offset"))
    single = common.written(single, "substring-singles")
    place = F.struct(*KEY, "start")
    firsts = single.groupBy("window").agg(F.min(place).alias("first"), F.count("*").alias("n")).where("n > 1")
    later = single.join(firsts, "window").where(place != F.col("first"))
    hot_ones = later.groupBy(*KEY, "at").agg(F.collect_set("offset").alias("windows"))

    stand_ins = first.select(*KEY, "at", F.array().cast("array<int>").alias("windows")).unionByName(sorted_).unionByName(hot_ones)
    own = F.when(F.col("windows").isNotNull(), F.struct("at", "windows"))
    everything = held.select(*KEY, "at", F.lit(None).cast("array<int>").alias("windows")).unionByName(stand_ins)
    return everything.groupBy(*KEY).agg(F.collect_list(F.when(F.col("windows").isNull(), F.col("at"))).alias("whole"), F.collect_list(own).alias("own"))


FIELDS = {"n_bytes": "long", "n_removed": "long", "n_spans": "long", "spans": "array<struct<start:long,end:long>>", "kept": "binary", "kept_sha256": "string"}


def keyed(docs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """doc_id (NO_ID for null), tie and text of each row, and of each document. Where doc_ids are null or repeated the tie
    tells texts apart."""
    rows = docs.select("doc_id", common.text_of().alias("text"))
    unclear = rows.groupBy("doc_id").agg(F.count("*").alias("n")).where("n > 1 or doc_id is null")
    if unclear.isEmpty():
        rows = rows.select("doc_id", F.lit(0).cast("long").alias("tie"), "text")
        return rows, rows
    spread = F.shiftrightunsigned(F.xxhash64("text"), 1)
    tie = F.when(F.col("doc_id").isNull(), -1 - spread).otherwise(spread)
    rows = rows.select(F.coalesce("doc_id", F.lit(NO_ID)).alias("doc_id"), tie.alias("tie"), "text")
    return rows, common.written(rows.dropDuplicates(list(KEY)), "substring-documents")


def deduped(docs: DataFrame, outputs: tuple[str, ...] = ("kept", "spans"), length: int = LENGTH, block_contexts: int = BLOCK_CONTEXTS, hot: int = HOT) -> DataFrame:
    """doc_id and, of FIELDS, the outputs asked for, of each row of docs (doc_id, text)."""
    checked(length)
    common.importable(docs.sparkSession)
    rows, once = keyed(docs)
    found = marks(once, length, block_contexts, hot)
    kind, schema = common.arrow_schema("doc_id long, " + ", ".join(f"{k} {FIELDS[k]}" for k in outputs))

    def strip(batches):
        for batch in batches:
            for low in range(0, batch.num_rows, 256):
                part = batch.slice(low, 256)
                out = []
                for key, tie, text, whole, own in zip(*(part.column(k).to_pylist() for k in range(3)), listed(part.column(3)), listed(part.column(4)), strict=True):
                    raw = text.encode()
                    gone = removed(raw, whole, own, length)
                    edge = np.flatnonzero(np.diff(gone.view(np.int8), prepend=0, append=0)) if gone is not None else ()
                    kept = raw if not len(edge) else np.frombuffer(raw, np.uint8)[~gone].tobytes()
                    row = {"n_bytes": len(raw), "n_removed": len(raw) - len(kept), "n_spans": len(edge) // 2, "kept": kept, "kept_sha256": hashlib.sha256(kept).hexdigest() if "kept_sha256" in outputs else None}
                    if "spans" in outputs:
                        row["spans"] = [{"start": int(a), "end": int(b)} for a, b in zip(edge[::2], edge[1::2], strict=True)]
                    out.append((None if key == NO_ID and tie < 0 else key, *(row[k] for k in outputs)))
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*out, strict=True), schema, strict=True)], schema=schema)

    return rows.join(found.hint("shuffle_hash"), list(KEY), "left").select(*KEY, "text", "whole", "own").mapInArrow(strip, kind)


def listed(column: pa.Array):
    """The lists of a column, as arrays of their values; None for null."""
    for k in range(len(column)):
        x = column[k]
        yield x.values if x.is_valid else None


def removed(raw: bytes, whole: pa.Array | None, own: pa.Array | None, length: int) -> np.ndarray | None:
    """Which bytes go; None if nothing does. whole: occurrences of anchors; own: those of which only some windows go, with these."""
    if whole is None or not len(whole):
        return None
    at = whole.to_numpy(zero_copy_only=False)
    first, last = windows_of(at)
    starts, ends = first, last
    if len(own):
        known, windows = own.field("at"), own.field("windows")
        known = known.to_numpy(zero_copy_only=False)
        keep = ~np.isin(at, known)
        counts = windows.value_lengths().to_numpy(zero_copy_only=False)
        single = np.repeat(windows_of(known)[0], counts) + windows.flatten().to_numpy(zero_copy_only=False)
        starts, ends = np.concatenate([first[keep], single]), np.concatenate([last[keep], single])
    if not len(starts):
        return None
    change = np.zeros(len(raw) + 1, np.int64)
    np.add.at(change, starts, 1)
    np.add.at(change, ends + length, -1)
    return np.cumsum(change[:-1]) > 0


def op4_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document without the strings of 100 bytes that start earlier."""
    return deduped(common.documents(spark, sf_dir), ("n_bytes", "n_removed", "n_spans", "kept_sha256"))


QUERIES = {"op4_substring_dedup": op4_substring_dedup}
ORACLES: dict[str, str] = {}
