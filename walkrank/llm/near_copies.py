"""Near copies at a Jaccard similarity of 0.8 or more over five-word shingles, found whole.

Two sets are near copies if 9 * |A and B| >= 4 * (|A| + |B|), which is a similarity of 4/5. Three steps:

1. SimHash: fingerprints of the sets within 3 bits link by the trees of `simhash`; each link is then verified.
2. The rest: shingles have a global order (frequent ones last, others by hash). Of two near copies the first
   n - ceil(0.8 n) + 1 shingles of both meet in one at least, so all pairs with a shingle in common there are looked at,
   unless step 1 or their sizes settle them. A sketch counts the shingles of a set by SLOTS values of their hash; the
   summed differences of two sketches are never more than the sets' symmetric difference, so what a sketch rules out
   is no near copy.
3. The pairs left are verified on the whole sets, and all links go into components.

No step loses a pair: order and sketch only decide what it costs. All shingles of all texts are counted, on 4 million
counters by their hash, which are sent to the executors (16 MB, however many texts); those on one counter count as one,
and those that aren't frequent come in the order of their hashes. Sets and texts are known by 64-bit hashes.

A null text is an empty one; texts without words are copies of each other, and a text of fewer than five words is one
shingle. Repeated rows are documents alike. A null doc_id takes part without being a component's id (null if no other
has one). Other columns are left out, and an empty table gives an empty table.
"""

from __future__ import annotations

import zlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import common, simhash
from .components import components

WORDS, SLOTS = 5, 64
#: Shingles of more texts than that come last in the order; counters of shingles (a power of two) and those of a shuffled row;
#: shingles that a worker gathers before it adds them to its counters.
FREQUENT, COUNTER_BITS, BLOCK, COUNTED = 48, 22, 1 << 14, 60_000
#: Sets of texts that a verifying worker remembers.
MEMO = 64


def shingle_set(text: str, words: int = WORDS) -> np.ndarray:
    parts = list(simhash.shingle_hashes(text, words))
    return np.unique(np.concatenate(parts)) if parts else np.zeros(0, np.uint64)


def fingerprint(hashes: np.ndarray) -> int:
    ones = np.zeros(64, np.int64)
    for at in range(0, len(hashes), simhash.BLOCK):
        ones += np.unpackbits(hashes[at : at + simhash.BLOCK].astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(hashes), bitorder="little").view("<i8")[0])


def sketch(hashes: np.ndarray) -> bytes:
    return np.bincount((hashes >> np.uint64(58)).astype(np.int64), minlength=SLOTS).astype(np.uint8).tobytes()


def counter_of(hashes: np.ndarray) -> np.ndarray:
    return (hashes >> np.uint64(64 - COUNTER_BITS)).astype(np.int64)


def first_shingles(hashes: np.ndarray, late: np.ndarray) -> np.ndarray:
    """The shingles of a set of which near copies share one at least."""
    n = len(hashes)
    return hashes[np.lexsort((hashes, late[counter_of(hashes)]))][: n - (4 * n + 4) // 5 + 1] if n else hashes


def similar(a: np.ndarray, b: np.ndarray) -> bool:
    return 9 * len(np.intersect1d(a, b, assume_unique=True)) >= 4 * (len(a) + len(b))


def frequent_shingles(texts: DataFrame) -> np.ndarray:
    """texts: text. The shingles of all texts, those of a text once each, by counters that their hashes fall on."""
    each, schema = common.arrow_schema("block int, counts binary")

    def count(batches):
        counters, held, rows = np.zeros(1 << COUNTER_BITS, np.uint32), [], 0
        for batch in batches:
            for text in batch.column(0):
                held.append(shingle_set(text.as_py()))
                rows += len(held[-1])
                if rows > COUNTED:
                    np.add.at(counters, counter_of(np.concatenate(held)), 1)
                    held, rows = [], 0
        if held:
            np.add.at(counters, counter_of(np.concatenate(held)), 1)
        blocks = counters.reshape(-1, BLOCK)
        some = np.flatnonzero(blocks.any(1))
        # nearly all are small numbers, which are squeezed before they are shuffled
        yield pa.RecordBatch.from_arrays([pa.array(some, pa.int32()), pa.array([zlib.compress(blocks[i].tobytes(), 1) for i in some], pa.binary())], schema=schema)

    def total(table):
        counters = np.zeros(BLOCK, np.uint64)
        for part in table.column(1):
            counters += np.frombuffer(zlib.decompress(part.as_py()), np.uint32)
        return pa.Table.from_arrays([table.column(0)[:1], pa.array([counters.tobytes()], pa.binary())], schema=schema)

    common.importable(texts.sparkSession)
    counters = np.zeros(1 << COUNTER_BITS, np.uint64)
    for block, counts in texts.select("text").mapInArrow(count, each).groupBy("block").applyInArrow(total, each).collect():
        counters[block * BLOCK : (block + 1) * BLOCK] = np.frombuffer(counts, np.uint64)
    return counters


def late_counters(counters: np.ndarray) -> np.ndarray:
    """The counters of frequent shingles, with zeros in place of others: a counter has its share of rare ones as well."""
    return np.where(counters >= FREQUENT + int(counters.mean()), counters, 0).clip(max=0xFFFFFFFF).astype(np.uint32)


def sets_of(texts: DataFrame) -> DataFrame:
    """doc_id and key of each row, and of its set the id, size, fingerprint, sketch and first shingles."""
    late = texts.sparkSession.sparkContext.broadcast(late_counters(frequent_shingles(texts)))

    def setup():
        from xxhash import xxh64_intdigest

        def one(doc_id, key, text):
            s = shingle_set(text)
            name = xxh64_intdigest(s.tobytes())
            return doc_id, key, name - (1 << 64) if name >> 63 else name, len(s), fingerprint(s), sketch(s), first_shingles(s, late.value).view(np.int64)

        return one

    return common.map_rows(texts.select("doc_id", "key", "text"), setup, "doc_id long, key long, id long, n long, fp long, sketch binary, first array<long>")


def fingerprint_pairs(sets: DataFrame) -> DataFrame:
    """a, b: pairs of sets whose fingerprints link; sets of equal fingerprints by the first of them."""
    heads = common.written(sets.groupBy("fp").agg(F.min("id").alias("head")), "near-heads")
    equal = sets.join(heads, "fp").where("id <> head").select(F.col("head").alias("a"), F.col("id").alias("b"))
    near = simhash.links(heads.select("fp"))
    near = near.join(heads.select(F.col("fp").alias("a"), F.col("head").alias("_a")), "a").join(heads.select(F.col("fp").alias("b"), F.col("head").alias("_b")), "b")
    return equal.unionByName(near.select(F.col("_a").alias("a"), F.col("_b").alias("b")))


def shared_pairs(sets: DataFrame, roots: DataFrame) -> DataFrame:
    """a, b: pairs of sets of different roots that share a first shingle and are ruled out neither by size nor by sketch."""
    each = sets.select(F.explode("first").alias("h"), "n", "id")
    w = Window.partitionBy("h").orderBy("n", "id")
    each = each.select("*", F.lag("n").over(w).alias("_lag"), F.lead("n").over(w).alias("_lead"))
    each = each.where("5 * _lag >= 4 * n or 5 * n >= 4 * _lead").select("h", "n", "id")
    more = sets.select("id", "sketch").join(roots.withColumnRenamed("node", "id"), "id", "left").withColumn("root", F.coalesce("root", "id"))
    each = each.join(more, "id").select("h", "n", "id", "root", "sketch").repartition("h").sortWithinPartitions("h", "n", "id")
    kind, schema = common.arrow_schema("a long, b long")

    def pairs(table):
        h, n, name, root = (table.column(i).to_numpy() for i in range(4))
        marks = np.frombuffer(b"".join(table.column(4).to_pylist()), np.uint8).reshape(-1, SLOTS)
        at, k = np.arange(len(h)), 0
        while True:
            # sizes rise inside a shingle, so a row that has no partner k places on has none further on
            k += 1
            at = at[: np.searchsorted(at, len(h) - k)]
            at = at[(h[at] == h[at + k]) & (5 * n[at] >= 4 * n[at + k])]
            if not len(at):
                return
            for i in np.array_split(at, len(at) // 65536 + 1):
                i = i[root[i] != root[i + k]]
                gap = marks[i] - marks[i + k]
                i = i[9 * np.minimum(gap, 0 - gap).sum(1, dtype=np.int64) <= n[i] + n[i + k]]
                if len(i):
                    yield pa.RecordBatch.from_arrays([pa.array(np.minimum(name[i], name[i + k])), pa.array(np.maximum(name[i], name[i + k]))], schema=schema)

    def run(batches):
        held = []
        for batch in batches:
            h = batch.column(0).to_numpy()
            cut = int(np.searchsorted(h, h[-1])) if len(h) else 0
            held.append(batch.slice(0, cut) if cut else batch)
            if cut:  # a shingle ends in this batch
                yield from pairs(pa.Table.from_batches(held))
                held = [batch.slice(cut)]
            elif len(h) and len(held) > 1 and held[-2].num_rows and held[-2].column(0)[-1].as_py() != h[0]:
                yield from pairs(pa.Table.from_batches(held[:-1]))
                held = held[-1:]
        if held:
            yield from pairs(pa.Table.from_batches(held))

    return each.mapInArrow(run, kind).distinct()


def verified(pairs: DataFrame, sets: DataFrame, texts: DataFrame) -> DataFrame:
    """The pairs that are near copies by their whole sets, which are made again from the texts."""
    pairs = common.written(pairs, "near-pairs")
    ids = pairs.select(F.col("a").alias("id")).union(pairs.select("b")).distinct()
    keys = sets.join(ids, "id", "left_semi").select("id", "key")
    # the texts move, not the sets: they are smaller and compress
    whole = common.written(texts.select("key", "text").join(F.broadcast(keys), "key").groupBy("id").agg(F.first("text").alias("text")), "near-texts")
    both = pairs.join(whole.select(F.col("id").alias("a"), F.col("text").alias("x")), "a").join(whole.select(F.col("id").alias("b"), F.col("text").alias("y")), "b")

    def setup():
        known = lru_cache(MEMO)(shingle_set)  # pairs of one text follow each other
        return lambda a, b, x, y: [(a, b)] if similar(known(x), known(y)) else []

    tested = common.flat_map_rows(both.select("a", "b", "x", "y"), setup, "a long, b long")
    return common.written(tested, "near-links")


def groups(docs: DataFrame) -> DataFrame:
    """doc_id and component_id of each row."""
    texts = docs.select("doc_id", common.text_of().alias("text")).withColumn("key", F.xxhash64("text"))
    marked = common.written(sets_of(texts), "near-marked")
    same = [F.first(c).alias(c) for c in ("n", "fp", "sketch", "first")]
    sets = common.written(marked.groupBy("id").agg(F.min("doc_id").alias("rep"), F.min("key").alias("key"), *same), "near-distinct")
    links = verified(fingerprint_pairs(sets), sets, texts)
    links = links.unionByName(verified(shared_pairs(sets, components(links)), sets, texts))
    placed = sets.select("id", "rep").join(components(links).withColumnRenamed("node", "id"), "id", "left").withColumn("root", F.coalesce("root", "id"))
    named = placed.groupBy("root").agg(F.min("rep").alias("component_id"))
    return marked.select("doc_id", "id").join(placed.join(named, "root").select("id", "component_id"), "id").select("doc_id", "component_id")
