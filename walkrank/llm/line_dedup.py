"""Reversible line dedup: exact reference counts of lines, with sharded cuckoo filters in front.

The index has three tables in the shared folder: which document holds which line key (a 128-bit digest), the exact
count of documents for each key with the largest doc_id that holds it, and for each shard of keys a cuckoo filter of
those with `least` documents or more. Inserting documents or deleting them adds or takes away occurrences, recounts
the keys that are concerned alone, and inserts into or deletes from the filters the keys that cross the limit, so
deleting what was inserted gives the index back. From the first change on all three tables lie by shard, and a change
reads and writes the shards that it concerns alone, as a piece that stands for these; many pieces become one. A filter
that overflows is built anew from the exact table, and once the shards hold twice the keys they are made for, each is
split in two.

To dedup, the lines' keys are probed in the filters (those sent to the executors at once stay under WAVE_BYTES; more
shards take more waves over their own occurrences). What passes is looked up in the exact table, so a filter's false
positives lose no line. Hot keys are counted before they are shuffled and then joined as a skewed join.

A line's key has white space stripped at both ends and A-Z in lower case; only keys of `shortest` code points take
part. Null and empty texts are one empty line. Rows that repeat a doc_id are one document for counting, and each loses
the same keys. Rows without a doc_id count nowhere and lose nothing. Other columns are left out; an empty table gives
an empty table.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

SHORTEST, LEAST = 40, 5
SHARD_KEYS, WAVE_BYTES = 40_000, 64 << 20
#: Pieces of a table from which on they become one, and files of a shard in a piece.
PIECES, FILES = 16, 8
SPACE = b" \t\n\x0b\x0c\r"
SLOTS, KICKS, WIDEST = 4, 500, 64


def line_keys(text: str, shortest: int) -> list[bytes | None]:
    """For each line of a text its key's digest, or None if it is too short."""
    from xxhash import xxh3_128_digest

    out: list[bytes | None] = []
    for line in text.encode().split(b"\n"):
        key = line.strip(SPACE).lower()
        long = len(key) >= shortest and (key.isascii() or len(key) >= 4 * shortest or len(key.decode()) >= shortest)
        out.append(xxh3_128_digest(key) if long else None)
    return out


class Cuckoo:
    """A cuckoo filter: buckets of four 16-bit marks, each key in one of two buckets. Keys are pairs of 64-bit hashes."""

    def __init__(self, keys: int = 0, table: bytes | None = None):
        size = 1 << max(1, math.ceil(math.log2(max(keys, 1) / (0.85 * SLOTS))))
        self.table = np.zeros((size, SLOTS), np.uint16) if table is None else np.frombuffer(table, np.uint16).reshape(-1, SLOTS).copy()

    def places(self, h1: np.ndarray, h2: np.ndarray):
        """Marks and both buckets."""
        mask = np.uint64(len(self.table) - 1)
        mark = (h2.view(np.uint64) >> np.uint64(48)).astype(np.uint16)
        mark[mark == 0] = 1
        first = h1.view(np.uint64) & mask
        return mark, first, first ^ self.hop(mark)

    def hop(self, mark):
        return (np.asarray(mark, np.uint64) * np.uint64(0x5BD1E995) >> np.uint64(7)) & np.uint64(len(self.table) - 1)

    def has(self, h1: np.ndarray, h2: np.ndarray) -> np.ndarray:
        mark, a, b = self.places(h1, h2)
        return (self.table[a] == mark[:, None]).any(1) | (self.table[b] == mark[:, None]).any(1)

    def insert(self, h1: np.ndarray, h2: np.ndarray) -> bool:
        """False if there is no room."""
        for mark, a, b in zip(*(x.tolist() for x in self.places(h1, h2)), strict=True):
            at = a
            for kick in range(KICKS):
                for place in (a, b) if not kick else (at,):
                    free = np.flatnonzero(self.table[place] == 0)
                    if len(free):
                        self.table[place, free[0]] = mark
                        break
                else:
                    slot = kick & 3
                    mark, self.table[at, slot] = int(self.table[at, slot]), mark
                    at ^= int(self.hop(mark))
                    continue
                break
            else:
                return False
        return True

    def delete(self, h1: np.ndarray, h2: np.ndarray) -> None:
        for mark, a, b in zip(*(x.tolist() for x in self.places(h1, h2)), strict=True):
            for place in (a, b):
                found = np.flatnonzero(self.table[place] == mark)
                if len(found):
                    self.table[place, found[0]] = 0
                    break

    @staticmethod
    def of(h1: np.ndarray, h2: np.ndarray) -> Cuckoo | None:
        """A filter of all keys; None (which passes everything) if even a wide one overflows."""
        keys = max(len(h1), 8)
        while keys <= WIDEST * max(len(h1), 8):
            made = Cuckoo(keys)
            if made.insert(h1, h2):
                return made
            keys *= 2
        return None


def occurrences(docs: DataFrame, shortest: int = SHORTEST) -> DataFrame:
    """A row for each document and distinct key in it: doc_id, h1, h2."""
    common.importable(docs.sparkSession)
    kind, schema = common.arrow_schema("doc_id long, h1 long, h2 long")

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                ids, keys = [], []
                for key, text in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True):
                    found = {k for k in line_keys(text, shortest) if k}
                    keys += found
                    ids += [key] * len(found)
                h = np.frombuffer(b"".join(keys), "<i8").reshape(-1, 2)
                yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(h[:, 0].copy()), pa.array(h[:, 1].copy())], schema=schema)

    return docs.where("doc_id is not null").select("doc_id", common.text_of().alias("text")).mapInArrow(run, kind)


def shard_of(shards: int) -> Column:
    return F.pmod(F.shiftrightunsigned("h1", 20), F.lit(shards)).cast("int")


def refiltered(filters: DataFrame, keys: DataFrame) -> DataFrame:
    """New filters (shard, marks). keys: shard, h1, h2 and change: 1 comes, -1 goes, 0 is and stays. Keys of a shard are
    about SHARD_KEYS, twice that at most."""

    def update(old: pd.DataFrame, new: pd.DataFrame) -> pd.DataFrame:
        if not len(new):
            return old[["shard", "marks"]]
        pick = lambda sign: (new.h1[new.change == sign].to_numpy(np.int64), new.h2[new.change == sign].to_numpy(np.int64))
        filter_ = Cuckoo(table=old.marks[0]) if len(old) and old.marks[0] is not None else None
        if filter_:
            filter_.delete(*pick(-1))
        if not filter_ or not filter_.insert(*pick(1)):
            now = new[new.change >= 0]
            filter_ = Cuckoo.of(now.h1.to_numpy(np.int64), now.h2.to_numpy(np.int64))
        return pd.DataFrame({"shard": [int(new["shard"].iloc[0])], "marks": [filter_.table.tobytes() if filter_ else None]})

    return filters.groupBy("shard").cogroup(keys.groupBy("shard")).applyInPandas(update, "shard int, marks binary")


def counted(found: DataFrame) -> DataFrame:
    return found.groupBy("h1", "h2").agg(F.count_distinct("doc_id").alias("n_docs"), F.max("doc_id").alias("last_doc"))


@dataclass
class Sharded:
    """A table with the column shard, in pieces: each with the shards for which a later piece stands."""

    pieces: list[tuple[DataFrame, frozenset[int]]]

    def of(self, shards: set[int] | None = None) -> DataFrame:
        """The rows of some shards, or of all."""
        out = None
        for df, gone in self.pieces:
            if shards is not None:
                df = df.where(F.col("shard").isin(sorted(shards - gone)))
            elif gone:
                df = df.where(~F.col("shard").isin(sorted(gone)))
            out = df if out is None else out.unionByName(df)
        return out

    def added(self, df: DataFrame) -> Sharded:
        return Sharded([*self.pieces, (df, frozenset())]).joined()

    def replaced(self, shards: set[int], df: DataFrame) -> Sharded:
        """With df in place of some shards."""
        return Sharded([*((old, gone | shards) for old, gone in self.pieces), (df, frozenset())]).joined()

    def joined(self) -> Sharded:
        return self if len(self.pieces) <= PIECES else Sharded([(by_shard(self.of(), "line-table"), frozenset())])


def by_shard(df: DataFrame, name: str) -> DataFrame:
    """df as a table with a folder for each shard, of FILES files at most."""
    spread = F.pmod(F.xxhash64(*[c for c in df.columns if c != "shard"]), F.lit(FILES))
    return common.written(df.repartition("shard", spread), name, "shard")


KEY = ["h1", "h2"]


@dataclass
class LineIndex:
    """held: doc_id, h1, h2; counts: h1, h2, n_docs, last_doc; filters: marks; all with shard. repeated: keys in the filters."""

    held: Sharded
    counts: Sharded
    filters: Sharded
    shards: int
    repeated: int
    least: int
    shortest: int
    #: whether the tables lie by shard
    laid_out: bool = False

    @staticmethod
    def build(docs: DataFrame, least: int = LEAST, shortest: int = SHORTEST) -> LineIndex:
        held = common.written(occurrences(docs, shortest), "line-occurrences")
        return LineIndex.of(held, common.written(counted(held), "line-counts"), least, shortest)

    @staticmethod
    def of(held: DataFrame, counts: DataFrame, least: int, shortest: int) -> LineIndex:
        """An index with filters made anew; its tables are as they are until the first change."""
        some = counts.where(F.col("n_docs") >= least)
        repeated = some.count()
        shards = 1 << max(0, math.ceil(math.log2(max(1, repeated) / SHARD_KEYS)))
        whole = lambda df: Sharded([(df.withColumn("shard", shard_of(shards)), frozenset())])
        none = counts.sparkSession.createDataFrame([], "shard int, marks binary")
        filters = refiltered(none, some.select(shard_of(shards).alias("shard"), *KEY, F.lit(1).alias("change")))
        return LineIndex(whole(held), whole(counts), Sharded([(common.written(filters, "line-filters"), frozenset())]), shards, repeated, least, shortest)

    def by_shard(self) -> LineIndex:
        if self.laid_out:
            return self
        lay = lambda table, name: Sharded([(by_shard(table.of(), name), frozenset())])
        return replace(self, held=lay(self.held, "line-occurrences"), counts=lay(self.counts, "line-counts"), laid_out=True)

    def changed(self, held: Sharded, concerned: DataFrame, touched: set[int]) -> LineIndex:
        """The index with other occurrences; only the concerned keys (h1, h2), all in the touched shards, are counted anew."""
        again = counted(held.of(touched).join(concerned, KEY, "left_semi")).withColumn("shard", shard_of(self.shards))
        before = self.counts.of(touched)
        after = by_shard(before.join(concerned, KEY, "left_anti").unionByName(again), "line-counts")
        some = lambda df, name: df.where(F.col("n_docs") >= self.least).select(*KEY, F.lit(1).alias(name))
        both = some(before, "was").join(some(after, "now"), KEY, "full")
        change = (F.coalesce("now", F.lit(0)) - F.coalesce("was", F.lit(0))).alias("change")
        change = common.written(both.select(shard_of(self.shards).alias("shard"), *KEY, change), "line-changes")
        filters = common.written(refiltered(self.filters.of(touched), change), "line-filters")
        repeated = self.repeated + (change.agg(F.sum("change")).first()[0] or 0)
        now = replace(self, held=held, counts=self.counts.replaced(touched, after), filters=self.filters.replaced(touched, filters), repeated=repeated)
        if repeated > 2 * SHARD_KEYS * self.shards:
            return LineIndex.of(held.of().drop("shard"), now.counts.of().drop("shard"), self.least, self.shortest).by_shard()
        return now

    def insert(self, docs: DataFrame) -> LineIndex:
        base = self.by_shard()
        fresh = by_shard(occurrences(docs, self.shortest).withColumn("shard", shard_of(base.shards)), "line-occurrences")
        touched = {r.shard for r in fresh.select("shard").distinct().collect()}
        return base.changed(base.held.added(fresh), fresh.select(*KEY).distinct(), touched) if touched else base

    def delete(self, doc_ids: DataFrame) -> LineIndex:
        """doc_ids: the column doc_id. What the documents hold is looked for in all shards; those that have it are written."""
        base, ids = self.by_shard(), common.written(doc_ids.select("doc_id").distinct(), "line-ids")
        gone = common.written(base.held.of().join(ids, "doc_id", "left_semi"), "line-gone")
        touched = {r.shard for r in gone.select("shard").distinct().collect()}
        if not touched:
            return base
        left = by_shard(base.held.of(touched).join(ids, "doc_id", "left_anti"), "line-occurrences")
        return base.changed(base.held.replaced(touched, left), gone.select(*KEY).distinct(), touched)

    def passing(self) -> DataFrame:
        """The occurrences that the filters let pass."""
        filters = self.filters.of()
        total = filters.agg(F.sum(F.length("marks"))).first()[0] or 0
        waves, out = max(1, math.ceil(total / WAVE_BYTES)), []
        kind, schema = common.arrow_schema("doc_id long, h1 long, h2 long")
        for wave in range(waves):
            shared = filters.sparkSession.sparkContext.broadcast({r.shard: r.marks for r in filters.where(F.col("shard") % waves == wave).collect()})

            def run(batches, shared=shared):
                tables = {k: v is not None and Cuckoo(table=v) for k, v in shared.value.items()}
                for batch in batches:
                    shard, h1, h2 = (batch.column(k).to_numpy(zero_copy_only=False) for k in (0, 2, 3))
                    keep = np.zeros(len(shard), bool)
                    for k in np.unique(shard):
                        if k in tables:
                            at = np.flatnonzero(shard == k)
                            keep[at] = tables[k].has(h1[at], h2[at]) if tables[k] else True
                    yield pa.RecordBatch.from_arrays([batch.column(k).filter(pa.array(keep)) for k in (1, 2, 3)], schema=schema)

            out.append(self.held.of().where(F.col("shard") % waves == wave).select("shard", "doc_id", "h1", "h2").mapInArrow(run, kind))
        found = out[0]
        for x in out[1:]:
            found = found.unionByName(x)
        return found

    def dropped(self) -> DataFrame:
        """doc_id and the digests of the keys that it loses."""
        exact = self.counts.of().where(F.col("n_docs") >= self.least).select("h1", "h2", "last_doc")
        lost = self.passing().join(exact, ["h1", "h2"]).where("doc_id <> last_doc")
        return lost.groupBy("doc_id").agg(F.collect_set(F.struct("h1", "h2")).alias("lost"))

    def deduped(self, docs: DataFrame, outputs: tuple[str, ...] = ("text",), keep: tuple[str, ...] = ()) -> DataFrame:
        """Of each row of docs doc_id, n_lines, n_dropped, of text and kept_sha256 the outputs asked for, and the columns to keep."""
        import hashlib

        kinds, shortest = {"text": "string", "kept_sha256": "string"}, self.shortest

        def setup():
            def one(key, text, lost, *others):
                lines = text.split("\n")
                n, kept = len(lines), text
                if lost:
                    gone = {np.array([x["h1"], x["h2"]], "<i8").tobytes() for x in lost}
                    lines = [line for line, k in zip(lines, line_keys(text, shortest), strict=True) if k not in gone]
                    kept = "\n".join(lines)
                out = {"text": kept, "kept_sha256": hashlib.sha256(kept.encode()).hexdigest() if "kept_sha256" in outputs else None}
                return key, n, n - len(lines), *(out[k] for k in outputs), *others

            return one

        lost = self.dropped().withColumnRenamed("doc_id", "_id")
        rows = docs.select("doc_id", common.text_of().alias("text"), *(F.col(k).alias(f"_{k}") for k in keep))
        rows = rows.join(lost, F.col("doc_id") == F.col("_id"), "left").select("doc_id", "text", "lost", *(f"_{k}" for k in keep))
        ddl = "doc_id long, n_lines long, n_dropped long" + "".join(f", {k} {kinds[k]}" for k in outputs)
        return common.map_rows(rows, setup, ddl + "".join(f", `{k}` {docs.schema[k].dataType.simpleString()}" for k in keep))


def op1_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document without its repeated lines."""
    docs = common.documents(spark, sf_dir)
    return LineIndex.build(docs).deduped(docs, ("kept_sha256",))


LETTERS = "'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'"
#: SQL over a table {docs} of the kept lines (doc_id, i, line, drop).
MARKED = f"""
lines as (select doc_id, unnest(string_split(coalesce(text, ''), chr(10))) as line,
            generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) as i from {{docs}}),
keyed as (select *, translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), {LETTERS}) as k from lines),
held as (select k, max(doc_id) as last_doc from keyed where length(k) >= {SHORTEST} group by k having count(distinct doc_id) >= {LEAST}),
marked as (select a.doc_id, a.i, a.line, coalesce(a.doc_id <> b.last_doc, false) as gone from keyed a left join held b on a.k = b.k)
"""

QUERIES = {"op1_line_dedup": op1_line_dedup}
ORACLES = {
    "op1_line_dedup": f"""with {MARKED.format(docs="documents")}
select doc_id, count(*)::bigint as n_lines, (count(*) filter (where gone))::bigint as n_dropped,
       sha256(coalesce(string_agg(line, chr(10) order by i) filter (where not gone), '')) as kept_sha256
from marked group by doc_id"""
}
