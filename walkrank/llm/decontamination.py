"""Benchmark decontamination: every passage of the corpus queries a BM25 index of the test items.

The index has, for each word, the items that hold it in order with their BM25 weight, divided by what the item scores
against itself; so a score is the share of the item's weight that a passage has, and one threshold holds for all items.
Postings come in blocks with the largest weight of each. Block-max WAND moves through them: words in order of their
next item up to the first whose bounds add up to the threshold give the pivot; if the blocks at the pivot can't reach
it either, whole blocks are passed over. It returns all items at or above the threshold, not a number of best ones.

A passage has twice as many words as the longest item and starts each time that many words on, so any quotation lies
wholly in one. Before that the largest weights of the blocks are added up for all passages of a text at once; only
passages with a block that can reach the threshold go through the lists.

What is found is verified: of the item's question (its first line, or half of its words if it has one line) and of its
answer (the rest) the share of word shingles that the passage has must both reach `overlap`.

The index is built from all items and sent to the executors; where their texts are above INDEX_BYTES it is built and
queried in several waves of items, with word counts over all: the results of a wave are written and its index is
released before the next one is built. A text is read as a stream of words, CHUNK passages at a time, and bounds are
added up for CELLS passages times ranges of items at once, so neither a long text nor a long index needs memory for both.

Null texts are empty. Items or texts without words match
nothing. Repeated documents give repeated results; of items with one item_id each is an item of its own. Other columns
are left out; an empty table gives an empty table.
"""

from __future__ import annotations

import bisect
import math
import re
from dataclasses import dataclass
from functools import reduce
from itertools import islice

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

K1, B = 1.2, 0.75
THRESHOLD, OVERLAP, SHINGLE = 0.5, 0.6, 5
BLOCK, INDEX_BYTES = 4, 4 << 20
#: Passages of a text handled at once; sums of bounds, and postings, held at once.
CHUNK, CELLS = 256, 1 << 20
WORD = re.compile(r"\w+")


def words_of(text: str) -> list[str]:
    return WORD.findall(text.lower())


def chunks(text: str, step: int):
    """The words of a text for CHUNK passages at a time, which are 2 * step words each, and the place of the first of them."""
    most = (CHUNK + 1) * step
    if len(text) <= most:  # it can't have more words
        yield 0, words_of(text)
        return
    stream, at, held = (m[0] for m in WORD.finditer(text.lower())), 0, []
    while True:
        held += islice(stream, most + 1 - len(held))
        if len(held) <= most:
            yield at, held
            return
        yield at, held[:most]
        at += CHUNK * step
        held = held[CHUNK * step :]


def shingles(words: list[str], n: int = SHINGLE) -> set[tuple[str, ...]]:
    n = min(n, len(words))
    return {tuple(words[i : i + n]) for i in range(len(words) - n + 1)} if n else set()


def question_and_answer(text: str) -> tuple[list[str], list[str]]:
    first, found, rest = text.strip().partition("\n")
    question, answer = words_of(first), words_of(rest)
    if not question or not answer:
        both = question + answer
        question, answer = both[: (len(both) + 1) // 2], both[(len(both) + 1) // 2 :]
    return question, answer


@dataclass
class Posting:
    items: list[int]
    weights: list[float]
    most: float
    #: the last item and the largest weight of each block
    ends: list[int]
    block_most: list[float]


class Index:
    def __init__(self, items: list[tuple[int, str]], df: dict[str, int], n: int, mean: float):
        self.ids = [k for k, _ in items]
        split = [question_and_answer(t) for _, t in items]
        self.parts = [(shingles(q), shingles(a)) for q, a in split]
        self.longest = max((len(q) + len(a) for q, a in split), default=0)
        lists: dict[str, list[tuple[int, float]]] = {}
        for k, (q, a) in enumerate(split):
            tf: dict[str, int] = {}
            for w in q + a:
                tf[w] = tf.get(w, 0) + 1
            weight = {w: math.log(1 + (n - df[w] + 0.5) / (df[w] + 0.5)) * f * (K1 + 1) / (f + K1 * (1 - B + B * (len(q) + len(a)) / mean)) for w, f in tf.items()}
            total = sum(weight.values())
            for w, x in weight.items():
                lists.setdefault(w, []).append((k, x / total))
        self.number = {w: i for i, w in enumerate(lists)}
        self.postings = []
        for found in lists.values():
            blocks = [found[i : i + BLOCK] for i in range(0, len(found), BLOCK)]
            self.postings.append(Posting([k for k, _ in found], [x for _, x in found], max(x for _, x in found), [b[-1][0] for b in blocks], [max(x for _, x in b) for b in blocks]))
        # the blocks of all words, as numbers of fixed ranges of items, for bounds of many passages at once
        ranges = [{} for _ in self.postings]
        for held, p in zip(ranges, self.postings, strict=True):
            for k, x in zip(p.items, p.weights, strict=True):
                held[k // BLOCK] = max(held.get(k // BLOCK, 0.0), x)
        self.starts = np.concatenate([[0], np.cumsum([len(held) for held in ranges])]).astype(np.int64)
        self.range = np.array([k for held in ranges for k in held], np.int64)
        self.range_most = np.array([x for held in ranges for x in held.values()])
        self.ranges = -(-len(items) // BLOCK)

    def within_reach(self, passage: np.ndarray, term: np.ndarray, n: int, threshold: float) -> np.ndarray:
        """The passages (of n) with a range of items that may reach the threshold. passage, term: distinct pairs, by passage."""
        sizes = self.starts[term + 1] - self.starts[term]
        found, rows = [], max(1, CELLS // max(self.ranges, 1))
        for first in range(0, n, rows):
            count = min(rows, n - first)
            low, high = np.searchsorted(passage, [first, first + count]).tolist()
            bounds, ends = np.zeros(count * self.ranges), np.cumsum(sizes[low:high])
            while low < high:
                # as many pairs as have CELLS postings together, one at least
                done = int(ends[-1] - sizes[low:high].sum())
                end = low + max(1, int(np.searchsorted(ends[low - high :], done + CELLS, "right")))
                some = sizes[low:end]
                upto = np.cumsum(some)
                place = np.arange(int(upto[-1])) - np.repeat(upto - some - self.starts[term[low:end]], some)
                bounds += np.bincount(np.repeat(passage[low:end] - first, some) * self.ranges + self.range[place], self.range_most[place], count * self.ranges)
                low = end
            found.append(first + np.flatnonzero(bounds.reshape(count, self.ranges).max(1, initial=0.0) >= threshold - 1e-9))
        return np.concatenate(found) if found else np.zeros(0, np.int64)

    def search(self, terms: list[int], threshold: float) -> list[tuple[int, float]]:
        """Items of at least the threshold with their scores. terms: distinct."""
        lists = [self.postings[t] for t in terms]
        at = [0] * len(lists)
        out, limit = [], threshold - 1e-9
        order = sorted(range(len(lists)), key=lambda i: lists[i].items[0])
        while order:
            total, pivot = 0.0, -1
            for place, i in enumerate(order):
                total += lists[i].most
                if total >= limit:
                    pivot = place
                    break
            if pivot < 0:
                break
            item = lists[order[pivot]].items[at[order[pivot]]]
            while pivot + 1 < len(order) and lists[order[pivot + 1]].items[at[order[pivot + 1]]] == item:
                pivot += 1
            bound, target = 0.0, None
            for i in order[: pivot + 1]:
                p = lists[i]
                b = bisect.bisect_left(p.ends, item)
                if b < len(p.ends):
                    bound += p.block_most[b]
                    target = p.ends[b] if target is None else min(target, p.ends[b])
            if bound < limit:
                # no item up to the end of the shortest of these blocks, nor before the next list, can reach it
                to = target + 1 if target is not None else item + 1
                if pivot + 1 < len(order):
                    to = min(to, lists[order[pivot + 1]].items[at[order[pivot + 1]]])
                to, move = max(to, item + 1), order[: pivot + 1]
            elif lists[order[0]].items[at[order[0]]] == item:
                move, to = [i for i in order[: pivot + 1]], item + 1
                score = sum(lists[i].weights[at[i]] for i in move)
                if score >= limit:
                    out.append((item, score))
            else:
                move, to = [i for i in order[:pivot] if lists[i].items[at[i]] < item], item
            for i in move:
                at[i] = bisect.bisect_left(lists[i].items, to, at[i])
            order = sorted((i for i in order if at[i] < len(lists[i].items)), key=lambda i: lists[i].items[at[i]])
        return out

    def hits(self, text: str, threshold: float, overlap: float) -> list[tuple[int, int, int, float, float, float]]:
        """Place of the item, first word and number of words of the passage, score, and both overlaps; the best passage of each item."""
        found: dict[int, tuple] = {}
        if self.longest:
            for first, words in chunks(text, self.longest):
                self.look(first, words, threshold, overlap, found)
        return [found[k] for k in sorted(found)]

    def look(self, first: int, words: list[str], threshold: float, overlap: float, found: dict[int, tuple]) -> None:
        """Adds the items that some words of a text give away. first: the place of the first of these in the text."""
        step, get = self.longest, self.number.get
        ids = np.array([get(w, -1) for w in words], np.int64)
        where = np.flatnonzero(ids >= 0)
        if not len(where):
            return
        n, last = len(self.postings), max((len(words) - 1) // step, 1)
        # a word is in the passage that starts in its stretch of words and in the one before
        stretch = where // step
        pairs = np.unique(np.concatenate([np.minimum(stretch, last - 1) * n + ids[where], np.maximum(stretch - 1, 0) * n + ids[where]]))
        passages, term = pairs // n, pairs % n
        for k in self.within_reach(passages, term, last, threshold).tolist():
            low, high = np.searchsorted(passages, [k, k + 1])
            for item, score in self.search(term[low:high].tolist(), threshold):
                passage = words[k * step : (k + 2) * step]
                share = [len(p & held) / len(p) if p else 1.0 for p in self.parts[item] for held in [self.held(passage, p)]]
                if min(share) >= overlap and (item not in found or score > found[item][3]):
                    found[item] = (item, first + k * step, len(passage), score, *share)

    @staticmethod
    def held(passage: list[str], part: set) -> set:
        n = len(next(iter(part))) if part else 1
        return shingles(passage, n)


def indexes(items: DataFrame, index_bytes: int = INDEX_BYTES):
    """The waves of items (item_id, text): for each how many there are and its index, broadcast."""
    spark = common.importable(items.sparkSession)
    known = items.select("item_id", common.text_of().alias("text"))
    sizes = known.agg(F.sum(F.octet_length("text")).alias("b")).first()
    waves = max(1, math.ceil((sizes.b or 0) / index_bytes))
    known = known.withColumn("wave", F.pmod(F.xxhash64("item_id", "text"), F.lit(waves)))

    def terms():
        def many(wave, text):
            words = words_of(text)
            yield wave, "", len(words)
            for w in set(words):
                yield wave, w, 1

        return many

    terms_of = common.written(common.flat_map_rows(known.select("wave", "text"), terms, "wave long, word string, n long"), "benchmark-words")
    total = terms_of.where("word = ''").agg(F.count("*").alias("n"), F.avg("n").alias("mean")).first()
    df = terms_of.where("word <> ''").groupBy("word").agg(F.count("*").alias("df"))
    for wave in range(waves):
        rows = known.where(F.col("wave") == wave).select("item_id", "text").orderBy("item_id", "text").collect()
        counts = {r.word: r.df for r in df.join(terms_of.where((F.col("wave") == wave) & (F.col("word") != "")).select("word").distinct(), "word").collect()}
        yield waves, spark.sparkContext.broadcast(Index([(r.item_id, r.text) for r in rows], counts, total.n, total.mean or 1.0))


def contaminated(docs: DataFrame, items: DataFrame, threshold: float = THRESHOLD, overlap: float = OVERLAP, index_bytes: int = INDEX_BYTES) -> DataFrame:
    """A row for each document and item that a passage of it gives away: doc_id, item_id, the passage's first word and
    number of words, score, question and answer (shares of their shingles)."""
    texts, out = docs.select("doc_id", common.text_of().alias("text")), []
    for waves, shared in indexes(items, index_bytes):

        def setup(shared=shared):
            index = shared.value

            def many(key, text):
                for item, *rest in index.hits(text, threshold, overlap):
                    yield key, index.ids[item], *rest

            return many

        found = common.flat_map_rows(texts, setup, "doc_id long, item_id long, passage_start long, passage_words long, score double, question double, answer double")
        if waves > 1:
            found = common.written(found, "benchmark-hits")
            shared.destroy()
        out.append(found)
    return reduce(DataFrame.unionByName, out)


def clean(docs: DataFrame, items: DataFrame, threshold: float = THRESHOLD, overlap: float = OVERLAP, index_bytes: int = INDEX_BYTES) -> DataFrame:
    """The rows of docs, whole, that give no item away. Nothing is shuffled."""
    for waves, shared in indexes(items, index_bytes):
        docs = docs.where(quotes_nothing(shared, threshold, overlap)(common.text_of()))
        if waves > 1:
            docs = common.written(docs, "benchmark-clean")
            shared.destroy()
    return docs


def quotes_nothing(shared, threshold: float, overlap: float):
    @F.pandas_udf("boolean")
    def free(texts: pd.Series) -> pd.Series:
        return texts.map(lambda t: not shared.value.hits(t, threshold, overlap)).astype(bool)

    return free


def op8_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The benchmark items that documents quote."""
    return contaminated(common.documents(spark, sf_dir), common.documents(spark, sf_dir, "benchmark"))


QUERIES = {"op8_decontamination": op8_decontamination}
ORACLES: dict[str, str] = {}
