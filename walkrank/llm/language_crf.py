"""Language of words by a linear-chain conditional random field, for text that switches language.

A word is a run of letters. Its label score is the sum of hashed feature weights: pairs and triples of letters (with
word ends as a letter of their own, so these hold affixes of up to two letters), first and last three letters with the
word end, and the word itself if it is in the learned lexicon. Labels of neighbours score by a learned transition
matrix. Forward-backward gives the marginals of each word; the label of a text is the one with the largest mean.

Forward-backward runs on blocks of BLOCK words at once: the transfer matrix of each block, then a scan over the blocks
of each text, then both passes inside all blocks. Texts are taken together up to a number of characters that falls as the
labels grow; a longer text goes by in pieces, once forward and once backward, with the messages between
them. All of that is exact, and its memory is bounded whatever the texts and labels. A run of more than LONGEST letters
is cut into words of that many.

Fitting sees a bounded sample of whole texts: of each label at most `sample` texts, those of least hash of doc_id, with
at most SAMPLE_CHARS characters over all labels, each having an equal share (texts longer than a share come last, and
only where a label has no other one of them). All words of such a text carry its label. Every label with a text is
learned; beyond WEIGHTS weights in a table of 32,768 rows and one of 65,536 both are folded in half, for more labels
again. Everything else covers all rows.

Texts that are null or have no letter get `und` and score 0; so do all where nothing could be learned. Ties between
labels go to the first in order of name. Repeated rows give repeated results; other columns are left out; empty tables
give empty tables. Rows with a null doc_id count as not held out but teach nothing.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common

SAMPLE, SAMPLE_CHARS = 300, 16_000_000
#: Rows of the two hashed weight tables, and most words of the lexicon for each label.
GRAMS, WORDS, LEXICON = 1 << 15, 1 << 16, 3000
#: Most weights of both tables.
WEIGHTS = 64 * (GRAMS + WORDS)
BLOCK, LONGEST = 32, 10_000
#: Characters of texts that are handled at once with up to four labels, and what a text counts at least.
BATCH_CHARS, TEXT_CHARS = 1_500_000, 6 * BLOCK
PASSES, RATE = 3, 0.15
NONE = "und"


@lru_cache(1)
def letters() -> np.ndarray:
    """For each code point its lower case if it is a letter, else 0."""
    low = np.zeros(0x110000, np.uint32)
    for c in range(0x110000):
        x = chr(c)
        if x.isalpha():
            y = x.lower()
            low[c] = ord(y) if len(y) == 1 else c
    return low


@dataclass
class Words:
    """The words of some texts: the letters of all, each word's first and behind-last place, each text's first word."""

    chars: np.ndarray
    start: np.ndarray
    end: np.ndarray
    first: np.ndarray

    @staticmethod
    def of(texts: list[str]) -> Words:
        data = np.frombuffer(("\0" + "\0".join(texts) + "\0").encode("utf-32-le", "replace"), np.uint32)
        chars = letters()[data]
        inside = chars != 0
        edge = np.flatnonzero(inside[1:] != inside[:-1]) + 1
        start, end = edge[::2], edge[1::2]
        if len(start) and (end - start).max() > LONGEST:
            pieces = -(-(end - start) // LONGEST)
            at = np.arange(int(pieces.sum())) - np.repeat(np.cumsum(pieces) - pieces, pieces)
            start, end = np.repeat(start, pieces) + at * LONGEST, np.minimum(np.repeat(start, pieces) + (at + 1) * LONGEST, np.repeat(end, pieces))
        ends = np.cumsum([len(t) + 1 for t in texts])
        return Words(chars, start, end, np.concatenate([[0], np.searchsorted(start, ends)]))


def hashed(values: np.ndarray, size: int) -> np.ndarray:
    return ((values * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - size.bit_length() + 1)).astype(np.int64)


def features(words: Words) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Rows of the gram table for each place of a word (with those that belong to the word's ends), and of the word table."""
    c = words.chars.astype(np.uint64)
    s, e = words.start, words.end
    n = e - s
    before = np.concatenate([[np.uint64(0)], c[:-1]])
    after = np.concatenate([c[1:], [np.uint64(0)]])
    at = np.flatnonzero(words.chars)
    triple = hashed((before[at] << np.uint64(42)) | (c[at] << np.uint64(21)) | after[at], GRAMS)
    pair = hashed((np.uint64(1) << np.uint64(62)) | (c[at] << np.uint64(21)) | after[at], GRAMS)
    three = lambda i, j, k, tag: hashed((c[i] * np.uint64(0x1F35B2C9D) + c[j] * np.uint64(0x5851F42D) + c[k]) ^ (np.uint64(tag) << np.uint64(60)), GRAMS)
    ends = np.stack([three(s, np.minimum(s + 1, e - 1), np.minimum(s + 2, e - 1), 2), three(e - 1, np.maximum(e - 2, s), np.maximum(e - 3, s), 3)], 1)
    power = np.full(len(at), 0x100000001B3, np.uint64)
    head = np.cumsum(n) - n
    inside = np.arange(len(at)) - np.repeat(head, n)
    spread = c[at] * (inside.astype(np.uint64) * np.uint64(2) + np.uint64(1)) * power ^ (c[at] << (inside.astype(np.uint64) % np.uint64(40)))
    word = hashed(np.add.reduceat(spread, head) + n.astype(np.uint64) if len(n) else np.zeros(0, np.uint64), WORDS)
    return np.stack([triple, pair], 1), ends, head, word


@dataclass
class Model:
    labels: list[str]
    grams: np.ndarray
    words: np.ndarray
    moves: np.ndarray

    @property
    def folds(self) -> int:
        return (GRAMS // len(self.grams)).bit_length() - 1

    def features(self, words: Words):
        """Features as rows of this model's tables."""
        at, ends, head, word = features(words)
        return (at >> self.folds, ends >> self.folds, head, word >> self.folds) if self.folds else (at, ends, head, word)

    def emissions(self, f) -> np.ndarray:
        at, ends, head, word = f
        if not len(word):
            return np.zeros((0, len(self.labels)), np.float32)
        each = self.grams[at[:, 0]] + self.grams[at[:, 1]]
        return np.add.reduceat(each, head, axis=0) + self.grams[ends[:, 0]] + self.grams[ends[:, 1]] + self.words[word]


def limit(labels: int) -> int:
    """Characters handled at once: those of words hold a number for each label, blocks of words one for each two labels."""
    return max(TEXT_CHARS, min(BATCH_CHARS, 4 * BATCH_CHARS // labels, 512 * BATCH_CHARS // labels**2))


def marginals(emit: np.ndarray, moves: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of each word the label marginals, and of all neighbours in a text the summed pair marginals."""
    return passed(emit, moves, first)[:2]


def passed(emit: np.ndarray, moves: np.ndarray, first: np.ndarray, before: np.ndarray | None = None, after: np.ndarray | None = None) -> tuple[np.ndarray, ...]:
    """The same for texts or a piece of one text: before and after are messages from the words around it. Also the messages
    that the last piece sends on and the first one sends back."""
    n, k = emit.shape
    if not n:
        return emit, np.zeros((k, k), np.float32), before, after
    lengths = np.diff(first)
    blocks = -(-lengths // BLOCK)
    total = int(blocks.sum())
    opens = np.concatenate([[0], np.cumsum(blocks)[:-1]])
    text = np.repeat(np.arange(len(lengths)), blocks)
    local = np.arange(total) - opens[text]
    begin = first[:-1][text] + local * BLOCK
    size = np.minimum(BLOCK, first[1:][text] - begin)
    place = begin[:, None] + np.arange(BLOCK)
    valid = np.arange(BLOCK) < size[:, None]
    e = np.exp(emit - emit.max(1, keepdims=True)).astype(np.float32)
    e = np.where(valid[..., None], e[np.minimum(place, n - 1)], 1).astype(np.float32)
    a = np.exp(moves - moves.max()).astype(np.float32)
    # a block's transfer: from the label before it to the label at its end; the first word of a text has no move into it
    opening = local == 0 if before is None else np.zeros(total, bool)
    m = a[None] * e[:, 0, None, :]
    m[opening] = e[opening, 0][:, None, :] / k
    for t in range(1, BLOCK):
        on = valid[:, t]
        if not on.any():
            break
        step = (m @ a) * e[:, t, None, :]
        step /= step.max((1, 2), keepdims=True)
        m = np.where(on[:, None, None], step, m)
    into, out = np.full((total, k), 1 / k, np.float32), np.ones((total, k), np.float32)
    if before is not None:
        into[0] = before
    if after is not None:
        out[-1] = after
    order = np.argsort(-blocks, kind="stable")
    sizes, heads = blocks[order], opens[order]
    for b in range(1, int(blocks.max(initial=0))):
        at = heads[: np.searchsorted(-sizes, -b, "left")] + b
        v = np.einsum("bi,bij->bj", into[at - 1], m[at - 1])
        into[at] = v / v.sum(1, keepdims=True)
    for b in range(int(blocks.max(initial=0)) - 2, -1, -1):
        at = heads[: np.searchsorted(-sizes, -(b + 1), "left")] + b
        v = np.einsum("bij,bj->bi", m[at + 1], out[at + 1])
        out[at] = v / v.sum(1, keepdims=True)
    ahead = np.empty((total, BLOCK, k), np.float32)
    v = np.where(opening[:, None], e[:, 0], (into @ a) * e[:, 0])
    ahead[:, 0] = v / v.sum(1, keepdims=True)
    for t in range(1, BLOCK):
        v = (ahead[:, t - 1] @ a) * e[:, t]
        ahead[:, t] = np.where(valid[:, t, None], v / v.sum(1, keepdims=True), ahead[:, t - 1])
    behind, v = np.empty_like(ahead), out
    pairs = np.zeros((k, k), np.float64)
    for t in range(BLOCK - 1, -1, -1):
        behind[:, t] = v
        back = (e[:, t] * v) @ a.T
        back /= back.sum(1, keepdims=True)
        v = np.where(valid[:, t, None], back, v)
        if t:
            x = ahead[:, t - 1, :, None] * a * (e[:, t] * behind[:, t])[:, None, :]
            pairs += (x / x.sum((1, 2), keepdims=True))[valid[:, t]].sum(0)
    later = ~opening
    x = into[later][:, :, None] * a * (e[later, 0] * behind[later, 0])[:, None, :]
    pairs += (x / x.sum((1, 2), keepdims=True)).sum(0)
    p = ahead * behind
    return (p / p.sum(2, keepdims=True))[valid], pairs, ahead[-1, size[-1] - 1], v[0]


def fit(rows: list[tuple[str, str]], passes: int = PASSES) -> Model | None:
    """rows: texts and labels. Gradient ascent on the likelihood, with steps that shrink for each weight (AdaGrad)."""
    rows = sorted({(t, y) for t, y in rows if t}, key=lambda r: (hash_of(r[0]), r[1]))
    labels = sorted({y for _, y in rows})
    if not labels:
        return None
    k, folds = len(labels), 0
    while (GRAMS + WORDS >> folds) * k > WEIGHTS and GRAMS >> folds > 256:
        folds += 1
    size_g, size_w = GRAMS >> folds, WORDS >> folds
    model = Model(labels, np.zeros((size_g, k), np.float32), np.zeros((size_w, k), np.float32), np.zeros((k, k), np.float32))
    seen = np.zeros((k, size_w), np.int32)
    batches = []
    # a text is learned from in pieces, as if each were a text
    rows = [(piece, y) for t, y in rows for piece in pieces(t, max(TEXT_CHARS, limit(k) // 8))]
    for part in chunks([t for t, _ in rows], limit(k) // 8):
        words = Words.of([rows[i][0] for i in part])
        f = model.features(words)
        y = np.repeat([labels.index(rows[i][1]) for i in part], np.diff(words.first))
        for label in range(k):
            seen[label] += np.bincount(f[3][y == label], minlength=size_w)
        batches.append((words.first, f, y))
    lexicon = np.zeros(size_w, bool)
    for label in range(k):
        top = np.argsort(-seen[label], kind="stable")[:LEXICON]
        lexicon[top[seen[label][top] >= 3]] = True
    squares = [np.full(x.shape, 1e-6) for x in (model.grams, model.words, model.moves)]
    for _ in range(passes):
        for first, f, y in batches:
            if not len(y):
                continue
            at, ends, head, word = f
            p, pairs = marginals(model.emissions(f), model.moves, first)
            error = np.eye(k, dtype=np.float32)[y] - p
            spread = np.repeat(error, np.diff(np.append(head, len(at))), axis=0)
            add = lambda rows, v, size: np.stack([np.bincount(rows, v[:, j], size) for j in range(k)], 1)
            grams = add(at[:, 0], spread, size_g) + add(at[:, 1], spread, size_g) + add(ends[:, 0], error, size_g) + add(ends[:, 1], error, size_g)
            joined = np.ones(max(len(y) - 1, 0), bool)
            joined[first[(first > 0) & (first < len(y))] - 1] = False
            truth = np.bincount((y[:-1] * k + y[1:])[joined], minlength=k * k).reshape(k, k)
            for x, square, g in zip((model.grams, model.words, model.moves), squares, (grams / len(y), add(word, error, size_w) * lexicon[:, None] / len(y), (truth - pairs) / len(y) - 1e-3 * model.moves), strict=True):
                square += g * g
                x += (RATE * g / np.sqrt(square)).astype(np.float32)
    return model


def hash_of(text: str) -> int:
    import zlib

    return zlib.crc32(text.encode())


def chunks(texts: list[str], most: int):
    """Runs of places whose texts have at most so many characters together, or one text."""
    part, size = [], 0
    for i, t in enumerate(texts):
        n = max(len(t), TEXT_CHARS)
        if part and size + n > most:
            yield part
            part, size = [], 0
        part.append(i)
        size += n
    if part:
        yield part


def pieces(text: str, most: int):
    """A text cut between words, into pieces of about so many characters (one more word at most)."""
    at = 0
    while len(text) - at > most:
        cut = at + most
        if text[cut - 1].isalpha() and text[cut].isalpha():
            run = cut - 1
            while run > at and text[run - 1].isalpha():
                run -= 1
            while cut < len(text) and text[cut].isalpha() and (cut - run) % LONGEST:
                cut += 1
        yield text[at:cut]
        at = cut
    yield text[at:]


def long_text(model: Model, text: str, most: int):
    """The words of each piece of a text and their marginals, from the last piece to the first."""
    held, before = [], None
    for piece in pieces(text, most):
        words = Words.of([piece])
        if len(words.start):
            held.append((piece, before))
            before = passed(model.emissions(model.features(words)), model.moves, words.first, before)[2]
    after = None
    for piece, before in reversed(held):
        words = Words.of([piece])
        p, _, _, after = passed(model.emissions(model.features(words)), model.moves, words.first, before, after)
        yield piece, words, p


def predicted(model: Model | None, texts: list[str]) -> list[tuple[str, float]]:
    if model is None:
        return [(NONE, 0.0)] * len(texts)
    out, most, k = [], limit(len(model.labels)), len(model.labels)
    for part in chunks(texts, most):
        if len(part) == 1 and len(texts[part[0]]) > most:
            sums, n = np.zeros((1, k)), np.zeros(1, np.int64)
            for _, words, p in long_text(model, texts[part[0]], most):
                sums[0] += p.sum(0, dtype=np.float64)
                n[0] += len(words.start)
        else:
            words = Words.of([texts[i] for i in part])
            p, _ = marginals(model.emissions(model.features(words)), model.moves, words.first)
            upto = np.concatenate([np.zeros((1, k)), np.cumsum(p, axis=0, dtype=np.float64)])
            sums, n = upto[words.first[1:]] - upto[words.first[:-1]], np.diff(words.first)
        mean = sums / np.maximum(n, 1)[:, None]
        best = mean.argmax(1)
        out += [(model.labels[b], float(min(max(m[b], 0.0), 1.0))) if c else (NONE, 0.0) for b, m, c in zip(best, mean, n, strict=True)]
    return out


def word_labels(model: Model, text: str) -> list[tuple[str, str, float]]:
    """The words of a text with their labels and marginals."""
    out = []
    for piece, words, p in long_text(model, text, limit(len(model.labels))):
        out.append([(piece[s - 1 : e - 1], model.labels[x.argmax()], float(x.max())) for s, e, x in zip(words.start, words.end, p, strict=True)])
    return [x for part in reversed(out) for x in part]


def learn(docs: DataFrame, sample: int = SAMPLE, sample_chars: int = SAMPLE_CHARS) -> Model | None:
    """docs: doc_id, text and lang of rows to learn from only."""
    keys = docs.where("doc_id is not null and lang is not null").select("doc_id", "lang")
    counts = keys.groupBy("lang").agg(F.count("*").alias("_n"))
    counts = common.written(counts, "language-labels")
    labels = counts.count()
    if not labels:
        return None
    # a hash below a bound keeps about four times the sample of each label, and no task sorts more
    spread = F.pmod(F.xxhash64("doc_id"), F.lit(1 << 31))
    keys = keys.join(F.broadcast(counts) if labels <= 100_000 else counts, "lang").where(spread / (1 << 31) * F.col("_n") <= 4 * sample)
    order = Window.partitionBy("lang").orderBy(spread, "doc_id")
    chosen = keys.withColumn("_place", F.row_number().over(order)).where(F.col("_place") <= sample).select("doc_id", "lang").distinct()
    rows = docs.where("lang is not null").select("doc_id", "lang", common.text_of().alias("text")).join(F.broadcast(chosen), ["doc_id", "lang"])
    rows = common.written(rows.withColumn("_size", F.char_length("text")), "language-sample")
    share = max(1, sample_chars // labels)
    fits = Window.partitionBy("lang").orderBy(F.col("_size") > share, spread, "doc_id", F.xxhash64("text"))
    upto = F.sum("_size").over(fits.rowsBetween(Window.unboundedPreceding, 0))
    rows = rows.withColumn("_upto", upto).withColumn("_place", F.row_number().over(fits)).where((F.col("_upto") <= share) | (F.col("_place") == 1))
    return fit([(r.text, r.lang) for r in rows.select("text", "lang").toLocalIterator()])


def label_texts(docs: DataFrame, model: Model | None) -> DataFrame:
    """doc_id, lang_pred and score of each row."""
    common.importable(docs.sparkSession)
    kind, schema = common.arrow_schema("doc_id long, lang_pred string, score double")
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 1024):
                part = batch.slice(at, 1024)
                found = predicted(shared.value, part.column(1).to_pylist())
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([x for x, _ in found], pa.string()), pa.array([x for _, x in found], pa.float64())], schema=schema)

    return docs.select("doc_id", common.text_of().alias("text")).mapInArrow(run, kind)


def op7_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The language of every document, learned from those of remainder other than 2."""
    docs = common.documents(spark, sf_dir)
    fold = F.crc32(F.col("doc_id").cast("string")) % 4
    return label_texts(docs, learn(docs.where(fold != 2))).select("doc_id", F.coalesce(fold == 2, F.lit(False)).alias("held_out"), "lang_pred", "score")


QUERIES = {"op7_language": op7_language}
ORACLES: dict[str, str] = {}
