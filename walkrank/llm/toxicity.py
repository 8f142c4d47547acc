"""Toxicity as a weighted lexicon, matched by Aho-Corasick in folded text.

Folding maps letters with marks, full-width letters and look-alikes of other scripts to plain lower-case letters, one
character for one. A second folding also replaces digits and signs that stand for letters; both are searched, as a
sign may also just follow a word. A term counts where it is a whole word, or the start of one if it ends in a star; of
terms that start at one place the heaviest counts. A term inside an exception phrase doesn't count. The total weight,
normalised by length in two ways, goes through a logistic curve.

Lexicon, exceptions and curve are learned from a bounded sample of labelled rows: `sample` rows of each class (all where
there are fewer), the same for the same rows, chosen by a hash of doc_id. Words and starts of words are terms if toxic
texts have them at a higher rate, by SIGNIFICANT standard errors of the log odds; their weight is that log odds ratio.
Exceptions are pairs of neighbouring words, one a term, that several clean texts have and toxic texts have less often.
Everything else covers all rows.

Null and empty texts have no terms and get the curve's value at zero. Null labels teach nothing; of several labels of a
document the highest holds. Texts that repeat in the sample count once. Without rows of both classes nothing is
learned and all scores are 0. Rows with a null doc_id are scored, as not held out. Other columns are left out; empty
tables give empty tables.
"""

from __future__ import annotations

import math
import re
import unicodedata
from bisect import bisect_right
from collections import Counter
from dataclasses import dataclass, field
from functools import lru_cache
from itertools import accumulate

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

#: Labelled rows of each class that the lexicon is learned from.
SAMPLE = 3000
#: A term is in so many toxic texts at least, an exception in so many clean ones; a text counts so many times for a term at most.
LEAST_TEXTS, TIMES = 3, 2
#: Least log odds ratio of a term, and how many of its standard errors that is.
LEAST_WEIGHT, SIGNIFICANT = 1.0, 3.5
#: Letters of the word starts that may be terms.
STEMS = (4, 5, 6)
THRESHOLD = 0.7

# Look-alikes of Latin letters, and digits and signs that stand for letters.
LOOKALIKES = {"а": "a", "в": "b", "с": "c", "ԁ": "d", "е": "e", "һ": "h", "і": "i", "ј": "j", "к": "k", "ӏ": "l", "м": "m", "о": "o", "р": "p", "ԛ": "q", "ѕ": "s", "т": "t", "ѵ": "v", "ԝ": "w", "х": "x", "у": "y", "α": "a", "β": "b", "ε": "e", "ι": "i", "κ": "k", "ν": "v", "ο": "o", "ρ": "p", "τ": "t", "υ": "u", "χ": "x", "ɑ": "a", "ı": "i", "ł": "l", "ø": "o", "ß": "b"}
SUBSTITUTES = {"0": "o", "1": "i", "3": "e", "4": "a", "5": "s", "7": "t", "8": "b", "9": "g", "@": "a", "$": "s", "!": "i", "|": "l", "+": "t", "€": "e"}
WORD = re.compile(r"\w+")


@lru_cache(1)
def folding() -> tuple[dict[int, str], dict[int, str]]:
    plain = {}
    for c in [*range(0x41, 0x5B), *range(0xC0, 0x250), *range(0x1E00, 0x1F00), *range(0xFF21, 0xFF3B), *range(0xFF41, 0xFF5B)]:
        base = unicodedata.normalize("NFKD", chr(c))[0].lower()
        if base.isascii() and base.isalpha():
            plain[c] = base
    for a, b in LOOKALIKES.items():
        plain[ord(a)] = plain[ord(a.upper()) if len(a.upper()) == 1 else ord(a)] = b
    return plain, plain | {ord(a): b for a, b in SUBSTITUTES.items()}


SIGNS = re.escape("".join(SUBSTITUTES))
STANDS_IN = re.compile(f"[{SIGNS}]")
#: the same inside a word only: a word character follows, or more of them do and then one
INSIDE = re.compile(rf"[0-9]|[{SIGNS}](?=[{SIGNS}]{{0,8}}\w)")


def folded(text: str) -> list[str]:
    """Text in one to three foldings, all as long as the text."""
    plain, full = folding()
    out = [text.translate(plain)]
    if STANDS_IN.search(text):
        inner = INSIDE.sub(lambda m: SUBSTITUTES.get(m[0], m[0]), text).translate(plain)
        out += [x for x in dict.fromkeys((inner, text.translate(full))) if x != out[0]]
    return out


@dataclass
class Lexicon:
    weights: dict[str, float]
    exceptions: tuple[str, ...] = ()
    curve: tuple[float, float, float] = (0.0, 0.0, 0.0)
    learned: bool = True
    _machine: object = field(default=None, repr=False)

    def machine(self):
        import ahocorasick

        if self._machine is None:
            found = ahocorasick.Automaton()
            terms: dict[str, list] = {}
            for term, w in self.weights.items():
                text = term.removesuffix("*")
                terms.setdefault(text, []).append((len(text), w, text != term))
            for phrase in self.exceptions:
                text = phrase.translate(folding()[0])
                terms.setdefault(text, []).append((len(text), None, False))
            for text, kinds in terms.items():
                found.add_word(text, kinds)
            found.make_automaton()
            self._machine = found
        return self._machine

    def __getstate__(self):
        return self.__dict__ | {"_machine": None}

    def spans(self, text: str) -> list[tuple[int, int, float]]:
        """Start, end and weight of the terms that count, in order."""
        if not self.weights or not text:
            return []
        found: dict[int, tuple[int, float]] = {}
        for view in folded(text):
            terms, excused = [], []
            for last, kinds in self.machine().iter(view):
                for n, w, stem in kinds:
                    start, end = last + 1 - n, last + 1
                    inside = end < len(view) and view[end].isalnum()
                    if (start and view[start - 1].isalnum()) or inside != stem:
                        continue
                    if w is None:
                        excused.append((start, end, 0))
                    else:
                        terms.append((start, end, w))
            excused.sort()
            reach = list(accumulate((b for _, b, _ in excused), max))
            for start, end, w in terms:
                k = bisect_right(excused, start, key=lambda x: x[0])
                if w > found.get(start, (0, 0.0))[1] and not (k and reach[k - 1] >= end):
                    found[start] = end, w
        return sorted((a, b, w) for a, (b, w) in found.items())

    def features(self, text: str) -> tuple[float, float]:
        total = sum(w for _, _, w in self.spans(text))
        if not total:
            return 0.0, 0.0
        words = text.count(" ") + text.count("\n") + 1
        return math.log1p(total), math.log1p(1000 * total / (words + 20))

    def score(self, text: str) -> float:
        if not self.learned:
            return 0.0
        x, y = self.features(text)
        a, b, c = self.curve
        return 1 / (1 + math.exp(-max(-30.0, min(30.0, a * x + b * y + c))))


def fitted_curve(rows: list[tuple[float, float, int]]) -> tuple[float, float, float]:
    """Logistic regression with a small penalty, by Newton steps."""
    at = np.array([[x, y, 1.0] for x, y, _ in rows])
    truth, w = np.array([t for *_, t in rows], float), np.zeros(3)
    penalty = np.diag([0.05, 0.05, 0.001])
    for _ in range(40):
        p = 1 / (1 + np.exp(-np.clip(at @ w, -30, 30)))
        step = np.linalg.solve((at * (p * (1 - p))[:, None]).T @ at + penalty, at.T @ (truth - p) - penalty @ w)
        w += step
        if np.abs(step).max() < 1e-8:
            break
    return tuple(float(x) for x in w)


def counted_terms(text: str) -> dict[str, int]:
    """Words and starts of words of a text, with how often they come, TIMES at most. All words together under ''."""
    words: dict[str, int] = {}
    for view in folded(text):
        for w, n in Counter(WORD.findall(view)).items():
            if len(w) > 2 and not w.isdigit():
                words[w] = max(n, words.get(w, 0))
    out = Counter({w: min(n, TIMES) for w, n in words.items()})
    total = out.total()
    for w, n in words.items():
        for k in STEMS:
            if len(w) > k:
                out[w[:k] + "*"] += n
    return {w: min(n, TIMES) for w, n in out.items()} | {"": total}


def phrases(lexicon: Lexicon, text: str) -> set[str]:
    """Pairs of neighbouring words, in plain folding, that a term is in. Words are a space apart."""
    out, plain = set(), text.translate(folding()[0])
    words = [(m.start(), m.end()) for m in WORD.finditer(plain)]
    starts = [a for a, _ in words]
    for start, _, _ in lexicon.spans(text):
        k = bisect_right(starts, start) - 1
        for i in (k - 1, k):
            if k >= 0 and i >= 0 and i + 1 < len(words) and plain[words[i][1] : words[i + 1][0]] == " ":
                out.add(plain[words[i][0] : words[i + 1][1]])
    return out


def learn(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, exceptions: tuple[str, ...] = ()) -> Lexicon:
    """docs (doc_id, text) and labels (doc_id, toxic), of rows to learn from only. exceptions: phrases besides those learned."""
    known = labels.where("doc_id is not null and toxic in (0, 1)").groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    pick = lambda t: known.where(F.col("toxic") == t).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample)
    chosen = pick(1).unionByName(pick(0))
    rows = docs.select("doc_id", common.text_of().alias("text")).join(F.broadcast(chosen), "doc_id").select("text", "toxic")
    texts = common.written(rows.groupBy("text").agg(F.max("toxic").alias("toxic")), "toxicity-sample")
    sizes = {r.toxic: r.n for r in texts.groupBy("toxic").agg(F.count("*").alias("n")).collect()}
    bad, good = sizes.get(1, 0), sizes.get(0, 0)
    if not bad or not good:
        return Lexicon({}, exceptions, learned=False)

    def terms():
        def many(text, toxic):
            for w, n in counted_terms(text).items():
                yield w, toxic, n

        return many

    when = lambda t, x: F.sum(F.when(F.col("toxic") == t, x).otherwise(0))
    counts = common.flat_map_rows(texts, terms, "word string, toxic int, n long").groupBy("word").agg(when(1, F.col("n")).alias("a"), when(0, F.col("n")).alias("b"), when(1, 1).alias("texts"))
    counts = common.written(counts.where((F.col("texts") >= LEAST_TEXTS) | (F.col("word") == "")), "toxicity-terms")
    total = counts.where("word = ''").first()
    odds = lambda x, n: F.log((F.col(x) + 0.5) / (n - F.col(x) + 0.5))
    weight = odds("a", total.a + 1) - odds("b", total.b + 1)
    error = F.sqrt(1 / (F.col("a") + 0.5) + 1 / (F.col("b") + 0.5))
    found = counts.where("word <> ''").withColumn("w", F.round(weight, 6)).where((F.col("w") >= LEAST_WEIGHT) & (weight >= SIGNIFICANT * error)).collect()
    lexicon = Lexicon({r.word: r.w for r in sorted(found, key=lambda r: r.word)}, exceptions)
    if lexicon.weights:

        def around():
            return lambda text, toxic: ((p, toxic) for p in phrases(lexicon, text))

        share = lambda x, n: (F.col(x) + 0.5) / (n + 1)
        pairs = common.flat_map_rows(texts, around, "phrase string, toxic int").groupBy("phrase").agg(when(1, 1).alias("a"), when(0, 1).alias("b"))
        harmless = pairs.where((F.col("b") >= LEAST_TEXTS) & (share("a", bad) < share("b", good))).select("phrase").collect()
        lexicon = Lexicon(lexicon.weights, tuple(dict.fromkeys([*exceptions, *sorted(r.phrase for r in harmless)])))
    seen = common.map_rows(texts, lambda: lambda text, toxic: (*lexicon.features(text), toxic), "x double, y double, toxic int")
    lexicon.curve = fitted_curve(sorted((r.x, r.y, r.toxic) for r in seen.collect()))
    return lexicon


FIELDS = {"score": "double", "predicted": "int", "terms": "array<struct<start:int,end:int,weight:double>>"}


def score_texts(docs: DataFrame, lexicon: Lexicon, outputs: tuple[str, ...] = ("score", "predicted"), threshold: float = THRESHOLD) -> DataFrame:
    """doc_id and, of FIELDS, the outputs asked for."""

    def setup():
        def one(key, text):
            score = lexicon.score(text)
            out = {"score": score, "predicted": int(score >= threshold)}
            if "terms" in outputs:
                out["terms"] = [{"start": a, "end": b, "weight": w} for a, b, w in lexicon.spans(text)]
            return key, *(out[k] for k in outputs)

        return one

    return common.map_rows(docs.select("doc_id", common.text_of().alias("text")), setup, "doc_id long, " + ", ".join(f"{k} {FIELDS[k]}" for k in outputs))


def accepted(docs: DataFrame, lexicon: Lexicon, threshold: float = THRESHOLD) -> DataFrame:
    """The rows of docs, whole, that score less than the threshold. Nothing is shuffled."""
    common.importable(docs.sparkSession)

    @F.pandas_udf("double")
    def score(texts: pd.Series) -> pd.Series:
        return texts.map(lexicon.score).astype("float64")

    return docs.where(score(common.text_of()) < threshold)


def fold_of(modulus: int) -> Column:
    return F.crc32(F.col("doc_id").cast("string")) % modulus


def learned(docs: DataFrame, labels: DataFrame) -> Lexicon:
    """From the rows whose remainder by 3 is not 1."""
    return learn(docs, labels.where(fold_of(3) != 1).select("doc_id", "toxic"))


def op6_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document scored, with the rows of remainder 1 held out of the learning."""
    docs = common.documents(spark, sf_dir)
    lexicon = learned(docs, common.documents(spark, sf_dir, "labels"))
    return score_texts(docs, lexicon).select("doc_id", F.coalesce(fold_of(3) == 1, F.lit(False)).alias("held_out"), "score", "predicted")


QUERIES = {"op6_toxicity": op6_toxicity}
ORACLES: dict[str, str] = {}
