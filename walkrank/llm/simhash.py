"""Near-duplicates by SimHash, searched exactly with vantage-point trees.

Fingerprints of 64 bits link at `most` (3) or fewer differing bits. Of two such fingerprints one half differs in at
most 1 bit. So there is a tree for each half, over the Hamming distance in that half, with query radius 1; a pair that
it meets is then tested on all bits.

A tree's inner node has a vantage point and a radius; a fingerprint is at home on its side of the radius. By the
triangle inequality a partner differs in distance from the vantage point by at most the query radius: so a fingerprint
near the boundary on the inner side also visits the outer side, and visitors go wherever that bound lets a partner be.
Each pair so meets in the leaf where one of them is at home.

The upper levels are fitted to a bounded sample of fingerprints (SAMPLE, those of least hash) and deal all of them. A
leaf where more than half of FULL times LEAF rows are at home is dealt again, in chunks, by a tree fitted to a sample of
its own, until none is; where visitors are too many they meet those at home chunk by chunk. So no task gets an unbounded
leaf, however many there are. Inside a leaf the tree goes on with the
leaf's own rows until BRUTE are left. Where all points of a node agree in the half, it is split by all bits, with the
full radius. A leaf puts out a spanning forest of its links, so a dense group costs no square of rows. Visitors are the
price of the method: about 1.2 copies of a row for each doubling of the leaves.

Equal fingerprints are one before the search, whatever number of documents has them.

A null text is an empty one and has fingerprint zero, as any text without words; these link like any others. Repeated
rows are documents alike. A null doc_id takes part without being a component's id (null if no other has one). Other
columns are left out, and an empty table gives an empty table.
"""

from __future__ import annotations

import pickle
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common
from .components import components

WORDS, SEED, MOST = 3, 42, 3
SAMPLE, LEAF, BRUTE = 8192, 4096, 512
#: A leaf of more than FULL * leaf rows is dealt again, by chunks of so many rows, or its visitors by chunks of its own. Paths of leaves are numbers, so there is a deepest.
FULL, CHUNK, DEEPEST = 16, 1 << 17, 60
HALVES = (0xFFFFFFFF, 0xFFFFFFFF << 32)
#: Shingles hashed at once, and pairs tested at once.
BLOCK, PAIRS = 1 << 16, 1 << 21


def shingle_hashes(text: str, words: int = WORDS, seed: int = SEED):
    """Arrays of the hashes of a text's shingles."""
    from xxhash import xxh64_intdigest

    split = text.encode().lower().split()
    if not split:
        return
    line = b" ".join(split)
    ends = np.cumsum([len(w) + 1 for w in split])
    starts, ends = [0, *ends[:-1].tolist()], (ends - 1).tolist()
    k = min(words, len(split))
    for at in range(0, len(split) - k + 1, BLOCK):
        yield np.array([xxh64_intdigest(line[a:b], seed) for a, b in zip(starts[at : at + BLOCK], ends[at + k - 1 : at + k - 1 + BLOCK], strict=False)], np.uint64)


def fingerprint(text: str, words: int = WORDS, seed: int = SEED) -> int:
    ones, n = np.zeros(64, np.int64), 0
    for h in shingle_hashes(text, words, seed):
        ones += np.unpackbits(h.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
        n += len(h)
    return int(np.packbits(2 * ones > n, bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, words: int = WORDS, seed: int = SEED) -> DataFrame:
    """doc_id and the fingerprint as a signed long."""

    def setup():
        def one(key, text):
            x = fingerprint(text, words, seed)
            return key, x - (1 << 64) if x >> 63 else x

        return one

    return common.map_rows(docs.select("doc_id", common.text_of().alias("text")), setup, "doc_id long, fp long")


def apart(a: np.ndarray, b) -> np.ndarray:
    return np.bitwise_count(a ^ b).astype(np.int16)


@dataclass
class Split:
    """Vantage point and radius of an inner node; the metric counts the bits of mask, in which partners differ by `reach` at most."""

    point: int
    radius: int
    mask: int
    reach: int

    @staticmethod
    def of(points: np.ndarray, metrics: list[tuple[int, int]]) -> Split | None:
        """By the first metric (mask and reach) that parts the points the best of some vantage points: near halves, few at
        the boundary. None if all are far from halves in every metric."""
        for mask, reach in metrics:
            best = None
            for k in range(0, len(points), max(1, len(points) // 6)):
                d = apart(points & np.uint64(mask), points[k] & np.uint64(mask))
                counts = np.bincount(d, minlength=2)
                inner = np.cumsum(counts)
                for radius in {int(np.searchsorted(inner, len(points) / 2)), int(np.searchsorted(inner, len(points) / 2)) - 1}:
                    if radius < 0:
                        continue
                    larger = max(inner[radius], len(points) - inner[radius]) / len(points)
                    cost = larger + counts[radius] / len(points)
                    if larger < 0.95 and (best is None or cost < best[0]):
                        best = cost, Split(int(points[k]), radius, mask, reach)
            if best:
                return best[1]
        return None

    def inside(self, points: np.ndarray) -> np.ndarray:
        return apart(points & np.uint64(self.mask), np.uint64(self.point & self.mask)) <= self.radius

    def sides(self, points: np.ndarray, home: np.ndarray) -> tuple[tuple[np.ndarray, np.ndarray], ...]:
        """For the inner and the outer side: which points go there, and which of those are at home."""
        d = apart(points & np.uint64(self.mask), np.uint64(self.point & self.mask))
        inner, outer = d <= self.radius, d > self.radius
        to_inner = np.where(home, inner, d - self.reach <= self.radius)
        return (to_inner, home & inner), (d + self.reach > self.radius, home & outer)


def metrics_of(tree: int, most: int) -> list[tuple[int, int]]:
    """How a tree's nodes are split: by its half, or by all bits where that doesn't part them."""
    return [(HALVES[tree], most // 2), ((1 << 64) - 1, most)]


def grown(points: np.ndarray, metrics: list[tuple[int, int]], depth: int) -> list:
    """The upper levels of a tree: nested [split, inner, outer]; an empty list is a leaf."""
    split = Split.of(points, metrics) if depth and len(points) > 8 else None
    if not split:
        return []
    inner = split.inside(points)
    return [split, grown(points[inner], metrics, depth - 1), grown(points[~inner], metrics, depth - 1)]


def dealt(tree: list, points: np.ndarray, home: np.ndarray, leaf: int = 1):
    """Leaves with the points that go there and whether they are at home."""
    if not len(points):
        return
    if not tree:
        yield leaf, points, home
        return
    for k, (goes, stays) in enumerate(tree[0].sides(points, home)):
        yield from dealt(tree[1 + k], points[goes], stays[goes], 2 * leaf + k)


class Forest:
    """Union-find on arrays."""

    def __init__(self, n: int):
        self.up = np.arange(n)

    def root(self, x: np.ndarray) -> np.ndarray:
        r = self.up[x]
        while (self.up[r] != r).any():
            r = self.up[r]
        self.up[x] = r
        return r

    def unite(self, a: np.ndarray, b: np.ndarray) -> None:
        while len(a):
            a, b = self.root(a), self.root(b)
            differ = a != b
            a, b = a[differ], b[differ]
            np.minimum.at(self.up, np.maximum(a, b), np.minimum(a, b))


def search(points: np.ndarray, home: np.ndarray, metrics: list[tuple[int, int]], most: int, forest: Forest, names: np.ndarray) -> None:
    """Unites all pairs of at most `most` bits that have one at home."""
    n = int(home.sum())
    if not n:
        return
    split = Split.of(points[home], metrics) if n > BRUTE else None
    if split:
        for goes, stays in split.sides(points, home):
            search(points[goes], stays[goes], metrics, most, forest, names[goes])
        return
    order = np.argsort(~home, kind="stable")
    points, names = points[order], names[order]
    rows = max(1, PAIRS // len(points))
    for at in range(0, n, rows):
        i, j = np.nonzero(apart(points[at : min(at + rows, n), None], points[None, at:]) <= most)
        forest.unite(names[i + at], names[j + at])


DEALT = "tree int, leaf long, home boolean, fp long"


def dealt_table(tree: int, nodes: list, points: np.ndarray, home: np.ndarray, leaf: int = 1) -> pa.Table:
    parts = list(dealt(nodes, points, home, leaf))
    sizes = [len(p) for _, p, _ in parts]
    join = lambda k, kind: np.concatenate([x[k] for x in parts]) if parts else np.zeros(0, kind)
    leaves = np.repeat(np.array([k for k, _, _ in parts], np.int64), sizes)
    return pa.table({"tree": pa.array(np.full(len(leaves), tree, np.int32)), "leaf": pa.array(leaves), "home": pa.array(join(2, bool)), "fp": pa.array(join(1, np.uint64).view(np.int64))})


def levels_for(n: int, leaf: int) -> int:
    return max(0, int(np.ceil(np.log2(max(n, 1) / leaf))))


def leaves(reps: DataFrame, most: int, leaf: int, sample: int) -> list[DataFrame]:
    """The rows of all leaves: tree, leaf, chunk, home, fp, by rounds of dealing."""
    depth = levels_for(reps.count(), leaf)
    seen = np.array(sorted(r.fp for r in reps.orderBy(F.xxhash64("fp"), "fp").limit(sample).collect()) if depth else [], np.int64).view(np.uint64)
    trees = [grown(seen, metrics_of(t, most), depth) for t in range(2)]
    kind, _ = common.arrow_schema(DEALT)

    def deal(batches):
        for batch in batches:
            fps = batch.column(0).to_numpy(zero_copy_only=False).view(np.uint64)
            for t, tree in enumerate(trees):
                yield from dealt_table(t, tree, fps, np.ones(len(fps), bool)).to_batches()

    rows, out, stuck = common.written(reps.select("fp").mapInArrow(deal, kind), "simhash-dealt"), [], None
    while True:
        sizes = rows.groupBy("tree", "leaf").agg(F.count("*").alias("n"), F.count_if("home").alias("at_home")).where(F.col("n") > FULL * leaf)
        sizes = common.written(sizes, "simhash-sizes")
        if sizes.isEmpty():
            return [*out, rows.withColumn("chunk", F.lit(0).cast("long"))]
        large = sizes.where((F.col("at_home") > FULL // 2 * leaf) & (F.col("leaf") < F.lit(1 << DEEPEST)))
        if stuck is not None:  # leaves that a tree of their own left whole
            large = large.join(stuck, ["tree", "leaf"], "left_anti")
        crowded = sizes.join(large, ["tree", "leaf"], "left_anti").select("tree", "leaf", F.ceil(F.col("n") / (FULL * leaf)).cast("long").alias("chunks"))
        out.append(chunked(rows.join(large, ["tree", "leaf"], "left_anti"), crowded))
        if large.isEmpty():
            return out
        rows, stuck = common.written(dealt_again(rows, large, most, leaf, sample), "simhash-dealt"), large.select("tree", "leaf")


def chunked(rows: DataFrame, crowded: DataFrame) -> DataFrame:
    """Rows with a chunk: visitors of crowded leaves (tree, leaf, chunks) are dealt to chunks, those at home go to each."""
    rows = rows.join(crowded, ["tree", "leaf"], "left").withColumn("chunks", F.coalesce("chunks", F.lit(1).cast("long")))
    one = F.array(F.pmod(F.xxhash64("fp", F.lit(11)), F.col("chunks")))
    return rows.select("tree", "leaf", "home", "fp", F.explode(F.when(F.col("home"), F.sequence(F.lit(0).cast("long"), F.col("chunks") - 1)).otherwise(one)).alias("chunk"))


def dealt_again(rows: DataFrame, large: DataFrame, most: int, leaf: int, sample: int) -> DataFrame:
    """The rows of large leaves (tree, leaf, n, at_home), dealt by a tree for each that is fitted to a sample of its rows."""
    held = rows.join(large, ["tree", "leaf"])
    some = held.where("home").where(F.pmod(F.xxhash64("fp"), F.lit(1 << 31)) * F.col("at_home") <= F.lit(float(sample)) * (1 << 31))

    kind, schema = common.arrow_schema("tree int, leaf long, nodes binary")

    def grow(key, table):
        points = np.sort(table.column("fp").to_numpy()).view(np.uint64)
        nodes = grown(points, metrics_of(key[0].as_py(), most), levels_for(table.column("at_home")[0].as_py(), leaf))
        return pa.table({"tree": [key[0].as_py()], "leaf": [key[1].as_py()], "nodes": [pickle.dumps(nodes)]}, schema=schema)

    grown_ = common.written(some.groupBy("tree", "leaf").applyInArrow(grow, kind), "simhash-trees")
    chunks = F.ceil(F.col("n") / CHUNK).cast("long")
    held = held.withColumn("chunk", F.pmod(F.xxhash64("fp", F.lit(7)), chunks))
    copies = grown_.join(large, ["tree", "leaf"]).select("tree", "leaf", "nodes", F.explode(F.sequence(F.lit(0).cast("long"), chunks - 1)).alias("chunk"))

    def deal(key, left, right):
        nodes = pickle.loads(right.column("nodes")[0].as_py()) if right.num_rows else []
        return dealt_table(key[0].as_py(), nodes, left.column("fp").to_numpy().view(np.uint64), left.column("home").to_numpy(), key[1].as_py())

    by = ["tree", "leaf", "chunk"]
    return held.select(*by, "home", "fp").groupBy(*by).cogroup(copies.groupBy(*by)).applyInArrow(deal, DEALT)


def links(reps: DataFrame, most: int = MOST, leaf: int = LEAF, sample: int = SAMPLE) -> DataFrame:
    """reps: distinct fp. A spanning forest of the links: a, b."""
    common.importable(reps.sparkSession)

    def join(key, table):
        points = table.column("fp").to_numpy().view(np.uint64)
        home = table.column("home").to_numpy()
        order = np.lexsort((points, ~home))
        points, home, forest = points[order], home[order], Forest(len(points))
        search(points, home, metrics_of(key[0].as_py(), most), most, forest, np.arange(len(points)))
        root = forest.root(np.arange(len(points)))
        linked = root != np.arange(len(points))
        return pa.table({"a": points[linked].view(np.int64), "b": points[root[linked]].view(np.int64)})

    found = [rows.groupBy("tree", "leaf", "chunk").applyInArrow(join, "a long, b long") for rows in leaves(reps, most, leaf, sample)]
    return reduce(DataFrame.unionByName, found)


def groups(docs: DataFrame, words: int = WORDS, seed: int = SEED, most: int = MOST) -> DataFrame:
    """doc_id, fp and component_id of each row."""
    marked = common.written(fingerprints(docs, words, seed), "simhash")
    reps = common.written(marked.groupBy("fp").agg(F.min("doc_id").alias("rep")), "simhash-distinct")
    roots = components(links(reps, most)).withColumnRenamed("node", "fp")
    placed = reps.join(roots, "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    named = placed.groupBy("root").agg(F.min("rep").alias("component_id"))
    return marked.join(placed.select("fp", "root").join(named, "root").select("fp", "component_id"), "fp")


def op10_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fingerprint and component of every document."""
    found = groups(common.documents(spark, sf_dir))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


QUERIES = {"op10_simhash": op10_simhash}
ORACLES: dict[str, str] = {}
