"""Graphs built from the given tables, and the same edges in SQL.

Each builder takes the session and the folder of the tables; EDGES_SQL has for each name a query of its arcs (src, dst),
both ways where the graph is undirected, NODES_SQL its nodes where they are more than the ends."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.ids import pack, sql_pack, sql_text_id, text_id
from ..operators.graph import Graph
from ..plans import layout, ordered
from ..sources.tables import table

HEAVY = 45
TAU = 0.40
SHINGLE = 5


def pairs(a, b) -> tuple:
    return a.alias("src"), b.alias("dst")


def part_supplier(spark: SparkSession, sf_dir: str, heavy: int | None = None) -> Graph:
    rows = table(spark, sf_dir, "lineitem", ["l_partkey", "l_suppkey", "l_quantity"])
    if heavy:
        rows = rows.where(F.col("l_quantity") >= heavy)
    return Graph.from_edges(rows.select(*pairs(pack("part", "l_partkey"), pack("supplier", "l_suppkey"))), undirected=True)


def part_supplier_heavy(spark: SparkSession, sf_dir: str) -> Graph:
    return part_supplier(spark, sf_dir, HEAVY)


def customer_supplier(spark: SparkSession, sf_dir: str) -> Graph:
    lines, orders = table(spark, sf_dir, "lineitem", ["l_orderkey", "l_suppkey"]), table(spark, sf_dir, "orders", ["o_orderkey", "o_custkey"])
    rows = lines.join(orders, lines.l_orderkey == orders.o_orderkey)
    return Graph.from_edges(rows.select(*pairs(pack("customer", "o_custkey"), pack("supplier", "l_suppkey"))), undirected=True)


def nation_trade(spark: SparkSession, sf_dir: str) -> Graph:
    lines, orders = table(spark, sf_dir, "lineitem", ["l_orderkey", "l_suppkey"]), table(spark, sf_dir, "orders", ["o_orderkey", "o_custkey"])
    customers, suppliers = table(spark, sf_dir, "customer", ["c_custkey", "c_nationkey"]), table(spark, sf_dir, "supplier", ["s_suppkey", "s_nationkey"])
    rows = lines.join(orders, lines.l_orderkey == orders.o_orderkey).join(customers, F.col("o_custkey") == F.col("c_custkey")).join(suppliers, F.col("l_suppkey") == F.col("s_suppkey"))
    return Graph.from_edges(rows.select(*pairs(pack("nation", "c_nationkey"), pack("nation", "s_nationkey"))))


def part_copurchase(spark: SparkSession, sf_dir: str) -> Graph:
    bought = table(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey"]).distinct()
    other = bought.select(F.col("l_orderkey").alias("_order"), F.col("l_partkey").alias("_part"))
    rows = bought.join(other, (F.col("l_orderkey") == F.col("_order")) & (F.col("l_partkey") < F.col("_part")))
    return Graph.from_edges(rows.select(*pairs(pack("part", "l_partkey"), pack("part", "_part"))), undirected=True)


def order_tree(spark: SparkSession, sf_dir: str) -> Graph:
    orders, customers, nations = table(spark, sf_dir, "orders", ["o_orderkey", "o_custkey"]), table(spark, sf_dir, "customer", ["c_custkey", "c_nationkey"]), table(spark, sf_dir, "nation", ["n_nationkey", "n_regionkey"])
    rows = orders.select(*pairs(pack("order", "o_orderkey"), pack("customer", "o_custkey"))).unionByName(customers.select(*pairs(pack("customer", "c_custkey"), pack("nation", "c_nationkey")))).unionByName(nations.select(*pairs(pack("nation", "n_nationkey"), pack("region", "n_regionkey"))))
    return Graph.from_edges(rows, undirected=True)


EVENT_TYPES = ("click", "error", "purchase", "signup", "view")


def user_hour_event(spark: SparkSession, sf_dir: str) -> Graph:
    rows = table(spark, sf_dir, "events", ["ts", "user_id", "event_type"])
    hour = F.floor(F.unix_seconds(F.col("ts").cast("timestamp")) / 3600)
    kind = F.array_position(F.array(*[F.lit(x) for x in EVENT_TYPES]), F.col("event_type"))
    return Graph.from_edges(rows.select(*pairs(pack("user", "user_id"), pack("hour_event", hour * 8 + kind))), undirected=True)


#: Vectors of a block; two blocks make one task.
BLOCK_VECTORS = 2000


def embedding_sim(spark: SparkSession, sf_dir: str, tau: float = TAU, block: int = BLOCK_VECTORS) -> Graph:
    """Vectors of a cosine of at least tau. An angle that wide parts no buckets, so all pairs are looked at: vectors are
    dealt to blocks, and each two blocks are one task with a matrix product, whatever the number of blocks."""
    rows = table(spark, sf_dir, "embeddings", ["vec_id", "embedding"]).select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("e"))
    blocks = max(1, -(-rows.count() // block))
    own = rows.withColumn("own", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)))
    other = own.select("*", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long"))).alias("_k"))
    dealt = other.select("vec_id", "e", "own", F.least("own", "_k").alias("first"), F.greatest("own", "_k").alias("second"))

    def near(key, rows):
        ids, own = rows.column("vec_id").to_numpy(), rows.column("own").to_numpy()
        e = np.stack(rows.column("e").to_pylist()) if len(ids) else np.zeros((0, 1))
        norm = np.sqrt((e * e).sum(1))
        left, right = own == key[0].as_py(), own == key[1].as_py()
        i, j = np.nonzero(e[left] @ e[right].T >= tau * np.outer(norm[left], norm[right]))
        i, j = np.flatnonzero(left)[i], np.flatnonzero(right)[j]
        keep = (ids[i] != ids[j]) & (norm[i] > 0) & (norm[j] > 0) & ((key[0] != key[1]) | (ids[i] < ids[j]))
        a, b = ids[i][keep], ids[j][keep]
        return pa.table({"a": np.minimum(a, b), "b": np.maximum(a, b)})

    found = dealt.groupBy("first", "second").applyInArrow(near, "a long, b long")
    return Graph.from_edges(found.select(*pairs(pack("vector", "a"), pack("vector", "b"))), undirected=True)


def document_line(spark: SparkSession, sf_dir: str) -> Graph:
    """Documents and the lines that at least two of them share; documents without one are isolated."""
    docs = table(spark, sf_dir, "documents", ["doc_id", "text"])
    lines = docs.select("doc_id", F.explode(F.split(F.coalesce("text", F.lit("")), "\n")).alias("line")).select("doc_id", text_id(F.col("line")).alias("line")).distinct()
    lines = layout.commit(lines)  # a line of very many documents is then split by the join
    shared = lines.groupBy("line").agg(F.count("*").alias("n")).where("n > 1").select("line")
    return Graph.from_edges(lines.join(shared, "line").select(*pairs(pack("document", "doc_id"), F.col("line"))), docs.select(pack("document", "doc_id").alias("id")), undirected=True)


def user_follow(spark: SparkSession, sf_dir: str) -> Graph:
    """The user of an event to the user of the next one, without loops."""
    rows = follow_rows(table(spark, sf_dir, "events", ["event_id", "ts", "user_id"]))
    return Graph.from_edges(rows.where("user_id <> next_user").select(*pairs(pack("user", "user_id"), pack("user", "next_user"))))


def follow_rows(events: DataFrame) -> DataFrame:
    """Each event with the user of the next in order of ts, event_id."""
    return ordered.followed(events, ["ts", "event_id"], "user_id", "next_user").where("next_user is not null")


HREF = 'href="([^"]*)"'


def page_link(spark: SparkSession, sf_dir: str) -> Graph:
    pages = table(spark, sf_dir, "pages", ["page_id", "html"])
    rows = pages.select("page_id", F.explode(F.regexp_extract_all("html", F.lit(HREF), 1)).alias("href"))
    return Graph.from_edges(rows.select(*pairs(pack("page", "page_id"), text_id(F.col("href")))), pages.select(pack("page", "page_id").alias("id")))


def conversation_token(spark: SparkSession, sf_dir: str) -> Graph:
    rows = table(spark, sf_dir, "conversations", ["conv_id", "text"]).select("conv_id", F.explode(F.split(F.coalesce("text", F.lit("")), " ")).alias("token"))
    return Graph.from_edges(rows.where("token <> ''").select(*pairs(pack("conversation", "conv_id"), text_id(F.col("token")))).distinct(), undirected=True)


def shingled(df: DataFrame, key: str, n: int = SHINGLE) -> DataFrame:
    """key and each run of n words, joined by spaces."""
    words = F.split(F.coalesce("text", F.lit("")), " ")
    runs = F.transform(F.sequence(F.lit(1), F.size("words") - (n - 1)), lambda i: F.array_join(F.slice("words", i, n), " "))
    return df.select(key, words.alias("words")).where(F.size("words") >= n).select(key, F.explode(runs).alias("shingle"))


def benchmark_doc_token(spark: SparkSession, sf_dir: str) -> Graph:
    items, docs = table(spark, sf_dir, "benchmark", ["item_id", "text"]), table(spark, sf_dir, "documents", ["doc_id", "text"])
    rows = shingled(items, "item_id").distinct().join(shingled(docs, "doc_id"), "shingle")
    return Graph.from_edges(rows.select(*pairs(pack("item", "item_id"), pack("document", "doc_id"))).distinct(), items.select(pack("item", "item_id").alias("id")), undirected=True)


BUILDERS: dict[str, Callable[[SparkSession, str], Graph]] = {
    f.__name__: f
    for f in (part_supplier, part_supplier_heavy, customer_supplier, nation_trade, part_copurchase, order_tree, user_hour_event, embedding_sim, document_line, user_follow, page_link, conversation_token, benchmark_doc_token)
}
DIRECTED = {"nation_trade", "user_follow", "page_link"}


def build(name: str, spark: SparkSession, sf_dir: str) -> Graph:
    return BUILDERS[name](spark, sf_dir)


_P, _S, _C, _O, _N, _R, _U, _H = (sql_pack(k, "{}") for k in ("part", "supplier", "customer", "order", "nation", "region", "user", "hour_event"))
_LINES = "select distinct doc_id, unnest(string_split(coalesce(text, ''), chr(10))) as line from documents"
_ONE_WAY = {
    "part_supplier": f"select {_P.format('l_partkey')} as src, {_S.format('l_suppkey')} as dst from lineitem",
    "part_supplier_heavy": f"select {_P.format('l_partkey')} as src, {_S.format('l_suppkey')} as dst from lineitem where l_quantity >= {HEAVY}",
    "customer_supplier": f"select {_C.format('o_custkey')} as src, {_S.format('l_suppkey')} as dst from lineitem join orders on l_orderkey = o_orderkey",
    "nation_trade": f"select {_N.format('c_nationkey')} as src, {_N.format('s_nationkey')} as dst from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join supplier on l_suppkey = s_suppkey",
    "part_copurchase": f"select {_P.format('a.l_partkey')} as src, {_P.format('b.l_partkey')} as dst from lineitem a join lineitem b on a.l_orderkey = b.l_orderkey and a.l_partkey < b.l_partkey",
    "order_tree": f"select {_O.format('o_orderkey')} as src, {_C.format('o_custkey')} as dst from orders union all select {_C.format('c_custkey')}, {_N.format('c_nationkey')} from customer union all select {_N.format('n_nationkey')}, {_R.format('n_regionkey')} from nation",
    "user_hour_event": f"select {_U.format('user_id')} as src, {_H.format('(floor(epoch(ts) / 3600)::bigint * 8 + list_position(' + repr(list(EVENT_TYPES)) + ', event_type))')} as dst from events",
    "embedding_sim": f"select {sql_pack('vector', 'a.vec_id')} as src, {sql_pack('vector', 'b.vec_id')} as dst from embeddings a join embeddings b on a.vec_id < b.vec_id and list_cosine_similarity(a.embedding::double[], b.embedding::double[]) >= {TAU}",
    "document_line": f"select {sql_pack('document', 'doc_id')} as src, {sql_text_id('line')} as dst from ({_LINES}) where line in (select line from ({_LINES}) group by line having count(*) > 1)",
    "user_follow": f"select {_U.format('user_id')} as src, {_U.format('next_user')} as dst from (select user_id, lead(user_id) over (order by ts, event_id) as next_user from events) where user_id <> next_user",
    "page_link": f"select {sql_pack('page', 'page_id')} as src, {sql_text_id('href')} as dst from (select page_id, unnest(regexp_extract_all(html, '{HREF}', 1)) as href from pages)",
    "conversation_token": f"select {sql_pack('conversation', 'conv_id')} as src, {sql_text_id('token')} as dst from (select conv_id, unnest(string_split(coalesce(text, ''), ' ')) as token from conversations) where token <> ''",
    "benchmark_doc_token": f"""select {sql_pack('item', 'item_id')} as src, {sql_pack('document', 'doc_id')} as dst from
        (select distinct item_id, array_to_string(words[i:i + {SHINGLE - 1}], ' ') as shingle from (select item_id, words, unnest(range(1, len(words) - {SHINGLE - 2})) as i from (select item_id, string_split(text, ' ') as words from benchmark)))
        join (select doc_id, array_to_string(words[i:i + {SHINGLE - 1}], ' ') as shingle from (select doc_id, words, unnest(range(1, len(words) - {SHINGLE - 2})) as i from (select doc_id, string_split(text, ' ') as words from documents))) using (shingle)""",
}
EDGES_SQL = {k: f"select distinct src, dst from ({q})" if k in DIRECTED else f"select src, dst from (select * from ({q}) union select dst, src from ({q}))" for k, q in _ONE_WAY.items()}
_MORE_NODES = {
    "document_line": f"select {sql_pack('document', 'doc_id')} as id from documents",
    "page_link": f"select {sql_pack('page', 'page_id')} as id from pages",
    "benchmark_doc_token": f"select {sql_pack('item', 'item_id')} as id from benchmark",
}
NODES_SQL = {k: "select src as id from e union select dst from e" + (f" union {_MORE_NODES[k]}" if k in _MORE_NODES else "") for k in EDGES_SQL}
