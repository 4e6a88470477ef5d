"""Workload graphs on the given tables, as edges(src, dst, w); each with the SQL of the same edges."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from blockpart.functions.math import string_id
from blockpart.operators.relops import in_parts, settled
from blockpart.sources.tables import table

#: Vectors (64 floats) of a block, which is broadcast at a time, and of a task at most; those that are worth a task; and scores that a task makes at a time.
KNN_BLOCK, KNN_LEAST, KNN_SCORES = 20_000, 1_000, 1 << 22


def w1(spark: SparkSession, sf: str) -> DataFrame:
    """Trade: supplier's nation to customer's nation, order lines."""
    lines = table(spark, sf, "lineitem", "l_orderkey", "l_suppkey").join(table(spark, sf, "orders", "o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    pairs = lines.groupBy("l_suppkey", "o_custkey").agg(F.count(F.lit(1)).alias("w"))
    pairs = pairs.join(table(spark, sf, "customer", "c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey")).join(table(spark, sf, "supplier", "s_suppkey", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey"))
    return pairs.groupBy(F.col("s_nationkey").cast("bigint").alias("src"), F.col("c_nationkey").cast("bigint").alias("dst")).agg(F.sum("w").cast("double").alias("w"))


def w2(spark: SparkSession, sf: str) -> DataFrame:
    """Customer to supplier, order lines; ids 4 key + kind."""
    lines = table(spark, sf, "lineitem", "l_orderkey", "l_suppkey").join(table(spark, sf, "orders", "o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    return lines.groupBy((F.col("o_custkey") * 4).alias("src"), (F.col("l_suppkey") * 4 + 1).alias("dst")).agg(F.count(F.lit(1)).cast("double").alias("w"))


def w3(spark: SparkSession, sf: str) -> DataFrame:
    """Parts that share an order, each pair once (smaller id first)."""
    has = table(spark, sf, "lineitem", "l_orderkey", "l_partkey").distinct()
    a, b = has.toDF("o", "src"), has.toDF("o", "dst")
    return a.join(b, "o").where("src < dst").groupBy("src", "dst").agg(F.count(F.lit(1)).cast("double").alias("w"))


def w4(spark: SparkSession, sf: str) -> DataFrame:
    """User of an event to user of the next; ordered in ranges of rows, which are stitched at their ends."""
    events = in_parts(table(spark, sf, "events", "ts", "event_id", "user_id"), "ts", "event_id").withColumn("user", F.struct("user_id"))
    own = Window.partitionBy("_part").orderBy("_at")
    first = events.groupBy("_part").agg(F.min_by("user", "_at").alias("head"))
    following = first.select("_part", F.lead("head").over(Window.orderBy("_part")).alias("next_head"))  # a row per range
    pairs = events.withColumn("next", F.lead("user").over(own)).join(F.broadcast(following), "_part")
    pairs = pairs.select(F.col("user_id").alias("src"), F.coalesce("next", "next_head")["user_id"].alias("dst"))
    return pairs.where("dst is not null").groupBy("src", "dst").agg(F.count(F.lit(1)).cast("double").alias("w"))


def w5(spark: SparkSession, sf: str, k: int = 10) -> DataFrame:
    """The k nearest of all other vectors by cosine (ties: least id) to each vector.

    A task holds up to KNN_BLOCK vectors with the k best so far for each, and meets all vectors block by block, in runs of a bounded number of scores; nothing is shuffled but the vectors, once.
    """
    vectors = table(spark, sf, "embeddings", "vec_id", "embedding").where("embedding is not null")
    size = vectors.count()
    blocks = -(-size // KNN_BLOCK) or 1
    parts = max(blocks, min(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-size // KNN_LEAST))) or 1
    held = settled(vectors.withColumn("_block", F.pmod(F.xxhash64("vec_id"), F.lit(blocks))).repartition(blocks, "_block").sortWithinPartitions("_block"))
    shared = []
    for b in range(blocks):
        shared.append(spark.sparkContext.broadcast(few_of_each(*as_arrays(held.where(F.col("_block") == b).select("vec_id", "embedding").toArrow()), k)))

    def near(batches):
        batches = [x for x in batches if x.num_rows]
        if not batches:
            return
        ids, own = as_arrays(pa.Table.from_batches(batches))
        size, found = np.linalg.norm(own, axis=1), None
        for block in shared:
            found = nearest(ids, own, size, *(x.astype(y) for x, y in zip(block.value, (np.int64, np.float64), strict=True)), k, found)
            if block._path is not None:  # else a worker would come to hold all vectors
                vars(block).pop("_value", None)
        for at in range(0, len(found[0]), 100_000):
            q, other = (x[at : at + 100_000] for x in found[:2])
            yield pa.RecordBatch.from_arrays([pa.array(ids[q]), pa.array(other), pa.array(np.ones(len(q)))], ["src", "dst", "w"])

    return vectors.repartition(parts).mapInArrow(near, "src bigint, dst bigint, w double")


def as_arrays(rows: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    """Ids, and vectors as a matrix."""
    rows = rows.combine_chunks()
    ids = rows["vec_id"].to_numpy().astype(np.int64)
    if not len(ids):
        return ids, np.zeros((0, 1))
    if len(pc.unique(pc.list_value_length(rows["embedding"]))) > 1:
        raise ValueError("vectors of different lengths")
    return ids, pc.list_flatten(rows["embedding"]).to_numpy().astype(np.float64).reshape(len(ids), -1)


def few_of_each(ids: np.ndarray, own: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Of equal vectors those k + 1 with the least ids: they score the same with everyone, so that no other one can be among anyone's k nearest. In 32 bits, as the table has them, in the order of ids."""
    order = np.argsort(ids, kind="stable")
    ids, own = ids[order], np.ascontiguousarray(own[order], np.float32)
    if len(ids):
        _, same = np.unique(own.view(np.dtype((np.void, own.itemsize * own.shape[1])))[:, 0], return_inverse=True)
        order = np.argsort(same, kind="stable")
        place = np.empty(len(ids), np.int64)
        place[order] = np.arange(len(ids)) - np.searchsorted(same[order], same[order])
        ids, own = ids[place <= k], own[place <= k]
    return ids, own


def nearest(ids, unit, size, others, own, k, held, most=None):
    """The k best so far of each asked vector (its place, other id, score, and the least score that is still of use) after these vectors; runs grow, so that few scores pass at first."""
    q, other, score, least, seen = held or (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0), np.full(len(ids), -np.inf), 0)
    new, waiting = [], 0
    most = most or KNN_SCORES
    norm, at = np.linalg.norm(own, axis=1), 0
    with np.errstate(invalid="ignore", divide="ignore"):
        asked, near = (unit / size[:, None]).astype(np.float32).T, (own / norm[:, None]).astype(np.float32)
    while at < len(own):
        run = slice(at, at + max(1, min(max(k + 1, seen), most // len(ids))))
        row, col = np.divmod(np.flatnonzero(near[run] @ asked >= (least - 2e-5).astype(np.float32)), len(ids))  # wider than what 32 bits lose over 64 terms; those left are scored anew
        value, name = np.zeros(len(row)), others[run][row]
        for k0 in range(0, len(row), 100_000):
            some = slice(k0, k0 + 100_000)
            value[some] = np.round((own[run][row[some]] * unit[col[some]]).sum(1) / (norm[run][row[some]] * size[col[some]]), 9)
        keep = ids[col] != name
        new.append((col[keep], name[keep], value[keep]))
        waiting, at, seen = waiting + int(keep.sum()), run.stop, seen + run.stop - run.start
        if waiting < len(q) and at < len(own):
            continue
        q, other, score = (np.concatenate(x) for x in zip((q, other, score), *new, strict=True))
        new, waiting = [], 0
        order = np.lexsort((other, -score, q))
        q, other, score = q[order], other[order], score[order]
        first = np.searchsorted(q, np.arange(len(ids) + 1))
        best = np.arange(len(q)) - first[q] < k
        last = first[:-1][np.diff(first) >= k] + k - 1
        least[q[last]] = score[last]
        q, other, score = q[best], other[best], score[best]
    return q, other, score, least, seen


def doc_tokens(spark: SparkSession, sf: str, low: int = 2, high: int = 20) -> DataFrame:
    """doc_id and token, for tokens in `low` to `high` documents."""
    has = table(spark, sf, "documents", "doc_id", "text").select("doc_id", F.explode(F.array_distinct(F.split(F.lower("text"), r"\s+"))).alias("token")).where("token <> ''")
    kept = has.groupBy("token").agg(F.count(F.lit(1)).alias("n")).where(F.col("n").between(low, high)).select("token")
    return has.join(kept, "token")


def w6(spark: SparkSession, sf: str) -> DataFrame:
    """Documents that share rare tokens, each pair once; at most `high` documents a token bound the pairs."""
    has = doc_tokens(spark, sf)
    a, b = has.select("token", F.col("doc_id").alias("src")), has.select("token", F.col("doc_id").alias("dst"))
    return a.join(b, "token").where("src < dst").groupBy("src", "dst").agg(F.count(F.lit(1)).cast("double").alias("w"))


def w6b(spark: SparkSession, sf: str) -> DataFrame:
    """Document to rare token."""
    return doc_tokens(spark, sf).select((F.col("doc_id") * 4).alias("src"), string_id(F.col("token"), 1).alias("dst"), F.lit(1.0).alias("w"))


def w7(spark: SparkSession, sf: str) -> DataFrame:
    """Page to link target."""
    links = table(spark, sf, "pages", "page_id", "html").select("page_id", F.explode(F.expr("regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)")).alias("href"))
    return links.groupBy((F.col("page_id") * 4).alias("src"), string_id(F.col("href"), 1).alias("dst")).agg(F.count(F.lit(1)).cast("double").alias("w"))


def w8(spark: SparkSession, sf: str) -> DataFrame:
    """Role of a turn to role of the next: assistant 0, system 1, user 2."""
    turns = table(spark, sf, "conversations", "conv_id", "turn", "role")
    number = F.when(F.col("role") == "assistant", 0).when(F.col("role") == "system", 1).otherwise(2).cast("bigint")
    pairs = turns.select(number.alias("src"), F.lead(number).over(Window.partitionBy("conv_id").orderBy("turn")).alias("dst"))
    return pairs.where("dst is not null").groupBy("src", "dst").agg(F.count(F.lit(1)).cast("double").alias("w"))


GRAPHS = {"w1": w1, "w2": w2, "w3": w3, "w4": w4, "w5": w5, "w6": w6, "w6b": w6b, "w7": w7, "w8": w8}

_TOKENS = "has as (select distinct doc_id, unnest(regexp_split_to_array(lower(text), '\\s+')) as token from documents), rare as (select h.* from has h join (select token from has where token <> '' group by token having count(*) between 2 and 20) using (token))"
_ID = "('0x' || substr(md5({0}), 1, 13))::bigint * 4 + 1"
SQL = {
    "w1": "select s_nationkey::bigint as src, c_nationkey::bigint as dst, count(*)::double as w from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join supplier on l_suppkey = s_suppkey group by all",
    "w2": "select 4 * o_custkey as src, 4 * l_suppkey + 1 as dst, count(*)::double as w from lineitem join orders on l_orderkey = o_orderkey group by all",
    "w3": "with has as (select distinct l_orderkey as o, l_partkey as p from lineitem) select a.p as src, b.p as dst, count(*)::double as w from has a join has b on a.o = b.o and a.p < b.p group by all",
    "w4": "select src, dst, count(*)::double as w from (select user_id as src, lead(user_id) over (order by ts, event_id) as dst from events) where dst is not null group by all",
    "w5": "select src, dst, 1.0::double as w from (select a.vec_id as src, b.vec_id as dst, row_number() over (partition by a.vec_id order by round(list_cosine_similarity(a.embedding::double[], b.embedding::double[]), 9) desc, b.vec_id) as k from embeddings a join embeddings b on a.vec_id <> b.vec_id) where k <= 10",
    "w6": f"with {_TOKENS} select a.doc_id as src, b.doc_id as dst, count(*)::double as w from rare a join rare b on a.token = b.token and a.doc_id < b.doc_id group by all",
    "w6b": f"with {_TOKENS} select 4 * doc_id as src, {_ID.format('token')} as dst, 1.0::double as w from rare",
    "w7": f"select 4 * page_id as src, {_ID.format('href')} as dst, count(*)::double as w from (select page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) as href from pages) group by all",
    "w8": "select src, dst, count(*)::double as w from (select r as src, lead(r) over (partition by conv_id order by turn) as dst from (select *, case role when 'assistant' then 0 when 'system' then 1 else 2 end::bigint as r from conversations)) where dst is not null group by all",
}


def region_of_nation(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "nation", "n_nationkey", "n_regionkey").select(F.col("n_nationkey").cast("bigint").alias("i"), F.col("n_regionkey").cast("bigint").alias("b"))


def each_alone(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("src").alias("i")).union(edges.select("dst")).distinct().select("i", F.col("i").alias("b"))


def language_of_document(spark: SparkSession, sf: str) -> DataFrame:
    """de 0, en 1, es 2, fr 3."""
    lang = F.array_position(F.array(*map(F.lit, ("de", "en", "es", "fr"))), F.col("lang")) - 1
    return table(spark, sf, "documents", "doc_id", "lang").select(F.col("doc_id").alias("i"), lang.alias("b"))


ASSIGN_SQL = {
    "region": "select n_nationkey::bigint as i, n_regionkey::bigint as b from nation",
    "language": "select doc_id as i, (case lang when 'de' then 0 when 'en' then 1 when 'es' then 2 else 3 end)::bigint as b from documents",
    "mod5": "select distinct i, i % 5 as b from (select src as i from edges union all select dst from edges)",
    "alone": "select distinct i, i as b from (select src as i from edges union all select dst from edges)",
}
