"""SimHash near-duplicates at a similarity: documents whose sets of five-word shingles have a Jaccard similarity of 0.8 or more, and all that such links join.

Fingerprints at similarity 0.8 lie some 10 bits apart, too many for tries that are led by bits which must agree. So the tries are led by least-hash
buckets here: 20 of four least hashes each, of which a pair at similarity 0.8 shares none with odds of 3 in 100,000 and one at 0.9 with 1 in 10 to the 9. In a
bucket the binary trie goes down in pairs of nodes as in the operator, under an error budget of 24 bits (five standard deviations beyond the mean at 0.8);
the pairs left are decided on the shingles. Equal texts count as one.

A pair is decided only while links have not joined its ends, nearest pairs first, so that a group of copies costs about its size. A bucket with more rows or
shingles than a block is dealt into blocks by hash; after the links within blocks, the rows outside its largest class meet all of its rows, block by block.
So no task holds more than two blocks, nothing is emitted but links, and no pair of a bucket is left out but those joined already.

Results for odd input: null, empty and blank texts are equal; texts of less than five words are one shingle; a null doc_id is no candidate for
component_id, which is null only if all of a component are null; an empty table gives an empty result; other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockpart.llm.common import forget, give_back, hot_share, mapped, materialise, portions, ranges
from blockpart.llm.simhash import BITS, SEED, components, copy_key, majority, merge_labels, node_pairs, one_row_of_each, shingle_hashes

SHINGLE = 5
SIMILARITY = 0.8
#: Differing bits of a fingerprint up to which the shingles are compared.
APART = 24
BANDS = 20
ROWS = 4
#: Rows, and shingles, of a block at about most; a longer text stands in a block of its own.
BLOCK_ROWS, BLOCK_SHINGLES = 512, 1 << 18
#: Shingles that a task holds at a time before it decides, and that are compared at a time.
HELD, COMPARED = 1 << 20, 1 << 20
#: Odd factors and terms of the hash orders.
_DRAW = np.random.default_rng(SEED).integers(0, 1 << 63, (2, BANDS * ROWS + BANDS), dtype=np.uint64)
FACTOR, TERM = (_DRAW[0] << np.uint64(1)) | np.uint64(1), _DRAW[1]


# ---- what is read from a text ------------------------------------------------------------------------------------

def buckets(texts: pa.Array, shingle: int = SHINGLE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Size of each text's shingle set, its fingerprint, and its BANDS buckets."""
    size, fp, least = np.zeros(len(texts), np.int64), np.zeros(len(texts), np.uint64), np.full((len(texts), BANDS * ROWS), np.uint64(0xFFFFFFFFFFFFFFFF))
    for a, b, hashes, doc, many in shingle_hashes(texts, shingle):
        fp[a:b] = majority(hashes, doc, many)
        order = np.lexsort((hashes, doc))
        hashes, doc = hashes[order], doc[order]
        new = np.concatenate([[True], (hashes[1:] != hashes[:-1]) | (doc[1:] != doc[:-1])])
        hashes, doc = hashes[new], doc[new]
        border = np.flatnonzero(np.concatenate([[True], doc[1:] != doc[:-1]]))
        own = a + doc[border]
        size[own] = np.diff(np.append(border, len(doc)))
        for k in range(BANDS * ROWS):
            least[own, k] = np.minimum.reduceat(hashes * FACTOR[k] + TERM[k], border)
    out = np.zeros((len(texts), BANDS), np.uint64)
    for k in range(BANDS):
        out[:, k] = TERM[BANDS * ROWS + k]
        for r in range(ROWS):
            out[:, k] = (out[:, k] ^ least[:, k * ROWS + r]) * FACTOR[BANDS * ROWS + k]
            out[:, k] ^= out[:, k] >> np.uint64(29)
    return size, fp, out.view(np.int64)


def bucket_table(docs: DataFrame, shingle: int = SHINGLE) -> DataFrame:
    def run(batches):
        for batch in batches:
            for part in portions(batch, 1):
                size, fp, own = buckets(part.column(1), shingle)
                lists = pa.ListArray.from_arrays(pa.array(np.arange(0, own.size + 1, BANDS, dtype=np.int32)), pa.array(own.reshape(-1)))
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), pa.array(size), pa.array(fp.view(np.int64)), lists], names=["doc_id", "copy", "size", "fp", "buckets"])
        give_back()

    kind = docs.schema["doc_id"].dataType.simpleString()
    return mapped(docs.select("doc_id", "text", copy_key().alias("copy")), run, f"doc_id {kind}, copy binary, size bigint, fp bigint, buckets array<bigint>")


def shingle_sets(texts: DataFrame, shingle: int = SHINGLE) -> DataFrame:
    """node, fp and the sorted distinct shingle hashes, as bytes."""

    def run(batches):
        for batch in batches:
            for part in portions(batch, 1):
                out = [b""] * part.num_rows
                for a, b, hashes, _, many in shingle_hashes(part.column(1), shingle):
                    stop = np.cumsum(many)
                    for i in range(b - a):
                        out[a + i] = np.unique(hashes[stop[i] - many[i] : stop[i]]).tobytes()
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), pa.array(out, pa.binary())], names=["node", "fp", "shingles"])
        give_back()

    return mapped(texts.select("node", "text", "fp"), run, "node bigint, fp bigint, shingles binary")


# ---- links within blocks -----------------------------------------------------------------------------------------

def linked(values: np.ndarray, at: np.ndarray, label: np.ndarray, i: np.ndarray, j: np.ndarray, similarity: float) -> tuple[np.ndarray, np.ndarray]:
    """Of the candidate pairs (nearest first), similar ones that join all that similar ones join.

    values: the sorted sets end to end, set k from at[k] to at[k + 1]; label: the class that earlier links give each set.
    """
    size = np.diff(at)
    near = np.minimum(size[i], size[j]) >= similarity * np.maximum(size[i], size[j]) - 1e-9
    i, j, found = i[near], j[near], []
    _, ident = np.unique(values, return_inverse=True)
    wide = int(ident.max()) + 1 if len(ident) else 1
    keys = np.repeat(np.arange(len(size)), size) * wide + ident
    turn = 0
    while True:
        open_ = label[i] != label[j]
        i, j = i[open_], j[open_]
        if not len(i):
            break
        if turn < 8:  # the nearest pair of each class
            take = np.unique(np.concatenate([np.unique(label[i], return_index=True)[1], np.unique(label[j], return_index=True)[1]]))
        else:
            take = np.arange(max(1, int(np.searchsorted(np.cumsum(np.minimum(size[i], size[j])), COMPARED))))
        turn += 1
        rest = np.ones(len(i), bool)
        rest[take] = False
        for low in range(0, len(take), 4096):
            p, q = i[take[low : low + 4096]], j[take[low : low + 4096]]
            p, q = np.where(size[p] <= size[q], p, q), np.where(size[p] <= size[q], q, p)
            want = np.repeat(q, size[p]) * wide + ident[ranges(at[p], size[p])]
            place = np.minimum(np.searchsorted(keys, want), max(len(keys) - 1, 0))
            hit = keys[place] == want if len(keys) else np.zeros(0, bool)
            both = np.bincount(np.repeat(np.arange(len(p)), size[p]), hit, len(p))
            good = both >= similarity * (size[p] + size[q] - both) - 1e-9
            if good.any():
                found.append((p[good], q[good]))
                label = merge_labels(label, p[good], q[good])
        i, j = i[rest], j[rest]
    return tuple(np.concatenate(x) for x in zip(*found, strict=True)) if found else (np.zeros(0, np.int64),) * 2


def block_links(block: np.ndarray, side: np.ndarray, node: np.ndarray, fp: np.ndarray, root: np.ndarray, values: np.ndarray, at: np.ndarray, similarity: float) -> tuple[np.ndarray, np.ndarray]:
    """Links (as nodes) within whole blocks. side 0: all rows of a block meet; 1 and 2: the rows of one side meet those of the other."""
    order = np.lexsort((fp, side, block))
    block, side, code = block[order], side[order], fp[order]
    border = np.flatnonzero(np.concatenate([[True], (block[1:] != block[:-1]) | (side[1:] != side[:-1])]))
    stop, kind, of = np.append(border[1:], len(block)), side[border], block[border]
    own = (kind == 0) & (stop - border > 1)
    cross = np.flatnonzero((kind[:-1] == 1) & (kind[1:] == 2) & (of[:-1] == of[1:]))
    a, b = np.concatenate([border[own], border[cross]]), np.concatenate([stop[own], stop[cross]])
    c, d = np.concatenate([border[own], border[cross + 1]]), np.concatenate([stop[own], stop[cross + 1]])
    pairs = list(node_pairs(code, list(range(BITS - 1, -1, -1)), a, b, c, d, APART))
    if not pairs:
        return (np.zeros(0, np.int64),) * 2
    i, j = (np.concatenate(x) for x in zip(*pairs, strict=True))
    nearest = np.argsort(np.bitwise_count(code[i] ^ code[j]), kind="stable")
    i, j = order[i[nearest]], order[j[nearest]]
    # One number for each class, and one for each node that stands in several blocks.
    _, label = np.unique(root, return_inverse=True)
    first = np.full(int(label.max()) + 1, len(label))
    np.minimum.at(first, label, np.arange(len(label)))
    p, q = linked(values, at, first[label], i, j, similarity)
    return node[p], node[q]


def links(rows: DataFrame, similarity: float) -> DataFrame:
    """u, v: links within the blocks of rows(block, side, node, root, fp, shingles)."""
    dealt = rows.repartition(hot_share(rows.sparkSession), "block").sortWithinPartitions("block").select("block", "side", "node", "root", "fp", "shingles")

    def decided(held: list[pa.RecordBatch]) -> pa.RecordBatch:
        table = pa.Table.from_batches(held).combine_chunks()
        block, side, node, root, fp = (table.column(k).to_numpy() for k in range(5))
        sets = [x.as_buffer() for x in table.column(5)]
        at = np.concatenate([[0], np.cumsum([x.size // 8 for x in sets])]).astype(np.int64)
        values = np.frombuffer(b"".join(x.to_pybytes() for x in sets), np.uint64)
        u, v = block_links(block, side, node, fp.view(np.uint64), root, values, at, similarity)
        return pa.RecordBatch.from_arrays([pa.array(u), pa.array(v)], names=["u", "v"])

    def run(batches: Iterator[pa.RecordBatch]):
        held, size = [], 0
        for batch in batches:
            of = batch.column(0).to_numpy()
            low = 0
            for high in [*(np.flatnonzero(of[1:] != of[:-1]) + 1).tolist(), batch.num_rows]:
                # A new block may begin at low: what is held ends with whole blocks.
                if held and size >= HELD and of[low] != held[-1].column(0)[-1].as_py():
                    yield decided(held)
                    held, size = [], 0
                part = batch.slice(low, high - low)
                held.append(part)
                size += part.column(5).nbytes // 8
                low = high
        if held:
            yield decided(held)
        give_back()

    return mapped(dealt, run, "u bigint, v bigint")


# ---- the whole ---------------------------------------------------------------------------------------------------

def classes(docs: DataFrame, shingle: int = SHINGLE, similarity: float = SIMILARITY) -> tuple[DataFrame, DataFrame]:
    """table(doc_id, copy, ...) of all rows, and known(copy, root, least) of all distinct texts: root numbers their class, least is its least doc_id."""
    if similarity < SIMILARITY:
        raise ValueError(f"the buckets hold links of similarity {SIMILARITY} and more")
    table = materialise(bucket_table(docs, shingle))
    distinct = table.groupBy("copy").agg(F.min("doc_id").alias("least"), F.first(F.struct("size", "fp", "buckets")).alias("x")).select("copy", "least", "x.*")
    distinct = materialise(distinct.withColumn("node", F.monotonically_increasing_id()))
    member = distinct.select("node", "size", F.explode("buckets").alias("bucket"))
    # Of buckets with the same rows one is enough.
    many = member.groupBy("bucket").agg(F.count(F.lit(1)).alias("n"), F.sum("size").alias("total"), F.bit_xor(F.xxhash64("node")).alias("x"), F.bit_xor(F.xxhash64("node", F.lit(1))).alias("y")).where("n > 1")
    many = materialise(many.groupBy("n", "total", "x", "y").agg(F.min("bucket").alias("bucket")))
    parts = F.greatest(F.ceil(F.col("n") / BLOCK_ROWS), F.ceil(F.col("total") / BLOCK_SHINGLES))
    shared = materialise(member.join(many.select("bucket", parts.cast("int").alias("parts")), "bucket"))
    wanted = shared.select("node").distinct()
    keys = distinct.join(wanted, "node", "left_semi").select(F.col("copy").alias("_copy"), "least", "node", "fp")
    texts = docs.select("doc_id", "text", copy_key().alias("copy")).join(keys, (F.col("copy") == F.col("_copy")) & F.col("doc_id").eqNullSafe(F.col("least")))
    sets = materialise(shingle_sets(texts.select("node", "text", "fp").dropDuplicates(["node"]), shingle))

    dealt = shared.withColumn("block", F.xxhash64("bucket", F.pmod(F.xxhash64("node"), F.col("parts")))).select("block", F.lit(0).alias("side"), "node", F.col("node").alias("root"))
    inner = materialise(links(dealt.join(sets, "node"), similarity))
    found = inner
    split = shared.where("parts > 1")
    if not split.isEmpty():
        rows = split.join(components(inner), "node", "left").select("bucket", "node", "size", F.coalesce("root", "node").alias("root"))
        by_root = rows.groupBy("bucket", "root").agg(F.count(F.lit(1)).alias("n"), F.sum("size").alias("total"))
        most = by_root.groupBy("bucket").agg(F.sum("n").alias("n"), F.sum("total").alias("total"), F.max(F.struct("n", "total", "root")).alias("top"))
        cut = lambda n, total: F.greatest(F.lit(1), F.ceil(F.col(n) / BLOCK_ROWS), F.ceil(F.col(total) / BLOCK_SHINGLES)).cast("int")
        most = most.select("bucket", F.col("top.root").alias("main"), (F.col("n") - F.col("top.n")).alias("others"), (F.col("total") - F.col("top.total")).alias("others_total"), "n", "total").where("others > 0")
        most = most.select("bucket", "main", cut("others", "others_total").alias("lefts"), cut("n", "total").alias("rights"))
        rows = rows.join(most, "bucket")
        place = lambda k: F.pmod(F.xxhash64("node", F.lit(7)), F.col(k)).cast("int")
        every = lambda k: F.explode(F.sequence(F.lit(0), F.col(k) - 1))
        left = rows.where("root <> main").select("bucket", "node", "root", place("lefts").alias("a"), every("rights").alias("b"), F.lit(1).alias("side"))
        right = rows.select("bucket", "node", "root", place("rights").alias("b"), every("lefts").alias("a"), F.lit(2).alias("side"))
        met = left.unionByName(right).select(F.xxhash64("bucket", "a", "b").alias("block"), "side", "node", "root")
        found = inner.union(materialise(links(met.join(sets, "node"), similarity)))

    roots = components(found)
    least = roots.join(distinct.select("node", "least"), "node").groupBy("root").agg(F.min("least").alias("component_least"))
    known = distinct.select("copy", "node", "least").join(roots, "node", "left").join(least, "root", "left")
    known = materialise(known.select("copy", F.coalesce("root", "node").alias("root"), F.coalesce("component_least", "least").alias("least")))
    for done in (many, distinct, shared, sets, inner):
        forget(done)
    return table, known


def near_copies(docs: DataFrame, shingle: int = SHINGLE, similarity: float = SIMILARITY) -> DataFrame:
    """doc_id and component_id, the least doc_id that links reach."""
    table, known = classes(docs, shingle, similarity)
    return table.select("doc_id", "copy").join(known, "copy").select("doc_id", F.col("least").alias("component_id"))


def one_of_each(docs: DataFrame, shingle: int = SHINGLE, similarity: float = SIMILARITY) -> DataFrame:
    """The documents, same columns, with one row of each class."""
    table, known = classes(docs, shingle, similarity)
    return one_row_of_each(docs, table.select("doc_id", "copy").join(known, "copy"))
