"""SimHash near-duplicates by a self-join of binary tries.

Fingerprints: majority bits over the XXH64 hashes of word shingles. Distinct fingerprints, with the number of their
documents, are dealt to tries whose leading bits must agree: two fingerprints at two or fewer differing bits agree in one
of three blocks of bits, and outside of it in one of three smaller ones, so nine tries led by 35 or so of the bits
hold every link, and a link counts only in the first trie that has it. In a trie, pairs of nodes go down together, level by
level, adding up differing bits, and are dropped beyond the budget. A trie yields a star per cluster, not its pairs; stars
are joined into components by large-star and small-star rounds over written tables.

Results for odd input: null, empty or blank texts have fingerprint zero and link like others; texts of one or two words
are one shingle; repeated rows share a result; a null doc_id is no candidate for component_id, which is null only if all of a
component are null; an empty table gives an empty result; other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from blockpart.llm.common import LOWER, SOLID, byte_view, forget, give_back, hot_share, mapped, materialise, portions, ranges, row_slices, word_spans

BITS = 64
BUDGET = 2
SHINGLE = 3
SEED = 42
#: Pairs of nodes that go down together at a time.
FRONT = 1 << 20
#: Fingerprints of a task at about most (some 300 bytes each with the counts of their bits).
PORTION_ROWS = 1 << 20


def _bits(low: int, high: int) -> int:
    return ((1 << high) - 1) ^ ((1 << low) - 1)


def lead_masks() -> list[tuple[int, list[int], list[int]]]:
    """(lead, earlier, smaller): the bits that must agree; the blocks before, all of which must differ for the link to count here."""
    blocks = [_bits(0, 21), _bits(21, 42), _bits(42, 64)]
    out = []
    for r, block in enumerate(blocks):
        rest = [i for i in range(BITS) if not block >> i & 1]
        cuts = [0, len(rest) // 3, 2 * len(rest) // 3, len(rest)]
        parts = [sum(1 << i for i in rest[a:b]) for a, b in zip(cuts, cuts[1:], strict=False)]
        out += [(block | part, blocks[:r] + parts[:s]) for s, part in enumerate(parts)]
    return out


MASKS = lead_masks()


def shingle_hashes(texts: pa.Array, shingle: int = SHINGLE, seed: int = SEED) -> Iterator[tuple[int, int, np.ndarray, np.ndarray, np.ndarray]]:
    """(a, b, hashes, doc, many) by slices of rows a to b: the shingles' hashes, the row (from a) of each, and their number for each row. Slices without a word are left out."""
    data, at = byte_view(texts)
    digest = xxhash.xxh64_intdigest
    for a, b in row_slices(at):
        part, here = data[at[a] : at[b]], at[a : b + 1] - at[a]
        solid = SOLID[part]
        start, end, first = word_spans(solid, here)
        if not len(start):
            continue
        # One space after each word that the text goes on after; other blanks go.
        keep, joined = solid.copy(), LOWER[part]
        after = end[end < len(part)]
        blank = after[~solid[after]]
        keep[blank], joined[blank] = True, 0x20
        place = np.cumsum(keep)
        raw = joined[keep].tobytes()
        head, tail = place[start] - 1, place[end - 1]
        count = np.diff(first)
        many = np.where(count >= shingle, count - shingle + 1, np.minimum(count, 1))
        size = np.minimum(count, shingle)
        doc = np.repeat(np.arange(b - a), many)
        lead = np.cumsum(many) - many
        begin = first[:-1][doc] + np.arange(len(doc)) - lead[doc]
        cuts = zip(head[begin].tolist(), tail[begin + size[doc] - 1].tolist(), strict=True)
        yield a, b, np.fromiter((digest(raw[x:y], seed) for x, y in cuts), np.uint64, len(doc)), doc, many


def majority(hashes: np.ndarray, doc: np.ndarray, many: np.ndarray) -> np.ndarray:
    """The fingerprint of each row: bits set in over half of its hashes."""
    ones = np.zeros((len(many), BITS), np.int64)
    for k in range(0, len(doc), 1 << 17):
        own = doc[k : k + (1 << 17)]
        bits = np.unpackbits(hashes[k : k + (1 << 17)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        border = np.flatnonzero(np.concatenate([[True], own[1:] != own[:-1]]))
        ones[own[border]] += np.add.reduceat(bits, border, axis=0, dtype=np.int64)
    return np.packbits(ones * 2 > many[:, None], axis=1, bitorder="little").view(np.uint64).reshape(-1)


def fingerprints(texts: pa.Array, shingle: int = SHINGLE, seed: int = SEED) -> np.ndarray:
    out = np.zeros(len(texts), np.uint64)
    for a, b, hashes, doc, many in shingle_hashes(texts, shingle, seed):
        out[a:b] = majority(hashes, doc, many)
    return out


def fingerprint_table(docs: DataFrame, shingle: int = SHINGLE, seed: int = SEED) -> DataFrame:
    """doc_id, copy (the MD5 sum of the text) and fp (the 64 bits as a signed long) of each row."""

    def run(batches):
        for batch in batches:
            for part in portions(batch, 1):
                fp = fingerprints(part.column(1), shingle, seed)
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), pa.array(fp.view(np.int64))], names=["doc_id", "copy", "fp"])
        give_back()

    kind = docs.schema["doc_id"].dataType.simpleString()
    return mapped(docs.select("doc_id", "text", copy_key().alias("copy")), run, f"doc_id {kind}, copy binary, fp bigint")


def trie_pairs(fp: np.ndarray, lead: int, earlier: list[int], budget: int = BUDGET):
    """Index pairs at `budget` or fewer differing bits that agree in the bits of lead; fp sorted by those, then by the rest. In portions."""
    n = len(fp)
    head = fp & np.uint64(lead)
    border = np.flatnonzero(np.concatenate([[True], head[1:] != head[:-1]])) if n else np.zeros(0, np.int64)
    stop = np.append(border[1:], n)
    many = stop - border > 1
    a, b = border[many], stop[many]
    for i, j in node_pairs(fp, [i for i in range(BITS - 1, -1, -1) if not lead >> i & 1], a, b, a, b, budget):
        good = np.ones(len(i), bool)
        for mask in earlier:
            good &= ((fp[i] ^ fp[j]) & np.uint64(mask)) != 0
        if good.any():
            yield i[good], j[good]


def node_pairs(fp: np.ndarray, rest: list[int], alo: np.ndarray, ahi: np.ndarray, blo: np.ndarray, bhi: np.ndarray, budget: int):
    """Index pairs at `budget` or fewer differing bits, in portions, between tries that go down together: rows alo:ahi with rows blo:bhi, each range
    sorted by the bits `rest` from the first on. A range with itself gives each pair once; two ranges must else be apart."""
    n = len(fp)
    ones = []
    for i in rest:
        count = np.zeros(n + 1, np.int32)
        np.cumsum((fp >> np.uint64(i)) & np.uint64(1), out=count[1:])
        ones.append(count)
    stack = [(0, alo, ahi, blo, bhi, np.zeros(len(alo), np.int8))]
    while stack:
        level, alo, ahi, blo, bhi, apart = stack.pop()
        if len(alo) > FRONT:
            half = len(alo) // 2
            stack += [(level, *(x[:half] for x in (alo, ahi, blo, bhi, apart))), (level, *(x[half:] for x in (alo, ahi, blo, bhi, apart)))]
            continue
        if level == len(rest):
            # Equal fingerprints below each node: every pair of theirs.
            each = ahi - alo
            alo, blo, bhi = ranges(alo, each), np.repeat(blo, each), np.repeat(bhi, each)
            within = (alo >= blo) & (alo < bhi)
            blo = np.where(within, alo + 1, blo)
            i, j = np.repeat(alo, bhi - blo), ranges(blo, bhi - blo)
            if len(i):
                yield i, j
            continue
        single = (ahi - alo == 1) & (bhi - blo == 1)
        if single.any():
            i, j = alo[single], blo[single]
            i, j = i[i != j], j[i != j]
            good = np.bitwise_count(fp[i] ^ fp[j]) <= budget
            if good.any():
                yield i[good], j[good]
            alo, ahi, blo, bhi, apart = (x[~single] for x in (alo, ahi, blo, bhi, apart))
        if not len(alo):
            continue
        count = ones[level]
        asplit, bsplit = ahi - (count[ahi] - count[alo]), bhi - (count[bhi] - count[blo])
        same = alo == blo
        # Children: both 0, both 1, and crosswise with one more differing bit; a node with itself crosses once.
        next_ = [(alo, asplit, blo, bsplit, apart), (asplit, ahi, bsplit, bhi, apart), (alo, asplit, bsplit, bhi, apart + 1), tuple(x[~same] for x in (asplit, ahi, blo, bsplit, apart + 1))]
        lo1, hi1, lo2, hi2, d = (np.concatenate(x) for x in zip(*next_, strict=True))
        good = (hi1 > lo1) & (hi2 > lo2) & (d <= budget) & ~((lo1 == lo2) & (hi1 - lo1 == 1))
        if good.any():
            stack.append((level + 1, *(x[good] for x in (lo1, hi1, lo2, hi2, d))))


def merge_labels(label: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Least index of each cluster after the links i - j."""
    while True:
        least = np.minimum(label[i], label[j])
        before = label.copy()
        np.minimum.at(label, label[i], least)
        np.minimum.at(label, label[j], least)
        label = label[label]
        while (further := label[label] != label).any():
            label[further] = label[label[further]]
        if (label == before).all() and (label[i] == label[j]).all():
            return label


def trie_links(distinct: DataFrame, budget: int = BUDGET) -> DataFrame:
    """fp, root (a linked fingerprint, the same for a whole cluster of this trie) and links (documents at its links); fps without a link are left out."""
    if budget > BUDGET:
        raise ValueError(f"the tries' leading bits hold every link of {BUDGET} differing bits, not of {budget}")
    lead = F.array(*[F.lit(m - (1 << 64) if m >> 63 else m).cast("bigint") for m, _ in MASKS])
    dealt = distinct.select("fp", "copies", F.posexplode(lead).alias("trie", "mask")).select("fp", "copies", F.col("trie").cast("int"), F.col("fp").bitwiseAND(F.col("mask")).alias("head"))
    # A task holds its whole portion, so portions grow in number with the rows.
    portions_ = max(hot_share(distinct.sparkSession), -(-distinct.count() * len(MASKS) // PORTION_ROWS))
    dealt = dealt.repartition(portions_, F.xxhash64("trie", "head")).select("fp", "copies", "trie")

    def run(batches):
        got = [(b.column(0).to_numpy(), b.column(1).to_numpy(), b.column(2).to_numpy()) for b in batches]
        if not got:
            return
        fps, copies, tries = (np.concatenate(x) for x in zip(*got, strict=True))
        for k, (lead, earlier) in enumerate(MASKS):
            own = np.flatnonzero(tries == k)
            fp, weight = fps[own].view(np.uint64), copies[own]
            order = np.lexsort((fp & np.uint64(~lead & (1 << 64) - 1), fp & np.uint64(lead)))
            fp, weight = fp[order], weight[order]
            label, links = np.arange(len(fp)), np.zeros(len(fp), np.int64)
            for i, j in trie_pairs(fp, lead, earlier, budget):
                np.add.at(links, i, weight[j])
                np.add.at(links, j, weight[i])
                label = merge_labels(label, i, j)
            linked = np.flatnonzero(links)
            if len(linked):
                signed = fp.view(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(signed[linked]), pa.array(signed[label[linked]]), pa.array(links[linked])], names=["fp", "root", "links"])
        del fps, copies, tries
        give_back()

    return mapped(dealt, run, "fp bigint, root bigint, links bigint")


def components(edges: DataFrame) -> DataFrame:
    """node, root (the least of its component) of every node of edges(u, v). Alternating large-star and small-star; a written table per round."""
    now = materialise(edges.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct())
    mark = None
    while True:
        both = now.union(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        small_least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(small_least, "u").select(F.explode(F.array(F.struct(F.col("u").alias("u"), F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("e")).select("e.*").where("u <> v").distinct()
        new = materialise(small)
        seen = new.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        forget(now)
        now = new
        if seen == mark:
            break
        mark = seen
    return now.select(F.col("u").alias("node"), F.col("v").alias("root")).union(now.select(F.col("v"), F.col("v")).distinct())


def near_duplicates(docs: DataFrame, shingle: int = SHINGLE, budget: int = BUDGET, seed: int = SEED) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id (least doc_id reachable), links (documents within the budget, itself not counted)."""
    table = materialise(fingerprint_table(docs, shingle, seed))
    distinct = materialise(table.groupBy("fp").agg(F.count(F.lit(1)).alias("copies"), F.min("doc_id").alias("least")))
    stars = materialise(trie_links(distinct, budget))
    roots = components(stars.select(F.col("fp").alias("u"), F.col("root").alias("v")))
    near = roots.join(distinct, roots["node"] == distinct["fp"]).groupBy("root").agg(F.min("least").alias("component_id"))
    near = roots.join(near, "root").select(F.col("node").alias("fp"), "component_id")
    links = stars.groupBy("fp").agg(F.sum("links").alias("links"))
    known = distinct.join(near, "fp", "left").join(links, "fp", "left").select("fp", F.coalesce("component_id", "least").alias("component_id"), (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("links"))
    return table.join(materialise(known), "fp", "left").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id", "links")


def one_row_of_each(docs: DataFrame, classes: DataFrame) -> DataFrame:
    """The documents, same columns, with one row of each class: that of the least doc_id (none comes last), then of the least MD5 sum of its text.

    classes(doc_id, copy, root): copy is the MD5 sum, and rows of one doc_id and text may repeat. Rows of other texts under one doc_id stay apart.
    """
    key = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "copy")
    kept = classes.groupBy("root").agg(F.min(key).alias("k")).select(F.col("k.doc_id").alias("_id"), F.col("k.copy").alias("_kept"))
    names = {c: f"_own_{i}" for i, c in enumerate(docs.columns)}
    own = docs.select(*[F.col(f"`{c}`").alias(n) for c, n in names.items()], copy_key().alias("_copy"))
    ident = F.col(names["doc_id"])
    found = own.join(materialise(kept), (F.col("_copy") == F.col("_kept")) & ident.eqNullSafe(F.col("_id")), "left_semi").dropDuplicates([names["doc_id"], "_copy"])
    return found.select(*[F.col(n).alias(c) for c, n in names.items()])


def copy_key() -> Column:
    return F.unhex(F.md5(F.coalesce("text", F.lit(""))))


def one_of_each(docs: DataFrame, shingle: int = SHINGLE, budget: int = BUDGET, seed: int = SEED) -> DataFrame:
    """The documents, same columns, with one row of each component."""
    table = materialise(fingerprint_table(docs, shingle, seed))
    distinct = materialise(table.groupBy("fp").agg(F.count(F.lit(1)).alias("copies"), F.min("doc_id").alias("least")))
    stars = materialise(trie_links(distinct, budget))
    roots = components(stars.select(F.col("fp").alias("u"), F.col("root").alias("v"))).withColumnRenamed("node", "fp")
    classes = table.join(roots, "fp", "left").select("doc_id", "copy", F.coalesce("root", "fp").alias("root"))
    return one_row_of_each(docs, classes)
