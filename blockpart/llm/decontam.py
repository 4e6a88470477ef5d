"""Benchmark decontamination with an FM-index per shard of documents.

A shard is some SHARD_BYTES of documents. Its words become symbols (the number of the word among the benchmark's
words, 0 for others). A window holds benchmark words only, so only runs of such words that are as long as the
shortest window can hold one: these runs, with separators, are the indexed sequence. Windows are found by backward
search over the ranks of a level-wise wavelet tree, and their places by walking to sampled suffix positions.

Results for odd input: a null or empty text has no words and is clean; a repeated row gives a repeated result; an
item without words matches nothing; a null item_id counts as one item, shown as the empty string; equal windows of
several items count for each; without documents or items nothing is hit; other columns pass unread, whatever their names.
Words are told apart by 64-bit hashes (distinct for all benchmark words, which is checked).
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockpart.llm.common import ALNUM, LOWER, WordHash, byte_view, give_back, mapped, portions, ranges, row_slices, word_spans

WINDOW = 10
#: Bytes of benchmark text that one pass broadcasts; a larger benchmark takes several passes.
BLOCK_BYTES = 8 << 20
SAMPLE = 8
#: Bytes of text under one index.
SHARD_BYTES = 8 << 20


class WaveletTree:
    """Bits of a symbol sequence by level, most significant first, with counts of zeros before each place."""

    def __init__(self, symbols: np.ndarray, depth: int):
        self.depth, self.zeros, self.total = depth, [], []
        now = symbols
        for level in range(depth - 1, -1, -1):
            bit = (now >> level) & 1
            count = np.zeros(len(now) + 1, np.int32)
            np.cumsum(1 - bit, out=count[1:])
            self.zeros.append(count)
            self.total.append(int(count[-1]))
            now = np.concatenate([now[bit == 0], now[bit == 1]])

    def rank(self, symbol: np.ndarray, place: np.ndarray) -> np.ndarray:
        """How often each symbol stands before each place."""
        low, high = np.zeros_like(place), place
        for k, (count, total) in enumerate(zip(self.zeros, self.total, strict=True)):
            one = ((symbol >> (self.depth - 1 - k)) & 1).astype(bool)
            a, b = count[low], count[high]
            low, high = np.where(one, total + low - a, a), np.where(one, total + high - b, b)
        return high - low

    def access(self, place: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The symbol at each place and its rank there."""
        symbol, low, high = np.zeros_like(place), np.zeros_like(place), place
        for count, total in zip(self.zeros, self.total, strict=True):
            a, b, c = count[low], count[high], count[high + 1]
            one = c == b
            symbol = symbol * 2 + one
            low, high = np.where(one, total + low - a, a), np.where(one, total + high - b, b)
        return symbol, high - low


def suffix_order(symbols: np.ndarray) -> np.ndarray:
    """Suffixes in order, by doubling. Zeros are separators, each less than the next one, so no comparison runs past one."""
    n = len(symbols)
    gap = symbols == 0
    rank = np.where(gap, np.cumsum(gap) - 1, symbols.astype(np.int64) + int(gap.sum()))
    order = np.argsort(rank)
    step = 1
    while True:
        key = rank[order]
        new = np.empty(n, np.int64)
        new[order] = np.cumsum(np.concatenate([[0], (key[1:] != key[:-1]).astype(np.int64)]))
        rank = new
        if rank[order[-1]] == n - 1:
            return order
        follow = np.zeros(n, np.int64)
        follow[: n - step] = rank[step:] + 1
        rank = rank * (n + 1) + follow
        order = np.argsort(rank)
        step *= 2


class FMIndex:
    """Counts and places of short patterns in a sequence of symbols 1 .. alphabet - 1 with separators 0; the last symbol is a separator."""

    def __init__(self, symbols: np.ndarray, alphabet: int):
        order = suffix_order(symbols)
        self.n = len(symbols)
        last = symbols[order - 1]
        self.first = np.concatenate([[0], np.cumsum(np.bincount(symbols, minlength=alphabet))]).astype(np.int64)
        self.tree = WaveletTree(last.astype(np.int64), max(1, int(alphabet - 1).bit_length()))
        kept = (order % SAMPLE == 0) | (last == 0)
        self.kept = np.concatenate([[0], np.cumsum(kept)]).astype(np.int64)
        self.samples = order[kept]

    def search(self, patterns: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Row ranges of patterns of one length (a row each), from their last symbols to their first."""
        low, high = np.zeros(len(patterns), np.int64), np.full(len(patterns), self.n, np.int64)
        alive = np.arange(len(patterns))
        for k in range(patterns.shape[1] - 1, -1, -1):
            symbol = patterns[alive, k]
            low[alive] = self.first[symbol] + self.tree.rank(symbol, low[alive])
            high[alive] = self.first[symbol] + self.tree.rank(symbol, high[alive])
            high = np.maximum(high, low)
            alive = alive[high[alive] > low[alive]]
            if not len(alive):
                break
        return low, high

    def locate(self, row: np.ndarray) -> np.ndarray:
        """Places of the suffixes in these rows. What follows a separator is always sampled, so no walk passes one."""
        out, open_, now, steps = np.zeros(len(row), np.int64), np.arange(len(row)), row.copy(), 0
        while len(open_):
            there = self.kept[now + 1] > self.kept[now]
            out[open_[there]] = self.samples[self.kept[now[there]]] + steps
            open_, now = open_[~there], now[~there]
            if len(open_):
                symbol, rank = self.tree.access(now)
                now = self.first[symbol] + rank
                steps += 1
        return out


class Windows:
    """A block of the benchmark: word hashes in order, and the windows by length with the items that have them."""

    def __init__(self, rows: list[tuple[int | None, str | None]], window: int = WINDOW):
        data, at = byte_view(pa.array([t or "" for _, t in rows], pa.string()))
        low = LOWER[data]
        start, end, first = word_spans(ALNUM[data], at)
        self.names = ["" if i is None else str(i) for i, _ in rows]
        for base in range(0x9E3779B97F4A7C15, 0x9E3779B97F4A7C15 + 200, 2):
            self.base = base
            hashed = WordHash(base)(low, start, end)
            self.words, number = np.unique(hashed, return_inverse=True)
            raw = low.tobytes()
            if len({raw[a:b] for a, b in zip(start.tolist(), end.tolist(), strict=True)}) == len(self.words):
                break
        found: dict[int, dict[tuple[int, ...], set[int]]] = {}
        for i in range(len(rows)):
            own = (number[first[i] : first[i + 1]] + 1).tolist()
            size = min(window, len(own))
            for k in range(len(own) - size + 1 if size else 0):
                found.setdefault(size, {}).setdefault(tuple(own[k : k + size]), set()).add(i)
        self.patterns = {n: np.array(list(w), np.int64).reshape(-1, n) for n, w in found.items()}
        self.items = {n: [sorted(x) for x in w.values()] for n, w in found.items()}
        self.shortest = min(found, default=0)


def shard_hits(texts: pa.Array, block: Windows, hashes: WordHash) -> Iterator[tuple[int, int, list[tuple[int, int]], np.ndarray, set[int]]]:
    """For each text: number of words, merged spans of hit words as byte ranges, hit words and the block's items found."""
    data, at = byte_view(texts)
    n = len(at) - 1
    n_words = np.zeros(n, np.int64)
    symbols, origin, spans = [], [], []
    seen = 0
    for a, b in row_slices(at):
        part = data[at[a] : at[b]]
        start, end, first = word_spans(ALNUM[part], at[a : b + 1] - at[a])
        n_words[a:b] = np.diff(first)
        spans.append((start + at[a], end + at[a]))
        if block.shortest and len(start):
            hashed = hashes(LOWER[part], start, end)
            place = np.searchsorted(block.words, hashed)
            place[place == len(block.words)] = 0
            known = block.words[place] == hashed
            # Runs of known words, cut where a text ends.
            run_start, run_end, _ = word_spans(known, first)
            long = run_end - run_start >= block.shortest
            run_start, run_end = run_start[long], run_end[long]
            if len(run_start):
                count = run_end - run_start + 1  # with the separator
                index = ranges(run_start, count)
                tail = np.cumsum(count) - 1
                index[tail] = 0
                own = place[index] + 1
                own[tail] = 0
                symbols.append(own)
                origin.append(index + seen)
        seen += len(start)
    first_word = np.concatenate([[0], np.cumsum(n_words)])
    word_start = np.concatenate([s for s, _ in spans]) if spans else np.zeros(0, np.int64)
    word_end = np.concatenate([e for _, e in spans]) if spans else np.zeros(0, np.int64)
    hit_doc: list[np.ndarray] = []
    hit_item: list[np.ndarray] = []
    mark = np.zeros(len(word_start) + 1, np.int32)
    if symbols:
        text, source = np.concatenate(symbols), np.concatenate(origin)
        index = FMIndex(text, len(block.words) + 1)
        for size, patterns in block.patterns.items():
            low, high = index.search(patterns)
            count = high - low
            which = np.repeat(np.arange(len(patterns)), count)
            place = source[index.locate(ranges(low, count))]
            np.add.at(mark, place, 1)
            np.add.at(mark, place + size, -1)
            doc = np.searchsorted(first_word, place, "right") - 1
            pair = np.unique(np.stack([doc, which], 1), axis=0) if len(doc) else np.zeros((0, 2), np.int64)
            owners = block.items[size]
            many = np.array([len(owners[w]) for w in pair[:, 1]], np.int64)
            hit_doc.append(np.repeat(pair[:, 0], many))
            hit_item.append(np.array([i for w in pair[:, 1] for i in owners[w]], np.int64))
    hit = np.cumsum(mark[:-1]) > 0
    items: dict[int, set[int]] = {}
    if hit_doc:
        for d, i in zip(np.concatenate(hit_doc).tolist(), np.concatenate(hit_item).tolist(), strict=True):
            items.setdefault(d, set()).add(i)
    for d in range(n):
        a, b = int(first_word[d]), int(first_word[d + 1])
        if d in items:
            own = hit[a:b]
            s, e, _ = word_spans(own, np.array([0, b - a]))
            cut = [(int(word_start[a + x] - at[d]), int(word_end[a + y - 1] - at[d])) for x, y in zip(s.tolist(), e.tolist(), strict=True)]
            yield b - a, int(own.sum()), cut, np.flatnonzero(own), items[d]
        else:
            yield b - a, 0, [], np.zeros(0, np.int64), set()


def searched(batch: pa.RecordBatch, names: list[str], block: Windows, hashes: WordHash) -> pa.RecordBatch:
    """A shard with what this block of the benchmark adds to its n_words, hits, spans and items."""
    found = {"n_words": [], "hits": [], "spans": [], "items": []}
    old = {k: batch.column(names.index(k)) for k in ("hits", "spans", "items")}
    for d, (n, _, cut, words, own) in enumerate(shard_hits(batch.column(names.index("text")), block, hashes)):
        found["n_words"].append(n)
        if len(cut):
            found["hits"].append(sorted({*old["hits"][d].as_py(), *words.tolist()}))
            found["spans"].append(old["spans"][d].as_py() + [{"a": x, "b": y} for x, y in cut])
            found["items"].append(sorted({*old["items"][d].as_py(), *(block.names[i] for i in own)}))
        else:
            for k in old:
                found[k].append(old[k][d].as_py() if len(old[k][d]) else [])
    return pa.RecordBatch.from_arrays([pa.array(found[k], f.type) if k in found else batch.column(i) for i, (k, f) in enumerate(zip(names, batch.schema, strict=True))], schema=batch.schema)


def _blocks(benchmark: DataFrame, block_bytes: int) -> Iterator[list]:
    """The benchmark in blocks of about block_bytes, dealt by hash: (item_id, text) rows, one block on the driver at a time."""
    rows = benchmark.select(F.col("item_id"), F.col("text"))
    size = rows.agg(F.sum(F.octet_length("text") + 16)).first()[0] or 0
    n = max(1, -(-size // block_bytes))
    for k in range(n):
        own = rows if n == 1 else rows.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(n)) == k)
        yield [(r[0], r[1]) for r in own.toLocalIterator()]


def contamination(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, block_bytes: int = BLOCK_BYTES, keep: list[str] | None = None) -> DataFrame:
    """The columns `keep` (default doc_id) and text of each row, with n_words, hits (word numbers), spans (merged byte ranges) and items.

    A larger benchmark than block_bytes takes a narrow pass for each block, so that what is broadcast has a bound.
    """
    spark = docs.sparkSession
    keep = ["doc_id"] if keep is None else keep
    out = docs.select(*keep, "text", F.lit(None).cast("bigint").alias("n_words"), F.array().cast("array<bigint>").alias("hits"), F.array().cast("array<struct<a:bigint,b:bigint>>").alias("spans"), F.array().cast("array<string>").alias("items"))
    for rows in _blocks(benchmark, block_bytes):
        shared = spark.sparkContext.broadcast(Windows(rows, window))

        def scan(batches, shared=shared):
            block = shared.value
            hashes = WordHash(block.base)
            for whole in batches:
                names = whole.schema.names
                for batch in portions(whole, names.index("text"), SHARD_BYTES):
                    yield searched(batch, names, block, hashes)
            give_back()

        out = mapped(out, scan, out.schema)
    return out


def report(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """One row per document: doc_id, n_words, n_hit, n_items, items_sha256, contaminated."""
    found = contamination(docs, benchmark, **options)
    return found.select("doc_id", "n_words", F.size("hits").cast("long").alias("n_hit"), F.size("items").cast("long").alias("n_items"), F.sha2(F.concat_ws(",", F.array_sort("items")), 256).alias("items_sha256"), (F.size("hits") > 0).alias("contaminated"))


def without_spans(text: str | None, spans: list[tuple[int, int]]) -> str | None:
    """The text without the merged byte ranges."""
    if text is None or not spans:
        return text
    raw, out, done = text.encode(), [], 0
    for a, b in sorted(spans):
        if a > done:
            out.append(raw[done:a])
        done = max(done, b)
    return b"".join([*out, raw[done:]]).decode()


def cleaned(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """The documents, same columns (whatever their names), with benchmark passages cut out of their texts; those left without a word go."""
    names = {c: f"_own_{i}" for i, c in enumerate(docs.columns) if c != "text"}
    own = docs.select("text", *[F.col(f"`{c}`").alias(n) for c, n in names.items()])
    found = contamination(own, benchmark, keep=list(names.values()), **options).where("n_words = 0 or size(hits) < n_words")

    # Bytes between the spans, end to end; spans of several blocks may overlap.
    raw, none = F.col("text").cast("binary"), F.lit(b"")

    def gap(low, high):
        return F.substr(raw, (low + 1).cast("int"), F.greatest(high - low, F.lit(0)).cast("int"))

    start = F.struct(F.lit(0).cast("bigint").alias("done"), none.alias("out"))
    ended = F.aggregate(
        F.array_sort("spans"),
        start,
        lambda have, span: F.struct(F.greatest(have["done"], span["b"]).alias("done"), F.concat(have["out"], gap(have["done"], span["a"])).alias("out")),
        lambda have: F.concat(have["out"], gap(have["done"], F.octet_length("text").cast("bigint"))),
    )
    hit = F.size("spans") > 0
    out = found.withColumn("text", F.when(hit, ended.cast("string")).otherwise(F.col("text")))
    if size := names.get("n_chars"):
        out = out.withColumn(size, F.when(hit, F.length("text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col(size)))
    return out.select(*[F.col("text") if c == "text" else F.col(names[c]).alias(c) for c in docs.columns])
