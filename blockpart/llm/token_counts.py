"""Token counts by dynamic programming over a trie that the distinct pre-tokens share.

The pre-tokens of a portion of texts (units as in the encoder) are sorted, which makes the nodes of their trie runs of
rows at each depth. Forward scores and piece counts are computed once per node from those of its ancestors; a pre-token's count is
that of its terminal node, and a text's the sum over its pre-tokens. Counts equal the numbers of ids that encoding yields.

Results for odd input: a null text has null tokens, an empty one 0; repeated rows repeat; pre-tokens longer than
two pieces, which share next to no prefix, are counted by the streaming pass of the encoder; an empty table gives no row; other columns are not read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from blockpart.llm.common import give_back, mapped, portions
from blockpart.llm.pieces import ESCAPED, MEMO, NEVER, SPACE, VOCABULARY, Encoder, PieceTables, Vocabulary, read_model, streaming_viterbi


def trie_counts(units: list[str], tables: PieceTables) -> np.ndarray:
    """The number of tokens of each distinct unit; units must be sorted."""
    size, code, hashed = tables.prefixes(units)
    n, deep = code.shape
    new = np.zeros(n, bool)  # whether a row's prefix differs from the row above
    new[0] = True
    node = [np.zeros(n, np.int64)]  # by depth, the node of each row
    score, many = [np.zeros(1)], [np.zeros(1, np.int64)]
    out = np.zeros(n, np.int64)
    wide = np.array([1, 1, 2, 3, 4])
    for d in range(1, deep + 1):
        new[1:] |= code[1:, d - 1] != code[:-1, d - 1]
        node.append(np.cumsum(new) - 1)
        row = np.flatnonzero(new)
        row = row[size[row] >= d]
        place = node[d][row]
        best, pieces = np.full(node[d][-1] + 1, NEVER), np.zeros(node[d][-1] + 1, np.int64)
        tokens = np.zeros(len(best), np.int64)
        for l in range(min(d, tables.longest), 0, -1):
            if l not in tables.by and l > 1:
                continue
            found, at = tables.find(l, hashed[row, d] - hashed[row, d - l] * tables.power[l]) if l in tables.by else (np.zeros(len(row), bool), np.zeros(len(row), np.int64))
            if l == 1:
                some = np.arange(len(row))
                gain = np.where(found, tables.by[1][1][at], tables.worst) if 1 in tables.by else np.full(len(row), tables.worst)
                point = np.where(code[row, d - 1] == ord(ESCAPED), ord(SPACE), code[row, d - 1])
                cost = np.where(found, 1, wide[1 + (point >= 0x80) + (point >= 0x800) + (point >= 0x10000)])
            else:
                some = np.flatnonzero(found)
                gain, cost = tables.by[l][1][at[some]], 1
            above, own = node[d - l][row[some]], place[some]
            value, number = score[d - l][above] + gain, pieces_of[d - l][above] - 1 if d - l else np.full(len(some), -1)
            better = (value > best[own]) | ((value == best[own]) & (number > pieces[own]))
            own, above = own[better], above[better]
            best[own], pieces[own] = value[better], number[better]
            tokens[own] = many[d - l][above] + (cost[better] if l == 1 else 1)
        score.append(best)
        many.append(tokens)
        if d == 1:
            pieces_of = [np.zeros(1, np.int64)]
        pieces_of.append(pieces)
        done = size == d
        out[done] = tokens[node[d][done]]
    return out


class Counter:
    """Token counts of texts, with a memo of units."""

    def __init__(self, vocabulary: Vocabulary, memo: int = 2 * MEMO):
        self.encoder, self.most, self.memo = Encoder(vocabulary), memo, {}

    def counts(self, texts: list[str | None]) -> list[int | None]:
        if len(self.memo) > self.most:
            self.memo.clear()
        memo = self.memo
        own = [self.encoder.units(t) if t else [] for t in texts]
        new = {u for units in own for u in units if u not in memo}
        window = 2 * self.encoder.vocabulary.longest
        short = sorted(u for u in new if len(u) <= window)
        for k in range(0, len(short), 100_000):
            part = short[k : k + 100_000]
            memo.update(zip(part, trie_counts(part, self.encoder.tables).tolist(), strict=True))
        rare = {u: sum(map(len, streaming_viterbi((u,), self.encoder.vocabulary))) for u in new if len(u) > window}
        look = memo.__getitem__ if not rare else lambda u: memo[u] if u in memo else rare[u]
        return [None if t is None else sum(map(look, units)) for t, units in zip(texts, own, strict=True)]


_READY: dict[int, Counter] = {}


def token_counts(docs: DataFrame, vocabulary: str = VOCABULARY, keep: str = "doc_id") -> DataFrame:
    """keep, and n_tokens of every text."""
    shared = docs.sparkSession.sparkContext.broadcast(read_model(vocabulary))

    def run(batches):
        key = hash(tuple(shared.value))
        if key not in _READY:
            _READY.clear()
            _READY[key] = Counter(Vocabulary(shared.value))
        for batch in batches:
            for part in portions(batch, 1):
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(_READY[key].counts(part.column(1).to_pylist()), pa.int64())], names=[keep, "n_tokens"])

    return mapped(docs.select(keep, "text"), run, f"{keep} {docs.schema[keep].dataType.simpleString()}, n_tokens bigint")
