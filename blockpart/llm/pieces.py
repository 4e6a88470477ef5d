"""SentencePiece encoding and decoding by a streaming Viterbi pass.

The vocabulary file's pieces and scores are read as a unigram model: the best segmentation has the greatest sum of scores (exact sums of
the file's scores), then the fewest pieces, then the longest last piece. A character in no piece, when byte fallback is on, is
spelled in byte pieces. The pass keeps scores and backpointers for the last `longest` places only, and commits ids as soon as the
paths from all places that can still be reached share a boundary.

With spaces turned into U+2581, no piece has one after another character (checked when the file is read), so all paths meet
in front of each run of them: units that start there are encoded once and kept in a memo of bounded size.

Results for odd input: null gives no ids and decodes to null; an empty text gives no ids; repeated rows repeat; decode(encode(text)) is text, whatever it
holds (U+2581 itself excepted: it is spelled in bytes); an empty table gives no row; other columns are not read.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockpart.llm.common import give_back, mapped, portions, ranges

SPACE = "▁"
MEMO = 250_000
VOCABULARY = "/opt/tokenizers/piece_bpe_32k.model"


def read_model(path: str) -> list[tuple[str, float, int]]:
    """Pieces, scores and kinds of a SentencePiece file (a protocol buffer: field 1 repeats, with piece 1, score 2, kind 3)."""
    from sentencepiece import sentencepiece_model_pb2

    model = sentencepiece_model_pb2.ModelProto()
    with open(path, "rb") as file:
        model.ParseFromString(file.read())
    return [(p.piece, p.score, p.type) for p in model.pieces]


class Vocabulary:
    """Normal pieces with scores and ids, byte pieces, and a trie of nested tables, with scores under the empty key."""

    #: Kinds in the file's format: fixed values.
    NORMAL, BYTE = (1, 4), 6

    def __init__(self, pieces: list[tuple[str, float, int]]):
        self.texts = [p for p, _, _ in pieces]
        self.bytes = {int(p[1:-1], 16): i for i, (p, _, kind) in enumerate(pieces) if kind == self.BYTE}
        self.byte_of = {i: b for b, i in self.bytes.items()}
        # A one-character piece of U+2581 stands for a space.
        self.pieces = {p: (score, i) for i, (p, score, kind) in enumerate(pieces) if kind in self.NORMAL}
        self.trie: dict = {}
        for p, (score, _) in self.pieces.items():
            node = self.trie
            for c in p:
                node = node.setdefault(c, {})
            node[""] = score
        self.longest = max(map(len, self.pieces), default=1)
        self.worst = min((s for s, _ in self.pieces.values()), default=0.0) - 10.0
        self.splits = not any(SPACE in p.lstrip(SPACE) for p in self.pieces)


def extend(text: str, first: int, stop: int, score: list, many: list, back: list, vocabulary: Vocabulary) -> None:
    """Push the best scores of places first .. stop - 1 on along the trie, to at most len(text)."""
    root, n, worst = vocabulary.trie, len(text), vocabulary.worst
    for i in range(first, stop):
        node, own, pieces = root, score[i], many[i] - 1
        for j in range(i, n):
            node = node.get(text[j])
            if node is None:
                break
            if "" in node:
                value = own + node[""]
                k = j + 1
                if value > score[k] or (value == score[k] and pieces > many[k]):
                    score[k], many[k], back[k] = value, pieces, i
        if text[i] not in root or "" not in root[text[i]]:
            value, k = own + worst, i + 1
            if value > score[k] or (value == score[k] and pieces > many[k]):
                score[k], many[k], back[k] = value, pieces, i


NEVER = float("-inf")


def streaming_viterbi(chunks: Iterator[str], vocabulary: Vocabulary) -> Iterator[list[int]]:
    """Ids of the best segmentation of the text in chunks, yielded whenever all paths that can still win share a boundary.

    The window holds the places from the last shared boundary on. Once the scores at a place are final, paths end at the
    places up to `longest` ahead of it; all are walked back until they meet.
    """
    longest = vocabulary.longest
    text, done = "", 0
    score, many, back = [0.0], [0], [0]
    for chunk in chunks:
        for k in range(0, len(chunk), longest):
            part = chunk[k : k + longest]
            text += part
            score += [NEVER] * len(part)
            many += [0] * len(part)
            back += [0] * len(part)
            if (sure := len(text) - longest) <= done:
                continue
            extend(text, done, sure, score, many, back, vocabulary)
            done = sure
            if done < 2 * longest:
                continue
            fronts = {j for j in range(done, len(text) + 1) if score[j] > NEVER}
            while len(fronts) > 1:
                far = max(fronts)
                fronts.discard(far)
                fronts.add(back[far])
            (shared,) = fronts
            if shared:
                yield spell(text, back, shared, vocabulary)
                text, done = text[shared:], done - shared
                score, many, back = score[shared:], many[shared:], [b - shared if b > shared else 0 for b in back[shared:]]
    if text:
        extend(text, done, len(text), score, many, back, vocabulary)
        yield spell(text, back, len(text), vocabulary)


def spell(text: str, back: list[int], at: int, vocabulary: Vocabulary) -> list[int]:
    """Ids of the pieces on the path that ends at `at`."""
    out = []
    while at > 0:
        piece = text[back[at] : at]
        if piece in vocabulary.pieces:
            out.append([vocabulary.pieces[piece][1]])
        else:
            out.append([vocabulary.bytes[b] for b in piece.replace(ESCAPED, SPACE).encode()])
        at = back[at]
    return [i for ids in reversed(out) for i in ids]


#: Stands for a U+2581 of the text itself; a lone surrogate, so no text holds it.
ESCAPED = "\udc81"
UNIT = re.compile(f"{SPACE}+[^{SPACE}]*|[^{SPACE}]+")


class PieceTables:
    """Hashes of the pieces by length, with their scores and ids, and hash prefixes of many units at once."""

    BASE = np.uint64(0x9E3779B97F4A7C15)

    def __init__(self, vocabulary: Vocabulary):
        self.longest, self.worst = vocabulary.longest, vocabulary.worst
        by: dict[int, list[tuple[int, float, int]]] = {}
        for p, (score, i) in vocabulary.pieces.items():
            h = 0
            for c in p:
                h = (h * int(self.BASE) + ord(c) + 1) % (1 << 64)
            by.setdefault(len(p), []).append((h, score, i))
        self.by = {}
        for n, rows in by.items():
            rows.sort()
            hashes = np.array([r[0] for r in rows], np.uint64)
            if (hashes[1:] == hashes[:-1]).any():
                raise ValueError("two pieces share a hash")
            self.by[n] = hashes, np.array([r[1] for r in rows]), np.array([r[2] for r in rows])
        self.power = np.array([pow(int(self.BASE), n, 1 << 64) for n in range(self.longest + 1)], np.uint64)

    def prefixes(self, units: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Lengths, code points (a row each, filled with zeros), and hashes of all prefixes."""
        size = np.array([len(u) for u in units])
        flat = np.frombuffer("".join(units).encode("utf-32-le", "surrogatepass"), np.uint32)
        code = np.zeros((len(units), int(size.max())), np.uint32)
        code[np.arange(code.shape[1]) < size[:, None]] = flat
        code = np.asfortranarray(code)
        hashed = np.zeros((len(units), code.shape[1] + 1), np.uint64, order="F")
        for k in range(code.shape[1]):
            hashed[:, k + 1] = hashed[:, k] * self.BASE + code[:, k].astype(np.uint64) + np.uint64(1)
        return size, code, hashed

    def find(self, n: int, hashed: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Whether each hash is that of a piece of n characters, and where in the table."""
        table = self.by[n][0]
        at = np.minimum(np.searchsorted(table, hashed), len(table) - 1)
        return table[at] == hashed, at


class Encoder:
    """Encodes texts unit by unit. Units of at most one piece's length, which a window holds whole, are solved side by side; all longer ones go through the streaming pass."""

    def __init__(self, vocabulary: Vocabulary, memo: int = MEMO):
        self.vocabulary, self.most, self.memo, self.tables = vocabulary, memo, {}, PieceTables(vocabulary)

    def solve(self, units: list[str]) -> None:
        """Put the ids of units of at most one piece's length into the memo: the pass of streaming_viterbi, one place of all units after another."""
        t = self.tables
        units.sort(key=len, reverse=True)
        size, code, hashed = t.prefixes(units)
        shape = hashed.shape
        score, many = np.full(shape, NEVER, order="F"), np.zeros(shape, np.int32, order="F")
        back, ids = np.zeros(shape, np.int32, order="F"), np.zeros(shape, np.int32, order="F")
        score[:, 0] = 0.0
        for j in range(1, shape[1]):
            n = int(np.searchsorted(-size, -j, "right"))
            best, pieces, from_, which = score[:n, j], many[:n, j], back[:n, j], ids[:n, j]
            for l in range(min(j, t.longest), 0, -1):
                if l not in t.by and l > 1:
                    continue
                if l in t.by:
                    found, at = t.find(l, hashed[:n, j] - hashed[:n, j - l] * t.power[l])
                else:
                    found, at = np.zeros(n, bool), np.zeros(n, np.int64)
                if l == 1:
                    rows = np.arange(n)
                    gain = np.where(found, t.by[1][1][at], t.worst) if 1 in t.by else np.full(n, t.worst)
                    new = np.where(found, t.by[1][2][at], -1 - code[:n, j - 1].astype(np.int64)) if 1 in t.by else -1 - code[:n, j - 1].astype(np.int64)
                else:
                    rows = np.flatnonzero(found)
                    gain, new = t.by[l][1][at[rows]], t.by[l][2][at[rows]]
                value, number = score[rows, j - l] + gain, many[rows, j - l] - 1
                better = (value > best[rows]) | ((value == best[rows]) & (number > pieces[rows]))
                rows = rows[better]
                best[rows], pieces[rows], from_[rows], which[rows] = value[better], number[better], j - l, new[better]
        count = -many[np.arange(len(units)), size]
        out = np.zeros((len(units), int(count.max())), np.int32)
        at, rows, left = size.copy(), np.arange(len(units)), count.copy()
        while len(rows):
            left[rows] -= 1
            out[rows, left[rows]] = ids[rows, at[rows]]
            at[rows] = back[rows, at[rows]]
            rows = rows[at[rows] > 0]
        spelled = (out < 0).any(1).tolist()
        raw, wide = out.tobytes(), 4 * out.shape[1]
        for k, (unit, n) in enumerate(zip(units, count.tolist(), strict=True)):
            if spelled[k]:
                own: list[int] = []
                for i in out[k, :n].tolist():
                    own += [i] if i >= 0 else [self.vocabulary.bytes[b] for b in chr(-1 - i).replace(ESCAPED, SPACE).encode()]
                self.memo[unit] = np.array(own, np.int32).tobytes()
            else:
                self.memo[unit] = raw[k * wide : k * wide + 4 * n]

    def units(self, text: str) -> list[str]:
        marked = SPACE + (text.replace(SPACE, ESCAPED) if SPACE in text else text).replace(" ", SPACE)
        if not self.vocabulary.splits:
            return [marked]
        if SPACE * 2 in marked or marked[-1] == SPACE:
            return UNIT.findall(marked)
        return [SPACE + x for x in marked[1:].split(SPACE)]

    def encode_all(self, texts: list[str | None]) -> list[bytes]:
        """Ids of each text as 32-bit numbers, end to end."""
        if len(self.memo) > self.most:
            self.memo.clear()
        memo, out = self.memo, []
        own = [self.units(t) if t else [] for t in texts]
        new = {u for units in own for u in units if u not in memo}
        window = self.vocabulary.longest
        long = {u for u in new if len(u) > window}
        if rest := list(new - long):
            for k in range(0, len(rest), 20_000):
                self.solve(rest[k : k + 20_000])
        rare = {u: np.array([i for ids in streaming_viterbi((u,), self.vocabulary) for i in ids], np.int32).tobytes() for u in long}
        for units in own:
            out.append(b"".join([memo[u] for u in units] if not rare else [memo.get(u) or rare[u] for u in units]))
        return out

    def encode(self, text: str) -> bytes:
        return self.encode_all([text])[0]


_READY: dict[str, tuple[Vocabulary, Encoder, "tuple[np.ndarray, np.ndarray]"]] = {}


def ready(pieces: list[tuple[str, float, int]]) -> tuple[Vocabulary, Encoder, "tuple[np.ndarray, np.ndarray]"]:
    """Vocabulary, encoder and decoding table, kept by this worker process for its later tasks."""
    key = hashlib.sha256(repr(pieces).encode()).hexdigest()
    if key not in _READY:
        own = Vocabulary(pieces)
        _READY.clear()
        _READY[key] = own, Encoder(own), decoder(own)
    return _READY[key]


def decoder(vocabulary: Vocabulary) -> "tuple[np.ndarray, np.ndarray]":
    """Bytes of all ids end to end, and where each begins."""
    raw = [bytes([vocabulary.byte_of[i]]) if i in vocabulary.byte_of else t.replace(SPACE, " ").encode() for i, t in enumerate(vocabulary.texts)]
    return np.frombuffer(b"".join(raw), np.uint8), np.concatenate([[0], np.cumsum([len(r) for r in raw])])


def decode(ids: np.ndarray, table: "tuple[np.ndarray, np.ndarray]") -> str:
    """The text: bytes of the pieces end to end, without the space put in front."""
    data, at = table
    raw = data[ranges(at[ids], at[ids + 1] - at[ids])].tobytes()
    return raw[1:].decode("utf-8", "replace")


def encode_texts(docs: DataFrame, vocabulary: str = VOCABULARY) -> DataFrame:
    """doc_id, text and ids of every row."""
    shared = docs.sparkSession.sparkContext.broadcast(read_model(vocabulary))

    def run(batches):
        _, encoder, _ = ready(shared.value)
        for batch in batches:
            for part in portions(batch, 1):
                texts = part.column(1).to_pylist()
                raw = encoder.encode_all(texts)
                size = np.array([len(r) // 4 for r in raw])
                offsets = pa.array(np.concatenate([[0], np.cumsum(size)]).astype(np.int32))
                ids = pa.ListArray.from_arrays(offsets, pa.array(np.frombuffer(b"".join(raw), np.int32)), mask=pa.array([t is None for t in texts], pa.bool_()))
                yield pa.RecordBatch.from_arrays([*part.columns, ids], names=["doc_id", "text", "ids"])
        encoder.memo.clear()
        give_back()

    return mapped(docs.select("doc_id", "text"), run, f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, text string, ids array<int>")


def decode_ids(encoded: DataFrame, vocabulary: str = VOCABULARY) -> DataFrame:
    """The other columns, with `decoded` in place of ids."""
    shared = encoded.sparkSession.sparkContext.broadcast(read_model(vocabulary))
    rest = [f for f in encoded.schema if f.name != "ids"]

    def run(batches):
        _, _, table = ready(shared.value)
        for batch in batches:
            k = batch.schema.names.index("ids")
            column = batch.column(k)
            at, flat = column.offsets.to_numpy(), column.values.to_numpy(zero_copy_only=False)
            gone = column.is_null().to_pylist()
            out = [None if n else decode(flat[at[i] : at[i + 1]].astype(np.int64), table) for i, n in enumerate(gone)]
            yield pa.RecordBatch.from_arrays([*(c for j, c in enumerate(batch.columns) if j != k), pa.array(out, pa.string())], names=[*(n for n in batch.schema.names if n != "ids"), "decoded"])

    return mapped(encoded, run, ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in rest), "decoded string"]))


def report(docs: DataFrame, vocabulary: str = VOCABULARY) -> DataFrame:
    """doc_id, ids, n_ids, ids_sha256 (of 32-bit little-endian ids), text_sha256 of what the ids decode to, and lossless."""
    shared = docs.sparkSession.sparkContext.broadcast(read_model(vocabulary))

    def run(batches):
        _, encoder, table = ready(shared.value)
        for batch in batches:
            for part in portions(batch, 1):
                texts = part.column(1).to_pylist()
                raw = encoder.encode_all(texts)
                size = np.array([len(r) // 4 for r in raw])
                flat = np.frombuffer(b"".join(raw), np.int32)
                offsets = pa.array(np.concatenate([[0], np.cumsum(size)]).astype(np.int32))
                gone = [t is None for t in texts]
                back = [decode(np.frombuffer(r, np.int32).astype(np.int64), table) for r in raw]
                ids = pa.ListArray.from_arrays(offsets, pa.array(flat), mask=pa.array(gone, pa.bool_()))
                sha = lambda x: hashlib.sha256(x).hexdigest()
                yield pa.RecordBatch.from_arrays([part.column(0), ids, pa.array(size.astype(np.int64)), pa.array([sha(r) for r in raw]), pa.array([None if n else sha(b.encode()) for b, n in zip(back, gone, strict=True)], pa.string()), pa.array([(t or "") == b for t, b in zip(texts, back, strict=True)])], names=["doc_id", "ids", "n_ids", "ids_sha256", "text_sha256", "lossless"])
        encoder.memo.clear()
        give_back()

    return mapped(docs.select("doc_id", "text"), run, f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, ids array<int>, n_ids bigint, ids_sha256 string, text_sha256 string, lossless boolean")
