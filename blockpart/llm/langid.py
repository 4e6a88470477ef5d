"""Language identification: script ranges narrow the candidates, then Viterbi over words labels spans.

Learned from labelled texts: for each language the counts of character n-grams (1 to 4, with word borders, in hashed
buckets) and the scripts in which it is written. A word's score for a language is the mean log probability of its n-grams;
languages that do not use the word's script are out unless none does. The best path over a text's words pays a penalty for
each switch, and its runs are the spans of one language each. Texts of a batch go through the recursion side by side.

Training reads at most PER_LANGUAGE labelled texts of each language in expectation (chosen by a hash), and gathers one number
for each bucket and language, whatever the input's size. Prediction reads whole texts.

Results for odd input: null text, or one without a letter, is `und` with score 0 and no spans; words without letters take the label of
their neighbours; equal rows get equal labels; null labels are not learned from; ties go to the language that sorts first; without any
labelled text all is `und`; other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from blockpart.llm.common import SOLID, WordHash, byte_view, give_back, mapped, portions, row_slices, word_spans

PER_LANGUAGE = 2000
BUCKETS = 1 << 16
GRAMS = (1, 2, 3, 4)
PENALTY = 4.0
#: Words whose n-grams are laid out at once.
WORDS_AT_ONCE = 1 << 15
#: A language uses a script that holds at least this share of its letters.
SCRIPT_SHARE = 0.02
UND = "und"

#: First code points of script blocks (fixed values of Unicode) and their names; a code point belongs to the last block that starts at or before it.
SCRIPTS = (
    (0x41, "latin"), (0x370, "greek"), (0x400, "cyrillic"), (0x530, "armenian"), (0x590, "hebrew"), (0x600, "arabic"), (0x700, "other"), (0x900, "devanagari"), (0x980, "bengali"), (0xA00, "gurmukhi"), (0xA80, "gujarati"), (0xB00, "other"),
    (0xB80, "tamil"), (0xC00, "telugu"), (0xC80, "kannada"), (0xD00, "malayalam"), (0xD80, "sinhala"), (0xE00, "thai"), (0xE80, "lao"), (0xF00, "tibetan"), (0x1000, "myanmar"), (0x10A0, "georgian"), (0x1100, "hangul"), (0x1200, "ethiopic"),
    (0x13A0, "other"), (0x1780, "khmer"), (0x1800, "mongolian"), (0x18B0, "other"), (0x1E00, "latin"), (0x1F00, "greek"), (0x2000, "other"), (0x3040, "kana"), (0x3100, "other"), (0x3400, "han"), (0xA000, "other"), (0xAC00, "hangul"), (0xD7B0, "other"), (0xF900, "han"), (0xFB00, "other"), (0xFF21, "latin"), (0xFF66, "kana"), (0xFFA0, "hangul"), (0xFFE0, "other"), (0x20000, "han"), (0x30000, "other"),
)
STARTS = np.array([a for a, _ in SCRIPTS])
NAMES = sorted({n for _, n in SCRIPTS})
KIND = np.array([NAMES.index(n) for _, n in SCRIPTS])


@lru_cache(1)
def letters() -> np.ndarray:
    """Whether each code point is a letter."""
    return np.array([chr(i).isalpha() for i in range(0x110000)])


def word_table(data: np.ndarray, start: np.ndarray, end: np.ndarray, known: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray, list[str]]:
    """Each word's number among the distinct words; those' hashes and numbers of occurrences; and, lower-cased, those whose hash is not `known`."""
    hashed, first, number, many = np.unique(WORDS(data, start, end), return_index=True, return_inverse=True, return_counts=True)
    if known is not None and len(known):
        first = first[known[np.minimum(np.searchsorted(known, hashed), len(known) - 1)] != hashed]
    raw = data.tobytes()
    return number, hashed, many, [raw[a:b].decode("utf-8", "replace").lower() for a, b in zip(start[first].tolist(), end[first].tolist(), strict=True)]


class Memo:
    """Scores of words seen before, by hash; emptied when it holds too many."""

    def __init__(self, model: "Model", most: int = 500_000):
        self.model, self.most = model, most
        self.clear()

    def clear(self) -> None:
        self.hashes, self.score, self.letters = np.zeros(0, np.uint64), np.zeros((0, len(self.model.languages))), np.zeros(0, np.int64)

    def look_up(self, data: np.ndarray, start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        if len(self.hashes) > self.most:
            self.clear()
        number, hashed, _, words = word_table(data, start, end, self.hashes)
        if words:
            score, n_letters = self.model.scores(words)
            new = hashed if not len(self.hashes) else hashed[self.hashes[np.minimum(np.searchsorted(self.hashes, hashed), len(self.hashes) - 1)] != hashed]
            place = np.searchsorted(self.hashes, new)
            self.hashes, self.letters = np.insert(self.hashes, place, new), np.insert(self.letters, place, n_letters)
            self.score = np.insert(self.score, place, score, axis=0)
        at = np.searchsorted(self.hashes, hashed)
        return self.score[at][number], self.letters[at][number]


WORDS = WordHash()


def features(words: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(word, bucket) pairs of all n-grams; each word's number of letters; and its main script."""
    text = " " + " ".join(words) + " "
    code = np.frombuffer(text.encode("utf-32-le", "replace"), np.uint32).astype(np.int64)
    space = np.zeros(len(code), bool)
    lengths = np.array([len(w) for w in words], np.int64)
    border = np.concatenate([[0], np.cumsum(lengths + 1)])
    space[border] = True
    alpha = letters()[code] & ~space
    owner = np.cumsum(space) - 1
    kept = np.where(alpha, code, 32)
    n_letters = np.add.reduceat(alpha, border[:-1], dtype=np.int64) if len(words) else np.zeros(0, np.int64)
    scripts = KIND[np.maximum(np.searchsorted(STARTS, code, "right") - 1, 0)]
    tally = np.bincount(owner[alpha] * len(NAMES) + scripts[alpha], minlength=len(words) * len(NAMES)).reshape(len(words), len(NAMES))
    who, what = [], []
    mixed = np.zeros(len(code), np.uint64)
    for n in range(1, max(GRAMS) + 1):
        stop = len(code) - n + 1
        if stop <= 0:
            break
        mixed = mixed[:stop] * np.uint64(0x100000001B3) + kept[n - 1 :].astype(np.uint64) + np.uint64(n)
        if n not in GRAMS:
            continue
        # An n-gram belongs to the word it starts in or just before; it may not run over the border at the word's end.
        inner = np.arange(stop)
        own = owner[:stop]
        fits = inner + n - 1 <= border[np.minimum(own + 1, len(border) - 1)]
        some = fits & (own < len(words)) & (alpha[:stop] | (alpha[1 : stop + 1] if n > 1 else False)) if len(code) > stop or n > 1 else fits & alpha[:stop]
        key = (mixed[some] * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - 16)
        who.append(own[some])
        what.append(key.astype(np.int64) % BUCKETS)
    return (np.concatenate(who), np.concatenate(what), n_letters, tally.argmax(1)) if who else (np.zeros(0, np.int64), np.zeros(0, np.int64), n_letters, tally.argmax(1))


class Model:
    """Log probabilities of buckets by language, and which language uses which script."""

    def __init__(self, languages: list[str], counts: np.ndarray, scripts: np.ndarray):
        self.languages = languages
        total = counts.sum(1, keepdims=True)
        self.logs = np.log((counts + 0.5) / (total + 0.5 * BUCKETS)).T.astype(np.float64).copy() if languages else np.zeros((BUCKETS, 0))
        self.uses = (scripts >= SCRIPT_SHARE * np.maximum(scripts.sum(1, keepdims=True), 1)).T if languages else np.zeros((len(NAMES), 0), bool)

    def scores(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """For each word and language the mean log probability times its letters; and the numbers of letters."""
        parts = [self._scores(words[k : k + WORDS_AT_ONCE]) for k in range(0, len(words), WORDS_AT_ONCE)]
        return np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts])

    def _scores(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        who, what, n_letters, script = features(words)
        total = np.zeros((len(words), len(self.languages)))
        many = np.maximum(np.bincount(who, minlength=len(words)), 1)
        for k in range(len(self.languages)):
            total[:, k] = np.bincount(who, self.logs[what, k], minlength=len(words))
        out = total / many[:, None] * np.minimum(n_letters, 12)[:, None]
        allowed = self.uses[script]
        barred = ~allowed & allowed.any(1, keepdims=True) & (n_letters > 0)[:, None]
        return np.where(barred, -1e6, np.where((n_letters > 0)[:, None], out, 0.0)), n_letters


def best_paths(score: np.ndarray, first: np.ndarray, penalty: float) -> np.ndarray:
    """The best label of each word of each text (words first[i] .. first[i + 1] - 1): texts side by side, one word after another."""
    many, n_lang = np.diff(first), score.shape[1]
    label = np.zeros(len(score), np.int16)
    by_size = np.argsort(-many, kind="stable")
    size = many[by_size]
    begin = first[:-1][by_size]
    longest = int(size[0]) if len(size) else 0
    if n_lang == 1 or not longest:
        return label
    live = np.append(np.searchsorted(-size, -np.arange(longest), "left"), 0)  # texts with more than t words
    came = np.zeros(len(score), np.int16)
    stay = np.zeros((len(score), n_lang), bool)
    value = score[begin[: live[0]]]
    for t in range(longest):
        n, next_ = live[t], live[t + 1]
        if t:
            at = begin[:n] + t
            lead = value.argmax(1)
            jump = value[np.arange(n), lead] - penalty
            keep = value >= jump[:, None]
            stay[at], came[at] = keep, lead
            value = np.where(keep, value, jump[:, None]) + score[at]
        if next_ < n:
            label[begin[next_:n] + t] = value[next_:].argmax(1)
            value = value[:next_]
    for t in range(longest - 1, 0, -1):
        at = begin[: live[t]] + t
        now = label[at]
        label[at - 1] = np.where(stay[at, now], now, came[at])
    return label


def label_texts(texts: pa.Array, model: Model, penalty: float = PENALTY, memo: Memo | None = None) -> Iterator[tuple[str, float, list[tuple[int, int, str]]]]:
    """For each text: language, score, and spans (first and end byte, language)."""
    data, at = byte_view(texts)
    memo = memo or Memo(model)
    for a, b in row_slices(at):
        part, here = data[at[a] : at[b]], at[a : b + 1] - at[a]
        start, end, first = word_spans(SOLID[part], here)
        if not len(start) or not model.languages:
            yield from ((UND, 0.0, []) for _ in range(b - a))
            continue
        score, weight = memo.look_up(part, start, end)
        label = best_paths(score, first, penalty)
        doc = np.repeat(np.arange(b - a), np.diff(first))
        share = np.bincount(doc * len(model.languages) + label, weight, (b - a) * len(model.languages)).reshape(b - a, -1)
        total = share.sum(1)
        lead = share.argmax(1)
        change = np.flatnonzero(np.concatenate([[True], (doc[1:] != doc[:-1]) | (label[1:] != label[:-1])]))
        stop = np.append(change[1:], len(doc)) - 1
        owner = np.searchsorted(doc[change], np.arange(b - a + 1))
        begins, ends = start[change] - here[doc[change]], end[stop] - here[doc[change]]
        for i in range(b - a):
            if total[i] == 0:
                yield UND, 0.0, []
            else:
                own = range(owner[i], owner[i + 1])
                yield model.languages[lead[i]], float(share[i, lead[i]] / total[i]), [(int(begins[k]), int(ends[k]), model.languages[label[change[k]]]) for k in own]


def train(labelled: DataFrame, per_language: int = PER_LANGUAGE) -> Model:
    """Fit on text and lang; about per_language texts of each language at most, those of least hash."""
    sizes = {r[0]: r[1] for r in labelled.where("lang is not null and text is not null").groupBy("lang").count().collect()}
    languages = sorted(sizes)
    if not languages:
        return Model([], np.zeros((0, BUCKETS)), np.zeros((0, len(NAMES))))
    share = F.create_map(*[x for k in languages for x in (F.lit(k), F.lit(int(min(1.0, per_language / sizes[k]) * (1 << 30))))])
    chosen = labelled.where(F.col("lang").isNotNull() & F.col("text").isNotNull()).select("text", "lang").where(F.pmod(F.xxhash64("text"), F.lit(1 << 30)) < share[F.col("lang")])

    def run(batches):
        counts: dict[str, np.ndarray] = {}
        for batch in batches:
            tags = np.array(batch.column(1).to_pylist(), object)
            for tag in dict.fromkeys(tags.tolist()):
                data, at = byte_view(batch.column(0).filter(pa.array(tags == tag)))
                own = counts.setdefault(tag, np.zeros(BUCKETS + len(NAMES), np.int64))
                for a, b in row_slices(at):
                    part = data[at[a] : at[b]]
                    start, end, _ = word_spans(SOLID[part], at[a : b + 1] - at[a])
                    if len(start):
                        _, _, many, words = word_table(part, start, end)
                        for k in range(0, len(words), WORDS_AT_ONCE):
                            who, what, n_letters, script = features(words[k : k + WORDS_AT_ONCE])
                            times = many[k : k + WORDS_AT_ONCE]
                            own[:BUCKETS] += np.bincount(what, times[who], BUCKETS).astype(np.int64)
                            own[BUCKETS:] += np.bincount(script, n_letters * times, len(NAMES)).astype(np.int64)
        give_back()
        for tag, own in counts.items():
            some = np.flatnonzero(own)
            yield pa.RecordBatch.from_arrays([pa.array([tag] * len(some), pa.string()), pa.array(some), pa.array(own[some])], names=["lang", "bucket", "n"])

    table = np.zeros((len(languages), BUCKETS + len(NAMES)))
    for r in mapped(chosen, run, "lang string, bucket bigint, n bigint").groupBy("lang", "bucket").agg(F.sum("n")).collect():
        table[languages.index(r[0]), r[1]] = r[2]
    return Model(languages, table[:, :BUCKETS], table[:, BUCKETS:])


def predict(docs: DataFrame, model: Model, keep: list[str] | None = None, penalty: float = PENALTY, spans: bool = True, text: str = "text") -> DataFrame:
    """The columns `keep` (default doc_id), lang_pred, score and spans."""
    keep = ["doc_id"] if keep is None else keep
    shared = docs.sparkSession.sparkContext.broadcast(model)
    own = docs.select(*keep) if text in keep else docs.select(*keep, text)
    at = own.columns.index(text)
    kind = pa.list_(pa.struct([("a", pa.int64()), ("b", pa.int64()), ("lang", pa.string())]))

    def run(batches):
        memo = Memo(shared.value)
        for batch in batches:
            for part in portions(batch, at):
                found = list(label_texts(part.column(at), shared.value, penalty, memo))
                more = [pa.array([[{"a": a, "b": b, "lang": g} for a, b, g in f[2]] for f in found], kind)] if spans else []
                yield pa.RecordBatch.from_arrays([*part.columns[: len(keep)], pa.array([f[0] for f in found], pa.string()), pa.array([f[1] for f in found], pa.float64()), *more], names=[*keep, "lang_pred", "score", *(["spans"] if spans else [])])
        del memo
        give_back()

    schema = ", ".join([*(f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in keep), "lang_pred string, score double", *(["spans array<struct<a:bigint,b:bigint,lang:string>>"] if spans else [])])
    return mapped(own, run, schema)


def held_out(doc_id) -> F.Column:
    return F.coalesce(F.crc32(F.col(doc_id).cast("string").cast("binary")) % 4 == 2, F.lit(False))


def report(docs: DataFrame, **options) -> DataFrame:
    """doc_id, held_out, lang_pred, score, n_spans; learned from the rest of the labelled rows."""
    model = train(docs.where(~held_out("doc_id")), **options)
    out = predict(docs, model)
    return out.select("doc_id", held_out("doc_id").alias("held_out"), "lang_pred", "score", F.size("spans").cast("long").alias("n_spans"))


def identified(docs: DataFrame, **options) -> DataFrame:
    """The documents, same columns, whose language can be told."""
    model = train(docs.where(~held_out("doc_id")), **options)
    names = {c: f"_own_{i}" for i, c in enumerate(docs.columns)}
    own = docs.select(*[F.col(f"`{c}`").alias(n) for c, n in names.items()])
    found = predict(own, model, keep=list(names.values()), spans=False, text=names["text"])
    return found.where(F.col("lang_pred") != UND).select(*[F.col(n).alias(c) for c, n in names.items()])
