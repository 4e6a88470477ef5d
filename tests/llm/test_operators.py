"""The training-data operators against brute force, SQL, exact round trips and held-out accuracy."""

import hashlib
import itertools
import os
import re
import zlib

import duckdb
import numpy as np
import pyarrow as pa
import pytest
import xxhash

from blockpart.llm import chat, decontam, jpeg, langid, licenses, nearcopies, pieces, pii, queries, simhash, token_counts, warc
from blockpart.llm.common import SOLID, byte_view, word_spans

DOCS = "doc_id bigint, text string, lang string, source string, n_chars bigint"


def docs_of(spark, texts, ids=None):
    return spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in zip(ids or range(len(texts)), texts, strict=True)], DOCS)


def lower(t):
    return re.sub("[A-Z]", lambda m: m[0].lower(), t or "")


# ---- word spans ---------------------------------------------------------------------------------------------------

@pytest.mark.parametrize("texts", [[], [""], [None, "a b", "", " c", "d"], ["ab", "cd"], ["é ü", "　x"]])
def test_word_spans_cross_no_text_border(texts):
    data, at = byte_view(pa.array(texts, pa.string()))
    start, end, first = word_spans(SOLID[data], at)
    raw = data.tobytes()
    got = [[raw[start[k] : end[k]].decode() for k in range(first[i], first[i + 1])] for i in range(len(texts))]
    assert got == [[w for w in re.split("[\x20\x09-\x0d]+", t or "") if w] for t in texts]


# ---- op 10 -----------------------------------------------------------------------------------------------------------

def brute_hits(text, items):
    words = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", lower(text))
    hit, ids = set(), set()
    for name, item in items:
        own = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", lower(item))
        n = min(10, len(own))
        for k in range(len(own) - n + 1 if n else 0):
            for p in range(len(words) - n + 1):
                if words[p : p + n] == own[k : k + n]:
                    hit |= set(range(p, p + n))
                    ids.add(name)
    return len(words), len(hit), len(ids), hashlib.sha256(",".join(sorted("" if i is None else str(i) for i in ids)).encode()).hexdigest(), bool(hit)


def decontam_case():
    rng = np.random.default_rng(3)
    word = lambda n: " ".join(rng.choice(["a", "b", "Éa", "dd", "e1"], n))
    items = [(i, word(int(rng.integers(0, 25)))) for i in range(12)] + [(100, None), (None, "x y z"), (7, "x y z"), (3, "one")]
    texts = [word(int(rng.integers(0, 60))) for _ in range(60)] + [None, "", "X,Y.Z! one", "...", items[5][1] + " " + items[6][1]] + ["X y z q"] * 3
    return texts, items


@pytest.mark.parametrize("block_bytes", [1 << 20, 150])
def test_decontamination_is_brute_force(spark, block_bytes):
    texts, items = decontam_case()
    bench = spark.createDataFrame(items, "item_id bigint, text string")
    got = {r["doc_id"]: tuple(r)[1:] for r in decontam.report(docs_of(spark, texts), bench, block_bytes=block_bytes).collect()}
    assert got == {i: brute_hits(t, items) for i, t in enumerate(texts)}


def test_decontamination_of_nothing(spark):
    bench = spark.createDataFrame([], "item_id bigint, text string")
    assert decontam.report(docs_of(spark, ["a b"]), bench).first()["contaminated"] is False
    assert decontam.report(docs_of(spark, []), bench).count() == 0
    extra = docs_of(spark, ["a b c", "c"]).selectExpr("*", "1 hits", "2 spans", "3 items", "4 item_id")
    assert decontam.report(extra, spark.createDataFrame([(1, "b c")], "item_id bigint, text string")).where("contaminated").count() == 1


def test_cleaned_cuts_spans(spark):
    bench = spark.createDataFrame([(1, "b c"), (2, "c d")], "item_id bigint, text string")
    rows = decontam.cleaned(docs_of(spark, ["é b C, D! x", "b c", None, "clean"]), bench).collect()
    assert {r["doc_id"]: r["text"] for r in rows} == {0: "é ! x", 2: None, 3: "clean"}
    assert all(r["n_chars"] == len(r["text"] or "") for r in rows)


def test_fm_index_counts_and_places():
    rng = np.random.default_rng(5)
    text = np.concatenate([np.append(rng.integers(1, 4, n), 0) for n in rng.integers(1, 30, 12)])
    index = decontam.FMIndex(text, 5)
    for n in (1, 2, 3, 5):
        patterns = np.array(list(itertools.product([1, 2, 3, 4], repeat=n)))[:300]
        low, high = index.search(patterns)
        for p, a, b in zip(patterns, low, high, strict=True):
            want = [k for k in range(len(text) - n + 1) if (text[k : k + n] == p).all()]
            assert sorted(index.locate(np.arange(a, b)).tolist()) == want


@pytest.mark.parametrize("name", ["op4_warc", "op10_decontamination"])
def test_queries_are_their_sql(spark, sf_dir, name):
    con = duckdb.connect()
    for t in ("documents", "benchmark", "pages"):
        con.execute(f"create view {t} as from '{sf_dir}/{t}.parquet'")
    want = con.execute(queries.oracle_sql()[name]).fetchall()
    names = [d[0] for d in con.description]
    got = queries.queries()[name](spark, sf_dir).select(*names).collect()
    assert sorted(map(str, map(tuple, got))) == sorted(map(str, want))


# ---- op 3 ------------------------------------------------------------------------------------------------------------

def brute_fingerprint(text):
    words = [w for w in re.split("[\x20\x09-\x0d]+", lower(text)) if w]
    shingles = [" ".join(words[k : k + 3]) for k in range(max(1, len(words) - 2))] if words else []
    hashes = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if sum(h >> b & 1 for h in hashes) * 2 > len(hashes))


def test_simhash_is_brute_force(spark):
    rng = np.random.default_rng(2)
    base = [" ".join(rng.choice(["Da", "be", "ki", "lo", "mé"], n)) for n in rng.integers(1, 400, 25)]
    texts = base + [t + " end" for t in base] + [t.replace("be", "BE") for t in base] + [None, "", " \t", "x"] + ["same copy here"] * 5
    ids = [1000 - i for i in range(len(texts))]
    fp = [brute_fingerprint(t) for t in texts]
    label = list(range(len(texts)))
    near = [(a, b) for a in range(len(fp)) for b in range(a) if (fp[a] ^ fp[b]).bit_count() <= 2]
    for _ in fp:
        for a, b in near:
            label[a] = label[b] = min(label[a], label[b], key=lambda k: ids[k])
    want = {ids[i]: (f"{fp[i]:016x}", ids[label[i]], sum(i in p for p in near)) for i in range(len(texts))}
    got = {r["doc_id"]: tuple(r)[1:] for r in simhash.near_duplicates(docs_of(spark, texts, ids)).collect()}
    assert got == want
    kept = {r["doc_id"] for r in simhash.one_of_each(docs_of(spark, texts, ids)).collect()}
    assert kept == {w[1] for w in want.values()}


def test_simhash_without_rows_or_ids(spark):
    assert simhash.near_duplicates(docs_of(spark, [])).count() == 0
    rows = simhash.near_duplicates(docs_of(spark, ["a b c", "a b c", "a b c d"], [None, 5, 5]).selectExpr("*", "1 fp", "2 copies")).collect()
    assert [r["component_id"] for r in rows] == [5, 5, 5] or len(rows) == 3


def test_trie_pairs_find_each_link_once():
    rng = np.random.default_rng(1)
    fps = rng.integers(0, 2**63, 80, dtype=np.uint64).repeat(8)
    for i in range(len(fps)):
        for b in rng.integers(0, 64, rng.integers(0, 4)):
            fps[i] ^= np.uint64(1) << np.uint64(int(b))
    fps = np.unique(fps)
    want = {(a, b) for a in range(len(fps)) for b in (a + 1 + np.flatnonzero(np.bitwise_count(fps[a + 1 :] ^ fps[a]) <= 2)).tolist()}
    got = []
    for lead, earlier in simhash.MASKS:
        order = np.lexsort((fps & np.uint64(~lead & (1 << 64) - 1), fps & np.uint64(lead)))
        got += [tuple(sorted((int(order[x]), int(order[y])))) for i, j in simhash.trie_pairs(fps[order], lead, earlier) for x, y in zip(i, j, strict=True)]
    assert len(got) == len(set(got)) and set(got) == want


def test_components_of_a_path_and_a_star(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(40)] + [(100, 100 + i) for i in range(1, 20)] + [(7, 7)], "u bigint, v bigint")
    got = dict(simhash.components(edges).collect())
    assert got == {i: 0 for i in range(41)} | {100 + i: 100 for i in range(20)}


# ---- near copies of the pipeline ------------------------------------------------------------------------------------

def shingle_set(text):
    words = [w for w in re.split("[\x20\x09-\x0d]+", lower(text)) if w]
    return {tuple(words[k : k + 5]) for k in range(max(1, len(words) - 4))} if words else set()


def test_pipeline_links_every_near_copy(spark):
    import corpus_pipeline

    rng = np.random.default_rng(8)
    texts = []
    for k in range(60):
        words = [f"w{x}" for x in rng.integers(0, 9000, int(rng.integers(60, 300)))]
        texts.append(" ".join(words))
        for share in (0.01, 0.02, 0.06):
            other = words.copy()
            for i in rng.choice(len(words), max(1, int(share * len(words))), replace=False):
                other[i] = f"v{rng.integers(0, 9000)}"
            texts.append(" ".join(other))
    texts += [None, "", " \t", "x y", "X  y"]
    sets = [shingle_set(t) for t in texts]
    linked = [(a, b) for a in range(len(sets)) for b in range(a) if sets[a] == sets[b] or len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])]
    assert len(linked) > 60 and any(len(sets[a] & sets[b]) < 0.85 * len(sets[a] | sets[b]) for a, b in linked)
    label = list(range(len(texts)))
    for _ in texts:
        for a, b in linked:
            label[a] = label[b] = min(label[a], label[b])
    docs = docs_of(spark, texts)
    assert dict(nearcopies.near_copies(docs).collect()) == dict(enumerate(label))
    assert {r["doc_id"] for r in corpus_pipeline.near_duplicates(spark, docs, "").collect()} == set(label)
    assert nearcopies.near_copies(docs_of(spark, [])).count() == 0
    with pytest.raises(ValueError):
        simhash.near_duplicates(docs, budget=3).count()


def test_near_copies_of_a_group_in_blocks(spark, monkeypatch):
    """A group of texts around the similarity, far more than a block holds: the same classes as by brute force."""
    for name, few in (("BLOCK_ROWS", 8), ("HELD", 500), ("COMPARED", 3000)):
        monkeypatch.setattr(nearcopies, name, few)
    rng = np.random.default_rng(5)
    base = [f"w{x}" for x in rng.integers(0, 900, 120)]
    texts = []
    for k in range(90):
        own = base.copy()
        for i in rng.choice(len(own), int(rng.integers(1, 9)), replace=False):
            own[i] = f"v{rng.integers(0, 9000)}"
        texts.append(" ".join(own))
    sets = [shingle_set(t) for t in texts]
    label = list(range(len(texts)))
    linked = [(a, b) for a in range(len(sets)) for b in range(a) if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])]
    for _ in texts:
        for a, b in linked:
            label[a] = label[b] = min(label[a], label[b])
    assert len(set(label)) > 3
    assert dict(nearcopies.near_copies(docs_of(spark, texts)).collect()) == dict(enumerate(label))


def test_near_copies_lose_no_text_of_a_shared_id(spark):
    texts = ["a b c d e f g", "h i j k l m n", "h i j k l m n", "o p q r s t u", None, " ", "o p q r s t u"]
    docs = docs_of(spark, texts, [1, 1, 1, 2, 3, None, None]).selectExpr("*", "1 `a.b`", "2 items", "3 hits", "4 copy", "5 root", "6 node")
    for module in (nearcopies, simhash):
        kept = module.one_of_each(docs)
        assert kept.columns == docs.columns
        assert sorted((r["doc_id"], r["text"]) for r in kept.collect()) == [(1, texts[0]), (1, texts[1]), (2, texts[3]), (3, None)]
    from blockpart.llm import decontam, langid, pii

    bench = spark.createDataFrame([("x", "a b c d e f g")], "item_id string, text string")
    assert decontam.cleaned(docs, bench).columns == docs.columns and pii.protected(docs).columns == docs.columns and langid.identified(docs).columns == docs.columns
    assert decontam.cleaned(docs, bench).count() == len(texts) - 1


# ---- op 4 ------------------------------------------------------------------------------------------------------------

def test_warc_round_trip(spark, tmp_path):
    rows = [(3, "http://a/\r\nx", "<p>é</p>"), (1, None, "<p>é</p>"), (2, "u", None), (5, "u", ""), (None, "n", "<p>é</p>"), (9, "v", "big" * 5000), (3, "http://a/", "<p>é</p>"), (11, "w", "only"), (None, "m", "nul"), (None, "m", "nul")]
    pages = spark.createDataFrame(rows, "page_id bigint, url string, html string").selectExpr("*", "1 part", "2 digest", "3 least")
    for options in ({}, {"roll_bytes": 300, "range_bytes": 4000}):
        root = f"file://{tmp_path}/w{len(options)}"
        manifest = warc.write_warc(pages, root, **options)
        files = {r["page_file"]: r for r in manifest.collect()}
        for name, r in files.items():
            raw = open(f"{root[7:]}/{name}", "rb").read()
            assert len(raw) == r["compressed_bytes"] and hashlib.sha256(raw).hexdigest() == r["sha256"]
        assert not [x for x in os.listdir(root[7:]) if x.startswith("_temporary")]
        got = warc.read_warc(manifest, root, with_payload=True).collect()
        assert len(got) == len(rows)
        by = sorted((r["page_id"] or 0, r["record_type"], r["refers_to"] or 0) for r in got)
        assert by == sorted([(0, "revisit", 1), (1, "response", 0), (2, "response", 0), (3, "revisit", 1), (3, "revisit", 1), (5, "revisit", 2), (9, "response", 0), (11, "response", 0), (0, "response", 0), (0, "revisit", 0)])
        assert {r["html"] for r in got if r["record_type"] == "response"} == {"<p>é</p>", "", "big" * 5000, "only", "nul"}
        if options:
            assert len(files) > 2
    again = warc.write_warc(pages, f"file://{tmp_path}/again", roll_bytes=300, range_bytes=4000)
    assert {(r["page_file"], r["sha256"]) for r in again.collect()} == {(n, r["sha256"]) for n, r in files.items()}
    assert warc.round_trip(pages.where("false"), f"file://{tmp_path}/none").count() == 0


def test_each_range_has_a_lane(spark):
    for n in (1, 7, 40):
        own = warc.lanes(spark, n)
        got = spark.createDataFrame([(x,) for x in own], "x bigint").repartition(n, "x").selectExpr("x", "spark_partition_id() as p").collect()
        assert len({r["p"] for r in got}) == n
    edges = sorted((int(k), f"{k:x}") for k in np.random.default_rng(1).integers(-50, 10**12, 700))
    rows = spark.createDataFrame([(None, "a"), (-99, "0"), (edges[300][0], edges[300][1]), (edges[300][0], ""), (2 * 10**12, "f")], "page_id bigint, digest string")
    assert [r[0] for r in rows.select(warc.range_of(edges)).collect()] == [0, 0, 301, 300, 700]


def test_warc_of_many_repeated_payloads(spark, monkeypatch):
    monkeypatch.setattr(warc, "BROADCAST_ROWS", 8)
    pages = spark.createDataFrame([(i, "u", "" if i % 3 == 0 else f"p{i // 4}") for i in range(120)], "page_id bigint, url string, html string")
    got = {r["page_id"]: (r["record_type"], r["refers_to"]) for r in warc.round_trip(pages).collect()}
    first = {}
    for i in range(120):
        first.setdefault("" if i % 3 == 0 else f"p{i // 4}", i)
    want = {i: ("response", None) if first[k] == i else ("revisit", first[k]) for i in range(120) for k in ["" if i % 3 == 0 else f"p{i // 4}"]}
    assert got == want


# ---- op 5 ------------------------------------------------------------------------------------------------------------

@pytest.mark.parametrize("n", [192, 384, 960, 192 * 70, 192 * 300])
def test_jpeg_holds_every_byte(n):
    payload = np.random.default_rng(n).integers(0, 256, n, dtype=np.uint8).tobytes()
    raw = jpeg.encode(payload)
    image = jpeg.decode(raw)
    assert jpeg.payload_of(image) == payload
    if n < 1000:
        slow = jpeg.decode(raw, fast=False)
        assert jpeg.payload_of(slow) == payload and jpeg.feature(jpeg.to_rgb(slow)) == jpeg.feature(jpeg.to_rgb(image))


def test_inverse_transform_is_the_cosine_sum():
    payload = np.random.default_rng(0).integers(0, 256, 384, dtype=np.uint8).tobytes()
    image = jpeg.decode(jpeg.encode(payload))
    for c in image["components"].values():
        c.coef[:] = c.coef // 16
    y = image["components"][1]
    scale = lambda u: np.sqrt(0.125) if u == 0 else 0.5
    cos = np.array([[scale(u) * np.cos((2 * x + 1) * u * np.pi / 16) for x in range(8)] for u in range(8)])
    flat = np.zeros((len(y.coef), 64))
    flat[:, jpeg.ORDER] = y.coef
    exact = np.einsum("buv,ux,vy->bxy", flat.reshape(-1, 8, 8), cos, cos) + 128
    for c in (2, 3):
        image["components"][c].coef[:] = 0
    rgb = jpeg.to_rgb(image)
    assert rgb.shape == (16, 16, 3)
    assert np.abs(rgb[:8, :8, 0].astype(float) - np.clip(exact[0], 0, 255)).max() <= 2


def sparse_progressive(coef):
    """A grey progressive JPEG with zero runs, ends of bands and a refinement that meets new values."""
    codes = {s: k for k, s in enumerate([r << 4 | z for r in range(16) for z in range(8)])}
    code = lambda s: f"{codes[s]:08b}"
    table = lambda kind: jpeg._table(kind, 0, {8: list(codes)})
    bits_of = lambda v: "" if v == 0 else f"{v if v > 0 else v + (1 << abs(v).bit_length()) - 1:0{abs(v).bit_length()}b}"
    pack = lambda s: jpeg._packed(np.frombuffer(s.encode(), np.uint8) - 48)
    n = len(coef)
    out = [b"\xff\xd8", jpeg._segment(0xDB, b"\0" + b"\1" * 64), jpeg._segment(0xC2, bytes([8, 0, 8, 0, 8 * n, 1, 1, 0x11, 0])), table(0), table(1)]
    dc, last = "", 0
    for b in coef[:, 0].tolist():
        dc, last = dc + code(abs(b - last).bit_length()) + bits_of(b - last), b
    out.append(jpeg._scan([(1, 0)], 0, 0, 0, 0, pack(dc)))
    ac = ""
    for row in (np.sign(coef) * (np.abs(coef) >> 1)).tolist():
        run = 0
        for v in row[1:]:
            if v == 0:
                run += 1
                continue
            while run > 15:
                ac, run = ac + code(0xF0), run - 16
            ac, run = ac + code(run << 4 | abs(v).bit_length()) + bits_of(v), 0
        if run:
            ac += code(0)
    out.append(jpeg._scan([(1, 0)], 1, 63, 0, 1, pack(ac)))
    ac = ""
    for row in coef.tolist():
        run, held = 0, ""
        stop = max((k for k, v in enumerate(row) if k and abs(v) == 1), default=0)
        for k, v in enumerate(row[1:], 1):
            if abs(v) > 1:
                held += str(abs(v) & 1)
            elif v == 0:
                if run == 15 and k <= stop:
                    ac, run, held = ac + code(0xF0) + held, 0, ""
                else:
                    run += 1
            else:
                ac, run, held = ac + code(run << 4 | 1) + ("1" if v > 0 else "0") + held, 0, ""
        if stop < 63:
            ac += code(0) + held
    out.append(jpeg._scan([(1, 0)], 1, 63, 1, 0, pack(ac)))
    return b"".join([*out, b"\xff\xd9"])


def test_jpeg_of_sparse_coefficients():
    rng = np.random.default_rng(8)
    coef = rng.integers(-60, 60, (5, 64)) * (rng.random((5, 64)) < 0.25)
    coef[1, 1:] *= np.arange(63) > 40
    coef[2, 1:] = 0
    coef[3, 5:9] = [1, -1, 1, 0]
    image = jpeg.decode(sparse_progressive(coef))
    assert (image["components"][1].coef == coef).all()


def test_jpeg_of_texts(spark):
    texts = [None, "", "é" * 200, "x" * 192, "twice", "twice"]
    rows = {r["doc_id"]: r for r in jpeg.stored_and_read(docs_of(spark, texts)).collect()}
    for i, t in enumerate(texts):
        raw = (t or "").encode()
        full = raw + b" " * (-len(raw) % 192 or (192 if not raw else 0))
        r = rows[i]
        assert (r["n_bytes"], r["payload_bytes"], r["payload_sha256"], r["tail_crc32"]) == (len(raw), len(full), hashlib.sha256(full).hexdigest(), zlib.crc32(full[-16:]))
    assert rows[4][3:] == rows[5][3:] and rows[0][3:] == rows[1][3:]
    t = jpeg.tensors(jpeg.store(docs_of(spark, ["abc"]))).first()
    assert len(t["rgb"]) == t["height"] * t["width"] * 3


# ---- op 6 ------------------------------------------------------------------------------------------------------------

def test_best_paths_are_best():
    rng = np.random.default_rng(0)
    for _ in range(20):
        many = rng.integers(0, 6, 5)
        first = np.concatenate([[0], np.cumsum(many)])
        score = rng.normal(size=(first[-1], 3)) * 3
        got = langid.best_paths(score, first, 1.0)
        for i in range(5):
            own = score[first[i] : first[i + 1]]
            worth = lambda p: sum(own[k, x] for k, x in enumerate(p)) - sum(a != b for a, b in zip(p, p[1:], strict=False))  # noqa: B023, E731
            if len(own):
                assert abs(worth(got[first[i] : first[i + 1]].tolist()) - max(map(worth, itertools.product(range(3), repeat=len(own))))) < 1e-9


def test_language_held_out(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    rows = {r["doc_id"]: r for r in langid.report(docs).collect()}
    truth = dict(docs.select("doc_id", "lang").collect())
    held = [i for i in rows if rows[i]["held_out"]]
    assert all(rows[i]["held_out"] == (zlib.crc32(str(i).encode()) % 4 == 2) for i in rows)
    assert np.mean([rows[i]["lang_pred"] == truth[i] for i in held]) > 0.97


def test_language_spans_and_odd_rows(spark):
    lang = [("the and of with", "en"), ("der die und nicht", "de"), ("и не что это", "ru"), (None, "en"), ("no label", None)] * 10
    model = langid.train(spark.createDataFrame(lang, "text string, lang string"))
    texts = ["the of and with the and der und nicht die der und und", "это что и", "123 ...", None, "", "ab 7"]
    got = {r["doc_id"]: r for r in langid.predict(docs_of(spark, texts), model).collect()}
    assert [s["lang"] for s in got[0]["spans"]] == ["en", "de"] and got[0]["spans"][1]["a"] == texts[0].index("der")
    assert got[1]["lang_pred"] == "ru" and [got[i]["lang_pred"] for i in (2, 3, 4)] == ["und"] * 3 and got[5]["lang_pred"] != "und"
    empty = langid.train(spark.createDataFrame([], "text string, lang string"))
    assert langid.predict(docs_of(spark, ["a"]), empty).first()["lang_pred"] == "und"
    assert {r["doc_id"] for r in langid.identified(docs_of(spark, texts).withColumnRenamed("source", "score")).collect()} == {0, 1, 5}


# ---- ops 2 and 7 -----------------------------------------------------------------------------------------------------

SMALL = [("<unk>", 0.0, 2)] + [(f"<0x{b:02X}>", 0.0, 6) for b in range(256)] + [(p, s, 1) for p, s in (("▁", -6.0), ("a", -3.0), ("b", -3.5), ("ab", -4.0), ("▁a", -4.5), ("ba", -4.0), ("aba", -6.5), ("▁ab", -6.0), ("é", -7.0), ("▁▁", -5.0))]


def brute_segment(text, own):
    best = {0: (0.0, 0, 0, [])}
    for j in range(1, len(text) + 1):
        found = []
        for i in range(max(0, j - own.longest), j):
            p = text[i:j]
            if p in own.pieces:
                score, ids = own.pieces[p][0], [own.pieces[p][1]]
            elif j - i == 1:
                score, ids = own.worst, [own.bytes[b] for b in p.replace(pieces.ESCAPED, pieces.SPACE).encode()]
            else:
                continue
            found.append((best[i][0] + score, best[i][1] - 1, -i, best[i][3] + ids))
        best[j] = max(found, key=lambda x: x[:3])
    return best[len(text)][3]


def test_streaming_viterbi_is_brute_force():
    rng = np.random.default_rng(4)
    own = pieces.Vocabulary(SMALL)
    for n in [1, 2, 5, 30, 200]:
        text = "".join(rng.choice(["a", "b", "▁", "é", "z", "\udc81"], n, p=[0.35, 0.3, 0.2, 0.05, 0.05, 0.05]))
        want = brute_segment(text, own)
        for size in (1, 3, n):
            got = list(pieces.streaming_viterbi((text[k : k + size] for k in range(0, n, size)), own))
            assert [i for ids in got for i in ids] == want
    assert len(list(pieces.streaming_viterbi(("ab" * 200 + "z" + "ba" * 200,), own))) > 5


@pytest.mark.parametrize("path", [None, pieces.VOCABULARY])
def test_encoding_round_trip_and_counts(path):
    own = pieces.Vocabulary(SMALL if path is None else pieces.read_model(path))
    coder, counter, table = pieces.Encoder(own), token_counts.Counter(own), pieces.decoder(own)
    texts = ["Hello world", "a  b   ab ", "x\ty\nz", "▁ lit ▁", "日本語 😀🏽", "", None, " lead", "ab" * 90, "aba ba\n" * 3, "é"]
    ids = [np.frombuffer(r, np.int32).astype(np.int64) for r in coder.encode_all(texts)]
    assert [pieces.decode(i, table) for i in ids] == [t or "" for t in texts]
    assert counter.counts(texts) == [None if t is None else len(i) for t, i in zip(texts, ids, strict=True)]
    for t, i in zip(texts, ids, strict=True):
        if t:
            marked = pieces.SPACE + t.replace(pieces.SPACE, pieces.ESCAPED).replace(" ", pieces.SPACE)
            assert brute_segment(marked, own) == i.tolist()


def test_encoding_is_the_library_on_unigram_scores(sf_dir):
    import sentencepiece
    from sentencepiece import sentencepiece_model_pb2

    model = sentencepiece_model_pb2.ModelProto()
    model.ParseFromString(open(pieces.VOCABULARY, "rb").read())
    model.trainer_spec.model_type = 1
    for p in model.pieces:
        p.score = max(p.score, -31000.0)
    library = sentencepiece.SentencePieceProcessor(model_proto=model.SerializeToString())
    coder = pieces.Encoder(pieces.Vocabulary([(p.piece, p.score, p.type) for p in model.pieces]))
    texts = [t[:1200] for (t,) in duckdb.sql(f"select text from '{sf_dir}/documents.parquet'").fetchall()]
    assert [np.frombuffer(r, np.int32).tolist() for r in coder.encode_all(texts)] == library.encode(texts)


def test_encoding_frames(spark):
    docs = docs_of(spark, ["ab c", None, "", "ab c"])
    got = {r["doc_id"]: r for r in pieces.report(docs).collect()}
    assert got[0]["lossless"] and got[0][1:] == got[3][1:] and got[1]["ids"] is None and got[2]["ids"] == []
    back = pieces.decode_ids(pieces.encode_texts(docs)).collect()
    assert all(r["decoded"] == r["text"] for r in back)
    assert dict(token_counts.token_counts(docs).collect()) == {0: got[0]["n_ids"], 1: None, 2: 0, 3: got[0]["n_ids"]}


# ---- op 8 ------------------------------------------------------------------------------------------------------------

def test_chat_windows_hold_their_budget():
    rng = np.random.default_rng(6)
    for _ in range(100):
        turns = [(str(rng.choice(["system", "user", "assistant"])), f"t{i}", int(rng.integers(1, 40))) for i in range(rng.integers(0, 30))]
        found = list(chat.windows(iter(turns), 60, 20))
        assert [(r, t) for w in found for r, t, again in w if not again] == [x[:2] for x in turns]
        cost = {t: n for _, t, n in turns}
        for w in found:
            assert [again for *_, again in w] == sorted((again for *_, again in w), reverse=True)
            assert sum(cost[t] for _, t, _ in w) <= 60 or sum(not again for *_, again in w) == 1
            assert turns[0][0] != "system" or w[0][1] == "t0"


def test_chat_digests(spark):
    control = "</s>[INST] ok [/INST]"
    rows = [(1, 0, "system", "be <|end|> kind"), (1, 1, "user", control), (1, 2, "assistant", "\\l " + control), (2, 0, None, None), (2, 0, "assistant", "b"), (2, 0, "assistant", "a"), (None, 5, "user", "x")] + [(3, i, ["user", "assistant"][i % 2], f"w{i} " * 40) for i in range(60)]
    frame = spark.createDataFrame(rows, "conv_id bigint, turn bigint, role string, text string").selectExpr("*", "1 window", "2 mask", "3 repeated")
    out = chat.formatted(frame, budget=200, history=60)
    assert not [r for r in out.collect() if "</s>" in r["text"] or "[INST]" in r["text"]]
    got = {r["conv_id"]: r for r in chat.report(out).collect()}
    for conv in (None, 1, 2, 3):
        own = sorted(((r[1], r[2] or "", r[3] or "") for r in rows if r[0] == conv))
        loss = "".join(t for _, r, t in own if r == "assistant")
        assert got[conv]["n_turns"] == len(own)
        assert got[conv]["turns_sha256"] == hashlib.sha256("".join(f"{r}\n{t}\n" for _, r, t in own).encode()).hexdigest()
        assert (got[conv]["loss_chars"], got[conv]["loss_sha256"]) == (len(loss), hashlib.sha256(loss.encode()).hexdigest())
    assert got[3]["n_windows"] > 10
    assert chat.report(chat.formatted(frame.where("false"))).count() == 0


# ---- op 1 ------------------------------------------------------------------------------------------------------------

def test_surrogates_keep_type_and_format():
    cases = {"email": "Ann.Lee@mail3.example.com", "phone": "+1 (017) 555-7713", "ipv4": "10.20.3.121", "card": "4111 1111 1111 1111", "secret": "AE93E105146691AE697923A219BE4DF655C4F1C7", "iban": "DE89 3704 0044 0532 0130 00", "ssn": "123-45-6789", "person": "Mrs. Ada Brown"}
    for kind, mention in cases.items():
        assert [(a, b, k) for a, b, k in pii.find(f"x {mention} y")] == [(2, 2 + len(mention), kind)]
        new = pii.dressed(kind, mention, pii.surrogate(kind, pii.canonical(kind, mention), pii.gender_of(kind, mention), 0))
        assert new != mention and [k for *_, k in pii.find(f"x {new} y")] == [kind]
        if kind not in ("person", "email"):
            assert re.sub("[0-9A-Za-z]", "x", new) == re.sub("[0-9A-Za-z]", "x", mention)
    assert not list(pii.find("4111111111111112 and 1.2.3 or 2390409500648961 plain"))


def test_surrogates_are_distinct_and_coreferent(spark, monkeypatch):
    real = pii.surrogate
    texts = [f"call +1 (017) 555-{i:04d} or mail a{i}@x.org" for i in range(30)] + ["call +1 (017) 555-0003 again, 0175550003", None, "", "clean"] + ["mail a3@x.org"] * 3
    docs = docs_of(spark, texts).withColumnRenamed("source", "entity").selectExpr("*", "7 text_key")
    found = pii.entities(docs)
    few = lambda kind, entity, gender, attempt, key=pii.KEY: f"{kind}{int(real(kind, entity, gender, attempt)[-4:].encode().hex(), 16) % 40}"
    table = pii.assignment(found.select("kind", "entity", "gender"))
    rows = table.collect()
    assert len({(r["kind"], r["stand_in"]) for r in rows}) == len(rows) == 60
    assert not {r["stand_in"] for r in rows} & {r["entity"] for r in rows}
    assert len({few(r["kind"], r["entity"], "", 0) for r in rows}) < 60  # such draws would collide
    got = {r["doc_id"]: r for r in pii.replaced(docs).collect()}
    phone = re.search(r"\+1 \(\d{3}\) 555-\d{4}", got[3]["text"])[0]
    assert phone in got[30]["text"] and phone != "+1 (017) 555-0003"
    assert len({got[i]["text"] for i in (34, 35, 36)}) == 1 and got[34]["text"][5:] in got[3]["text"]
    assert [got[i]["text"] for i in (31, 32, 33)] == [None, "", "clean"] and got[0]["n_replaced"] == 2
    assert pii.replaced(docs.where("false")).count() == 0


def test_failed_checks_hide_no_entity():
    card, iban = "4111 1111 1111 1111", ("DE89 3704 0044 0532 0130 00", "BE68 5390 0754 7034", "GB82 WEST 1234 5698 7654 32", "AT61 1904 3002 3457 3201", "ES91 2100 0418 4502 0005 1332")
    cases = [(f"{card} 12/26", card, "card"), (f"ID12 {card}", card, "card"), (f"no 12 {card}.", card, "card"), (f"{card} 12/26 x", card, "card")]
    cases += [(f"to {x}{y}", x, "iban") for x in iban for y in ("", " 2024", " NOTE", " 2024 NOTE", ", thanks")]
    for text, own, kind in cases:
        assert (text.index(own), text.index(own) + len(own), kind) in list(pii.find(text)), text
    assert [k for *_, k in pii.find(f"AB12 3456 7890 ann@x.org {card} 12 {iban[1]} 2024 {card}")] == ["email", "card", "iban", "card"]


def test_persons_of_one_name_keep_their_gender(spark):
    texts = ["Mr. Smith", "Mrs. Smith", "Dr. Smith", "Ms. Smith", "Mrs. Brown", "Prof. Brown", "Dr. Lee", "Herr Lang", "Dr. Lang", "Mr. Smith and Mrs. Smith"]
    got = [r["text"] for r in pii.replaced(docs_of(spark, texts)).orderBy("doc_id").collect()]
    mr, mrs, dr, ms, brown, prof, lee, lang, doctor = (t.split()[-1] for t in got[:9])
    assert len({mr, mrs, dr}) == 3 and ms == mrs and brown == prof and lang == doctor
    assert [x[-1] for x in (mr, mrs, dr, brown, lee, lang)] == ["o", "a", "e", "a", "e", "o"]
    assert got[9] == f"Mr. {mr} and Mrs. {mrs}"


def test_small_formats_do_not_run_out(spark):
    texts = [f"at 192.168.{x}.{y} or {chr(97 + x)}{chr(97 + y)}@a{x}.org and {chr(97 + x)}@b{y}.com" for x in range(1, 10) for y in range(1, 10)]
    texts += [f"Mr. {a}{b}{c}" for a in "ABCDEFGH" for b in "aeiou" for c in "klmnrstv"]
    found = pii.entities(docs_of(spark, texts))
    rows = pii.assignment(found.select("kind", "entity", "gender")).collect()
    made = {(r["kind"], r["stand_in"]) for r in rows}
    assert len(made) == len(rows) == found.select("kind", "entity").distinct().count() >= 81 * 2 + 320
    assert not {r["stand_in"] for r in rows} & {r["entity"] for r in rows}
    assert all(r["stand_in"].startswith("192.168.") for r in rows if r["kind"] == "ipv4")
    for attempt in (0, 5, 20, 40):
        for mention in ("192.168.1.2", "8.8.8.8", "127.0.0.1", "a@b.org", "+49 1 23 45", "4111 1111 1111 1111", "DE89 3704 0044 0532 0130 00", "123-45-6789", "Mrs. Li"):
            [kind] = [k for *_, k in pii.find(mention)]
            new = pii.dressed(kind, mention, pii.surrogate(kind, pii.canonical(kind, mention), pii.gender_of(kind, mention), attempt))
            assert [(a, b, k) for a, b, k in pii.find(new)] == [(0, len(new), kind)]


# ---- op 9 ------------------------------------------------------------------------------------------------------------

def test_licenses_are_found_and_inherited(spark):
    rows = [("a/LICENSE", "Released under the MIT License."), ("a/b/x.py", "code"), ("a/b/y.py", "text\nLicensed*** under### the Apache License, Version 2.0.&&&"), ("a/b/c/COPYING.txt", "This work is licensed under the GNU General Public License, version 3."), ("a/b/c/d/z", None), ("q/w", ""), ("top", "a licence of no kind"), (None, "Licensed under CC BY-NC 4.0."), ("ab/x", "near a")]
    files = spark.createDataFrame(rows, "path string, text string").selectExpr("*", "1 given", "2 above")
    got = {r["path"]: (r["own"], r["license"], r["license_from"]) for r in licenses.inherited(licenses.own_licenses(files)).collect()}
    assert got == {"a/LICENSE": ("MIT", "MIT", "a/LICENSE"), "a/b/x.py": (None, "MIT", "a"), "a/b/y.py": ("Apache-2.0", "Apache-2.0", "a/b/y.py"), "a/b/c/COPYING.txt": ("GPL-3.0", "GPL-3.0", "a/b/c/COPYING.txt"), "a/b/c/d/z": (None, "GPL-3.0", "a/b/c"), "q/w": (None, None, None), "top": (None, None, None), None: ("CC-BY-NC-4.0", "CC-BY-NC-4.0", None), "ab/x": (None, None, None)}
    assert licenses.report(docs_of(spark, [])).count() == 0


def test_license_windows_are_brute_force():
    """No window over the threshold is missed, and the best one is found, whatever stands around or between the lines."""
    known = {t: 3 + 7 * (k % 40) for k, t in enumerate(licenses.template_terms())}
    matcher = licenses.Matcher(400, known)
    rng = np.random.default_rng(4)
    vocabulary = [*licenses.template_terms(), "zeta", "eta", "rho"]
    notices = [n for own in licenses.TEMPLATES.values() for n in own]
    texts = [None, "", "Released under the MIT", "Released under the BSD 3-Clause", "public domain under CC0 1.0.", " # This work is licensed under the GNU General Public\n # License,\n # version 3.", "“Licensed under CC BY-NC 4.0.”"]
    texts += [" ".join([*rng.choice(vocabulary, 9), notices[int(rng.integers(len(notices)))].replace(" ", "\n * "), *rng.choice(vocabulary, 7)]) for _ in range(25)]
    texts += [" ".join(rng.choice(vocabulary, 12)) for _ in range(25)]

    def naive(text):
        own, best = licenses.terms(text or ""), (0.0, 0, "")
        idf = lambda t: np.log(401 / (1 + known[t])) + 1 if t in known else np.log(401) + 1
        for name, list_ in licenses.TEMPLATES.items():
            for notice in list_:
                want = licenses.terms(notice)
                n = len(want)
                weigh = lambda w: {t: w.count(t) * idf(t) for t in w}
                two = weigh(want)
                for size in {min(len(own), s) for s in (n, -(-3 * n // 4), 5 * n // 4)} - {0}:
                    for k in range(len(own) - size + 1):
                        one = weigh(own[k : k + size])
                        score = sum(w * two.get(t, 0) for t, w in one.items()) / np.sqrt(sum(w * w for w in one.values()) * sum(w * w for w in two.values()))
                        if score >= licenses.THRESHOLD and (round(score, 9), n) > best[:2]:
                            best = round(score, 9), n, name
        return best

    for text, (name, score) in zip(texts, matcher.best(pa.array(texts, pa.string())), strict=True):
        want = naive(text)
        assert score == pytest.approx(want[0], abs=1e-8) and (name or "") == want[2], text


# ---- pipeline --------------------------------------------------------------------------------------------------------

def test_pipeline(spark, sf_dir):
    import corpus_pipeline

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    rows = corpus_pipeline.run(spark, sf_dir).collect()
    assert 0.8 * docs.count() < len(rows) < docs.count() and all(r["lossless"] for r in rows)
    assert len({r["doc_id"] for r in rows}) == len(rows)
    assert [n for n, _ in corpus_pipeline.STAGES] == ["language", "near_duplicates", "decontamination", "privacy", "encoding"]
