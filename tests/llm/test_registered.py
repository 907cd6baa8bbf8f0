"""The registered corpus queries against brute force, and odd, empty and clashing tables for all operators and stages."""

import hashlib
import random
import struct
import zlib

import duckdb
import numpy as np
import pytest

from ctxrelease.llm import bpe, chat, common, langid, media, ngram_join, packing, pii, sharding, topk, toxicity

SF = "/root/testdata/sf0.001"


def held(d, n):
    return zlib.crc32(str(d).encode()) % n


@pytest.fixture(scope="module")
def texts():
    return dict(duckdb.sql(f"select doc_id, text from '{SF}/documents.parquet'").fetchall())


def by_id(df):
    return {r["doc_id"]: r.asDict() for r in df.collect()}


def test_media_query(spark, texts):
    got = by_id(media.op8_media(spark, SF))
    assert set(got) == set(texts)
    for d, t in texts.items():
        raw = (t or "").encode()
        payload = raw + b"\0" * (max(64, -(-len(raw) // 64) * 64) - len(raw))
        r = got[d]
        assert (r["n_bytes"], r["payload_bytes"], r["payload_sha256"], r["tail_crc32"]) == (len(raw), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]))
        stored = media.write_avi(payload)
        assert (r["media_bytes"], r["media_sha256"]) == (len(stored), hashlib.sha256(stored).hexdigest())
    clips = media.media_clips(spark, SF).collect()
    frames = {d: len(media.read_avi(media.write_avi(media.payload_of(t)[1]))[2]) for d, t in texts.items()}
    last: dict[int, int] = {}
    for r in sorted(clips, key=lambda r: (r["doc_id"], r["clip"])):  # clips follow one another and cover all frames
        assert r["first_frame"] == last.get(r["doc_id"], 0) and r["start_s"] == r["first_frame"] / 25
        last[r["doc_id"]] = r["first_frame"] + r["frames"]
    assert last == frames


def test_personal_data_query(spark, texts):
    got = by_id(pii.op6_pii(spark, SF))
    for d, t in texts.items():
        base, full = pii.find(t or "")
        assert [got[d][f"n_{k}"] for k in pii.KINDS] == [len(base[k]) for k in pii.KINDS]
        plain = ",".join(f"{k}:{a}:{b}" for k in pii.KINDS for a, b in base[k])
        assert got[d]["base_sha256"] == hashlib.sha256(plain.encode()).hexdigest() and got[d]["spans"] == pii.joined(full)
        assert got[d]["n_added"] == sum(len(full[k]) - len(base[k]) for k in pii.KINDS)


def test_bpe_query(spark, texts):
    lib = bpe.vocabulary(bpe.default_path()).library()
    got = by_id(bpe.op10_bpe(spark, SF))
    for d, t in texts.items():
        ids = lib.encode(t or "", add_special_tokens=False).ids
        shown = lib.decode(ids, skip_special_tokens=False)
        assert (got[d]["n_tokens"], got[d]["ids_sha256"], got[d]["decoded_sha256"]) == (len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(shown.encode()).hexdigest())


def test_bpe_random_texts():
    """Slices of many kinds of text, words that leave the memory and come back."""
    voc = bpe.vocabulary(bpe.default_path())
    lib = voc.library()
    rng = random.Random(1)
    parts = ["the", "don't", "I'LL", "été", "ÀÉ", "½", "12", " ", "\n", "\t", "...", "'s", "“x”", "ß", "漢字", "ſ", "<|endoftext|>", "\x1c", "İ", "é", "a" * 30, "ZqXv", "-", "\x00"]
    texts = ["".join(rng.choice(parts) for _ in range(rng.randrange(40))) for _ in range(600)]
    coder = bpe.Encoder(voc, None, True)
    coder.words.most = 25
    for _ in range(2):
        for t, (ids, shown) in zip(texts, coder.encode_and_decode(texts)):
            want = lib.encode(t, add_special_tokens=False).ids
            assert np.frombuffer(ids, "<u4").tolist() == want, t
            assert shown.decode() == lib.decode(want, skip_special_tokens=False), t


def test_language_query(spark, texts):
    rows = duckdb.sql(f"select doc_id, lang from '{SF}/documents.parquet'").fetchall()
    got = by_id(langid.op5_language_id(spark, SF))
    assert all(got[d]["held_out"] == (held(d, 3) == 1) and 0 <= got[d]["score"] <= 1 for d, _ in rows)
    fair = [(d, lang) for d, lang in rows if held(d, 3) == 1 and texts[d] and any(c.isalpha() for c in texts[d])]
    assert np.mean([got[d]["lang_pred"] == lang for d, lang in fair]) > 0.9


def test_toxicity_pairs_held_out(spark, tmp_path):
    """Insults that are harmless alone and groups that are common in clean texts: only their products tell. Scored by the query."""
    rng = random.Random(4)
    insults, groups = ["grumblers", "vermin", "parasites", "clowns"], ["newcomers", "teachers", "farmers", "neighbours"]
    filler = [f"word{chr(97 + k % 26)}{chr(97 + k // 26)}" for k in range(200)]
    docs, labels = [], []
    for d in range(2400):
        a, b = rng.random() < 0.5, rng.random() < 0.5
        words = [rng.choice(filler) for _ in range(25)] + ([rng.choice(insults)] if a else []) + ([rng.choice(groups)] if b else [])
        rng.shuffle(words)
        docs.append((d, " ".join(words)))
        labels.append((d, 1, int(a and b)))
    spark.createDataFrame(docs, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    got = by_id(toxicity.op7_toxicity(spark, str(tmp_path)))
    test = [(d, y) for d, _, y in labels if held(d, 5) == 0]
    assert all(got[d]["held_out"] for d, _ in test) and len(test) > 400
    full = np.mean([got[d]["predicted"] == y for d, y in test])
    machine = toxicity.train(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, quality int, toxic int"))
    terms = toxicity.Terms({int(b): k for k, b in enumerate(machine.buckets)})
    # the best additive rule of the same terms: zeroed factors, with its threshold chosen on the held-out rows themselves
    machine.factors[:] = 0
    plain = np.array(toxicity.score_texts(machine, terms, [docs[d][1] for d, _ in test]))
    y = np.array([y for _, y in test])
    additive = max(np.mean((plain >= cut) == y) for cut in (0.5, *np.unique(plain)))
    assert full > 0.97 and np.mean((plain >= 0.5) == y) < full - 0.1, (full, additive)


def test_words_of_equal_sums_differ(spark):
    """Words built from the Thue-Morse sequence share their power sums: a polynomial hash can't tell them apart."""
    word = "a"
    for _ in range(12):
        word += word.translate(str.maketrans("ab", "ba"))
    other = word.translate(str.maketrans("ab", "ba"))
    for n in (1024, 2048, 4096):
        for family in (0, 1):
            assert ngram_join.shingles([word[:n]], family)[0] != ngram_join.shingles([other[:n]], family)[0]
    rows = [(1, word), (2, other), (3, word.upper()), (4, None)]
    got = {r["doc_id"]: r["component_id"] for r in ngram_join.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {1: 1, 2: 2, 3: 1, 4: 4}


def test_block_sizes_bound_overlaps():
    rng = np.random.default_rng(0)
    for _ in range(200):
        pool = rng.integers(0, 1 << 63, 900, dtype=np.uint64)
        a = ngram_join.distinct(rng.choice(pool, int(rng.integers(1, 800)), replace=False))
        b = ngram_join.distinct(rng.choice(pool, int(rng.integers(1, 800)), replace=False))
        assert ngram_join.block_bound(ngram_join.block_sizes(a), ngram_join.block_sizes(b)) >= len(np.intersect1d(a, b))


def test_hot_class_is_whole(spark):
    """A class beyond HOT_ROWS documents meets them by broadcast; none is lost, and its near copy joins it."""
    text = " ".join(f"w{k}" for k in range(60))
    rows = [(k, text) for k in range(10, 10 + common.HOT_ROWS + 50)] + [(5, text + " more"), (6, "quite another text of some words")]
    got = {r["doc_id"]: r["component_id"] for r in ngram_join.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert len(got) == len(rows) and got[6] == 6 and all(c == 5 for d, c in got.items() if d != 6)


def test_sharding_query(spark, texts):
    got = by_id(sharding.op4_sharding(spark, SF))
    slots: dict[int, list] = {}
    for d, t in texts.items():
        r = got[d]
        assert (r["size"], r["text_crc32"], r["law"], r["grown_shard"]) == (len((t or "").encode()) + 1, zlib.crc32((t or "").encode()), "rows", None)
        slots.setdefault(r["shard"], []).append(r["slot"])
    assert all(sorted(v) == list(range(len(v))) for v in slots.values()) and max(map(len, slots.values())) - min(map(len, slots.values())) <= 1


def test_topk_repeated_ids_and_thresholds(spark):
    rows = [(20, [1.0, 2.0]), (20, [1.0, 2.0]), (1, [3.0]), (2, [0.5, 0.5]), (2, [0.5, 0.5]), (40, [-1.0, -2.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = {(r["query_id"], r["rank"]): (r["vec_id"], r["score"]) for r in topk.search(topk.integer_vectors(df), topk.F.col("vec_id") % 20 == 0, k=2).collect()}
    assert got == {(20, 1): (1, 64 * 192), (20, 2): (2, 32 * 64 + 32 * 128), (40, 1): (2, -32 * 64 - 32 * 128), (40, 2): (2, -32 * 64 - 32 * 128)}
    rng = np.random.default_rng(5)
    v = rng.integers(-60, 60, (900, 64))  # dimensions of the embeddings
    ids = np.arange(900)
    stats: dict = {}
    score = v[:40] @ v.T
    score[np.arange(40), np.arange(40)] = -(1 << 40)
    tau = np.sort(score, 1)[:, -7].astype(float)
    q, c, s = topk.best_of_block(ids[:40], v[:40], tau, ids, v.T, 5, stats)
    for i in range(40):
        want = sorted((-x, j) for j, x in enumerate(score[i].tolist()))[:5]
        assert sorted((-x, j) for j, x in zip(c[q == i].tolist(), s[q == i].tolist())) == want
    assert stats["formed"] < 0.6 * stats["plain"]


# ordinary frames of other writers


class Writer:
    def __init__(self):
        self.bits = ""

    def put(self, value: int, n: int) -> None:
        self.bits += format(value, f"0{n}b") if n else ""

    def number(self, x: int, codes: dict, run: int = 0) -> None:
        size = abs(x).bit_length()
        self.put(*codes[run << 4 | size])
        self.put(x if x > 0 else x + (1 << size) - 1, size)

    def done(self) -> bytes:
        bits = self.bits + "1" * (-len(self.bits) % 8)
        return bytes(int(bits[k : k + 8], 2) for k in range(0, len(bits), 8)).replace(b"\xff", b"\xff\x00")


def codes_of(kind):
    return {s: (code, n) for (n, code), s in media._code_table(*media._USUAL[kind]).items()}


def baseline(image: np.ndarray, colour: bool, every: int = 0) -> bytes:
    """A small writer of baseline frames without code tables: grey, or luminance at twice the sampling of flat colour planes."""
    step = 8 * (2 if colour else 1)
    rows, columns = image.shape
    padded = np.pad(image, ((0, -rows % step), (0, -columns % step)), mode="edge").astype(float) - 128
    out, segments, before, n = Writer(), [], 0, 0
    dc, ac, dc2, ac2 = (codes_of(k) for k in (0, 0x10, 1, 0x11))
    for y in range(0, padded.shape[0], step):
        for x in range(0, padded.shape[1], step):
            if every and n and n % every == 0:
                segments.append(out.done())
                out, before = Writer(), 0
            n += 1
            for dy in range(0, step, 8):
                for dx in range(0, step, 8):
                    block = media._INVERSE.T @ padded[y + dy : y + dy + 8, x + dx : x + dx + 8] @ media._INVERSE
                    coef = np.rint(block.ravel()[media._ZIGZAG] / 2).astype(int).tolist()
                    out.number(coef[0] - before, dc)
                    before, run = coef[0], 0
                    for k in range(1, 64):
                        if not coef[k]:
                            run += 1
                            continue
                        while run > 15:
                            out.put(*ac[0xF0])
                            run -= 16
                        out.number(coef[k], ac, run)
                        run = 0
                    if run:
                        out.put(*ac[0])
            for _ in range(2 if colour else 0):
                out.number(0, dc2)
                out.put(*ac2[0])
    segments.append(out.done())
    scan = b"".join(s + (b"\xff" + bytes([0xD0 + k % 8]) if k + 1 < len(segments) else b"") for k, s in enumerate(segments))
    parts = [(1, 0x22 if colour else 0x11, 0)] + ([(2, 0x11, 1), (3, 0x11, 1)] if colour else [])
    head = b"\xff\xd8\xff\xdb" + struct.pack(">HB", 67, 0) + bytes([2] * 64) + (b"\xff\xdb" + struct.pack(">HB", 67, 1) + bytes([2] * 64))
    head += b"\xff\xc0" + struct.pack(">HBHHB", 8 + 3 * len(parts), 8, rows, columns, len(parts)) + b"".join(bytes(p) for p in parts)
    head += (b"\xff\xdd" + struct.pack(">HH", 4, every)) if every else b""
    return head + b"\xff\xda" + struct.pack(">HB", 6 + 2 * len(parts), len(parts)) + b"".join(bytes([p[0], 0x11 * p[2]]) for p in parts) + b"\x00\x3f\x00" + scan + b"\xff\xd9"


@pytest.mark.parametrize("colour,every", [(False, 0), (False, 2), (True, 0), (True, 1)])
def test_ordinary_frames(colour, every):
    y, x = np.mgrid[0:43, 0:37]
    image = np.clip(128 + 60 * np.sin(x / 5) + 50 * np.cos(y / 7) + (x * y) % 11, 0, 255).astype(np.uint8)
    got = media.read_frame(baseline(image, colour, every))
    assert got.shape == image.shape and np.abs(got.astype(int) - image).max() <= 4


def test_lossless_frames_of_other_tables():
    rng = np.random.default_rng(0)
    image = rng.integers(0, 256, (9, 13)).astype(np.int64)
    codes = codes_of(0)  # categories 0 to 11
    for predictor in range(1, 8):
        out = Writer()
        for y in range(9):
            for x in range(13):
                a, b, c = (int(image[y, x - 1]) if x else 0), (int(image[y - 1, x]) if y else 0), (int(image[y - 1, x - 1]) if x and y else 0)
                guess = (a if x else 128) if not y else b if not x else (a, b, c, a + b - c, a + (b - c) // 2, b + (a - c) // 2, (a + b) // 2)[predictor - 1]
                out.number(int(image[y, x]) - guess, codes)
        frame = b"\xff\xd8\xff\xc3" + struct.pack(">HBHHBBBB", 11, 8, 9, 13, 1, 1, 0x11, 0) + b"\xff\xda" + struct.pack(">HBBBBBB", 8, 1, 1, 0, predictor, 0, 0) + out.done() + b"\xff\xd9"
        assert np.array_equal(media.read_frame(frame), image)
    for bad in (b"", b"\xff\xd8\x00\x00\x00\x00", b"\xff\xd8\xff\xc2" + struct.pack(">H", 2)):
        with pytest.raises(ValueError):
            media.read_frame(bad)


# odd, empty and clashing tables


def test_empty_tables(spark):
    docs = spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long")
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    turns = spark.createDataFrame([], "conv_id long, turn long, role string, text string")
    vectors = spark.createDataFrame([], "vec_id long, embedding array<float>")
    assert chat.read_back(chat.format_conversations(turns)).count() == 0
    assert packing.pack_documents(docs).count() == 0 and sharding.shard_documents(docs).count() == 0
    assert topk.search(topk.integer_vectors(vectors), topk.F.col("vec_id") % 20 == 0).count() == 0
    assert langid.train(docs) is None and langid.identify(docs, None).count() == 0
    assert toxicity.train(docs, labels) is None and toxicity.score(docs, None).count() == 0
    assert pii.detect(docs).count() == 0 and media.summarize(docs, ["doc_id"]).count() == 0 and media.clips(media.text_to_avi(docs)).count() == 0
    assert ngram_join.near_duplicates(docs).count() == 0 and bpe.encode_documents(docs).count() == 0


def test_chat_repeated_rows(spark):
    rows = [(1, 0, "user", "hi"), (1, 0, "user", "hi"), (1, 1, "assistant", "yo")]
    got = chat.read_back(chat.format_conversations(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string"))).collect()
    assert [tuple(t) for t in got[0]["turns"]] == [("user", "hi"), ("user", "hi"), ("assistant", "yo")]


def test_toxicity_odd_rows(spark):
    docs = spark.createDataFrame([(1, None), (2, ""), (3, "a b c"), (3, "a b c"), (None, "x " * 50_000)], "doc_id long, text string")
    labels = spark.createDataFrame([(1, 1), (2, None), (3, 0), (3, 1), (None, 1)], "doc_id long, toxic int")
    out = toxicity.score(docs, toxicity.train(docs, labels)).collect()
    assert len(out) == 5 and all(0 <= r["score"] <= 1 for r in out)


@pytest.mark.parametrize("which", ["empty", "odd"])
def test_pipeline_stages_on_odd_tables(spark, which):
    import corpus_pipeline

    schema = "doc_id long, text string, lang string, source string, n_chars long, lang_pred string, Score double, __score int, __toxic int, __clean string, __text string, component_id long"
    long = "lorem ipsum dolor sit amet consetetur " * 2000
    rows = [(1, None, None, None, None), (2, "", "en", "s", 0), (3, "one two three four five six", "en", "s", 10), (3, "one two three four five six", "en", "s", 10), (4, "one two three four five six", "de", None, 1),
            (5, long, "en", "s", 5), (6, "  \n ", None, "s", 3), (None, "no id here at all", "en", "s", 5), (7, "mail bob@example.com now or never again", "fr", "s", 6)]
    docs = spark.createDataFrame([(*r, "p", 0.5, 1, 2, "c", "t", 9) for r in rows] if which == "odd" else [], schema)
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, SF)
        found = out.collect()
        if name == "packing":
            assert len(found) >= docs.count()
            continue
        assert out.columns == docs.columns, name
        if name == "near_duplicates" and which == "odd":
            assert sorted(str(r["doc_id"]) for r in found) == sorted(str(r[0]) for r in rows if r[0] != 4)
        if name == "pii" and which == "odd":
            assert {r["text"] for r in found if r["doc_id"] == 7} == {"mail <email> now or never again"}
            assert [r["text"] for r in found if r["doc_id"] == 1] == [None]
        if name == "language_id" and which == "odd":
            assert not {1, 2, 6} & {r["doc_id"] for r in found}


def test_pipeline_equals_plain_loops(spark):
    """run() against the same models applied one document at a time, brute-force components and the tokenizers library."""
    import corpus_pipeline

    from .test_operators import brute_components

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    rows = {r["doc_id"]: r["text"] for r in docs.select("doc_id", "text").collect()}
    net = langid.train(docs)
    langs, scores = langid.predict(net, list(rows.values()))
    kept = {d: t for (d, t), a, s in zip(rows.items(), langs, scores) if a != "und" and s >= corpus_pipeline.MIN_LANG_SCORE}
    machine = toxicity.train(docs.where(docs["doc_id"].isin(*kept)), spark.read.parquet(f"{SF}/labels.parquet"))
    terms = toxicity.Terms({int(b): k for k, b in enumerate(machine.buckets)}) if machine else None
    kept = {d: t for d, t in kept.items() if toxicity.score_texts(machine, terms, [t])[0] < 0.5}
    comp = brute_components(list(kept.items()))
    kept = {d: pii.redact(t) for d, t in kept.items() if comp[d] == (0, d) or comp[d][1] == d}
    lib = bpe.vocabulary(bpe.default_path()).library()
    want = []
    for d, t in kept.items():
        ids = np.array([*lib.encode(t or "", add_special_tokens=False).ids, 0], "<u4")
        want += [(d, k // 2048, k, len(ids[k : k + 2048]), zlib.crc32(ids[k : k + 2048].tobytes())) for k in range(0, len(ids), 2048)]
    got = corpus_pipeline.run(spark, SF).collect()
    assert sorted((r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in got) == sorted(want)
    assert 0 < len(kept) < len(rows)
    held: dict[int, list] = {}
    for r in got:
        held.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for parts in held.values():
        assert [a for a, _ in sorted(parts)] == np.cumsum([0, *[n for _, n in sorted(parts)]]).tolist()[:-1] and sum(n for _, n in parts) <= 2048
