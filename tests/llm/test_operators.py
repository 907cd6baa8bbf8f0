"""The corpus operators on small fixtures: brute force, round trips, held-out accuracy, odd rows."""

import hashlib
import random
import re
import zlib

import duckdb
import numpy as np
import pytest

import __spark_entry__ as entry
from ctxrelease.llm import bpe, chat, langid, media, ngram_join, packing, pii, sharding, topk, toxicity
from ctxrelease.llm import registry as corpus

SF = "/root/testdata/sf0.001"
DOCS = "doc_id long, text string, lang string, source string, n_chars long, score double, extra string"


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, empty and very long texts, repeated rows, extra columns with clashing names."""
    long = "lorem ipsum dolor sit amet consetetur " * 3000
    rows = [(1, None, None, None, None), (2, "", "en", "s", 0), (3, "one two three four five six", "en", "s", 10), (3, "one two three four five six", "en", "s", 10),
            (4, "one two three four five six", "de", None, 1), (5, long, "en", "s", 5), (6, "  \n ", None, "s", 3), (None, "no id", "en", "s", 5), (7, "123 !!", "fr", "s", 6)]
    return spark.createDataFrame([(*r, 0.5, "x") for r in rows], DOCS)


@pytest.fixture(scope="module")
def empty(odd):
    return odd.where("false")


def test_chat_equals_sql(spark):
    con = duckdb.connect()
    con.execute(f"create view conversations as select * from '{SF}/conversations.parquet'")
    want = con.sql(chat.OP1_SQL)
    got = chat.op1_chat_formatting(spark, SF).select(*want.columns)
    assert sorted(map(tuple, got.collect())) == sorted(want.fetchall())


def test_chat_odd_turns(spark):
    rows = [(1, 0, "user", "a\\<|im_end|>|>"), (1, 1, "user", ""), (1, 2, "assistant", None), (1, 3, "assistant", "x<|"), (1, 4, None, "\\"), (None, 0, "us\ner", "<|im_sep|>"), (2, None, "assistant", "é\U0001f600")]
    df = chat.read_back(chat.format_conversations(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")))
    got = {r["conv_id"]: r for r in df.collect()}
    assert [tuple(t) for t in got[1]["turns"]] == [(r or "", x or "") for c, _, r, x in rows if c == 1]
    assert got[1]["loss_text"] == "x<|" and got[2]["loss_text"] == "é\U0001f600" and got[1]["formatted"].count("<|im_start|>") == 3
    assert [tuple(t) for t in got[None]["turns"]] == [("us\ner", "<|im_sep|>")]


def test_packing_is_tight_and_exact(spark):
    rng = random.Random(3)
    hist: dict[int, int] = {}
    for _ in range(4000):
        k = min(2048, int(rng.expovariate(1 / 700)) + 1)
        hist[k] = hist.get(k, 0) + 1
    solution = packing.solve(hist, 2048)
    held: dict[int, int] = {}
    for template, n in solution:
        assert sum(x * m for x, m in template) <= 2048
        for x, m in template:
            held[x] = held.get(x, 0) + m * n
    assert held == hist
    assert sum(n for _, n in solution) <= 1.01 * packing.lower_bound(hist, 2048) + 1
    assert packing.solve({}, 2048) == []


def test_packing_solves_histograms_with_little_choice():
    """No configuration is full here: 1035 + 527 + 468 and 2 x 548 + 2 x 468 need 9 sequences, best fit opens 11."""
    for n in (1, 10, 1000):
        hist = {1035: 6 * n, 548: 6 * n, 527: 6 * n, 468: 12 * n}
        solution = packing.solve(hist, 2048)
        got: dict[int, int] = {}
        for template, runs in solution:
            assert sum(x * m for x, m in template) <= 2048
            for x, m in template:
                got[x] = got.get(x, 0) + m * runs
        assert got == hist and sum(runs for _, runs in solution) == 9 * n
    rng = np.random.default_rng(1)
    for _ in range(3):
        hist = {int(x): int(c) for x, c in zip(rng.integers(150, 1100, 8), rng.integers(1000, 9000, 8))}
        cover, dual = packing.fractional(hist, 2048, packing.ROUNDS, packing.COLUMNS, packing.RATE)
        report: dict = {}
        used = sum(n for _, n in packing.solve(hist, 2048, report=report))
        assert dual <= used + 1e-6 and used == report["program"] < report["best_fit"] and report["share_of_program"] > 0.5
        assert all(sum(x * m for x, m in c) <= 2048 and y > 0 for c, y in cover.items())


def test_packing_round_trip(spark, odd, empty):
    assert packing.pack_documents(empty).count() == 0
    rows = packing.pack_documents(odd).collect()
    tk = bpe.vocabulary(bpe.default_path()).library()
    for doc_id, text in {(r["doc_id"], r["text"]) for r in odd.collect()}:
        ids = np.array([*tk.encode(text or "", add_special_tokens=False).ids, 0], "<u4")
        own = sorted((r for r in rows if r["doc_id"] == doc_id), key=lambda r: r["piece"])
        for k in range(0, len(ids), 2048):
            part = ids[k : k + 2048]
            assert any((r["start"], r["length"], r["ids_crc32"]) == (k, len(part), zlib.crc32(part.tobytes())) for r in own)
    by: dict[int, list] = {}
    for r in rows:
        by.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for parts in by.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 2048


def test_bpe_equals_the_library(spark, tmp_path):
    voc = bpe.vocabulary(bpe.default_path())
    lib = voc.library()
    texts = [r[0] for r in duckdb.sql(f"select text from '{SF}/documents.parquet' limit 60").fetchall()]
    texts += ["", "<|endoftext|> Ab'S <|startoftext|>x", "ΣΑΣ 漢字 é é a\x1cb \x85 İı ǅ", "a" * 500, "don't I'LL 123 ½", "x<|y\n\n", "a\x00b  　c", "́ x"]
    words = sorted({w for t in texts for w in bpe.pieces(voc, t)})
    bpe.compile_lexicon([w.encode() for w in words[::2]], voc.merge, str(tmp_path / "lexicon"))
    coder = bpe.Encoder(voc, bpe.Lexicon(str(tmp_path / "lexicon")), True)
    for t, (ids, shown) in zip(texts, coder.encode_and_decode(texts)):
        want = lib.encode(t, add_special_tokens=False).ids
        assert np.frombuffer(ids, "<u4").tolist() == want
        assert shown.decode() == lib.decode(want, skip_special_tokens=False) == bpe.decode(voc, np.array(want, int))


def test_bpe_merges_a_large_vocabulary_once(monkeypatch):
    """More distinct words than were remembered before, in two rounds: the second one merges none anew."""
    letters, merged = "etaoinshrdlcumwfgypbvkxqjz", []
    words = ["".join(letters[n // 26**k % 26] for k in range(4)) for n in range(380_000)]
    texts = [" ".join(words[at : at + 19_000]) for at in range(0, len(words), 19_000)]
    monkeypatch.setattr(bpe, "TEXT_SLICE", 100_000)
    coder = bpe.Encoder(bpe.vocabulary(bpe.default_path()))
    merge = coder.voc.merge
    monkeypatch.setattr(coder.voc, "merge", lambda words: merged.append(len(words)) or merge(words))
    first, second = (list(coder.encode(texts)) for _ in range(2))
    assert first == second and sum(merged) == 380_000


def test_bpe_memory_of_chunks_is_bounded():
    rng, voc = random.Random(3), bpe.vocabulary(bpe.default_path())
    texts = [" ".join("".join(rng.choice("abcdeé'.,9") for _ in range(rng.randint(1, 9))) for _ in range(rng.randint(0, 60))) for _ in range(300)] + ["x" * 99, "", " "]
    coder = bpe.Encoder(voc, None, True)
    coder.chunks.most = 50
    for some in [texts[:1], texts[:200], texts[100:], texts[-1:]]:
        got = [(np.frombuffer(ids, "<u4").tolist(), shown.decode()) for ids, shown in coder.encode_and_decode(some)]
        want = [voc.library().encode(t, add_special_tokens=False).ids for t in some[:9]]
        assert [x for x, _ in got[:9]] == want and [x for _, x in got] == [bpe.decode(voc, np.array(x, int)) for x, _ in got]
        assert len(coder.chunks.keys) == len(coder.chunks.used) <= 50
    assert max(map(len, coder.chunks.keys.to_pylist())) <= bpe.MEMO_CHUNK_BYTES


def test_bpe_odd_rows(spark, odd, empty):
    assert bpe.encode_documents(empty).count() == 0
    got = bpe.encode_documents(odd).collect()
    assert len(got) == odd.count()
    none = hashlib.sha256(b"").hexdigest()
    assert all((r["n_tokens"], r["ids_sha256"], r["decoded_sha256"]) == (0, none, none) for r in got if r["doc_id"] in (1, 2, 6))


def test_topk_equals_brute_force(spark):
    rng = np.random.default_rng(2)
    rows = [(i, [float(x) for x in rng.normal(size=6)]) for i in range(150)] + [(200 + i, [0.5] * 6) for i in range(60)] + [(400, None), (401, [1.0, None]), (402, [float("nan")]), (403, [float("inf")]), (420, [1.0, 2.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    got: dict[int, list] = {}
    for r in topk.search(topk.integer_vectors(df), (topk.F.col("vec_id") % 20) == 0, candidates=40, queries=5).orderBy("query_id", "rank").collect():
        got.setdefault(r["query_id"], []).append((r["vec_id"], r["score"]))
    good = {i: [int(np.floor(64 * float(np.float32(x)))) for x in v] for i, v in rows if v and all(x is not None and np.isfinite(x) for x in v)}
    for q in [i for i in good if i % 20 == 0]:
        score = sorted(((-sum(a * b for a, b in zip(good[q], v)), i) for i, v in good.items() if i != q))[:20]
        assert got[q] == [(i, -s) for s, i in score]
    assert set(got) == {i for i in good if i % 20 == 0}


def test_sharding_is_balanced_and_keeps_copies_together(spark, odd, empty):
    rows = [(i, f"text {i // 5}" if i < 400 else f"own {i}") for i in range(1000)] + [(2000 + i, "hot") for i in range(500)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    out = sharding.shard_documents(df)
    placed = out.collect()
    count: dict[int, list] = {}
    for r in placed:
        count.setdefault(r["shard"], []).append(r["slot"])
        assert r["size"] == len(dict(rows)[r["doc_id"]].encode()) + 1
    assert set(count) == set(range(16)) and max(map(len, count.values())) - min(map(len, count.values())) <= 1
    assert all(sorted(v) == list(range(len(v))) for v in count.values())
    cut = sharding.cut_edges(out.where("doc_id < 2000")).first()
    assert cut["cut"] < 0.1 * cut["links"]
    assert len(sharding.shard_documents(odd).collect()) == odd.count() and sharding.shard_documents(empty).count() == 0


def test_language_held_out(spark, odd):
    rows = duckdb.sql("select doc_id, text, lang from '/root/testdata/sf0.01/documents.parquet'").fetchall()
    train = [r for r in rows if zlib.crc32(str(r[0]).encode()) % 3 != 1][:400]
    net = langid.fit([r[1][k : k + 256] for r in train for k in (0, max(0, len(r[1]) - 256))], [r[2] for r in train for _ in range(2)], epochs=6)
    test = [r for r in rows if zlib.crc32(str(r[0]).encode()) % 3 == 1]
    got, score = langid.predict(net, [r[1] for r in test])
    assert np.mean([a == r[2] for a, r in zip(got, test)]) > 0.95 and all(0 <= s <= 1 for s in score)
    assert langid.predict(net, [None, "", "12 !"])[0] == ["und"] * 3
    assert langid.predict(None, ["abc"]) == (["und"], [0.0])
    out = langid.identify(odd, net)
    assert out.columns == [*[c for c in odd.columns if c != "score"], "lang_pred", "score"] and out.count() == odd.count()


def test_personal_data():
    pats = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}

    def plain(text):
        out = {}
        for k, p in pats.items():
            out[k] = []
            for m in re.finditer(p, text):
                d = re.sub("[^0-9]", "", m.group())
                ok = {"email": True, "ip": k == "ip" and all(int(x) <= 255 for x in m.group().split(".")), "card": 16 <= len(d) <= 19 and pii.luhn(d), "phone": 8 <= len(d) <= 15}[k]
                if ok:
                    out[k].append(m.span())
        return out

    rng = random.Random(5)
    for _ in range(3000):
        t = "".join(rng.choice("ab.@-1 2+%") for _ in range(50))
        assert pii.base_spans(t) == plain(t)
    cases = {"mail john (at) ex.com now": "john (at) ex.com", "j dot doe at example dot com": "j dot doe at example dot com", "jоhn@exаmple.com": "jоhn@exаmple.com",
             "plus one two three four five six seven eight nine": "plus one two three four five six seven eight nine", "１９２.168.0.1": "１９２.168.0.1"}
    for text, part in cases.items():
        base, full = pii.find(text)
        got = [text[a:b] for k in pii.KINDS for a, b in full[k]]
        assert part in got and all(set(base[k]) <= set(full[k]) for k in pii.KINDS), text
        assert part not in pii.redact(text)
    clean = "the one at the dot of two or three things."
    assert pii.find(clean)[1] == {k: [] for k in pii.KINDS} and pii.redact(clean) == clean
    assert pii.redact(None) is None and pii.redact("") == ""


def test_personal_data_in_every_disguise():
    """Whatever the rewrite rule covers passes the gate: languages, blanks, any ending."""
    for text in ("ana(arroba)firma(punto)es", "name [arobase] site [point] fr", "john [ at ] example.com", "john ( at ) example.com", "john {AT} example {Punkt} de", "j\tdot\tdoe\tat\texample\tdot\tcom",
                 "john\nat\nexample\ndot\ncom", "john at example dot museum", "j dot doe at mail dot example dot travel", "john (at) example dot museum", "john@example dot museum", "john at the dot com",
                 "plus oh one oh 2 3 4 5 6 7", "juan arroba ejemplo punto es", "hans at beispiel punkt de", "jean arobase exemple point fr",
                 "plus vier neun drei null eins zwei drei vier fünf", "más tres cuatro seis uno dos tres cuatro cinco", "plus trois trois un deux trois quatre cinq six",
                 "vier eins eins eins eins eins eins eins eins eins eins eins eins eins eins eins"):
        for around in (text, f"to: {text}, thanks", f"é {text} é"):
            base, full = pii.find(around)
            assert text in [around[a:b] for k in pii.KINDS for a, b in full[k]], around
            assert text not in pii.redact(around)
    for clean in ("the one at the dot of two or three things.", "a dot museum is at rest", "(at) [dot]", "see it at this dot matrix show", "un point de vue de la mairie", "der Punkt an dem ein acht ist", "dos o tres puntos de vista, uno a uno", "at this point com is one, two, three"):
        assert pii.redact(clean) == clean
    parts = ["john", " ", " at ", " dot ", "(", ")", "[", "at", "dot", "\t", "\n", "punkt", "example", "com", "xyz", "one ", "oh ", "five-", "ſix ", "7", "\u200b", "<", ">", "é", "@", "fİve ", "un ", "dos-", "punto", "arroba", "point", "fünf ", "más "]
    rng = random.Random(3)
    for _ in range(20_000):
        t = "".join(rng.choice(parts) for _ in range(10))
        assert pii._disguised(t) or not pii.Transducer(t).changed, t


def test_toxicity_pairs_and_held_out():
    def rows(texts):
        t = toxicity.Terms()
        return [np.array(sorted(t.of(x)), np.int64) for x in texts]

    texts, labels = [], []
    for k in range(400):  # toxic only if both words meet
        a, b = k % 2, k // 2 % 2
        texts.append(f"{'grumble ' * a}{'newcomer ' * b}walk {k % 7} talk")
        labels.append(a & b)
    m = toxicity.fit(rows(texts), labels, epochs=40)
    t = toxicity.Terms({int(b): k for k, b in enumerate(m.buckets)})
    both, one, other = toxicity.score_texts(m, t, ["grumble newcomer", "grumble", "newcomer"])
    assert both >= 0.5 > max(one, other)
    assert toxicity.fit([], []) is None and toxicity.score_texts(None, t, ["x", None]) == [0.0, 0.0]
    assert 0 <= toxicity.score_texts(m, t, [None])[0] < 0.5


def test_media_round_trip(spark, odd):
    for text in (None, "", "a" * 70_000, "é\xff" * 999, "x" * 64):
        n, payload = media.payload_of(text)
        stored = media.write_avi(payload)
        fps, length, frames = media.read_avi(stored)
        assert np.stack(frames).tobytes()[:length] == payload and fps == 25 and len(payload) % 64 == 0
        for f in frames:
            assert media.frame_bytes(f)[:2] == b"\xff\xd8"
    dark, light = np.zeros((8, 64), np.uint8), np.full((8, 64), 200, np.uint8)
    assert media.shots([dark] * 3 + [light] * 2) == [(0, 3), (3, 5)] and media.shots([]) == []
    rows = media.clips(media.text_to_avi(odd.where("doc_id = 5"), ["doc_id"])).collect()
    assert rows[0]["first_frame"] == 0 and rows[-1]["end_s"] > 0
    assert len(media.summarize(odd, ["doc_id"]).collect()) == odd.count()


def brute_components(texts):
    sets = {}
    for d, t in texts:
        w = (t or "").encode().lower().split()
        sets[d] = {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())
    comp = {d: d for d in sets}

    def root(x):
        while comp[x] != x:
            x = comp[x]
        return x

    ids = sorted(sets)
    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            inter = len(sets[a] & sets[b])
            if inter and 100 * inter >= 80 * len(sets[a] | sets[b]):
                x, y = root(a), root(b)
                comp[max(x, y)] = min(x, y)
    return {d: (len(sets[d]), root(d)) for d in ids}


def test_join_equals_brute_force(spark, odd, empty):
    rng = random.Random(7)
    words = [f"w{k}" for k in range(300)]
    texts, passage = [], [rng.choice(words) for _ in range(60)]
    for g in range(12):
        base = [rng.choice(words) for _ in range(rng.choice((4, 12, 60, 150)))]
        for _ in range(8):
            own = list(base)
            for _ in range(rng.choice((0, 0, 1, 2, 3))):
                own[rng.randrange(len(own))] = rng.choice(words)
            if rng.random() < 0.3:
                own += passage
            texts.append((len(texts), " ".join(own)))
    texts += [(500, None), (501, ""), (502, " \t"), (503, "A b"), (504, "a B")]
    df = spark.createDataFrame(texts, "doc_id long, text string")
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in ngram_join.near_duplicates(df).collect()}
    assert got == brute_components(texts)
    assert ngram_join.near_duplicates(empty).count() == 0
    assert ngram_join.near_duplicates(odd).count() == odd.count()


def test_pipeline_stages(spark):
    import corpus_pipeline

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    for name, stage in corpus_pipeline.STAGES[:4]:
        out = stage(spark, docs, SF)
        assert out.columns == docs.columns, name
    kept = corpus_pipeline.near_duplicates(spark, docs, SF)
    want = {c for _, c in brute_components([tuple(r) for r in docs.select("doc_id", "text").collect()]).values()}
    assert {r[0] for r in kept.select("doc_id").collect()} == want
    assert "pipeline" in entry.queries() and set(corpus.oracle_sql()) <= set(corpus.queries())
