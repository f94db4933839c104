"""The operators on texts against plain versions, held-out accuracy, and edge cases in every column."""

import hashlib
import random
import re
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from aclvec.llm import bpe, hmm, langid, linecrf, linededup, media, mixing, quality
from aclvec.llm.common import crc_mod, id_and_bytes

WORD = re.compile(r"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, score double, lost_id string, weight string, s string"
LONG = "wort und satz, ein langer text mit worten\n" * 30_000
EDGE = [
    (1, None, None, None, None, 0.1, "x", "w", "s"), (2, "", "en", "src0", 0, None, None, None, None), (3, LONG, "de", "src1", None, 0.5, "y", None, "s"),
    (4, "Same text here, twice over\nthe shared line of both", "en", "src0", 1, 0.2, "z", None, None), (4, "Same text here, twice over\nthe shared line of both", "en", "src0", 1, 0.2, "z", None, None),
    (5, "Same text here, twice over\nthe shared line of both", "fr", None, 1, 0.2, "z", None, None), (None, "no id, \u00e9t\u00e9 \U0001F600 12\u00b2\nthe shared line of both", "fr", "src2", 1, 0.2, "z", None, None),
    (7, " \t\n ", "en", "src0", 3, 0.1, "q", None, None), (8, "12 34 -- !!", "en", "src0", 3, 0.1, "q", None, None),
]


@pytest.fixture(scope="module")
def edge(spark):
    return spark.createDataFrame(EDGE, SCHEMA)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def docs(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")


@pytest.fixture(scope="module")
def labels(spark, sf):
    return spark.read.parquet(f"{sf}/labels.parquet")


def texts_of(df):
    return {r.doc_id: r.text for r in df.select("doc_id", "text").collect()}


# Byte-level BPE


@pytest.fixture(scope="module")
def ranks():
    return bpe.read_ranks(bpe.default_path())


@pytest.fixture(scope="module")
def library(ranks):
    import public_tokenizers
    import tiktoken

    return tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})


def test_pieces_and_ids_equal_the_library(ranks, library):
    rng = random.Random(5)
    chars = list("ab'strevmld  \n\t \u3000\u00e9\u6f22\u5b5712\u00b2!?.,'\u2019\U0001F600\x1c\x85\u00a0_\u00f1\u0301")
    texts = ["".join(rng.choice(chars) for _ in range(rng.randint(0, 40))) for _ in range(4000)] + ["", "'s", "they'll   ", "x" * 3000, "'" * 60, "\u6f22" * 400, " " * 300]
    e, d = bpe.Encoder(ranks), bpe.Decoder(ranks)
    for t, got in zip(texts, e.encode([t.encode() for t in texts]), strict=True):
        ids = np.frombuffer(got, "<u4")
        assert ids.tolist() == library.encode_ordinary(t), t
        back, at = d.decode(ids)
        assert back == t.encode()
        assert [back[a:b] for a, b in zip(at, [*at[1:], len(back)], strict=False)] == [library.decode_single_token_bytes(i) for i in ids.tolist()]


def test_a_small_cache_changes_nothing(ranks, docs):
    texts = [t.encode() for t in list(texts_of(docs).values())[:40]]
    small, large = bpe.Encoder(ranks, cache_size=10, widest=4), bpe.Encoder(ranks)
    assert [small.encode([t])[0] for t in texts] == large.encode(texts)


def test_codec_on_edges(edge, none, ranks, library):
    rows = bpe.encode(edge, ranks, digests=True).collect()
    assert sorted(len(r.ids) for r in rows) == sorted(len(library.encode_ordinary(t or "")) for _, t, *_ in EDGE)
    assert all(r.n_tokens == len(r.ids) for r in rows)
    want = Counter(hashlib.sha256((t or "").encode()).hexdigest() for _, t, *_ in EDGE)
    assert Counter(r.decoded_sha256 for r in rows) == want
    back = bpe.decode(bpe.encode(edge, ranks), ranks).collect()
    assert Counter(r.text for r in back) == Counter(t or "" for _, t, *_ in EDGE)
    assert bpe.encode(none, ranks).count() == 0


# Media


def test_companding_tables():
    mu, a = media.mulaw_table(), media.alaw_table()
    assert mu[0xFF] == 0 and mu[0x7F] == 0 and mu[0x00] == -32124 and mu[0x80] == 32124
    assert a[0xD5] == 8 and a[0x55] == -8 and a[0xAA] == 32256 and a[0x2A] == -32256
    assert len(set(a.tolist())) == 256


def scalar_adpcm(block: bytes) -> list[int]:
    steps, move = media.ima_steps(), media.IMA_INDEX * 2
    value, index = int.from_bytes(block[:2], "little", signed=True), min(block[2], 88)
    out = [value]
    for byte in block[4:]:
        for code in (byte & 15, byte >> 4):
            step = int(steps[index])
            delta = step >> 3
            for bit, part in ((4, step), (2, step >> 1), (1, step >> 2)):
                delta += part if code & bit else 0
            value = max(-32768, min(32767, value - delta if code & 8 else value + delta))
            index = max(0, min(88, index + move[code]))
            out.append(value)
    return out


def test_adpcm_blocks():
    rng = np.random.default_rng(1)
    blocks = rng.integers(0, 256, (20, 36), dtype=np.uint8)
    got = media.adpcm_decode(blocks)
    for b, row in zip(blocks, got, strict=True):
        assert row.tolist() == scalar_adpcm(b.tobytes())
    tone = (8000 * np.sin(np.arange(65 * 20) / 9)).astype(np.int64).reshape(20, 65)
    again = media.adpcm_decode(media.adpcm_encode(tone)).astype(int)
    assert np.abs(again - tone)[:, 20:].mean() < 400
    assert len(media.ima_steps()) == 89


def test_every_kind_of_file_becomes_pcm():
    data = bytes(range(256)) * 3
    for tag in (media.MULAW, media.ALAW):
        rate, x = media.samples(media.wave(tag, data, 8000))
        assert rate == 8000 and len(x) == 768
    rate, x = media.samples(media.wave(media.IMA, bytes(144), 8000, 36, 4))
    assert len(x) == 4 * 65
    assert len(media.resample(x, 8000, 16000)) == 2 * len(x) and len(media.resample(x, 8000, 11025)) == len(x) * 11025 // 8000
    with pytest.raises(ValueError):
        media.parse_wave(b"nothing")


def test_payload_is_read_back(edge, none, docs):
    rows = media.described(media.read_media(media.encode_media(edge.union(docs.selectExpr("doc_id", "text", "lang", "source", "n_chars", "0D", "''", "''", "''"))))).collect()
    want = Counter()
    for t in [t or "" for _, t, *_ in EDGE] + [t or "" for t in texts_of(docs).values()]:
        b = t.encode()
        b += b"\xff" * (576 - len(b) % 576 if len(b) % 576 or not b else 0)
        want[(len(t.encode()), len(b), hashlib.sha256(b).hexdigest(), zlib.crc32(b[-32:]))] += 1
    assert Counter((r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) for r in rows) == want
    assert len({r.feature for r in rows if r.doc_id in (4, 5) and r.n_bytes == len(EDGE[3][1])}) == 1
    assert media.described(media.read_media(media.encode_media(none))).count() == 0


def test_stored_speech_equals_a_plain_decoder(spark):
    """Each coding of a payload, sample by sample: mu-law and A-law by their formulas, ADPCM one code at a time, linear steps between."""
    text = "Telephony \u00e9 " * 70
    r = media.read_media(media.encode_media(spark.createDataFrame([(1, text)], "doc_id long, text string"))).first()
    payload = media.padded(text.encode())

    def mulaw(b):
        b = ~b & 255
        size = (((b & 15) * 2 + 33) << (b >> 4 & 7)) * 4 - 132
        return -size if b & 128 else size

    def alaw(b):
        b ^= 0x55
        seg, low = b >> 4 & 7, b & 15
        size = (low * 2 + 1) * 8 if seg == 0 else (low * 2 + 33) * 8 << (seg - 1)
        return size if b & 128 else -size

    def twice(x):
        out = []
        for a, b in zip(x, [*x[1:], x[-1]], strict=True):
            out += [a, (a + b) >> 1]
        return np.array(out, np.int16)

    rate, pcm = media.samples(r.pcm)
    assert rate == media.OUT_RATE and pcm.tolist() == twice([mulaw(b) for b in payload]).tolist()
    assert r.alaw == media.describe(twice([alaw(b) for b in payload]))
    assert r.adpcm == media.describe(twice([x for i in range(0, len(payload), media.BLOCK) for x in scalar_adpcm(payload[i : i + media.BLOCK])]))


# Language


def test_languages_of_held_out_documents(spark, sf):
    rows = langid.op1_language_id(spark, "/root/testdata/sf0.01").join(spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "lang"), "doc_id").filter("held_out").collect()
    assert sum(r.lang == r.lang_pred for r in rows) / len(rows) > 0.97
    assert all(0 <= r.score <= 1 for r in rows)


def test_language_edges(edge, none, docs):
    known = docs.filter(crc_mod("doc_id", 4) != 2)
    model = langid.train(known, known.count())
    rows = langid.predict(id_and_bytes(edge), model).collect()
    assert {r.lang_pred for r in rows if r.doc_id in (1, 2, 7, 8)} == {"und"}
    assert len(rows) == len(EDGE) and all(r.lang_pred in (*model["langs"], "und") for r in rows)
    empty = langid.train(none, 0)
    assert {r.lang_pred for r in langid.predict(id_and_bytes(edge), empty).collect()} == {"und"}
    assert langid.predict(id_and_bytes(none), model).count() == 0


def test_unseen_words_back_off(docs):
    known = docs.filter("lang in ('de', 'es')")
    scorer = langid.Scorer(langid.train(known, known.count()))
    lang, _ = scorer.predict(["cióncióndoraxq menteqq".encode(), "schheitungxq keitungqq".encode()])
    assert lang == ["es", "de"]


def test_rare_languages_keep_their_words(spark):
    """Four Spanish texts against thousands of others: what Spanish chooses doesn't depend on the others' size, and true counts stay."""
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").filter("lang is not null").select("doc_id", "text", "lang")
    held = crc_mod("doc_id", 4) == 2
    few = docs.filter("lang = 'es'").filter(~held).orderBy("doc_id").limit(4)
    others = docs.filter("lang <> 'es'").filter(~held).crossJoin(spark.range(20).withColumnRenamed("id", "copy")).drop("copy")
    known = others.union(few)
    model = langid.train(known, 0)
    test = docs.filter(held & (F.col("lang") == "es"))
    rows = langid.predict(id_and_bytes(test), model).collect()
    assert sum(r.lang_pred == "es" for r in rows) / len(rows) > 0.97
    counts = langid.count_features(known).cache()
    kept = {(r.lang, r.kind, r.gram): r.n for r in langid.chosen(counts, 4).collect()}
    grams = {(k, g) for _, k, g in kept}
    assert kept == {(r.lang, r.kind, r.gram): r.n for r in counts.collect() if (r.kind, r.gram) in grams}
    assert all((r.kind, r.gram) in grams for r in counts.filter("lang = 'es' and n >= 2").collect())
    assert sum(k == 0 for k, _ in grams) <= langid.WORDS and sum(k > 0 for k, _ in grams) <= langid.GRAMS


# Quality


def test_quality_of_held_out_documents(spark):
    at = "/root/testdata/sf0.01"
    rows = quality.op3_quality(spark, at).join(spark.read.parquet(f"{at}/labels.parquet"), "doc_id").collect()
    for held in (False, True):
        own = [r for r in rows if r.held_out == held]
        assert sum(r.predicted == r.quality for r in own) / len(own) > 0.95
    assert all(r.predicted == int(r.score >= 0.7) for r in rows)


def test_quality_edges(edge, none, docs, labels):
    model = quality.train(docs, labels.union(labels.limit(1).selectExpr("doc_id", "cast(null as int)", "0")))
    assert quality.predict(id_and_bytes(edge), model).count() == len(EDGE)
    assert quality.train(docs, labels.limit(0)) is None
    assert {r.score for r in quality.predict(id_and_bytes(edge), None).collect()} == {1.0}
    assert quality.accepted(none, model).columns == none.columns and quality.accepted(none, model).count() == 0


def test_additive_model_finds_an_interaction():
    rng = np.random.default_rng(0)
    x = rng.random((4000, 3))
    y = ((x[:, 0] > 0.5) ^ (x[:, 1] > 0.5)).astype(float)
    m = quality.fit(x[:3000], y[:3000])
    assert (0, 1) in m.pairs
    assert ((m.score(x[3000:]) > 0.5) == (y[3000:] > 0)).mean() > 0.9


# Line labelling


def plain_counts(t):
    w = WORD.findall(t)
    windows = [tuple(w[i : i + 5]) for i in range(len(w) - 4)]
    often, hit, seen, dup = Counter(windows), set(), set(), 0
    for i, x in enumerate(windows):
        if often[x] > 1:
            hit |= set(range(i, i + 5))
    for line in t.split("\n"):
        dup += line in seen and bool(WORD.search(line))
        seen.add(line)
    return len(w), sum(map(len, w)), sum(t.count(c) for c in "#*$%&|<>"), dup, len(hit)


def test_line_rules(edge, none, docs, labels):
    both = docs.select("doc_id", "text").union(edge.filter("doc_id <> 3").select("doc_id", "text"))
    field = linecrf.train(docs, labels)
    rows = linecrf.judge(both, field).collect()
    got = Counter((r.doc_id, r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) for r in rows)
    assert got == Counter((r.doc_id, *plain_counts(r.text or "")) for r in both.collect())
    assert all(r.base_failed == (r.n_words < 10 or 100 * r.n_repeat_words > 20 * r.n_words) and not (r.base_failed and r.kept) for r in rows)
    quality_of = {r.doc_id: r.quality for r in labels.collect()}
    own = [r for r in rows if r.doc_id in quality_of and not r.base_failed]
    assert sum(r.kept == bool(quality_of[r.doc_id]) for r in own) / len(own) > 0.9
    assert linecrf.judge(none, field).count() == 0 and linecrf.judge(edge, linecrf.Field()).count() == len(EDGE)


def test_viterbi_is_the_best_of_all_paths():
    import itertools

    rng = np.random.default_rng(7)
    f = linecrf.Field(rng.normal(size=(linecrf.FEATURES, 2)), rng.normal(size=(2, 2)))
    counts = np.array([1, 5, 3])
    x = rng.random((9, linecrf.FEATURES)) < 0.4
    first = np.array([0, 1, 6])
    label, emit = f.decode(x, first, counts), x @ f.weight
    for a, n in zip(first, counts, strict=True):
        value = lambda path, a=a: sum(emit[a + i, s] for i, s in enumerate(path)) + sum(f.move[s, t] for s, t in zip(path, path[1:], strict=False))
        best = max(itertools.product((0, 1), repeat=int(n)), key=value)
        assert tuple(label[a : a + n]) == best


def test_field_learns_runs():
    rng = np.random.default_rng(9)
    y = np.repeat(rng.integers(0, 2, 200), 6)
    x = np.zeros((1200, linecrf.FEATURES), bool)
    x[:, 0] = True
    x[:, 1] = np.where(rng.random(1200) < 0.75, y, 1 - y)
    first, counts = np.arange(0, 1200, 60), np.full(20, 60)
    f = linecrf.Field().train(x, y, first, counts)
    assert (f.decode(x, first, counts) == y).mean() > (x[:, 1] == y).mean() + 0.03


# Hidden Markov model


def naive(model, seq):
    a, total = model.start, 0.0
    for s in seq:
        a = (a @ model.move) * model.emit[s]
        total += np.log(a.sum())
        a = a / a.sum()
    return total


def test_likelihood_and_counts_are_exact():
    rng = np.random.default_rng(1)
    model = hmm.Model.first(rng.integers(1, 50, hmm.END + 1).astype(float), 3)
    seqs = [rng.integers(0, hmm.END + 1, n).astype(np.uint16) for n in (1, 2, 63, 200, hmm.SEGMENT - 1, hmm.SEGMENT, hmm.SEGMENT + 1, 3 * hmm.SEGMENT + 7)]
    total = hmm.likelihood(model, seqs)
    assert total == pytest.approx([naive(model, s) for s in seqs])
    assert hmm.likelihood(model, seqs[:2]) == pytest.approx(total[:2]) and hmm.likelihood(model, seqs[-1:]) == pytest.approx(total[-1:])
    start, move, emit, logp = hmm.expected(model, seqs)
    for plain, quick in zip(hmm.expected(model, seqs, np.float64), (start, move, emit, logp), strict=True):
        assert np.allclose(plain, quick, rtol=1e-4, atol=1e-5)
    n = sum(map(len, seqs))
    assert logp == pytest.approx(total.sum())
    assert (start.sum(), move.sum(), emit.sum()) == pytest.approx((len(seqs), n, n))
    apart = [hmm.expected(model, [s]) for s in seqs]
    for k, whole in enumerate((start, move, emit)):
        assert np.allclose(sum(p[k] for p in apart), whole)


def test_baum_welch_raises_the_likelihood():
    rng = np.random.default_rng(2)
    seqs = [np.concatenate([rng.integers(a, a + 30, 40) for a in (0, 100, 0)]).astype(np.uint16) for _ in range(30)]
    counts = np.bincount(np.concatenate(seqs), minlength=hmm.END + 1).astype(float)
    model, logs = hmm.Model.first(counts, 2), []
    for _ in range(8):
        *sums, logp = hmm.expected(model, seqs)
        logs.append(logp)
        model = model.updated(*sums, (counts + 0.5) / (counts + 0.5).sum())
    assert logs[-1] > logs[0] + 100 and all(b > a - 1 for a, b in zip(logs, logs[1:], strict=False))


def test_scores(edge, none, docs):
    both = docs.select("doc_id", "text").union(edge.filter("doc_id is null or doc_id <> 3").selectExpr("doc_id + 100000 as doc_id", "text"))
    rows = hmm.score_texts(both, crc_mod("doc_id", 10) == 0).collect()
    tokens = [(r.doc_id, [*[w.encode().translate(bytes.maketrans(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz")) for w in WORD.findall(r.text or "")], None]) for r in both.collect()]
    held = lambda i: i is None or zlib.crc32(str(i).encode()) % 10 == 0
    c = Counter(w for i, ws in tokens if not held(i) for w in ws)
    n, v = sum(c.values()), len(c)
    want = sorted((i or -1, len(ws), sum(c[w] > 0 for w in ws), n, round(sum(np.log10((c[w] + 0.1) / (n + 0.1 * (v + 1))) for w in ws), 6)) for i, ws in tokens)
    got = sorted((r.doc_id or -1, r.n_tokens, r.n_known, r.train_tokens, round(r.base_score, 6)) for r in rows)
    assert np.allclose(np.array(got), np.array(want, float), atol=1e-5)
    assert all(r.score < 0 and np.isfinite(r.score) for r in rows)
    for h in (False, True):
        own = [r for r in rows if r.held_out == h]
        assert sum(r.score for r in own) > sum(r.base_score for r in own)
    assert hmm.score_texts(none, F.lit(False)).count() == 0
    unknown = hmm.score_texts(edge.select("doc_id", "text"), F.lit(True)).collect()
    assert len(unknown) == len(EDGE) and all(np.isfinite(r.score) and r.n_known == 0 for r in unknown)


def test_score_equals_a_plain_forward_sum(edge, docs, monkeypatch):
    """The query's score, long text and unknown words included, against symbols and a recursion written out."""
    both = docs.select("doc_id", "text").union(edge.filter("doc_id = 3").selectExpr("100003L as doc_id", "text"))
    held, found, plain = (lambda i: zlib.crc32(str(i).encode()) % 10 == 0), [], hmm.train_model
    monkeypatch.setattr(hmm, "TOP", 300)
    monkeypatch.setattr(hmm, "train_model", lambda *a: found.append(plain(*a)) or found[-1])
    rows = {r.doc_id: r for r in hmm.score_texts(both, crc_mod("doc_id", 10) == 0).collect()}
    texts = {r.doc_id: hmm.words_of((r.text or "").encode()) for r in both.collect()}
    c = Counter(w for i, ws in texts.items() if not held(i) for w in ws)
    first = {w for w, _ in sorted(c.items(), key=lambda x: (-x[1], x[0]))[:300]}
    own = sorted((w for w in c if c[w] >= hmm.OWN or w in first), key=lambda w: (-int(np.log2(c[w])), zlib.crc32(w) % hmm.PARTS, w))
    symbol = {w: hmm.END + 1 + i for i, w in enumerate(own)}
    group_c, group_v = Counter(), Counter()
    for w in c.keys() - symbol.keys():
        group_c[hmm.group_of(w)] += c[w]
        group_v[hmm.group_of(w)] += 1
    for i in [*list(texts)[:60], 100_003]:
        seq = [symbol.get(w, hmm.group_of(w)) for w in texts[i]]
        inner = sum(np.log10((c[w] + 0.1) / (group_c[g] + 0.1 * (group_v[g] + 1))) for w, g in zip(texts[i], seq, strict=True) if w not in symbol)
        assert rows[i].score == pytest.approx(naive(found[0], [*seq, hmm.END]) / np.log(10) + inner)


def test_every_round_reads_all_training_texts(spark, monkeypatch):
    rng = np.random.default_rng(5)
    seqs = [np.concatenate([rng.integers(a, a + 30, 12) for a in rng.permutation([0, 100, 200])]).astype(np.uint32) for _ in range(1_200)]
    rows = spark.createDataFrame([(i, x.tobytes()) for i, x in enumerate(seqs)], "doc_id long, symbols binary").cache()
    counts = np.bincount(np.concatenate(seqs), minlength=hmm.END + 1).astype(float)
    read, plain = [], hmm.round_counts
    monkeypatch.setattr(hmm, "round_counts", lambda rows, model: read.append(rows.count()) or plain(rows, model))
    model = hmm.train_model(rows, counts, len(seqs))
    assert len(read) > 2 and set(read) == {len(seqs)}
    share = (counts + 0.5) / (counts + 0.5).sum()
    *sums, logp = hmm.expected(model, seqs)
    assert hmm.expected(model.updated(*sums, share), seqs)[3] - logp < 2 * hmm.GAIN * counts.sum()


def test_symbols_grow_with_the_vocabulary(spark):
    """Two words beyond the first 2,000, alike in their last bytes and counts, in texts of different kinds."""
    rng = random.Random(3)
    texts = []
    for i in range(400):
        kind = "ab"[i % 2]
        words = [f"{kind}{rng.randrange(1_300)}" for _ in range(700)]
        if i < 120:
            words[rng.randrange(700)] = f"{kind}-pairzzz"
        texts.append((i, " ".join(words)))
    run = [f"a{i}" for i in range(200, 260)]
    texts += [(1_000, " ".join([*run, "a-pairzzz", *run])), (1_001, " ".join([*run, "b-pairzzz", *run]))]
    docs = spark.createDataFrame(texts, "doc_id long, text string")
    got = {r.doc_id: r for r in hmm.score_texts(docs, F.col("doc_id") >= 1_000).filter("held_out").collect()}
    assert got[1_000].base_score == pytest.approx(got[1_001].base_score)
    assert got[1_000].score > got[1_001].score + 1


# Lines


def plain_dedup(rows):
    key = lambda x: x.strip(" \t\n\r\x0b\x0c").translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"))
    last = (1 << 63) - 1
    owner, many = {}, {}
    for i, t in rows:
        i = last if i is None else i
        for x in {key(x) for x in (t or "").split("\n")}:
            if len(x) >= 10:
                many.setdefault(x, set()).add(i)
                owner[x] = min(owner.get(x, last), i)
    out = []
    for i, t in rows:
        lines = (t or "").split("\n")
        kept = [x for x in lines if not (len(many.get(key(x), ())) > 1 and owner[key(x)] != (last if i is None else i))]
        out.append((i or -1, len(lines), len(lines) - len(kept), hashlib.sha256("\n".join(kept).encode()).hexdigest()))
    return Counter(out)


def test_lines(edge, none, docs):
    for frame in (edge, docs, docs.select("doc_id", "text").union(edge.select("doc_id", "text"))):
        rows = [(r.doc_id, r.text) for r in frame.select("doc_id", "text").collect()]
        got = Counter((r.doc_id or -1, r.n_lines, r.n_dropped, r.kept_sha256) for r in linededup.dedup_lines(frame, digests=True).collect())
        assert got == plain_dedup(rows)
    whole = linededup.dedup_lines(edge)
    assert whole.columns[: len(edge.columns)] == edge.columns and whole.count() == len(EDGE)
    assert linededup.dedup_lines(none).count() == 0


def test_hot_lines_are_probed_in_several_tasks(spark, monkeypatch):
    monkeypatch.setattr(linededup, "PROBES", 50)
    monkeypatch.setattr(linededup, "SHARD_LEAST", 20)
    rows = [(i, f"the line that all documents hold\nown line number {i % 90}\nrest {i}") for i in range(400)]
    frame = spark.createDataFrame(rows, "doc_id long, text string").repartition(7)
    got = Counter((r.doc_id or -1, r.n_lines, r.n_dropped, r.kept_sha256) for r in linededup.dedup_lines(frame, digests=True).collect())
    assert got == plain_dedup(rows)


def test_perfect_hash_is_minimal():
    rng = np.random.default_rng(4)
    a, b = (rng.integers(0, 1 << 63, 5000).astype(np.uint64) for _ in range(2))
    ph = linededup.PerfectHash.build(a, b)
    assert sorted(ph.place(a, b).tolist()) == list(range(5000))
    with pytest.raises(ValueError):
        linededup.PerfectHash.build(np.array([1, 1], np.uint64), np.array([2, 2], np.uint64))


# Mixing


def test_mix_meets_the_entropy_or_the_limit(docs):
    rows = mixing.draws(docs).collect()
    tokens, weight = Counter(), {}
    for r in rows:
        tokens[r.source] += r.n_tokens
        weight[r.source] = r.weight
    assert sum(weight.values()) == pytest.approx(1)
    total = sum(tokens.values())
    reps = {s: weight[s] / (tokens[s] / total) for s in tokens}
    entropy = -sum(w * np.log(w) for w in weight.values())
    assert max(reps.values()) / min(reps.values()) <= mixing.REPEATS + 1e-6
    assert entropy >= mixing.ENTROPY_SHARE * np.log(len(tokens)) - 1e-9 or max(reps.values()) / min(reps.values()) > mixing.REPEATS - 0.01
    assert min(r.copies for r in rows) >= 1
    drawn = Counter()
    for r in rows:
        drawn[r.source] += r.copies * r.n_tokens
    budget = max(tokens[s] / weight[s] for s in tokens)
    for s in tokens:
        assert abs(drawn[s] - weight[s] * budget) <= max(r.n_tokens for r in rows if r.source == s) + 1


def test_budget_and_blocks(docs, monkeypatch):
    monkeypatch.setattr(mixing, "BLOCK", 500)
    total = sum(len(WORD.findall(t)) for t in texts_of(docs).values())
    rows = mixing.draws(docs, budget=total).collect()
    assert sum(r.copies * r.n_tokens for r in rows) == pytest.approx(total, rel=0.15)
    spans = sorted((r.source, r.place, r.n_tokens) for r in rows if r.n_tokens)
    for (s, a, n), (t, b, _) in zip(spans, spans[1:], strict=False):
        assert s != t or a + n == b


def test_mix_edges(edge, none):
    assert mixing.draws(edge).count() == len(EDGE)
    out = mixing.mixed(edge)
    assert out.columns == edge.columns and out.count() >= len(EDGE)
    assert mixing.draws(none).count() == 0 and mixing.mixed(none).count() == 0


# Plain versions of fitted models, clashing names


def test_language_scores_equal_a_plain_version(docs):
    """Words first, then the longest known n-gram at each place of an unseen word, with plain sums."""
    known = docs.filter(crc_mod("doc_id", 4) != 2)
    model = langid.train(known, known.count())
    names, logs = model["words"]
    row = dict(zip(names, logs.astype(float), strict=True))

    def of(word):
        if word in row:
            return row[word]
        w, total = f"<{word}>", np.zeros(len(model["langs"]))
        for i in range(len(w)):
            for step, k in enumerate(langid.ORDERS):
                if i + k <= len(w) and w[i : i + k] in model["grams"][k]:
                    total += langid.DISCOUNT**step * model["grams"][k][w[i : i + k]].astype(float)
                    break
        return total / len(w)

    texts = [*list(texts_of(docs).values())[:60], "Zwqx unbekanntlich 12 Worté", LONG[:3000]]
    scorer = langid.Scorer(model)
    for t in texts:
        lang, score = (x[0] for x in scorer.predict([(t or "").encode()]))
        ws = re.findall(r"[^\W\d_]+", (t or "").lower())
        if not ws:
            assert (lang, score) == ("und", 0.0)
            continue
        z = sum(map(of, ws)) / len(ws) * min(len(ws), 30)
        p = np.exp(z - z.max())
        p /= p.sum()
        assert lang == model["langs"][int(p.argmax())] and score == pytest.approx(p.max(), rel=1e-3)


def test_quality_scores_equal_a_plain_lookup(docs, labels):
    """A score is the base plus an entry for each feature and pair, looked up by counting the edges passed."""
    m = quality.train(docs, labels)
    texts = [(t or "").encode() for t in [*list(texts_of(docs).values())[:40], "", LONG]]
    for x, got in zip(quality.features(texts), m.score(quality.features(texts)), strict=True):
        at = lambda edges, v: sum(v >= e for e in edges)
        z = m.base + sum(t[at(e, v)] for e, t, v in zip(m.edges, m.tables, x, strict=True))
        z += sum(g[at(m.coarse[a], x[a]), at(m.coarse[b], x[b])] for (a, b), g in zip(m.pairs, m.grids, strict=True))
        assert got == pytest.approx(1 / (1 + np.exp(-max(-30, min(30, z)))))


def test_results_replace_columns_of_their_names(edge, docs, labels):
    known = docs.filter("lang is not null")
    rows = langid.predict(id_and_bytes(edge, "score", "lost_id"), langid.train(known, known.count()))
    assert rows.columns == ["doc_id", "lost_id", "lang_pred", "score"] and rows.count() == len(EDGE)
    rows = quality.predict(id_and_bytes(edge, "score", "s"), quality.train(docs, labels))
    assert rows.columns == ["doc_id", "s", "score", "predicted"] and all(0 <= r.score <= 1 for r in rows.collect())


def test_held_out_documents_of_the_line_rules(spark):
    at = "/root/testdata/sf0.01"
    got = linecrf.op4_line_rules(spark, at).join(spark.read.parquet(f"{at}/labels.parquet"), "doc_id").filter((crc_mod("doc_id", 4) == 2) & ~F.col("base_failed")).collect()
    assert len(got) > 50 and sum(r.kept == bool(r.quality) for r in got) / len(got) > 0.9


def test_lines_have_the_label_of_most_texts(docs, labels, monkeypatch):
    code = np.array([5, 6, 0, 5, 7, 5, 0, 6])
    text = np.array([0, 0, 0, 1, 1, 2, 2, 2])
    assert linecrf.line_labels(code, text, np.array([1, 1, 0])).tolist() == [0, 0, 0, 0, 0, 0, 1, 1]
    assert linecrf.line_labels(code, text, np.array([1, 0, 0])).tolist() == [1, 0, 0, 1, 1, 1, 1, 1]
    monkeypatch.setattr(linecrf, "LINES", 40)
    few = linecrf.train(docs, labels)
    assert np.isfinite(few.weight).all()
    monkeypatch.setattr(linecrf, "LINES", 0)
    assert not linecrf.train(docs, labels).weight.any()


def test_codecs_of_two_vocabularies_stay_apart(spark, ranks):
    """Vocabularies that differ in one token, in the same workers; and bytes that are no UTF-8."""
    small = {t: i for t, i in ranks.items() if len(t) == 1 or t in (b"he", b"ll")}
    other = {b"lo" if t == b"ll" else t: i for t, i in small.items()}
    docs = spark.createDataFrame([(1, "hello")], "doc_id long, text string")
    for v, want in ((small, [b"he", b"ll", b"o"]), (other, [b"he", b"l", b"lo"]), (small, [b"he", b"ll", b"o"])):
        assert bpe.encode(docs, v).first().ids == [v[t] for t in want]
    broken = docs.select("doc_id", F.unhex(F.lit("61FF62C3")).cast("string").alias("text"))
    r = bpe.encode(broken, ranks, digests=True).first()
    assert r.decoded_sha256 == hashlib.sha256("a�b�".encode()).hexdigest()
