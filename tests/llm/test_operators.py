"""The training-data operators against brute force, the libraries, and exact round trips, with the odd rows of each."""

import hashlib
import zlib

import numpy as np
import public_tokenizers as P
import pytest
from tokenizers import Tokenizer

from blockdup.llm import audio, bpe, count_fst, embeddings, language_id, minhash, packing, pseudo_likelihood, quality, rans, token_files, trie_codec

ODD = [
    "", "   ", "I'll've 'sam  \n\n x'REd ' 's\t\ttab  ", "a<|endoftext|>b <|startoftext|>", "日本 語 123", "İstanbul ſ ŉ é", "x\x1cy z\xa0q", "don't\n's \n\r 're",
    "1234 5٣²½", "'l 'll 'r're''s ' s 'r", "á Σας 𝒳‍👍🏽 \x00 x", "supercali" * 60, "aaaa" * 700, "  'v'l 've\n", "one two three four five six", "one two three four five six",
]


@pytest.fixture(scope="module")
def odd(spark):
    rows = [(k, t, "en", "s", k) for k, t in enumerate(ODD)] + [(90, None, None, None, None), (None, "no id here", "en", "s", 1), (3, ODD[3], "en", "s", 3)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, score string, n long")


def rows_of(df):
    return df.toPandas().astype(object).where(lambda x: x.notna(), None)


def text_of(t):
    return t or ""


def test_coder_round_trip_checkpoints_and_damage():
    r = np.random.default_rng(0)
    for n in (0, 1, 7, 5000, 150_000):
        ids = np.minimum(r.zipf(1.3, n) - 1, 50_000).astype(np.uint16)
        coder = rans.Coder(rans.frequency_table(np.bincount(ids, minlength=65536)))
        block = coder.encode(ids)
        assert (coder.decode(block) == ids).all()
    step = rans.LANES * rans.ROWS_BETWEEN_CHECKPOINTS
    assert rans.segments(block) == -(-n // step) > 2
    for k in range(rans.segments(block)):
        assert (coder.decode_segment(block, k) == ids[k * step : (k + 1) * step]).all()
    with pytest.raises(ValueError):
        coder.decode(block[:50] + bytes([block[50] ^ 1]) + block[51:])


def test_token_files(spark, odd):
    lib = Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    got = rows_of(token_files.read_token_files(*token_files.write_token_files(odd, P.path("byte_bpe_50k.json"))))
    assert len(got) == odd.count()
    place = 0
    for r in got.sort_values("start").itertuples():
        text = "no id here" if r.doc_id is None else text_of(dict(enumerate(ODD)).get(r.doc_id))
        ids = [*lib.encode(text, add_special_tokens=False).ids, 2]
        assert (r.start, r.n_tokens, r.ids_crc32) == (place, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
        place += len(ids)
    assert token_files.read_token_files(*token_files.write_token_files(odd.where("false"), P.path("byte_bpe_50k.json"))).count() == 0


def test_packing(spark, odd):
    lib = Tokenizer.from_file(P.path("word_bpe_49k.json"))
    got = rows_of(packing.pack(odd, P.path("word_bpe_49k.json"), length=64, with_ids=True)).sort_values(["sequence_id", "offset"])
    place = 0
    for r in got.itertuples():
        assert r.sequence_id * 64 + r.offset == place and r.length <= 64
        place += r.length
    one = got[got.doc_id == 11].sort_values("start")
    assert [x for r in one.ids for x in r] == [*lib.encode(ODD[11], add_special_tokens=False).ids, 2]
    total = sum(len(lib.encode(text_of(t), add_special_tokens=False).ids) + 1 for t in [*ODD, None, "no id here", ODD[3]])
    assert place == total
    assert packing.pack(odd.where("false"), P.path("word_bpe_49k.json")).count() == 0


def test_trie_codec_is_the_library(spark, odd):
    lib = Tokenizer.from_file(P.path("word_bpe_49k.json"))
    got = rows_of(trie_codec.encode_digests(odd, P.path("word_bpe_49k.json")))
    sha = lambda x: hashlib.sha256(x).hexdigest()
    for r in got[got.doc_id.notna()].itertuples():
        ids = lib.encode(text_of(dict(enumerate(ODD)).get(r.doc_id)), add_special_tokens=False).ids
        assert (r.n_tokens, r.ids_sha256, r.decoded_sha256) == (len(ids), sha(np.array(ids, "<u4").tobytes()), sha(lib.decode(ids, skip_special_tokens=False).encode()))


def test_token_counts_are_the_librarys(spark, odd):
    lib = Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    for r in rows_of(count_fst.token_counts(odd, P.path("byte_bpe_50k.json"), limit=10)).itertuples():
        if r.doc_id is not None:
            text = text_of(dict(enumerate(ODD)).get(r.doc_id))
            n = len(lib.encode(text, add_special_tokens=False).ids)
            assert (r.n_bytes, r.n_tokens, r.over_limit) == (len(text.encode()), n, n > 10)


def test_state_maps_compose():
    r = np.random.default_rng(1)
    classes = r.integers(0, count_fst.N_CLASSES, 5000).astype(np.uint8)
    small, large = count_fst.word_starts(classes, 64), count_fst.word_starts(classes, 8192)
    assert (small == large).all()


def test_vocabulary_neighbours():
    v = bpe.Vocabulary(P.path("byte_bpe_50k.json"))
    lib = Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    words = [b"hello", b"unbelievable", b"zzzzqx", b"the"]
    assert bpe.PrefixTrie(v).encode(words) == {w: lib.encode(w.decode(), add_special_tokens=False).ids for w in words}


def test_audio(spark, odd):
    tensors = audio.media_tensors(audio.media_of(odd))
    got = rows_of(audio.digest(tensors))
    assert len(got) == odd.count()
    patches = rows_of(audio.media_patches(tensors))
    for r in got[got.doc_id.notna()].itertuples():
        payload = audio.padded(text_of(dict(enumerate(ODD)).get(r.doc_id)).encode())
        assert r.payload_bytes == len(payload) and len(payload) % 192 == 0 and r.payload_bytes >= max(192, r.n_bytes)
        assert r.payload_sha256 == hashlib.sha256(payload).hexdigest() and r.tail_crc32 == zlib.crc32(payload[-16:])
        media = audio.to_wav(payload)
        assert audio.from_wav(media) == (payload, audio.RATE) and (r.media_bytes, r.media_sha256) == (len(media), hashlib.sha256(media).hexdigest())
        mine = patches[patches.doc_id == r.doc_id].drop_duplicates("start_ms").sort_values("start_ms")
        x = plain_log_mel(payload)
        found = np.array([v for p in mine.log_mel for v in p]).reshape(-1, audio.MELS)
        off = np.abs(found[: len(x)] - np.maximum(x, -60))  # single precision shows at the bottom
        assert off[x > -40].max(initial=0) <= 0.26 and off.max() <= 1.5 and (found[len(x) :] == -60).all()
        ms = 1000 * audio.HOP / 12_000
        assert np.allclose(mine.end_ms.astype(float), np.minimum(mine.start_ms.astype(float) + 32 * ms, len(x) * ms)) and r.feature.startswith(f"frames={len(x)};patches={len(mine)}x32x24;span_ms={int(len(x) * ms + 1e-9)};")
    x = np.sin(2 * np.pi * 440 * np.arange(16_000) / 16_000).astype(np.float32)
    y = audio.resample(x)
    assert len(y) == 12_000 and abs(np.abs(np.fft.rfft(y)).argmax() - 440) <= 1 and 0.95 < np.abs(y[100:-100]).max() < 1.05
    assert audio.segments(np.array([0, 5, 2, 2, 0, 9.0]), 4, 1).tolist() == [[1, 4], [5, 6]]
    assert audio.loaded(audio.stored(audio.features(audio.to_wav(b"abc" * 64)))).schema.field("log_mel").type == audio.TENSOR
    low, high = audio.log_mel(x, 8_000)[0], audio.log_mel(x, 16_000)[0]
    assert np.abs(low - high).max() > 1 and (audio.log_mel(x, 8_000)[0] == low).all()
    assert audio.digest(audio.media_tensors(audio.media_of(odd.where("false")))).count() == 0


def plain_log_mel(payload):
    """The same features sample by sample: a sum over the windowed sinc for each output, one frame at a time."""
    x = (np.frombuffer(payload, np.uint8).astype(float) - 128) / 128
    x = x - x.mean()
    n = -(-len(x) * 3 // 4)
    reach, y = 32, np.zeros(n)
    for k in range(n):
        for j in range(max(0, -(-(4 * k - reach) // 3)), min(len(x) - 1, (4 * k + reach) // 3) + 1):
            t = 4 * k - 3 * j
            y[k] += x[j] * np.sinc(t / 4) / 4 * np.i0(6 * np.sqrt(max(0, 1 - (t / reach) ** 2))) / np.i0(6.0) * 3
    frames = 1 + max(0, -(-(n - 256) // 128))
    y = np.concatenate([y, np.zeros(frames * 128 + 256 - n)])
    mel = lambda f: 2595 * np.log10(1 + f / 700)
    edges = [700 * (10 ** (mel(6000) * k / 25 / 2595) - 1) for k in range(26)]
    f = np.arange(129) * 6000 / 128
    out = np.zeros((frames, 24))
    for k in range(frames):
        power = np.abs(np.fft.rfft(y[128 * k : 128 * k + 256] * np.hanning(256))) ** 2
        for b in range(24):
            out[k, b] = 10 * np.log10((power * np.clip(np.minimum((f - edges[b]) / (edges[b + 1] - edges[b]), (edges[b + 2] - f) / (edges[b + 2] - edges[b + 1])), 0, None)).sum() + 1e-6)
    return out


def components(texts, percent, width=5):
    import re

    sets = []
    for t in texts:
        w = re.findall("[^\x20\x09-\x0d]+", text_of(t).lower())
        sets.append({tuple(w[k : k + width]) for k in range(len(w) - width + 1)} if len(w) >= width else {tuple(w)} if w else set())
    label = list(range(len(texts)))
    for a in range(len(texts)):
        for b in range(a):
            both = len(sets[a] & sets[b])
            if sets[a] and sets[b] and 100 * both >= percent * (len(sets[a]) + len(sets[b]) - both):
                x, y = sorted((label[a], label[b]))
                label = [x if z == y else z for z in label]
    return [len(s) for s in sets], label


def test_near_duplicates(spark):
    r = np.random.default_rng(4)
    base = [f"w{x}" for x in r.integers(0, 900, 120)]
    texts = [None, "", " \n ", "Short one", "short ONE", "short", *(" ".join(base) for _ in range(3))]
    for k in range(40):  # near copies around the threshold, so that chains and misses both occur
        w = list(base)
        for at in r.integers(0, 120, int(r.integers(1, 4))):
            w[at] = f"edit{k}x{at}"
        texts.append(" ".join(w))
    docs = spark.createDataFrame([(k, t, "x") for k, t in enumerate(texts)], "doc_id long, text string, component_id string")
    got = rows_of(minhash.near_duplicates(docs, percent=85)).sort_values("doc_id")
    sizes, label = components(texts, 85)
    assert got.n_shingles.tolist() == sizes and got.component_id.tolist() == label
    assert got.kept.tolist() == [k == x for k, x in enumerate(label)]
    assert minhash.near_duplicates(docs.where("false")).count() == 0
    again = docs.unionByName(docs.where("doc_id < 8")).unionByName(spark.createDataFrame([(None, "short one", "x")], docs.schema))
    got = rows_of(minhash.near_duplicates(again, percent=85))
    assert len(got) == len(texts) + 9 and got[got.doc_id.isna()].component_id.tolist() == [3]


def test_super_minhash_estimates():
    r = np.random.default_rng(0)
    errors = []
    for _ in range(30):
        pool = r.integers(0, 2**63, 300).astype(np.uint64)
        a, b = pool[:200], pool[100:]
        errors.append(minhash.estimate(minhash.super_minhash(a, 256), minhash.super_minhash(b, 256)) - 100 / 300)
    assert abs(np.mean(errors)) < 0.02
    assert (minhash.super_minhash(pool, 64) == minhash.super_minhash(pool[::-1], 64, chunk=17)).all()


def test_linked_vectors(spark):
    r = np.random.default_rng(0)
    centre = r.normal(size=(12, 16))
    x = [*(centre[k % 12] + 0.12 * r.normal(size=16) for k in range(150))]
    rows = [(k, [float(np.float32(c)) for c in v]) for k, v in enumerate(x)]
    rows += [(150, None), (151, [0.0] * 16), (152, [float("nan")] * 16), (153, rows[0][1]), (154, rows[0][1]), (155, [1.0, None] * 8), (156, [1.0, 2.0]), (157, [])]
    df = spark.createDataFrame([(a, b, "z") for a, b in rows], "vec_id long, embedding array<float>, kept string")
    got = rows_of(embeddings.linked_vectors(df, 0.9, tile=32)).sort_values("vec_id").reset_index(drop=True)
    want = embeddings.brute_force([a for a, _ in rows], [b for _, b in rows], 0.9)
    assert got.n_links.tolist() == want.n_links.tolist() and got.component_id.tolist() == want.component_id.tolist()
    assert embeddings.linked_vectors(df.where("false")).count() == 0


def test_vectors_of_other_lengths_and_in_double_precision(spark):
    r = np.random.default_rng(1)
    rows = [r.normal(size=8).tolist() for _ in range(40)] + [(np.array([3.0, 4, 5]) + 0.3 * r.normal(size=3)).tolist() for _ in range(30)] + [[1.0], [2.0], [-1.0]]
    # two pairs as near to the threshold as doubles can tell and single precision cannot
    turn = lambda c: [[1.0, 0, 0, 0, 0], [c, float(np.sqrt(1 - c * c)), 0, 0, 0]]
    rows += [*turn(0.9 + 1e-10), *[[0, 0, 0, *x[:2]] for x in turn(0.9 - 1e-10)]]
    rows = [[float(c) for c in v] for v in rows]
    df = spark.createDataFrame(list(enumerate(rows)), "vec_id long, embedding array<double>")
    got = rows_of(embeddings.linked_vectors(df, 0.9, tile=7)).sort_values("vec_id").reset_index(drop=True)
    want = embeddings.brute_force(list(range(len(rows))), rows, 0.9)
    assert want.n_links.tolist()[-4:] == [1, 1, 0, 0] and want.n_links[40:70].sum() > 0
    assert got.n_links.tolist() == want.n_links.tolist() and got.component_id.tolist() == want.component_id.tolist()
    # rows of one id are vectors of their own
    twice = spark.createDataFrame([(3, [1.0, 0.0]), (5, [1.0, 0.0]), (4, [0.0, 1.0]), (5, [0.0, 1.0]), (None, [0.0, 2.0])], "vec_id long, embedding array<double>")
    got = sorted(((x.vec_id, x.n_links, x.component_id) for x in embeddings.linked_vectors(twice).collect()), key=str)
    assert got == [(3, 1, 3), (4, 2, 4), (5, 1, 3), (5, 2, 4), (None, 2, 4)]


def test_language_and_quality(spark, odd):
    sf = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    model = language_id.fit(docs)
    got = rows_of(language_id.predict(docs, *model).select("doc_id", "lang", "lang_pred", "score"))
    fold = np.array([zlib.crc32(str(k).encode()) % 5 for k in got.doc_id])
    assert (got.lang == got.lang_pred)[fold == 0].mean() > 0.97
    strange = rows_of(language_id.predict(odd, *model))
    assert set(strange[strange.doc_id.isin([0, 1, 90])].lang_pred) == {"und"} and strange.score.between(0, 1).all()
    assert set(rows_of(language_id.predict(odd, *language_id.fit(odd.where("false")))).lang_pred) == {"und"}
    fitted = quality.fit(docs, labels)
    judged = quality.score(docs, fitted).join(labels, "doc_id").toPandas()
    assert (judged.quality == judged.predicted)[[zlib.crc32(str(k).encode()) % 5 == 0 for k in judged.doc_id]].mean() > 0.95
    assert quality.score(odd, fitted).where("score between 0 and 1").count() == odd.count()
    assert quality.score(odd, quality.fit(odd, labels.where("false"))).count() == odd.count()


def test_nonnegative_risk_learns_from_positives_and_unlabelled():
    r = np.random.default_rng(0)
    p, n = r.normal(1.5, 1, (400, 3)), r.normal(-1.5, 1, (200, 3))
    u = np.concatenate([r.normal(1.5, 1, (400, 3)), n])
    net = quality.Descent(quality.initial(3))
    quality.learn(net, p.astype(np.float32), u.astype(np.float32), 2 / 3, 60, 5e-3, r)
    z = quality.forward(net.p, np.concatenate([p, n]).astype(np.float32))[1]
    counts = np.bincount(np.searchsorted(quality.CUTS, quality.forward(net.p, u.astype(np.float32))[1], side="right"), minlength=len(quality.CUTS) + 1)
    assert abs(quality.estimated_prior(z[:400], counts) - 2 / 3) < 0.1
    assert ((z > 0) == np.repeat([True, False], [400, 200])).mean() > 0.95


def test_texts_in_scripts_not_learned_are_dropped(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text", "lang")
    r = np.random.default_rng(4)
    scripts = [(0x3B1, 24), (0x430, 32), (0x4E00, 3000), (0xAC00, 3000)]
    texts = [" ".join("".join(chr(at + int(x)) for x in r.integers(0, n, 5)) for _ in range(120)) for at, n in scripts for _ in range(15)]
    unknown = spark.createDataFrame([(10**6 + k, t, None) for k, t in enumerate(texts)], docs.schema)
    kept = {r.doc_id for r in language_id.keep_known(docs.unionByName(unknown)).select("doc_id").collect()}
    assert not [k for k in kept if k >= 10**6]
    assert len(kept) >= 0.98 * docs.where("text is not null").count()


def test_pseudo_likelihood(spark, odd):
    vocab, net = pseudo_likelihood.fit(odd, rounds=1)
    got = rows_of(pseudo_likelihood.score(odd, vocab, net))
    p = pseudo_likelihood.unpacked(net)
    t = "one two three four five six"
    from blockdup.llm.texts import flat
    import pyarrow as pa

    ids, before = pseudo_likelihood.ids_of(*flat(pa.array([t])), vocab)
    table, total = pseudo_likelihood.tables(p), 0.0
    for k in range(len(ids)):  # each word by itself, with a plain softmax over classes and words
        around = [ids[k + s] if 0 <= k + s < len(ids) else pseudo_likelihood.EDGE for s in (-2, -1, 1, 2)]
        h = np.tanh(sum(table[q][w] for q, w in enumerate(around)) + p["hidden"])
        c, w = ids[k] % pseudo_likelihood.CLASSES, ids[k] // pseudo_likelihood.CLASSES
        for z, y in ((h @ p["top"] + p["top_bias"], c), (h @ p["low"][c] + p["low_bias"][c], w)):
            total += z[y] - np.log(np.exp(z).sum())
    assert abs(got[got.doc_id == 14].log_likelihood.iloc[0] - total) < 1e-3
    assert got[got.doc_id.isin([0, 90])].n_words.tolist() == [0, 0]


def test_pseudo_likelihood_learns_from_every_word(spark):
    docs = spark.createDataFrame([(0, " ".join(["often", *["always"] * 11] * 2))], "doc_id long, text string")
    vocab, net = pseudo_likelihood.fit(docs)
    bias = pseudo_likelihood.unpacked(net)["top_bias"]  # the commonest word has id 1, the other 2
    assert bias[1] > bias[2] > bias[3]
    before = np.array([0, 1, 1, 3, 104])
    places = [pseudo_likelihood.targets(before, k, 2) for k in range(2)]
    assert np.sort(np.concatenate(places)).tolist() == list(range(104))


def test_pseudo_likelihood_spells_words_outside_the_vocabulary(spark):
    common = [f"c{k}" for k in range(pseudo_likelihood.VOCABULARY)] * 2
    rare = [a + b + c for a in ("ba", "lo", "ti", "re") for b in ("na", "mo", "si", "du") for c in ("ra", "no", "li", "te")]
    asked = {100: "c1 bamoli c2", 101: "c1 timosi c2", 102: "c1 xqzjkv c2", 103: "c1 nqaab\u65e5 c2"}
    docs = spark.createDataFrame([(0, " ".join(common + rare)), (1, " ".join(common))], "doc_id long, text string")
    vocab, net = pseudo_likelihood.fit(docs)
    got = rows_of(pseudo_likelihood.score(spark.createDataFrame(list(asked.items()), "doc_id long, text string"), vocab, net)).set_index("doc_id").log_likelihood
    assert got.nunique() == 4 and min(got[100], got[101]) > max(got[102], got[103])
    letters = pseudo_likelihood.unpacked_spelling(net)
    assert np.allclose(np.exp(letters.astype(float)).reshape(-1, pseudo_likelihood.SIGNS).sum(1), 1, atol=1e-4)
    # by hand: the words differ in their bytes alone, the network sees the same
    by_hand = {}
    for k, text in asked.items():
        word, edge, total = [*text.split()[1].encode(), 256], 256, 0.0
        for j, sign in enumerate(word):
            one, two = word[j - 1] if j else edge, word[j - 2] % 32 if j > 1 else 32
            total += letters[(two * 257 + one) * 257 + sign]
        by_hand[k] = total
    assert all(abs(got[k] - got[100] - by_hand[k] + by_hand[100]) < 1e-3 for k in asked)


def test_pipeline_stages(spark, tmp_path):
    import corpus_pipeline as c

    sf = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    for name, stage in c.STAGES:
        out = stage(spark, docs, sf)
        if name == "packing":
            assert out.select("doc_id").distinct().count() == docs.count()
        else:
            assert out.columns == docs.columns and out.exceptAll(docs).count() == 0
        if name == "near_duplicates":
            rows = docs.toPandas().sort_values("doc_id")
            _, label = components(rows.text.tolist(), 80)
            want = {i for k, i in enumerate(rows.doc_id) if label[k] == k}
            assert {r.doc_id for r in out.select("doc_id").collect()} == want
        out.write.parquet(str(tmp_path / name))
        docs = spark.read.parquet(str(tmp_path / name))
