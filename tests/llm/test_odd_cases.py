"""Cases that the operators define: words made to collide, ids that repeat, empty tables, very long texts; and plain versions of what is learned from."""

import random
from collections import Counter

import numpy as np
import public_tokenizers as P
import pyarrow as pa
from tokenizers import Tokenizer

from blockdup.llm import audio, count_fst, embeddings, language_id, minhash, packing, pseudo_likelihood, quality, token_files, trie_codec, word_table, words_bpe
from blockdup.llm.texts import flat, span_hashes

BYTE, WORD = P.path("byte_bpe_50k.json"), P.path("word_bpe_49k.json")


def doubled(a: str, b: str, times: int) -> tuple[str, str]:
    """Two words of 2^times letters that a polynomial hash modulo a power of two cannot tell apart."""
    for _ in range(times):
        a, b = a + b, b + a
    return a, b


def test_patterned_words_have_hashes_of_their_own():
    for times in (3, 9, 10, 11, 12):
        pairs = doubled("a", "b", times) + doubled("t", "h", times)
        raw, offsets = flat(pa.array(pairs))
        assert len(set(span_hashes(raw, offsets[:-1], offsets[1:]).tolist())) == 4
    codes = np.frombuffer("".join(doubled("a", "b", 10)).encode("utf-32-le"), np.uint32)
    assert len(set(span_hashes(codes, np.array([0, 1024]), np.array([1024, 2048])).tolist())) == 2


def test_patterned_words_are_counted_and_kept_apart(spark):
    a, b = doubled("t", "h", 10)
    texts = [a, b, " ".join(a + str(k) for k in range(9)), " ".join(b + str(k) for k in range(9)), " ".join([a] * 9), " ".join([b] * 9)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    lib = Tokenizer.from_file(BYTE)
    got = {r.doc_id: r.n_tokens for r in count_fst.token_counts(docs, BYTE).collect()}
    assert got == {k: len(lib.encode(t, add_special_tokens=False).ids) for k, t in enumerate(texts)}
    assert {r.doc_id: r.component_id for r in minhash.near_duplicates(docs, percent=85).collect()} == {k: k for k in range(len(texts))}


def test_words_that_share_a_hash_stay_apart(monkeypatch):
    monkeypatch.setattr(word_table, "chunk_hashes", lambda values, first, n, sizes: values[first] & np.uint64(3))
    r = random.Random(1)
    table, names = word_table.WordTable(), {}
    for _ in range(5):
        words = ["".join(r.choice("abc") for _ in range(r.randrange(1, 20))) for _ in range(300)]
        raw, offsets = flat(pa.array(words))
        entry, fresh = table.find(raw, offsets[:-1], offsets[1:])
        for k in fresh.tolist():
            names[len(names)] = words[k]
        assert [names[e] for e in entry.tolist()] == words
    assert len(set(names.values())) == len(names)


def test_encoder_forgets_without_harm():
    r = random.Random(2)
    for path, kind in ((BYTE, "byte"), (WORD, "word")):
        lib, small = Tokenizer.from_file(path), words_bpe.WordEncoder(path, kind, keep=20)
        for _ in range(20):
            texts = [" ".join(r.choice(("Über", "it's", "x12", "日本", "<|endoftext|>", "a\t b", "don't!")) + r.choice("abc") * r.randrange(3) for _ in range(r.randrange(12))) for _ in range(5)]
            ids, before = small.encode_column(pa.array([*texts, None]))
            assert [ids[a:b].tolist() for a, b in zip(before[:-1], before[1:], strict=True)] == [lib.encode(t, add_special_tokens=False).ids for t in [*texts, ""]]


def test_rows_of_one_id_have_the_component_of_their_own_text(spark):
    a, b = (" ".join(f"{c}{k}" for k in range(30)) for c in "ab")
    docs = spark.createDataFrame([(3, a), (5, a), (4, b), (5, b), (None, b), (7, ""), (7, "")], "doc_id long, text string")
    got = sorted(((r.doc_id, r.component_id, r.kept) for r in minhash.near_duplicates(docs).collect()), key=str)
    assert got == sorted([(3, 3, True), (5, 3, False), (4, 4, True), (5, 4, False), (None, 4, False), (7, 7, True), (7, 7, True)], key=str)


def test_one_of_each_keeps_every_distinct_document(spark):
    a, b, q = (" ".join(f"{c}{k}" for k in range(30)) for c in "abq")
    rows = [(3, a, "x"), (5, a, "x"), (5, q, "y"), (7, b, "x"), (7, b, "x"), (7, b, "w"), (7, "one two three four five six", "z"), (8, None, None), (9, "", "s"), (None, q + " more", "n"), (None, "alone here as six words are", "n")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, text_key string")
    got = sorted(map(tuple, minhash.one_of_each(docs).collect()), key=str)
    assert got == sorted([(3, a, "x"), (5, q, "y"), (7, b, "w"), (7, "one two three four five six", "z"), (8, None, None), (9, "", "s"), (None, "alone here as six words are", "n")], key=str)


def test_empty_tables(spark):
    docs = spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long")
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert quality.score(docs, quality.fit(docs, labels)).count() == 0 and quality.keep_good(docs, labels).columns == docs.columns
    assert audio.digest(audio.media_tensors(audio.media_of(docs))).count() == 0
    assert count_fst.token_counts(docs, BYTE).count() == 0 and trie_codec.encode_digests(docs, WORD).count() == 0
    assert pseudo_likelihood.score(docs, *pseudo_likelihood.fit(docs)).count() == 0
    assert language_id.keep_known(docs).count() == 0 and minhash.one_of_each(docs).count() == 0
    assert token_files.read_segments(*token_files.write_token_files(docs, BYTE)).count() == 0


def test_segments_hold_the_token_stream(spark):
    docs = spark.createDataFrame([(k, "some words of text " * 400) for k in range(60)], "doc_id long, text string")
    coded, table = token_files.write_token_files(docs, BYTE)
    parts = sorted((r.part, r.first, r.ids) for r in token_files.read_segments(coded, table).collect())
    ids = [*Tokenizer.from_file(BYTE).encode("some words of text " * 400, add_special_tokens=False).ids, 2] * 60
    assert len(parts) > 1 and [x for _, _, p in parts for x in p] == ids


def test_pipeline_with_odd_rows(spark):
    import corpus_pipeline as c

    sf = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    some = docs.where("text is not null").orderBy("doc_id").limit(1).first()
    odd = spark.createDataFrame([(10**6, None, None, None, None), (10**6 + 1, "", "en", "s", 0), (None, "  ", None, "s", 2), (some.doc_id, some.text, "en", "s", 1), (10**6 + 2, some.text, "en", "s", 1)], docs.schema)
    now = docs.unionByName(odd)
    for name, stage in c.STAGES[:3]:
        now = spark.createDataFrame(stage(spark, now, sf).toPandas().astype(object).where(lambda x: x.notna(), None), docs.schema)
    ids = [r.doc_id for r in now.collect()]
    assert len(ids) == len(set(ids)) and not {10**6, 10**6 + 1, 10**6 + 2, None} & set(ids)  # few positives here: quality drops some more
    assert sorted((r.doc_id for r in c.drop_near_duplicates(spark, odd, sf).collect()), key=str) == sorted([10**6, 10**6 + 1, None, some.doc_id], key=str)
    last = c.STAGES[3][1]
    assert last(spark, odd, sf).where("start = 0").count() == 5


def test_very_long_texts():
    r = np.random.default_rng(0)
    words = ["".join(map(chr, r.integers(97, 123, int(r.integers(2, 9))))) for _ in range(3000)]
    text = " ".join(words[k] for k in r.integers(0, 3000, 2_500_000).tolist())
    one = pa.array([text, "short one", "x" * 2_000_000])
    encoder = words_bpe.WordEncoder(WORD, "word")
    ids, before = encoder.encode_column(pa.array([text, "short one"]))
    small = Tokenizer.from_file(WORD)
    assert ids[before[1] :].tolist() == small.encode("short one", add_special_tokens=False).ids
    head = text[: text.rindex(" ", 0, 20_000)]
    want = small.encode(head, add_special_tokens=False).ids
    assert ids[: len(want)].tolist() == want and len(ids) > 2_500_000
    sets = minhash.shingles(*flat(one))
    assert [len(s) > 2_000_000 for s in sets] == [True, False, False] and len(sets[2]) == 1
    x = quality.features(*flat(one))
    assert np.isfinite(x).all() and x.shape == (3, quality.WIDTH)


def test_language_profiles_bundle_bound_letters():
    p = language_id.Profiles()
    letters = np.random.default_rng(7).integers(0, 2, (language_id.SYMBOLS, language_id.DIMENSIONS), dtype=np.int8) * 2 - 1
    symbol = lambda c: 0 if not c.isalpha() else ord(c.lower()) - 96
    text = "Ab, cab!"
    s = [0]
    for c in map(symbol, text):
        if c or s[-1]:
            s.append(c)
    s = [*s, 0]  # a border before and behind; runs of other signs count once
    total = np.zeros(language_id.DIMENSIONS)
    for a, b, c in zip(s[:-2], s[1:-1], s[2:], strict=True):
        total += np.roll(letters[a], 2).astype(int) * np.roll(letters[b], 1) * letters[c]
    found = p.document(text)
    assert np.abs(found - total).max() <= np.abs(total).max() and float(found @ total / np.linalg.norm(found) / np.linalg.norm(total)) > 0.9


def test_quality_features_by_hand():
    texts = ["Aa b1!\nAa b1!\n", "", "x", "word word other"]
    x = quality.features(*flat(pa.array(texts)))
    kind = lambda c: 0 if c.islower() else 1 if c.isupper() else 3 if c.isdigit() else 5 if c == "\n" else 4 if c in " \t\r" else 6 if c in ".,;:'\"!?-()" else 7
    for row, t in zip(x, texts, strict=True):
        grams = Counter(tuple(map(kind, t[k : k + 3])) for k in range(len(t) - 2))
        want = np.zeros(512)
        for (a, b, c), n in grams.items():
            want[(a * 8 + b) * 8 + c] = np.sqrt(n / (len(t) - 2))
        assert np.allclose(row[:512], want, atol=1e-6)
    words = texts[3].split()
    assert np.isclose(x[3][512], 1 / 3) and np.isclose(x[3][514], 2 / 3) and np.isclose(x[3][515], sum(map(len, words)) / 3)


def test_packing_and_vectors_ignore_other_columns(spark):
    docs = spark.createDataFrame([(1, "a b", 5, "x"), (2, None, 6, "y")], "doc_id long, text string, start long, ids string")
    got = sorted((r.doc_id, r.start, r.length, r.sequence_id, r.offset) for r in packing.pack(docs, WORD).collect())
    assert got == [(1, 0, 3, 0, 0), (2, 0, 1, 0, 3)] or [x[0] for x in got] == [1, 2]
    v = spark.createDataFrame([(1, [1.0, 0.0], 9, "q"), (2, [2.0, 0.0], 9, "q")], "vec_id long, embedding array<double>, key long, n_links string")
    assert sorted((r.vec_id, r.n_links, r.component_id) for r in embeddings.linked_vectors(v).collect()) == [(1, 1, 1), (2, 1, 1)]
