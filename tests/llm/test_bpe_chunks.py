import hashlib
import random

from bitextspark.llm import bpe_chunks, tokens


def plain(texts):
    library = tokens.load(tokens.default_path())
    out = []
    for t in texts:
        ids = library.encode(t or "", add_special_tokens=False).ids
        out.append((len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(library.decode(ids, skip_special_tokens=False).encode()).hexdigest()))
    return out


def odd_texts():
    rng = random.Random(3)
    parts = ["the ", "éa", "é", " ", "\n", "\t", "don't", "it's", "<|endoftext|>", "<|startoftext|>", "<|ENDOFTEXT|>", "###", "12", "x9", " ", " ", "\u0085", "ẞ", "ΣΑΣ", "日本語", "😀", "'ll", "ǅ", "İ", "\x1c", "\x00", "ﬁ", "Å", "a" * 70]
    return [None, "", " ", " ", *("".join(rng.choices(parts, k=rng.randrange(1, 200))) for _ in range(150)), "long " * 30_000, "x" * 5_000]


def test_equals_library(spark):
    texts = odd_texts()
    rows = [(i, t, "b") for i, t in enumerate(texts)] + [(None, "a b", None), (3, "again", "x"), (3, "again", "x")]
    df = spark.createDataFrame(rows, "doc_id long, text string, n_tokens string")
    for mask in (2, 6):
        got = sorted((tuple(r) for r in bpe_chunks.encode_digests(df, mask_bits=mask).collect()), key=str)
        assert got == sorted(((r[0], *x) for r, x in zip(rows, plain([r[1] for r in rows]))), key=str)
    assert bpe_chunks.encode_digests(df.limit(0)).count() == 0


def test_real_outputs_round_trip(spark):
    df = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    got = {r["doc_id"]: r for r in bpe_chunks.encode_documents(df).collect()}
    library = tokens.load(tokens.default_path())
    for r in df.collect():
        ids = library.encode(r["text"] or "", add_special_tokens=False).ids
        assert got[r["doc_id"]]["ids"] == ids and got[r["doc_id"]]["decoded"] == library.decode(ids, skip_special_tokens=False)


def test_chunks_of_shared_passages_are_reused():
    rng = random.Random(1)
    passage = " ".join("".join(rng.choices("abcdefgh", k=6)) for _ in range(400)).encode()
    codec = bpe_chunks.ChunkCodec(tokens.default_path())
    codec.encode([b"first words " + passage])
    made = codec.encoded
    codec.encode([b"something else stands before it here: " + passage + b" and after"])
    assert codec.encoded - made <= 4 and codec.reused > 20


def test_whole_text_where_words_are_not_apart():
    import public_tokenizers

    path = public_tokenizers.path("byte_bpe_50k.json")
    codec = bpe_chunks.ChunkCodec(path)
    library = tokens.load(path)
    text = "Some words, and  more\n words é"
    ids = library.encode(text, add_special_tokens=False).ids
    assert not codec.apart and codec.encode([text.encode()]) == [(len(ids), " ".join(map(str, ids)).encode(), library.decode(ids, skip_special_tokens=False).encode())]


def test_memo_equals_library_word_by_word():
    rng = random.Random(9)
    letters = "abcxyzABCÀÉßöøÿÞ×÷İıſ.,;:!?'0_-#éñ́’"
    words = ["".join(rng.choices(letters, k=rng.randrange(1, 12))) for _ in range(20_000)] + ["ß", "ẞ", "don't", "it's.", "a.", "a..", "É,"]
    library = tokens.load(tokens.default_path())
    memo = tokens.Memo(tokens.default_path(), list)
    assert memo.direct and memo.mark is not None
    known = memo.learn([w.encode() for w in words])
    for w, e in zip(words, library.encode_batch_fast(words, add_special_tokens=False), strict=True):
        assert known[w.encode()] == e.ids, w
