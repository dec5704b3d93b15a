import base64
import hashlib
import random

import public_tokenizers
import pytest
import tiktoken

from graphloop.llm import byte_bpe

PATH = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")
ODD = ["", " ", "\n", "  \n x", "it's we're I'll 's  's\n's 'self ''s x''s", "a b　 c  ", "tab\t\tend\t", "12 345x6", "'" * 9 + "t", "…¡ñ é́",
       "\U0001f600\U0001f600 x", "x" * 3000, "\x1c\x1d \x85y", " 'll", "\n'll", "a'b'c'd'e're", "ab \n\n  cd   "]


@pytest.fixture(scope="module")
def reference():
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(PATH, "rb"))}
    return tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})


def test_equals_the_public_library(reference, monkeypatch):
    monkeypatch.setattr(byte_bpe, "CHUNK_CHARS", 2000)
    rng = random.Random(3)
    alphabet = "ab étd 1２'\n\t  !?sremvl  漢ß\U0001f680"
    texts = ODD + ["".join(rng.choice(alphabet) for _ in range(rng.randrange(400))) for _ in range(300)]
    encoder = byte_bpe.Encoder(byte_bpe.Vocabulary.load(PATH))
    got = []
    for ids, counts in encoder.encode(texts):
        at = 0
        for n in counts:
            got.append(ids[at : at + n].tolist())
            at += n
    assert len(got) == len(texts)
    for text, ids in zip(texts, got, strict=True):
        assert ids == reference.encode_ordinary(text), repr(text)
        assert encoder.vocabulary.decode(ids).tobytes() == text.encode()


def test_operator_rows_offsets_and_nulls(spark, reference):
    rows = [(i, t, "keep") for i, t in enumerate(ODD)] + [(99, None, None), (99, None, None)]
    df = spark.createDataFrame(rows, "doc_id long, text string, offsets string")
    out = byte_bpe.decode_ids(byte_bpe.encode_texts(df, PATH), PATH).collect()
    assert len(out) == len(rows)
    for row in out:
        text = row.text or ""
        assert row.ids == reference.encode_ordinary(text)
        assert bytes(row.decoded) == text.encode()
        pieces = [reference.decode_single_token_bytes(i) for i in row.ids]
        assert row.offsets == [sum(map(len, pieces[:k])) for k in range(len(pieces))]
    digest = byte_bpe.digest(df.drop("offsets"), PATH).where("doc_id = 4").first()
    ids = reference.encode_ordinary(ODD[4])
    assert digest.n_tokens == len(ids)
    assert digest.ids_sha256 == hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest()
    assert digest.decoded_sha256 == hashlib.sha256(ODD[4].encode()).hexdigest()


def test_empty_table(spark):
    df = spark.createDataFrame([], "doc_id long, text string")
    assert byte_bpe.digest(df, PATH).count() == 0


def test_long_texts_are_cut_without_a_trace(monkeypatch):
    import random

    rng = random.Random(8)
    pieces = ["word", "  ", " ", "\n", "\n\n", "don't", "12", "é漢", "\U0001f600", "\u2003", "'re", "...", " x"]
    vocabulary = byte_bpe.Vocabulary.load(public_tokenizers.path("byte_bpe_multi_50k.tiktoken"))
    texts = ["".join(rng.choice(pieces) for _ in range(400)) for _ in range(30)] + ["a" * 900, " " * 900, ""]
    whole = [[int(i) for i in ids] for t in texts for ids, _ in byte_bpe.Encoder(vocabulary).encode([t])]
    monkeypatch.setattr(byte_bpe, "CHUNK_CHARS", 50)
    assert [[int(i) for i in ids] for t in texts for ids, _ in byte_bpe.Encoder(vocabulary).encode([t])] == whole
    assert all("".join(byte_bpe.stretches(t, 50)) == t for t in texts)


def test_slices_of_one_hash_are_told_apart(monkeypatch):
    vocabulary = byte_bpe.Vocabulary.load(public_tokenizers.path("byte_bpe_multi_50k.tiktoken"))
    text = "alpha beta gamma alpha delta"
    expected = [int(i) for ids, _ in byte_bpe.Encoder(vocabulary).encode([text]) for i in ids]
    monkeypatch.setattr(byte_bpe, "mix", lambda x: x & byte_bpe.np.uint64(1))
    assert [int(i) for ids, _ in byte_bpe.Encoder(vocabulary).encode([text]) for i in ids] == expected
