import hashlib
import random

import numpy as np
import pytest

from veil.llm import chunk_bpe as B

tokenizers = pytest.importorskip("tokenizers")


@pytest.fixture(scope="module")
def codec():
    return B.codec(*B.default_paths())


@pytest.fixture(scope="module")
def library():
    return tokenizers.Tokenizer.from_file(B.default_paths()[1])


def texts():
    r = random.Random(5)
    alphabet = ["a", "be", " ", "  ", "\n", "\t", "é", "日本", "　", " ", "'s", "'ll", "12", "!", "<|endoftext|>", "<|endo", "ftext|>", "😀", " ", "ß", "the ", "."]
    for n in (0, 1, 7, 90, 700, 4000):
        for _ in range(6):
            yield "".join(r.choice(alphabet) for _ in range(n))
    yield "x" * 50_000
    yield " " * 30_000
    yield "日本語" * 9_000
    yield "ab cd " * 9_000


def test_stitching_any_pieces_gives_the_library_ids(codec, library):
    r = random.Random(7)
    for t in texts():
        want = library.encode(t, add_special_tokens=False).ids
        data = t.encode()
        cuts = sorted({B._border(np.frombuffer(data, np.uint8), r.randrange(len(data))) for _ in range(min(40, len(data)))}) if data else []
        spans = [data[a:b] for a, b in zip([0, *cuts], [*cuts, len(data)]) if b > a]
        got = codec.stitch([codec.encode(s.decode()) for s in spans])
        assert got.tolist() == want
        chunks = B._split(data)
        assert b"".join(chunks) == data
        assert codec.stitch([codec.encode(c.decode()) for c in chunks]).tolist() == want
        assert codec.decode_bytes(got).decode("utf-8", "replace") == library.decode(want, skip_special_tokens=False)


def test_chunks_follow_content():
    r = random.Random(1)
    body = bytes(r.choice(b"abcdefgh ") for _ in range(60_000))
    a, b = set(B._split(b"q" * 777 + body)), set(B._split(b"other start" * 50 + body))
    assert len(a & b) > 0.8 * len(a)


def test_documents_with_copies_nulls_and_repeats(spark, library):
    r = random.Random(2)
    shared = "".join(r.choice(["hot ", "passage ", "über ", "\n", "日本 "]) for _ in range(3000))
    rows = [(i, f"start {i} {r.random()} " + shared + f" end {i}") for i in range(12)]
    rows += [(3, rows[3][1]), (3, shared), (3, shared), (None, shared), (None, None), (77, None), (78, ""), (79, shared), (79, shared), (80, shared * 3)]
    df = spark.createDataFrame([(d, t, "x") for d, t in rows], "doc_id long, text string, n_tokens string")
    got = sorted(map(tuple, B.encode_documents(df).collect()), key=str)

    def want(doc, text):
        e = library.encode(text or "", add_special_tokens=False)
        ids = np.array(e.ids, "<u4").tobytes()
        back = library.decode(e.ids, skip_special_tokens=False)
        return doc, len(e.ids), hashlib.sha256(ids).hexdigest(), hashlib.sha256(back.encode()).hexdigest()

    assert got == sorted((want(*x) for x in rows), key=str)


def test_empty_table(spark):
    assert B.encode_documents(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_ids_of_a_large_vocabulary_take_four_bytes(codec, monkeypatch):
    wide = object.__new__(B.Codec)
    wide.__dict__.update(codec.__dict__)
    wide.kind = np.uint32
    t = "some words and 日本 " * 500
    pieces = [wide.encode(c.decode()) for c in B._split(t.encode())]
    assert pieces[0].dtype == np.uint32 and wide.stitch(pieces).tolist() == codec.encode(t).tolist()


def test_many_rows_without_an_id(spark, library):
    r = random.Random(8)
    shared = " ".join(r.choice(["hot", "passage", "x"]) + str(r.randrange(50)) for _ in range(900))
    rows = [(None if i % 2 else 7, f"{i} {r.random()} {shared} {i}") for i in range(60)]
    got = sorted(map(str, (x[1:3] for x in B.encode_documents(spark.createDataFrame(rows, "doc_id long, text string")).collect())))
    ids = [library.encode(t, add_special_tokens=False).ids for _, t in rows]
    assert got == sorted(str((len(x), hashlib.sha256(np.array(x, "<u4").tobytes()).hexdigest())) for x in ids)
