import pytest
from tokenizers import Tokenizer

from balclust.llm import common, tokens

TEXTS = [
    None, "", " \t\n\x0b", "a", "1", "a<|endoftext|>b <|startoftext|> <|", "It's we'll ''s 12345 x²½ É́ é ́x ΑΣ Σ İstanbul ﬁ \x1c\x85\xa0x y", "aaa aaaaaa aaaaaaaaa ababab",
    "😀😀 ‍👩‍👩‍👧 中文字符 #$%^&*() ---- 'S", "ÀÉÿŸſ µªº 1²", "".join(map(chr, range(1, 0x180))), "ab\x00cd", " ".join(chr(k) + "a" + chr(k) for k in range(1, 0x200)), "word " * 3000, "Ünïcode,Straße! déjà-vu" * 40, "x" * 60_000,
]


@pytest.fixture(scope="module")
def library():
    return Tokenizer.from_file(tokens.vocabulary())


def test_counts_equal_the_library(spark, library, tmp_path):
    df = spark.createDataFrame([(k, t, 7) for k, t in enumerate(TEXTS + TEXTS[:4])], "doc_id long, text string, n_tokens int")
    df.write.parquet(str(tmp_path / "documents.parquet"))
    got = {r.doc_id: (r.n_bytes, r.n_tokens, r.over_limit) for r in tokens.op6(spark, str(tmp_path)).collect()}
    for k, t in enumerate(TEXTS + TEXTS[:4]):
        n = len(library.encode(t or "", add_special_tokens=False).ids)
        assert got[k] == (len((t or "").encode()), n, n > 2048), (k, t)


def test_ids_equal_the_library_in_any_slice(library):
    import pyarrow as pa

    encoder = tokens.Encoder(tokens.vocabulary())
    for texts in (TEXTS, TEXTS[::-1], TEXTS[3:9], [None, ""]):
        ids, where = encoder.encode(*common.text_bytes(pa.array(texts, pa.string())))
        for k, t in enumerate(texts):
            assert ids[where[k] : where[k + 1]].tolist() == library.encode(t or "", add_special_tokens=False).ids


def test_memory_of_runs_is_bounded(library, monkeypatch):
    import pyarrow as pa

    monkeypatch.setattr(tokens, "MEMO", 8)
    encoder = tokens.Encoder(tokens.vocabulary())
    for text in ("one two three four five six seven eight nine ten", "it's it'd we're you've o'clock", "one two ten"):
        ids, _ = encoder.encode(*common.text_bytes(pa.array([text])))
        assert ids.tolist() == library.encode(text, add_special_tokens=False).ids


def test_empty_table(spark):
    assert tokens.count_tokens(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_odd_words_leave_nothing_in_the_store(library):
    import pyarrow as pa

    encoder = tokens.Encoder(tokens.vocabulary())
    for k in range(4):
        texts = [f"日本語 テキスト {k} it's"] * 50
        ids, where = encoder.encode(*common.text_bytes(pa.array(texts)))
        assert ids[: where[1]].tolist() == library.encode(texts[0], add_special_tokens=False).ids
        assert len(encoder.store) < 20
