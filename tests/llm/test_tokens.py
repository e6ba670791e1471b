import public_tokenizers
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from structcurve.llm.tokens import TokenLengths, split_safely, token_counts

PATH = public_tokenizers.path("byte_bpe_50k.json")


@pytest.fixture(scope="module")
def plain():
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(PATH)
    return lambda s: len(t.encode(s, add_special_tokens=False).ids)


@settings(max_examples=200, deadline=None)
@given(st.text(alphabet="ab1 \n\t'sé.,<|>endoftx　", max_size=80))
def test_cuts_do_not_change_counts(text):
    model = TokenLengths(PATH, batch_bytes=16, piece_chars=5)
    whole = TokenLengths(PATH)
    assert model.counts([text, text]) == whole.counts([text, text])
    assert "".join(split_safely(text, 5)) == text


def test_against_the_library(spark, plain):
    texts = ["", "Hello  world\n\nagain", "a" * 70_000, "x1" * 40_000, "<|endoftext|> is special", "é" * 100, ("tail ws   \n" * 9000)]
    rows = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    got = {r.doc_id: r for r in token_counts(rows).collect()}
    for i, t in enumerate(texts):
        assert got[i].n_tokens == plain(t) and got[i].n_bytes == len(t.encode()) and got[i].over_limit == (plain(t) > 512)


def test_sentencepiece(spark):
    path = public_tokenizers.path("piece_bpe_32k.model")
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    rows = spark.createDataFrame([(1, "some words to cut")], "doc_id bigint, text string")
    assert token_counts(rows, path).first().n_tokens == len(model.encode("some words to cut"))
