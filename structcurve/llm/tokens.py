"""Token counts with a public tokenizer: only lengths leave the Python workers."""

from __future__ import annotations

import os
import re
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_map, text_of

SCHEMA = "doc_id bigint, n_bytes bigint, n_tokens bigint, over_limit boolean"

#: A text is cut between a character that is no white space and white space that follows it:
#: the byte-level pre-tokenizer never joins the two, and a blank run stays whole on the right side.
_SAFE = re.compile(r"(?<=\S)(?=\s)")
#: Without white space, a change from letter to digit is a boundary of the same pre-tokenizer.
_SAFE_DENSE = re.compile(r"(?<=[^\W\d_])(?=[0-9])")


def split_safely(text: str, piece_chars: int) -> list[str]:
    """Pieces of about ``piece_chars`` whose token counts add up to the whole text's count.

    Cuts fall only at boundaries that the pre-tokenizer makes anyway; where a stretch has none,
    the piece runs on to the next one, however far that is.
    """
    if len(text) <= piece_chars:
        return [text]
    pieces, start = [], 0
    while len(text) - start > piece_chars:
        found = _SAFE.search(text, start + piece_chars) or _SAFE_DENSE.search(text, start + piece_chars)
        if not found:
            break
        pieces.append(text[start : found.start()])
        start = found.start()
    pieces.append(text[start:])
    return pieces


class TokenLengths:
    """Counts of many texts, encoded in batches of about ``batch_bytes``."""

    def __init__(self, path: str, batch_bytes: int = 1 << 20, piece_chars: int = 1 << 16):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        self.kind = "sentencepiece" if path.endswith(".model") else "tokenizers"
        if self.kind == "tokenizers":
            from tokenizers import Tokenizer

            self.model = Tokenizer.from_file(path)
            self.model.no_padding()
            self.model.no_truncation()
        else:
            import sentencepiece

            self.model = sentencepiece.SentencePieceProcessor(model_file=path)
        # cuts are proven safe for the byte-level pre-tokenizer only
        self.piece_chars = piece_chars if self.kind == "tokenizers" and "ByteLevel" in str(self.model.pre_tokenizer) else None
        self.batch_bytes = batch_bytes

    def _lengths(self, pieces: list[str]) -> list[int]:
        if self.kind == "tokenizers":
            return [len(e) for e in self.model.encode_batch_fast(pieces, add_special_tokens=False)]
        return [len(x) for x in self.model.encode(pieces, num_threads=1)]

    def counts(self, texts: list[str]) -> list[int]:
        totals, pieces, owners, size = [0] * len(texts), [], [], 0

        def flush() -> None:
            for owner, n in zip(owners, self._lengths(pieces)):
                totals[owner] += n
            pieces.clear()
            owners.clear()

        for i, text in enumerate(texts):
            for piece in split_safely(text, self.piece_chars) if self.piece_chars else [text]:
                pieces.append(piece)
                owners.append(i)
                size += len(piece)
                if size >= self.batch_bytes:
                    flush()
                    size = 0
        if pieces:
            flush()
        return totals


def token_counts(df: DataFrame, tokenizer: str = "byte_bpe_50k.json", limit: int = 512, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: ``doc_id, n_bytes, n_tokens, over_limit`` (n_tokens > limit).

    ``tokenizer`` is a file path, or the name of a file of the public tokenizer package, opened on
    the executors.  Null and empty texts count 0 bytes and 0 tokens; a null id stays null; repeated
    rows give repeated results; an empty table gives an empty table; other columns are ignored, so
    clashing names do no harm.  Very long texts are cut at safe boundaries, so no call sees more than
    a batch.  The work is a map without shuffle: its balance is that of the scan's byte splits.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        path = tokenizer
        if not os.path.isabs(path):
            import public_tokenizers

            path = public_tokenizers.path(path)
        model = TokenLengths(path)
        for batch in batches:
            text = batch.column(1)
            n = pa.array(model.counts(text.to_pylist()), pa.int64())
            size = pc.cast(pc.binary_length(text), pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0), size, n, pc.greater(n, limit)], ["doc_id", "n_bytes", "n_tokens", "over_limit"])

    return arrow_map(df.select(F.col(id_col).cast("bigint").alias("doc_id"), text_of(text_col).alias("text")), run, SCHEMA)
