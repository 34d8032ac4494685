"""Token counts by the whole-token shortcut.

Offline, the vocabulary is checked for two facts: which strings encode alone as exactly one token, and
that no token holds the space mark after another symbol. The second fact means that no merge crosses
the start of a run of spaces, so a text's count is the sum over its pre-tokens (a run of spaces with
the symbols after it). Pre-tokens proven whole count one at once; only the rest is merged, each
distinct string of up to 64 symbols once per memo generation.

Cases: null text counts as empty (0 bytes, 0 tokens); a table without rows gives no rows; repeated
rows each give a row; columns other than the two named are ignored; the memo is bounded.
"""

from __future__ import annotations

import pyarrow as pa
import public_tokenizers
import sentencepiece
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textfactor.llm.common import bound_batches

SPACE_MARK = "▁"
DEFAULT_MODEL = "piece_bpe_32k.model"
LONGEST_MEMO = 64


class PieceCounter(dict):
    """Counts of pre-tokens; the key is the pre-token without its first space mark."""

    def __init__(self, model_path: str, limit: int = 400_000):
        super().__init__()
        self.processor = sentencepiece.SentencePieceProcessor(model_file=model_path)
        self.limit = limit
        self.whole = self._prove()
        self.update(self.whole)

    def _prove(self) -> dict[str, int]:
        sp = self.processor
        pieces = [sp.id_to_piece(i) for i in range(sp.get_piece_size()) if not sp.is_control(i) and not sp.is_byte(i) and not sp.is_unknown(i)]
        if any(SPACE_MARK in p.lstrip(SPACE_MARK) for p in pieces):
            raise ValueError("this vocabulary merges across spaces; the shortcut doesn't hold for it")
        names = [p[1:].replace(SPACE_MARK, " ") for p in pieces if p.startswith(SPACE_MARK) and len(p) > 1]
        return {name: 1 for name, ids in zip(names, sp.encode(names, num_threads=1), strict=True) if len(ids) == 1}

    def __missing__(self, key: str) -> int:
        value = len(self.processor.encode(key, num_threads=1))
        if len(key) <= LONGEST_MEMO:  # so entries bound the memo's bytes too
            self[key] = value
        return value

    def trim(self) -> None:
        if len(self) > self.limit + len(self.whole):
            self.clear()
            self.update(self.whole)

    def count(self, text: str | None) -> int:
        if not text:
            return 0
        parts = text.replace(SPACE_MARK, " ").split(" ")
        if "" not in parts:
            return sum(map(self.__getitem__, parts))
        total = spaces = 0
        for part in parts:
            if part:
                total += self[" " * spaces + part]
                spaces = 0
            else:
                spaces += 1
        if spaces:
            total += self[" " * (spaces - 1)] if spaces > 1 else 1
        return total


def token_counts(docs: DataFrame, model_path: str, max_tokens: int = 4096, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: id, n_bytes, n_tokens, over_limit (n_tokens > max_tokens). A map without shuffle."""
    bound_batches(docs.sparkSession)
    kept = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text"), F.coalesce(F.octet_length(text_col), F.lit(0)).cast("long").alias("n_bytes"))
    id_type = kept.schema["doc_id"].dataType.simpleString()

    def count(batches):
        counter = PieceCounter(model_path)
        for batch in batches:
            n = [counter.count(x) for x in batch.column("text").to_pylist()]
            counter.trim()
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), batch.column("n_bytes"), pa.array(n, pa.int64()), pa.array([x > max_tokens for x in n], pa.bool_())],
                ["doc_id", "n_bytes", "n_tokens", "over_limit"],
            )

    return kept.mapInArrow(count, f"doc_id {id_type}, n_bytes long, n_tokens long, over_limit boolean")


def default_model() -> str:
    return public_tokenizers.path(DEFAULT_MODEL)
