"""Packing by concatenate and cut, with two-pass prefix sums.

Pass one tokenizes every document once and writes ids, token count and the running offset within its
input partition to the shared folder. The partition totals (one row per partition) are summed into
global bases. Pass two is a map: a document's global offset is base + offset, and each window boundary
inside it cuts a piece. Only the very last window is padded, so padding is below one window in all.

Cases: null text is an empty document and still gets its separator id; a table without rows gives no
pieces; repeated rows are packed each; order is that of the written table (partition, then row), which
stays fixed if executors are lost since pass two reads the committed table.
"""

from __future__ import annotations

import os
import re
import zlib
from array import array

import numpy as np
import pyarrow as pa
import public_tokenizers
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textfactor.llm.common import Scratch

DEFAULT_TOKENIZER = "word_bpe_49k.json"
SEPARATOR = 1
LONGEST_MEMO = 64
PIECE_SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


# Chunks of these symbols alone are cut here as the tokenizer's own pattern cuts them: letters, single digits,
# other symbols in runs. Apostrophes (contractions), "<" (special strings) and all further symbols go to the library whole.
PLAIN = re.compile(r"[!-&(-;=-~\u00c0-\u012f\u0131-\u024f]+")
PARTS = re.compile(r"[^\W\d_]+|[0-9]|(?:[^\w]|_)+")
# The same for a text of such chunks only, which is cut at once: most chunks of a text are new, most of their words are not.
PLAIN_TEXT = re.compile(r"[\x09-\x0d !-&(-;=-~\u00c0-\u012f\u0131-\u024f]*")
TEXT_PARTS = re.compile("[a-z\u00df-\u00f6\u00f8-\u02af\u2c65\u2c66]+|[0-9]|[!-/:-@\\[-`{-~\u00d7\u00f7]+")  # in lower case


def byte_symbols() -> list[str]:
    """The byte-level alphabet: printable Latin-1 bytes stand for themselves, the others follow from 256 on."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(shown)]
    table = {b: chr(b) for b in shown} | {b: chr(256 + k) for k, b in enumerate(rest)}
    return [table[b] for b in range(256)]


class WordIds(dict):
    """Memo from one pre-token (lower case) to its merged ids as bytes."""

    def __init__(self, tokenizer):
        super().__init__()
        self.merge = tokenizer.model.tokenize
        self.symbols = byte_symbols()
        self.code = "H" if tokenizer.get_vocab_size(with_added_tokens=True) <= 1 << 16 else "I"

    def __missing__(self, word: str) -> bytes:
        raw = word if word.isascii() else "".join([self.symbols[b] for b in word.encode()])
        value = array(self.code, [t.id for t in self.merge(raw)]).tobytes()
        if len(word) <= LONGEST_MEMO:  # so entries bound the memo's bytes too
            self[word] = value
        return value


class ChunkIds(dict):
    """Memo from a chunk between ASCII white space to its ids; this tokenizer drops white space, so chunks are independent."""

    def __init__(self, tokenizer_path: str, limit: int = 200_000):
        super().__init__()
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(tokenizer_path)
        self.words, self.limit = WordIds(self.tokenizer), limit
        self.code = self.words.code
        self.width = array(self.code).itemsize

    def __missing__(self, chunk: bytes) -> bytes:
        text = chunk.decode()
        if PLAIN.fullmatch(text):
            value = b"".join(map(self.words.__getitem__, PARTS.findall(text.lower())))
        else:
            value = array(self.code, self.tokenizer.encode(text, add_special_tokens=False).ids).tobytes()
        if len(chunk) <= LONGEST_MEMO:
            self[chunk] = value
        return value

    def ids(self, text: bytes | None) -> bytes:
        whole = text.decode() if text else ""
        if PLAIN_TEXT.fullmatch(whole):
            out = b"".join(map(self.words.__getitem__, TEXT_PARTS.findall(whole.lower())))
        else:
            out = b"".join(map(self.__getitem__, text.split()))
        for memo in (self, self.words):
            if len(memo) > self.limit:
                memo.clear()
        return out


_memos: dict[str, ChunkIds] = {}


def memo_of(tokenizer_path: str) -> ChunkIds:
    """One bounded memo for each worker process, kept from task to task."""
    if tokenizer_path not in _memos:
        _memos[tokenizer_path] = ChunkIds(tokenizer_path)
    return _memos[tokenizer_path]


def tokenized(docs: DataFrame, tokenizer_path: str, id_col: str = "doc_id", text_col: str = "text", separator: int = SEPARATOR) -> DataFrame:
    """(doc_id, ids binary, n_tokens, part, at): `at` counts the tokens before the document in its partition."""
    kept = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("binary").alias("text"), F.spark_partition_id().alias("part"))

    def encode(batches):
        memo, at = memo_of(tokenizer_path), 0
        end = array(memo.code, [separator]).tobytes()
        for whole in batches:
            for low in range(0, whole.num_rows, 1000):
                batch = whole.slice(low, 1000)
                ids = [memo.ids(x.as_py()) + end for x in batch.column("text")]
                n = np.fromiter((len(x) // memo.width for x in ids), np.int64, len(ids))
                before = at + np.cumsum(n) - n
                at += int(n.sum())
                yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(ids, pa.binary()), pa.array(n), batch.column("part"), pa.array(before)], ["doc_id", "ids", "n_tokens", "part", "at"])

    return kept.mapInArrow(encode, "doc_id long, ids binary, n_tokens long, part int, at long")


def pack(docs: DataFrame, tokenizer_path: str, window: int = 2048, id_col: str = "doc_id", text_col: str = "text", separator: int = SEPARATOR) -> DataFrame:
    """Boundary records of the packed stream: one row per piece (see PIECE_SCHEMA), together with piece_ids, the ids themselves."""
    spark = docs.sparkSession
    table = Scratch(spark, "pack").write(tokenized(docs, tokenizer_path, id_col, text_col, separator), "ids")
    totals = sorted(table.groupBy("part").agg(F.sum("n_tokens").alias("n")).collect())  # a row per input partition
    sums = np.cumsum([0] + [r.n for r in totals])
    bases = spark.createDataFrame([(r.part, int(b)) for r, b in zip(totals, sums, strict=False)], "part int, base long")
    # ids were written by one tokenizer: their width follows from the vocabulary
    width = memo_of(tokenizer_path).width

    def cut(batches):
        for batch in batches:
            rows = []
            for doc, ids, at in zip(*(batch.column(c).to_pylist() for c in ("doc_id", "ids", "at")), strict=True):
                ids = np.frombuffer(ids, f"<u{width}").astype("<u4")
                start, n = 0, len(ids)
                while start < n:
                    seq, off = divmod(at + start, window)
                    stop = min(n, start + window - off)
                    piece = ids[start:stop].tobytes()
                    rows.append((doc, start, stop - start, zlib.crc32(piece), n, seq, off, piece))
                    start = stop
            columns = list(zip(*rows, strict=True)) if rows else [[]] * 8
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns[:7]] + [pa.array(columns[7], pa.binary())], [*(x.split()[0] for x in PIECE_SCHEMA.split(", ")), "piece_ids"])

    placed = table.join(F.broadcast(bases), "part").select("doc_id", "ids", (F.col("at") + F.col("base")).alias("at"))
    return placed.mapInArrow(cut, PIECE_SCHEMA + ", piece_ids binary")


def default_tokenizer() -> str:
    return public_tokenizers.path(DEFAULT_TOKENIZER)
