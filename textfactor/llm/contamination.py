"""Benchmark decontamination: a BM25 inverted index of the test items, every training passage a query.

Scores are divided by the item's score of itself, so one threshold fits items of all lengths. Document frequencies and the mean length are taken over
all items. The index holds postings (term -> item, impact), items in the order of their length and cut into blocks, and for every term its largest impact
in each block and overall. Terms are numbered by their largest impact. For a batch of passages at a time:
1. pivot: a passage's terms of small impact stay closed while their largest impacts add up to at most a tenth of the threshold; a passage whose terms
   can't reach the threshold at all is left out;
2. the block lists of the other terms are read; a block whose maxima, with what stayed closed, miss the threshold is skipped;
3. postings of the remaining blocks are scored exactly over all terms of the passage: all items at or above the threshold are retrieved.
A retrieved item is confirmed by word n-grams (3 words): enough of its question and enough of its answer have to be in the passage. Without a column
`answer` all sentences but the last are the question (of a single sentence the first half); where a part has fewer than `short_words` words, the
n-grams of the whole item decide instead.

Passages are windows of 2 S words every S words, S the longest item of its group, so that any occurrence is whole in one of them. A group holds items
within a factor of 8 in length. Groups are broadcast together up to `index_bytes`; larger test sets take several passes over the texts.

Cases: null or empty texts have no passage; items without words are never reported; equal items are all reported; repeated rows are each
reported; empty tables give no rows; extra columns are ignored.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textfactor.llm.common import bound_batches, words_of

EDGE = b"!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~"
SENTENCE_END = re.compile(r"(?<=[.!?])\s+")
LONGEST_MEMO = 64
CELLS = 1 << 17  # sums of block maxima held at once
CLOSED = 0.1


def terms_of(text: bytes | None) -> list[bytes]:
    return [t for t in (w.strip(EDGE) for w in words_of(text)) if t]


class Item(NamedTuple):
    id: int | None
    terms: list[bytes]
    question: list[bytes]
    answer: list[bytes]


def read_item(number: int | None, text: str, answer: str | None = None) -> Item:
    if answer is not None:
        q, a = terms_of(text.encode()), terms_of(answer.encode())
        return Item(number, q + a, q, a)
    sentences = [s for s in SENTENCE_END.split(text.strip()) if s]
    terms = terms_of(text.encode())
    if len(sentences) > 1:
        return Item(number, terms, terms_of(" ".join(sentences[:-1]).encode()), terms_of(sentences[-1].encode()))
    half = (len(terms) + 1) // 2
    return Item(number, terms, terms[:half], terms[half:])


def gram_share(part: list, passage_grams: dict[int, set], passage: list) -> float:
    """Share of the part's n-grams (3 words, or all its words if fewer) that the passage holds."""
    n = min(3, len(part))
    if not n:
        return 1.0
    if n not in passage_grams:
        passage_grams[n] = set(zip(*(passage[i:] for i in range(n)), strict=False))
    own = set(zip(*(part[i:] for i in range(n)), strict=False))
    return len(own & passage_grams[n]) / len(own)


class Statistics:
    """Document frequencies and the mean length over all items."""

    def __init__(self, items: list[Item]):
        self.n = len(items)
        self.df = Counter(t for item in items for t in set(item.terms))
        self.mean = sum(len(item.terms) for item in items) / max(1, self.n)

    def impacts(self, item: Item, k1: float, b: float) -> dict[bytes, float]:
        """Each term's share of the item's BM25 score of itself."""
        norm = k1 * (1 - b + b * len(item.terms) / self.mean)
        raw = {t: math.log(1 + (self.n - self.df[t] + 0.5) / (self.df[t] + 0.5)) * tf * (k1 + 1) / (tf + norm) for t, tf in Counter(item.terms).items()}
        whole = sum(raw.values())
        return {t: v / whole for t, v in raw.items()}


class BlockMaxIndex:
    """Postings and block maxima of items, which are given in the order of their length."""

    def __init__(self, items: list[Item], statistics: Statistics, block: int = 4, k1: float = 1.2, b: float = 0.75):
        self.items, self.block = items, block
        self.longest = max((len(item.terms) for item in items), default=1)
        self.n_blocks = -(-len(items) // block)
        impacts = [statistics.impacts(item, k1, b) for item in items]
        largest: dict[bytes, float] = {}
        for own in impacts:
            for t, v in own.items():
                largest[t] = max(v, largest.get(t, 0.0))
        self.vocab = {t: k for k, t in enumerate(sorted(largest, key=lambda t: (largest[t], t)))}
        self.term_max = np.sort(np.array(list(largest.values()), np.float64))
        size = sum(map(len, impacts))
        item = np.repeat(np.arange(len(items)), [len(own) for own in impacts])
        term = np.fromiter((self.vocab[t] for own in impacts for t in own), np.int64, size)
        value = np.fromiter((v for own in impacts for v in own.values()), np.float64, size)
        order = np.lexsort((item, term))
        term, item, value = term[order], item[order], value[order]
        cell = term * max(1, self.n_blocks) + item // block
        first = np.flatnonzero(np.r_[True, cell[1:] != cell[:-1]]) if size else np.empty(0, np.int64)
        self.block_of = (item[first] // block).astype(np.int64)
        self.block_max = np.maximum.reduceat(value, first) if size else value
        self.blocks_from = np.searchsorted(term[first], np.arange(len(self.vocab) + 1))
        # the postings of a block lie together
        order = np.argsort(item // block, kind="stable")
        self.term, self.item, self.value = term[order], item[order], value[order]
        self.block_from = np.searchsorted(self.item // block, np.arange(self.n_blocks + 1))

    def nbytes(self) -> int:
        return sum(x.nbytes for x in (self.term, self.item, self.value, self.block_of, self.block_max, self.blocks_from)) + 64 * len(self.vocab)


def build_indexes(items: list[Item], factor: int = 8, **options) -> list[BlockMaxIndex]:
    """Groups of items within a factor in length, over statistics of all items."""
    items = sorted((item for item in items if item.terms), key=lambda x: (len(x.terms), x.id is None, x.id or 0, x.terms))
    statistics, groups = Statistics(items), []
    for item in items:
        if not groups or len(item.terms) > factor * len(groups[-1][0].terms):
            groups.append([])
        groups[-1].append(item)
    return [BlockMaxIndex(group, statistics, **options) for group in groups]


class TermIds(dict):
    """Memo from a raw word to its term number, -1 for words that no item holds, -2 for bare punctuation."""

    def __init__(self, index: BlockMaxIndex, limit: int = 500_000):
        super().__init__()
        self.vocab, self.limit = index.vocab, limit

    def __missing__(self, word: bytes) -> int:
        bare = word.strip(EDGE)
        value = self.vocab.get(bare, -1) if bare else -2
        if len(word) <= LONGEST_MEMO:
            self[word] = value
        return value


def spread(start: np.ndarray, count: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(owner, place) of the ranges start .. start + count - 1, one after another."""
    owner = np.repeat(np.arange(len(count)), count)
    return owner, np.arange(int(count.sum())) - np.repeat(np.cumsum(count) - count, count) + start[owner]


def candidate_blocks(index: BlockMaxIndex, passage: np.ndarray, term: np.ndarray, low: int, high: int, least: float) -> tuple[np.ndarray, np.ndarray]:
    """(passage, block) for the passages low .. high - 1 that may reach `least`. passage and term are sorted, each pair once."""
    a, b = np.searchsorted(passage, [low, high])
    passage, term, size = passage[a:b] - low, term[a:b], high - low
    if not len(passage):
        return passage, passage
    most = index.term_max[term]
    run = np.cumsum(most)
    first = np.flatnonzero(np.r_[True, passage[1:] != passage[:-1]])
    before = np.repeat(run[first] - most[first], np.diff(np.r_[first, len(passage)]))
    closed = run - before <= CLOSED * least  # terms come in the order of their largest impact
    rest = np.bincount(passage, most * closed, size)
    alive = np.bincount(passage, most, size) >= least - 1e-9
    use = np.flatnonzero(~closed & alive[passage])
    owner, at = spread(index.blocks_from[term[use]], index.blocks_from[term[use] + 1] - index.blocks_from[term[use]])
    sums = np.bincount(passage[use][owner] * index.n_blocks + index.block_of[at], index.block_max[at], size * index.n_blocks).reshape(size, -1)
    found, block = np.nonzero((sums + rest[:, None] >= least - 1e-9) & alive[:, None])
    return found + low, block


def search(index: BlockMaxIndex, memo: TermIds, texts: list[list[bytes]], least: float, least_overlap: float, short_words: int = 8):
    """Yields (text number, item id, score, question share, answer share, item share) per confirmed passage."""
    span, width = index.longest, len(index.vocab)
    ids = [np.fromiter(map(memo.__getitem__, w), np.int64, len(w)) for w in texts]
    ids = [x[x > -2] for x in ids]
    base = np.cumsum([0, *(-(-len(x) // span) + 1 for x in ids)])  # an empty half parts the texts
    keys = [(np.arange(len(x)) // span + base[k])[x >= 0] * width + x[x >= 0] for k, x in enumerate(ids)]
    keys = np.unique(np.concatenate(keys)) if keys else np.empty(0, np.int64)
    if not len(keys):
        return
    passage_of, term = np.divmod(np.unique(np.concatenate((keys, keys[keys >= width] - width))), width)  # half w is in the passages w and w - 1
    has = np.zeros(width, bool)
    step = max(1, CELLS // max(1, index.n_blocks))
    for low in range(0, int(base[-1]), step):
        passages, blocks = candidate_blocks(index, passage_of, term, low, min(int(base[-1]), low + step), least)
        for at in np.flatnonzero(np.r_[True, passages[1:] != passages[:-1]]) if len(passages) else ():
            w = int(passages[at])
            own = term[slice(*np.searchsorted(passage_of, [w, w + 1]))]
            has[own] = True
            mine = blocks[at : np.searchsorted(passages, w, "right")]
            _, posting = spread(index.block_from[mine], index.block_from[mine + 1] - index.block_from[mine])
            posting = posting[has[index.term[posting]]]
            has[own] = False
            hit, back = np.unique(index.item[posting], return_inverse=True)
            scores = np.bincount(back, index.value[posting], len(hit))
            hits = np.flatnonzero(scores >= least)
            if not len(hits):
                continue
            k = int(np.searchsorted(base, w, "right")) - 1
            passage = [t for t in (x.strip(EDGE) for x in texts[k]) if t][(w - base[k]) * span : (w - base[k] + 2) * span]
            grams: dict[int, set] = {}
            for h in hits.tolist():
                item = index.items[hit[h]]
                q, a, whole = (gram_share(part, grams, passage) for part in (item.question, item.answer, item.terms))
                if confirmed(item, q, a, whole, least_overlap, short_words):
                    yield k, item.id, float(scores[h]), q, a, whole


def confirmed(item: Item, question: float, answer: float, whole: float, least_overlap: float, short_words: int) -> bool:
    if min(len(item.question), len(item.answer)) < short_words:
        return whole >= least_overlap
    return question >= least_overlap and answer >= least_overlap


LEAK = "doc_id long, item_id long, n_passages long, score double, question_overlap double, answer_overlap double, item_overlap double"


def find_leaks(docs: DataFrame, benchmark: DataFrame, least: float = 0.5, least_overlap: float = 0.5, short_words: int = 8, index_bytes: int = 128 << 20, **options) -> DataFrame:
    """LEAK rows: one per document and confirmed item; the best passage's figures. The test set is read to the driver."""
    spark = docs.sparkSession
    bound_batches(spark)
    answer = F.col("answer") if "answer" in benchmark.columns else F.lit(None).cast("string")
    rows = benchmark.where("text is not null").select(F.col("item_id").cast("long").alias("item_id"), "text", answer.alias("answer"))
    groups: list[list[BlockMaxIndex]] = [[]]
    for index in build_indexes([read_item(*r) for r in rows.toLocalIterator()], **options):
        if groups[-1] and sum(x.nbytes() for x in groups[-1]) + index.nbytes() > index_bytes:
            groups.append([])
        groups[-1].append(index)
    kept = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("binary").alias("text"))
    names = [c.split()[0] for c in LEAK.split(", ")]

    def looking_up(sent):
        def look(batches):
            memos = [TermIds(index) for index in sent.value]
            for whole in batches:
                for low in range(0, whole.num_rows, 500):
                    batch = whole.slice(low, 500)
                    doc = batch.column("doc_id").to_pylist()
                    texts = [words_of(x) for x in batch.column("text").to_pylist()]
                    best: dict[tuple, list] = {}
                    for index, memo in zip(sent.value, memos, strict=True):
                        for k, item, *figures in search(index, memo, texts, least, least_overlap, short_words):
                            row = best.setdefault((k, item), [0, 0.0, 0.0, 0.0, 0.0])
                            row[0] += 1
                            row[1:] = max(row[1:], figures)
                        if len(memo) > memo.limit:
                            memo.clear()
                    rows = [(doc[k], item, *v) for (k, item), v in best.items()]
                    columns = list(zip(*rows, strict=True)) if rows else [[]] * 7
                    kinds = [pa.int64()] * 3 + [pa.float64()] * 4
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, kinds, strict=True)], names)

        return look

    out = None
    for group in groups:
        part = kept.mapInArrow(looking_up(spark.sparkContext.broadcast(group)), LEAK)
        out = part if out is None else out.unionByName(part)
    return out


def decontaminate(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """docs without the documents that hold a confirmed item."""
    leaked = find_leaks(docs, benchmark, **options).select("doc_id").distinct()
    return docs.join(leaked, "doc_id", "left_anti").select(docs.columns)
