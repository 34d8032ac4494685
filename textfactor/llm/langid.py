"""Language identification by compression.

For each language a raw-content zstandard dictionary is made of sampled training texts; a text is compressed
whole with every dictionary and the smallest result names its language. `margin` is the gain in bytes of the best
over the second, `score` its share of the second's size. A text is rejected if it has no letter, if the margin is under a byte, or if the score is under
`least_score`. That cut is calibrated on sampled training texts that are in no dictionary: half of the smallest score in a thousand among those
classified right, but never over 0.002, so that clean documents pass.

The sample is bounded: per language at most `sample_docs` whole texts of at most `sample_chars` characters, those with the smallest hash of their id
(texts of 200 to 4,000 characters first), up to `dictionary_bytes` and a third more for the calibration; everything else covers all rows. Ties go to the
language with more sampled bytes, then by name.

Cases: null, empty or letterless text gives `und`, score 0; a training table without labelled text gives `und` for all; rows with a null
language never train; extra columns pass through `classify` untouched, but for those named like a result column, which are replaced.
"""

from __future__ import annotations

from typing import NamedTuple

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from textfactor.llm.common import bound_batches, hash_sample

UND = "und"


class Model(NamedTuple):
    dictionaries: dict[str, bytes]
    least_score: float = 0.0


def train(labelled: DataFrame, sample_docs: int = 600, dictionary_bytes: int = 400_000, sample_chars: int = 1_000_000) -> Model:
    """labelled: (doc_id, text, lang). One raw-content dictionary per language, the most typical texts last since near offsets are cheapest."""
    usable = labelled.where(F.col("lang").isNotNull() & (F.length("text") <= sample_chars) & F.col("text").rlike("\\p{L}"))
    odd = F.when(F.length("text").between(200, 4000), "0").otherwise("1")
    rows = hash_sample(usable.select("doc_id", "lang", "text", odd.alias("odd"), F.concat(odd, "lang").alias("kind")), sample_docs, by="kind")
    order = Window.partitionBy("lang").orderBy("odd", "h", "doc_id")
    before = F.coalesce(F.sum(F.octet_length("text")).over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    rows = rows.withColumn("nth", F.row_number().over(order)).withColumn("before", before).where((F.col("nth") <= sample_docs) & (F.col("before") < dictionary_bytes * 4 // 3))
    found: dict[str, list[tuple]] = {}
    for r in rows.select("lang", "nth", "text").collect():
        found.setdefault(r.lang, []).append((r.nth, r.text))
    texts = {lang: [t for _, t in sorted(some)] for lang, some in found.items()}
    used = {lang: [t for k, t in enumerate(some) if k % 4 != 3] for lang, some in texts.items()}
    model = Model({lang: b"\n".join(t.lower().encode() for t in reversed(some))[-dictionary_bytes:] for lang, some in used.items()})
    judge = CompressionClassifier(model)
    right = sorted(score for lang, some in texts.items() for t in some[3::4] for best, _, score in [judge.classify(t)] if best == lang)
    return model._replace(least_score=min(0.002, right[len(right) // 1000] / 2) if right else 0.0)


class CompressionClassifier:
    """Lower-cased texts; while the margin is under `close` bytes, the sizes of the next of the `finer` levels are added."""

    def __init__(self, model: Model, level: int = 6, finer: tuple[int, ...] = (13, 9, 3), close: int = 4):
        dictionaries, self.least_score = model
        self.close, self.langs = close, sorted(dictionaries, key=lambda x: (-len(dictionaries[x]), x))
        self.coders = [[self._coder(dictionaries[lang], k) for lang in self.langs] for k in (level, *finer)]

    @staticmethod
    def _coder(raw: bytes, level: int):
        data = zstandard.ZstdCompressionDict(raw, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
        data.precompute_compress(level=level)
        return zstandard.ZstdCompressor(level=level, dict_data=data, write_content_size=False, write_dict_id=False, write_checksum=False).compress

    def classify(self, text: str | None) -> tuple[str, int, float]:
        """(language, margin in bytes, relative margin 0..1)"""
        if not self.langs or not text or not any(map(str.isalpha, text)):
            return UND, 0, 0.0
        raw = text.lower().encode()
        sizes = [len(compress(raw)) for compress in self.coders[0]]
        best, margin = self._best(sizes)
        for coders in self.coders[1:]:
            if margin >= self.close:
                break
            sizes = [s + len(compress(raw)) for s, compress in zip(sizes, coders, strict=True)]
            best, margin = self._best(sizes)
        return self.langs[best], margin, margin / max(1, sizes[best] + margin)

    def accepts(self, lang: str, margin: int, score: float) -> bool:
        return lang != UND and margin >= 1 and score >= self.least_score

    @staticmethod
    def _best(sizes: list[int]) -> tuple[int, int]:
        low, k = min((s, k) for k, s in enumerate(sizes))
        return k, min((s for j, s in enumerate(sizes) if j != k), default=2 * low) - low


def classify(docs: DataFrame, model: Model) -> DataFrame:
    """docs with lang_pred, margin, score, accepted added; only text is looked at. A map without shuffle."""
    bound_batches(docs.sparkSession)
    added = StructType.fromDDL("lang_pred string, margin long, score double, accepted boolean")
    names = [c for c in docs.columns if c not in added.names]
    sent = docs.sparkSession.sparkContext.broadcast(model)  # languages * dictionary_bytes
    schema = StructType([docs.schema[c] for c in names] + added.fields)

    def predict(batches):
        judge = CompressionClassifier(sent.value)
        for batch in batches:
            found = [judge.classify(x) for x in batch.column("text").to_pylist()]
            lang, margin, score = zip(*found, strict=True) if found else ((), (), ())
            extra = [pa.array(lang, pa.string()), pa.array(margin, pa.int64()), pa.array(score, pa.float64()), pa.array([judge.accepts(*f) for f in found], pa.bool_())]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in names), *extra], [*names, "lang_pred", "margin", "score", "accepted"])

    return docs.mapInArrow(predict, schema)


def in_training(doc_id="doc_id"):
    """The fixed split: crc32 of the id as text, modulo 3, is not 1."""
    return F.crc32(F.col(doc_id).cast("string")) % 3 != 1
