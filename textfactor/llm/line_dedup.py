"""Line deduplication over levelled sorted runs of line hashes.

The store holds runs of (key hash, owner): every line key seen so far with the id of the document that
owns it. Documents come in batches of ascending id. A batch's keys are merge-joined with the runs: keys found
there belong to an earlier document, the others (the anti-join) get the batch's smallest id as owner and become a new run
of level 0. When a level has `fanout` runs they are merged into one run of the next level, so a
key is rewritten once per level and a batch meets few runs. Only keys that a second document holds are joined back to the lines.

A key is a line stripped of ASCII white space with A-Z lower-cased; keys under `min_chars` code points are never
dropped. Hashes have 128 bits, so that a false match is out of reach at any corpus size.

Cases: null or empty text is one empty line and stays; repeated lines of the owning document all stay; rows that
repeat a document id share their ownership; a null id owns nothing and loses nothing; a table without rows gives no rows;
input columns named n_lines or n_dropped are replaced.
"""

from __future__ import annotations

import hashlib

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from textfactor.llm.common import Scratch

BLANK = b" \t\n\x0b\x0c\r"


def line_key(line: bytes, min_chars: int) -> bytes | None:
    key = line.strip(BLANK).lower()
    if len(key) < min_chars or (len(key) < 4 * min_chars and len(key.decode()) < min_chars):
        return None
    return xxhash.xxh3_128_digest(key)


def document_keys(docs: DataFrame, min_chars: int) -> DataFrame:
    """(doc_id, key): the distinct keys of each document."""

    def explode(batches):
        for whole in batches:
            for low in range(0, whole.num_rows, 2000):
                batch = whole.slice(low, 2000)
                ids, keys = [], []
                for doc, text in zip(batch.column("doc_id").to_pylist(), batch.column("text").to_pylist(), strict=True):
                    found = {line_key(x, min_chars) for x in text.split(b"\n")} - {None} if text else ()
                    keys += found
                    ids += [doc] * len(found)
                yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(keys, pa.binary())], ["doc_id", "key"])

    return docs.where("doc_id is not null").select("doc_id", F.col("text").cast("binary").alias("text")).mapInArrow(explode, "doc_id long, key binary")


class LineRuns:
    """Levels of sorted runs (key, owner), each run a table in the shared folder."""

    def __init__(self, scratch: Scratch, fanout: int = 4):
        self.scratch, self.fanout, self.levels, self.made = scratch, fanout, [[]], 0

    def _write(self, rows: DataFrame) -> DataFrame:
        self.made += 1
        return self.scratch.write(rows.sortWithinPartitions("key"), f"run-{self.made}")

    def owners(self) -> DataFrame | None:
        runs = [run for level in self.levels for run in level]
        out = runs[0] if runs else None
        for run in runs[1:]:  # runs are disjoint: a key enters the store once
            out = out.union(run)
        return out

    def add(self, batch: DataFrame) -> DataFrame:
        """batch: (doc_id, key). Its unseen keys become a run of level 0; returns (key, owner) of its keys that are held by an earlier batch or more than once here."""
        own = batch.groupBy("key").agg(F.min("doc_id").alias("first"), (F.count(F.lit(1)) > 1).alias("many"))
        known = self.owners()
        met = own.withColumn("owner", F.lit(None).cast("long")) if known is None else own.join(known, "key", "left")
        unseen = F.col("owner").isNull()
        table = self._write(met.select("key", F.coalesce("owner", "first").alias("owner"), unseen.alias("unseen"), (~unseen | F.col("many")).alias("hit")))
        self.levels[0].append(table.where("unseen").select("key", "owner"))
        for level in range(len(self.levels)):
            if len(self.levels[level]) >= self.fanout:
                self._compact(level)
        return table.where("hit").select("key", "owner")

    def _compact(self, level: int) -> None:
        merged = self.levels[level][0]
        for run in self.levels[level][1:]:
            merged = merged.union(run)
        if level + 1 == len(self.levels):
            self.levels.append([])
        self.levels[level] = []
        self.levels[level + 1].append(self._write(merged.repartition("key")))


def dedup_lines(docs: DataFrame, batches: int = 3, fanout: int = 2, min_chars: int = 10) -> DataFrame:
    """All columns of docs with text replaced by what is kept, and n_lines, n_dropped. docs needs doc_id and text."""
    scratch = Scratch(docs.sparkSession, "lines")
    keys = scratch.write(document_keys(docs, min_chars), "keys")
    cuts = sorted(set(docs.approxQuantile("doc_id", [i / batches for i in range(1, batches)], 0.01))) if batches > 1 else []
    store, hits = LineRuns(scratch, fanout), None
    for low, high in zip([None, *cuts], [*cuts, None], strict=True):
        inside = F.lit(True) if low is None else F.col("doc_id") > low
        found = store.add(keys.where(inside if high is None else inside & (F.col("doc_id") <= high)))
        hits = found if hits is None else hits.union(found)
    # a key has one owner, however many batches meet it; a hot key's rows are many on the left only, which adaptive execution splits
    lost = keys.join(hits.dropDuplicates(["key"]), "key").where("owner < doc_id")
    drops = lost.groupBy(F.col("doc_id").alias("_drop_id")).agg(F.collect_list("key").alias("_drop_keys"))  # no more than the document's own lines
    added = StructType.fromDDL("n_lines long, n_dropped long")
    names = [c for c in docs.columns if c not in ("n_lines", "n_dropped", "_drop_id", "_drop_keys")]
    out_schema = StructType([docs.schema[c] for c in names] + added.fields)
    joined = docs.select(names).join(drops, F.col("doc_id") == F.col("_drop_id"), "left").drop("_drop_id")
    shaped = joined.withColumn("text", F.col("text").cast("binary"))

    def keep(parts):
        for whole in parts:
            for low in range(0, whole.num_rows, 2000):
                batch = whole.slice(low, 2000)
                texts, n_lines, n_dropped = [], [], []
                for text, dropped in zip(batch.column("text").to_pylist(), batch.column("_drop_keys").to_pylist(), strict=True):
                    n = text.count(b"\n") + 1 if text else 1
                    if dropped:
                        gone = set(dropped)
                        lines = [x for x in text.split(b"\n") if line_key(x, min_chars) not in gone]
                        n_dropped.append(n - len(lines))
                        text = b"\n".join(lines)
                    else:
                        n_dropped.append(0)
                    n_lines.append(n)
                    texts.append(None if text is None else text.decode())
                columns = [pa.array(texts, pa.string()) if c == "text" else batch.column(c) for c in names]
                yield pa.RecordBatch.from_arrays([*columns, pa.array(n_lines, pa.int64()), pa.array(n_dropped, pa.int64())], [*names, "n_lines", "n_dropped"])

    return shaped.mapInArrow(keep, out_schema)


def kept_digest(text: str | None) -> str:
    return hashlib.sha256((text or "").encode()).hexdigest()
