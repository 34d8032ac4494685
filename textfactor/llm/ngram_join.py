"""N-gram Jaccard join with rare-first prefix filtering.

1. One pass over the texts gives each document's set size and fingerprint, and a fixed-size sketch of how many documents hold
   each shingle hash bucket. Documents with equal sets form a class, named by the fingerprint; classes are joined from here on.
2. A total order (sketch count, hash) puts rare shingles first. Two sets with Jaccard >= t share a shingle among the first
   n - ceil(t n) + 1 of both. A second pass emits those prefixes as blobs by shard; a shard keeps the rows that have a partner: another class with the same
   token whose length, and what follows the token on both sides, allow the overlap. At its first common token a similar pair passes, so no
   link is lost, and passages that unlike documents share fall out before anything else is shuffled. Tokens that the sketch shows as very frequent
   are dealt by class, so that no shard holds a hot token.
3. Candidates: per token every class meets one hub class, the one whose shingles are the most frequent (the centre of a group of near
   copies), then the most central class outside the first hub's component; verified links merge components, and the last round takes all
   pairs that are still in different components, by bands of length and, for tokens of many classes, in salted blocks. So a group of thousands of
   near copies costs a multiple of its size, and no pair that could join two components is left out. Length, positional and
   suffix (counts over hash ranges) filters come before the sets are fetched, and each pair is verified once.
4. Components by alternating large-star and small-star steps on tables.
5. The rounds link every component but leave out pairs inside it. Both ends of any link are in one component, so all links are found by comparing
   all classes of each component: small components whole, large ones in pairs of blocks, each block pair by products of its incidence matrix.

Shingles and sets are compared by 64-bit hashes. Cases: null or empty texts have no shingle and link with nothing; a text with fewer words than
the shingle size has one shingle; repeated rows are in one class; a row with a null id takes part only through equal rows that have one;
a table without rows gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from textfactor.llm.common import Scratch, bounded_broadcast, mix64, release, word_keys

SKETCH_BITS = 20
SKETCH_BLOCKS = 16
PARTS = 16
# fixed values: odd multipliers that combine the words of a shingle
MULTIPLIERS = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F, 0xE7037ED1A0B428DB, 0x8EBC6AF09C88C6E3, 0x589965CC75374CC3], np.uint64)


def shingle_sets(texts: list[bytes | None], size: int) -> list[np.ndarray]:
    """Sorted distinct 64-bit shingle hashes of every text."""
    keys, at = word_keys(texts)
    with np.errstate(over="ignore"):
        wide = np.zeros(max(0, len(keys) - size + 1), np.uint64)
        for i in range(size):
            wide += keys[i : i + len(wide)] * MULTIPLIERS[i]
        wide = mix64(wide + np.uint64(size))
        out = []
        for low, high in zip(at[:-1].tolist(), at[1:].tolist(), strict=True):
            n = high - low
            if n >= size:
                s = np.sort(wide[low : high - size + 1])
                out.append(s[np.r_[True, s[1:] != s[:-1]]])
            elif n:
                out.append(mix64((keys[low:high] * MULTIPLIERS[:n]).sum(keepdims=True) + np.uint64(n)))
            else:
                out.append(np.empty(0, np.uint64))
    return out


def needed_overlap(na, nb, percent):
    """Least intersection with 100 * i >= percent * (na + nb - i)."""
    return -((-percent * (na + nb)) // (100 + percent))


def prefix_length(n: int, percent: int) -> int:
    return n - -(-percent * n // 100) + 1


def bucket_of(h: np.ndarray) -> np.ndarray:
    return (h >> np.uint64(64 - SKETCH_BITS)).astype(np.int64)


def _texts(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("binary").alias("text"))


def _slices(batches, rows=1000):
    for whole in batches:
        for low in range(0, whole.num_rows, rows):
            yield whole.slice(low, rows)


def profile(docs: DataFrame, size: int) -> DataFrame:
    """Rows (doc_id, n, sig, parts) of documents, and rows (block, counts) of each partition's share of the sketch."""

    def run(batches):
        sketch, used = np.zeros(1 << SKETCH_BITS, np.uint32), False
        for batch in _slices(batches):
            ids, n, sig, parts = batch.column("doc_id"), [], [], []
            for s in shingle_sets(batch.column("text").to_pylist(), size):
                n.append(len(s))
                sig.append(fingerprint(s))
                parts.append(np.bincount((s >> np.uint64(60)).astype(np.int64), minlength=PARTS).astype(np.int32).tolist())
                if len(s):
                    b = bucket_of(s)  # sorted, since s is
                    first = np.flatnonzero(np.r_[True, b[1:] != b[:-1]])
                    sketch[b[first]] += np.diff(np.r_[first, len(b)]).astype(np.uint32)
                    used = True
            nothing = pa.nulls(len(n))
            yield pa.RecordBatch.from_arrays([ids, pa.array(n, pa.int32()), pa.array(sig, pa.int64()), pa.array(parts, pa.list_(pa.int32())), nothing.cast(pa.int32()), nothing.cast(pa.binary())], ["doc_id", "n", "sig", "parts", "block", "counts"])
        if used:
            blocks = sketch.reshape(SKETCH_BLOCKS, -1)
            empty = pa.nulls(SKETCH_BLOCKS)
            yield pa.RecordBatch.from_arrays([empty.cast(pa.int64()), empty.cast(pa.int32()), empty.cast(pa.int64()), empty.cast(pa.list_(pa.int32())), pa.array(range(SKETCH_BLOCKS), pa.int32()), pa.array([x.tobytes() for x in blocks], pa.binary())], ["doc_id", "n", "sig", "parts", "block", "counts"])

    return _texts(docs).mapInArrow(run, "doc_id long, n int, sig long, parts array<int>, block int, counts binary")


def read_sketch(rows: DataFrame) -> np.ndarray:
    """Adds up the partitions' shares block by block; the result has a fixed size of 4 bytes * 2^SKETCH_BITS."""

    def add(batches):
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            for block, counts in zip(batch.column("block").to_pylist(), batch.column("counts").to_pylist(), strict=True):
                c = np.frombuffer(counts, np.uint32).astype(np.uint64)
                sums[block] = sums[block] + c if block in sums else c
        yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int32()), pa.array([np.minimum(x, 2**32 - 1).astype(np.uint32).tobytes() for x in sums.values()], pa.binary())], ["block", "counts"])

    shares = rows.where("block is not null").select("block", "counts").repartition(SKETCH_BLOCKS, "block")
    out = np.zeros((SKETCH_BLOCKS, (1 << SKETCH_BITS) // SKETCH_BLOCKS), np.uint32)
    for r in shares.mapInArrow(add, "block int, counts binary").collect():
        out[r.block] = np.frombuffer(bytes(r.counts), np.uint32)
    return out.reshape(-1)


def fingerprint(s: np.ndarray) -> int:
    return int(np.uint64(xxhash.xxh3_64_intdigest(s)).astype(np.int64)) if len(s) else 0


def partnered(token: np.ndarray, n: np.ndarray, rest: np.ndarray, percent: int) -> np.ndarray:
    """Rows are sorted by (token, n); rest counts a set's elements from the token on. True where another row of the token has a length that this row
    allows and allows this row's: needed_overlap(n, m) <= rest holds just for m <= reach."""
    size = len(token)
    if not size:
        return np.empty(0, bool)
    reach = np.maximum((100 + percent) * rest // percent - n, 0)
    new = np.r_[True, token[1:] != token[:-1]]
    group = np.cumsum(new) - 1
    start = np.flatnonzero(new)[group]
    stop = np.searchsorted((group << 32) + n, (group << 32) + reach, "right")  # of the rows that are short enough
    here = np.arange(size)
    best = [reach]
    while 2 << (len(best) - 1) <= int(np.diff(np.r_[np.flatnonzero(new), size]).max()):
        half = 1 << (len(best) - 1)
        best.append(np.maximum(best[-1][:-half], best[-1][half:]))
    found = np.zeros(size, bool)
    for low, high in ((start, np.minimum(here, stop)), (here + 1, stop)):
        width = high - low
        for t, table in enumerate(best):
            mine = np.flatnonzero((width >> t) == 1)
            found[mine] |= np.maximum(table[low[mine]], table[high[mine] - (1 << t)]) >= n[mine]
    return found


def shared_prefixes(docs: DataFrame, sketch: np.ndarray, size: int, percent: int, shards: int, hot: int) -> DataFrame:
    """(token, id, n, pos, central): prefix tokens of classes that have a possible partner there, each class once."""
    sent = docs.sparkSession.sparkContext.broadcast(sketch)

    def emit(batches):
        held, rows, seen = [], 0, set()
        counts, pack = sent.value, zstandard.ZstdCompressor(level=1).compress

        def flush():
            token, sig, n, pos, central, frequent = (np.concatenate(x) for x in zip(*held, strict=True))
            shard = (mix64(np.where(frequent, sig, token)) % np.uint64(shards)).astype(np.int64) * 2 + frequent
            order = np.argsort(shard, kind="stable")
            token, sig, n, pos, central, shard = (x[order] for x in (token, sig, n, pos, central, shard))
            first = np.flatnonzero(np.r_[True, shard[1:] != shard[:-1]])
            ends = np.r_[first[1:], len(shard)]
            blobs = [pa.array([x[a:b].tobytes() for a, b in zip(first, ends, strict=True)], pa.binary()) for x in (token, sig)]
            blobs += [pa.array([pack(x[a:b].tobytes()) for a, b in zip(first, ends, strict=True)], pa.binary()) for x in (n, pos, central)]  # hashes don't shrink, these do
            return pa.RecordBatch.from_arrays([pa.array(shard[first] // 2), pa.array(shard[first] % 2 == 1), *blobs], ["shard", "frequent", "token", "sig", "n", "pos", "central"])

        for batch in _slices(batches):
            for s in shingle_sets(batch.column("text").to_pylist(), size):
                if not len(s) or (sig := fingerprint(s)) in seen:  # a class is sent once per task
                    continue
                seen.add(sig)
                p = prefix_length(len(s), percent)
                c = counts[bucket_of(s)]
                order = np.lexsort((s, c))[:p]
                held.append((s[order], np.full(p, np.int64(sig).view(np.uint64)), np.full(p, len(s), np.uint32), np.arange(p, dtype=np.uint32), np.full(p, 1000 * np.log2(1.0 + c).mean(), np.uint32), c[order] >= hot))
                rows += p
                if rows > 1_500_000:
                    yield flush()
                    held, rows = [], 0
        if held:
            yield flush()

    def reduce(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        unpack = zstandard.ZstdDecompressor().decompress
        column = lambda name: np.frombuffer(b"".join(table.column(name).to_pylist()), np.uint64)
        small = lambda name: np.frombuffer(b"".join(map(unpack, table.column(name).to_pylist())), np.uint32)
        rows = [column("token"), column("sig"), small("n"), small("pos"), small("central")]
        order = np.lexsort((rows[1], rows[2], rows[0]))
        token, sig, n, pos, central = (x[order] for x in rows)
        if len(token):
            keep = np.r_[True, (token[1:] != token[:-1]) | (sig[1:] != sig[:-1])]
            token, sig, n, pos, central = (x[keep] for x in (token, sig, n, pos, central))
        if not key[1].as_py():
            wide = n.astype(np.int64)
            keep = partnered(token, wide, wide - pos, percent)
            token, sig, n, pos, central = (x[keep] for x in (token, sig, n, pos, central))
        return pa.table({"token": token.view(np.int64), "id": sig.view(np.int64), "n": n.astype(np.int32), "pos": pos.astype(np.int32), "central": central.astype(np.int32)})

    blobs = _texts(docs.where("doc_id is not null")).mapInArrow(emit, "shard long, frequent boolean, token binary, sig binary, n binary, pos binary, central binary")
    return blobs.groupBy("shard", "frequent").applyInArrow(reduce, "token long, id long, n int, pos int, central int")


def fetch_sets(docs: DataFrame, wanted: DataFrame, size: int) -> DataFrame:
    """(id, set) of the classes whose documents are in wanted (column doc): a map over the texts behind a fixed-size Bloom filter, so a few more
    classes come along, and rarely one twice."""
    bits, spark = 26, docs.sparkSession

    def place(batches):
        found = np.zeros((1 << bits) // 8, np.uint8)
        for batch in batches:
            at = mix64(batch.column("doc").to_numpy().astype(np.uint64)) >> np.uint64(64 - bits)
            np.bitwise_or.at(found, (at >> np.uint64(3)).astype(np.int64), np.uint8(1) << (at & np.uint64(7)).astype(np.uint8))
        used = np.flatnonzero(found)
        for low in range(0, len(used), 100_000):
            some = used[low : low + 100_000]
            yield pa.RecordBatch.from_arrays([pa.array(some // 4096), pa.array(some), pa.array(found[some].astype(np.int64))], ["block", "at", "bits"])

    bloom = np.zeros((1 << bits) // 8, np.uint8)
    bytes_set = wanted.select("doc").mapInArrow(place, "block long, at long, bits long").groupBy("block", "at").agg(F.bit_or("bits").alias("bits"))
    packed = bytes_set.groupBy("block").agg(F.collect_list(F.struct("at", "bits")).alias("cells"))  # at most 4096 cells a block
    for r in packed.collect():
        bloom[[c["at"] for c in r.cells]] = [c["bits"] for c in r.cells]
    sent = spark.sparkContext.broadcast(bloom)

    def build(batches):
        for batch in _slices(batches):
            at = mix64(batch.column("doc_id").to_numpy(zero_copy_only=False).astype(np.uint64)) >> np.uint64(64 - bits)
            hit = (sent.value[(at >> np.uint64(3)).astype(np.int64)] >> (at & np.uint64(7)).astype(np.uint8)) & 1
            sets = shingle_sets(batch.filter(pa.array(hit == 1)).column("text").to_pylist(), size)
            yield pa.RecordBatch.from_arrays([pa.array([fingerprint(s) for s in sets], pa.int64()), pa.array([s.tobytes() for s in sets], pa.binary())], ["id", "set"])

    return _texts(docs.where("doc_id is not null")).mapInArrow(build, "id long, set binary")


def verify(docs: DataFrame, pairs: DataFrame, classes: DataFrame, size: int, percent: int, scratch: Scratch, name: str) -> DataFrame:
    """(a, b) of the pairs whose Jaccard similarity reaches percent."""
    wanted = pairs.select(F.col("a").alias("id")).union(pairs.select(F.col("b").alias("id"))).distinct().join(classes.select("id", "doc"), "id")
    sets = scratch.write(fetch_sets(docs, wanted, size), f"{name}-sets")
    left, right = sets.select(F.col("id").alias("a"), F.col("set").alias("set_a")), sets.select(F.col("id").alias("b"), F.col("set").alias("set_b"))

    def test(batches):
        for batch in _slices(batches, 500):
            keep = []
            for x, y in zip(batch.column("set_a").to_pylist(), batch.column("set_b").to_pylist(), strict=True):
                x, y = np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)
                both = np.concatenate((x, y))
                both.sort()
                shared = int(np.count_nonzero(both[1:] == both[:-1]))
                keep.append(100 * shared >= percent * (len(x) + len(y) - shared))
            some = batch.filter(pa.array(keep, pa.bool_()))
            yield pa.RecordBatch.from_arrays([some.column("a"), some.column("b")], ["a", "b"])

    linked = pairs.join(left, "a").join(right, "b").select("a", "b", "set_a", "set_b").mapInArrow(test, "a long, b long").distinct()
    links = scratch.write(linked, f"{name}-links")
    scratch.drop(f"{name}-sets")
    return links


def components(edges: DataFrame, scratch: Scratch, name: str) -> DataFrame:
    """(id, comp) for every id in edges (u, v): comp is the smallest id that is reachable."""
    now = scratch.write(edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).where("u <> v").distinct(), f"{name}-e0")
    state = lambda e: e.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
    before, step = state(now), 0
    while before[0]:
        step += 1
        both = now.union(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
        large = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).union(least.select("u", F.col("m").alias("v"))).distinct()
        new = scratch.write(small, f"{name}-e{step}")
        scratch.drop(f"{name}-e{step - 1}")
        after, now = state(new), new
        if after == before:
            break
        before = after
    return now.select(F.col("u").alias("id"), F.col("v").alias("comp")).union(now.select(F.col("v").alias("id"), F.col("v").alias("comp")).distinct())


def shared_counts(sets: list[np.ndarray], cut: int | None = None, width: int = 8192) -> np.ndarray:
    """Sizes of the intersections of all sets with each other, or of those before `cut` with the rest."""
    m = len(sets)
    if m == 2:
        shared = len(np.intersect1d(sets[0], sets[1], assume_unique=True))
        return np.array([[shared]]) if cut else np.array([[len(sets[0]), shared], [shared, len(sets[1])]])
    owner = np.repeat(np.arange(m), [len(x) for x in sets])
    _, column, held = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    use = held[column] > 1  # others are in no intersection
    owner, (_, column) = owner[use], np.unique(column[use], return_inverse=True)
    order = np.argsort(column, kind="stable")
    owner, column = owner[order], column[order]
    out = np.zeros((cut or m, m - (cut or 0)), np.int64)
    for low in range(0, int(column.max(initial=-1)) + 1, width):
        first, end = np.searchsorted(column, [low, low + width])
        cells = np.zeros((m, width), np.float32)
        cells[owner[first:end], column[first:end] - low] = 1
        out += (cells[: cut or m] @ cells[cut or 0 :].T).astype(np.int64)
    return out


def linked_pairs(docs: DataFrame, inside: DataFrame, size: int, percent: int, scratch: Scratch, block: int = 256) -> tuple[DataFrame, DataFrame]:
    """inside: (id, doc, n, comp, docs) of the classes that have a link. All links (a, b) between their documents doc, and (id, others): the documents in linked classes."""
    inside = scratch.write(inside, "inside")
    blocks = F.ceil(F.col("m") / F.lit(block)).cast("int")
    held = inside.join(inside.groupBy("comp").agg(F.count(F.lit(1)).alias("m")), "comp").withColumn("k", blocks).withColumn("own", F.pmod(F.xxhash64("id"), F.col("k")).cast("int"))
    sent = held.agg(F.sum(F.col("n").cast("long") * 8 * F.col("k"))).first()[0] or 0
    sets = scratch.write(fetch_sets(docs, inside, size).dropDuplicates(["id"]), "inside-sets")
    dealt = held.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("k") - 1))).withColumn("low", F.least("own", "other")).withColumn("high", F.greatest("own", "other"))
    dealt = dealt.join(sets, "id").withColumn("bin", F.pmod(F.xxhash64("comp", "low", "high"), F.lit(max(32, sent // (8 << 20)))))

    def pieces(table: pa.Table):
        """(ids, their documents, documents of each, linked matrix, cut) of each block pair in a bin."""
        comp, low, high, own, ids, rows, weight = (table.column(c).to_numpy() for c in ("comp", "low", "high", "own", "id", "doc", "docs"))
        order = np.lexsort((own, high, low, comp))
        comp, low, high, own, ids, rows, weight = (x[order] for x in (comp, low, high, own, ids, rows, weight))
        raw = table.column("set").to_pylist()
        new = np.flatnonzero(np.r_[True, (comp[1:] != comp[:-1]) | (low[1:] != low[:-1]) | (high[1:] != high[:-1])])
        for a, b in zip(new, np.r_[new[1:], len(comp)], strict=True):
            cut = int(np.searchsorted(own[a:b], high[a])) if low[a] < high[a] else None
            if b - a < 2 or cut in (0, b - a):
                continue
            members = [np.frombuffer(raw[k], np.uint64) for k in order[a:b]]
            n = np.array([len(x) for x in members])
            shared = shared_counts(members, cut)
            linked = 100 * shared >= percent * (n[: cut or len(n), None] + n[None, cut or 0 :] - shared)
            if cut is None:
                np.fill_diagonal(linked, False)
            yield ids[a:b], rows[a:b], weight[a:b], linked, cut

    def pairs(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        found = [(np.empty(0, np.int64),) * 2]
        for _, rows, _, linked, cut in pieces(table):
            x, y = np.nonzero(linked if cut else np.triu(linked))
            x, y = rows[x], rows[y + (cut or 0)]
            found.append((np.minimum(x, y), np.maximum(x, y)))
        a, b = (np.concatenate(x) for x in zip(*found, strict=True))
        return pa.table({"a": a, "b": b})

    def sums(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        found = [(np.empty(0, np.int64),) * 2]
        for ids, _, weight, linked, cut in pieces(table):
            if cut is None:
                found.append((ids, linked @ weight))
            else:
                found += [(ids[:cut], linked @ weight[cut:]), (ids[cut:], linked.T @ weight[:cut])]
        ids, others = (np.concatenate(x) for x in zip(*found, strict=True))
        return pa.table({"id": ids, "others": others})

    bins = dealt.select("bin", "comp", "low", "high", "own", "id", "doc", "docs", "set").groupBy("bin")
    return bins.applyInArrow(pairs, "a long, b long"), bins.applyInArrow(sums, "id long, others long").groupBy("id").agg(F.sum("others").alias("others"))


def near_duplicates(docs: DataFrame, size: int = 5, percent: int = 80, hot: int = 20_000, shard_rows: int = 250_000, whole_links: bool = True, salt_rows: int = 1000) -> tuple[DataFrame, DataFrame]:
    """(documents, links): rows (doc_id, n_shingles, class_id, component_id, n_links), and all verified links between class representatives.
    n_links counts the other documents that a document is linked with, those of its own class included. Without whole_links there is no n_links,
    and the links are only those that the rounds needed for the components."""
    scratch = Scratch(docs.sparkSession, "ngrams")
    docs = docs.select("doc_id", "text")
    rows = scratch.write(profile(docs, size), "profile")
    sketch = read_sketch(rows)
    release(docs.sparkSession)
    members = rows.where("block is null")
    total = members.agg(F.sum(F.col("n") * F.lit((100 - percent) / 100) + 1)).first()[0] or 0
    tokens = scratch.write(shared_prefixes(docs, sketch, size, percent, max(32, int(total // shard_rows)), hot), "tokens")
    # id names a class by its fingerprint, doc is its smallest document
    classes = members.where("n > 0").groupBy(F.col("sig").alias("id")).agg(F.min("doc_id").alias("doc"), F.first("n").alias("n"), F.first("parts").alias("parts"), F.count(F.lit(1)).alias("docs"))
    classes = scratch.write(classes, "classes")
    release(docs.sparkSession)
    parts = classes.select("id", "parts")

    def usable(pairs: DataFrame) -> DataFrame:
        """Length and positional filters on rows (id, n, pos, hub_id, hub_n, hub_pos), then one row per pair and the suffix filter."""
        need = F.ceil(F.lit(percent) * (F.col("n") + F.col("hub_n")) / F.lit(100 + percent))
        near = pairs.where(F.least("n", "hub_n") * 100 >= F.greatest("n", "hub_n") * percent).where(F.least(F.col("n") - F.col("pos"), F.col("hub_n") - F.col("hub_pos")) >= need)
        one = near.select(F.least("id", "hub_id").alias("a"), F.greatest("id", "hub_id").alias("b"), need.alias("need")).distinct()
        pa_, pb = parts.select(F.col("id").alias("a"), F.col("parts").alias("pa")), parts.select(F.col("id").alias("b"), F.col("parts").alias("pb"))
        bound = F.aggregate(F.zip_with("pa", "pb", lambda x, y: F.least(x, y)), F.lit(0), lambda s, x: s + x)
        return one.join(pa_, "a").join(pb, "b").where(bound >= F.col("need")).select("a", "b")

    ratio = max(float(np.log(100 / percent)), 1e-6) * (1 + 1e-9)
    band = F.floor(F.log("n") / F.lit(ratio)).cast("int")  # partners are in the same band of lengths or in the next
    links, tested, comp = None, None, None
    for k in range(3):
        here = tokens.withColumn("comp", F.col("id")) if comp is None else tokens.join(comp, "id", "left").withColumn("comp", F.coalesce("comp", "id"))
        if k < 2:
            best = F.min_by(F.struct("id", "n", "pos", "comp"), F.struct((-F.col("central")).alias("c"), "id")).alias("hub")
            mixed = here.groupBy("token").agg(best, F.min("comp").alias("c1"), F.max("comp").alias("c2")).where("c1 <> c2")
            hub = mixed if k == 0 else here.join(mixed.select("token", F.col("hub.comp").alias("first")), "token").where("comp <> first").groupBy("token").agg(best)
            met = here.join(hub.select("token", F.col("hub.id").alias("hub_id"), F.col("hub.n").alias("hub_n"), F.col("hub.pos").alias("hub_pos"), F.col("hub.comp").alias("hub_comp")), "token").where("comp <> hub_comp")
        else:
            mixed = here.groupBy("token").agg(F.min("comp").alias("c1"), F.max("comp").alias("c2"), F.ceil(F.count(F.lit(1)) / F.lit(salt_rows)).cast("int").alias("salts")).where("c1 <> c2").select("token", "salts")
            left = scratch.write(here.join(mixed, "token").withColumn("band", band), "open")
            reach = left.withColumn("band", F.explode(F.array(F.col("band"), F.col("band") + 1))).withColumn("salt", F.explode(F.sequence(F.lit(0), F.col("salts") - 1)))
            other = reach.select("token", "band", "salt", F.col("id").alias("hub_id"), F.col("n").alias("hub_n"), F.col("pos").alias("hub_pos"), F.col("comp").alias("hub_comp"))
            dealt = left.withColumn("salt", F.pmod(F.xxhash64("id"), F.col("salts")).cast("int"))
            met = dealt.join(other, ["token", "band", "salt"]).where("(hub_n < n or (hub_n = n and hub_id < id)) and comp <> hub_comp")
        pairs = usable(met)
        if tested is not None:
            pairs = pairs.join(tested, ["a", "b"], "left_anti")
        pairs = scratch.write(pairs, f"pairs{k}")
        found = verify(docs, pairs, classes, size, percent, scratch, f"round{k}")
        links = found if links is None else links.union(found)
        tested = pairs if tested is None else tested.union(pairs)
        comp = bounded_broadcast(scratch.write(components(links.select(F.col("a").alias("u"), F.col("b").alias("v")), scratch, f"comp{k}"), f"comp{k}"), 64)
        pairs = found = here = mixed = met = hub = left = reach = other = dealt = None
        release(docs.sparkSession)
    linked = classes.select("id", "doc", "n", "docs").join(comp, "id")
    least = linked.groupBy("comp").agg(F.min("doc").alias("least"))
    labels = linked.join(least, "comp").select("id", "least")
    sig = F.when(F.col("n") > 0, F.col("sig")).alias("id")
    labelled = members.select("doc_id", "n", sig).join(classes.select("id", "doc", "docs"), "id", "left").join(labels, "id", "left")
    own, others = [], None
    if whole_links:
        links, others = linked_pairs(docs, linked, size, percent, scratch)
        labelled = labelled.join(others, "id", "left")
        own = [(F.coalesce(F.col("docs") - 1, F.lit(0)) + F.coalesce("others", F.lit(0))).alias("n_links")]
    out = labelled.select("doc_id", F.col("n").cast("long").alias("n_shingles"), F.coalesce("doc", "doc_id").alias("class_id"), F.coalesce("least", "doc", "doc_id").alias("component_id"), *own)
    return out, links
