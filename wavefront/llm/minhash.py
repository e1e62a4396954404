"""Near-duplicate documents: one-permutation MinHash with optimal densification, banded buckets, star-shaped candidates.

A document's set holds its distinct shingles of five words (words are runs of bytes other than ASCII white space, A-Z
lower-cased). One 64-bit hash serves every slot: its top seven bits choose one of 128 bins and the least hash of a bin
is the slot's value. Empty bins borrow from a full bin found along a fixed pseudo-random probe sequence of their own,
so two sets that agree borrow alike. 25 bands of 5 slots make bucket keys: a pair at similarity 0.85 misses every
band with probability below 1e-6, at 0.8 below 1e-4.

Equal sets first fall into one class by a 128-bit digest; only one representative of a class goes on. In a bucket
every member is paired with the least member (a star), so a bucket of n gives n-1 candidates. A centre has then met its
whole bucket and leaves it. Buckets whose other members do not lie in one component yet are open: they take more stars,
each around the member that shares most open buckets with others (the text that edited copies derive from). What is
open after these is compared in blocks: members of a bucket's largest component stay in one block each, the others
visit every block. So every pair of a bucket is tried or lies in one component. Candidates are confirmed on the full
sets, recomputed from the texts.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wavefront.llm.bitmap import marked, marks
from wavefront.llm.bytehash import mix, prefix_sums, range_hash, spans_of_bytes, text_buffer
from wavefront.llm.workers import give_back, let_go, small_batches
from wavefront.operators.components import connected_components
from wavefront.session import cut

WORDS = 5
BINS = 128
BAND_ROWS = 5
BANDS = BINS // BAND_ROWS
PIECE = 1 << 18
STEP = 4 << 20
PAIRS = 500
STARS = 1
BLOCK_BYTES = 2 << 20
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[32, *range(9, 14)]] = True
_FACTORS = mix(np.arange(1, 33, dtype=np.uint64)) | np.uint64(1)
_EDGES = np.arange(BINS, dtype=np.uint64) << np.uint64(57)
_PROBES = (mix(np.arange(BINS * 2048, dtype=np.uint64) + np.uint64(7919)) >> np.uint64(57)).astype(np.int64).reshape(BINS, 2048)


def shingle_sets(data: np.ndarray, offsets: np.ndarray) -> list[np.ndarray]:
    """The sorted distinct shingle hashes of each text ``data[offsets[i]:offsets[i+1]]``."""
    out: list[np.ndarray] = []
    for i, j in spans_of_bytes(offsets, PIECE):
        at = offsets[i : j + 1] - offsets[i]
        b = _LOWER[data[offsets[i] : offsets[j]]]
        out += _sets(b, at)
    return out


def _sets(b: np.ndarray, at: np.ndarray) -> list[np.ndarray]:
    none = np.empty(0, np.uint64)
    if not len(b):
        return [none] * (len(at) - 1)
    word = ~_SPACE[b]
    before = np.empty_like(word)
    before[0] = False
    before[1:] = word[:-1]
    after = np.empty_like(word)
    after[-1] = False
    after[:-1] = word[1:]
    inner = at[1:-1]
    inner = inner[(inner > 0) & (inner < len(b))]
    before[inner] = False
    after[inner - 1] = False
    start = np.flatnonzero(word & ~before)
    end = np.flatnonzero(word & ~after) + 1
    w = mix(range_hash(prefix_sums(b), start, end) + (end - start).astype(np.uint64) * _FACTORS[31])
    n = len(w)
    first = np.searchsorted(start, at)  # the words of text i are first[i]..first[i+1]-1
    if n >= WORDS:
        h = w[: n - WORDS + 1] * _FACTORS[0]
        for k in range(1, WORDS):
            h = h + w[k : n - WORDS + 1 + k] * _FACTORS[k]
        h = mix(h)
    sets = []
    for lo, hi in zip(first[:-1].tolist(), first[1:].tolist(), strict=True):
        m = hi - lo
        if m >= WORDS:
            x = np.sort(h[lo : hi - WORDS + 1])
            if len(x) > 1:
                x = x[np.concatenate(([True], x[1:] != x[:-1]))]
            sets.append(x)
        elif m:
            sets.append(mix(np.array([int(np.add.reduce(w[lo:hi] * _FACTORS[8 : 8 + m])) + m & (1 << 64) - 1], np.uint64)))
        else:
            sets.append(none)
    return sets


def one_permutation(s: np.ndarray) -> np.ndarray:
    """128 slot values of a sorted, non-empty set."""
    at = np.searchsorted(s, _EDGES)
    value = s[np.minimum(at, len(s) - 1)]
    full = (at < len(s)) & ((value >> np.uint64(57)) == np.arange(BINS, dtype=np.uint64))
    if not full.all():
        for lo, hi in ((0, 8), (8, 64), (64, 2048)):
            empty = np.flatnonzero(~full)
            hit = full[_PROBES[empty, lo:hi]] if lo == 0 else done[_PROBES[empty, lo:hi]]
            if lo == 0:
                done, donor = full.copy(), np.arange(BINS)
            ok = hit.any(axis=1)
            donor[empty[ok]] = _PROBES[empty[ok], lo + hit[ok].argmax(axis=1)]
            full = full.copy()
            full[empty[ok]] = True
            if full.all():
                break
        rest = np.flatnonzero(~full)
        donor[rest] = np.flatnonzero(done)[0]
        value = value[donor]
    return value


def band_keys(value: np.ndarray) -> np.ndarray:
    rows = value[: BANDS * BAND_ROWS].reshape(BANDS, BAND_ROWS)
    return mix((rows * _FACTORS[:BAND_ROWS]).sum(axis=1, dtype=np.uint64) + np.arange(BANDS, dtype=np.uint64) * _FACTORS[9])


def _digest(s: np.ndarray) -> tuple[int, int]:
    d = np.frombuffer(xxhash.xxh3_128_digest(s.tobytes()), dtype="<i8")
    return int(d[0]), int(d[1])


def _sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    let_go()
    for batch in batches:
        data, offsets = text_buffer(batch.column(1))
        for i, j in spans_of_bytes(offsets, STEP):
            sets = shingle_sets(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i])
            d = [_digest(s) if len(s) else (None, None) for s in sets]
            keys = [band_keys(one_permutation(s)).view(np.int64) if len(s) else np.empty(0, np.int64) for s in sets]
            at = np.concatenate(([0], np.cumsum([len(k) for k in keys]))).astype(np.int32)
            flat = np.concatenate(keys) if keys else np.empty(0, np.int64)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0).slice(i, j - i), pa.array([len(s) for s in sets], pa.int64()), pa.array([x for x, _ in d], pa.int64()), pa.array([x for _, x in d], pa.int64()), pa.ListArray.from_arrays(pa.array(at), pa.array(flat))],
                names=["doc_id", "n_shingles", "d1", "d2", "bands"],
            )
        del data, offsets, batch
        give_back()


def _confirm(percent: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        let_go()
        kept_id, kept_set = None, None
        for whole in batches:
            for at in range(0, whole.num_rows, PAIRS):
                batch = whole.slice(at, PAIRS)
                u, v = batch.column(0).to_pylist(), list(zip(batch.column(1).to_pylist(), batch.column(4).to_pylist(), strict=True))
                sets = shingle_sets(*text_buffer(batch.column(2)))
                first = [k for k in range(len(v)) if (k == 0 or v[k] != v[k - 1]) and v[k] != kept_id]  # a centre's text is read once for a run of its members
                centres = shingle_sets(*text_buffer(batch.column(3).take(pa.array(first, pa.int32()))))
                by = {v[k]: c for k, c in zip(first, centres, strict=True)} | ({kept_id: kept_set} if kept_id else {})
                ok = []
                for a, c, s in zip(u, v, sets, strict=True):
                    o = by[c]
                    both = len(np.intersect1d(s, o, assume_unique=True))
                    if 100 * both >= percent * (len(s) + len(o) - both) and both:
                        ok.append((a, c[0]))
                kept_id, kept_set = v[-1], by[v[-1]]
                yield pa.RecordBatch.from_arrays([pa.array([a for a, _ in ok], pa.int64()), pa.array([c for _, c in ok], pa.int64())], names=["u", "v"])
            give_back()

    return run


def _star_links(docs: DataFrame, keys: DataFrame, centres: DataFrame, percent: int) -> DataFrame:
    """Confirmed pairs (u, v) of each bucket's members with its centre, where they are not connected yet."""
    near = F.least("n", "cn") * 100 >= F.greatest("n", "cn") * percent
    pairs = cut(keys.join(centres.hint("merge"), "key").where((F.col("component") != F.col("cc")) & near).select(F.col("doc_id").alias("u"), F.col("c").alias("v")).distinct())
    ends = pairs.select(F.explode(F.array(F.xxhash64("u"), F.xxhash64("v"))).alias("_dk"))
    docs = marked(docs.withColumn("_dk", F.xxhash64("doc_id")), marks(ends, "_dk"), "_dk").where("hit")  # other texts are not moved
    member = pairs.join(docs.select(F.col("doc_id").alias("u"), "text").hint("merge"), "u")
    both = member.join(docs.select(F.col("doc_id").alias("v"), F.col("text").alias("other")).hint("merge"), "v")
    return both.select("u", "v", "text", "other", F.xxhash64("other").alias("other_key")).mapInArrow(_confirm(percent), "u long, v long")


def _still_open(keys: DataFrame, centres: DataFrame, label: DataFrame) -> DataFrame:
    """Buckets without their centre, those only whose members lie in several components: (key, doc_id, n, component)."""
    rest = keys.select("key", "doc_id", "n").join(centres.select("key", "c").hint("merge"), "key").where("doc_id <> c").drop("c")
    rest = rest.join(label.withColumnRenamed("node", "doc_id").hint("merge"), "doc_id", "left")
    rest = cut(rest.withColumn("component", F.coalesce("component", "doc_id")))
    several = rest.groupBy("key").agg(F.min("component").alias("a"), F.max("component").alias("b")).where("a <> b").select("key")
    return cut(rest.join(several.hint("merge"), "key", "left_semi"))


def _hubs(keys: DataFrame) -> DataFrame:
    """The centre of each open bucket: the member that meets most others over all its open buckets, then the least."""
    size = keys.groupBy("key").agg(F.count(F.lit(1)).alias("m"))
    met = keys.join(size.hint("merge"), "key").groupBy("doc_id").agg(F.sum("m").alias("met"))
    best = F.struct(-F.col("met"), "doc_id")
    scored = keys.join(met.hint("merge"), "doc_id")
    return scored.groupBy("key").agg(F.min_by("doc_id", best).alias("c"), F.min_by("n", best).alias("cn"), F.min_by("component", best).alias("cc"))


def _block_links(docs: DataFrame, keys: DataFrame, percent: int) -> DataFrame:
    """Confirmed pairs (u, v) of different components among the members of each bucket.

    A bucket is dealt into blocks of bounded size. Members of its largest component stay in their block; each of the
    others goes to all blocks, so what is moved grows with the members that are not connected yet.
    """
    parts = keys.groupBy("key", "component").agg(F.count(F.lit(1)).alias("m"), F.sum("n").alias("n"))
    blocks = parts.groupBy("key").agg(F.max_by("component", F.struct("m", "component")).alias("most"), F.ceil(F.sum("n") * 8 / BLOCK_BYTES).alias("of"))
    dealt = keys.join(blocks.hint("merge"), "key").withColumn("block", F.pmod(F.xxhash64("doc_id"), "of"))
    own = dealt.select("key", "block", F.lit(0).alias("visits"), "doc_id", "component")
    guests = dealt.where("component <> most").select("key", F.explode(F.sequence(F.lit(0).cast("long"), F.col("of") - 1)).alias("block"), F.lit(1).alias("visits"), "doc_id", "component")
    seats = cut(own.unionByName(guests).groupBy("doc_id", "component").agg(F.collect_list(F.struct("key", "block", "visits")).alias("seats")))
    ends = seats.select(F.xxhash64("doc_id").alias("_dk"))
    texts = marked(docs.withColumn("_dk", F.xxhash64("doc_id")), marks(ends, "_dk"), "_dk").where("hit").select("doc_id", "text")
    rows = texts.join(seats.hint("merge"), "doc_id").mapInArrow(_seated, "key long, block long, visits int, doc_id long, component long, body binary")
    rows = rows.repartition("key", "block").sortWithinPartitions("key", "block", "visits")
    return rows.mapInArrow(_paired(percent), "u long, v long")


def _seated(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(doc_id, text, component, seats) -> a row for each seat with the text's band keys and set."""
    let_go()
    names = ["key", "block", "visits", "doc_id", "component", "body"]
    kinds = [pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.binary()]

    def made(rows: list[tuple]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names=names)

    for batch in batches:
        data, offsets = text_buffer(batch.column(1))
        for i, j in spans_of_bytes(offsets, STEP):
            sets = shingle_sets(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i])
            rows, size = [], 0
            for k, own in zip(range(i, j), sets, strict=True):
                if not len(own):  # an id's other row may have no words
                    continue
                body = band_keys(one_permutation(own)).tobytes() + own.tobytes()
                doc, component = batch.column(0)[k].as_py(), batch.column(2)[k].as_py()
                for seat in batch.column(3)[k]:
                    rows.append((*(seat[c].as_py() for c in names[:3]), doc, component, body))
                    size += len(body)
                    if size > 2 << 20:
                        yield made(rows)
                        rows, size = [], 0
            if rows:
                yield made(rows)
        give_back()


def _paired(percent: int):
    """Rows in order of (key, block, visits) -> links of a block's members with one another and with its guests.

    A pair is tried in the first bucket it shares; where that bucket is no longer open or has lost one of the two, the
    pair lies in one component or was tried with a centre.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        let_go()
        group, ids, labels, sets, bands, table = None, [], [], [], [], None

        def links_of(key: int, u: int, component: int, band: np.ndarray, own: np.ndarray) -> Iterator[tuple[int, int]]:
            same = table[0] == band
            first = same.argmax(axis=1)
            try_ = same.any(axis=1) & (band[first] == key) & (table[1] != component)
            try_ &= np.minimum(table[2], len(own)) * 100 >= np.maximum(table[2], len(own)) * percent
            for j in np.flatnonzero(try_).tolist():
                both = len(np.intersect1d(own, sets[j], assume_unique=True))
                if 100 * both >= percent * (len(own) + len(sets[j]) - both) and both:
                    yield u, ids[j]

        for batch in batches:
            out: list[tuple[int, int]] = []
            columns = [batch.column(k).to_pylist() for k in range(6)]
            for key, block, visits, u, component, body in zip(*columns, strict=True):
                if group != (key, block):
                    group, ids, labels, sets, bands, table = (key, block), [], [], [], [], None
                band, own = np.frombuffer(body[: 8 * BANDS], "<i8"), np.frombuffer(body[8 * BANDS :], "<u8")
                if not visits:
                    for column, x in zip((ids, labels, sets, bands), (u, component, own, band), strict=True):
                        column.append(x)
                    continue
                if table is None:
                    table = (np.stack(bands), np.array(labels), np.array([len(x) for x in sets])) if ids else ()
                if table:
                    out += links_of(key, u, component, band, own)
            yield pa.RecordBatch.from_arrays([pa.array([u for u, _ in out], pa.int64()), pa.array([v for _, v in out], pa.int64())], names=["u", "v"])
            give_back()

    return run


def near_duplicates(docs: DataFrame, percent: int = 85) -> DataFrame:
    """Classes of near-duplicate rows of ``docs(doc_id long, text string, ...)``.

    Returns ``doc_id, n_shingles, component_id, kept``, a row for each input row. Two documents are linked when
    100 * |A n B| >= percent * |A u B| over shingle sets. Null or wordless texts have the empty set and link with
    nothing. A null doc_id links with nothing and keeps a null component. Rows that repeat a doc_id are one node
    with each row's links. Other columns are ignored; an empty table gives an empty result.
    """
    docs = small_batches(docs).select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    sig = cut(docs.mapInArrow(_sign, "doc_id long, n_shingles long, d1 long, d2 long, bands array<long>"))
    some = sig.where("n_shingles > 0 and doc_id is not null")
    classes = cut(some.groupBy("d1", "d2").agg(F.min("doc_id").alias("rep"), F.count(F.lit(1)).alias("n")))
    copies = some.select("doc_id", "d1", "d2").join(classes.where("n > 1").hint("merge"), ["d1", "d2"]).where("doc_id <> rep").select("doc_id", "rep")
    copies = cut(copies.distinct())
    reps = some.join(classes.select(F.col("rep").alias("doc_id"), "d1", "d2").hint("merge"), ["doc_id", "d1", "d2"])
    keys = reps.select("doc_id", F.col("n_shingles").alias("n"), F.explode("bands").alias("key"))
    full = keys.groupBy("key").agg(F.count(F.lit(1)).alias("m")).where("m > 1").select("key")
    keys = cut(keys.join(full.hint("merge"), "key", "left_semi"))
    keys = keys.withColumn("component", F.col("doc_id"))
    centres = keys.groupBy("key").agg(F.min("doc_id").alias("c"), F.min_by("n", "doc_id").alias("cn"), F.min("doc_id").alias("cc"))
    several = some.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    more = cut(copies.join(several, "doc_id", "left_semi").select(F.col("doc_id").alias("u"), F.col("rep").alias("v")))
    links = None
    for turn in range(STARS + 1):
        centres = cut(centres)
        found = _star_links(docs, keys, centres, percent)
        links = cut(found if links is None else links.unionByName(found))
        comp = cut(connected_components(links))
        keys = _still_open(keys, centres, comp)
        if keys.isEmpty():
            break
        if turn < STARS:
            centres = _hubs(keys)
    else:
        more = cut(more.unionByName(_block_links(docs, keys, percent)))
    if not more.isEmpty():
        comp = cut(connected_components(links.unionByName(more)))
    node = copies.join(comp.select(F.col("node").alias("rep"), "component").hint("merge"), "rep", "left").select(F.col("doc_id").alias("node"), F.coalesce("component", "rep").alias("component"))
    labels = cut(comp.unionByName(node).groupBy("node").agg(F.min("component").alias("component")))
    out = sig.join(labels.withColumnRenamed("node", "doc_id").hint("merge"), "doc_id", "left")
    one = F.coalesce(F.col("component"), F.col("doc_id"))
    return out.select("doc_id", "n_shingles", one.alias("component_id"), F.col("doc_id").eqNullSafe(one).alias("kept"))


def one_of_each(docs: DataFrame, percent: int = 80) -> DataFrame:
    """The rows of ``docs`` whose document is the least of its class, with their own columns.

    Ids that go are told by a bit map first, so rows that stay for certain are not moved.
    """
    gone = cut(near_duplicates(docs, percent).where("not kept").select(F.col("doc_id").alias("gone"), F.xxhash64("doc_id").alias("key")).distinct())
    rows = docs.select(F.struct("*").alias("row"), F.col("doc_id").cast("long").alias("id")).withColumn("key", F.xxhash64("id"))  # own columns may bear any name
    split = marked(rows, marks(gone, "key"), "key")
    left = split.where("hit").join(gone.select("gone").hint("merge"), F.col("id") == F.col("gone"), "left_anti")
    return split.where("not hit").select("row.*").unionByName(left.select("row.*"))
