"""Removal of repeated passages: every byte covered by a 400-byte string that also starts anywhere else goes.

The suffixes of the corpus (starts of 400-byte strings inside one document) are dealt into buckets by an anchor: the
161-byte-window minimum rule picks, among the 160-byte grams inside the string, the one with the least hash. Equal
strings have equal anchors at equal offsets, so they share a bucket. Starts that follow one another and share an anchor
form a run, so a bucket row stands for about a hundred suffixes.

1. Anchors that occur once cannot hold a repeat and leave after one narrow count (8-byte keys, summed map-side).
2. Runs of one text (128-bit key) are one class with a count; one text of each class is moved.
3. Classes come together by anchor, in blocks of bounded bytes, and ``suffix_order.repeated_starts`` orders the block's
   suffixes with cover-sample ranks. Every repeat comes out of that order, those of whole runs too: a suffix repeats
   if the classes that hold it stand for two places or more.
4. A bucket of more classes than a block should hold is dealt out by the bytes that come next. A string at offset o of
   its anchor shows o bytes before and 240 - o bytes after it, so either half of the missing bytes lies on its left or
   half on its right: its run is cut in two there, each part goes to the bucket of those bytes, and equal parts are one
   class again. After eight such steps a bucket knows all 400 bytes and is one class, so no block is unbounded. A bucket
   that a task can hold takes these steps where it is sorted, a larger one takes them as tables.
5. Starts become byte intervals, are gathered by document and cut out of the text.

``without_repeats`` also cuts passages of 51 words or more, however few bytes they take: a text becomes the 8-byte codes
of its pairs of neighbouring words, where 400 bytes are 50 codes, that is 51 words.
"""

from __future__ import annotations

import hashlib
import re
import struct
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wavefront.llm.bitmap import marked, marks
from wavefront.llm.bytehash import mix, prefix_sums, range_hash, spans_of_bytes, text_buffer
from wavefront.llm.suffix_order import LENGTH, repeated_starts
from wavefront.llm.workers import give_back, let_go, small_batches
from wavefront.session import cut

GRAM = 160
WINDOW = LENGTH - GRAM + 1
PIECE = 1 << 18
SPARE = LENGTH - GRAM
BLOCK_BYTES = 1 << 19
BUCKET_CLASSES = 512
IN_TASK = 8  # a bucket of at most so many times BUCKET_CLASSES is split by the task that sorts it
CODE = 8
PASSAGE_WORDS = LENGTH // CODE + 1
_LOW = np.uint64((1 << 20) - 1)
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[32, *range(9, 14)]] = True
_WORD = re.compile(rb"[^\x20\x09-\x0d]+")
_FACTORS = mix(np.arange(1, 4, dtype=np.uint64)) | np.uint64(1)


def anchor_runs(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, ...]:
    """Runs of string starts that share an anchor: (row, first start, last start, anchor, gram hash), in row terms."""
    found = []
    length = np.diff(offsets)
    total = len(data)
    piece = min(PIECE, (1 << 20) - 2 * LENGTH)
    row_of_start = np.flatnonzero(length >= LENGTH)
    for c in range(0, max(0, total - LENGTH + 1), piece):
        stop = min(c + piece, total - LENGTH + 1)  # starts c..stop-1
        here = row_of_start[(offsets[row_of_start] < stop) & (offsets[row_of_start + 1] - LENGTH >= c)]
        if not len(here):
            continue
        b = data[c : stop + LENGTH - 1]
        p = prefix_sums(b)
        n = len(b) - GRAM + 1
        at = np.arange(n)
        g = mix(range_hash(p, at, at + GRAM))
        least = (g & ~_LOW) | at.astype(np.uint64)
        w = 1
        while 2 * w <= WINDOW:
            least = np.minimum(least[:-w], least[w:])
            w *= 2
        if w < WINDOW:
            least = np.minimum(least[: len(least) - (WINDOW - w)], least[WINDOW - w :])
        pick = (least & _LOW).astype(np.int64)
        lo = np.maximum(offsets[here] - c, 0)
        hi = np.minimum(offsets[here + 1] - LENGTH - c, stop - 1 - c)  # last start of each row in this piece
        count = hi - lo + 1
        ends = np.cumsum(count)
        x = np.arange(int(ends[-1])) + np.repeat(lo - (ends - count), count)
        a = pick[x]
        new = np.empty(len(x), bool)
        new[0] = True
        new[1:] = a[1:] != a[:-1]
        new[ends[:-1]] = True
        first = np.flatnonzero(new)
        last = np.append(first[1:], len(x)) - 1
        row = np.repeat(here, count)[first]
        shift = c - offsets[row]
        found.append((row, x[first] + shift, x[last] + shift, a[first] + shift, g[a[first]]))
    if not found:
        none = np.empty(0, np.int64)
        return none, none, none, none, np.empty(0, np.uint64)
    return tuple(np.concatenate(k) for k in zip(*found, strict=True))


def _runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(doc_id, tk, text) -> rows (gram, k1, k2, doc_id, tk, loc); loc packs start, run length and anchor offset."""
    let_go()
    for batch in batches:
        data, offsets = text_buffer(batch.column(2))
        row, first, last, anchor, gram = anchor_runs(data, offsets)
        whole = memoryview(data)
        lo, hi = (offsets[row] + first).tolist(), (offsets[row] + last + LENGTH).tolist()
        key = np.frombuffer(b"".join(xxhash.xxh3_128_digest(whole[a:b]) for a, b in zip(lo, hi, strict=True)), "<i8").reshape(-1, 2)
        loc = (first << 16) | ((last - first) << 8) | (anchor - first)
        take = pa.array(row)
        yield pa.RecordBatch.from_arrays([pa.array(gram.view(np.int64)), pa.array(key[:, 0].copy()), pa.array(key[:, 1].copy()), batch.column(0).take(take), batch.column(1).take(take), pa.array(loc)], names=["gram", "k1", "k2", "doc_id", "tk", "loc"])
        give_back()


def _grams(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    let_go()
    for batch in batches:
        yield pa.RecordBatch.from_arrays([pa.array(anchor_runs(*text_buffer(batch.column(0)))[4].view(np.int64))], names=["gram"])
        give_back()


#: A class in its bucket: one text, its count, where its anchor lies and what the bucket knows to its left and right.
_CLASS = pa.schema([("bucket", pa.int64()), ("k1", pa.int64()), ("k2", pa.int64()), ("weight", pa.int64()), ("lead", pa.int32()), ("left", pa.int32()), ("right", pa.int32()), ("bytes", pa.binary())])
_PART = pa.schema([*_CLASS, ("from_bucket", pa.int64()), ("from_k1", pa.int64()), ("from_k2", pa.int64())])
_DDL = "bucket long, k1 long, k2 long, weight long, lead int, left int, right int, bytes binary"


def _table(rows: list[tuple], schema: pa.Schema) -> pa.RecordBatch:
    columns = zip(*rows, strict=True) if rows else [[]] * len(schema)
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(columns, schema, strict=True)], schema=schema)


def _slices(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(doc_id, tk, text, wanted) -> the classes whose text is taken from this row, and whether their bucket is to be split."""
    let_go()
    schema = pa.schema([*_CLASS, ("many", pa.bool_())])
    for batch in batches:
        data, offsets = text_buffer(batch.column(2))
        whole = memoryview(data)
        rows, size = [], 0
        for k, wanted in enumerate(batch.column(3).to_pylist()):
            for w in wanted:
                loc = w["loc"]
                a = int(offsets[k]) + (loc >> 16)
                piece = bytes(whole[a : a + (loc >> 8 & 255) + LENGTH])
                rows.append((w["gram"], w["k1"], w["k2"], w["weight"], loc & 255, 0, 0, piece, w["many"]))
                size += len(piece)
                if size > 2 << 20:
                    yield _table(rows, schema)
                    rows, size = [], 0
        if rows:
            yield _table(rows, schema)
        give_back()


def parts_of(bucket: int, lead: int, left: int, right: int, text: bytes) -> Iterator[tuple[int, int, int, int, bytes]]:
    """A run cut where its strings show the next bytes on their left or on their right: (bucket, lead, left, right, text)."""
    low = lead - (len(text) - LENGTH)
    slack = SPARE - left - right
    step = (slack + 1) // 2
    border = left + step  # strings from this offset on show ``step`` more bytes on the left, the others slack - step + 1 on the right
    if lead >= border:
        ctx = text[lead - border : lead - left]
        yield xxhash.xxh3_64_intdigest(struct.pack("<qb", bucket, 0) + ctx), lead, border, right, text[: lead - max(low, border) + LENGTH]
    if low < border:
        at, more = lead + GRAM + right, slack - step + 1
        ctx = text[at : at + more]
        yield xxhash.xxh3_64_intdigest(struct.pack("<qb", bucket, 1) + ctx), min(lead, border - 1), left, right + more, text[max(0, lead - border + 1) :]


def _split(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        rows = []
        for bucket, k1, k2, weight, lead, left, right, text in zip(*(batch.column(k).to_pylist() for k in range(8)), strict=True):
            for b, *rest, piece in parts_of(bucket, lead, left, right, text):
                a, c = struct.unpack("<qq", xxhash.xxh3_128_digest(struct.pack("<q", rest[0]) + piece))
                rows.append((b - (b >> 63 << 64), a, c, weight, *rest, piece, bucket, k1, k2))
        yield _table(rows, _PART)
        give_back()


_FOUND = pa.schema([("bucket", pa.int64()), ("k1", pa.int64()), ("k2", pa.int64()), ("hi", pa.int32()), ("lo", pa.int32())])


def split_here(group: list[tuple], most: int) -> Iterator[list[tuple]]:
    """Parts (weight, lead, text, classes) of one bucket, by the steps of ``_dealt_out``: buckets of at most ``most`` parts, of which some string may repeat."""
    todo = [(0, 0, group)]
    while todo:
        left, right, group = todo.pop()
        if len(group) <= most:
            if sum(x[0] for x in group) > 1:
                yield group
            continue
        parts: dict[tuple, dict[tuple, list]] = {}
        for weight, lead, text, classes in group:
            for b, at, *known, piece in parts_of(0, lead, left, right, text):
                part = parts.setdefault((b, *known), {}).setdefault((at, piece), [0, []])
                part[0] += weight
                part[1] += classes
        todo += [(*known, [(w, at, piece, classes) for (at, piece), (w, classes) in own.items()]) for (_, *known), own in parts.items()]


def _sorted_buckets(most: int):
    """Classes in order of (bucket, key) -> their repeated strings as runs of offsets hi..lo from the anchor, a block of whole buckets
    at a time. A bucket of more than ``most`` classes is split first."""

    def done(block: list[list[tuple]]) -> pa.RecordBatch:
        weight, lead, text, classes = zip(*(x for group in block for x in group), strict=True)
        flags = repeated_starts(list(text), np.repeat(np.arange(len(block)), [len(group) for group in block]), np.array(lead, np.int64), np.array(weight, np.int64))
        out = []
        for own, a, f in zip(classes, lead, flags, strict=True):
            edge = np.diff(np.concatenate(([0], f.view(np.int8), [0])))
            runs = list(zip(np.flatnonzero(edge == 1).tolist(), np.flatnonzero(edge == -1).tolist(), strict=True))
            out += [(*c, a - s, a - e + 1) for c in own for s, e in runs]
        return _table(out, _FOUND)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        let_go()
        block, size = [], 0

        def groups() -> Iterator[list[tuple]]:
            bucket: list[tuple] = []
            for batch in batches:
                for row in zip(*(batch.column(k).to_pylist() for k in range(6)), strict=True):
                    if bucket and row[:3] == bucket[-1][3][0]:
                        continue  # a row that stands in the table twice gives its texts twice
                    if bucket and row[0] != bucket[-1][3][0][0]:
                        yield from split_here(bucket, most) if len(bucket) > most else [bucket]
                        bucket = []
                    bucket.append((*row[3:], [row[:3]]))
                give_back()
            if bucket:
                yield from split_here(bucket, most) if len(bucket) > most else [bucket]

        for group in groups():
            block.append(group)
            size += sum(len(x[2]) + 64 for x in group)
            if size > BLOCK_BYTES:
                yield done(block)
                block, size = [], 0
        if block:
            yield done(block)

    return run


def _cut_texts(keep: bool):
    """Rows are cut a few megabytes at a time, so a batch's texts and what is left of them are never held at once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        let_go()
        kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.binary()]
        for batch in batches:
            data, offsets = text_buffer(batch.column(1))
            view, spans = memoryview(data), batch.column(2)
            for i, j in spans_of_bytes(offsets, 2 << 20):
                rows = []
                for k in range(i, j):
                    text = bytes(view[offsets[k] : offsets[k + 1]])
                    own = spans[k]
                    left, n = cut_text(text, [(x["s"], x["e"]) for x in own.as_py()]) if own.is_valid else (text, 0)
                    rows.append((len(text), len(text) - len(left), n, hashlib.sha256(left).hexdigest(), left if keep else None))
                columns = [pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, j - i), *columns], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"])
            give_back()

    return run


def word_codes(data: np.ndarray, offsets: np.ndarray) -> list[bytes]:
    """For each text the codes of its pairs of neighbouring words (runs of bytes other than ASCII white space)."""
    out: list[bytes] = []
    for i, j in spans_of_bytes(offsets, PIECE):
        at = offsets[i : j + 1] - offsets[i]
        b = data[offsets[i] : offsets[j]]
        edge = np.zeros(len(b) + 1, bool)
        edge[at] = True
        word = np.concatenate(([False], ~_SPACE[b], [False]))
        start = np.flatnonzero(word[1:-1] & (~word[:-2] | edge[:-1]))
        end = np.flatnonzero(word[1:-1] & (~word[2:] | edge[1:])) + 1
        w = mix(range_hash(prefix_sums(b), start, end) + (end - start).astype(np.uint64) * _FACTORS[2])
        code = mix(w[:-1] * _FACTORS[0] + w[1:] * _FACTORS[1])
        first = np.searchsorted(start, at).tolist()
        out += [code[lo : max(lo, hi - 1)].tobytes() for lo, hi in zip(first[:-1], first[1:], strict=True)]
    return out


def _coded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    let_go()
    for batch in batches:
        data, offsets = text_buffer(batch.column(2))
        for i, j in spans_of_bytes(offsets, 2 << 20):
            codes = pa.array(word_codes(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]), pa.binary())
            yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, j - i), batch.column(1).slice(i, j - i), codes], names=["doc_id", "tk", "text"])
        give_back()


def repeated_passages(docs: DataFrame) -> DataFrame:
    """``(doc_id, tk, s, e)``: the windows of 51 words that start at words s..e of that row repeat elsewhere."""
    found = repeated_intervals(cut(docs.select("doc_id", "tk", "text").mapInArrow(_coded, "doc_id long, tk long, text binary")))
    # only starts at whole codes are words
    words = found.select("doc_id", "tk", F.ceil(F.col("s") / CODE).alias("s"), F.floor(F.col("e") / CODE).alias("e"))
    return words.where("s <= e")


def repeated_intervals(docs: DataFrame) -> DataFrame:
    """``(doc_id, tk, s, e)``: string starts s..e of the row with that id and text key repeat elsewhere."""
    docs = small_batches(docs)
    runs = docs.select("doc_id", "tk", "text").mapInArrow(_runs, "gram long, k1 long, k2 long, doc_id long, tk long, loc long")
    often = docs.select("text").mapInArrow(_grams, "gram long").groupBy("gram").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("gram")
    often = cut(often)
    shared = cut(runs.join(often.hint("merge"), "gram", "left_semi"))
    first = F.min(F.struct(F.xxhash64("doc_id", "tk", "loc"), "doc_id", "tk", "loc")).alias("one")
    classes = cut(shared.groupBy("gram", "k1", "k2").agg(F.count(F.lit(1)).alias("weight"), first).select("gram", "k1", "k2", "weight", "one.doc_id", "one.tk", "one.loc"))
    large = cut(classes.groupBy("gram").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > IN_TASK * BUCKET_CLASSES).select("gram", F.lit(True).alias("large")))
    wanted = classes.join(large.hint("merge"), "gram", "left").select("doc_id", "tk", F.struct("gram", "k1", "k2", "weight", F.coalesce("large", F.lit(False)).alias("many"), "loc").alias("w"))
    by_doc = cut(wanted.groupBy(F.col("doc_id").alias("d2"), F.col("tk").alias("t2")).agg(F.collect_list("w").alias("w")))
    holders = marked(docs.select("doc_id", "tk", "text"), marks(by_doc, "t2"), "tk").where("hit")
    joined = holders.select("doc_id", "tk", "text").join(by_doc.hint("merge"), F.col("doc_id").eqNullSafe(F.col("d2")) & (F.col("tk") == F.col("t2")))
    slices = cut(joined.select("doc_id", "tk", "text", "w").mapInArrow(_slices, f"{_DDL}, many boolean"))
    sorting, links = slices.where("not many").drop("many"), []
    if not large.isEmpty():
        parts, links = _dealt_out(slices.where("many").drop("many").dropDuplicates(["bucket", "k1", "k2"]))
        sorting = sorting.unionByName(parts)
    sorting = sorting.select("bucket", "k1", "k2", "weight", "lead", "bytes").repartition("bucket").sortWithinPartitions("bucket", "k1", "k2")
    found = sorting.mapInArrow(_sorted_buckets(BUCKET_CLASSES), "bucket long, k1 long, k2 long, hi int, lo int")
    key = ["bucket", "k1", "k2"]
    found = cut(found)
    for table in reversed(links):  # what holds for a part holds for the classes it was cut from; buckets of two steps never bear one name
        up = found.join(table.hint("merge"), key).select(F.col("from_bucket").alias("bucket"), F.col("from_k1").alias("k1"), F.col("from_k2").alias("k2"), "hi", "lo")
        found = cut(found.unionByName(up).distinct())
    found = found.withColumnRenamed("bucket", "gram")
    anchor = F.shiftright("loc", 16) + F.col("loc").bitwiseAND(255)
    return shared.join(found.hint("merge"), ["gram", "k1", "k2"]).select("doc_id", "tk", (anchor - F.col("hi")).alias("s"), (anchor - F.col("lo")).alias("e"))


def _dealt_out(large: DataFrame) -> tuple[DataFrame, list[DataFrame]]:
    """Classes of large buckets -> classes of buckets of bounded size, and the tables that lead back, one a step.

    A part that is alone has no repeat and goes. At most eight steps: the bytes not yet known halve in each.
    """
    small, links = None, []
    while True:
        parts = cut(large.mapInArrow(_split, f"{_DDL}, from_bucket long, from_k1 long, from_k2 long"))
        links.append(parts.select("bucket", "k1", "k2", "from_bucket", "from_k1", "from_k2"))
        same = [F.first(c).alias(c) for c in ("lead", "left", "right", "bytes")]
        merged = cut(parts.groupBy("bucket", "k1", "k2").agg(F.sum("weight").alias("weight"), *same))
        sizes = cut(merged.groupBy("bucket").agg(F.count(F.lit(1)).alias("n"), F.sum("weight").alias("all")).where("all > 1").select("bucket", "n"))
        sized = merged.join(sizes.hint("merge"), "bucket")
        few = sized.where(F.col("n") <= BUCKET_CLASSES).drop("n")
        small = few if small is None else small.unionByName(few)
        if sizes.where(F.col("n") > BUCKET_CLASSES).isEmpty():
            return small, links
        large = sized.where(F.col("n") > BUCKET_CLASSES).drop("n")


def remove_repeats(docs: DataFrame, keep: bool = True) -> DataFrame:
    """Cut every byte of ``docs(doc_id long, text string, ...)`` that lies in a 400-byte string starting twice or more.

    Returns ``doc_id, n_bytes, n_removed, n_spans, kept_sha256, kept binary``, a row for each input row. Strings never cross documents and are judged on the input. Null and short texts lose
    nothing; rows that repeat a document repeat its strings; a null doc_id is a document like any other. Other
    columns are ignored; an empty table gives an empty result. ``kept`` is null unless asked for by ``keep`` and may not be valid UTF-8 where a cut splits a
    character.
    """
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    rows = with_spans(docs.select(F.col("doc_id").cast("long").alias("doc_id"), text.alias("text")))
    out = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary"
    return rows.select("row.doc_id", "row.text", SPANS).mapInArrow(_cut_texts(keep), out)


SPANS = "_repeated"


def with_spans(docs: DataFrame, passages: bool = False) -> DataFrame:
    """``row`` (a struct of the columns of ``docs``) and ``SPANS``, the string-start intervals (s, e) that repeat elsewhere, null where there are none.

    With ``passages`` there are intervals of 51-word windows too, counted in words and marked by ``words``.
    Rows without a repeat are told by a bit map and stay where they are; only the others meet their spans in a join.
    """
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    keyed = docs.select(F.struct("*").alias("row"), F.col("doc_id").cast("long").alias("id"), F.xxhash64(text).alias("tk"))
    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(text).alias("tk"), text.alias("text"))
    found = repeated_intervals(slim).withColumn("words", F.lit(False))
    if passages:
        found = found.unionByName(repeated_passages(slim).withColumn("words", F.lit(True)))
    spans = found.groupBy("doc_id", "tk").agg(F.collect_set(F.struct("s", "e", "words")).alias(SPANS))
    spans = cut(spans.select(F.col("doc_id").alias("d2"), F.col("tk").alias("t2"), SPANS))
    split = marked(keyed, marks(spans, "t2"), "tk")
    alone = split.where("not hit").select("row", F.lit(None).cast("array<struct<s:bigint,e:bigint,words:boolean>>").alias(SPANS))
    met = split.where("hit").join(spans.hint("merge"), F.col("id").eqNullSafe(F.col("d2")) & (F.col("tk") == F.col("t2")), "left")
    return alone.unionByName(met.select("row", SPANS))


def cut_text(text: bytes, spans: list[tuple[int, int]]) -> tuple[bytes, int]:
    """What is left of ``text`` without the strings that start in ``spans``, and the number of runs cut out."""
    gone: list[list[int]] = []
    for s, e in sorted((s, e + LENGTH) for s, e in spans):
        if gone and s <= gone[-1][1]:
            gone[-1][1] = max(gone[-1][1], e)
        else:
            gone.append([s, e])
    edges = [0, *(x for g in gone for x in g), len(text)]
    return b"".join(text[a:b] for a, b in zip(edges[::2], edges[1::2], strict=True)), len(gone)


def _byte_spans(text: bytes, spans: list) -> list[tuple[int, int]]:
    """All spans as starts of strings in bytes; a word span ends where its last window does."""
    words = [m.span() for m in _WORD.finditer(text)] if any(x["words"] for x in spans) else []
    return [(words[x["s"]][0], words[x["e"] + PASSAGE_WORDS - 1][1] - LENGTH) if x["words"] else (x["s"], x["e"]) for x in spans]


def _without(place: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        let_go()
        for batch in batches:
            texts = []
            for text, own in zip(batch.column(place), batch.column(batch.num_columns - 1), strict=True):
                raw = text.as_py().encode()
                texts.append(cut_text(raw, _byte_spans(raw, own.as_py()))[0].decode("utf-8", "ignore"))
            columns = batch.columns[:-1]
            columns[place] = pa.array(texts, batch.schema.field(place).type)
            yield pa.RecordBatch.from_arrays(columns, schema=pa.schema(list(batch.schema)[:-1]))
            give_back()

    return run


def without_repeats(docs: DataFrame) -> DataFrame:
    """``docs`` with repeated passages (400 bytes or 51 words) cut from ``text`` (halves of characters at a cut go too) and n_chars, if any, set anew."""
    rows = with_spans(docs, passages=True)
    rest = rows.where(F.col(SPANS).isNull()).select("row.*")
    name = SPANS
    while name in docs.columns:
        name += "_"
    own = [F.col(f"row.`{c}`").cast("string").alias(c) if c == "text" else F.col(f"row.`{c}`") for c in docs.columns]
    found = rows.where(F.col(SPANS).isNotNull()).select(*own, F.col(SPANS).alias(name))
    hit = found.mapInArrow(_without(docs.columns.index("text")), found.drop(name).schema)
    if "n_chars" in docs.columns:
        hit = hit.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))
    return rest.unionByName(hit)
