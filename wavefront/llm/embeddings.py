"""Near-duplicate vectors: random-hyperplane sign hashing in several tables, exact cosines, connected components.

A table's key is the signs of k hyperplane products; two vectors at cosine c agree on a sign with probability
1 - acos(c)/pi. k follows log2 of the number of vectors, so buckets keep their size, and the number of tables follows
from k and the recall wanted at the threshold. A bucket's vectors meet in one task and their exact cosines come from
blocks of matrix products, so no pair is ever a row: a task returns a vector's new links as a count and its least
reachable partner as one edge. A pair that also met in an earlier table is counted there (each vector carries all
its keys, so that is one comparison). A bucket of more than ``CHUNK`` vectors is dealt into chunks and every pair of
chunks is a task of its own.

Rows of one vector are one class with a count, known by a digest of the normalised vector; only a representative goes
on, so a vector that recurs a million times is one row of its buckets.
"""

from __future__ import annotations

import functools
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wavefront.llm.workers import give_back, let_go, small_batches
from wavefront.operators.components import connected_components
from wavefront.session import cut

CHUNK = 1024
MISS = 0.002
HOT_ROWS = 100_000
SEED = 20240607


def layout(vectors: int, threshold: float, miss: float = MISS) -> tuple[int, int]:
    """(bits a key, tables)."""
    bits = max(4, min(30, int(math.log2(max(vectors, 2))) - 4))
    hit = (1 - math.acos(threshold) / math.pi) ** bits
    return bits, math.ceil(math.log(miss) / math.log(1 - hit))


@functools.cache
def planes(size: int, bits: int, tables: int) -> np.ndarray:
    return np.random.Generator(np.random.PCG64([SEED, size])).standard_normal((size, bits * tables))


def _usable(column: pa.Array) -> tuple[list[int], list[np.ndarray]]:
    rows, out = [], []
    for k, x in enumerate(column):
        values = x.values if x.is_valid else None
        if values is None or len(values) == 0 or values.null_count:
            continue
        v = np.asarray(values.to_numpy(zero_copy_only=False), np.float64)
        if np.isfinite(v).all() and v.any():
            rows.append(k)
            out.append(v)
    return rows, out


def _normalised(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(vec_id, embedding) -> (vec_id, size, h1, h2, unit) for usable vectors; unit: the normalised components as doubles."""
    let_go()
    for batch in batches:
        rows, vectors = _usable(batch.column(1))
        units = []
        for v in vectors:
            v = v / np.abs(v).max()
            units.append((v / np.linalg.norm(v)).tobytes())
        digest = np.frombuffer(b"".join(xxhash.xxh3_128_digest(u) for u in units), "<i8").reshape(-1, 2)
        yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(rows, pa.int64())), pa.array([len(v) for v in vectors], pa.int32()), pa.array(digest[:, 0].copy(), pa.int64()), pa.array(digest[:, 1].copy(), pa.int64()), pa.array(units, pa.binary())], names=["vec_id", "size", "h1", "h2", "unit"])
        give_back()


def _keyed(bits: int, tables: int):
    """(rep, weight, size, unit) -> a row for each table."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        let_go()
        turn = 1 << np.arange(bits, dtype=np.int64)
        for whole in batches:
            for at in range(0, whole.num_rows, 500):
                batch = whole.slice(at, 500)
                by_size: dict[int, list[int]] = {}
                for k, size in enumerate(batch.column(2).to_pylist()):
                    by_size.setdefault(size, []).append(k)
                for size, found in by_size.items():
                    part = batch.take(pa.array(found))
                    x = np.frombuffer(b"".join(part.column(3).to_pylist()), np.float64).reshape(len(found), size)
                    sign = (x @ planes(size, bits, tables) > 0).reshape(len(found), tables, bits)
                    sig = (sign * turn).sum(axis=2)
                    key = (np.tile(np.arange(tables), len(found)) << 40) | sig.ravel()
                    each = pa.array(np.repeat(np.arange(len(found)), tables))
                    body = [r.tobytes() for r in np.concatenate([x.view(np.uint8).reshape(len(found), -1), sig.astype("<i4").view(np.uint8).reshape(len(found), -1)], axis=1)]
                    yield pa.RecordBatch.from_arrays([pa.array(key), part.column(2).take(each), part.column(0).take(each), part.column(1).take(each), pa.array(body, pa.binary()).take(each)], names=["key", "size", "rep", "weight", "body"])
            give_back()

    return run


def _labels(n: int, i: np.ndarray, j: np.ndarray, start: np.ndarray) -> np.ndarray:
    """The least ``start`` reachable over the links i-j."""
    label = start.copy()
    while True:
        new = label.copy()
        np.minimum.at(new, i, label[j])
        np.minimum.at(new, j, new[i])
        if (new == label).all():
            return label
        label = new


def _links(threshold: float, tables: int):
    def meet(key: int, size: int, a: int, b: int, ids: list[int], weights: list[int], chunk: list[int], body: list[bytes]) -> tuple[np.ndarray, ...]:
        raw = np.frombuffer(b"".join(body), np.uint8).reshape(len(body), -1)
        x = raw[:, : 8 * size].copy().view(np.float64)
        sig = raw[:, 8 * size :].copy().view("<i4")
        who, side, table, many = np.array(ids, np.int64), np.array(chunk), key >> 40, np.array(weights, float)
        left, right = (np.flatnonzero(side == a), np.flatnonzero(side == b))
        found_i, found_j = [np.empty(0, np.int64)], [np.empty(0, np.int64)]
        for p in range(0, len(left), 512):
            part = left[p : p + 512]
            i, j = np.nonzero(x[part] @ x[right].T >= threshold)
            i, j = part[i], right[j]
            ok = (i < j) if a == b else np.ones(len(i), bool)
            ok &= who[i] != who[j]
            found_i.append(i[ok])
            found_j.append(j[ok])
        i, j = np.concatenate(found_i), np.concatenate(found_j)
        if not len(i):
            return np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0, np.int64)
        new = np.ones(len(i), bool)
        for k in range(0, len(i), 1 << 16):
            new[k : k + (1 << 16)] = ~(sig[i[k : k + (1 << 16)], :table] == sig[j[k : k + (1 << 16)], :table]).any(axis=1)
        count = (np.bincount(i[new], many[j[new]], len(who)) + np.bincount(j[new], many[i[new]], len(who))).astype(np.int64)
        label = _labels(len(who), i, j, who)
        some = np.zeros(len(who), bool)
        some[i] = some[j] = True
        return who[some], count[some], label[some]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now: tuple | None = None
        held: tuple[list, list, list, list] = ([], [], [], [])
        out: list[tuple[np.ndarray, ...]] = []

        def flush() -> pa.RecordBatch:
            columns = [np.concatenate([o[k] for o in out]) if out else np.empty(0, np.int64) for k in range(3)]
            out.clear()
            return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], names=["rep", "n", "least"])

        let_go()
        for batch in batches:
            for *group, vec, weight, chunk, body in zip(*(batch.column(k).to_pylist() for k in range(8)), strict=True):
                if now != (group := tuple(group)):
                    if now and len(held[0]) > 1:
                        out.append(meet(*now, *held))
                    now, held = group, ([], [], [], [])
                for column, value in zip(held, (vec, weight, chunk, body), strict=True):
                    column.append(value)
            yield flush()
        if now and len(held[0]) > 1:
            out.append(meet(*now, *held))
        yield flush()

    return run


def near_vectors(vectors: DataFrame, threshold: float = 0.9) -> DataFrame:
    """Links of cosine >= threshold between rows of ``vectors(vec_id long, embedding array<float|double>, ...)``.

    Returns ``vec_id, n_links, component_id, kept``, a row for each input row. Vectors of different lengths are not
    compared; null, empty and zero vectors and those with null or non-finite components link with nothing, and so do
    rows with a null vec_id (their component is null). Rows that repeat a vec_id are not linked to each other and
    share the counts and component of that id. Other columns are ignored; an empty table gives an empty result. Links
    found are exact; a pair at the threshold is missed with probability ``MISS`` or less, nearer pairs far less.
    """
    rows = small_batches(vectors).select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("embedding"))
    units = cut(rows.where("vec_id is not null").mapInArrow(_normalised, "vec_id long, size int, h1 long, h2 long, unit binary"))
    # an id that stands in several rows is a class of its own for each of its vectors: those are not linked to each other
    often = units.groupBy("vec_id").agg(F.count(F.lit(1)).alias("m")).where("m > 1").select("vec_id", F.col("vec_id").alias("own"))
    member = cut(units.drop("unit").join(often.hint("merge"), "vec_id", "left"))
    alike = ["size", "h1", "h2", "own"]
    classes = cut(member.groupBy(*alike).agg(F.min("vec_id").alias("rep"), F.count(F.lit(1)).alias("weight")))
    bodies = units.groupBy("size", "h1", "h2").agg(F.first("unit").alias("unit"))
    one = classes.join(bodies.hint("merge"), ["size", "h1", "h2"]).select("rep", "weight", "size", "unit")
    bits, tables = layout(classes.count(), threshold)
    keyed = one.mapInArrow(_keyed(bits, tables), "key long, size int, rep long, weight long, body binary")
    hot = cut(keyed.groupBy("key", "size").agg(F.count(F.lit(1)).alias("m")).where(F.col("m") > CHUNK))
    hot = hot.select("key", "size", F.ceil(F.col("m") / CHUNK).cast("int").alias("q"))
    dealt = keyed.join(F.broadcast(hot) if hot.count() <= HOT_ROWS else hot.hint("merge"), ["key", "size"], "left")
    q = F.coalesce("q", F.lit(1))
    dealt = dealt.withColumn("c", F.pmod(F.xxhash64("rep"), q).cast("int")).withColumn("o", F.explode(F.sequence(F.lit(0), q - 1)))
    dealt = dealt.select("key", "size", F.least("c", "o").alias("a"), F.greatest("c", "o").alias("b"), "rep", "weight", "c", "body")
    group = ["key", "size", "a", "b"]
    found = cut(dealt.repartition(*group).sortWithinPartitions(*group).mapInArrow(_links(threshold, tables), "rep long, n long, least long"))
    met = cut(found.groupBy("rep").agg(F.sum("n").alias("n")))
    joined = found.select(F.col("rep").alias("u"), F.col("least").alias("v")).where("u <> v").distinct()
    component = cut(connected_components(joined))
    # the rows of a class link one another, but for the rows of one id
    inner = F.when(F.col("own").isNull(), F.col("weight") - 1).otherwise(F.lit(0))
    known = classes.join(met.hint("merge"), "rep", "left").join(component.withColumnRenamed("node", "rep").hint("merge"), "rep", "left")
    known = cut(known.select(*alike, (F.coalesce("n", F.lit(0)) + inner).alias("n"), F.coalesce("component", "rep").alias("component")))
    plain = member.where("own is null").join(known.where("own is null").drop("own").hint("merge"), ["size", "h1", "h2"]).select("vec_id", "n", "component")
    repeated = known.where("own is not null").groupBy(F.col("own").alias("vec_id")).agg(F.max("n").alias("n"), F.min("component").alias("component"))
    labels = cut(plain.unionByName(repeated))
    out = rows.select("vec_id").join(labels.hint("merge"), "vec_id", "left")
    one_id = F.coalesce("component", "vec_id")
    return out.select("vec_id", F.coalesce("n", F.lit(0)).cast("long").alias("n_links"), one_id.alias("component_id"), F.col("vec_id").eqNullSafe(one_id).alias("kept"))
