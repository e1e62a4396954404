"""All five stages over odd rows, each held against a brute-force version on its own input."""

import hashlib
import re
from collections import Counter

import pytest
import tokenizers

import corpus_pipeline
from test_dedup import classes
from wavefront.llm import toxicity
from wavefront.llm.queries import tokenizer_path

LABELS = "doc_id long, quality int, toxic int"


@pytest.fixture(scope="module")
def staged(spark, docs, tmp_path_factory):
    """The output of every stage, written and read again."""
    base = str(tmp_path_factory.mktemp("corpus"))
    toxic = [(500 + k, f"plain words number {k} " + "vile scum idiot " * (k % 2) + f"and more of {k * 7}", "xx", "a", 0, "clash", "clash", "clash") for k in range(260)]
    rows = docs.unionByName(spark.createDataFrame(toxic, docs.schema))
    rows.write.parquet(f"{base}/documents.parquet")
    spark.createDataFrame([(500 + k, 1, k % 2) for k in range(240)], LABELS).write.parquet(f"{base}/labels.parquet")
    out = [("documents", spark.read.parquet(f"{base}/documents.parquet"))]
    for name, stage in corpus_pipeline.STAGES:
        stage(spark, out[-1][1], base).write.parquet(f"{base}/{name}")
        out.append((name, spark.read.parquet(f"{base}/{name}")))
    return base, dict(out)


def rows_of(df):
    return sorted(map(str, df.collect()))


def test_columns_stay(staged):
    frames = staged[1]
    assert all(frames[n].columns == frames["documents"].columns for n in ("toxicity", "near_duplicates", "suffix_dedup", "mixing"))


def test_toxic_rows_go(spark, staged):
    base, frames = staged
    want = toxicity.grade_documents(frames["documents"], spark.read.parquet(f"{base}/labels.parquet")).where("not toxic")
    assert sorted(r["doc_id"] or -1 for r in frames["toxicity"].collect()) == sorted(r["doc_id"] or -1 for r in want.collect())
    left = {r["doc_id"] for r in frames["toxicity"].collect()}
    assert not left & {501 + 2 * k for k in range(130)} and left >= {500 + 2 * k for k in range(130)} | {1, 5, 6, None}


def test_one_of_a_class_stays(staged):
    frames = staged[1]
    before = frames["toxicity"].collect()
    least = classes([(r["doc_id"], r["text"]) for r in before], 80)
    want = sorted(str(r) for r in before if r["doc_id"] is None or least[r["doc_id"]] == r["doc_id"])
    assert rows_of(frames["near_duplicates"]) == want


def test_repeats_are_cut(staged):
    """Bytes under a 400-byte string or a window of 51 words that starts twice or more go."""
    frames = staged[1]
    before = frames["near_duplicates"].select("doc_id", "text").collect()
    raw = [(r["text"] or "").encode() for r in before]
    words = [list(re.finditer(rb"[^\x20\x09-\x0d]+", t)) for t in raw]
    strings = Counter(t[k : k + 400] for t in raw for k in range(len(t) - 399))
    windows = Counter(tuple(m[0] for m in w[k : k + 51]) for w in words for k in range(len(w) - 50))
    want = []
    for r, t, w in zip(before, raw, words, strict=True):
        gone = bytearray(len(t))
        for k in range(len(t) - 399):
            if strings[t[k : k + 400]] > 1:
                gone[k : k + 400] = b"\1" * 400
        for k in range(len(w) - 50):
            if windows[tuple(m[0] for m in w[k : k + 51])] > 1:
                a, b = w[k].start(), w[k + 50].end()
                gone[a:b] = b"\1" * (b - a)
        left = bytes(x for x, g in zip(t, gone, strict=True) if not g).decode("utf-8", "ignore")
        want.append((r["doc_id"] or -1, left if r["text"] is not None else None))
    got = [(r["doc_id"] or -1, r["text"]) for r in frames["suffix_dedup"].select("doc_id", "text").collect()]
    assert sorted(map(str, got)) == sorted(map(str, want))
    assert sum(x != y for x, y in zip(sorted(map(str, got)), sorted(str((r["doc_id"] or -1, r["text"])) for r in before), strict=True)) > 0


def test_the_mix_takes_whole_documents(staged):
    frames = staged[1]
    before, after = Counter(map(str, frames["suffix_dedup"].collect())), Counter(map(str, frames["mixing"].collect()))
    assert after and set(after) <= set(before) and all(n <= 3 * before[k] for k, n in after.items())


def test_encoding_of_what_is_left(staged):
    frames = staged[1]
    lib = tokenizers.Tokenizer.from_file(tokenizer_path())
    want = Counter()
    for r in frames["mixing"].select("doc_id", "text").collect():
        ids = lib.encode(r["text"] or "", add_special_tokens=False).ids
        want[r["doc_id"], len(ids), hashlib.sha256(b"".join(i.to_bytes(4, "little") for i in ids)).hexdigest()] += 1
    assert Counter((r["doc_id"], r["n_tokens"], r["ids_sha256"]) for r in frames["bpe"].collect()) == want


def test_run_is_the_stages_in_turn(spark, staged):
    base, frames = staged
    assert rows_of(corpus_pipeline.run(spark, base)) == rows_of(frames["bpe"])


def test_empty_tables(spark, staged, tmp_path):
    frames = staged[1]
    frames["documents"].limit(0).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([], LABELS).write.parquet(f"{tmp_path}/labels.parquet")
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0
