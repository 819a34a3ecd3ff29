"""Each stage of the pipeline against brute force on its own input, and the whole on awkward rows."""

import numpy as np
import pytest

import corpus_pipeline
from blockpress.llm.common import stored

STAGE = dict(corpus_pipeline.STAGES)
COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


@pytest.fixture(scope="module")
def stages(spark, small):
    """The documents and what each stage but the last makes of them."""
    docs = spark.read.parquet(f"{small}/documents.parquet")
    out = [docs]
    for _, stage in corpus_pipeline.STAGES[:-1]:
        out.append(stored(stage(spark, out[-1], small), "stage"))
    return out


def texts(df):
    return {r.doc_id: r.text for r in df.collect()}


def shingles(text, k=5):
    w = (text or "").lower().split()
    return {tuple(w[i : i + k]) for i in range(max(1, len(w) - k + 1))} if w else set()


def test_columns_stay(stages):
    assert all(s.columns == COLUMNS for s in stages)


def test_language_keeps_clean_documents(stages):
    before, after = texts(stages[0]), texts(stages[1])
    assert after.items() <= before.items() and len(after) >= 0.98 * len(before)


def test_near_duplicates_leave_one(stages):
    before, after = texts(stages[1]), texts(stages[2])
    assert after.items() <= before.items()
    sets = {k: shingles(t) for k, t in before.items()}
    like = lambda a, b: len(sets[a] & sets[b]) / max(1, len(sets[a] | sets[b]))
    for a in after:
        assert not any(a < b and like(a, b) >= 0.85 for b in after)
    for gone in before.keys() - after.keys():  # nothing goes without a likeness that stays before it in a chain
        assert max(like(gone, other) for other in before if other != gone) >= 0.6


def test_repeats_go(stages):
    before, after = texts(stages[2]), texts(stages[3])
    assert before.keys() == after.keys()
    raw = {k: t.encode() for k, t in before.items()}
    seen: dict = {}
    for t in raw.values():
        for i in range(len(t) - 199):
            seen[t[i : i + 200]] = seen.get(t[i : i + 200], 0) + 1
    for k, t in raw.items():
        gone = np.zeros(len(t), bool)
        for i in range(len(t) - 199):
            if seen[t[i : i + 200]] > 1:
                gone[i : i + 200] = True
        left, at = [], 0
        for ch in before[k]:
            n = len(ch.encode())
            if not gone[at : at + n].any():
                left.append(ch)
            at += n
        assert after[k] == "".join(left)


def test_leaks_go(stages, spark, small):
    before, after = texts(stages[3]), texts(stages[4])
    items = [r.text.lower().split() for r in spark.read.parquet(f"{small}/benchmark.parquet").collect()]
    clean = lambda ws: [w.strip(".,") for w in ws]
    grams = {tuple(clean(w)[i : i + 13]) for w in items for i in range(len(w) - 12)}
    for k, t in before.items():
        w = clean(t.lower().split())
        if any(tuple(w[i : i + 13]) in grams for i in range(len(w) - 12)):
            assert k not in after
    assert len(after) >= 0.9 * len(before)


def test_packing_holds_what_is_left(stages, spark, small):
    rows = STAGE["best-fit packing"](spark, stages[4], small).collect()
    assert {r.doc_id for r in rows} == set(texts(stages[4]))
    bins: dict = {}
    for r in rows:
        bins.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for parts in bins.values():
        at = 0
        for off, n in sorted(parts):
            assert off == at
            at += n
        assert at <= 2048


def test_run(spark, small, stages):
    assert {r.doc_id for r in corpus_pipeline.run(spark, small).collect()} == set(texts(stages[4]))


def test_awkward_rows(spark, small):
    base = "the quick brown fox jumps over the lazy dog while many other small animals look on from green hills " * 4
    rows = [(0, None, None, None, None), (1, "", "en", "s", 0), (2, base, "en", "s", 1), (2, base, "en", "s", 1), (None, base + " x", "en", "s", 1), (3, base.replace("fox", "cat"), "en", None, 1), (4, "été " * 3, "fr", "t", 12)]
    docs = spark.createDataFrame([(*r, "u") for r in rows], "doc_id long, text string, lang string, source string, n_chars long, component_id string")
    for _, stage in corpus_pipeline.STAGES[:-1]:
        docs = stored(stage(spark, docs, small), "awkward")
        assert docs.columns[-1] == "component_id"
    assert corpus_pipeline.STAGES[-1][1](spark, docs, small).count() > 0
    empty = docs.limit(0)
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, empty, small).count() == 0
