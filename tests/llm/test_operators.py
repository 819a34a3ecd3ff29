"""Each corpus operator against brute force, and on awkward rows."""

import hashlib
import re
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
import xxhash

from blockpress.llm import queries as Q

DOCS = "doc_id long, text string, lang string, source string, n_chars long, uid string, core string"
BASE = "Über the quick brown fox jumps over the lazy dog while many other small animals look on from the wet green hills nearby; " * 3


def awkward():
    """Null, empty and long texts, ties, repeated rows, clashing further columns."""
    texts = [None, "", " ", "one", "a b", BASE, BASE, BASE + " and a little more", "xx " * 400, "é" * 300, "x" + BASE[1:], BASE.replace("fox", "cat")]
    rows = [(k, t, "en", "src1", None, "clash", "clash") for k, t in enumerate(texts)]
    return rows + [rows[5], (None, BASE, None, None, 3, None, None), (77, "tail text without repeats " + "".join(map(str, range(200))), "en", "s", 1, "", "")]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(awkward(), DOCS).repartition(3).cache()


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], DOCS)


# 1: suffix-array dedup


def removed(texts, length=200):
    raw = [(t or "").encode() for t in texts]
    seen = Counter(t[i : i + length] for t in raw for i in range(len(t) - length + 1))
    out = []
    for t in raw:
        gone = np.zeros(len(t), bool)
        for i in range(len(t) - length + 1):
            if seen[t[i : i + length]] > 1:
                gone[i : i + length] = True
        runs = int((np.diff(np.concatenate([[0], gone.astype(int)])) == 1).sum())
        out.append((len(t), int(gone.sum()), runs, hashlib.sha256(bytes(np.frombuffer(t, np.uint8)[~gone])).hexdigest()))
    return out


def digests(df):
    return Counter((r.doc_id, r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in df.collect())


@pytest.mark.parametrize("limit", [600, 1])
def test_suffix_dedup_awkward(docs, monkeypatch, limit):
    from blockpress.llm import suffix_dedup as S

    monkeypatch.setattr(S, "CORE_CONTEXTS", limit)  # 1: contexts are cut into runs
    rows = awkward()
    want = Counter((r[0], *x) for r, x in zip(rows, removed([r[1] for r in rows]), strict=True))
    assert digests(S.removal_digests(docs)) == want


@pytest.mark.parametrize("limit", [600, 2])
def test_suffix_dedup_random(spark, monkeypatch, limit):
    """Random pieces strung together, with few letters: repeats of every length around the limit."""
    from blockpress.llm import suffix_dedup as S

    monkeypatch.setattr(S, "CORE_CONTEXTS", limit)
    rng = np.random.default_rng(3)
    pool = ["".join(rng.choice(list("ab"), rng.integers(20, 260))) for _ in range(12)]
    texts = ["".join(pool[j] for j in rng.integers(0, 12, rng.integers(1, 8))) for _ in range(60)] + ["a" * 500, "ab" * 300, "a" * 199, "a" * 200]
    df = spark.createDataFrame([(k, t) for k, t in enumerate(texts)], "doc_id long, text string")
    want = Counter((k, *x) for k, x in enumerate(removed(texts)))
    assert digests(S.removal_digests(df)) == want


def test_suffix_dedup_empty(empty):
    from blockpress.llm.suffix_dedup import removal_digests, without_repeats

    assert removal_digests(empty).count() == 0
    assert without_repeats(empty).count() == 0


def test_suffix_dedup_texts(docs):
    from blockpress.llm.suffix_dedup import without_repeats

    out = without_repeats(docs)
    assert out.columns == docs.columns
    texts = [r.text for r in out.collect() if r.doc_id == 77]
    assert texts == [awkward()[-1][1]]
    assert all(len(r.text) == r.n_chars for r in out.collect())


def test_full_suffix_array_order(spark):
    """Ranks against a plain sort, by the bytes that the last level's names stand for."""
    from blockpress.llm import suffix_array as A

    rng = np.random.default_rng(5)
    texts = sorted({"".join(rng.choice(list("ab"), rng.integers(0, 40))) for _ in range(25)})
    df = spark.createDataFrame([(t,) for t in texts], "text string")
    name = {r.sid: r.text for r in A._texts(df).collect()}
    got = sorted((r["rank"], name[r.sid][r.i :]) for r in A.suffix_array(df, 27).collect())
    assert len(got) == sum(map(len, texts))
    assert all(x[1][:27] <= y[1][:27] for x, y in zip(got, got[1:], strict=False))


def test_full_suffix_array_repeats(spark, docs, empty, monkeypatch):
    """The full difference cover against brute force; short blocks and few hot names, so that both ways are taken."""
    from blockpress.llm import suffix_array as A

    monkeypatch.setattr(A, "BLOCK", 64)
    monkeypatch.setattr(A, "HOT", 8)
    rng = np.random.default_rng(3)
    pool = ["".join(rng.choice(list("ab"), rng.integers(20, 260))) for _ in range(12)]
    texts = ["".join(pool[j] for j in rng.integers(0, 12, rng.integers(1, 8))) for _ in range(20)] + ["a" * 500, "ab" * 300, "a" * 199, "a" * 200]
    rows = [(r[0], r[1]) for r in awkward()] + [(100 + k, t) for k, t in enumerate(texts)]
    more = spark.createDataFrame(rows[len(awkward()) :], "doc_id long, text string")
    want = Counter((r[0], *x) for r, x in zip(rows, removed([r[1] for r in rows]), strict=True))
    assert digests(A.removal_digests(docs.select("doc_id", "text").unionByName(more))) == want
    assert A.removal_digests(empty).count() == 0


# 2: fingerprints


def test_minhash(docs, spark):
    from blockpress.llm.minhash import edited_fingerprints

    rows = sorted(((k, t or "") for k, t in ((r[0], r[1]) for r in awkward()) if k is not None and k != 5), reverse=True)
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r for r in edited_fingerprints(df).collect()}
    assert len(got) == len(rows)
    for j, (k, t) in enumerate(rows):
        after, half = rows[(j + 1) % len(rows)][1], len(t) // 2
        edited = t[: len(t) - half] + after[:half]
        assert got[k].edited_sha256 == hashlib.sha256(edited.encode()).hexdigest()
        assert got[k].n_chars == len(t)
        assert 0 <= got[k].near_edited <= 1 and 0 <= got[k].near_next <= 1
    assert edited_fingerprints(docs).count() == len(awkward())
    same = {r.fingerprint for r in edited_fingerprints(docs).collect() if r.doc_id in (5, 6)}
    assert len(same) == 1


def test_minhash_estimates(spark, small):
    got = Q.op2_minhash_fingerprints(spark, small).toPandas().set_index("doc_id")
    docs = sorted(((r.doc_id, r.text) for r in spark.read.parquet(f"{small}/documents.parquet").collect()), reverse=True)

    def shingles(x):
        w = x.lower().split()
        return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()

    off = []
    for j, (k, t) in enumerate(docs):
        after, half = docs[(j + 1) % len(docs)][1], len(t) // 2
        a, b = shingles(t), shingles(t[: len(t) - half] + after[:half])
        off.append(got.near_edited[k] - len(a & b) / max(1, len(a | b)))
    assert abs(np.mean(off)) < 0.02 and np.std(off) < 0.06


def test_minhash_links(spark, empty):
    from blockpress.llm.minhash import similar_documents, similar_links

    words = [f"w{k}" for k in range(120)]
    near = words.copy()
    near[60] = "zz"
    rows = [(0, " ".join(words)), (1, " ".join(near)), (2, " ".join(words)), (3, " ".join(reversed(words))), (4, None)]
    members, links = similar_links(spark.createDataFrame(rows, "doc_id long, text string"))
    assert {(r.doc_id, r.class_id) for r in members.collect()} == {(0, 0), (2, 0), (1, 1), (3, 3), (4, 4)}
    assert [(r.a, r.b) for r in links.collect()] == [(0, 1)]
    assert similar_links(empty)[0].count() == 0
    assert similar_documents(empty).count() == 0
    got = similar_documents(spark.createDataFrame([*rows, (5, "")], "doc_id long, text string"))
    assert sorted(map(tuple, got.collect())) == [(0, 0, 1), (1, 1, 1), (2, 0, 1), (3, 3, 0), (4, 4, 0), (5, 4, 0)]


@pytest.mark.parametrize("block", [3, 256])
def test_minhash_links_brute_force(spark, monkeypatch, block):
    """Every pair at 0.8 or more, and none below, in one block and in several; a hot template shared by all."""
    from blockpress.llm import minhash

    monkeypatch.setattr(minhash, "BLOCK", block)
    rng = np.random.default_rng(11)
    base = [f"w{k}" for k in range(150)]
    texts = []
    for _ in range(40):
        words = base.copy()
        for at in rng.choice(150, rng.integers(0, 7), replace=False):
            words[at] = f"x{rng.integers(1000)}"
        texts.append(" ".join(words))
    texts += [" ".join(base[:3]), "", " ".join(base).upper()]
    sets = [{tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set() for w in (t.lower().split() for t in texts)]
    names = [next(i for i, s in enumerate(sets) if s == mine) for mine in sets]
    classes = sorted(set(names))
    want = {(a, b) for a in classes for b in classes if a < b and sets[a] and sets[b] and len(sets[a] & sets[b]) / len(sets[a] | sets[b]) >= 0.8}
    members, links = minhash.similar_links(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"))
    assert {r.doc_id: r.class_id for r in members.collect()} == dict(enumerate(names))
    got = [(r.a, r.b) for r in links.collect()]
    assert len(got) == len(set(got)) and set(got) == want and 20 < len(want) < len(classes) * (len(classes) - 1) // 2


def test_minhash_empty(empty):
    from blockpress.llm.minhash import edited_fingerprints

    assert edited_fingerprints(empty).count() == 0


# 3: token counts


def unigram():
    from tokenizers import Tokenizer, models, pre_tokenizers

    from blockpress.llm.token_count import unigram_vocabulary

    v = unigram_vocabulary(Q.vocabulary("piece_bpe_32k.model"))
    t = Tokenizer(models.Unigram(v, 0))
    t.pre_tokenizer = pre_tokenizers.Metaspace(prepend_scheme="always")
    return v, t


def test_token_counts(spark, small, docs):
    from blockpress.llm.token_count import Counter as Count
    from blockpress.llm.token_count import count_tokens

    v, t = unigram()
    got = {r.doc_id: r.n_tokens for r in Q.op3_token_counts(spark, small).collect()}
    rows = spark.read.parquet(f"{small}/documents.parquet").collect()
    assert all(got[r.doc_id] == len(t.encode(r.text, add_special_tokens=False).ids) for r in rows)
    texts = ["", " ", "  a  b", "▁x▁▁y", "日本語 ☃☃ ☃", "a\nb", "a ▁ b"]
    assert Count(v).count(texts) == [len(t.encode(x, add_special_tokens=False).ids) for x in texts]
    assert count_tokens(docs, Q.vocabulary("piece_bpe_32k.model")).count() == len(awkward())


def test_token_count_ties():
    """Equal scores: the piece that begins first wins, as in the library."""
    from tokenizers import Tokenizer, models

    from blockpress.llm.token_count import Counter as Count

    v = [("<unk>", 0.0), ("a", -1.0), ("b", -1.0), ("ab", -2.0), ("ba", -2.0), ("aba", -3.0), ("bb", -2.0)]
    t, c = Tokenizer(models.Unigram(v, 0)), Count(v)
    rng = np.random.default_rng(0)
    for _ in range(300):
        w = "".join(rng.choice(list("abc"), rng.integers(1, 9)))
        assert c.word(w) == len(t.encode(w).ids), w


# 4: SimHash


def brute_simhash(text):
    raw = bytes(c + 32 if 65 <= c <= 90 else c for c in (text or "").encode())
    w = re.findall(rb"[^\x20\x09-\x0D]+", raw)
    h = [xxhash.xxh64_intdigest(b" ".join(w[i : i + 3]), 42) for i in range(max(1, len(w) - 2))] if w else []
    return sum(1 << b for b in range(64) if sum(x >> b & 1 for x in h) * 2 > len(h))


def components(fps, limit=3):
    ids = sorted(fps)
    up = {i: i for i in ids}

    def root(i):
        while up[i] != i:
            i = up[i]
        return i

    for i in ids:
        for j in ids:
            if i < j and bin(fps[i] ^ fps[j]).count("1") <= limit:
                a, b = sorted((root(i), root(j)))
                up[b] = a
    return {i: root(i) for i in ids}


def test_simhash_documents(spark, small):
    got = {r.doc_id: (r.fingerprint, r.component_id) for r in Q.op4_simhash_near_dedup(spark, small).collect()}
    fps = {r.doc_id: brute_simhash(r.text) for r in spark.read.parquet(f"{small}/documents.parquet").collect()}
    comp = components(fps)
    assert got == {k: (f"{v:016x}", comp[k]) for k, v in fps.items()}


@pytest.mark.parametrize("joined,block", [(48, 1024), (2, 8)])
def test_simhash_links(spark, monkeypatch, joined, block):
    """Chains of close fingerprints, by joins and by blocks."""
    from blockpress.llm import simhash as S
    from blockpress.operators.components import connected_components

    monkeypatch.setattr(S, "JOINED", joined)
    monkeypatch.setattr(S, "BLOCK", block)
    rng = np.random.default_rng(5)
    fps = {int(x) for x in rng.integers(0, 1 << 63, 40)}
    for f in list(fps)[:12]:
        for _ in range(12):
            for b in rng.choice(64, rng.integers(1, 5), replace=False):
                f ^= 1 << int(b)
            fps.add(f)
    signed = [f - (1 << 64) if f >> 63 else f for f in fps]
    df = spark.createDataFrame([(f,) for f in signed], "fp long")
    got = {r.node: r.component for r in connected_components(S.links(df)).collect()}
    want = components({f: f % (1 << 64) for f in signed})
    names = {}
    for f in signed:
        names.setdefault(want[f], set()).add(f)
    assert {frozenset(v) for v in names.values() if len(v) > 1} == {frozenset(k for k in got if got[k] == c) for c in set(got.values())}


def test_simhash_awkward(docs, empty):
    from blockpress.llm.simhash import near_duplicates

    rows = near_duplicates(docs).collect()
    assert len(rows) == len(awkward())
    assert {r.component_id for r in rows if r.doc_id in (0, 1, 2)} == {0}
    assert {r.fingerprint for r in rows if r.doc_id in (0, 1, 2)} == {"0" * 16}
    assert near_duplicates(empty).count() == 0


# 5: token files


@pytest.mark.parametrize("top", [1, 2, 60, 50_000, 1 << 31, 1 << 59])
def test_simple8b(top):
    from blockpress.llm.token_binary import pack, unpack

    rng = np.random.default_rng(top % 97)
    for n in (0, 1, 59, 60, 61, 9000):
        ids = rng.integers(0, top, n).astype(np.uint64)
        assert (unpack(pack(ids)) == ids).all()
    mixed = np.where(rng.random(5000) < 0.01, top, 1).astype(np.uint64)
    assert (unpack(pack(mixed)) == mixed).all()
    with pytest.raises(ValueError):
        pack(np.array([1 << 60], np.uint64))


ODD = ["a  b", "a\n\nb ", " x", "x ", "a\tb c\t d", "\x1ca 0 b 00 a0", "É  é <|endoftext|> z<|startoftext|>", "", "\n", "don't I'll 'S", "a\0b c", "日本 語。x", "x\n y", "a..b", "a.b,c .d", "é. é,f", "3.5,6", "_.a", "´. b"]


@pytest.mark.parametrize("name,byte_level", [("byte_bpe_50k.json", True), ("word_bpe_49k.json", False)])
def test_encoder(name, byte_level, spark, small):
    from blockpress.llm.tokens import Encoder

    texts = ODD + [r.text for r in spark.read.parquet(f"{small}/documents.parquet").limit(60).collect()]
    e = Encoder(Q.vocabulary(name), byte_level)
    want = [x.ids for x in e.tok.encode_batch(texts, add_special_tokens=False)]
    for _ in range(2):
        ids, at = e.encode(pa.array(texts))
        assert [ids[a:b].tolist() for a, b in zip(at, at[1:], strict=False)] == want


def test_token_file(spark, docs, empty):
    from tokenizers import Tokenizer

    from blockpress.llm.common import shared_dir
    from blockpress.llm.token_binary import encode_to_file_and_back, read_token_file, write_token_file

    path = Q.vocabulary("byte_bpe_50k.json")
    rows = sorted((r[0], r[1] or "") for r in awkward() if r[0] is not None and r[0] != 5)
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    got = {r.doc_id: (r.start, r.n_tokens, r.ids_crc32) for r in encode_to_file_and_back(df, path).collect()}
    t, start = Tokenizer.from_file(path), 0
    for k, text in rows:
        ids = np.array([*t.encode(text, add_special_tokens=False).ids, 0], "<u4")
        assert got[k] == (start, len(ids), zlib.crc32(ids.tobytes()))
        start += len(ids)
    assert encode_to_file_and_back(docs, path).count() == len(awkward())
    assert encode_to_file_and_back(empty, path).count() == 0
    where = f"{shared_dir(spark)}/a-token-file"
    write_token_file(df, where, path)
    assert {r.doc_id: len(r.ids) for r in read_token_file(spark, where).collect()} == {k: v[1] for k, v in got.items()}


# 6: url filter


def test_cascade(spark):
    from blockpress.llm.url_filter import Cascade, keys_frame

    rng = np.random.default_rng(1)
    keys = [f"k{x}" for x in rng.integers(0, 1 << 40, 4000)]
    listed = keys[:900]
    cascade = Cascade.build(keys_frame(spark, listed), keys_frame(spark, keys), error=0.25)
    assert len(cascade.levels) > 2
    from pyspark.sql import functions as F

    frame = keys_frame(spark, keys).select("key", F.xxhash64("key").alias("a"), F.xxhash64(F.lit(1), F.col("key")).alias("b")).toPandas()
    assert (cascade.listed(frame.a.to_numpy(), frame.b.to_numpy()) == frame.key.isin(listed).to_numpy()).all()


URLS = [None, "", "no scheme", "http://", "http://WWW.Example.com/en/x?y", "https://a.example.com/en/", "https://example.com/en", "x://example.net/es/a#b", "http://example.net?q=/es/", "http://spam-farm.example.org/", "http://m.spam-farm.example.org", "http://notexample.com/en/", "http://com/", "http://é.net/fr/ü"]


def judged(url):
    if url is None or "://" not in url:
        host = path = ""
    else:
        rest = url.split("://", 1)[1]
        host = re.match(r"[^/?#]*", rest)[0]
        path = re.match(r"[^?#]*", rest[len(host) :])[0]
        host = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in host)
    fits = [(h + p, v) for h, p, v in Q.URL_RULES if (host == h or host.endswith("." + h)) and path.startswith(p)]
    rule, verdict = max(fits, key=lambda x: len(x[0])) if fits else (None, "block" if any(host == h or host.endswith("." + h) for h in Q.LISTED_HOSTS) else "allow")
    return host, path, rule, verdict


def test_url_filter(spark):
    from blockpress.llm.url_filter import Rule, filter_urls

    rows = [(k, u, "<p>", "clash") for k, u in enumerate(URLS)] + [(4, URLS[4], None, None)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string, keys string")
    got = Counter((r.page_id, r.host, r.path, r.rule, r.verdict) for r in filter_urls(df, [Rule(*r) for r in Q.URL_RULES], Q.LISTED_HOSTS).collect())
    assert got == Counter((r[0], *judged(r[1])) for r in rows)
    assert filter_urls(df.limit(0), [Rule(*r) for r in Q.URL_RULES], Q.LISTED_HOSTS).count() == 0
    assert {r.verdict for r in filter_urls(df, []).collect()} == {"allow"}


# 7: language


def test_language(spark, small, empty):
    from blockpress.llm.language_id import TextModel, document_evidence, identify, page_evidence, training_rows

    docs = spark.read.parquet(f"{small}/documents.parquet")
    rows = training_rows(docs, 100)
    model = TextModel.fit(rows)
    got = {r.doc_id: r for r in identify(document_evidence(docs), model).collect()}
    truth = {r.doc_id: r.lang for r in docs.collect()}
    assert np.mean([got[k].lang == v for k, v in truth.items()]) > 0.97
    assert np.mean([got[k].text_lang == v for k, v in truth.items()]) > 0.95
    assert np.mean([r.kept for r in got.values()]) > 0.97
    assert identify(document_evidence(empty), model).count() == 0
    pages = identify(page_evidence(spark.read.parquet(f"{small}/pages.parquet")), model, "page_id").collect()
    assert len(pages) == 50 and all(r.lang in model.languages for r in pages)


def test_language_awkward(spark, docs):
    from blockpress.llm.language_id import TextModel, document_evidence, identify

    model = TextModel.fit([("en", BASE), ("fr", "le chat noir est sur la table et il ne veut pas descendre " * 5)])
    rows = identify(document_evidence(docs), model).collect()
    assert len(rows) == len(awkward())
    assert {r.kept for r in rows if r.doc_id in (0, 1, 2)} == {False}
    assert {r.lang for r in rows if r.doc_id in (6, 7, 11)} == {"en"}


def test_language_evidence_counts(spark):
    """A text that says little follows its host and its declaration."""
    from blockpress.llm.language_id import TextModel, identify

    en, fr = "the house and the table with the tree ", "la maison et la table avec un arbre "
    model = TextModel.fit([("en", en * 20), ("fr", fr * 20)])
    rows = [(k, en, "a.org", "en", "uk") for k in range(40)] + [(100 + k, fr, "b.org", "fr", "fr") for k in range(40)] + [(200, "table", "b.org", "fr", "fr"), (201, "table", "a.org", "en", "uk"), (202, "table", None, None, None)]
    got = {r.doc_id: r.lang for r in identify(spark.createDataFrame(rows, "doc_id long, text string, host string, declared string, suffix string"), model).collect()}
    assert got[200] == "fr" and got[201] == "en" and got[202] in ("en", "fr")


# 8: packing


def one_at_a_time(lengths, capacity):
    import bisect

    free, bins = [], 0
    for n in sorted(lengths, reverse=True):
        k = bisect.bisect_left(free, n)
        if k == len(free):
            bins, left = bins + 1, capacity - n
        else:
            left = free.pop(k) - n
        bisect.insort(free, left)
    return bins, sorted(free)


@pytest.mark.parametrize("seed", range(6))
def test_plan_is_best_fit_decreasing(seed):
    from blockpress.llm.packing import plan

    rng = np.random.default_rng(seed)
    capacity = int(rng.integers(5, 200))
    lengths = np.minimum(rng.geometric(3 / capacity, 3000), capacity).tolist()
    runs, bins = plan(Counter(lengths), capacity)
    want, free = one_at_a_time(lengths, capacity)
    assert bins == want
    used = np.zeros(bins, int)
    for length, lo, hi, first, each, off in runs:
        for nth in range(hi - lo):
            b, o = first + nth // each, off + nth % each * length
            assert used[b] == o
            used[b] += length
    assert sorted((capacity - used).tolist()) == free


def test_packing(spark, docs, empty):
    from tokenizers import Tokenizer

    from blockpress.llm.packing import best_fit_pack

    path = Q.vocabulary("word_bpe_49k.json")
    rows = best_fit_pack(docs, path, 32).collect()
    t = Tokenizer.from_file(path)
    want = Counter((r[0], len(t.encode(r[1] or "", add_special_tokens=False).ids) + 1) for r in awkward())
    assert sum(r.length for r in rows) == sum(n * c for (_, n), c in want.items())
    bins = {}
    for r in rows:
        bins.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for parts in bins.values():
        at = 0
        for off, n in sorted(parts):
            assert off == at
            at += n
        assert at <= 32
    assert best_fit_pack(empty, path).count() == 0


# 9: decontamination


def test_every_window_has_a_seed():
    """Of 13 words with two replaced, or 20 with four, some mask's words are all left."""
    from itertools import combinations

    from blockpress.llm.decontaminate import MASKS

    for n, lost in ((13, 2), (20, 4)):
        for gone in combinations(range(n), lost):
            assert any(all(i + j not in gone for j, b in enumerate(m) if b == "1") for m in MASKS for i in range(n - len(m) + 1))


def test_decontamination(spark, empty):
    from blockpress.llm.decontaminate import contaminated, drop_contaminated, worst_overlap

    rng = np.random.default_rng(2)
    word = lambda: "".join(rng.choice(list("abcdefghij"), 6))
    item = [word() for _ in range(30)]
    replaced = item[:20]
    for k in (3, 9, 14):
        replaced[k] = word()
    clean = [word() for _ in range(200)]
    rows = [(0, " ".join(clean)), (1, " ".join(clean[:50] + item + clean[50:])), (2, " ".join(clean[:9] + [w.upper() + "," for w in replaced] + clean[9:])), (3, " ".join(item[:8])), (4, None), (5, ""), (6, " ".join(item[:8] + clean[:3] + item[8:14]))]
    df = spark.createDataFrame([(*r, "x") for r in rows], "doc_id long, text string, item_id string")
    tests = spark.createDataFrame([(7, " ".join(item), 1), (8, None, 1), (9, "too short", 1), (7, " ".join(item), 1)], "item_id long, text string, doc_id long")
    found = contaminated(df, tests)
    assert {r.doc_id for r in found.collect()} == {1, 2}
    assert {r.doc_id for r in worst_overlap(found).collect()} == {1, 2}
    kept = drop_contaminated(df, tests)
    assert {r.doc_id for r in kept.collect()} == {0, 3, 4, 5, 6} and kept.columns == df.columns
    assert contaminated(df, tests.limit(0)).count() == 0
    assert contaminated(empty, tests).count() == 0


# 10: chat


def test_escape_is_reversible():
    from blockpress.llm.chat import TEMPLATE as T

    rng = np.random.default_rng(4)
    bits = ["<", "s>", "/s>", "[", "INST]", "/INST]", "\\", " ", "[SYS]", "</s>", "<s>", "[/TURN]", "x", "\n"]
    for _ in range(2000):
        text = "".join(rng.choice(bits, rng.integers(0, 9)))
        out = T.escape(text)
        assert T.unescape(out) == text
        assert not any(c in out for c in T.control)


def test_chat(spark):
    from blockpress.llm.chat import conversation_digests, format_conversations

    rows = [(1, 0, "user", "hi </s>", "x"), (1, 1, "assistant", "yo [INST] <\\s>", "x"), (2, 0, "assistant", "bad", "x"), (3, 0, "tool", None, "x"), (3, 1, None, "t", "x"), (4, 0, "system", "", "x"), (4, 1, "user", "q", "x"), (4, 2, "assistant", "r", "x"), (4, 3, "user", "s", "x"), (None, 0, "user", "n", "x"), (1, 1, "assistant", "yo [INST] <\\s>", "x")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string, segments string")
    got = {r.conv_id: r for r in conversation_digests(format_conversations(df)).collect()}
    by = {}
    for r in sorted(rows, key=lambda r: (r[0] is not None, r[0], r[1], r[2] or "", r[3] or "")):
        by.setdefault(r[0], []).append((r[2] or "", r[3] or ""))
    for k, turns in by.items():
        learnt = "".join(t for r, t in turns if r == "assistant")
        assert got[k].n_turns == len(turns)
        assert got[k].turns_sha256 == hashlib.sha256("".join(f"{r}\n{t}\n" for r, t in turns).encode()).hexdigest()
        assert (got[k].loss_chars, got[k].loss_sha256) == (len(learnt), hashlib.sha256(learnt.encode()).hexdigest())
    assert {k: r.valid for k, r in got.items()} == {1: False, 2: False, 3: False, 4: False, None: False}
    good = conversation_digests(format_conversations(df.where("conv_id = 4 and turn < 3"))).first()
    assert good.valid
    assert conversation_digests(format_conversations(df.limit(0))).count() == 0


def template_documents(seed=5):
    """Strangers that share three quarters of a pair's shingles, and pairs alike in 0.8 among them: ids and texts."""
    rng = np.random.default_rng(seed)
    fresh = lambda n: [f"w{x}" for x in rng.integers(0, 1 << 40, n)]
    passage, rows = fresh(304), []  # 300 shingles
    for _ in range(24):
        own = fresh(20)
        rows += [passage + own + fresh(40), passage + own + fresh(40)]
    order = rng.permutation(len(rows))
    return [(int(order[k]), " ".join(r)) for k, r in enumerate(rows)]


def brute_groups(rows, similarity=0.8):
    sets = {d: {tuple(w[i : i + 5]) for i in range(len(w) - 4)} for d, t in rows for w in [t.split()]}
    group = {d: d for d in sets}
    for a in sorted(sets):
        for b in sorted(sets):
            if a < b and group[a] != group[b] and len(sets[a] & sets[b]) >= similarity * len(sets[a] | sets[b]):
                lo, hi = sorted((group[a], group[b]))
                group = {d: lo if g == hi else g for d, g in group.items()}
    return group


def test_near_groups_are_exact(spark):
    """Documents that share a template and are below 0.8 stay apart."""
    from blockpress.llm.simhash import near_groups

    rows = template_documents()
    truth = brute_groups(rows)
    assert len(set(truth.values())) == 24
    got = {r.doc_id: r.component_id for r in near_groups(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got.keys() == truth.keys()
    assert all(truth[d] == truth[g] for d, g in got.items())


@pytest.mark.parametrize("block", [256, 10])
def test_sample_links_compare_all(spark, monkeypatch, block):
    """Classes between the first and the last of their only key find each other, in one block or in several."""
    from blockpress.llm import simhash as S
    from blockpress.llm.minhash import PERMUTATIONS

    monkeypatch.setattr(S, "COMPARED", block, raising=False)
    monkeypatch.setattr(S, "SAMPLES", 1)
    rng = np.random.default_rng(3)
    rows = []
    for k in range(20):  # first and last are strangers to all, the others come in pairs alike in 90 of 110
        own = rng.integers(0, 1 << 62, 110).astype(np.uint64)
        for half in (own[:100], own[10:]):
            sig = rng.integers(0, 256, PERMUTATIONS).astype(np.uint8)
            sig[:230] = np.resize(own.view(np.uint8), 230)
            sig[:4] = 7
            rows.append((len(rows) + 1, bytes(sig), np.sort(half).tobytes()))
    for i in (0, 99):
        sig = rng.integers(0, 256, PERMUTATIONS).astype(np.uint8)
        sig[:4] = 7
        rows.append((i, bytes(sig), np.sort(rng.integers(0, 1 << 62, 100).astype(np.uint64)).tobytes()))
    classes = spark.createDataFrame(rows, "id long, sig binary, shingles binary")
    none = spark.createDataFrame([], "a long, b long")
    got = {(min(r), max(r)) for r in S.sample_links(classes, 0.8, none).collect()}
    assert got == {(2 * k + 1, 2 * k + 2) for k in range(20)}


def shared_ids():
    """Rows that share an id or have none, with texts that have no word in common."""
    a, b = " ".join(f"a{k}" for k in range(60)), " ".join(f"b{k}" for k in range(60))
    return [(7, a), (7, b), (8, b + " und"), (9, a + " und"), (None, a), (None, "c " * 3), (None, "d " * 9)]


def test_near_groups_by_text_not_id(spark):
    from blockpress.llm.simhash import near_groups, one_of_each

    rows = shared_ids()
    df = spark.createDataFrame(rows, "doc_id long, text string")
    groups: dict = {}
    texts = {r.text_hash: r.text for r in df.selectExpr("xxhash64(text) as text_hash", "text").collect()}
    for r in near_groups(df).collect():
        groups.setdefault(r.group_id, set()).add((r.doc_id, texts[r.text_hash][0]))
    assert sorted(map(len, groups.values())) == [1, 1, 2, 3] and all(len({t for _, t in g}) == 1 for g in groups.values())
    kept = one_of_each(df.unionByName(df)).collect()
    assert sorted(r.text[0] for r in kept) == ["a", "b", "c", "d"]


def test_minhash_links_by_text_not_id(spark):
    from blockpress.llm.minhash import similar_links

    rows = shared_ids()
    members, links = similar_links(spark.createDataFrame(rows, "doc_id long, text string"))
    texts = {r.h: r.text for r in spark.createDataFrame(rows, "doc_id long, text string").selectExpr("xxhash64(text) as h", "text").collect()}
    named = {r.class_id: texts[r.text_hash] for r in members.collect()}
    assert len(named) == 6
    assert {frozenset((named[r.a][0], named[r.b][0])) for r in links.collect()} == {frozenset("a"), frozenset("b")} and links.count() == 2


def test_near_groups_recall(spark):
    """Of pairs alike in 0.8 to 0.9 of their shingles nine in ten are in one group, and none below 0.8."""
    from blockpress.llm.simhash import near_groups

    rng = np.random.default_rng(11)
    rows, pairs = [], []
    for k in range(150):
        words = [f"w{x}" for x in rng.integers(0, 10**6, 120)]
        other = words.copy()
        for j in rng.choice(24, 1 + k % 4, replace=False) * 5:
            other[j] += "x"
        rows += [(2 * k, " ".join(words)), (2 * k + 1, " ".join(other))]
        a, b = ({tuple(w[i : i + 5]) for i in range(116)} for w in (words, other))
        pairs.append(len(a & b) / len(a | b))
    got = {r.doc_id: r.group_id for r in near_groups(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    found = np.array([got[2 * k] == got[2 * k + 1] for k in range(150)])
    like = np.array(pairs)
    assert not found[like < 0.8].any() and found[like >= 0.8].mean() >= 0.9 and (like >= 0.8).sum() >= 50


def test_short_windows_have_a_seed():
    """Of 13 words with two replaced some long mask's words are left; of 6 to 12 with the share's number some short mask's."""
    from itertools import combinations
    from math import ceil

    from blockpress.llm.decontaminate import LONG_MASKS, MASKS, SHARE

    for n in range(6, 14):
        for gone in combinations(range(n), n - ceil(SHARE * n)):
            assert any(all(i + j not in gone for j, b in enumerate(m) if b == "1") for m in (LONG_MASKS if n == 13 else MASKS) for i in range(n - len(m) + 1))


def brute_overlaps(docs, items, least=6):
    """(document, item): words that agree in the best of all windows along all lines."""
    clean = lambda t: [w for w in (re.sub(r"[!-/:-@\[-`{-~]", "", x) for x in (t or "").lower().split()) if w]
    out = {}
    for d, text in docs:
        a = clean(text)
        for i, item in items:
            b = clean(item)
            w = min(13, len(b))
            if len(b) < least or len(a) < w:
                continue
            best = max(sum(x == y for x, y in zip(a[p : p + w], b[q : q + w], strict=True)) for p in range(len(a) - w + 1) for q in range(len(b) - w + 1))
            if best >= np.ceil((0.8 if least >= 6 or w >= 6 else 1.0) * w - 1e-9):
                out[d, i] = (best, w)
    return out


@pytest.mark.parametrize(("hot", "least"), [(20_000, 6), (3, 6), (20_000, 2)])
def test_decontamination_brute_force(spark, monkeypatch, hot, least):
    """Over a table: items of 2 to 30 words, some shared by many documents, words replaced, null ids."""
    from blockpress.llm import decontaminate as D

    monkeypatch.setattr(D, "HOT", hot)
    rng = np.random.default_rng(8)
    word = lambda: "".join(rng.choice(list("abcdefgh"), 5))
    items = [(k, " ".join(word() for _ in range(n))) for k, n in enumerate([2, 3, 5, 6, 7, 8, 9, 10, 11, 12, 13, 14, 20, 30] * 2)]
    docs = []
    for k in range(90):
        words = [word() for _ in range(int(rng.integers(0, 60)))]
        for _ in range(int(rng.integers(0, 3))):
            piece = items[int(rng.integers(len(items)))][1].split()
            for j in rng.choice(len(piece), int(rng.integers(0, 1 + len(piece) // 4)), replace=False):
                piece[j] = word()
            at = int(rng.integers(0, len(words) + 1))
            words[at:at] = [p.upper() + "," for p in piece]
        docs.append((k, " ".join(words)))
    got = {(r.doc_id, r.item_id): (r.matched, r.window) for r in D.contaminated(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string"), least).collect()}
    assert got == brute_overlaps(docs, items, least) and len(got) > 20


def test_decontamination_null_ids(spark):
    from blockpress.llm.decontaminate import contaminated, drop_contaminated

    item = " ".join(f"q{k}" for k in range(15))
    docs = spark.createDataFrame([(None, "lead " + item), (None, "clean words only here"), (1, item), (1, "clean too")], "doc_id long, text string")
    tests = spark.createDataFrame([(None, item), (None, "other " * 9)], "item_id long, text string")
    assert sorted((r.doc_id is None, r.item_id is None) for r in contaminated(docs, tests).collect()) == [(False, True), (True, True)]
    assert sorted(r.text for r in drop_contaminated(docs, tests).collect()) == ["clean too", "clean words only here"]


def brute_posterior(rows, model):
    """(language, confidence) of ``rows(text, host, declared, suffix)`` by loops over the evidence."""
    from math import exp, inf, log

    from blockpress.llm import language_id as M

    langs = model.languages
    k = len(langs)
    scores, guess = [], []
    for text, *_ in rows:
        mean, count = model.score(pa.array([text], pa.large_string()))
        scores.append([x * min(count[0], M.TEXT_WEIGHT) if count[0] else (-inf if j < k - 1 else 0.0) for j, x in enumerate(mean[0])])
        guess.append(int(mean[0].argmax()) if count[0] else k - 1)

    def counts(pick):
        out: dict = {}
        for r, g in zip(rows, guess, strict=True):
            if pick(r) is not None:
                out.setdefault(pick(r), [0] * k)[g] += 1
        return out

    parent = lambda h: h.partition(".")[2] if "." in h else re.sub(r"[0-9]+$", "", h)
    total = counts(lambda r: 0)[0]
    prior = [(c + 1) / (len(rows) + k) for c in total]
    smooth = lambda c, p: [(x + M.SMOOTHING * q) / (sum(c) + M.SMOOTHING) for x, q in zip(c, p, strict=True)]
    hosts, parents = counts(lambda r: r[1]), counts(lambda r: None if r[1] is None else parent(r[1]))
    ratios = []
    for at in (2, 3):
        seen = counts(lambda r, at=at: r[at])
        ratios.append({v: [log(M.FLOOR + (1 - M.FLOOR) * (c + p) / (sum(cs) + 1) / p) for c, p in zip(cs, prior, strict=True)] for v, cs in seen.items()})
    out = []
    for r, s in zip(rows, scores, strict=True):
        p = prior if r[1] is None else smooth(hosts[r[1]], smooth(parents[parent(r[1])], prior))
        fused = [log(p[j]) + s[j] + sum(x.get(r[at], [0.0] * k)[j] for at, x in zip((2, 3), ratios, strict=True)) for j in range(k)]
        top = max(fused)
        out.append((langs[fused.index(top)], 1 / sum(exp(f - top) for f in fused)))
    return out


def test_language_posterior(spark, small):
    """The query's fused posterior against loops, on all pages; and accuracy where nothing is declared."""
    from blockpress.llm.language_id import TextModel, identify, page_evidence

    docs, pages = (spark.read.parquet(f"{small}/{t}.parquet") for t in ("documents", "pages"))
    model = TextModel.fit_on(docs)
    evidence = page_evidence(pages)
    rows = evidence.collect()
    want = brute_posterior([(r.text, r.host, r.declared, r.suffix) for r in rows], model)
    got = {r.page_id: r for r in Q.op7_language_id(spark, small).collect()}
    assert len(got) == len(rows) and {r.declared for r in rows} == set(model.languages) - {"und"}
    for r, (lang, confidence) in zip(rows, want, strict=True):
        assert got[r.page_id].lang == lang and abs(got[r.page_id].confidence - confidence) < 2e-6
    bare = identify(evidence.selectExpr("page_id", "text", "host", "cast(null as string) as declared", "cast(null as string) as suffix"), model, "page_id").collect()
    truth = {r.page_id: r.declared for r in rows}
    assert np.mean([r.lang == truth[r.page_id] for r in bare]) > 0.95


def test_language_sample_has_every_language(spark):
    """A language of one row in a thousand is in the sample, and held-out texts are told."""
    from blockpress.llm.language_id import TextModel, document_evidence, identify, languages_of, training_rows

    rng = np.random.default_rng(4)
    parts = {"aa": "ka lo mi ne pu".split(), "bb": "ship frog tree glass".split(), "zz": "qua xen vox wyr".split()}
    rows = [(k, " ".join(rng.choice(parts[x], 40)), x, "s") for k, x in enumerate(["aa"] * 1500 + ["bb"] * 1500 + ["zz"] * 3)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    sample = training_rows(docs, 30)
    assert {x: sum(r[0] == x for r in sample) for x in parts} == {"aa": 10, "bb": 10, "zz": 3}
    assert {r.lang: r.rows for r in languages_of(docs).collect()} == {"aa": 1500, "bb": 1500, "zz": 3}
    got = {r.doc_id: r.lang for r in identify(document_evidence(docs), TextModel.fit_on(docs, 30)).collect()}
    used = {t for _, t in sample}
    assert all(got[k] == x for k, t, x, _ in rows if t not in used)
    nothing = identify(document_evidence(docs), TextModel.fit_on(docs.limit(0))).collect()
    assert {r.lang for r in nothing} == {"und"} and not any(r.kept for r in nothing)


def pages_of_many(n=400):
    rng = np.random.default_rng(6)
    urls = [f"https://{rng.choice(['www.', '', 'a.b.'])}h{rng.integers(30)}.example.{rng.choice(['com', 'net', 'org'])}/{rng.choice(['en', 'es'])}/{rng.integers(200)}{rng.choice(['', '?ref=x', '#top'])}" for _ in range(n)]
    return urls + [None, "no host", "http://" + ".".join(["x"] * 4000) + ".example.org/p", "http://H1.example.org", "http:///p"]


@pytest.mark.parametrize("most", [256 << 20, 8])
def test_url_lists(spark, monkeypatch, most):
    """Long lists of hosts and addresses, by cascade and, where a filter would be too large, by join."""
    from blockpress.llm import url_filter as U

    urls = pages_of_many()
    pages = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string")
    parts = {r.page_id: (r.host, r.path) for r in U.with_parts(pages).collect()}
    hosts = {f"h{k}.example.org" for k in range(0, 30, 3)} | {"example.net"}
    addresses = {h + p for k, (h, p) in parts.items() if urls[k] and "ref=" in urls[k]}
    frame = lambda keys: spark.createDataFrame([(k,) for k in [*keys, *keys, None]], "key string")
    monkeypatch.setattr(U, "MAX_FILTER_BYTES", most)
    got = {r.page_id: r for r in U.filter_urls(pages, [U.Rule("com", "/", "allow")] if most > 8 else [], frame(hosts), frame(addresses)).collect()}
    for k, (h, p) in parts.items():
        listed = any(h == x or h.endswith("." + x) for x in hosts) or h + p in addresses
        ruled = most > 8 and (h == "com" or h.endswith(".com")) and p.startswith("/")
        assert (got[k].rule, got[k].verdict) == ("com/" if ruled else None, "allow" if ruled or not listed else "block")
