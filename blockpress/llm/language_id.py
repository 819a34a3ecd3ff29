"""Language identification by Bayesian evidence fusion (operator 7).

Evidence for a text's language: the likelihood of its byte trigrams under each language, the language
that its markup declares, the suffix of its address, and its host's prior. Log terms add up. Trigrams
are far from independent, so the text's likelihood counts per trigram, times ``TEXT_WEIGHT`` at most.

Host priors are smoothed in levels, each towards the one above with ``SMOOTHING`` rows' weight: host,
the host's parent (``parent_of``), all. They and the declarations' and suffixes' reliability are
counted by grouped aggregation over all rows, with the text's own best guess as the label.

``und`` stands for text in no known language: each of the hashed trigrams is equally likely, less a
margin. Only trigrams of letters and blanks count, so numbers and codes inside a text say nothing
against its language. ``und`` has its place in the priors and the fused posterior like any language, and
rows for which it wins there are rejected.

The languages are all those that occur as labels, by a full count. The text model is fitted on
``TRAINING_ROWS`` labelled rows at most, an equal share of each language's, those with the least hash;
their trigrams are counted in tasks, and counts alone reach the driver.

Cases: null, empty or very short texts, or texts without letters: no trigram, ``und``, rejected; null
host, declaration or suffix: no evidence; repeated rows: each its own; null key: a row like any other;
further columns are kept out of the evidence; no rows: no rows; no labelled rows: only ``und`` is known.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from blockpress.llm.common import free_columns, slices, small_batches, stored, text_bytes

BUCKETS = 1 << 15
TRAINING_ROWS = 2000
TEXT_WEIGHT = 60.0
SMOOTHING = 20.0
FLOOR = 0.02
#: Nats a trigram by which a known language may do worse than pure chance and still be believed.
UNKNOWN_MARGIN = 1.0


#: Bytes that say something about a language: small letters, blanks, and all beyond ASCII.
_TELLING = np.zeros(256, bool)
_TELLING[[*range(97, 123), 9, 10, 13, 32, 39, *range(128, 256)]] = True


def trigrams(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of the telling byte trigrams of lower-cased texts, and offsets by text."""
    raw, at = text_bytes(pc.utf8_lower(texts.fill_null("")))
    n = max(0, len(raw) - 2)
    ok = _TELLING[raw]
    good = ok[:n] & ok[1 : n + 1] & ok[2 : n + 2]
    for end in (1, 2):  # none across two texts
        cut = at[1:-1] - end
        good[cut[(cut >= 0) & (cut < n)]] = False
    place = np.flatnonzero(good)
    x = raw.astype(np.uint32)
    g = ((x[place] << np.uint32(16)) | (x[place + 1] << np.uint32(8)) | x[place + 2]) * np.uint32(2654435761) >> np.uint32(17)
    return g, np.searchsorted(place, at)


class TextModel:
    """Log-likelihoods of trigram buckets by language; the last column is ``und``."""

    def __init__(self, languages: list[str], table: np.ndarray):
        self.languages, self.table = languages, table

    @classmethod
    def fit(cls, rows: list[tuple[str, str]]) -> TextModel:
        """From rows at hand."""
        languages = sorted({lang for lang, _ in rows if lang})
        counts = [np.bincount(trigrams(pa.array([t for x, t in rows if x == lang], pa.large_string()))[0], minlength=BUCKETS) for lang in languages]
        return cls._of(languages, counts)

    @classmethod
    def fit_on(cls, labelled: DataFrame, limit: int = TRAINING_ROWS, key: str = "doc_id") -> TextModel:
        """From the training sample of ``labelled(key, lang, text)``."""

        def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            totals: dict[str, np.ndarray] = {}
            for batch in slices(batches, "text"):
                g, at = trigrams(batch.column("text"))
                for k, lang in enumerate(batch.column("lang").to_pylist()):
                    totals.setdefault(lang, np.zeros(BUCKETS, np.int64))
                    totals[lang] += np.bincount(g[at[k] : at[k + 1]], minlength=BUCKETS)
            for lang, total in totals.items():
                seen = np.flatnonzero(total)
                yield pa.record_batch([pa.array([lang] * len(seen), pa.string()), pa.array(seen.astype(np.int32)), pa.array(total[seen])], names=["lang", "bucket", "n"])

        small_batches(labelled.sparkSession)
        chosen = chosen_rows(labelled, limit, key)
        found = chosen.mapInArrow(count, "lang string, bucket int, n long").groupBy("lang", "bucket").agg(F.sum("n").alias("n")).toArrow()  # languages x buckets
        languages = sorted(r[0] for r in languages_of(labelled).collect())
        lang, bucket, n = (found.column(c).to_numpy() for c in ("lang", "bucket", "n"))
        counts = []
        for x in languages:
            total, mine = np.zeros(BUCKETS, np.int64), lang == x
            total[bucket[mine]] = n[mine]
            counts.append(total)
        return cls._of(languages, counts)

    @classmethod
    def _of(cls, languages: list[str], counts: list[np.ndarray]) -> TextModel:
        table = np.zeros((BUCKETS, len(languages) + 1), np.float32)
        for k, total in enumerate(counts):
            seen = total + 0.2
            table[:, k] = np.log(seen / seen.sum())
        table[:, -1] = np.log(1 / BUCKETS) - UNKNOWN_MARGIN
        return cls([*languages, "und"], table)

    def score(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Mean log-likelihood of each text by language, and its number of trigrams."""
        g, at = trigrams(texts)
        count = np.diff(at)
        out = np.zeros((len(count), len(self.languages)), np.float64)
        full = np.flatnonzero(count)
        if len(full):
            for k in range(len(self.languages) - 1):
                out[full, k] = np.add.reduceat(self.table[:, k][g], at[full], dtype=np.float64) / count[full]
            out[full, -1] = self.table[0, -1]
        return out, count


def parent_of(host: Column) -> Column:
    """The host without its first label; of a name without a dot, the name without its digits."""
    return F.when(F.instr(host, ".") > 0, F.regexp_replace(host, r"^[^.]*\.", "")).otherwise(F.regexp_replace(host, "[0-9]+$", ""))


def languages_of(labelled: DataFrame) -> DataFrame:
    """``lang, rows``: every label with usable text, counted over all rows."""
    return labelled.where("lang is not null and lang <> '' and length(text) >= 3").groupBy("lang").agg(F.count("*").alias("rows"))


def chosen_rows(labelled: DataFrame, limit: int = TRAINING_ROWS, key: str = "doc_id") -> DataFrame:
    """``lang, text`` of each language's rows with the least hashes, ``limit`` over all languages, one of each at least.

    Hashes alone are ranked, and of them only those below a bound that lets about four times as many pass as
    are wanted, so that no task sees more, however large the table; only the chosen rows' texts are read on.
    """
    known = languages_of(labelled).collect()  # a row for each language
    share = max(1, limit // max(1, len(known)))
    bounds = [(r.lang, -(2.0**63) + min(1.0, (4 * share + 40) / r.rows) * 2.0**64) for r in known]
    bounds = labelled.sparkSession.createDataFrame(bounds, "lang string, bound double")
    usable = labelled.where("lang is not null and lang <> '' and length(text) >= 3").select("lang", "text", F.xxhash64(key, "text").alias("h"))
    low = usable.select("lang", "h").join(F.broadcast(bounds), "lang").where("cast(h as double) <= bound").select("lang", "h")
    ranked = low.withColumn("n", F.row_number().over(Window.partitionBy("lang").orderBy("h"))).where(F.col("n") <= share)
    last = ranked.groupBy("lang").agg(F.max("h").alias("last"))
    return usable.join(F.broadcast(last), "lang").where("h <= last").dropDuplicates(["lang", "h"]).select("lang", "text")  # a row for each language


def training_rows(labelled: DataFrame, limit: int = TRAINING_ROWS, key: str = "doc_id") -> list[tuple[str, str]]:
    """``chosen_rows`` on the driver: for looking at them."""
    return [(r.lang, r.text) for r in chosen_rows(labelled, limit, key).toLocalIterator()]


def identify(rows: DataFrame, model: TextModel, key: str | list[str] = "doc_id") -> DataFrame:
    """Language of each row of ``rows(key, text, host, declared, suffix)``; absent evidence columns may be null.

    ``key`` names a long column, or several. Returns ``key, lang, confidence, text_lang, kept``. The texts are scanned once; what is shuffled
    is a row's key, host, codes and scores.
    """
    langs = model.languages
    keys = [key] if isinstance(key, str) else list(key)

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, "text"):
            mean, count = model.score(batch.column("text"))
            weight = np.minimum(count, TEXT_WEIGHT)[:, None]
            best = mean.argmax(axis=1)
            best[count == 0] = len(langs) - 1
            mean[count == 0, :-1] = -np.inf  # nothing to go by: no prior makes a language of it
            with np.errstate(invalid="ignore"):
                weighed = np.where(np.isinf(mean), mean, mean * weight)
            scores = pa.LargeListArray.from_arrays(pa.array(np.arange(len(count) + 1) * len(langs)), pa.array(weighed.ravel())).cast(pa.list_(pa.float64()))
            yield pa.record_batch([*(batch.column(c) for c in (*keys, "host", "declared", "suffix")), scores, pa.array(best.astype(np.int32))], names=[*keys, "host", "declared", "suffix", "scores", "guess"])

    schema = f"{', '.join(f'{k} long' for k in keys)}, host string, declared string, suffix string, scores array<double>, guess int"
    scored = stored(free_columns(rows, [*keys, "text", "host", "declared", "suffix"]).mapInArrow(score, schema), "language")

    # all counts below have at most (values x languages) rows
    def shares(by: str) -> Column:
        """Counts of the guesses under ``by``, as an array by language."""
        return F.array(*[F.count_if(F.col("guess") == k).cast("double") for k in range(len(langs))]).alias(by)

    total = F.aggregate("n", F.lit(0.0), lambda a, x: a + x)
    overall = scored.agg(shares("n")).select(F.transform("n", lambda x: (x + 1) / (total + len(langs))).alias("p_all"))
    p_all = [float(x) for x in overall.first().p_all]
    prior = F.array(*[F.lit(p) for p in p_all])

    def smoothed(counts: str, above: Column) -> Column:
        """Counts of one level, drawn towards the level above."""
        n = F.aggregate(counts, F.lit(0.0), lambda a, x: a + x)
        return F.zip_with(counts, above, lambda c, p: (c + SMOOTHING * p) / (n + SMOOTHING))

    hosts = scored.where("host is not null").groupBy("host").agg(shares("n")).withColumn("parent", parent_of(F.col("host")))
    hosts = stored(hosts, "hosts")
    adding = F.array(*[F.sum(F.element_at("n", k + 1)) for k in range(len(langs))])
    parents = hosts.groupBy("parent").agg(adding.alias("m")).select("parent", smoothed("m", prior).alias("p_parent"))
    host_prior = stored(hosts.join(parents, "parent").select("host", smoothed("n", F.col("p_parent")).alias("p_host")), "host-priors")

    zero = F.array(*[F.lit(0.0)] * len(langs))
    out = scored.join(host_prior, "host", "left")
    for column in ("declared", "suffix"):
        values = scored.where(F.col(column).isNotNull()).groupBy(column).agg(shares("n"))
        known = F.aggregate("n", F.lit(0.0), lambda a, x: a + x)
        ratio = values.select(column, F.zip_with("n", prior, lambda c, p: F.log(F.lit(FLOOR) + (1 - FLOOR) * (c + p) / (known + 1.0) / p)).alias(f"e_{column}"))
        out = out.join(stored(ratio, column), column, "left")
    fused = F.coalesce(F.transform("p_host", lambda p: F.log(p)), F.transform(prior, lambda p: F.log(p)))
    for term in (F.col("scores"), F.coalesce("e_declared", zero), F.coalesce("e_suffix", zero)):
        fused = F.zip_with(fused, term, lambda a, b: a + b)
    top = F.array_max("fused")
    odds = F.aggregate(F.transform("fused", lambda x: F.exp(x - top)), F.lit(0.0), lambda a, x: a + x)
    names = F.array(*[F.lit(x) for x in langs])
    out = out.withColumn("fused", fused)
    lang = F.element_at(names, F.array_position("fused", top).cast("int"))
    out = out.select(*keys, lang.alias("lang"), F.round(1 / odds, 6).alias("confidence"), F.element_at(names, F.col("guess") + 1).alias("text_lang"))
    return out.withColumn("kept", F.col("lang") != "und")


def document_evidence(docs: DataFrame) -> DataFrame:
    """Evidence of a document: its text, and its source as host. It has no markup and no address, and its ``lang`` is the model's label, never evidence."""
    none = F.lit(None).cast("string")
    return docs.select("doc_id", "text", F.col("source").alias("host"), none.alias("declared"), none.alias("suffix"))


def page_evidence(pages: DataFrame) -> DataFrame:
    """Evidence of a web page: markup as text, declared language, path or top-level suffix, host."""
    host = F.lower(F.regexp_extract("url", r"://([^/?#]*)", 1))
    suffix = F.coalesce(F.nullif(F.regexp_extract("url", r"://[^/?#]*/([a-z]{2})(?:/|$)", 1), F.lit("")), F.nullif(F.regexp_extract(host, r"\.([a-z]+)$", 1), F.lit("")))
    text = F.regexp_replace(F.regexp_replace("html", r"(?is)<(script|style)[^>]*>.*?</\1>", " "), r"<[^>]*>", " ")
    declared = F.nullif(F.lower(F.regexp_extract("html", r"(?i)<html[^>]*\blang=[\"']?([a-zA-Z]{2})", 1)), F.lit(""))
    return pages.select("page_id", text.alias("text"), F.nullif(host, F.lit("")).alias("host"), declared.alias("declared"), suffix.alias("suffix"))
