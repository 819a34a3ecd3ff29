"""URL filtering by Bloom filter cascades (operator 6).

A cascade holds a set exactly over a known universe of keys: level 0 encodes the listed keys, level 1
those of the universe that level 0 lets through wrongly, level 2 the listed keys that level 1 lets
through, and so on until a level errs on nothing. A key is listed if the first level that refuses it
is an odd one. The universe is every key that the corpus's urls can ask for (each host suffix with
each path prefix as long as a rule's), so every verdict is exact and no join is needed.

Filters are broadcast inside the tasks' code; their size is set by the number of listed keys and
checked against ``MAX_FILTER_BYTES`` before one is built. Longer lists of hosts or addresses are not
broadcast: ``filter_urls`` then looks them up by a join on the key (``by_join``), with the same result.

Of a host only as many suffixes are asked for as the longest listed or ruled host has labels, so a
host of thousands of labels costs no more than its length.

Cases: null url or one without ``://``: empty host and path, no rule, the method's verdict; repeated
rows and pages are judged one by one; very long hosts and paths are judged whole; null and repeated
listed keys do no harm; further columns are ignored; no rows: no rows; no rules and no list: allow.
"""

from __future__ import annotations

import math
from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from blockpress.llm.common import free_columns, mixed, stored

MAX_FILTER_BYTES = 256 << 20
#: Share of the unlisted keys that level 0 lets through.
ERROR = 1 / 64
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


@dataclass(frozen=True)
class Rule:
    host: str
    path: str
    verdict: str

    @property
    def key(self) -> str:
        return self.host + self.path


@dataclass
class Level:
    words: np.ndarray
    probes: int

    def has(self, a: np.ndarray, b: np.ndarray, salt: int) -> np.ndarray:
        out = np.ones(len(a), bool)
        for p in positions(a, b, salt, len(self.words) * 64, self.probes):
            out &= (self.words[p >> np.uint64(6)] >> (p & np.uint64(63))) & np.uint64(1) == 1
        return out


def positions(a: np.ndarray, b: np.ndarray, salt: int, bits: int, probes: int) -> Iterator[np.ndarray]:
    """Bit positions of keys with hashes ``a`` and ``b``, anew for each level."""
    x = mixed(a.view(np.uint64) + np.uint64(salt * 2 + 1))
    y = mixed(b.view(np.uint64) + np.uint64(salt * 2 + 2)) | np.uint64(1)
    for j in range(probes):
        yield (x + np.uint64(j) * y) % np.uint64(bits)


def key_hashes(key: Column) -> list[Column]:
    return [F.xxhash64(key).alias("a"), F.xxhash64(F.lit(1), key).alias("b")]


class Cascade:
    """Exact membership in a listed set, for keys of a universe."""

    def __init__(self, levels: list[Level]):
        self.levels = levels

    def listed(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        out = np.zeros(len(a), bool)
        live = np.arange(len(a))
        for k, level in enumerate(self.levels):
            passed = level.has(a[live], b[live], k)
            if k % 2:
                out[live[~passed]] = True  # no false positive of the level before: listed
            live = live[passed]
        out[live] = len(self.levels) % 2 == 1  # the last level errs on no key
        return out

    @classmethod
    def build(cls, listed: DataFrame, universe: DataFrame, error: float = ERROR) -> Cascade:
        """``listed(key)`` and ``universe(key)``: any rows, repeats and nulls do no harm.

        The universe is scanned once, without a shuffle; only level 0's errors on it are kept.
        """
        listed = stored(listed.where(F.col("key").isNotNull()).select(*key_hashes(F.col("key"))).distinct(), "listed")
        n = listed.count()
        if not n:
            return cls([])
        levels = [filter_of(listed, n, error, 0)]
        others = universe.where(F.col("key").isNotNull()).select(*key_hashes(F.col("key")))
        wrong = stored(passing(others, levels, 0).distinct().join(listed, ["a", "b"], "left_anti"), "wrong")
        right = listed
        while True:
            k = len(levels)
            fresh = wrong if k % 2 else right
            if k > 1:
                fresh = stored(passing(fresh, levels, k - 1), "level")
            n = fresh.count()
            if not n:
                return cls(levels)
            levels.append(filter_of(fresh, n, 0.5, k))
            if k % 2:
                wrong = fresh
            else:
                right = fresh


def passing(keys: DataFrame, levels: list[Level], k: int) -> DataFrame:
    """Keys that level ``k`` lets through."""
    level = levels[k]

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            a, b = (batch.column(c).to_numpy() for c in ("a", "b"))
            yield batch.filter(pa.array(level.has(a, b, k)))

    return keys.select("a", "b").mapInArrow(emit, "a long, b long")


def filter_size(n: int, error: float) -> tuple[int, int]:
    """Probes of a filter of ``n`` keys, and its 64-bit words."""
    probes = max(1, round(math.log2(1 / error)))
    return probes, max(4, math.ceil(n * probes / math.log(2) / 64))


def filter_of(keys: DataFrame, n: int, error: float, k: int) -> Level:
    """Bloom filter of ``n`` hashed keys; bits are set in tasks and joined by a grouped OR."""
    probes, words = filter_size(n, error)
    if words * 8 > MAX_FILTER_BYTES:
        raise ValueError(f"a filter of {words * 8} bytes is too large to broadcast: look the keys up by a join")

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            a, b = (batch.column(c).to_numpy() for c in ("a", "b"))
            at = np.concatenate([*positions(a, b, k, words * 64, probes)]) if len(a) else np.zeros(0, np.uint64)
            at = np.unique(at)
            yield pa.record_batch([pa.array((at >> np.uint64(6)).astype(np.int64)), pa.array(np.left_shift(np.uint64(1), at & np.uint64(63)).view(np.int64))], names=["word", "bits"])

    found = keys.mapInArrow(emit, "word long, bits long").groupBy("word").agg(F.bit_or("bits").alias("bits")).toArrow()  # bounded above
    out = np.zeros(words, np.uint64)
    out[found.column("word").to_numpy()] = found.column("bits").to_numpy().view(np.uint64)
    return Level(out, probes)


def with_parts(pages: DataFrame) -> DataFrame:
    """``page_id, host, path`` of pages."""
    rest = "substring(url, instr(url, '://') + 3)"
    there = "coalesce(instr(url, '://') > 0, false)"
    return free_columns(pages, ["page_id", "url"]).select(
        "page_id",
        F.expr(f"if({there}, translate(regexp_extract({rest}, '^[^/?#]*', 0), '{UPPER}', '{LOWER}'), '')").alias("host"),
        F.expr(f"if({there}, regexp_extract({rest}, '^[^/?#]*([^?#]*)', 1), '')").alias("path"),
    )


def candidate_keys(lengths: Sequence[int], labels: int) -> Column:
    """The host's suffixes of up to so many labels, longest first, each with each prefix of the path of one of these lengths."""
    suffixes = F.expr(f"transform(sequence(least({labels}, size(split(host, '[.]'))), 1), i -> substring_index(host, '.', -i))")
    prefixes = F.array_distinct(F.filter(F.array(*[F.when(F.length("path") >= n, F.substring("path", 1, n)) for n in lengths]), lambda p: p.isNotNull()))
    return F.flatten(F.transform(suffixes, lambda s: F.transform(prefixes, lambda p: F.concat(s, p))))


def most_labels(hosts: DataFrame) -> int:
    """Labels of the longest of ``hosts(key)``."""
    return hosts.agg(F.max(F.size(F.split("key", r"\."))).alias("n")).first().n or 1


def too_many(keys: DataFrame) -> bool:
    """Whether a filter of ``keys(key)`` would be larger than may be broadcast."""
    return filter_size(keys.select("key").distinct().count(), ERROR)[1] * 8 > MAX_FILTER_BYTES


def by_join(parts: DataFrame, hosts: DataFrame, addresses: DataFrame, labels: int) -> DataFrame:
    """``parts`` and ``evil``: whether the host or one above it, or the address, is listed. Different hosts and addresses are looked up once."""
    asked = parts.select("host").distinct().withColumn("path", F.lit("")).withColumn("key", F.explode(candidate_keys([0], labels)))
    bad_hosts = asked.join(hosts.select("key").distinct(), "key", "left_semi").select("host").distinct().withColumn("_h", F.lit(True))
    bad = addresses.where("key is not null").select(F.col("key").alias("address")).distinct().withColumn("_a", F.lit(True))
    found = parts.withColumn("address", F.concat("host", "path")).join(bad_hosts, "host", "left").join(bad, "address", "left")
    return found.select(*parts.columns, (F.coalesce("_h", F.lit(False)) | F.coalesce("_a", F.lit(False))).alias("evil"))


def filter_urls(pages: DataFrame, rules: Sequence[Rule], listed_hosts: Sequence[str] | DataFrame = (), listed_addresses: DataFrame | None = None) -> DataFrame:
    """Judge every page's url: the longest rule that fits, else whether its host or its address is listed.

    ``listed_hosts`` is a sequence or ``(key)`` rows and holds for subdomains too; ``listed_addresses(key)``
    are hosts with their whole paths. Four cascades: the rules' keys, the listed hosts and the listed
    addresses, each over the keys of all urls, and the blocking rules' keys over the rules'.
    """
    spark = pages.sparkSession
    hosts = stored(listed_hosts.select("key") if isinstance(listed_hosts, DataFrame) else keys_frame(spark, listed_hosts), "listed-hosts")
    addresses = stored(listed_addresses.select("key"), "listed-addresses") if listed_addresses is not None else keys_frame(spark, [])
    labels = most_labels(hosts)
    parts = with_parts(pages)
    joined = too_many(hosts) or too_many(addresses)
    parts = by_join(parts, hosts, addresses, labels) if joined else parts.withColumn("evil", F.lit(False))
    if joined:
        hosts = addresses = keys_frame(spark, [])
    rule_labels = max([r.host.count(".") + 1 for r in rules], default=1)
    rule_keys = candidate_keys(sorted({len(r.path) for r in rules}), rule_labels) if rules else F.array().cast("array<string>")
    asked = parts.select("page_id", "host", "path", "evil", rule_keys.alias("keys"), candidate_keys([0], labels).alias("hosts"), F.concat("host", "path").alias("address"))
    fits = Cascade.build(keys_frame(spark, [r.key for r in rules]), asked.select(F.explode("keys").alias("key")))
    blocks = Cascade.build(keys_frame(spark, [r.key for r in rules if r.verdict == "block"]), keys_frame(spark, [r.key for r in rules]))
    bad = Cascade.build(hosts, asked.select(F.explode("hosts").alias("key")))
    places = Cascade.build(addresses, asked.select(F.col("address").alias("key")))
    hashed = asked.select(
        "page_id", "host", "path", "evil", "keys",
        *(F.transform("keys", f).alias(n) for n, f in (("a", lambda k: F.xxhash64(k)), ("b", lambda k: F.xxhash64(F.lit(1), k)), ("size", lambda k: F.length(k)))),
        *(F.transform("hosts", f).alias(n) for n, f in (("ha", lambda k: F.xxhash64(k)), ("hb", lambda k: F.xxhash64(F.lit(1), k)))),
        F.xxhash64("address").alias("pa"), F.xxhash64(F.lit(1), "address").alias("pb"),
    )

    def flat(column: pa.Array) -> np.ndarray:
        return column.flatten().to_numpy(zero_copy_only=False).astype(np.int64)

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = batch.num_rows
            if not n:
                continue
            keys = batch.column("keys")
            row = np.repeat(np.arange(n), keys.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64))
            a, b, size = (flat(batch.column(c)) for c in ("a", "b", "size"))
            hit = np.flatnonzero(fits.listed(a, b)) if len(a) else np.zeros(0, np.int64)
            best = np.full(n, -1, np.int64)
            order = hit[np.lexsort((-hit, size[hit], row[hit]))]  # longest last; of equal ones the longer host
            best[row[order]] = order
            found = best >= 0
            rule = np.full(n, None, object)
            rule[found] = keys.flatten().take(pa.array(best[found])).to_pylist()
            verdict = np.full(n, "allow", object)
            if found.any():
                verdict[found] = np.where(blocks.listed(a[best[found]], b[best[found]]), "block", "allow")
            hosts = np.repeat(np.arange(n), batch.column("ha").value_lengths().to_numpy(zero_copy_only=False).astype(np.int64))
            evil = batch.column("evil").to_numpy(zero_copy_only=False).astype(bool)
            if len(hosts):
                evil[hosts[bad.listed(flat(batch.column("ha")), flat(batch.column("hb")))]] = True
            evil |= places.listed(batch.column("pa").to_numpy(), batch.column("pb").to_numpy())
            verdict[evil & ~found] = "block"
            yield pa.record_batch([batch.column("page_id"), batch.column("host"), batch.column("path"), pa.array(rule.tolist(), pa.string()), pa.array(verdict.tolist(), pa.string())], names=["page_id", "host", "path", "rule", "verdict"])

    return hashed.mapInArrow(judge, "page_id long, host string, path string, rule string, verdict string")


def keys_frame(spark: SparkSession, keys: Sequence[str]) -> DataFrame:
    return spark.createDataFrame([(k,) for k in keys], "key string")
