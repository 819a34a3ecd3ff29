"""From a raw table to a table of categorical codes.

Columns with at most ``max_card`` values become dictionary codes, numeric ones with more become
quantile codes, others are dropped. The codebook is fitted once, in three scans, and small (``max_card``
rows a column at most), so it goes to the driver and into the plan as constants; encoding is one narrow
projection. NULL is a symbol of its own, coded behind the values.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from blockpress.sources.storage import kept

MAX_CARD = 256
BINS = 4
#: Ranks to each side of a quantile, as a share of all, between which its values are counted exactly: above a sketch's error.
SLACK = 3e-4
#: Rows that are sorted at once for a summary of their values, and ranks that a summary holds.
SUMMARY_ROWS, SUMMARY_RANKS = 1 << 20, 2048
CODEBOOK = "col_id int, col_name string, kind string, code smallint, value string, cut_lo double, cut_hi double"


def is_numeric(kind: T.DataType) -> bool:
    return isinstance(kind, (T.NumericType, T.DateType, T.TimestampType, T.TimestampNTZType))


def numeric(df: DataFrame, name: str) -> Column:
    """A number-like column as double: dates in days, times in microseconds."""
    kind, c = df.schema[name].dataType, F.col(name)
    if isinstance(kind, T.DateType):
        return F.datediff(c, F.lit("1970-01-01").cast("date")).cast("double")
    if isinstance(kind, (T.TimestampType, T.TimestampNTZType)):
        return F.unix_micros(c.cast("timestamp")).cast("double")
    return c.cast("double")


def profile_columns(df: DataFrame, max_card: int = MAX_CARD) -> DataFrame:
    """``col_name, dtype, n_distinct, kind``: C (dictionary), Q (quantiles) or D (dropped).

    One pass of sketches; only columns near the limit or below are counted exactly, in a second pass.
    ``n_distinct`` is exact up to ``max_card`` and null beyond. NULL does not count as a value.
    """
    names = df.columns
    rough = df.agg(*[F.approx_count_distinct(F.col(c), 0.05).alias(c) for c in names]).first()
    near = [c for c in names if rough[c] <= 2 * max_card]
    exact = df.agg(*[F.count_distinct(F.col(c)).alias(c) for c in near]).first() if near else {}
    rows = []
    for c in names:
        n = exact[c] if c in near else None
        kind = "C" if n is not None and n <= max_card else "Q" if is_numeric(df.schema[c].dataType) else "D"
        rows.append((c, df.schema[c].dataType.simpleString(), n if kind == "C" else None, kind))
    return df.sparkSession.createDataFrame(rows, "col_name string, dtype string, n_distinct bigint, kind string")


@dataclass
class ColumnCodes:
    name: str
    kind: str
    values: list = field(default_factory=list)
    cuts: list[float] = field(default_factory=list)
    has_null: bool = False

    @property
    def card(self) -> int:
        """Codes that really occur."""
        return (len(self.values) if self.kind == "C" else len(self.cuts) + 1) + self.has_null


@dataclass
class Codebook:
    """Kept columns in order, with their codes."""

    columns: list[ColumnCodes]
    dropped: list[str] = field(default_factory=list)

    @property
    def cards(self) -> list[int]:
        return [c.card for c in self.columns]

    @property
    def n(self) -> int:
        return len(self.columns)

    def frame(self, spark: SparkSession) -> DataFrame:
        rows = []
        for j, c in enumerate(self.columns):
            if c.kind == "C":
                rows += [(j, c.name, "C", k, str(v), None, None) for k, v in enumerate(c.values)]
            else:
                edges = [None, *c.cuts, None]
                rows += [(j, c.name, "Q", k, None, edges[k], edges[k + 1]) for k in range(len(c.cuts) + 1)]
            if c.has_null:
                rows.append((j, c.name, c.kind, c.card - 1, None, None, None))
        return spark.createDataFrame(rows, CODEBOOK)


@dataclass
class Summary:
    """Of a column: whether it has nulls, its values where they are few, and for each quantile a value not above and one not below."""

    has_null: bool
    values: list | None
    around: list[float] | None


def summaries(df: DataFrame, shares: list[float], max_card: int = MAX_CARD) -> dict[str, Summary]:
    """Summaries of number, date, time, boolean and text columns, in one scan; other columns have none, and neither have those with NaN or negative zeros.

    Tasks sort stretches of rows and tell values at even ranks; a column's ranks are added up in a task of its own, so that
    its quantiles surely lie between the two values told. Times with few values have none either.
    """
    import datetime as dt

    import numpy as np
    import pyarrow as pa

    whole = (T.ByteType, T.ShortType, T.IntegerType, T.LongType, T.BooleanType, T.DateType, T.TimestampType, T.TimestampNTZType)
    kinds = {c: df.schema[c].dataType for c in df.columns}
    names = [c for c, k in kinds.items() if isinstance(k, (*whole, T.DoubleType)) or k == T.StringType()]
    if not names:
        return {}
    told = "col int, nulls long, n long, many boolean, odd boolean, numbers binary, ranks binary, texts array<string>"
    fields = [f.split()[0] for f in told.split(", ")]
    types = [pa.int32(), pa.int64(), pa.int64(), pa.bool_(), pa.bool_(), pa.binary(), pa.binary(), pa.list_(pa.string())]
    text = [isinstance(kinds[c], T.StringType) for c in names]
    real = [isinstance(kinds[c], T.DoubleType) for c in names]

    def shown(c):
        k = kinds[c]
        if isinstance(k, T.DateType):
            return F.unix_date(c).cast("long")
        if isinstance(k, (T.TimestampType, T.TimestampNTZType)):
            return F.unix_micros(F.col(c).cast("timestamp"))
        return F.col(c) if isinstance(k, (T.StringType, T.DoubleType)) else F.col(c).cast("long")

    def summary(j, arrays):
        x = pa.chunked_array(arrays)
        nulls, x = x.null_count, x.drop_null()
        if text[j]:
            values = x.unique()
            few = len(values) <= max_card
            return j, nulls, len(x), not few, False, None, None, values.to_pylist() if few else []
        x = x.to_numpy()
        odd = real[j] and bool(np.isnan(x).any() or ((x == 0) & np.signbit(x)).any())
        x = np.sort(x)
        new = np.flatnonzero(np.concatenate([[True], x[1:] != x[:-1]])) if len(x) else np.zeros(0, np.int64)
        at = new if len(new) <= SUMMARY_RANKS else np.unique(np.linspace(0, len(x) - 1, SUMMARY_RANKS + 1).astype(np.int64))
        if len(new) <= SUMMARY_RANKS and len(x):
            at = np.unique(np.concatenate([new, np.append(new[1:] - 1, len(x) - 1)]))  # first and last of each value
        return j, nulls, len(x), len(new) > max_card, odd, x[at].tobytes(), at.astype(np.int64).tobytes(), []

    def tell(batches):
        held, rows = [[] for _ in names], 0

        def table():
            out = [summary(j, arrays) for j, arrays in enumerate(held)]
            return pa.record_batch([pa.array(c, t) for c, t in zip(zip(*out, strict=True), types, strict=True)], names=fields)

        for batch in batches:
            for j in range(len(names)):
                held[j].append(batch.column(j))
            rows += batch.num_rows
            if rows >= SUMMARY_ROWS:
                yield table()
                held, rows = [[] for _ in names], 0
        if rows:
            yield table()

    def add(key, part):
        j, parts = key[0].as_py(), part.to_pylist()
        n, nulls = sum(p["n"] for p in parts), sum(p["nulls"] for p in parts)
        odd, many = any(p["odd"] for p in parts), any(p["many"] for p in parts)
        texts, numbers, around = [], np.zeros(0, float if real[j] else np.int64), np.zeros(0)
        if text[j]:
            texts = sorted({t for p in parts for t in p["texts"]})
            many |= len(texts) > max_card
        else:
            points = [(np.frombuffer(p["numbers"], numbers.dtype), np.frombuffer(p["ranks"], np.int64), p["n"]) for p in parts if p["n"]]
            if not many and points:
                numbers = np.unique(np.concatenate([x for x, _, _ in points]))
                many = len(numbers) > max_card
            if n and not odd:
                every = np.unique(np.concatenate([x for x, _, _ in points]))

                def below(v):  # at most so many are less
                    return sum(int(r[k]) if (k := int(np.searchsorted(x, v, "left"))) < len(x) else m for x, r, m in points)

                def upto(v):  # at least so many are not more
                    return sum(int(r[k - 1]) + 1 if (k := int(np.searchsorted(x, v, "right"))) else 0 for x, r, _ in points)

                found = []
                for share in shares:
                    place = (n - 1) * share
                    lo, hi = 0, len(every) - 1  # the greatest value that at most floor(place) are less than
                    while lo < hi:
                        mid = (lo + hi + 1) // 2
                        lo, hi = (mid, hi) if below(every[mid]) <= math.floor(place) else (lo, mid - 1)
                    first = every[lo]
                    lo, hi = 0, len(every) - 1  # the least value that more than ceil(place) are not above
                    while lo < hi:
                        mid = (lo + hi) // 2
                        lo, hi = (lo, mid) if upto(every[mid]) >= math.ceil(place) + 1 else (mid + 1, hi)
                    found += [float(first), float(every[lo])]
                around = np.array(found)
        few = b"" if many else numbers.tobytes()
        out = (j, nulls, n, many, odd, few, around.tobytes(), [] if many else texts)
        return pa.table([pa.array([x], t) for x, t in zip(out, types, strict=True)], names=fields)

    rows = df.select(*[shown(c).alias(f"c{j}") for j, c in enumerate(names)]).mapInArrow(tell, told).groupBy("col").applyInArrow(add, told).collect()  # a row a column
    out = {}
    for r in rows:
        c, k = names[r.col], kinds[names[r.col]]
        values = None
        if not r.many:
            if isinstance(k, (T.TimestampType, T.TimestampNTZType)):
                continue
            values = list(r.texts) if text[r.col] else np.frombuffer(bytes(r.numbers), float if real[r.col] else np.int64).tolist()
            if isinstance(k, T.DateType):
                values = [dt.date(1970, 1, 1) + dt.timedelta(days=v) for v in values]
            elif isinstance(k, T.BooleanType):
                values = [bool(v) for v in values]
        if not r.odd:
            out[c] = Summary(r.nulls > 0, values, None if text[r.col] or not r.n else np.frombuffer(bytes(r.ranks)).tolist())
    return out


def fit_codebook(df: DataFrame, max_card: int = MAX_CARD, bins: int = BINS, exact: bool = True) -> Codebook:
    """Fit codes to ``df``: one scan of summaries; columns without any take one of sketches and null counts, one of value sets and quantiles.

    ``exact`` quantiles take a further scan for the values near them; ``exact=False`` takes
    sketches, with a rank error of one in 10,000.
    """
    names = df.columns
    shares = [k / bins for k in range(1, bins)]
    told = summaries(df, shares, max_card) if exact else {}
    rest = [j for j, c in enumerate(names) if c not in told]
    rough = df.agg(*[F.approx_count_distinct(F.col(names[j]), 0.05).alias(f"d{j}") for j in rest], *[F.count_if(F.col(names[j]).isNull()).alias(f"n{j}") for j in rest]).first() if rest else None
    asked = F.array(*[F.lit(q) for q in shares])
    around = F.array(*[F.lit(min(max(q + e, 0.0), 1.0)) for q in shares for e in (-SLACK, SLACK)])
    cut = lambda c: F.percentile_approx(numeric(df, c), around if exact else asked, 10000)
    wanted = []
    for j in rest:
        c = names[j]
        if rough[f"d{j}"] <= 2 * max_card:  # by the sketch's error, no column within the limit is beyond this
            wanted.append(F.array_sort(F.collect_set(F.col(c))).alias(f"v{j}"))
        if rough[f"d{j}"] > max_card // 2 and is_numeric(df.schema[c].dataType):
            wanted.append(cut(c).alias(f"q{j}"))
    found = df.agg(*wanted).first() if wanted else None
    got = found.asDict() if found else {}
    nulls = {j: rough[f"n{j}"] > 0 for j in rest}
    for j, c in enumerate(names):
        if c in told:
            nulls[j] = told[c].has_null
            if told[c].values is not None:
                got[f"v{j}"] = told[c].values
            elif is_numeric(df.schema[c].dataType):
                got[f"q{j}"] = told[c].around
    columns, dropped = [], []
    cuts = {f"q{j}": got[f"q{j}"] for j in range(len(names)) if f"q{j}" in got and not (f"v{j}" in got and len(got[f"v{j}"]) <= max_card)}
    if exact and cuts:
        cuts = dict(zip(cuts, exact_quantiles(df, [names[int(q[1:])] for q in cuts], shares, list(cuts.values())), strict=True))
    for j, c in enumerate(names):
        if f"v{j}" in got and len(got[f"v{j}"]) <= max_card:
            columns.append(ColumnCodes(c, "C", list(got[f"v{j}"]), has_null=nulls[j]))
        elif f"q{j}" in got:
            columns.append(ColumnCodes(c, "Q", cuts=[float(x) for x in cuts[f"q{j}"] or []], has_null=nulls[j]))
        else:
            dropped.append(c)
    return Codebook(columns, dropped)


def exact_quantiles(df: DataFrame, names: list[str], shares: list[float], around: list[list[float] | None]) -> list[list[float] | None]:
    """Interpolated quantiles of each column, as ``percentile`` has them, in one scan: ``around`` has a value below and one above for each share.

    Tasks count the values below each stretch and add up those within; their ranks are told in Spark, and two values
    for each quantile reach the driver. A column whose stretch misses its rank is done by ``percentile``.
    """
    import numpy as np
    import pyarrow as pa

    bounds = [(j, k, a[2 * k], a[2 * k + 1]) for j, a in enumerate(around) if a for k in range(len(shares))]

    def count(batches):
        below = np.zeros(len(bounds), np.int64)
        seen = np.zeros(len(names), np.int64)
        within: list[list[tuple[np.ndarray, np.ndarray]]] = [[] for _ in bounds]
        for batch in batches:
            cells = [batch.column(j).drop_null().to_numpy(zero_copy_only=False) for j in range(len(names))]
            seen += [len(x) for x in cells]
            for b, (j, _, lo, hi) in enumerate(bounds):
                x = cells[j]
                below[b] += np.count_nonzero(x < lo)
                inside = x[(x >= lo) & (x <= hi)]
                if len(inside):
                    within[b].append(np.unique(inside, return_counts=True))
        out = [(len(bounds) + j, None, int(c)) for j, c in enumerate(seen.tolist())] + [(b, None, int(c)) for b, c in enumerate(below.tolist())]
        id_, value, n = (pa.array(c, t) for c, t in zip(zip(*out, strict=True), (pa.int32(), pa.float64(), pa.int64()), strict=True))
        yield pa.record_batch([id_, value, n], names=["b", "x", "n"])
        for b, parts in enumerate(within):
            if parts:
                x, at = np.unique(np.concatenate([v for v, _ in parts]), return_inverse=True)
                c = np.bincount(at, np.concatenate([c for _, c in parts])).astype(np.int64)
                yield pa.record_batch([pa.array(np.full(len(x), b, np.int32)), pa.array(x), pa.array(c)], names=["b", "x", "n"])

    found = kept(df.select(*[numeric(df, c).alias(f"x{j}") for j, c in enumerate(names)]).mapInArrow(count, "b int, x double, n long").groupBy("b", "x").agg(F.sum("n").alias("n")), "ranks")
    fixed = {r.b: r.n for r in found.where("x is null").collect()}  # a row a stretch and a column
    ranks, want = [], {}
    for b, (j, k, _, _) in enumerate(bounds):
        place = (fixed.get(len(bounds) + j, 0) - 1) * shares[k]
        want[b] = (place, math.floor(place), math.ceil(place))
        ranks += [(b, at, int(want[b][at + 1]) - fixed.get(b, 0)) for at in (0, 1)]
    upto = F.sum("n").over(Window.partitionBy("b").orderBy("x"))
    run = found.where("x is not null").withColumn("upto", upto)
    asked = df.sparkSession.createDataFrame(ranks or [(-1, 0, 0)], "b int, at int, rank long")
    hit = run.join(F.broadcast(asked), "b").where((F.col("rank") < F.col("upto")) & (F.col("rank") >= F.col("upto") - F.col("n")))
    values = {(r.b, r.at): r.x for r in hit.collect()}  # two rows a stretch
    out: list[list[float] | None] = []
    for j, c in enumerate(names):
        mine = [b for b, bound in enumerate(bounds) if bound[0] == j]
        if around[j] and all((b, at) in values for b in mine for at in (0, 1)):
            pairs = [(want[b], values[b, 0], values[b, 1]) for b in mine]
            out.append([x if lo == hi or x == y else (hi - place) * x + (place - lo) * y for (place, lo, hi), x, y in pairs])
        else:
            out.append(df.agg(F.percentile(numeric(df, c), F.array(*[F.lit(q) for q in shares]))).first()[0])
    return out


def code_of(df: DataFrame, codes: ColumnCodes) -> Column:
    """Code of one column: place in the sorted values, or the number of cuts strictly below."""
    c = F.col(codes.name)
    if codes.kind == "C":
        kind = df.schema[codes.name].dataType
        values = F.array(*[F.lit(v).cast(kind) for v in codes.values])
        found = F.array_position(values, c) - 1
    else:
        x = numeric(df, codes.name)
        found = sum((F.when(x > cut, 1).otherwise(0) for cut in codes.cuts), F.lit(0))
    if codes.has_null:
        found = F.when(c.isNull(), codes.card - 1).otherwise(found)
    return found.cast("smallint")


def encode_table(df: DataFrame, book: Codebook, keep: list[str] | None = None) -> DataFrame:
    """``keep`` columns and ``codes ARRAY<SMALLINT>``; only kept columns reach the scan. Unseen values: -1."""
    return df.select(*(keep or []), F.array(*[code_of(df, c) for c in book.columns]).alias("codes"))


def encode_rows(df: DataFrame, book: Codebook, key: str) -> DataFrame:
    """``encode_table`` of ``df`` with the one column ``key`` kept, batch by batch in numpy: values are looked up, not compared one after the other.

    Columns of other kinds than numbers, dates, booleans and texts take ``code_of``.
    """
    import numpy as np
    import pyarrow as pa
    import pyarrow.compute as pc

    plain = (T.ByteType, T.ShortType, T.IntegerType, T.LongType, T.DoubleType, T.BooleanType, T.DateType)
    shown, steps = [], []
    for j, c in enumerate(book.columns):
        kind = df.schema[c.name].dataType
        null = c.card - 1 if c.has_null else None if c.kind == "C" else 0
        if c.kind == "Q":
            shown.append(numeric(df, c.name).alias(f"c{j}"))
            steps.append(("cuts", np.array(c.cuts, float), null))
        elif isinstance(kind, plain) and c.values and not any(v != v for v in c.values):
            shown.append((F.unix_date(c.name) if isinstance(kind, T.DateType) else F.col(c.name).cast("int") if isinstance(kind, T.BooleanType) else F.col(c.name)).alias(f"c{j}"))
            values = [v.toordinal() - 719163 if isinstance(kind, T.DateType) else int(v) if isinstance(kind, T.BooleanType) else v for v in c.values]
            steps.append(("numbers", np.array(values), null))
        elif isinstance(kind, T.StringType) and c.values and kind == T.StringType():
            shown.append(F.col(c.name).alias(f"c{j}"))
            steps.append(("texts", c.values, null))
        else:
            shown.append(code_of(df, c).alias(f"c{j}"))
            steps.append(("codes", None, None))

    def emit(batches):
        for batch in batches:
            m, n = batch.num_rows, len(steps)
            cells, none = np.zeros((m, n), np.int16), np.zeros((m, n), bool)
            for j, (how, values, null) in enumerate(steps):
                column = batch.column(j + 1)
                gone = column.is_null().to_numpy(zero_copy_only=False)
                if how == "texts":
                    got = pc.fill_null(pc.index_in(column, value_set=pa.array(values, column.type)), -1).to_numpy(zero_copy_only=False)
                elif how == "codes":
                    got = pc.fill_null(column, 0).to_numpy(zero_copy_only=False)
                else:
                    x = (pc.fill_null(column, 0) if column.null_count else column).to_numpy(zero_copy_only=False)
                    got = np.searchsorted(values, x)  # as many cuts lie strictly below
                    if how == "numbers":
                        got = np.where(values[np.minimum(got, len(values) - 1)] == x, got, -1)
                cells[:, j] = got
                if gone.any():
                    none[gone, j] = null is None
                    cells[gone, j] = null or 0
            at = np.arange(m + 1, dtype=np.int32) * n
            flat = pa.array(cells.ravel(), mask=none.ravel() if none.any() else None)
            yield pa.record_batch([batch.column(0), pa.ListArray.from_arrays(pa.array(at), flat)], names=[key, "codes"])

    schema = T.StructType([df.schema[key], T.StructField("codes", T.ArrayType(T.ShortType()))])
    return df.select(key, *shown).mapInArrow(emit, schema)


def code_counts(codes: DataFrame) -> DataFrame:
    """``col_id, code, cnt`` of ``codes(codes)``: a task adds its cells up in arrays, so that only counts are shuffled."""
    import numpy as np
    import pyarrow as pa

    def emit(batches):
        total = None
        for batch in batches:
            if not batch.num_rows:
                continue
            cells = batch.column("codes").flatten().to_numpy(zero_copy_only=False).astype(np.int64).reshape(batch.num_rows, -1) + 1
            n = cells.shape[1]
            wide = max(int(cells.max()) + 1, 0 if total is None else total.shape[1])
            own = np.bincount((cells + np.arange(n) * wide).ravel(), minlength=n * wide).reshape(n, wide)
            if total is not None:
                own[:, : total.shape[1]] += total
            total = own
        if total is not None:
            col, code = np.nonzero(total)
            yield pa.record_batch([pa.array(col.astype(np.int32)), pa.array((code - 1).astype(np.int32)), pa.array(total[col, code])], names=["col_id", "code", "cnt"])

    return codes.select("codes").mapInArrow(emit, "col_id int, code int, cnt long").groupBy("col_id", "code").agg(F.sum("cnt").alias("cnt"))


def assign_row_ids(df: DataFrame, order: list[str | Column], keep: list[str] | None = None) -> DataFrame:
    """A dense ``row_id`` from 0 in the order given, and the columns of ``keep`` (all); no task sees more than its range.

    Rows go by range, are numbered within their partition and written; the partitions' sizes (one row
    each) give the offsets. Rows that tie in ``order`` are numbered as they come, once and for all.
    """
    spark = df.sparkSession
    parts = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    ranged = df.repartitionByRange(parts, *order).sortWithinPartitions(*order)
    names = df.columns if keep is None else keep
    numbered = kept(ranged.select(*names, F.monotonically_increasing_id().alias("_n")), "rows")
    part, inside = F.shiftright("_n", 33), F.col("_n").bitwiseAND((1 << 33) - 1)
    sizes = sorted((r.part, r.n) for r in numbered.groupBy(part.alias("part")).agg(F.count("*").alias("n")).collect())
    offsets, before = [], 0
    for p, n in sizes:
        offsets.append((p, before))
        before += n
    lookup = spark.createDataFrame(offsets or [(0, 0)], "part long, before long")
    joined = numbered.withColumn("part", part).join(F.broadcast(lookup), "part")
    return joined.select((F.col("before") + inside).alias("row_id"), *names)


def shuffle_rows(codes: DataFrame, seed: int = 42) -> DataFrame:
    """Permute the rows of ``codes(row_id, ...)``: by a hash of their number and the seed, the same in any SQL engine."""
    key = F.md5(F.concat_ws("|", F.lit(str(seed)), F.col("_r").cast("string")))
    return assign_row_ids(codes.withColumnRenamed("row_id", "_r").withColumn("_k", key).drop("_r"), ["_k"], [c for c in codes.columns if c != "row_id"])


def to_long(codes: DataFrame) -> DataFrame:
    """``row_id, col_id, code``."""
    return codes.select("row_id", F.posexplode("codes").alias("col_id", "code"))


def image(codes: DataFrame, cards: list[int], psi: str = "index", values: list[list[float]] | None = None) -> DataFrame:
    """Numeric image of the codes: ``index`` (the codes), ``scaled`` (to 0..1 by column), ``onehot`` (an indicator for each symbol, columns side by side) or ``mapping`` (``values`` by column and code)."""
    if psi == "index":
        made = F.transform("codes", lambda x: x.cast("double"))
    elif psi == "scaled":
        top = F.array(*[F.lit(float(max(k - 1, 1))) for k in cards])
        made = F.zip_with("codes", top, lambda x, t: x / t)
    elif psi == "onehot":
        width = F.array(*[F.lit(int(k)) for k in cards])
        made = F.flatten(F.zip_with("codes", width, lambda x, k: F.transform(F.sequence(F.lit(0), k - 1), lambda s: (s == x).cast("double"))))
    elif psi == "mapping":
        table = F.array(*[F.array(*[F.lit(float(x)) for x in v]) for v in values])
        made = F.zip_with("codes", table, lambda x, v: F.element_at(v, x.cast("int") + 1))
    else:
        raise ValueError(psi)
    return codes.select("row_id", made.alias("x"))


def raw_size(cards: list[int], m: int, unit: str = "KB") -> float:
    """Uncoded size in kilobytes or megabytes of 1,024."""
    return raw_bits(cards, m) / 8 / 1024 ** {"B": 0, "KB": 1, "MB": 2}[unit]


def raw_bits(cards: list[int], m: int, alphabet: str = "per_column") -> float:
    """Bits of the uncoded table: log2 of each column's alphabet, or of the largest one for all."""
    import math

    if alphabet == "per_column":
        return m * sum(math.log2(k) for k in cards if k > 1)
    return m * len(cards) * math.log2(max(max(cards), 2))
