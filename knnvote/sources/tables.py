"""Reading the given tables as points and queries, other vector inputs, and generated vectors."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.vectors import normalize, valid
from ..plans.config import VectorSchemaError
from .storage import settle

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


WIDE = 64  # dimensions beyond which vectors are filled in Arrow blocks


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register(spark: SparkSession, sf_dir: str) -> None:
    """All tables as temporary views."""
    for name in TABLES:
        load(spark, sf_dir, name).createOrReplaceTempView(name)


def read_any(spark: SparkSession, path: str, fmt: str = "parquet", schema: str | None = None, **options: str) -> DataFrame:
    """Parquet, ORC, JSON, CSV or text."""
    reader = spark.read.options(**options)
    return (reader.schema(schema) if schema else reader).format(fmt).load(path)


def write(df: DataFrame, path: str, fmt: str = "parquet", mode: str = "overwrite", **options: str) -> None:
    """To files, or to nowhere with fmt noop, for timing."""
    writer = df.write.mode(mode).options(**options)
    writer.format("noop").save() if fmt == "noop" else writer.format(fmt).save(path)


def to_points(df: DataFrame, id_col: str, vec_col: str, kind: str = "array", on_invalid: str = "raise") -> DataFrame:
    """(id long, vec array<float>) from a numeric array, an ml Vector, comma-separated text, a JSON array, or packed float32.

    Rows with null ids or vectors, null or NaN components, or a length other than the longest are dropped, or raise
    VectorSchemaError.
    """
    v = F.col(vec_col)
    if kind == "ml":
        from pyspark.ml.functions import vector_to_array

        v = vector_to_array(v)
    elif kind == "csv":
        v = F.transform(F.split(v, ","), lambda x: F.trim(x))
    elif kind == "json":
        v = F.from_json(v, "array<double>")
    elif kind == "binary":
        df = df.select(F.col(id_col), v.alias(vec_col)).mapInArrow(_unpacked, f"`{id_col}` {df.schema[id_col].dataType.simpleString()}, `{vec_col}` array<float>")
        v = F.col(vec_col)
    out = df.select(F.col(id_col).cast("long").alias("id"), v.cast("array<float>").alias("vec"))
    d = out.agg(F.max(F.size("vec"))).first()[0]
    good = valid("vec", d) & F.col("id").isNotNull()
    if on_invalid == "drop":
        return out.where(good)
    bad = out.where(~good).limit(1).count()
    if bad:
        raise VectorSchemaError(f"a vector is null, holds null or NaN, or has not {d} components")
    return out


def _unpacked(batches):
    import numpy as np
    import pyarrow as pa

    for b in batches:
        lists = [None if x is None else np.frombuffer(x, "<f4") for x in b.column(1).to_pylist()]
        yield pa.record_batch([b.column(0), pa.array(lists, pa.list_(pa.float32()))], names=b.schema.names)


def embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec"))


def hold_out(points: DataFrame, queries: int = 100) -> tuple[DataFrame, DataFrame]:
    """(points left, queries as qid, qvec): the rows of least md5 of "q:" and the id, at most a fifth of all."""
    n = points.count()
    ids = points.select("id", F.md5(F.concat(F.lit("q:"), F.col("id").cast("string"))).alias("h")).orderBy("h", "id").limit(min(queries, n // 5)).select("id")
    held = points.join(F.broadcast(ids), "id", "left_semi").select(F.col("id").alias("qid"), F.col("vec").alias("qvec"))
    return points.join(F.broadcast(ids), "id", "left_anti"), held


def gaussian_sphere(spark: SparkSession, n: int, d: int, seed: int = 42, partitions: int | None = None) -> DataFrame:
    """(id, vec): n normal vectors scaled to length 1, the same on every run."""
    def component(i: Column, j: Column) -> Column:
        u = lambda part: (F.shiftrightunsigned(F.xxhash64(F.lit(seed), i, j, F.lit(part)), 11).cast("double") + 1) / 9007199254740993.0
        return F.sqrt(-2 * F.ln(u(0))) * F.cos(2 * F.pi() * u(1))

    rows = spark.range(0, n, 1, partitions) if partitions else spark.range(n)
    raw = F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda j: component(F.col("id"), j))
    return rows.withColumn("raw", raw).select("id", normalize("raw").cast("array<float>").alias("vec"))


# ---- vectors from the other tables ------------------------------------------------------------

def histogram(rows: DataFrame, key: str, bucket: str, value: str, d: int) -> DataFrame:
    """(id, vec): the sum of value in each of d buckets of a key; buckets without rows are 0."""
    sums = rows.groupBy(key, bucket).agg(F.sum(value).alias("v"))
    if d > WIDE:
        held = sums.groupBy(F.col(key).alias("id")).agg(F.collect_list(F.struct(F.col(bucket).cast("int").alias("b"), F.col("v").cast("double").alias("v"))).alias("m"))
        return held.select("id", F.col("m.b").alias("b"), F.col("m.v").alias("v")).mapInArrow(_spread(d), "id long, vec array<double>")
    held = sums.groupBy(F.col(key).alias("id")).agg(F.map_from_entries(F.collect_list(F.struct(bucket, "v"))).alias("m"))
    # built-in expressions alone: the map is read once for each of the d places
    return held.select("id", F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda i: F.coalesce(F.try_element_at("m", i.cast("int")), F.lit(0.0)).cast("double")).alias("vec"))


def _spread(d: int):
    """Blocks of sparse rows (id, b, v) as dense vectors of d places: a place is written once, whatever d is."""
    import numpy as np
    import pyarrow as pa

    rows = max(1, (1 << 21) // d)  # 16 MB of doubles a batch

    def run(batches):
        for whole in batches:
            for at in range(0, whole.num_rows, rows):
                b = whole.slice(at, rows)
                lengths = np.diff(b.column(1).offsets.to_numpy())
                x = np.zeros((b.num_rows, d))
                x[np.repeat(np.arange(b.num_rows), lengths), b.column(1).flatten().to_numpy()] = b.column(2).flatten().to_numpy()
                vec = pa.ListArray.from_arrays(pa.array(np.arange(0, x.size + 1, d, dtype=np.int32)), pa.array(x.ravel()))
                yield pa.record_batch([b.column(0).cast(pa.int64()), vec], names=["id", "vec"])

    return run


def user_profiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events by user: 5 types x 24 hours."""
    e = load(spark, sf_dir, "events")
    kinds = e.select("event_type").distinct().withColumn("k", F.row_number().over(W.orderBy("event_type")) - 1)  # a handful of types
    e = e.join(F.broadcast(kinds), "event_type").select(F.col("user_id").alias("u"), (F.col("k") * 24 + F.hour("ts")).cast("int").alias("b"), F.lit(1.0).alias("v"))
    return histogram(e, "u", "b", "v", 120)


def part_demand(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quantity sold by part in 128 buckets of 20 days from 1995-01-01."""
    rows = load(spark, sf_dir, "lineitem").select(F.col("l_partkey").alias("p"), F.expr("int(datediff(date(l_shipdate), date'1995-01-01') div 20)").alias("b"), F.col("l_quantity").alias("v"))
    return histogram(rows.where("b between 0 and 127"), "p", "b", "v", 128)


def customer_brand(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Spend by customer and brand, over a star join."""
    brands = load(spark, sf_dir, "part").select("p_brand").distinct().withColumn("b", (F.row_number().over(W.orderBy("p_brand")) - 1).cast("int"))  # 25 brands
    parts = load(spark, sf_dir, "part").select("p_partkey", "p_brand").join(F.broadcast(brands), "p_brand").select("p_partkey", "b")
    lines = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("v"))
    sold = lines.join(load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    sold = sold.join(load(spark, sf_dir, "customer").select("c_custkey"), F.col("o_custkey") == F.col("c_custkey")).join(parts, F.col("l_partkey") == F.col("p_partkey"))
    return histogram(sold, "c_custkey", "b", "v", 25)


def _whole(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(u, text) in lower case, a row a key: the texts of a repeated key are joined by a line break, which no word or pair of letters spans."""
    rows = docs.select(F.col(id_col).alias("u"), F.lower(text_col).alias("text"))
    again = rows.groupBy("u").count().where("count > 1").select(F.col("u").alias("again"))
    if again.isEmpty():
        return rows
    same = F.col("u").eqNullSafe(F.col("again"))
    joined = rows.join(again, same, "left_semi").groupBy("u").agg(F.concat_ws("\n", F.collect_list("text")).alias("text"))
    return rows.join(again, same, "left_anti").unionByName(joined)


def letter_bigrams(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents as counts of letter pairs in 784 hashed buckets, at length 1."""
    return _whole(load(spark, sf_dir, "documents"), "doc_id", "text").mapInArrow(_pair_counts(784), "id long, vec array<double>")


def _pair_counts(d: int):
    """Counts of the overlapping pairs of letters a to z, hashed, at length 1; texts without a pair give no row.

    The bytes of a block of texts are looked up at once: in UTF-8, other characters have no byte of a letter.
    """
    import numpy as np
    import pyarrow as pa

    letters = "abcdefghijklmnopqrstuvwxyz"
    place = np.array([_bucket_of((a + b).encode(), d) for a in letters for b in letters])

    def run(batches):
        for whole in batches:
            texts = whole.column(1).fill_null("").cast(pa.large_string())
            ends = np.frombuffer(texts.buffers()[1], np.int64)[texts.offset : texts.offset + len(texts) + 1]
            data = np.frombuffer(texts.buffers()[2] or b"", np.uint8)
            at = 0
            while at < len(texts):
                # 2,000 texts or 4 MB at a time, one text at least
                to = min(len(texts), at + 2_000, max(at + 1, int(np.searchsorted(ends, ends[at] + (1 << 22), side="right")) - 1))
                letter = data[ends[at] : ends[to]] - np.uint8(97)
                small = letter < 26
                pair = np.flatnonzero(small[:-1] & small[1:])
                row = np.searchsorted(ends[at : to + 1] - ends[at], pair, side="right") - 1
                own = pair + 1 < ends[at + 1 + row] - ends[at]  # both letters in one text
                pair, row = pair[own], row[own]
                x = np.bincount(row * d + place[letter[pair].astype(np.int64) * 26 + letter[pair + 1]], minlength=(to - at) * d).reshape(-1, d).astype(float)
                met = np.flatnonzero(x.any(1))
                yield _unit_rows(whole.column(0).slice(at, to - at).take(pa.array(met)), x[met])
                at = to

    return run


def _unit_rows(ids, x):
    """A batch (id, vec) of the rows of x at length 1; zero rows stay. Squares are added up from the left, as `normalize` does."""
    import numpy as np
    import pyarrow as pa

    size = np.sqrt((x * x).cumsum(1)[:, -1:])
    x = x * np.divide(1.0, size, out=np.zeros_like(size), where=size > 0)
    vec = pa.ListArray.from_arrays(pa.array(np.arange(0, x.size + 1, x.shape[1], dtype=np.int32)), pa.array(x.ravel()))
    return pa.record_batch([ids.cast(pa.int64()), vec], names=["id", "vec"])


def _bucket(gram: str, d: int) -> Column:
    return (F.conv(F.substring(F.md5(gram), 1, 8), 16, 10).cast("long") % d).cast("int")


def _bucket_of(gram: bytes, d: int) -> int:
    """What `_bucket` gives."""
    import hashlib

    return int(hashlib.md5(gram).hexdigest()[:8], 16) % d


KNOWN_WORDS = 1 << 18  # words whose bucket a task remembers


def _word_buckets(docs: DataFrame, id_col: str, text_col: str, d: int) -> DataFrame:
    """(u, b, n): for each key the buckets of its words, ascending, and how many words each has. Keys without words give no row."""
    def run(batches):
        import numpy as np
        import pyarrow as pa
        from collections import Counter

        spaces = bytes(c if 97 <= c <= 122 else 32 for c in range(256))
        known: dict[bytes, int] = {}

        def bucket(word: bytes) -> int:
            if len(known) >= KNOWN_WORDS:
                known.clear()
            return known.setdefault(word, _bucket_of(word, d))

        for whole in batches:
            for at in range(0, whole.num_rows, 2_000):
                b = whole.slice(at, 2_000)
                rows, places, counts = [], [], []
                for i, text in enumerate(b.column(1).fill_null("").cast(pa.binary())):
                    words = Counter(text.as_py().translate(spaces).split())
                    places += [known[w] if w in known else bucket(w) for w in words]
                    counts += words.values()
                    rows += [i] * len(words)
                n = np.bincount(np.array(rows, np.int64) * d + np.array(places, np.int64), weights=counts, minlength=b.num_rows * d).reshape(-1, d) if rows else np.zeros((b.num_rows, d))
                row, place = np.nonzero(n)
                met, first = np.unique(row, return_index=True)
                starts = pa.array(np.append(first, len(row)).astype(np.int32))
                lists = [pa.ListArray.from_arrays(starts, pa.array(v.astype(np.int32))) for v in (place, n[row, place])]
                yield pa.record_batch([b.column(0).take(pa.array(met)).cast(pa.int64()), *lists], names=["u", "b", "n"])

    return _whole(docs, id_col, text_col).mapInArrow(run, "u long, b array<int>, n array<int>")


def _weighted(weight, d: int):
    """Blocks of (u, b, n) as dense rows of counts by weight, at length 1; buckets without a weight (NaN) are left out, and rows that have no others."""
    import numpy as np
    import pyarrow as pa

    def run(batches):
        for whole in batches:
            for at in range(0, whole.num_rows, 2_000):
                b = whole.slice(at, 2_000)
                row = np.repeat(np.arange(b.num_rows), np.diff(b.column(1).offsets.to_numpy()))
                place, n = b.column(1).flatten().to_numpy(), b.column(2).flatten().to_numpy()
                has = ~np.isnan(weight[place])
                row, place, n = row[has], place[has], n[has]
                x = np.zeros((b.num_rows, d))
                x[row, place] = n * weight[place]
                met = np.unique(row)
                yield _unit_rows(b.column(0).take(pa.array(met)), x[met])

    return run


def word_counts(docs: DataFrame, id_col: str, text_col: str, d: int, idf: bool = True, base: DataFrame | None = None) -> DataFrame:
    """(id, vec): hashed word counts in d buckets, weighted by the log of documents over documents with the bucket, at length 1.

    base: the documents (of the same two columns) that give the weights, where they are not docs: queries from
    elsewhere then lie in the space of base. A bucket that base lacks has no weight.
    """
    import numpy as np

    counts, weight = _word_buckets(docs, id_col, text_col, d), np.ones(d)
    if idf:
        if base is None:
            counts = settle(counts, "counts")
        of = counts if base is None else _word_buckets(base, id_col, text_col, d)
        n = (docs if base is None else base).select(F.countDistinct(id_col)).first()[0]
        held = of.mapInArrow(_with_bucket(d), "b int, df long").groupBy("b").agg(F.sum("df").alias("df"))
        weight = np.full(d, np.nan)
        for r in held.select("b", F.ln(F.lit(n) / F.col("df")).alias("w")).collect():  # a row a bucket
            weight[r["b"]] = r["w"]
    return counts.mapInArrow(_weighted(weight, d), "id long, vec array<double>")


def _with_bucket(d: int):
    def run(batches):
        import numpy as np
        import pyarrow as pa

        df = np.zeros(d, np.int64)
        for b in batches:
            df += np.bincount(b.column(0).flatten().to_numpy(), minlength=d)
        met = np.flatnonzero(df)
        yield pa.record_batch([pa.array(met.astype(np.int32)), pa.array(df[met])], names=["b", "df"])

    return lambda batches: run(b.select(["b"]) for b in batches)


def char_ngrams(docs: DataFrame, id_col: str, text_col: str, d: int, n: int = 3) -> DataFrame:
    """(id, vec): counts of character n-grams of the lower-case text in d hashed buckets, at length 1. Texts shorter than n give no row."""
    pattern = rf"(?s)(?=([^\x{{DC00}}-\x{{DFFF}}].{{{n - 1}}}))"  # no gram starts within a character of two units
    grams = docs.select(F.col(id_col).alias("u"), F.explode(F.regexp_extract_all(F.lower(text_col), F.lit(pattern), F.lit(1))).alias("g"))
    counted = grams.groupBy("u", _bucket("g", d).alias("b")).agg(F.count("*").cast("double").alias("v"))
    return histogram(counted, "u", "b", "v", d).select("id", normalize("vec").alias("vec"))


def page_features(spark: SparkSession, sf_dir: str, d: int = 960) -> DataFrame:
    """Pages as hashed word counts of the text outside tags."""
    pages = load(spark, sf_dir, "pages").select("page_id", F.regexp_replace("html", "<[^>]*>", " ").alias("t"))
    return word_counts(pages, "page_id", "t", d, idf=False)
