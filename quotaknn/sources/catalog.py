"""Vector relations over the given tables, and readers and writers for vectors kept elsewhere.

A relation has rec_id, vec (array<double>) and attribute columns. RELATION_SQL has the same relations in DuckDB's SQL.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

ATTRS = {
    "V_EMB": ["status", "priority", "lang"],
    "V_EMB5": ["status", "priority", "lang", "segment", "label"],
    "V_COR": ["g1", "g2", "g3"],
    "V_LINE": ["returnflag", "linestatus", "linenumber"],
    "V_DOC": ["lang", "source", "quality", "toxic", "length_band"],
    "V_PART": ["brand", "type", "size_band"],
    "V_CUST": ["segment", "nation", "region"],
    "V_SUPP": ["nation", "region"],
    "V_PAGE": ["host", "length_band"],
    "V_CONV": ["role", "parity"],
    "V_EVENT": ["event_type", "weekday"],
    "V_BENCH": [],
}
METRIC = {"V_DOC": "cosine", "V_PAGE": "cosine", "V_CONV": "cosine", "V_BENCH": "cosine"}
HASHED_DIM = 128


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def hashed_text(text: Column, dim: int = HASHED_DIM) -> Column:
    """Signed feature hashing of character 3-grams to a unit vector, by an Arrow function."""
    from pyspark.sql import types as T

    @F.arrow_udf(T.ArrayType(T.DoubleType()))
    def hashed(texts):
        import numpy as np
        import pyarrow as pa

        out = np.zeros((len(texts), dim))
        for i, t in enumerate(texts.to_pylist()):
            b = np.frombuffer((t or "").lower().encode(), np.uint8).astype(np.uint64)
            if len(b) < 3:
                continue
            g = (b[:-2] << np.uint64(16)) | (b[1:-1] << np.uint64(8)) | b[2:]
            h = g * np.uint64(0x9E3779B97F4A7C15)
            h ^= h >> np.uint64(29)
            h *= np.uint64(0xBF58476D1CE4E5B9)
            at, sign = (h >> np.uint64(40)) % np.uint64(dim), (h >> np.uint64(39)) & np.uint64(1)
            out[i] = np.bincount(at.astype(int), weights=1.0 - 2.0 * sign, minlength=dim)
            size = np.linalg.norm(out[i])
            out[i] /= size if size else 1
        return pa.ListArray.from_arrays(pa.array(np.arange(len(out) + 1, dtype=np.int32) * dim), pa.array(out.ravel()))

    return hashed(text)


def band(x: Column, cuts: list[float]) -> Column:
    out = F.lit(len(cuts) + 1)
    for i, c in reversed(list(enumerate(cuts))):
        out = F.when(x < c, i + 1).otherwise(out)
    return F.when(x.isNotNull(), out.cast("string"))


def standardised(df: DataFrame, columns: list[str]) -> DataFrame:
    """Columns less their mean, over their deviation; one pass gathers both."""
    stats = df.agg(*[f(c).alias(f"{n}_{c}") for c in columns for n, f in (("m", F.avg), ("s", F.stddev_pop))])
    joined = df.join(F.broadcast(stats))
    return joined.withColumns({c: (F.col(c) - F.col(f"m_{c}")) / F.coalesce(F.nullif(F.col(f"s_{c}"), F.lit(0.0)), F.lit(1.0)) for c in columns}).select(*df.columns)


def vector_relation(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    t = lambda n: table(spark, sf_dir, n)
    vec = F.col("embedding").cast("array<double>").alias("vec")
    if name in ("V_EMB", "V_EMB5", "V_COR"):
        emb = t("embeddings").select(F.col("vec_id").alias("rec_id"), vec, F.col("label").cast("string").alias("label"))
        orders = t("orders").select(F.col("o_orderkey").alias("rec_id"), F.col("o_orderstatus").alias("status"), F.col("o_orderpriority").alias("priority"), "o_totalprice")
        rows = emb.join(orders, "rec_id")
        if name == "V_COR":
            i = F.col("rec_id")
            rows = rows.withColumn("g1", band(F.col("o_totalprice"), [351000, 425000, 475000]))
            rows = rows.withColumn("g2", F.when(i % 20 < 3, (F.floor(i / 20) % 4).cast("string")).otherwise(F.col("g1")))
            rows = rows.withColumn("g3", F.when(F.floor(i / 7) % 20 < 3, (F.floor(i / 3) % 4).cast("string")).otherwise(F.col("g2")))
            return rows.select("rec_id", "vec", "g1", "g2", "g3")
        rows = rows.join(t("documents").select(F.col("doc_id").alias("rec_id"), "lang"), "rec_id", "left")
        if name == "V_EMB":
            return rows.select("rec_id", "vec", *ATTRS[name])
        rows = rows.join(t("customer").select(F.col("c_custkey").alias("rec_id"), F.col("c_mktsegment").alias("segment")), "rec_id", "left")
        return rows.select("rec_id", "vec", *ATTRS[name])
    if name == "V_LINE":
        day = 2 * 3.141592653589793 * F.dayofyear("l_shipdate") / 366
        cols = ["l_quantity", "l_extendedprice", "l_discount", "l_tax"]
        key = F.struct("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_shipdate")
        rows = t("lineitem").select("*", F.xxhash64(key).alias("rec_id"), F.sin(day).alias("s_"), F.cos(day).alias("c_"))
        return standardised(rows, cols).select("rec_id", F.array(*cols, "s_", "c_").alias("vec"), F.col("l_returnflag").alias("returnflag"), F.col("l_linestatus").alias("linestatus"), F.col("l_linenumber").cast("string").alias("linenumber"))
    if name == "V_DOC":
        labels = t("labels").select("doc_id", F.col("quality").cast("string"), F.col("toxic").cast("string"))
        rows = t("documents").join(labels, "doc_id", "left")
        return rows.select(F.col("doc_id").alias("rec_id"), hashed_text(F.col("text")).alias("vec"), "lang", "source", "quality", "toxic", band(F.col("n_chars"), [500, 2000, 8000]).alias("length_band"))
    if name == "V_PART":
        rows = standardised(t("part").withColumn("size_", F.col("p_size").cast("double")), ["size_", "p_retailprice"])
        return rows.select(F.col("p_partkey").alias("rec_id"), F.array("size_", "p_retailprice").alias("vec"), F.col("p_brand").alias("brand"), F.col("p_type").alias("type"), band(F.col("p_size"), [13, 26, 39]).alias("size_band"))
    if name in ("V_CUST", "V_SUPP"):
        p, kind = ("c", "customer") if name == "V_CUST" else ("s", "supplier")
        places = t("nation").join(t("region"), F.col("n_regionkey") == F.col("r_regionkey")).select(F.col("n_nationkey").alias(f"{p}_nationkey"), F.col("n_name").alias("nation"), F.col("r_name").alias("region"))
        rows = standardised(t(kind), [f"{p}_acctbal"]).join(F.broadcast(places), f"{p}_nationkey", "left")
        rows = rows.withColumnRenamed("c_mktsegment", "segment")
        return rows.select(F.col("c_custkey" if p == "c" else "s_suppkey").alias("rec_id"), F.array(f"{p}_acctbal").alias("vec"), *ATTRS[name])
    if name == "V_PAGE":
        plain = F.regexp_replace(F.regexp_replace("html", "(?s)<(script|style)[^>]*>.*?</\\1>", " "), "<[^>]*>", " ")
        return t("pages").select(F.col("page_id").alias("rec_id"), hashed_text(plain).alias("vec"), F.expr("try_parse_url(url, 'HOST')").alias("host"), band(F.length("html"), [1000, 2000, 4000]).alias("length_band"))
    if name == "V_CONV":
        return t("conversations").select(F.xxhash64("conv_id", "turn").alias("rec_id"), hashed_text(F.col("text")).alias("vec"), "role", (F.col("turn") % 2).cast("string").alias("parity"))
    if name == "V_EVENT":
        hour = 2 * 3.141592653589793 * (F.hour("ts") + F.minute("ts") / 60) / 24
        k = F.coalesce(F.get_json_object("props", "$.k").cast("double"), F.lit(0.0)) / 100
        return t("events").select(F.col("event_id").alias("rec_id"), "ts", F.array(F.col("value") / 100, F.sin(hour), F.cos(hour), k).alias("vec"), "event_type", F.dayofweek("ts").cast("string").alias("weekday"))
    if name == "V_BENCH":
        return t("benchmark").select(F.col("item_id").alias("rec_id"), hashed_text(F.col("text")).alias("vec"))
    raise ValueError(f"unknown relation {name!r}; one of {sorted(ATTRS)}")


RELATION_SQL = {
    "V_EMB": """select e.vec_id as rec_id, e.embedding::double[] as vec, o.o_orderstatus as status, o.o_orderpriority as priority, d.lang as lang
from embeddings e join orders o on e.vec_id = o.o_orderkey left join documents d on e.vec_id = d.doc_id""",
    "V_EMB5": """select e.vec_id as rec_id, e.embedding::double[] as vec, o.o_orderstatus as status, o.o_orderpriority as priority, d.lang as lang, c.c_mktsegment as segment, cast(e.label as varchar) as label
from embeddings e join orders o on e.vec_id = o.o_orderkey left join documents d on e.vec_id = d.doc_id left join customer c on e.vec_id = c.c_custkey""",
    "V_COR": """select rec_id, vec, g1, g2, case when (rec_id // 7) % 20 < 3 then cast((rec_id // 3) % 4 as varchar) else g2 end as g3
from (select *, case when rec_id % 20 < 3 then cast((rec_id // 20) % 4 as varchar) else g1 end as g2
from (select e.vec_id as rec_id, e.embedding::double[] as vec, case when o_totalprice < 351000 then '1' when o_totalprice < 425000 then '2' when o_totalprice < 475000 then '3' else '4' end as g1
from embeddings e join orders o on e.vec_id = o.o_orderkey))""",
}


def read_vectors(spark: SparkSession, path: str, kind: str, rec_id: str = "rec_id", vec: str = "vec", attrs: list[str] | None = None) -> DataFrame:
    """Vectors in files: parquet or orc (arrays), csv, json or text lines of JSON (vectors as JSON text). A row whose vector
    cannot be read has a null vector; see bad_vectors."""
    attrs = attrs or []
    if kind in ("parquet", "orc"):
        rows = spark.read.format(kind).load(path)
        return rows.select(F.col(rec_id).cast("long").alias("rec_id"), F.col(vec).cast("array<double>").alias("vec"), *[F.col(a).cast("string") for a in attrs])
    fields = ", ".join([f"{rec_id} long", f"{vec} string", *[f"{a} string" for a in attrs]])
    if kind == "csv":
        rows = spark.read.schema(fields).option("header", True).option("escape", '"').csv(path)
    elif kind == "json":
        rows = spark.read.schema(fields).json(path)
    elif kind == "text":
        rows = spark.read.text(path).select(F.from_json("value", fields).alias("r")).select("r.*")
    else:
        raise ValueError(f"unknown kind {kind!r}")
    return rows.select(F.col(rec_id).alias("rec_id"), F.from_json(F.col(vec), "array<double>").alias("vec"), *attrs)


def write_vectors(vectors: DataFrame, path: str, kind: str = "parquet", files: int | None = None) -> None:
    """The counterpart of read_vectors; text kinds hold vectors as JSON."""
    rows = vectors if files is None else vectors.repartition(files)
    if kind in ("csv", "json"):
        rows = rows.withColumn("vec", F.to_json("vec"))
    writer = rows.write.option("header", True).option("escape", '"') if kind == "csv" else rows.write
    writer.format(kind).save(path)


def bad_vectors(vectors: DataFrame, dim: int) -> DataFrame:
    """Rows with a null vector, another dimension, or null or non-finite components."""
    return vectors.where(~sound(F.col("vec"), dim))


def sound(vec: Column, dim: int) -> Column:
    ok = vec.isNotNull() & (F.size(vec) == dim) & ~F.exists(vec, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return F.coalesce(ok, F.lit(False))


def latest_attributes(records: DataFrame, snapshots: DataFrame, attrs: list[str]) -> DataFrame:
    """As-of join: for each record (rec_id, at, ...) the last known value of each attribute at that time. One shuffle by
    record and a running last value, instead of a range join."""
    cols = [c for c in records.columns if c not in ("rec_id", "at")]
    left = records.select("rec_id", "at", F.struct(*cols).alias("own") if cols else F.lit(True).alias("own"), F.lit(1).alias("side"), *[F.lit(None).cast("string").alias(a) for a in attrs])
    right = snapshots.select("rec_id", "at", F.lit(None).cast(left.schema["own"].dataType).alias("own"), F.lit(0).alias("side"), *[F.col(a).cast("string") for a in attrs])
    w = Window.partitionBy("rec_id").orderBy("at", "side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    both = left.unionByName(right).withColumns({a: F.last(a, ignorenulls=True).over(w) for a in attrs}).where("side = 1")
    return both.select("rec_id", "at", *(["own.*"] if cols else []), *attrs)
