"""Cells: the combination of a record's attribute values as one bit code, and matching of cells with queries.

Each attribute has a field of ceil(log2(values + 1)) bits; codes start at 1, and 0 means that the value is absent. Matching
is an equality join on (mask, masked code): as many comparisons as cells and query codes, not their product.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

WORD_BITS = 62


@dataclass
class CellDictionary:
    """Attributes in order, each with its values in order (code i + 1 for the i-th)."""

    values: dict[str, list[str]]

    @property
    def attrs(self) -> list[str]:
        return list(self.values)

    def width(self, attr: str) -> int:
        return len(self.values[attr]).bit_length()

    @property
    def words(self) -> list[list[str]]:
        """Attributes by the 62-bit word that holds their field; a single word unless the widths add up to more."""
        out, used = [[]], 0
        for a in self.attrs:
            if used + self.width(a) > WORD_BITS:
                out.append([])
                used = 0
            out[-1].append(a)
            used += self.width(a)
        return out

    def shift(self, attr: str) -> int:
        own = next(w for w in self.words if attr in w)
        return sum(self.width(a) for a in own[own.index(attr) + 1 :])

    def mask(self, attr: str) -> int:
        return ((1 << self.width(attr)) - 1) << self.shift(attr)

    def code(self, attr: str, value) -> int:
        return self.values[attr].index(str(value)) + 1 if value is not None else 0

    def frame(self, spark: SparkSession) -> DataFrame:
        rows = [(i, a, v, c + 1, self.width(a), self.shift(a), self.mask(a)) for i, a in enumerate(self.attrs) for c, v in enumerate(self.values[a])]
        return spark.createDataFrame(rows, "attr_no int, attr string, value string, code long, width int, shift int, mask long")

    def _field(self, attr: str) -> Column:
        pairs = [F.lit(x) for c, v in enumerate(self.values[attr]) for x in (v, c + 1)]
        if not pairs:
            return F.lit(0).cast("long")
        code = F.element_at(F.create_map(*pairs), F.col(attr).cast("string"))
        return F.shiftleft(F.coalesce(code, F.lit(0)).cast("long"), self.shift(attr))

    def cell_words(self) -> Column:
        """array<long>, one code for each word."""
        def one(attrs):
            out = F.lit(0).cast("long")
            for a in attrs:
                out = out.bitwiseOR(self._field(a))
            return out

        return F.array(*[one(w) for w in self.words])

    def cell_code(self) -> Column:
        """The code as a long. With several words, which no 62 bits hold, use cell_words."""
        if len(self.words) > 1:
            raise ValueError("the attributes need more than 62 bits; use cell_words")
        return self.cell_words()[0]

    def decode(self, code: Column) -> Column:
        """struct of values; absent is null."""
        out = []
        for a in self.attrs:
            c = F.shiftright(code, self.shift(a)).bitwiseAND((1 << self.width(a)) - 1)
            out.append(F.when(c > 0, F.get(F.array(*[F.lit(v) for v in self.values[a]]), (c - 1).cast("int"))).alias(a))
        return F.struct(*out)

    def code_bits(self, code: Column) -> Column:
        return F.lpad(F.bin(code), sum(self.width(a) for a in self.attrs), "0")


def build_dictionary(vectors: DataFrame, attrs: list[str], order: dict | None = None, most: int = 1 << 20) -> CellDictionary:
    """One pass over the attribute columns alone; their finite domains are frozen in order of value, or as `order` has them.
    Domains are checked to be no larger than `most`."""
    names = F.explode(F.array(*[F.struct(F.lit(i).alias("no"), F.col(a).cast("string").alias("value")) for i, a in enumerate(attrs)]))
    # values are told apart in the cluster; no more of them than make domains reach the driver
    found = vectors.select(names.alias("x_")).select("x_.*").where("value is not null").distinct().limit(most * len(attrs) + 1).collect()
    sets: dict = {a: [r["value"] for r in found if r["no"] == i] for i, a in enumerate(attrs)}
    for a in attrs:
        if len(sets[a]) > most or len(found) > most * len(attrs):
            raise ValueError(f"{a} has {len(sets[a])} values or more; at most {most} make a domain")
    return CellDictionary({a: [v for v in (order or {}).get(a, sorted(sets[a]))] for a in attrs})


def cell_stats(vectors: DataFrame, dictionary: CellDictionary) -> DataFrame:
    """cell_code, n_cell; the sizes add up to the number of records."""
    return vectors.groupBy(dictionary.cell_code().alias("cell_code")).agg(F.count(F.lit(1)).alias("n_cell"))


def query_cells(quotas: DataFrame, dictionary: CellDictionary) -> DataFrame:
    """query_id, mask, qcode, k_cell, share of each code asked for: the product of the values needed, one join for each
    attribute; k_cell is the least need among a code's values."""
    known = F.broadcast(dictionary.frame(quotas.sparkSession).select("attr", "value", "code", "shift", "mask"))
    coded = quotas.where("need > 0").join(known, ["attr", "value"])
    out = quotas.select("query_id").distinct().select("query_id", F.lit(0).cast("long").alias("mask"), F.lit(0).cast("long").alias("qcode"), F.lit(None).cast("int").alias("k_cell"))
    for a in dictionary.attrs:
        own = coded.where(F.col("attr") == a).select(
            "query_id", F.col("mask").alias("m_"), F.expr("shiftleft(code, shift)").alias("c_"), F.col("need").alias("n_")
        )
        out = out.join(own, "query_id", "left").select(
            "query_id", F.col("mask").bitwiseOR(F.coalesce("m_", F.lit(0).cast("long"))).alias("mask"),
            F.col("qcode").bitwiseOR(F.coalesce("c_", F.lit(0).cast("long"))).alias("qcode"), F.least("k_cell", "n_").alias("k_cell"),
        )
    return out.where("mask > 0")


def query_mask(quotas: DataFrame, dictionary: CellDictionary) -> DataFrame:
    known = F.broadcast(dictionary.frame(quotas.sparkSession).select("attr", "mask").distinct())
    return quotas.select("query_id", "attr").distinct().join(known, "attr").groupBy("query_id").agg(F.bit_or("mask").alias("mask"))


def match_cells(cells: DataFrame, asked: DataFrame) -> DataFrame:
    """query_id, cell_code, n_cell, qcode, k_cell of the relevant cells. The few distinct masks of the batch are applied to
    the cells, then a hash join finds equal codes."""
    masks = asked.select("mask").distinct()
    masked = cells.join(F.broadcast(masks)).withColumn("qcode", F.col("cell_code").bitwiseAND(F.col("mask")))
    return masked.join(asked, ["mask", "qcode"]).select("query_id", "cell_code", "n_cell", "mask", "qcode", "k_cell")


def match_cells_xor(cells: DataFrame, asked: DataFrame) -> DataFrame:
    """The same by the test as it is defined, (code AND mask) XOR query code = 0: a nested loop, for reference."""
    test = F.col("cell_code").bitwiseAND(F.col("mask")).bitwiseXOR(F.col("qcode")) == 0
    return cells.join(F.broadcast(asked), test).select("query_id", "cell_code", "n_cell", "mask", "qcode", "k_cell")


def value_bitmaps(cells: DataFrame, dictionary: CellDictionary) -> DataFrame:
    """attr, value, cells as a bitmap: numbered cells by the values that they have."""
    numbered = cells.withColumn("cell_no", F.row_number().over(_by_code()).cast("long")).select("cell_no", "cell_code")
    long = numbered.select("cell_no", F.explode(F.array(*[
        F.struct(F.lit(a).alias("attr"), dictionary.decode(F.col("cell_code"))[a].alias("value")) for a in dictionary.attrs
    ])).alias("x")).select("cell_no", "x.*").where("value is not null")
    bucket = F.bitmap_bucket_number("cell_no").alias("bucket")
    return long.groupBy("attr", "value", bucket).agg(F.bitmap_construct_agg(F.bitmap_bit_position("cell_no")).alias("bits"))


def match_counts_by_bitmap(bitmaps: DataFrame, quotas: DataFrame) -> DataFrame:
    """query_id, n_cells: how many cells are relevant, by OR over an attribute's needed values and AND over attributes."""
    asked = quotas.where("need > 0").join(bitmaps, ["attr", "value"])
    either = asked.groupBy("query_id", "attr", "bucket").agg(F.bitmap_or_agg("bits").alias("bits"))
    m = quotas.where("need > 0").groupBy("query_id").agg(F.count_distinct("attr").alias("m_"))
    both = either.groupBy("query_id", "bucket").agg(F.count(F.lit(1)).alias("n_"), F.bitmap_and_agg("bits").alias("bits")).join(m, "query_id")
    return both.groupBy("query_id").agg(F.sum(F.when(F.col("n_") == F.col("m_"), F.bitmap_count("bits")).otherwise(0)).alias("n_cells"))


def _by_code():
    from pyspark.sql import Window

    # the cell table alone is ordered: at most the product of the domains, never the records
    return Window.orderBy("cell_code")
