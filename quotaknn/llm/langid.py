"""Language identification with language-bitmask n-gram filters.

Training counts byte n-grams (letters lower-cased, everything else a space) for each language over a bounded sample of
labelled rows. An n-gram belongs to each language where it is frequent enough against the language that has it most. All
languages share one bit-sliced Bloom filter: position p holds a bitmask, bit l is language l's filter at p, and the AND of
an n-gram's positions gives all languages containing it. A text's score for a language is the share of its n-grams with
that bit, corrected for the filter's false positives; the largest decides.

Defined cases: null text or a text without a letter is `und` with score 0; a null doc_id is not held out; rows with null
lang train nothing; with nothing to learn from every row is `und`; texts are read whole, whatever their length;
a text with a letter but too short for an n-gram gets the first language with score 0; languages that tie go by name, the
first wins; repeated rows are judged alike; an empty table gives no rows; names that clash are told apart by fresh().
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import regex
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from quotaknn.llm.common import col, forget, fresh, hash_rows, lean, release, slabs, text_bytes

SLAB = 1 << 20
LETTER = regex.compile(r"\p{L}")
_FOLD = np.full(256, 32, np.uint8)
_FOLD[97:123] = np.arange(97, 123)
_FOLD[65:91] = np.arange(97, 123)
_FOLD[128:] = np.arange(128, 256)


def grams(lowered: np.ndarray, n: int) -> np.ndarray:
    """n-grams (n up to 8) at each position but the last n - 1, packed into uint64."""
    b = _FOLD[lowered].astype(np.uint64)
    m = max(0, len(b) - n + 1)
    out = np.zeros(m, np.uint64)
    for k in range(n):
        out = (out << np.uint64(8)) | b[k : k + m]
    return out


def positions(g: np.ndarray, log2_size: int, hashes: int) -> list[np.ndarray]:
    h = hash_rows(g)
    step, mask = np.uint64(64 // hashes), np.uint64((1 << log2_size) - 1)
    return [(h >> np.uint64(k) * step) & mask for k in range(hashes)]


@dataclass
class Model:
    langs: list[str]
    n: int
    log2_size: int
    hashes: int
    table: np.ndarray  # (2 ** log2_size, words of 64 languages)

    def masks(self, g: np.ndarray) -> np.ndarray:
        at = positions(g, self.log2_size, self.hashes)
        out = self.table[at[0]]
        for p in at[1:]:
            out = out & self.table[p]
        return out

    def false_rate(self) -> np.ndarray:
        fill = np.array([((self.table[:, i >> 6] >> np.uint64(i & 63)) & np.uint64(1)).mean() for i in range(len(self.langs))])
        return np.minimum(fill**self.hashes, 0.999)

    def score(self, column) -> tuple[np.ndarray, np.ndarray]:
        """Best language (-1: und) and its corrected share of n-grams, for an Arrow array of texts."""
        return self.measured(column)[:2]

    def measured(self, column) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """score(), and how many n-grams each text has."""
        best, score, count = np.full(len(column), -1), np.zeros(len(column)), np.zeros(len(column), np.int64)
        if not self.langs:
            return best, score, count
        import pyarrow as pa

        fp = self.false_rate()
        for i, j in slabs(text_bytes(column)[1], SLAB):
            texts = column.slice(i, j - i).to_pylist()
            has = np.array([bool(t and LETTER.search(t)) for t in texts], bool)
            low, o = text_bytes(pa.array([(f" {t.lower()} " if h else "") for t, h in zip(texts, has)], pa.large_string()))
            g = grams(low, self.n)
            m = self.masks(g)
            # n-grams that cross into the next text do not count
            inside = np.ones(len(g), bool)
            for k in range(1, self.n):
                cut = o[1:] - k
                inside[cut[(cut >= 0) & (cut < len(g))]] = False
            own = np.concatenate([[0], np.cumsum(inside)])
            lo, hi = np.minimum(o[:-1], len(g)), np.minimum(o[1:], len(g))
            total = own[hi] - own[lo]
            share = np.zeros((j - i, len(self.langs)))
            for k in range(len(self.langs)):
                bit = ((m[:, k >> 6] >> np.uint64(k & 63)) & np.uint64(1)).astype(bool) & inside
                run = np.concatenate([[0], np.cumsum(bit)])
                hits = run[hi] - run[lo]
                share[:, k] = np.clip((hits - total * fp[k]) / np.maximum(total * (1 - fp[k]), 1e-9), 0, 1)
            best[i:j], score[i:j] = np.where(has, share.argmax(1), -1), np.where(has, share.max(1), 0.0)
            count[i:j] = total
        return best, score, count


def train(docs: DataFrame, may_learn: Column, text: str = "text", lang: str = "lang", salt: str = "doc_id", n: int = 5,
          log2_size: int = 20, hashes: int = 2, rows_per_lang: int = 3000, share: float = 0.25, least: int = 4,
          grams_per_lang: int = 100_000) -> Model:
    """Fit on about `rows_per_lang` rows of each language, drawn by a hash of the id (that bound is the documented sample;
    all texts drawn are used whole), keeping at most `grams_per_lang` n-grams for each, the most frequent."""
    spark = docs.sparkSession
    labelled = docs.where(may_learn & col(lang).isNotNull() & col(text).isNotNull())
    sizes = {r[0]: r[1] for r in labelled.groupBy(col(lang).alias("k")).count().collect()}
    langs = sorted(sizes)
    if not langs:
        return Model([], n, log2_size, hashes, np.zeros((1 << log2_size, 1), np.uint64))
    part = F.create_map(*[F.lit(x) for k in langs for x in (k, min(1.0, rows_per_lang / sizes[k]))])
    drawn = labelled.select(col(lang).alias("lang"), col(text).alias("text"), col(salt).alias("salt"))
    drawn = drawn.where(F.pmod(F.xxhash64("salt"), F.lit(1 << 30)) < F.element_at(part, F.col("lang")) * (1 << 30))

    def count(batches):
        import pyarrow as pa

        def flush():
            for k, parts in held.items():
                g, inv = np.unique(np.concatenate([p[0] for p in parts]), return_inverse=True)
                c = np.bincount(inv, weights=np.concatenate([p[1] for p in parts])).astype(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array([k] * len(g), pa.string()), pa.array(g.view(np.int64)), pa.array(c, pa.int64())], names=["lang", "gram", "n"])
            held.clear()

        held: dict = {}
        size = 0
        for b in batches:
            langs_in = b.column(0).to_pylist()
            for i, j in slabs(text_bytes(b.column(1))[1], SLAB):
                texts = b.column(1).slice(i, j - i).to_pylist()
                for k in set(langs_in[i:j]):
                    joined = " ".join(f" {t.lower()} " for t, x in zip(texts, langs_in[i:j]) if x == k)
                    g, c = np.unique(grams(np.frombuffer(joined.encode(), np.uint8), n), return_counts=True)
                    held.setdefault(k, []).append((g, c))
                    size += len(g)
            if size > 1_500_000:
                yield from flush()
                size = 0
        yield from flush()

    counts = drawn.select("lang", "text").mapInArrow(lean(count), "lang string, gram long, n long").groupBy("lang", "gram").agg(F.sum("n").alias("n")).where(F.col("n") >= least)
    totals = counts.groupBy("lang").agg(F.sum("n").alias("total"))
    rates = counts.join(F.broadcast(totals), "lang").withColumn("rate", F.col("n") / F.col("total"))
    top = rates.groupBy("gram").agg(F.max("rate").alias("most"))
    from pyspark.sql import Window

    kept = (
        rates.join(top, "gram").where(F.col("rate") >= share * F.col("most"))
        .withColumn("rn", F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("n"), "gram")))
        .where(F.col("rn") <= grams_per_lang).groupBy("lang").agg(F.collect_list("gram").alias("grams"))
    )
    table = np.zeros((1 << log2_size, (len(langs) + 63) // 64), np.uint64)
    for r in kept.collect():
        k = langs.index(r["lang"])
        for p in positions(np.array(r["grams"], np.int64).view(np.uint64), log2_size, hashes):
            table[p, k >> 6] |= np.uint64(1) << np.uint64(k & 63)
    return Model(langs, n, log2_size, hashes, table)


def predictor(spark: SparkSession, model: Model):
    """An Arrow function from a text column to struct<lang_pred, score, grams>."""
    shared = spark.sparkContext.broadcast((model.langs, model.n, model.log2_size, model.hashes, model.table))

    @F.arrow_udf("struct<lang_pred:string,score:double,grams:long>")
    def predict(texts):
        import pyarrow as pa

        forget()
        m = Model(*shared.value)
        best, score, count = m.measured(texts)
        release()
        names = pa.array([m.langs[b] if b >= 0 else "und" for b in best], pa.string())
        return pa.StructArray.from_arrays([names, pa.array(score), pa.array(count)], names=["lang_pred", "score", "grams"])

    return predict


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2, F.lit(False))


def identify(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", lang: str = "lang") -> DataFrame:
    """All rows and columns, and a struct column named by fresh(docs, "language") at the end."""
    model = train(docs, ~held_out(col(doc_id)), text, lang, doc_id)
    return docs.withColumn(fresh(docs, "language"), predictor(docs.sparkSession, model)(col(text)))


def accepted(docs: DataFrame, least: float = 0.05, **names) -> DataFrame:
    """The rows whose text has a letter and enough known n-grams of some language, or is too short to have any n-gram; columns
    as they were."""
    scored = identify(docs, **names)
    c = scored.columns[-1]
    return scored.where((col(c)["lang_pred"] != "und") & ((col(c)["score"] >= least) | (col(c)["grams"] == 0))).drop(c)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "lang")
    return identify(docs).select(
        "doc_id", held_out(F.col("doc_id")).alias("held_out"), "language.lang_pred", "language.score"
    )
