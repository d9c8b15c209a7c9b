"""Line and paragraph deduplication by hashing.

Units are lines, or paragraphs, and the sentences inside them: a passage that was pasted into the middle of a line is met by
its sentences. Every unit that is not blank is normalised (lower case, runs of blanks as one space, trimmed) and its digest
grouped over all documents; of equal units the earliest ranked occurrence stays, by doc_id, then order of the source, then
place in the text. The rest are removed; what is left keeps its bytes, and every removed unit keeps its character offsets
in the original. A line counts whatever its length; a sentence inside a longer line counts from `sentence_words` words on,
as shorter ones ("And so on.") recur in texts that have nothing else in common.

A sentence ends at . ! or ? before blanks and holds those blanks. Equal lines have equal sentences, and ranks go by place,
so the first occurrence of any text always stays somewhere.

Defined cases: null text is empty and has no units; null doc_ids rank last; blank lines are no units and stay; repeated rows
repeat all their units; texts of any length are read whole; an empty table gives no rows; other columns are not read, so
names that clash do no harm.
"""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from quotaknn.llm.common import discard, materialise, placed, tidied

BREAK = {"line": "\n", "paragraph": "\n\n"}
BLANKS = re.compile("[ \t\r\v\f\n]+")
SENTENCES = re.compile("(?s).*?[.!?][ \t\r\v\f\n]+|.+")
SENTENCE_WORDS = 8
FLUSH = 100_000


def normal(unit: str) -> str:
    return BLANKS.sub(" ", unit.lower()).strip(" ")


def units_of(text: str, sep: str, min_words: int, sentence_words: int):
    """(normalised unit, start, stop) of the units of one text, in order of place; a line comes before its sentences."""
    at = 0
    for own in text.split(sep):
        norm = normal(own)
        if norm and norm.count(" ") + 1 >= min_words:
            yield norm, at, at + len(own)
        if norm and sentence_words:
            inner = SENTENCES.findall(own)
            if len(inner) > 1:
                place = at
                for part in inner:
                    small = normal(part)
                    if small.count(" ") + 1 >= sentence_words:
                        yield small, place, place + len(part)
                    place += len(part)
        at += len(own) + len(sep)


def units(rows: DataFrame, unit: str, min_words: int, sentence_words: int) -> DataFrame:
    """digest, row_key, doc_id, start, stop of each unit of (row_key, doc_id, text)."""
    sep = BREAK[unit]

    def run(batches):
        import hashlib

        import pyarrow as pa

        kinds = [pa.binary(), pa.int64(), pa.int64(), pa.int64(), pa.int64()]
        names = ["digest", "row_key", "doc_id", "start", "stop"]
        for b in batches:
            rows: list[list] = [[] for _ in kinds]
            for key, k, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2)):
                for norm, start, stop in units_of(t.as_py(), sep, min_words, sentence_words):
                    for c, v in zip(rows, (hashlib.blake2b(norm.encode(), digest_size=16).digest(), key, k, start, stop)):
                        c.append(v)
                    if len(rows[0]) >= FLUSH:
                        yield pa.RecordBatch.from_arrays([pa.array(r, t_) for r, t_ in zip(rows, kinds)], names=names)
                        rows = [[] for _ in kinds]
            yield pa.RecordBatch.from_arrays([pa.array(r, t_) for r, t_ in zip(rows, kinds)], names=names)

    return rows.mapInArrow(tidied(run), "digest binary, row_key long, doc_id long, start long, stop long")


def later_copies(found: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The units that equal an earlier ranked one, and the table behind them. Groups are pre-aggregated into a table of
    its own: Spark can split a hot digest in a join of two tables, not in one that continues an aggregation."""
    rank = F.struct(F.col("doc_id").isNull(), "doc_id", "row_key", "start", "stop")
    first = materialise(found.groupBy("digest").agg(F.count(F.lit(1)).alias("n"), F.min(rank).alias("first")).where("n > 1"), "firsts")
    other = (F.col("first.row_key") != F.col("row_key")) | (F.col("first.start") != F.col("start")) | (F.col("first.stop") != F.col("stop"))
    return found.join(first, "digest").where(other), first


def left_over(text: str, sep: str, gone: list[tuple[int, int]]) -> tuple[str, list[tuple[int, int]]]:
    """The text without the spans of removed units, and those spans without the ones inside removed lines."""
    out, spans, at, i = [], [], 0, 0
    gone = sorted(gone, key=lambda s: (s[0], -s[1]))
    for own in text.split(sep):
        stop, here = at + len(own), []
        while i < len(gone) and gone[i][0] < stop:
            here.append(gone[i])
            i += 1
        if here and here[0] == (at, stop):
            spans.append(here[0])
        else:
            kept, place = [], at
            for a, b in here:
                kept.append(text[place:a])
                place = b
            out.append("".join([*kept, text[place:stop]]))
            spans += here
        at = stop + len(sep)
    return sep.join(out), spans


def remove_units(docs: DataFrame, unit: str = "line", min_words: int = 1, sentence_words: int = SENTENCE_WORDS, doc_id: str = "doc_id", text: str = "text", with_text: bool = False) -> DataFrame:
    """row_key, doc_id, n_removed (units), chars_removed, spans (start, stop in characters of the original, in order),
    kept_chars, kept_sha256 and, if asked for, the text kept. sentence_words = 0 leaves sentences inside lines alone."""
    sep = BREAK[unit]
    rows = placed(docs, doc_id, text)
    found = materialise(units(rows, unit, min_words, sentence_words), "units")
    copies, first = later_copies(found)
    per = materialise(copies.groupBy("row_key").agg(F.collect_list(F.struct("start", "stop")).alias("gone")), "gone")
    discard(found, first)
    whole = rows.join(per, "row_key", "left")

    def cut(batches):
        import hashlib

        import pyarrow as pa

        names = ["row_key", "doc_id", "n_removed", "chars_removed", "spans", "kept_chars", "kept_sha256"] + ["kept"] * with_text
        span = pa.list_(pa.struct([("start", pa.int64()), ("stop", pa.int64())]))
        kinds = [pa.int64(), pa.int64(), span, pa.int64(), pa.string()] + [pa.string()] * with_text
        for b in batches:
            rows: list[list] = [[] for _ in kinds]
            for t, g in zip(b.column(2), b.column(3)):
                t, g = t.as_py(), [(s["start"], s["stop"]) for s in g.as_py() or ()]
                left, spans = left_over(t, sep, g) if g else (t, [])
                values = (len(g), sum(j - i for i, j in spans), [{"start": i, "stop": j} for i, j in spans], len(left), hashlib.sha256(left.encode()).hexdigest())
                for c, v in zip(rows, (*values, left) if with_text else values):
                    c.append(v)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), *[pa.array(c, k) for c, k in zip(rows, kinds)]], names=names)

    schema = "row_key long, doc_id long, n_removed long, chars_removed long, spans array<struct<start:long,stop:long>>, kept_chars long, kept_sha256 string"
    return whole.mapInArrow(tidied(cut), schema + ", kept string" * with_text)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lines of any length and sentences inside them; offsets as text (start-stop, ...)."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    told = F.transform("spans", lambda s: F.concat_ws("-", s["start"].cast("string"), s["stop"].cast("string")))
    return remove_units(docs).select("doc_id", "n_removed", "chars_removed", F.concat_ws(",", told).alias("removed_spans"), "kept_chars", "kept_sha256")


SQL = f"""
with lines as (
  select doc_id, line_no, line, sum(length(line) + 1) over (partition by doc_id order by line_no) - length(line) - 1 as line_start
  from (
    select doc_id, unnest(parts) as line, unnest(range(1, len(parts) + 1)) as line_no
    from (select doc_id, string_split(coalesce(text, ''), chr(10)) as parts from documents)
  )
), inner_ as (
  select doc_id, line_no, unnest(parts) as part, unnest(range(1, len(parts) + 1)) as part_no, line_start
  from (select doc_id, line_no, line_start, regexp_extract_all(line, '(?s).*?[.!?][ \t\r\v\f]+|.+') as parts from lines)
  where len(parts) > 1
), placed as (
  select *, line_start + sum(length(part)) over (partition by doc_id, line_no order by part_no) - length(part) as part_start from inner_
), every as (
  select doc_id, line_no, 0 as part_no, line as own, line_start as start, trim(regexp_replace(lower(line), '[ \t\r\v\f]+', ' ', 'g'), ' ') as norm from lines
  union all
  select doc_id, line_no, part_no, part, part_start, trim(regexp_replace(lower(part), '[ \t\r\v\f]+', ' ', 'g'), ' ') from placed
), units as (
  select * from every where norm <> '' and (part_no = 0 or len(string_split(norm, ' ')) >= {SENTENCE_WORDS})
), gone as (
  select * from units qualify row_number() over (partition by norm order by doc_id, start, part_no) > 1
), whole as (
  select doc_id, line_no from gone where part_no = 0
), cut as (
  select g.* from gone g left join whole w using (doc_id, line_no) where g.part_no = 0 or w.line_no is null
), kept_parts as (
  select p.doc_id, p.line_no, string_agg(p.part, '' order by p.part_no) filter (c.part_no is null) as line
  from placed p left join cut c using (doc_id, line_no, part_no) group by all
), kept as (
  select l.doc_id, string_agg(coalesce(case when k.line_no is null then l.line else coalesce(k.line, '') end, ''), chr(10) order by l.line_no) as text
  from lines l left join whole w using (doc_id, line_no) left join kept_parts k using (doc_id, line_no)
  where w.line_no is null group by l.doc_id
), told as (
  select doc_id, cast(sum(length(own)) as bigint) as chars, string_agg(start || '-' || (start + length(own)), ',' order by start) as spans from cut group by doc_id
), counted as (
  select doc_id, count(*) as n from gone group by doc_id
)
select d.doc_id, coalesce(n, 0) as n_removed, coalesce(chars, 0) as chars_removed, coalesce(spans, '') as removed_spans,
       length(coalesce(k.text, '')) as kept_chars, sha256(coalesce(k.text, '')) as kept_sha256
from (select distinct doc_id from documents) d left join counted using (doc_id) left join told using (doc_id) left join kept k on k.doc_id = d.doc_id
"""
