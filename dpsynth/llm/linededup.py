"""Line dedup in DataFrame operations only.

Lines travel as 128-bit hashes of their keys, never as text.  The hashes are range-partitioned
with document and position as secondary sort, and document is part of the range, so a line that
a third of the corpus shares runs over as many tasks as it fills.  Each task streams through its
sorted run: the first occurrence in each document, then per hash the number of documents and the
first occurrence of all, partial per task, so that the shuffle behind it carries one row per hash
and task.  What comes back to the documents is a sparse bitmap of 64-line words.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from dpsynth.llm.common import ASCII_SPACE, byte_text, cut, fresh, named, shuffle_width

#: Production parameters: keys of at least so many code points, found in at least so many documents.
MIN_CHARS, MIN_DOCS = 1, 10


def line_keys(text: Column, min_chars: int = MIN_CHARS) -> Column:
    """Array over the lines of a text: two hashes of the key with seeds of their own, or null where the key is too short.

    The key is the line stripped of ASCII white space at both ends, A-Z lowered.  It is hashed in
    the byte form of common.byte_text; code points are its bytes that don't continue a character.
    """

    def hashed(line: Column) -> Column:
        key = F.btrim(line, F.lit(ASCII_SPACE))
        size = F.length(key) if min_chars <= 1 else F.length(F.regexp_replace(key, "[\u0080-¿]", ""))
        return F.when(size >= min_chars, F.struct(F.xxhash64(key).alias("h1"), F.xxhash64(F.lit("second"), key).alias("h2")))

    return F.transform(F.split(byte_text(text), "\n", -1), hashed)


def occurrences(docs: DataFrame, min_chars: int = MIN_CHARS) -> DataFrame:
    """One row per line with a key: h1, h2, doc_id, row_hash (of the text), pos.  Cut behind here,
    as the hashes are read three times and the texts should be read once."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    lines = rows.select("doc_id", F.xxhash64("text").alias("row_hash"), F.posexplode(line_keys(F.col("text"), min_chars)).alias("pos", "k"))
    return cut(lines.where("k is not null").select("k.h1", "k.h2", "doc_id", "row_hash", "pos"))


def key_statistics(lines: DataFrame) -> DataFrame:
    """Per key: h1, h2, n_docs (documents of different doc_id) and the first occurrence.

    The exchange by range on (h1, h2, doc_id) already holds the rows of a key and a document
    together, so only the last step, on one row per key and task, shuffles again.
    """
    n = shuffle_width(lines.sparkSession)
    ranged = lines.repartitionByRange(n, "h1", "h2", "doc_id").sortWithinPartitions("h1", "h2", "doc_id", "pos")
    each = ranged.groupBy("h1", "h2", "doc_id").agg(F.min(F.struct("pos", "row_hash")).alias("at"))
    first = F.min(F.struct(F.col("doc_id"), F.col("at.pos").alias("pos"), F.col("at.row_hash").alias("row_hash")))
    return each.groupBy("h1", "h2").agg(F.count("*").alias("n_docs"), first.alias("first"))


def drop_bitmaps(lines: DataFrame, policy: str = "all", min_docs: int = MIN_DOCS) -> DataFrame:
    """Per document with dropped lines: doc_id, row_hash, n_dropped, dropped: map of word -> bits.

    Bit pos % 64 of word pos // 64 stands for line pos; words without dropped lines are left out.
    policy "all": keys in at least min_docs documents lose all their lines; "later": they keep
    the first occurrence (smallest doc_id, then position).
    """
    # cut, so that the join below has plain exchanges on both sides and AQE can split a hot line
    frequent = cut(key_statistics(lines).where(F.col("n_docs") >= min_docs))
    hit = lines.join(frequent, ["h1", "h2"])
    if policy == "later":
        same = F.col("doc_id").eqNullSafe(F.col("first.doc_id")) & (F.col("pos") == F.col("first.pos")) & (F.col("row_hash") == F.col("first.row_hash"))
        hit = hit.where(~same)
    words = hit.groupBy("doc_id", "row_hash", F.shiftright("pos", 6).alias("word")).agg(F.bit_or(F.expr("shiftleft(1L, pos % 64)")).alias("bits"))
    return words.groupBy("doc_id", "row_hash").agg(F.sum(F.bit_count("bits")).cast("long").alias("n_dropped"), F.map_from_entries(F.array_sort(F.collect_list(F.struct("word", "bits")))).alias("dropped"))


def dense_words(dropped: Column) -> Column:
    """The words of a sparse bitmap as an array from word 0 on, for access by index."""
    return F.transform(F.sequence(F.lit(0), F.element_at(F.map_keys(dropped), -1)), lambda w: F.coalesce(F.element_at(dropped, w), F.lit(0).cast("long")))


def kept_text(text: Column, dense: Column) -> Column:
    """The lines of a text whose bit isn't set, joined by \\n."""
    bit = lambda i: F.getbit(F.get(dense, F.shiftright(i, 6)), i % 64)
    kept = F.filter(F.split(text, "\n", -1), lambda _, i: F.coalesce(bit(i), F.lit(0)) == 0)
    return F.when(dense.isNull(), text).otherwise(F.array_join(kept, "\n"))


def dedup_lines(docs: DataFrame, policy: str = "all", min_docs: int = MIN_DOCS, min_chars: int = MIN_CHARS) -> DataFrame:
    """``docs`` with the kept text in place of ``text`` and two more columns: llm_n_lines and llm_n_dropped.

    A null text counts as one empty line and becomes an empty text.  Rows of the same doc_id
    count as one document (null is one id); each keeps its own bitmap, repeated rows equal
    ones.  All other columns stay as they are, whatever their names; the two new ones get
    underscores where their names are taken.  An empty table stays empty.
    """
    bitmaps = drop_bitmaps(occurrences(docs, min_chars), policy, min_docs)
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    lines_col, dropped_col, key, row, doc, hashed, n, bits = fresh(docs, "llm_n_lines", "llm_n_dropped", "llm_key", "llm_hash", "llm_doc", "llm_row", "llm_n", "llm_bits")
    rows = docs.withColumns({"text": text, key: F.col("doc_id").cast("long"), row: F.xxhash64(text)})
    found = bitmaps.select(F.col("doc_id").alias(doc), F.col("row_hash").alias(hashed), F.col("n_dropped").alias(n), dense_words(F.col("dropped")).alias(bits))
    met = rows.join(found.hint("shuffle_hash"), F.col(key).eqNullSafe(F.col(doc)) & (F.col(row) == F.col(hashed)), "left")
    n_lines = F.length("text") - F.length(F.replace(F.col("text"), F.lit("\n"), F.lit(""))) + 1
    return met.select(*[named(c) for c in docs.columns if c != "text"], kept_text(F.col("text"), F.col(bits)).alias("text"), n_lines.cast("long").alias(lines_col), F.coalesce(n, F.lit(0).cast("long")).alias(dropped_col))


def line_digests(docs: DataFrame, min_docs: int = MIN_DOCS, min_chars: int = MIN_CHARS) -> DataFrame:
    """Per row of ``docs``: doc_id, n_lines, n_dropped, kept_sha256.

    Null and empty texts are one empty line; repeated rows each give a row; an empty table gives
    an empty result.  Other columns are not read.
    """
    kept = dedup_lines(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), "all", min_docs, min_chars)
    return kept.select("doc_id", F.col("llm_n_lines").alias("n_lines"), F.col("llm_n_dropped").alias("n_dropped"), F.sha2("text", 256).alias("kept_sha256"))


#: DuckDB twin of line_digests with the production parameters.
ORACLE = """
with d as (select row_number() over () as rid, doc_id, coalesce(text, '') as text from documents),
l as (select rid, doc_id, unnest(string_split(text, chr(10))) as line, generate_subscripts(string_split(text, chr(10)), 1) as pos from d),
k as (select rid, doc_id, pos, line, translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as key from l),
f as (select key from k where length(key) >= 1 group by key having count(distinct doc_id) >= 10)
select any_value(k.doc_id) as doc_id, count(*)::bigint as n_lines, count(f.key)::bigint as n_dropped,
       sha256(coalesce(string_agg(k.line, chr(10) order by k.pos) filter (where f.key is null), '')) as kept_sha256
from k left join f on k.key = f.key group by k.rid
"""
