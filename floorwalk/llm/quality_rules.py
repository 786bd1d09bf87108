"""Quality rules: base rules on each text, then cross-document line frequency within each host.

Lines are normalised (A-Z lower-cased, digits made alike, white space collapsed) and hashed; a line that stands in more
than max(min_docs, share * documents of the host) distinct texts of its host is boilerplate. Boilerplate lines are
removed, and a document that loses more than max_loss of its words, or keeps fewer than min_words, is depleted and rejected.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from floorwalk.llm.runtime import DOCUMENT, content_keys, guarded, materialize_texts
from floorwalk.llm.textkit import HASH_A, HASH_B, IS_LEAD, IS_SPACE, NEWLINE, TO_LOWER, chunks, mix64, repeats

MIN_DOCS, SHARE, MAX_LOSS, MIN_WORDS = 20, 0.1, 0.5, 10
WINDOW = 5
# The symbol characters of the contract's pattern.
SYMBOLS = b"#*$%&|<>"

IS_SYMBOL = np.zeros(256, dtype=bool)
IS_SYMBOL[list(SYMBOLS)] = True
NORMAL = TO_LOWER.copy()
NORMAL[48:58] = 48


def _windows(word_hash: np.ndarray, doc: np.ndarray) -> np.ndarray:
    """Which words stand in a window of WINDOW words that the text holds at least twice."""
    inside = np.zeros(len(word_hash), dtype=bool)
    n = len(word_hash) - WINDOW + 1
    if n < 2:
        return inside
    key = doc[:n].astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    for j in range(WINDOW):
        key += mix64(word_hash[j : j + n] + np.uint64(j + 1))
    whole = np.flatnonzero(doc[:n] == doc[WINDOW - 1 :])
    twice = whole[repeats(mix64(key[whole]))]
    for j in range(WINDOW):
        inside[twice + j] = True
    return inside


def _line_table(chunk, start, doc):
    """Lines that hold a word: index of the first word, of the word after the last, bounds in bytes, text number."""
    newline = np.flatnonzero(chunk.data == NEWLINE) + 1
    begin = np.unique(np.concatenate([chunk.offsets[:-1], newline]))
    line = np.searchsorted(begin, start, side="right") - 1
    first = np.flatnonzero(np.diff(line, prepend=-1))
    last = np.append(first[1:], len(line))
    line = line[first]
    end = np.append(begin, len(chunk.data))[line + 1]
    end = end - (chunk.data[end - 1] == NEWLINE)
    return first, last, begin[line], end, doc[first]


def text_statistics(column: pa.Array) -> dict[str, np.ndarray | list]:
    """All counts of the contract per text, and its normalised lines as (hash, words)."""
    names = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
    out: dict[str, list] = {n: [] for n in (*names, "text_hash", "line_hash", "line_words")}
    for chunk in chunks(column):
        start, end, doc = chunk.words()
        lower = HASH_A.prefix(NORMAL[chunk.data])
        raw = HASH_B.prefix(chunk.data)
        out["n_words"].append(chunk.per_doc(doc))
        out["word_chars"].append(chunk.count_bytes(IS_LEAD[chunk.data] & ~IS_SPACE[chunk.data]))
        out["n_symbols"].append(chunk.count_bytes(IS_SYMBOL[chunk.data]))
        out["n_repeat_words"].append(chunk.per_doc(doc[_windows(HASH_B.spans(raw, start, end), doc)]))
        first, last, begin, stop, line_doc = _line_table(chunk, start, doc)
        line_raw = HASH_B.spans(raw, begin, stop) + line_doc.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        order = np.lexsort((begin, line_raw))
        again = np.zeros(len(order), dtype=bool)
        again[order[1:]] = line_raw[order[1:]] == line_raw[order[:-1]]
        out["n_dup_lines"].append(chunk.per_doc(line_doc[again]))
        folded = HASH_A.prefix(HASH_A.spans(lower, start, end))
        line_hash, n_words = HASH_A.spans(folded, first, last).view(np.int64), (last - first).astype(np.int32)
        cut = np.searchsorted(line_doc, np.arange(chunk.n_docs + 1))
        for i in range(chunk.n_docs):
            out["line_hash"].append(line_hash[cut[i] : cut[i + 1]])
            out["line_words"].append(n_words[cut[i] : cut[i + 1]])
        out["text_hash"].append(HASH_B.spans(raw, chunk.offsets[:-1], chunk.offsets[1:]).view(np.int64))
    return {k: v if k.startswith("line_") else np.concatenate(v) if v else np.zeros(0, np.int64) for k, v in out.items()}


def _lists(values: list[np.ndarray], kind: pa.DataType) -> pa.Array:
    sizes = np.zeros(len(values) + 1, dtype=np.int32)
    np.cumsum([len(v) for v in values], out=sizes[1:])
    flat = np.concatenate(values) if values else np.zeros(0)
    return pa.ListArray.from_arrays(pa.array(sizes), pa.array(flat, type=kind))


def _measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        stats = text_statistics(batch.column("text"))
        columns = {"rid": batch.column("rid"), "k1": batch.column("k1"), "k2": batch.column("k2"), "doc_id": batch.column("doc_id"), "host": batch.column("host")}
        for name, values in stats.items():
            if name == "line_hash":
                columns[name] = _lists(values, pa.int64())
            elif name == "line_words":
                columns[name] = _lists(values, pa.int32())
            else:
                columns[name] = pa.array(values, type=pa.int64())
        yield pa.RecordBatch.from_pydict(columns)


MEASURED = "rid long, k1 long, k2 long, doc_id long, host string, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, text_hash long, line_hash array<long>, line_words array<int>"


def judge(docs: DataFrame, host: str = "source", min_docs: int = MIN_DOCS, share: float = SHARE, max_loss: float = MAX_LOSS, min_words: int = MIN_WORDS) -> DataFrame:
    """A row per document: the base counts, base_failed, words and hashes of its boilerplate lines, and kept.

    A null text has no word and fails; a null host is a host of its own; copies of one text count once towards a line's
    document count, so a group of copies never turns its own lines into boilerplate; repeated rows are judged each; an
    empty table gives no row. Columns beyond doc_id, text and the host column are not read.
    """
    rows = docs.select(F.monotonically_increasing_id().alias("rid"), *content_keys(host, "text"), F.col("doc_id").cast("long").alias("doc_id"), F.col(host).cast("string").alias("host"), F.col("text").cast("string").alias("text"))
    measured = materialize_texts(rows.mapInArrow(_measure, MEASURED))
    named = measured.withColumn("host", F.coalesce(F.concat(F.lit("h"), "host"), F.lit("null")))
    lines = named.select("rid", "host", "text_hash", F.explode(F.arrays_zip("line_hash", "line_words")).alias("line"))
    lines = lines.select("rid", "host", "text_hash", F.col("line.line_hash").alias("line_hash"), F.col("line.line_words").alias("line_words"))
    distinct = lines.select("host", "line_hash", "text_hash").distinct()
    texts = named.select("host", "text_hash").distinct().groupBy("host").agg(F.count("*").alias("texts"))
    often = distinct.groupBy("host", "line_hash").agg(F.count("*").alias("n_docs")).where(F.col("n_docs") > min_docs)
    boilerplate = often.join(texts, "host").where(F.col("n_docs") > F.col("texts") * share).select("host", "line_hash")
    removed = lines.join(boilerplate, ["host", "line_hash"]).groupBy("rid").agg(F.sum("line_words").cast("long").alias("removed_words"), F.collect_set("line_hash").alias("removed_lines"))
    out = measured.drop("text_hash", "line_hash", "line_words").join(removed, "rid", "left")
    out = out.withColumn("removed_words", F.coalesce("removed_words", F.lit(0)).cast("long"))
    failed = (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))
    depleted = (F.col("removed_words") > F.col("n_words") * max_loss) | (F.col("n_words") - F.col("removed_words") < min_words)
    return out.withColumn("base_failed", failed).withColumn("kept", ~failed & ~depleted)


def strip_lines(text: str, hashes: set[int]) -> str:
    """The text without the lines whose normalised hash is in hashes."""
    column = pa.array([text])
    lines = text_statistics(column)["line_hash"][0]
    kept, at = [], 0
    for line in text.split("\n"):
        if line.strip(" \t\n\x0b\x0c\r"):
            at += 1
            if int(lines[at - 1]) in hashes:
                continue
        kept.append(line)
    return "\n".join(kept)


def _strip(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        cut = batch.column("removed_lines").is_valid()
        at = batch.schema.get_field_index("text")
        if cut.true_count:
            texts, removed = batch.column("text").filter(cut), batch.column("removed_lines").filter(cut)
            fixed = pa.array((strip_lines(t.as_py(), set(r.as_py())) for t, r in zip(texts, removed, strict=True)), type=batch.schema.field(at).type)
            batch = batch.set_column(at, "text", pc.replace_with_mask(batch.column("text"), cut, fixed))
        yield batch.drop_columns(["removed_lines"])


def clean(docs: DataFrame, host: str = "source", **options) -> DataFrame:
    """The kept rows with their own columns, boilerplate lines cut out of their texts (n_chars follows).

    A verdict follows from host and text alone, so it is joined by hashes of both: rows without an id and rows that repeat one
    get their own. Columns beyond those that are read may have any name.
    """

    def work(named: DataFrame) -> DataFrame:
        columns = named.columns
        verdict = judge(named, host, **options).where("kept").groupBy("k1", "k2").agg(F.first("removed_lines").alias("removed_lines"))
        rows = named.select("*", *content_keys(host, "text"))
        kept = rows.join(verdict, ["k1", "k2"]).select(*columns, "removed_lines").mapInArrow(_strip, named.schema)
        if "n_chars" in columns:
            kept = kept.withColumn("n_chars", F.length("text").cast(named.schema["n_chars"].dataType))
        return kept

    return guarded(docs, work, (*DOCUMENT, host))


RESULT = ("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")

ORACLE = r"""
with d as (select doc_id, coalesce('h' || source, 'null') as host, coalesce(text, '') as text from documents),
  w as (select doc_id, regexp_extract_all(text, '[^\x20\x09-\x0D]+') as ws from d),
  base as (select doc_id, len(ws) as n_words, length(array_to_string(ws, '')) as word_chars from w),
  tok as (select doc_id, unnest(ws) as t, unnest(range(len(ws))) as i from w),
  win as (select doc_id, i, case when lead(t, 4) over o is not null then concat_ws(' ', t, lead(t, 1) over o, lead(t, 2) over o, lead(t, 3) over o, lead(t, 4) over o) end as g from tok window o as (partition by doc_id order by i)),
  twice as (select doc_id, i from win where g is not null qualify count(*) over (partition by doc_id, g) > 1),
  rep as (select doc_id, count(distinct i + j) as n_repeat_words from twice, range(5) r(j) group by doc_id),
  lines as (select doc_id, host, unnest(string_split(text, chr(10))) as raw from d),
  full_lines as (select doc_id, host, raw, regexp_extract_all(raw, '[^\x20\x09-\x0D]+') as ws from lines where regexp_matches(raw, '[^\x20\x09-\x0D]')),
  dup as (select doc_id, count(*) - count(distinct raw) as n_dup_lines from full_lines group by doc_id),
  norm as (select f.doc_id, f.host, d.text, len(ws) as n, translate(array_to_string(ws, ' '), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ123456789', 'abcdefghijklmnopqrstuvwxyz000000000') as line from full_lines f join d using (doc_id)),
  texts as (select host, count(distinct text) as n from d group by host),
  boiler as (select norm.host, line from norm join texts using (host) group by norm.host, line, texts.n having count(distinct text) > 20 and count(distinct text) > texts.n * 0.1),
  removed as (select doc_id, sum(n) as removed_words from norm join boiler using (host, line) group by doc_id),
  j as (select d.doc_id, n_words::bigint as n_words, word_chars::bigint as word_chars,
      length(regexp_replace(d.text, '[^#*$%&|<>]', '', 'g'))::bigint as n_symbols, coalesce(n_dup_lines, 0)::bigint as n_dup_lines,
      coalesce(n_repeat_words, 0)::bigint as n_repeat_words, coalesce(removed_words, 0) as removed_words
    from d join base using (doc_id) left join rep using (doc_id) left join dup using (doc_id) left join removed using (doc_id))
select doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, (n_words < 10 or 100 * n_repeat_words > 20 * n_words) as base_failed,
  not (n_words < 10 or 100 * n_repeat_words > 20 * n_words) and not (removed_words > n_words * 0.5 or n_words - removed_words < 10) as kept from j
"""


def query(spark, sf_dir: str) -> DataFrame:
    return judge(spark.read.parquet(f"{sf_dir}/documents.parquet")).select(*RESULT)
