"""Quality rules: counts within a document, and lines that too many documents of a host share.

Lines are normalised and hashed; for each (host, line) the different documents that hold it are counted (copies of one text
are one document). A line in more than ``max_documents`` of them is over the limit and leaves all texts of the host.
A document that keeps less than a fifth of its words then is depleted and rejected.

Counts within texts are vectorised over Arrow batches; counts across documents are aggregations whose first
step is local to each task, so a hot host or a hot line costs one row per task, and per text where the line may be over the limit.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, LongType, StructField, StructType

from supportbounds.llm.common import ASCII_BLANKS, LOOKUP_KEYS, discard, keep, lookup, text_of

MIN_WORDS, MAX_REPEAT_SHARE = 50, 0.5
MAX_DOCUMENTS, LEAST_LEFT = 10, 0.2
STATS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
_IS_SYMBOL = np.zeros(256, dtype=np.int64)
_IS_SYMBOL[np.frombuffer(b"#*$%&|<>", dtype=np.uint8)] = 1
_SLICE = 4_000_000
#: Of the hash of a normalised line; the one that Spark's own xxhash64 has.
SEED = 42
LISTS = {"lines": pa.int64(), "line_words": pa.int64()}


def _sums(values: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    total = np.concatenate([[0], np.cumsum(values, dtype=np.int64)])
    return total[offsets[1:]] - total[offsets[:-1]]


def _flat(lists: pa.ListArray, keep_mask: np.ndarray | None = None) -> tuple[pa.Array, np.ndarray]:
    """Values of a list array and their offsets per list; a mask leaves some values out."""
    values, offsets = lists.flatten(), lists.offsets.to_numpy() - lists.offsets[0].as_py()
    if keep_mask is None:
        return values, offsets
    counts = np.concatenate([[0], np.cumsum(keep_mask)])
    return values.filter(pa.array(keep_mask)), counts[offsets]


def measure(texts: pa.Array) -> dict[str, np.ndarray | pa.Array]:
    """Statistics of each text of a non-null string array; ``lines`` and ``line_words`` are lists."""
    n = len(texts)
    split = pc.ascii_split_whitespace(texts)
    words, at = _flat(split, pc.not_equal(split.flatten(), "").to_numpy(zero_copy_only=False))
    out: dict = {"n_words": np.diff(at), "word_chars": _sums(pc.utf8_length(words).to_numpy(), at)}
    raw = texts.cast(pa.binary())
    bounds = np.frombuffer(raw.buffers()[1], dtype=np.int32)[raw.offset : raw.offset + n + 1].astype(np.int64)
    data = np.frombuffer(raw.buffers()[2], dtype=np.uint8) if raw.buffers()[2] is not None else np.empty(0, np.uint8)
    out["n_symbols"] = _sums(_IS_SYMBOL[data[bounds[0] : bounds[-1]]], bounds - bounds[0])
    out["n_repeat_words"] = _repeats(words, at)
    out |= _lines(texts)
    return out


def _repeats(words: pa.Array, at: np.ndarray) -> np.ndarray:
    """Words inside three-word windows that occur twice or more, for each text."""
    coded = words.dictionary_encode()
    code, size = coded.indices.to_numpy().astype(np.int64), max(1, len(coded.dictionary))
    doc = np.repeat(np.arange(len(at) - 1), np.diff(at))
    whole = np.flatnonzero(doc[2:] == doc[:-2])
    key = _triple(code[whole], code[whole + 1], code[whole + 2], size)
    order = np.argsort(key, kind="stable")  # stable: the windows of one text stay together within a key
    same = (key[order[1:]] == key[order[:-1]]) & (doc[whole[order[1:]]] == doc[whole[order[:-1]]])
    again = np.zeros(len(whole), dtype=bool)
    again[order[1:][same]] = True
    again[order[:-1][same]] = True
    covered = np.zeros(len(code), dtype=np.int64)
    for shift in range(3):
        covered[whole[again] + shift] = 1
    return _sums(covered, at)


def _triple(a: np.ndarray, b: np.ndarray, c: np.ndarray, size: int) -> np.ndarray:
    """One integer for three codes below ``size``, in their order."""
    pair = a * size + b
    if size >= 1 << 21:  # three codes don't fit into 63 bits: number the pairs first, in order
        pair = np.unique(pair, return_inverse=True)[1]
    return pair * size + c


def _lines(texts: pa.Array) -> dict[str, np.ndarray | pa.Array]:
    split = pc.split_pattern(texts, "\n")
    coded = split.flatten().dictionary_encode()
    tokens = [line.lower().split() for line in coded.dictionary.cast(pa.binary()).to_pylist()]
    counts = np.array([len(t) for t in tokens], dtype=np.int64)
    hashes = np.array([xxhash.xxh64_intdigest(b" ".join(t), SEED) for t in tokens], dtype=np.uint64).view(np.int64)
    at = split.offsets.to_numpy() - split.offsets[0].as_py()
    code = coded.indices.to_numpy()
    n = len(texts)
    doc = np.repeat(np.arange(n), np.diff(at))
    real = counts[code] > 0 if len(code) else np.zeros(0, dtype=bool)
    code, doc = code[real], doc[real]
    distinct = np.unique(doc * max(1, len(tokens)) + code) // max(1, len(tokens))
    n_dup = np.bincount(doc, minlength=n) - np.bincount(distinct, minlength=n)
    if not len(code):
        empty = pa.array(np.zeros(n + 1, np.int32))
        lists = {c: pa.ListArray.from_arrays(empty, pa.array([], k)) for c, k in LISTS.items()}
        return {"n_dup_lines": n_dup, **lists}
    # normalised lines of a text, each once, with the words of all its repeats
    order = np.lexsort((hashes[code], doc))
    d, h, c = doc[order], hashes[code][order], counts[code][order]
    first = np.flatnonzero(np.r_[True, (d[1:] != d[:-1]) | (h[1:] != h[:-1])])
    per_doc = pa.array(np.concatenate([[0], np.cumsum(np.bincount(d[first], minlength=n))]).astype(np.int32))
    values = {"lines": pa.array(h[first]), "line_words": pa.array(np.add.reduceat(c, first))}
    return {"n_dup_lines": n_dup, **{name: pa.ListArray.from_arrays(per_doc, v) for name, v in values.items()}}


def slices(batch: pa.RecordBatch, column: str, most: int = _SLICE) -> Iterator[pa.RecordBatch]:
    """The batch in pieces of a few MB of text each (one text at least), so that working arrays stay small."""
    size = np.cumsum(pc.binary_length(batch.column(column)).fill_null(0).to_numpy(zero_copy_only=False))
    start = 0
    while start < batch.num_rows:
        stop = max(start + 1, int(np.searchsorted(size, (size[start - 1] if start else 0) + most, side="right")))
        yield batch.slice(start, stop - start)
        start = stop


def with_stats(docs: DataFrame, text: str) -> DataFrame:
    """``docs`` with the statistics and lines of ``text`` in place of it; the text must not be null."""
    others = [f for f in docs.schema.fields if f.name != text]

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, text):
                got = measure(part.column(text))
                arrays = [*(part.column(f.name) for f in others), *(pa.array(got[s]).cast(pa.int64()) for s in STATS), *(got[c] for c in LISTS)]
                yield pa.RecordBatch.from_arrays(arrays, names=[*(f.name for f in others), *STATS, *LISTS])

    lists = [StructField(c, ArrayType(LongType())) for c in LISTS]
    return docs.mapInArrow(add, StructType([*others, *(StructField(s, LongType()) for s in STATS), *lists]))


def base_failed():
    return (F.col("n_words") < MIN_WORDS) | (F.col("n_repeat_words") > MAX_REPEAT_SHARE * F.col("n_words"))


def line_rows(rows: DataFrame) -> DataFrame:
    """(row, host, text_key, line, words): the lines of the kept rows."""
    zipped = rows.select("row", "host", "text_key", F.explode(F.arrays_zip(*LISTS)).alias("l"))
    return zipped.select("row", "host", "text_key", F.col("l.lines").alias("line"), F.col("l.line_words").alias("words"))


def over_limit_lines(lines: DataFrame, max_documents: int = MAX_DOCUMENTS) -> DataFrame:
    """(host, line) of the lines that more than ``max_documents`` different texts of the host hold."""
    # rows first, which copies only add to; texts are told apart where they can matter
    common = lines.groupBy("host", "line").agg(F.count("*").alias("n")).where(F.col("n") > max_documents).select("host", "line")
    common = keep(common, "common-lines")
    texts = lines.select("host", "line", "text_key").join(common, ["host", "line"], "left_semi").distinct()
    over = keep(texts.groupBy("host", "line").agg(F.count("*").alias("n")).where(F.col("n") > max_documents).select("host", "line"), "frequent-lines")
    discard(common)
    return over


def _measured(docs: DataFrame, text: str, host: str, *others: str) -> DataFrame:
    """The statistics of each row, its host, the key of its text and a number, and the named columns, in the shared folder."""
    whole = text_of(docs, text)
    named = {"host": F.coalesce(F.col(host).cast("string"), F.lit("")), "text_key": F.xxhash64(whole), "measured_text": whole}
    plain = docs.select(*[F.col(c).alias(f"in_{i}") for i, c in enumerate(others)], *[c.alias(n) for n, c in named.items()])
    return keep(with_stats(plain, "measured_text").withColumn("row", F.monotonically_increasing_id()), "quality-rows")


def _gone(rows: DataFrame, frequent: DataFrame) -> DataFrame:
    """(row, gone): words in lines over the limit, of the rows that pass the base rules."""
    held = line_rows(rows.where(~base_failed())).select("row", "host", "line", "words")
    return held.join(frequent, ["host", "line"]).groupBy("row").agg(F.sum("words").alias("gone"))


def judge(docs: DataFrame, text: str = "text", key: str = "doc_id", host: str = "source", max_documents: int = MAX_DOCUMENTS, least_left: float = LEAST_LEFT) -> DataFrame:
    """One row per document: key, counts, base_failed, kept, words left, and the digest of the text (``text_key``).

    Null texts count as empty (no words: rejected), null hosts as one host; repeated rows are judged row by row and count as one
    document; ties do not arise; texts of any length are counted whole; an empty table gives an empty result.
    """
    rows = _measured(docs, text, host, key)
    frequent = over_limit_lines(line_rows(rows), max_documents)
    out = rows.drop(*LISTS).join(_gone(rows, frequent), "row", "left")
    left = F.col("n_words") - F.coalesce("gone", F.lit(0))
    failed = base_failed()
    return out.select(
        F.col("in_0").alias(key), F.col("host"), *STATS, failed.alias("base_failed"), (~failed & (left >= least_left * F.col("n_words"))).alias("kept"), left.alias("n_words_left"), "text_key"
    )


def _normalised(line: Column) -> Column:
    lower = F.translate(line, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    return F.trim(F.regexp_replace(lower, ASCII_BLANKS, " "))


def reject(
    docs: DataFrame, text: str = "text", host: str = "source", max_documents: int = MAX_DOCUMENTS, least_left: float = LEAST_LEFT, lookup_keys: int = LOOKUP_KEYS
) -> DataFrame:
    """The rows of ``docs`` that the rules keep, their texts without the lines over the limit.

    All columns stay. The rules for nulls, repeated rows, long texts and empty tables are those of :func:`judge`. A text that holds no such line stays as
    it is, character by character. Lines are looked up in a list of checked size; beyond it every text is joined with its own lines.
    """
    rows = _measured(docs, text, host)
    frequent = over_limit_lines(line_rows(rows), max_documents)
    lost = _gone(rows, frequent).join(rows.select("row", "n_words"), "row").where(F.col("n_words") - F.col("gone") < least_left * F.col("n_words"))
    # a verdict depends on host and text alone
    out = rows.join(lost.select("row"), "row", "left_semi").unionByName(rows.where(base_failed())).select("host", "text_key").distinct()
    out = keep(out.select(F.col("host").alias("__sb_host"), F.col("text_key").alias("__sb_text")), "rejected")
    named = docs.withColumns({"__sb_host": F.coalesce(F.col(host).cast("string"), F.lit("")), "__sb_text": F.xxhash64(text_of(docs, text))})
    left = named.join(out, ["__sb_host", "__sb_text"], "left_anti")
    key = lambda h, line: (F.xxhash64(h, line), F.xxhash64(F.lit(1), h, line))
    h1, h2 = key(F.col("host"), F.col("line"))
    known = lookup(frequent.select(h1.alias("h1"), h2.alias("h2")), lookup_keys)
    if known is None:
        own = line_rows(rows).join(frequent, ["host", "line"], "left_semi").select("host", "text_key", "line").distinct()
        own = keep(own.groupBy("host", "text_key").agg(F.collect_list("line").alias("own")), "own-lines")
        own = own.select(F.col("host").alias("__sb_host"), F.col("text_key").alias("__sb_text"), F.col("own").alias("__sb_own"))
        left = left.join(own, ["__sb_host", "__sb_text"], "left")

    left = left.withColumn("__sb_lines", F.split(text_of(left, text), "\n"))
    left = left.withColumn("__sb_hashes", F.transform("__sb_lines", lambda x: F.xxhash64(_normalised(x))))
    if known is None:
        left = left.withColumn("__sb_over", F.transform("__sb_hashes", lambda h: F.coalesce(F.array_contains("__sb_own", h), F.lit(False))))
    else:
        left = known.marked(left, "__sb_hashes", lambda h: key(F.col("__sb_host"), h), "__sb_over")
    left = left.withColumn("__sb_left", F.filter("__sb_lines", lambda x, i: ~F.get("__sb_over", i)))
    cut = F.size("__sb_left") < F.size("__sb_lines")
    return left.select(*[F.when(cut, F.array_join("__sb_left", "\n")).otherwise(F.col(c)).alias(c) if c == text else F.col(c) for c in docs.columns])


_WORDS = r"list_filter(string_split_regex(text, '[\x20\x09-\x0D]+'), lambda w: w <> '')"
ORACLE = rf"""
WITH d AS (SELECT doc_id, coalesce(source, '') AS host, coalesce(text, '') AS text FROM documents
), w AS (SELECT *, {_WORDS} AS w, string_split(text, chr(10)) AS ls FROM d
), x AS (SELECT *, list_transform(range(1, len(w) - 1), lambda i: [w[i], w[i + 1], w[i + 2]]) AS tri FROM w
), e AS (SELECT doc_id, unnest(tri) AS t, generate_subscripts(tri, 1) AS i FROM x
), r AS (SELECT *, count(*) OVER (PARTITION BY doc_id, t) AS c FROM e
), p AS (SELECT doc_id, count(DISTINCT j) AS n FROM (SELECT doc_id, unnest([i, i + 1, i + 2]) AS j FROM r WHERE c > 1) GROUP BY doc_id
), l AS (SELECT doc_id, host, unnest(ls) AS raw FROM w
), ln AS (SELECT doc_id, host, raw, trim(regexp_replace(translate(raw, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+', ' ', 'g')) AS line FROM l
), lc AS (SELECT doc_id, host, line, sum(len(string_split(line, ' '))) AS words FROM ln WHERE line <> '' GROUP BY ALL
), dup AS (SELECT doc_id, count(*) - count(DISTINCT raw) AS n FROM ln WHERE line <> '' GROUP BY doc_id
), f AS (SELECT lc.host, lc.line FROM lc JOIN d USING (doc_id) GROUP BY ALL HAVING count(DISTINCT d.text) > {MAX_DOCUMENTS}
), gone AS (SELECT doc_id, sum(words) AS n FROM lc JOIN f USING (host, line) GROUP BY doc_id
), b AS (
  SELECT x.doc_id, len(w) AS n_words, coalesce(list_sum(list_transform(w, lambda s: length(s))), 0) AS word_chars,
    length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')) AS n_symbols, coalesce(dup.n, 0) AS n_dup_lines, coalesce(p.n, 0) AS n_repeat_words, coalesce(gone.n, 0) AS gone
  FROM x LEFT JOIN p ON p.doc_id = x.doc_id LEFT JOIN dup ON dup.doc_id = x.doc_id LEFT JOIN gone ON gone.doc_id = x.doc_id
)
SELECT doc_id, CAST(n_words AS BIGINT) AS n_words, CAST(word_chars AS BIGINT) AS word_chars, CAST(n_symbols AS BIGINT) AS n_symbols, CAST(n_dup_lines AS BIGINT) AS n_dup_lines,
  CAST(n_repeat_words AS BIGINT) AS n_repeat_words, n_words < {MIN_WORDS} OR 100 * n_repeat_words > 50 * n_words AS base_failed,
  NOT (n_words < {MIN_WORDS} OR 100 * n_repeat_words > 50 * n_words) AND n_words - CASE WHEN n_words < {MIN_WORDS} OR 100 * n_repeat_words > 50 * n_words THEN 0 ELSE gone END >= {LEAST_LEFT} * n_words AS kept
FROM b
"""
