"""Removal of boilerplate lines that are spread over many sites, in DataFrame expressions only.

Each non-blank line is reduced to a 128-bit key. A HyperLogLog sketch of the sites of each key is
merged by partial aggregation, so a line on a million pages costs one small sketch per task. Only lines whose estimate
can reach the threshold are looked at again. Exact copies of a text are one page there, which stands on the least of its
sites: a page that was copied to many sites is no boilerplate, and is left to the duplicate stages. Their sites are sketched
anew; an estimate clearly above the threshold decides, and lines near it get an exact distinct count.

Texts are cleaned in the scan that reads them. The spread lines are looked up in a list of checked size; should it be
too long for that, each text meets the list of its own lines in a join.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from supportbounds.llm.common import LOOKUP_KEYS, discard, keep, lookup, text_of

#: What is cut from both ends of a line before lines are compared.
_EDGES = " \t\r\x0b\x0c"


def _trimmed(line: Column) -> Column:
    return F.trim(line, F.lit(_EDGES))


def _key(line: Column) -> tuple[Column, Column]:
    return F.xxhash64(line), F.xxhash64(F.lit(1), line)


def lines_of(docs: DataFrame, text: str, site: str) -> DataFrame:
    """(site, d1, d2, h1, h2): one row per distinct non-blank line of each document; d1, d2 are the key of its text."""
    whole = text_of(docs, text)
    kept = F.filter(F.array_distinct(F.transform(F.split(whole, "\n"), _trimmed)), lambda x: x != "")
    d1, d2 = _key(whole)
    lines = docs.select(F.coalesce(F.col(site).cast("string"), F.lit("")).alias("site"), d1.alias("d1"), d2.alias("d2"), F.explode(kept).alias("line"))
    h1, h2 = _key(F.col("line"))
    return lines.select("site", "d1", "d2", h1.alias("h1"), h2.alias("h2"))


def spread_lines(docs: DataFrame, text: str = "text", site: str = "source", min_sites: int = 5, log2_registers: int = 9) -> DataFrame:
    """(h1, h2, n_sites) of every line that stands on ``min_sites`` sites or more."""
    lines = lines_of(docs, text, site)
    # five standard errors on either side; below them a line can't reach the threshold
    margin = 5 * 1.04 / 2 ** (log2_registers / 2)
    low, high = min_sites * (1 - margin), max(min_sites * (1 + margin), min_sites + 1)

    def guessed(rows: DataFrame) -> DataFrame:
        sketched = rows.groupBy("h1", "h2").agg(F.hll_sketch_agg("site", F.lit(log2_registers)).alias("sketch"))
        return sketched.select("h1", "h2", F.hll_sketch_estimate("sketch").alias("guess")).where(F.col("guess") >= int(low))

    # copies can only add sites, so no spread line is missed here
    first = keep(guessed(lines), "line-guesses")
    pages = lines.join(first.select("h1", "h2"), ["h1", "h2"], "left_semi").groupBy("h1", "h2", "d1", "d2").agg(F.min("site").alias("site"))
    pages = keep(pages.select("h1", "h2", "site"), "line-pages")
    again = keep(guessed(pages), "line-spread")
    near = again.where(F.col("guess") <= high).select("h1", "h2")
    # pairs first (hot lines are spread by their sites), then the count
    exact = pages.join(near, ["h1", "h2"], "left_semi").distinct().groupBy("h1", "h2").agg(F.count("*").alias("n_sites"))
    sure = again.where(F.col("guess") > high).select("h1", "h2", F.col("guess").alias("n_sites"))
    found = keep(exact.where(F.col("n_sites") >= min_sites).unionByName(sure), "spread-lines")
    discard(first, pages, again)
    return found


def removals(docs: DataFrame, spread: DataFrame, text: str = "text") -> DataFrame:
    """(d1, d2, drop): by the key of a text, the keys of its lines that are spread. Copies of a text fold into one row."""
    rows = lines_of(docs.withColumn("__sb_site", F.lit("")), text, "__sb_site")
    found = rows.join(spread.select("h1", "h2"), ["h1", "h2"], "left_semi").select("d1", "d2", "h1", "h2").distinct()
    return keep(found.groupBy("d1", "d2").agg(F.collect_list(F.struct("h1", "h2")).alias("drop")), "line-removals")


def remove_lines(
    docs: DataFrame, text: str = "text", site: str = "source", min_sites: int = 5, counts: tuple[str, str] | None = None, lookup_keys: int = LOOKUP_KEYS
) -> DataFrame:
    """``docs`` with the text rid of lines on ``min_sites`` sites or more; no row and no other column changes.

    Null text stays null; null sites count as one site of their own; blank lines stay; repeated rows are
    treated alike; an empty table gives an empty result; texts of any length are cleaned whole. A document of nothing but
    spread lines keeps its row and its blank lines. ``counts`` names two further columns, the non-blank lines and
    those removed; names that ``docs`` has are refused.
    """
    if counts and set(counts) & set(docs.columns):
        raise ValueError(f"columns {counts} are there already")
    spread = spread_lines(docs, text, site, min_sites)
    known = lookup(spread, lookup_keys)
    df = docs
    if known is None:
        drop = removals(docs, spread, text)
        d1, d2 = _key(text_of(docs, text))
        own = drop.select(F.col("d1").alias("__sb_d1"), F.col("d2").alias("__sb_d2"), F.col("drop").alias("__sb_drop"))
        # texts without a word have no lines to remove: they stay apart, or all would meet in one task
        salt = F.when(text_of(docs, text).rlike(r"\S"), d1).otherwise(F.monotonically_increasing_id())
        df = df.withColumns({"__sb_d1": salt, "__sb_d2": d2}).join(own, ["__sb_d1", "__sb_d2"], "left")

    df = df.withColumn("__sb_lines", F.split(text_of(df, text), "\n"))
    df = df.withColumn("__sb_cut", F.transform("__sb_lines", _trimmed))
    if known is not None:
        df = known.marked(df, "__sb_cut", _key, "__sb_hit")
    else:
        listed = lambda x: F.coalesce(F.array_contains("__sb_drop", F.struct(_key(x)[0].alias("h1"), _key(x)[1].alias("h2"))), F.lit(False))
        df = df.withColumn("__sb_hit", F.transform("__sb_cut", listed))
    # blank lines are never among the spread ones
    df = df.withColumn("__sb_left", F.filter("__sb_lines", lambda x, i: ~F.get("__sb_hit", i)))
    filled = F.size(F.filter("__sb_cut", lambda x: x != "")).cast("long")
    cut = F.size("__sb_left") < F.size("__sb_lines")
    out = [F.when(cut, F.array_join("__sb_left", "\n")).otherwise(F.col(c)).alias(c) if c == text else F.col(c) for c in docs.columns]
    if counts:
        out += [filled.alias(counts[0]), (F.size("__sb_lines") - F.size("__sb_left")).cast("long").alias(counts[1])]
    return df.select(*out)


#: The same in DuckDB, with exact counts: the sketches decide only where they cannot err at this margin.
ORACLE = r"""
WITH l AS (
  SELECT doc_id, coalesce(text, '') AS text, coalesce(source, '') AS source, string_split(coalesce(text, ''), chr(10)) AS ls FROM documents
), e AS (
  SELECT doc_id, text, source, unnest(ls) AS raw, generate_subscripts(ls, 1) AS pos FROM l
), t AS (
  SELECT *, trim(raw, ' ' || chr(9) || chr(13) || chr(11) || chr(12)) AS line FROM e
), p AS (
  SELECT line, text, min(source) AS source FROM t WHERE line <> '' GROUP BY line, text
), s AS (
  SELECT line FROM p GROUP BY line HAVING count(DISTINCT source) >= 5
), m AS (
  SELECT t.*, s.line IS NOT NULL AS hit FROM t LEFT JOIN s ON t.line = s.line
)
SELECT doc_id, count(*) FILTER (line <> '') AS n_lines, count(*) FILTER (hit) AS n_removed,
       sha256(coalesce(string_agg(raw, chr(10) ORDER BY pos) FILTER (NOT hit), '')) AS text_sha256
FROM m GROUP BY doc_id
"""
