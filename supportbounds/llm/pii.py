"""Information-theoretic removal of personal data, in DataFrame expressions only.

Base detection finds four kinds of protected entities by pattern (:data:`KINDS`). Corpus statistics then tell which
ordinary terms give an entity away. A term of a document stands with the entity before it and the entity after it; with one entity
in a document that is co-occurrence in the document, with many it stays linear in the text. Over different texts (copies count once),

    p(c | t) = n(c, t) / (n(t) + prior)     hidden(c, t) = -log2 p(c | t)     PMI(c; t) = log2(p(c | t) N / n(c))

where n(t) counts the texts with term t anywhere, n(c) those with the entity and n(c, t) those in which t stands with c. ``hidden`` is
what stays unknown of the entity once the term is known, in bits; the prior keeps a few chance meetings from looking certain.
A term discloses c if little stays hidden and the PMI is at least half of the entity's information IC(c) = log2(N / n(c)).
Terms with p(c | t) of ``remove_at`` or more are removed, those from ``generalise_at`` on are replaced by a class word: all their occurrences,
in all texts.

Arrays are added up, cut and joined in blocks of about the root of their length, so that a text of a megabyte with many thousands of spans is no
special case.
"""

from __future__ import annotations

from math import ceil

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from supportbounds.llm.common import LOOKUP_KEYS, keep, lookup, text_of, with_hint

#: Kind and pattern, in the order of the output. Each is written so that a search takes time in proportion to the
#: text: possessive runs, and starts only where a run starts (or where the last match ended, \G).
KINDS = {
    "email": r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
_OCTET = r"0*(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[0-9]{1,2})"
_TERM = r"\p{L}{3,}"


def _blocks(df: DataFrame, values: dict[str, str]) -> DataFrame:
    """Adds ``out``: the array cut into blocks of about the root of its length, for each array column -> ``out``."""
    size = lambda c: F.greatest(F.ceil(F.sqrt(F.size(c))).cast("int"), F.lit(1))
    firsts = lambda c: F.when(F.size(c) > 0, F.sequence(F.lit(0), F.floor((F.size(c) - 1) / size(c)).cast("int"))).otherwise(F.array().cast("array<int>"))
    cut = lambda c: F.transform(firsts(c), lambda k: F.slice(F.col(c), k * size(c) + 1, size(c)))
    return df.withColumns({out: cut(c) for c, out in values.items()})


def _adding(values: Column) -> Column:
    """Sums of an array up to and with each place; quadratic, for one block."""
    empty = F.struct(F.lit(0).alias("at"), F.array().cast("array<int>").alias("found"))

    def step(acc: Column, x: Column) -> Column:
        at = acc["at"] + x
        return F.struct(at.alias("at"), F.concat(acc["found"], F.array(at)).alias("found"))

    return F.aggregate(values, empty, step)["found"]


def located(df: DataFrame, columns: dict[tuple[str, str], str]) -> DataFrame:
    """Adds ``out``: (start, end, value) of each match, in code points, for each (pieces between matches, matches) -> ``out``."""
    names = {out: f"__{out}" for out in columns.values()}
    steps = {f"{names[out]}_steps": F.zip_with(F.slice(F.col(parts), 1, F.size(hits)), hits, lambda p, h: F.length(p) + F.length(h)) for (parts, hits), out in columns.items()}
    df = _blocks(df.withColumns(steps), {f"{n}_steps": f"{n}_cut" for n in names.values()})
    df = df.withColumns({f"{n}_in": F.transform(f"{n}_cut", _adding) for n in names.values()})
    df = df.withColumns({f"{n}_sums": _adding(F.transform(f"{n}_in", lambda b: F.element_at(b, -1))) for n in names.values()})
    before = lambda n: F.concat(F.array(F.lit(0)), F.slice(f"{n}_sums", 1, F.greatest(F.size(f"{n}_sums") - 1, F.lit(0))))
    df = df.withColumns({f"{n}_ends": F.flatten(F.zip_with(F.when(F.size(f"{n}_in") > 0, F.col(f"{n}_in")).otherwise(F.array(F.array().cast("array<int>"))), before(n), lambda b, o: F.transform(b, lambda x: x + o))) for n in names.values()})
    span = lambda h, e: F.struct((e - F.length(h)).alias("start"), e.alias("end"), h.alias("value"))
    df = df.withColumns({out: F.zip_with(hits, f"{names[out]}_ends", span) for (_, hits), out in columns.items()})
    return df.drop(*[f"{n}_{x}" for n in names.values() for x in ("steps", "cut", "in", "sums", "ends")])


def _luhn(digits: Column) -> Column:
    backwards = F.reverse(digits)

    def add(acc: Column, i: Column) -> Column:
        d = F.substring(backwards, i, F.lit(1)).cast("int")
        return acc + F.when(i % 2 == 1, d).when(d > 4, 2 * d - 9).otherwise(2 * d)

    return F.aggregate(F.sequence(F.lit(1), F.length(digits)), F.lit(0), add) % 10 == 0


def _valid(kind: str, value: Column) -> Column:
    if kind == "ip":
        return value.rlike(rf"^{_OCTET}(?:\.{_OCTET}){{3}}$")
    if kind == "card":
        digits = F.regexp_replace(value, "[ -]", "")
        return F.when(F.length(digits).between(16, 19), _luhn(digits)).otherwise(False)
    if kind == "phone":
        return F.length(F.regexp_replace(value, "[^0-9]", "")).between(8, 15)
    return F.lit(True)


def _spans_of_kind(kind: str, found: Column) -> Column:
    held = F.filter(found, lambda x: _valid(kind, x["value"]))
    return F.transform(held, lambda x: F.struct(F.lit(kind).alias("kind"), x["start"].alias("start"), x["end"].alias("end"), x["value"].alias("value")))


def _count_of_kind(kind: str) -> Column:
    return F.size(F.filter("base", lambda x: x["kind"] == kind)).cast("long").alias(f"n_{kind}")


def with_base_spans(df: DataFrame, text: str, out: str = "base") -> DataFrame:
    """Adds ``out``: array of (kind, start, end, value), by kind as listed and then by start."""
    none = F.array().cast("array<string>")
    for kind, pattern in KINDS.items():
        # texts without a trace of the kind skip the search
        seen = F.contains(df[text], F.lit({"email": "@", "ip": ".", "phone": "+"}.get(kind, ""))) if kind != "card" else df[text].rlike("[0-9][ -]?[0-9]")
        df = df.withColumn(f"__hits_{kind}", F.when(seen, F.regexp_extract_all(F.col(text), F.lit(pattern), F.lit(0))).otherwise(none))
        df = df.withColumn(f"__parts_{kind}", F.when(F.size(f"__hits_{kind}") > 0, F.split(F.col(text), pattern, -1)).otherwise(none))
    df = located(df, {(f"__parts_{k}", f"__hits_{k}"): f"__at_{k}" for k in KINDS})
    df = df.withColumn(out, F.concat(*[_spans_of_kind(k, F.col(f"__at_{k}")) for k in KINDS]))
    return df.drop(*[f"__{x}_{k}" for k in KINDS for x in ("parts", "hits", "at")])


def _entity(value: Column) -> Column:
    """What counts as the same entity: addresses without regard to case, numbers by their digits, hosts as they are."""
    plain = F.when(value.rlike(r"^[0-9]+(\.[0-9]+){3}$"), value).otherwise(F.regexp_replace(value, "[^0-9]", ""))
    return F.when(F.contains(value, F.lit("@")), F.lower(value)).otherwise(plain)


#: Entities and terms in the order of the text. An address is told by its first letter, wherever the last match ended.
_STREAM = "|".join([KINDS["email"].replace(r"|\G", ""), KINDS["phone"], KINDS["ip"], KINDS["card"], _TERM])
_MARK = "\u0001"


def _stream(text: Column) -> Column:
    """The lower-cased terms of a text, with its entities in between, each behind a mark."""
    found = F.regexp_extract_all(F.lower(text), F.lit(_STREAM), F.lit(0))
    return F.array_join(F.transform(found, lambda x: F.when(x.rlike("[0-9@]"), F.concat(F.lit(_MARK), _entity(x))).otherwise(x)), " ")


def _digest(text: Column) -> tuple[Column, Column]:
    return F.xxhash64(text), F.xxhash64(F.lit(1), text)


def detect(docs: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """One kept row per document: key, digest of the text (d1, d2), base spans, their entities, and the stream of terms where there is an entity."""
    df = with_base_spans(docs.select(F.col(key).alias("key"), text_of(docs, text).alias("text")), "text")
    bare = F.transform("base", lambda x: F.struct(x["kind"].alias("kind"), x["start"].alias("start"), x["end"].alias("end")))
    entities = F.array_distinct(F.transform("base", lambda x: _entity(x["value"])))
    d1, d2 = _digest(F.col("text"))
    stream = F.when(F.size("base") > 0, _stream(F.col("text")))
    return keep(df.select("key", d1.alias("d1"), d2.alias("d2"), bare.alias("base"), entities.alias("entities"), stream.alias("stream")), "pii-rows")


def _meetings(rows: DataFrame, least: int) -> tuple[DataFrame, DataFrame] | None:
    """(entity, term, n_ct) and (entity, n_c), both kept, of the pairs that ``least`` different texts hold; None if there are none."""
    held = rows.where(F.size("entities") > 0).select("d1", "d2", F.explode("entities").alias("entity")).distinct()
    shared = keep(held.groupBy("entity").agg(F.count("*").alias("n_c")).where(F.col("n_c") >= least), "shared-entities")
    texts = held.join(shared, "entity", "left_semi").select("d1", "d2").distinct()
    streams = rows.where("stream IS NOT NULL").join(texts, ["d1", "d2"], "left_semi").groupBy("d1", "d2").agg(F.any_value("stream").alias("stream"))
    cut = streams.withColumn("runs", F.transform(F.split("stream", _MARK), lambda s: F.split(s, " ")))
    # each run after the first begins with its entity
    terms = F.transform("runs", lambda r, i: F.array_distinct(F.filter(r, lambda x, k: (x != "") & ((i == 0) | (k > 0)))))
    cut = cut.withColumn("terms", terms).withColumn("owners", F.transform(F.slice("runs", 2, F.size("runs")), lambda r: F.get(r, F.lit(0))))
    pair = lambda e, t: F.struct(e.alias("entity"), t.alias("terms"))
    n = F.size("owners")
    both = F.concat(F.zip_with("owners", F.slice("terms", 1, n), pair), F.zip_with("owners", F.slice("terms", 2, n), pair))
    flat = cut.select("d1", "d2", F.explode(both).alias("x")).select("d1", "d2", F.col("x.entity").alias("entity"), F.explode("x.terms").alias("term"))
    met = flat.join(shared.select("entity"), "entity", "left_semi").distinct().groupBy("entity", "term").agg(F.count("*").alias("n_ct"))
    met = keep(met.where(F.col("n_ct") >= least), "pii-meetings")
    return None if met.isEmpty() else (met, shared)


def _terms_of(docs: DataFrame, text: str) -> DataFrame:
    """(d1, d2, h): the hash of each different term of each row's text."""
    whole = text_of(docs, text)
    d1, d2 = _digest(whole)
    words = F.array_distinct(F.transform(F.regexp_extract_all(F.lower(whole), F.lit(_TERM), F.lit(0)), lambda t: F.xxhash64(t)))
    return docs.select(d1.alias("d1"), d2.alias("d2"), F.explode(words).alias("h"))


def _holders(docs: DataFrame, met: DataFrame, text: str, prior: float, generalise_at: float, part: int = 64) -> DataFrame:
    """(d1, d2, term): which different texts hold the terms of ``met`` that may be rare enough to disclose something.

    A term that many of one part of all texts hold is in at least as many texts, so frequent terms leave before rows are moved; no other one does.
    """
    terms = keep(met.groupBy("term").agg(F.max("n_ct").alias("most")).withColumn("h", F.xxhash64("term")), "pii-terms")
    share = docs.where(F.pmod(F.xxhash64(text_of(docs, text)), F.lit(part)) == 0)
    least = _terms_of(share, text).join(terms.select("h"), "h", "left_semi").groupBy("h").agg(F.count_distinct("d1").alias("least"))
    rare = terms.join(least, "h", "left").where(F.col("most") >= generalise_at * (F.coalesce("least", F.lit(0)) + prior))
    rare = keep(rare.select("h", "term"), "pii-rare-terms")
    hinted = with_hint(_terms_of(docs, text), rare, "h", "hinted").where("hinted")
    return keep(hinted.join(rare, "h").select("d1", "d2", "term").distinct(), "term-holders")


def _occurrences(docs: DataFrame, own: DataFrame, text: str) -> DataFrame:
    """(d1, d2, found): places and lower-cased values of the terms that ``own`` lists for a text; terms inside addresses are left out."""
    whole = text_of(docs, text)
    d1, d2 = _digest(whole)
    df = with_hint(docs.select(d1.alias("d1"), d2.alias("d2"), whole.alias("text")), own, "d1", "hinted").where("hinted").drop("hinted")
    # the other texts are left behind before places are looked for
    df = keep(df.join(own, ["d1", "d2"]).dropDuplicates(["d1", "d2"]), "texts-with-terms")
    blank = lambda p, h: F.concat(p, F.repeat(F.lit(" "), F.length(F.coalesce(h, F.lit("")))))
    df = df.withColumn("mail", F.regexp_extract_all("text", F.lit(KINDS["email"]), F.lit(0)))
    df = df.withColumn("masked", F.when(F.size("mail") > 0, F.array_join(F.zip_with(F.split("text", KINDS["email"], -1), "mail", blank), "")).otherwise(F.col("text")))
    df = df.withColumns({"hits": F.regexp_extract_all("masked", F.lit(_TERM), F.lit(0)), "parts": F.split("masked", _TERM, -1)})
    df = located(df, {("parts", "hits"): "all"})
    # no condition on what is found: it would be pushed below the arrays, which would then be made anew for each element
    span = lambda x: F.struct(x["start"].alias("start"), x["end"].alias("end"), F.lower(x["value"]).alias("term"))
    return keep(df.select("d1", "d2", F.filter(F.transform("all", span), lambda x: F.array_contains("own", x["term"])).alias("found")), "term-places")


def disclosing_spans(
    docs: DataFrame, rows: DataFrame, text: str = "text", prior: float = 1.0, remove_at: float = 0.75, generalise_at: float = 0.6
) -> DataFrame:
    """(d1, d2, terms): for each text that needs it, the term spans with their action, from the kept rows of :func:`detect`."""
    spark = docs.sparkSession
    # fewer texts than this cannot reach the lower threshold, however they are distributed
    least = max(1, ceil(prior * generalise_at / (1 - generalise_at) - 1e-9))
    none = spark.createDataFrame([], "d1 long, d2 long, terms array<struct<start:int,end:int,action:string>>")
    found = _meetings(rows, least)
    if found is None:
        return none
    met, shared = found
    holders = _holders(docs, met, text, prior, generalise_at)
    frequencies = holders.groupBy("term").agg(F.count("*").alias("n_t"))
    total = rows.select("d1", "d2").distinct().count()
    scored = met.join(shared, "entity").join(frequencies, "term").withColumn("p", F.col("n_ct") / (F.greatest("n_t", "n_ct") + prior))
    pmi, information = F.log2(F.col("p") * total / F.col("n_c")), F.log2(F.lit(float(total)) / F.col("n_c"))
    scored = scored.where((F.col("p") >= generalise_at) & (2 * pmi >= information) & (information > 0))
    told = keep(scored.groupBy("term").agg(F.max("p").alias("p")), "disclosing-terms")
    if told.isEmpty():
        return none
    own = keep(holders.join(told, "term", "left_semi").groupBy("d1", "d2").agg(F.collect_list("term").alias("own")), "terms-of-texts")
    places = _occurrences(docs, own, text)
    action = F.when(F.col("p") >= remove_at, "remove").otherwise("generalise").alias("action")
    hit = places.select("d1", "d2", F.explode("found").alias("x")).select("d1", "d2", F.col("x.term").alias("term"), F.col("x.start").alias("start"), F.col("x.end").alias("end"))
    hit = hit.join(told.select("term", action), "term")
    return keep(hit.groupBy("d1", "d2").agg(F.sort_array(F.collect_list(F.struct("start", "end", "action"))).alias("terms")), "pii-spans")


def find(docs: DataFrame, text: str = "text", key: str = "doc_id", **limits) -> DataFrame:
    """One row per document: key, counts of the four kinds, digest of the base spans, all spans.

    Null text is empty (no spans); repeated rows and equal keys each give their own row; further columns do not matter; an empty table gives
    an empty result. Texts of any length are read whole, in time that grows little faster than their length.
    """
    rows = detect(docs, text, key)
    hits = disclosing_spans(docs, rows, text, **limits)
    out = rows.join(hits, ["d1", "d2"], "left")
    counts = [_count_of_kind(kind) for kind in KINDS]
    written = F.transform("base", lambda x: F.concat_ws(":", x["kind"], x["start"], x["end"]))
    added = F.transform(F.coalesce("terms", F.array().cast("array<struct<start:int,end:int,action:string>>")), lambda x: F.concat_ws(":", F.lit("term"), x["start"], x["end"]))
    return out.select(
        F.col("key").alias(key), *counts, F.sha2(F.array_join(written, ","), 256).alias("base_sha256"), F.array_join(F.concat(written, added), ",").alias("spans"), F.size(added).cast("long").alias("n_term")
    )


def _with_terms(docs: DataFrame, hits: DataFrame, lookup_keys: int) -> DataFrame:
    """``docs`` with the term spans of their texts (``__terms``); only texts that have some are moved, as long as their list is small."""
    df = docs.withColumns(dict(zip(("__d1", "__d2"), _digest(F.col("__text")), strict=True)))
    none = F.lit(None).cast(hits.schema["terms"].dataType)
    named = hits.select(F.col("d1").alias("__d1"), F.col("d2").alias("__d2"), F.col("terms").alias("__terms"))
    known = lookup(hits.select(F.col("d1").alias("h1"), F.col("d2").alias("h2")), lookup_keys)
    if known is None:
        return df.join(named, ["__d1", "__d2"], "left")
    if not known.places:
        return df.withColumn("__terms", none)
    listed = known.holds(F.col("__d1"), F.col("__d2"))
    return df.where(listed).join(named, ["__d1", "__d2"], "left").unionByName(df.where(~listed).withColumn("__terms", none))


def redact(docs: DataFrame, text: str = "text", key: str = "doc_id", lookup_keys: int = LOOKUP_KEYS, **limits) -> DataFrame:
    """``docs`` with personal data and disclosing terms replaced in the text; columns and rows stay the same.

    The terms join by the digest of the text, so equal texts are treated alike and equal keys do no harm. Null texts stay null; texts without a span
    stay as they are. Where spans overlap, the first one (of these the longest) is replaced and the rest of the others goes with it.
    """
    hits = disclosing_spans(docs, detect(docs, text, key), text, **limits)
    df = _with_terms(docs.withColumn("__text", text_of(docs, text)), hits, lookup_keys)
    df = with_base_spans(df, "__text", "__base")
    base = F.transform("__base", lambda x: F.struct(x["start"].alias("start"), (-x["end"]).alias("end"), F.concat(F.lit("["), F.upper(x["kind"]), F.lit("]")).alias("by")))
    added = F.transform("__terms", lambda x: F.struct(x["start"].alias("start"), (-x["end"]).alias("end"), F.when(x["action"] == "remove", "").otherwise("[TERM]").alias("by")))
    df = df.withColumn("__spans", F.array_sort(F.concat(base, F.coalesce(added, F.array().cast("array<struct<start:int,end:int,by:string>>")))))
    df = _blocks(df, {"__spans": "__cut"})
    # the furthest end in the blocks before each one
    reach = F.struct(F.lit(0).alias("at"), F.array().cast("array<int>").alias("found"))
    furthest = lambda b: F.array_max(F.transform(b, lambda x: -x["end"]))
    further = lambda acc, b: F.struct(F.greatest(acc["at"], furthest(b)).alias("at"), F.concat(acc["found"], F.array(acc["at"])).alias("found"))
    df = df.withColumn("__reach", F.aggregate("__cut", reach, further)["found"])
    df = df.withColumn("__firsts", F.concat(F.array(F.lit(0)), F.transform(F.slice("__cut", 2, F.size("__cut")), lambda b: F.get(b, F.lit(0))["start"]), F.array(F.length("__text"))))
    # each block with its part of the text, up to the first span of the next block
    part = lambda i: F.substring(F.col("__text"), F.get("__firsts", i) + 1, F.get("__firsts", i + 1) - F.get("__firsts", i))
    piece = lambda b, i: F.struct(b.alias("spans"), F.get("__firsts", i).alias("first"), F.get("__reach", i).alias("reach"), part(i).alias("text"))
    df = df.withColumn("__pieces", F.transform("__cut", piece))

    def cleaned(p: Column) -> Column:
        start = F.struct(F.greatest(p["first"], p["reach"]).alias("at"), F.lit("").alias("done"))

        def step(acc: Column, x: Column) -> Column:
            between = F.substring(p["text"], acc["at"] - p["first"] + 1, F.greatest(x["start"] - acc["at"], F.lit(0)))
            done = F.when(x["start"] >= acc["at"], F.concat(acc["done"], between, x["by"])).otherwise(acc["done"])
            return F.struct(F.greatest(acc["at"], -x["end"]).alias("at"), done.alias("done"))

        rest = lambda acc: F.concat(acc["done"], F.substring(p["text"], acc["at"] - p["first"] + 1, F.length(p["text"])))
        return F.aggregate(p["spans"], start, step, rest)

    changed = F.array_join(F.transform("__pieces", cleaned), "")
    return df.withColumn(text, F.when(F.size("__spans") > 0, changed).otherwise(F.col(text))).select(*docs.columns)
