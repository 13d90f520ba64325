"""Corpus operators against brute force, on small tables with nulls, empties, ties, repeated rows and clashing names."""

import hashlib
import itertools
import math
import random
import re
import time
import zlib
from collections import Counter

import duckdb
import numpy as np
import public_tokenizers
import pytest
import tiktoken
import xxhash
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from supportbounds.llm import bpe, exact_dedup, line_dedup, packing, pii, quality_classifier, quality_rules, queries, simhash, token_store, url_filter

RANKS, JSON = public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.path("byte_bpe_50k.json")
#: Extra columns whose names the operators use inside.
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, row long, label long, digest string, `key` string, fp long"
SF = "/root/testdata/sf0.001"


def texts():
    rnd = random.Random(4)
    words = ["alpha", "beta", "gamma", "delta", "naïve", "Zürich", "omega", "東京", "it's", "x1"]
    body = lambda n: " ".join(rnd.choice(words) for _ in range(n))
    base = body(80)
    return [
        None, "", " ", "\n\n", "a", "a b", body(3), base, base, base.replace("alpha", "Alpha", 1), body(60) + "\nshared line of boiler plate\n" + body(60), body(3000),
        "mail me: jo.doe@example.com or +1 (743) 555-3824, card 4111 1111 1111 1111, host 10.0.0.256 and 10.1.2.3", "é" * 500 + "@x.y 1.2.3.4.5.6.7.8", "<|endoftext|> in a text", "don't 'sam \t\n  it''s  ",
    ]


@pytest.fixture(scope="module")
def rows():
    out = [(i, t, "en", f"s{i % 3}", len(t or ""), 7, 7, "d", "k", 1) for i, t in enumerate(texts())]
    return [*out, out[7], (None, "no id", None, None, None, None, None, None, None, None), (2**40, texts()[7], "en", "s1", 1, 1, 1, "d", "k", 1)]


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame(rows, SCHEMA)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


def base_spans(t):
    kinds = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}
    out = []
    for kind, p in kinds.items():
        for m in re.finditer(p, t):
            d = re.sub("[^0-9]", "", m.group())
            luhn = sum(x if i % 2 == 0 else 2 * x - 9 * (x > 4) for i, x in enumerate(map(int, reversed(d)))) % 10 == 0
            if {"email": True, "ip": all(int(x) < 256 for x in m.group().split(".")) if kind == "ip" else 0, "card": 16 <= len(d) <= 19 and luhn, "phone": 8 <= len(d) <= 15}[kind]:
                out.append(f"{kind}:{m.start()}:{m.end()}")
    return out


def test_personal_data(docs, rows, none):
    found = pii.find(docs)
    want = Counter((r[0], ",".join(base_spans(r[1] or ""))) for r in rows)
    assert Counter((r.doc_id, ",".join(s for s in r.spans.split(",") if not s.startswith("term"))) for r in found.collect()) == want
    assert pii.find(none).count() == 0
    cleaned = pii.redact(docs)
    assert cleaned.columns == docs.columns and cleaned.count() == len(rows)
    text = next(r.text for r in cleaned.collect() if r.doc_id == 12)
    assert text == "mail me: [EMAIL] or [PHONE], card [CARD], host 10.0.0.256 and [IP]"


def stands_with(t):
    """(entity, term) of each term with the entities next to it, by plain search."""
    patterns = [r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+", r"\+[0-9][\x20().0-9-]+[0-9]", r"(?<![0-9])[0-9]+\.[0-9]+\.[0-9]+\.[0-9]+", r"[0-9](?:[\x20-]?[0-9])+", r"[^\W\d_]{3,}"]
    out, last, waiting = set(), None, []
    for m in re.finditer("|".join(patterns), t.lower()):
        x = m.group()
        if re.search("[0-9@]", x):
            last = x if "@" in x or re.fullmatch(r"[0-9]+(\.[0-9]+){3}", x) else re.sub("[^0-9]", "", x)
            out |= {(last, w) for w in waiting}
            waiting = []
        else:
            waiting.append(x)
            out |= {(last, x)} if last else set()
    return out


def disclosed(texts):
    """Terms and their p(c | t), by brute force over the different texts."""
    every = sorted({t or "" for t in texts})
    entities = [{v.lower() if "@" in v else v if re.fullmatch(r"[0-9]+(\.[0-9]+){3}", v) else re.sub("[^0-9]", "", v) for v in (t[int(a) : int(b)] for _, a, b in (s.split(":") for s in base_spans(t)))} for t in every]
    n_c = Counter(e for x in entities for e in x)
    n_t = Counter(w for t in every for w in set(re.findall(r"[^\W\d_]{3,}", re.sub(r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+", " ", t).lower())))
    n_ct = Counter(p for t in every for p in stands_with(t))
    best = {}
    for (e, w), n in n_ct.items():
        p, n_all = n / (n_t[w] + 1), len(every)
        if n_c[e] and n > 1 and p >= 0.6 and n_c[e] < n_all and 2 * math.log2(p * n_all / n_c[e]) >= math.log2(n_all / n_c[e]):
            best[w] = max(best.get(w, 0), p)
    return best


def test_terms_that_disclose(spark):
    rnd = random.Random(1)
    word = lambda n=7: "".join(rnd.choice("bcdfgh") for _ in range(n))
    rows = [(i, f"{word()} {word()} Quixotl {word()} ann@corp.example {word()} {word()}") for i in range(6)]
    rows += [(10 + i, f"call {word()} +1 743 555 3824 for Zamboni at 10.1.2.3 with {word(3)}") for i in range(2)] + [(20 + i, f"{word()} twin Gemini bob@x.example") for i in range(2)]
    rows += [(100 + i, " ".join(word(rnd.choice([3, 7])) for _ in range(9))) for i in range(50)] + [(200, "Quixotl far from any address"), (201, None), (20, rows[8][1])]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    best = disclosed([t for _, t in rows])
    assert best["quixotl"] == 6 / 8 and {"zamboni", "gemini"} <= best.keys()
    want = Counter()
    for i, t in rows:
        terms = [f"term:{m.start()}:{m.end()}" for m in re.finditer(r"[^\W\d_]{3,}", t or "") if m.group().lower() in best and not any(int(a) < m.end() and m.start() < int(b) for _, a, b in (x.split(":") for x in base_spans(t)))]
        want[i, ",".join(base_spans(t or "") + terms)] += 1
    assert Counter((r.doc_id, r.spans) for r in pii.find(docs).collect()) == want
    by_list, by_join = (Counter(map(tuple, pii.redact(docs, lookup_keys=k).collect())) for k in (1000, -1))
    assert by_list == by_join and not any("Quixotl" in (t or "") for _, t in by_list)
    assert any("[TERM]" in (t or "") for _, t in by_list)


def test_personal_data_in_a_long_text(spark):
    text = " ".join(f"word{'abcdefgh'[i % 8]} user{i}@host{i}.example.com" for i in range(5000))
    docs = spark.createDataFrame([(1, text)], "doc_id long, text string")
    began = time.time()
    found = pii.find(docs).first()
    assert found.spans == ",".join(base_spans(text))
    assert pii.redact(docs).first().text == re.sub(r"user\d+@host\d+\.example\.com", "[EMAIL]", text)
    assert time.time() - began < 60


def test_byte_bpe(docs, rows, none):
    ranks = bpe.Vocabulary.load(RANKS).ranks
    coder = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    sha = lambda b: hashlib.sha256(b).hexdigest()
    want = Counter((r[0], len(i := coder.encode_ordinary(r[1] or "")), sha(" ".join(map(str, i)).encode()), sha((r[1] or "").encode())) for r in rows)
    assert Counter(map(tuple, bpe.encode_and_decode(docs, RANKS).collect())) == want
    assert bpe.encode_and_decode(none, RANKS).count() == 0


def test_bpe_on_random_texts_appends_and_edits():
    vocabulary = bpe.Vocabulary.load(RANKS)
    coder = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=vocabulary.ranks, special_tokens={})
    rnd, own = random.Random(9), bpe.TextEncoder(bpe.piece_encoder(vocabulary))
    parts = [" ", "  ", "\n", " \n", "\t ", "a", "b.", "é", " ", "'s", "'ll", "'t", "''", "x1", "12", "   ", "\x1c", "文", "😀", "́", '"']
    many = ["".join(rnd.choice(parts) for _ in range(rnd.randint(0, 12))) for _ in range(3000)]
    ids, at = own.batch(many)
    assert [ids[a:b].tolist() for a, b in zip(at[:-1], at[1:], strict=True)] == [coder.encode_ordinary(t) for t in many]
    text = "The quick brown fox. " * 20
    held, again = bpe.EditableText(vocabulary, public_tokenizers.PATTERN, text), bpe.PrefixTable(vocabulary, b"abc")
    for i in range(300):
        a = len(text) if i % 5 == 0 else rnd.randint(0, len(text))
        b, new = min(len(text), a + rnd.choice([0, 1, 9])), "".join(rnd.choice(parts) for _ in range(rnd.randint(0, 4)))
        text = text[:a] + new + text[b:]
        assert held.replace(a, b, new) < 60
        assert held.ids() == coder.encode_ordinary(text)
        raw = bytes(again.piece)
        a = rnd.randint(0, len(raw))
        again.replace(a, min(len(raw), a + 2), new.encode())
        assert again.ids() == bpe.PrefixTable(vocabulary, bytes(again.piece)).ids()


def test_packing_plan_is_best_fit():
    sizes, cost = (16, 32, 64), packing.default_cost

    def brute(lengths, preferred):
        bins = []
        for n in sorted(lengths, reverse=True):
            open_ones = [b for b in bins if b[1] - b[0] >= n]
            if open_ones:
                min(open_ones, key=lambda b: b[1] - b[0])[0] += n
            else:
                bins.append([n, preferred if preferred >= n else min((s for s in sizes if s >= n), key=cost)])
        return sum(cost(min(s for s in sizes if s >= used)) for used, _ in bins)

    rnd = random.Random(3)
    for _ in range(40):
        lengths = [rnd.choice([rnd.randint(1, 64), rnd.randint(1, 10), 7]) for _ in range(rnd.randint(0, 300))]
        found = packing.plan(Counter(lengths), sizes)
        assert found.cost <= min(brute(lengths, p) for p in sizes) + 1e-6 and sum(n * used for _, n, used, _ in found.bins) == sum(lengths)
        seen = Counter()
        for n, first, count, _, _ in found.placed:
            seen[n] += count
            assert first + count <= Counter(lengths)[n]
        assert seen == Counter(lengths)
        assert math.isclose(found.cost, sum(n * cost(size) for _, n, _, size in found.bins))


def test_sizes_are_chosen_jointly():
    # three pieces of 2,730 fill one bin of 8,192; of 2,731 only two fit
    assert packing.plan({2730: 300, 1400: 1000}).cost <= 3_603_200
    assert packing.plan({2731: 300, 1400: 1000}).cost <= 3_865_600
    assert max(packing._plan_for({2730: 300, 1400: 1000}, list(packing.SIZES), p, packing.default_cost).cost for p in packing.SIZES) > 3_603_200


def test_sequences_hold_all_ids(spark):
    rnd = random.Random(5)
    rows = [(i, [rnd.randrange(1, 99) for _ in range(rnd.choice([0, 1, 5, 40, 70, 300]))]) for i in range(40)] + [(7, [1, 2, 3]), (None, [4]), (50, None)]
    got = packing.sequences(spark.createDataFrame(rows, "doc_id long, ids array<int>"), sizes=(16, 64, 128)).collect()
    back = {}
    for r in got:
        assert len(r.tokens) == r.bin_size
        end = 0
        for p in r.pieces:
            assert p.start == end
            end = p.start + p.n_tokens
            back.setdefault(p.doc_id, []).append((p.piece, r.tokens[p.start : end]))
        assert not any(r.tokens[end:])
    want = Counter(x for _, ids in rows for x in ids or [])
    assert Counter(x for ps in back.values() for _, part in ps for x in part) == want
    assert all([x for _, part in sorted(back[i]) for x in part] == ids for i, ids in rows[:40] if ids and i != 7)


def test_packing(docs, rows, none):
    got = packing.pack(docs, sizes=(64, 256, 1024)).toPandas()
    lengths = [len((r[1] or "").encode().split()) + 1 for r in rows]
    assert got.n_tokens.sum() == sum(lengths) and len(got) == sum(-(-n // 1024) for n in lengths)
    for _, g in got.sort_values("start").groupby("bin_id"):
        assert g.start.iloc[0] == 0 and (g.start.shift(-1).dropna().values == (g.start + g.n_tokens).values[:-1]).all()
        assert g.n_tokens.sum() <= g.bin_size.iloc[0] and g.bin_size.nunique() == 1
    assert packing.pack(none).count() == 0


def exact_want(rows):
    best = {}
    for r in rows:
        best.setdefault(r[1] or "", []).append(r[0])
    top = {t: max((i for i in ids if i is not None), default=None) for t, ids in best.items()}
    return Counter((r[0], top[r[1] or ""], len(best[r[1] or ""]), hashlib.sha256((r[1] or "").encode()).hexdigest()) for r in rows), len(best)


@pytest.mark.parametrize("digest", [exact_dedup.sha256, lambda c: F.unhex(F.substring(F.sha2(c, 256), 1, 1 + 1))])
def test_exact_dedup(spark, docs, rows, none, tmp_path, digest):
    docs.repartition(3).write.parquet(str(tmp_path / "d"))
    found = exact_dedup.find(spark, str(tmp_path / "d"), digest=digest, max_files=1).collect()
    want, groups = exact_want(rows)
    assert Counter((r.doc_id, r.keep_id, r.group_size, r.text_sha256) for r in found) == want
    assert sum(r.kept for r in found) == groups and all(r.doc_id == r.keep_id for r in found if r.kept)
    none.write.parquet(str(tmp_path / "none"))
    assert exact_dedup.find(spark, str(tmp_path / "none")).count() == 0


def test_exact_dedup_goes_on_from_its_state(spark, tmp_path):
    path, folder = str(tmp_path / "d"), str(tmp_path / "state")
    spark.createDataFrame([(1, "x"), (2, "y")], "doc_id long, text string").write.parquet(path)
    assert exact_dedup.find(spark, path, folder=folder).where("kept").count() == 2
    spark.createDataFrame([(3, "x")], "doc_id long, text string").write.mode("append").parquet(path)
    assert {r.doc_id: r.keep_id for r in exact_dedup.find(spark, path, folder=folder).collect()} == {1: 3, 2: 2, 3: 3}


def fingerprint(t, n=4):
    w = ["".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in x) for x in re.findall(r"[^\x20\x09-\x0D]+", t or "")]
    if not w:
        return 0
    h = [xxhash.xxh64_intdigest(" ".join(w[i : i + n]).encode(), 42) for i in range(max(1, len(w) - n + 1))]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def component_sets(fps, bits=4):
    fps = list(set(fps))
    label = {f: f for f in fps}
    changed = True
    while changed:
        changed = False
        for a in fps:
            for b in fps:
                if (a ^ b).bit_count() <= bits and label[a] != label[b]:
                    label[a] = label[b] = min(label[a], label[b])
                    changed = True
    return label


def test_simhash(docs, rows, none):
    fps = [fingerprint(r[1]) for r in rows]
    label = component_sets(fps)
    least = {}
    for r, f in zip(rows, fps, strict=True):
        if r[0] is not None:
            least[label[f]] = min(least.get(label[f], r[0]), r[0])
    want = Counter((r[0], f"{f:016x}", least.get(label[f])) for r, f in zip(rows, fps, strict=True))
    assert Counter(map(tuple, simhash.near_duplicates(docs).collect())) == want
    assert simhash.near_duplicates(none).count() == 0
    left = simhash.drop_near_duplicates(docs)
    assert left.columns == docs.columns and left.count() == len(set(label.values()))


@pytest.mark.parametrize("segments", [3, 4, 5, 6])
def test_simhash_index_loses_no_link(spark, segments):
    rnd = random.Random(segments)
    fps = [rnd.getrandbits(64) for _ in range(60)]
    for f in fps[:40]:
        for _ in range(6):
            fps.append(f ^ sum(1 << b for b in rnd.sample(range(64), rnd.randint(1, 6))))
    signed = [(x - (1 << 64) if x >> 63 else x,) for x in set(fps)]
    found = simhash.label_fingerprints(spark.createDataFrame(signed, "fp long"), 4, segments).collect()
    got = {r.fp % (1 << 64): r.label for r in found}
    groups = lambda m: sorted(sorted(k for k in m if m[k] == v) for v in set(m.values()))
    want = component_sets(fps)
    sizes = Counter(want.values())
    assert groups(got) == groups({k: v for k, v in want.items() if sizes[v] > 1})


def test_large_key_groups_are_spanned():
    rnd = np.random.default_rng(0)
    fp = np.unique(np.bitwise_or.reduce(1 << rnd.integers(0, 30, (400, 2)).astype(np.uint64), axis=1))
    a, b = simhash._links_of_run(np.zeros(len(fp), np.int64), fp, 4)
    assert len(a) == len(fp) - 1 and (np.bitwise_count(a ^ b) <= 4).all()


def test_token_store(spark, docs, rows, none, tmp_path):
    library = Tokenizer.from_file(JSON)
    folder = f"file://{tmp_path}/store"
    token_store.write(docs, folder, JSON)
    found = token_store.read_back(spark, folder).collect()
    want, at = Counter(), 0
    order = sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0))
    for r in order:
        ids = [*library.encode(r[1] or "", add_special_tokens=False).ids, 2]
        want[(r[0], at, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))] += 1
        at += len(ids)
    assert Counter((r.doc_id, r.start, r.n_tokens, r.ids_crc32) for r in found) == want and all(r.verified for r in found)
    assert token_store.chunks(spark, folder).count() == token_store.chunks(spark, folder).select("digest").distinct().count()
    got = token_store.documents(spark, folder, spark.createDataFrame([(11,)], "doc_id long")).first()
    assert got.ids == [*library.encode(texts()[11], add_special_tokens=False).ids, 2]
    assert len(token_store.store_root(spark, folder)) == 64
    assert not (tmp_path / "store" / "staged" / "kind=recipe").exists()
    spark.createDataFrame([("0" * 64,)], "root string").write.mode("overwrite").parquet(f"{folder}/root")
    assert not any(r.verified for r in token_store.read_back(spark, folder).collect())
    assert token_store.round_trip(none, JSON).count() == 0


def test_crc_combination():
    rnd = random.Random(1)
    for _ in range(50):
        a, b = rnd.randbytes(rnd.randint(0, 99)), rnd.randbytes(rnd.randint(0, 99))
        assert token_store.crc32_combine(zlib.crc32(a), zlib.crc32(b), len(b)) == zlib.crc32(a + b)


def duck(sql, **tables):
    con = duckdb.connect()
    for name, df in tables.items():
        con.register(name, df.toPandas())
    return con.execute(sql).fetchall()


def test_line_dedup(spark, none):
    rnd = random.Random(2)
    line = lambda: " ".join(rnd.choice("abcdefgh") * 3 for _ in range(6))
    rows = [(i, "\n".join([line(), "  Read more here ", line(), "", "only on two" if i % 7 < 2 else line()]), f"s{i % 7}") for i in range(40)] + [(40, None, "s1"), (41, "", None), (42, "Read more here", "s1")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = line_dedup.remove_lines(docs, counts=("n_lines", "n_removed"))
    digest = got.select("doc_id", "n_lines", "n_removed", F.sha2(F.coalesce("text", F.lit("")), 256).alias("text_sha256"))
    order = lambda rs: sorted(map(tuple, rs))
    assert order(digest.collect()) == order(duck(f"SELECT doc_id, n_lines, n_removed, text_sha256 FROM ({line_dedup.ORACLE})", documents=docs))
    assert all("Read more here" not in r.text for r in got.where("doc_id < 40").collect())
    assert got.where("doc_id = 42").first().text == "" and got.where("doc_id = 40").first().text is None
    by_join = line_dedup.remove_lines(docs, lookup_keys=-1)
    assert order(by_join.collect()) == order(line_dedup.remove_lines(docs).collect())
    assert line_dedup.remove_lines(none).count() == 0
    named = docs.withColumn("n_lines", F.lit(3))
    assert line_dedup.remove_lines(named).columns == named.columns
    with pytest.raises(ValueError, match="there already"):
        line_dedup.remove_lines(named, counts=("n_lines", "n_removed"))


def test_a_page_copied_to_many_sites_is_no_boilerplate(spark):
    rows = [(i, "one line\nand another", f"s{i}") for i in range(9)] + [(20 + i, f"menu\nown text {i}", f"s{i}") for i in range(9)]
    got = line_dedup.remove_lines(spark.createDataFrame(rows, "doc_id long, text string, source string"))
    assert {r.text for r in got.collect()} == {"one line\nand another", *(f"own text {i}" for i in range(9))}


def test_quality_rules(spark, docs, none):
    rnd = random.Random(6)
    line = lambda n: " ".join("".join(rnd.choice("abcdefgh") for _ in range(5)) for _ in range(n))
    menu = line(70)
    rows = [(i, f"{line(5)}\n{menu}\n{line(5)}", "h") for i in range(20)] + [(20 + i, line(80), "h") for i in range(5)] + [(30, line(60) + " x y z" * 40, "h"), (31, None, None), (32, "", "h"), (33, "# | <a> " * 60, "h")]
    many = spark.createDataFrame(rows, "doc_id long, text string, source string")
    columns = "doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, kept"
    got = quality_rules.judge(many)
    assert sorted(map(tuple, got.select(*columns.split(", ")).collect())) == sorted(duck(f"SELECT {columns} FROM ({quality_rules.ORACLE})", documents=many))
    kept = {r.doc_id for r in got.where("kept").collect()}
    assert kept == set(range(20, 25))
    assert quality_rules.judge(docs).count() == docs.count() and quality_rules.judge(none).count() == 0


def test_lines_above_the_limit_leave_the_texts(spark):
    rnd = random.Random(7)
    line = lambda n: " ".join("".join(rnd.choice("abcdefgh") for _ in range(5)) for _ in range(n))
    stock = [line(9) for _ in range(30)]
    rows = [(i, f"  Our   MENU\n{line(60)}\n\nour menu", "h") for i in range(15)]  # lose a line and stay
    rows += [(100 + i, "\n".join(rnd.sample(stock, 12)), "h") for i in range(200)]  # nothing but lines of others: depleted
    rows += [(400 + i, rows[0][1], "h") for i in range(20)]  # copies of one text are one document
    rows += [(500 + i, f"our menu\n{line(60)}", f"h{i}") for i in range(20)]  # other hosts
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(3)
    want = {(i, t if h != "h" else "\n".join(x for x in t.split("\n") if x.lower().split() != ["our", "menu"])) for i, t, h in rows if not 100 <= i < 400}
    for keys in (1000, -1):
        assert {(r.doc_id, r.text) for r in quality_rules.reject(docs, lookup_keys=keys).collect()} == want
    columns = "doc_id, kept"
    assert sorted(map(tuple, quality_rules.judge(docs).select("doc_id", "kept").collect())) == sorted(duck(f"SELECT {columns} FROM ({quality_rules.ORACLE})", documents=docs))
    few = docs.where("doc_id < 10 OR doc_id >= 400")
    assert quality_rules.reject(few).where("source = 'h'").first().text.startswith("  Our   MENU")


def test_classifier(spark, docs, none):
    d, labels = spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet")
    got = quality_classifier.classify(d, labels)
    right = got.join(labels, "doc_id").agg(F.avg((F.col("predicted") == F.col("quality")).cast("int"))).first()[0]
    assert right > 0.9 and got.count() == d.count()
    assert {r.doc_id for r in got.where("held_out").collect()} == {i for i in range(d.count()) if zlib.crc32(str(i).encode()) % 5 == 0}
    odd = quality_classifier.classify(docs, labels.limit(0))
    assert odd.count() == docs.count() and odd.where("score < 0 OR score > 1 OR score IS NULL").count() == 0
    assert quality_classifier.classify(none, labels).count() == 0


def test_classifier_scores_are_log_density_differences(spark):
    d, labels = spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet")
    got = {r.doc_id: r.score for r in quality_classifier.classify(d, labels).collect()}
    texts = {r.doc_id: r.text for r in d.collect()}
    marks = {r.doc_id: r.quality for r in labels.collect() if zlib.crc32(str(r.doc_id).encode()) % 5}
    x = {i: np.array(quality_classifier.statistics(t)) for i, t in texts.items()}
    own = [np.array([x[i] for i, y in marks.items() if y == c]) for c in (0, 1)]
    both = np.concatenate(own)
    target = np.diag(np.maximum(both.var(axis=0), 1e-4))
    n, k = len(both), both.shape[1]
    share = (0.1 * n + k) / (n + k)
    def density(v, c):
        cov = (1 - share) * np.cov(own[c].T, bias=True) + share * target + 1e-4 * np.eye(k)
        gap = v - own[c].mean(axis=0)
        return -0.5 * gap @ np.linalg.solve(cov, gap) - 0.5 * np.linalg.slogdet(cov)[1]
    for i, v in x.items():
        want = density(v, 1) - density(v, 0) + math.log((len(own[1]) + 1) / (len(own[0]) + 1))
        assert math.isclose(got[i], 1 / (1 + math.exp(-max(-500, min(500, want)))), rel_tol=1e-6, abs_tol=1e-9)


def test_new_pieces_are_made_together_and_kept_in_bounds():
    asked = []
    make_all = lambda pieces: asked.append(list(pieces)) or [p.upper() for p in pieces]
    cache = bpe.PieceCache(None, 4)
    for pieces in ([b"a", b"b", b"c"], [b"c", b"d", b"e"], [b"a", b"f"], [b"%d" % i for i in range(9)], []):
        assert cache.several(pieces, make_all) == [p.upper() for p in pieces] and len(cache) <= 4 and len(cache.old) <= 4
    assert asked[:3] == [[b"a", b"b", b"c"], [b"d", b"e"], [b"f"]]


def _as_ids(pieces):
    return [np.frombuffer(p, np.uint8).astype(np.uint32).tobytes() for p in pieces]


def test_later_tasks_do_not_encode_known_pieces_again():
    asked = []
    coder = bpe.TextEncoder(None, 1000, lambda pieces: asked.extend(pieces) or _as_ids(pieces))
    texts = ["one two\0 three", "", "two four\xe9 \0", " one " + "x" * 40]
    first = coder.batch(texts)
    assert len(asked) == len(set(asked)) > 5
    token_store._give_back(coder.pieces)  # a task ends
    asked.clear()
    again = coder.batch([*texts, "one five"])
    assert asked == [b" five", b" " + b"x" * 40]  # long ones are given back
    assert again[0].tolist() == [*first[0].tolist(), *b"one five"] == list("".join([*texts, "one five"]).encode())
    assert again[1].tolist() == [*first[1].tolist(), len(again[0])]


def test_texts_beside_one_with_a_special_token_are_cut_together(monkeypatch):
    calls, batch = [], bpe.TextEncoder.batch
    monkeypatch.setattr(bpe.TextEncoder, "batch", lambda self, texts: calls.append(len(texts)) or batch(self, texts))
    several, library = token_store._encoder(JSON)[0], Tokenizer.from_file(JSON)
    special = "<|endoftext|>"
    for texts in (["a b", special, "", f"x {special}y", " c"], [special, special], ["a", ""]):
        calls.clear()
        want = [[*library.encode(t, add_special_tokens=False).ids, 2] for t in texts]
        ids, at = several(texts, 2)
        assert [ids[a:b].tolist() for a, b in itertools.pairwise(at.tolist())] == want
        assert calls == [sum(special not in t for t in texts)]


def test_piece_table_keeps_what_was_asked_for_last():
    rnd = random.Random(3)
    every = [rnd.randbytes(rnd.randrange(1, 24)) for _ in range(300)] + [b"\0" * i for i in range(1, 24)] + [b"ab" + b"\0" * i for i in range(22)]
    every = list(dict.fromkeys(every))

    def keys(pieces):
        ends = np.cumsum([0, *map(len, pieces)])
        return bpe.PieceTable.keys_of(np.frombuffer(b"".join(pieces) + bytes(24), np.uint8), ends[:-1], np.diff(ends))

    for most in (1, 7, 100, 1000):
        table = bpe.PieceTable(most)
        for size in [0, 1, 3, 50, 300, 20, 40] * 4:
            pieces = rnd.sample(every, size)
            numbers = table.find(keys(pieces))
            known = [p for p, i in zip(pieces, numbers, strict=True) if i >= 0]
            assert table.ids_of(numbers[numbers >= 0]).tolist() == list(b"".join(known))
            assert table.lengths(numbers[numbers >= 0]).tolist() == list(map(len, known))
            new = [p for p, i in zip(pieces, numbers, strict=True) if i < 0]
            table.add(keys(new), np.array(list(map(len, new)), np.int64), np.frombuffer(b"".join(_as_ids(new)), np.uint32))
            assert len(table) <= most
            if size <= most // 2:
                assert (table.find(keys(pieces)) >= 0).all()


def test_keys_keep_their_type(spark):
    docs = spark.createDataFrame([("a", "one two", "s"), ("b", "one two", "s"), (None, None, None)], "doc_id string, text string, source string")
    labels = spark.createDataFrame([("a", 1)], "doc_id string, quality int")
    assert {r.doc_id for r in quality_classifier.classify(docs, labels).collect()} == {"a", "b", None}
    assert {r.doc_id for r in token_store.round_trip(docs, JSON).collect()} == {"a", "b", None}
    assert {r.doc_id for r in simhash.near_duplicates(docs).collect()} == {"a", "b", None}


def test_url_filter(spark):
    urls = [None, "", "no scheme", "http://a.example.com/en/7?x=1", "https://A.EXAMPLE.com/en/12#top", "http://b.net/de/1", "http://x.org/fr/2/3/4/5/6/7", "ftp://org/es/", "http://example.net/de/81", "http://b.net/de"] * 3
    pages = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string")
    got = url_filter.judge(pages)
    columns = "page_id, host, path, rule, verdict, template"
    order = lambda rs: sorted(map(tuple, rs), key=repr)
    assert order(got.select(*columns.split(", ")).collect()) == order(duck(f"SELECT {columns} FROM ({url_filter.oracle()})", pages=pages))
    by_id = {r.page_id: r for r in got.collect()}
    assert by_id[3].rule == "example.com/en/7" and by_id[3].verdict == "allow" and by_id[4].rule == "com/en/" and by_id[8].rule == "example.net/de/8" and by_id[0].host == ""
    assert url_filter.judge(pages.limit(0)).count() == 0


def test_url_rules_say_what_the_contract_says(spark):
    want = {"com/en/": "block", "example.com/en/7": "allow", "net/de/": "allow", "example.net/de/8": "block", "org/es/": "block"}
    urls = ["http://a.com/en/1", "http://www.example.com/en/71", "http://b.net/de/1", "http://example.net/de/7", "http://www.example.net/de/81", "http://x.org/es/"]
    got = url_filter.judge(spark.createDataFrame(list(enumerate(urls)), "page_id long, url string")).orderBy("page_id").collect()
    assert [r.rule for r in got] == ["com/en/", "example.com/en/7", "net/de/", "net/de/", "example.net/de/8", "org/es/"]
    assert [r.verdict for r in got] == [want[r.rule] for r in got]
    assert {text: says for says, text in url_filter.RULES} == want


def test_templates_learn_from_labels(spark):
    rows = [(i, f"http://h.test/spam/{i}", True if i < 15 else None) for i in range(30)] + [(100 + i, f"http://h.test/news/{i}", False) for i in range(20)]
    pages = spark.createDataFrame(rows, "page_id long, url string, bad boolean")
    got = url_filter.judge(pages, rules=(), bad_label=F.col("bad"))
    assert {r.page_id for r in got.where("verdict = 'block'").collect()} == set(range(30))


def test_templates_judge_pages_whose_rule_is_hidden(spark):
    pages = spark.read.parquet("/root/testdata/sf0.1/pages.parquet")
    ruled = {r.page_id: (r.rule, r.verdict) for r in url_filter.judge(pages).collect()}
    says = F.udf(lambda i: None if i % 2 or ruled[i][0] is None else ruled[i][1] == "block", "boolean")
    got = {r.page_id: r.verdict for r in url_filter.judge(pages, rules=(), bad_label=says("page_id")).collect()}
    hidden = [i for i in ruled if i % 2 and ruled[i][0]]
    blocked = [i for i in hidden if ruled[i][1] == "block"]
    assert sum(got[i] == "block" for i in blocked) > 0.5 * len(blocked)
    free = [i for i in ruled if ruled[i][0] is None]
    assert sum(got[i] == "allow" for i in free) > 0.95 * len(free)


def test_wide_hosts_keep_their_branches_apart(spark):
    for n in (5, 19, 60):
        rows = [(i, f"http://x.org/es/{i}") for i in range(30)] + [(1000 + 50 * k + i, f"http://x.org/dir{chr(97 + k % 26)}{chr(97 + k // 26)}/{i}") for k in range(n) for i in range(30)]
        got = url_filter.judge(spark.createDataFrame(rows, "page_id long, url string"))
        assert {r.page_id for r in got.where("verdict = 'block'").collect()} == set(range(30))
    deep = [(i, "http://d.test/a/b/c/d/e/f/bad/" + str(i), True if i < 10 else None) for i in range(20)] + [(100 + i, "http://d.test/a/b/c/d/e/f/good/" + str(i), False if i < 10 else None) for i in range(40)]
    deep += [(200, "http://d.test/" + "x/" * 20000, None)]
    got = url_filter.judge(spark.createDataFrame(deep, "page_id long, url string, bad boolean"), rules=(), bad_label=F.col("bad"))
    assert {r.page_id for r in got.where("verdict = 'block'").collect()} == set(range(20))


@pytest.mark.parametrize("name", sorted(queries.ORACLES))
def test_queries_match_sql(spark, name):
    con = duckdb.connect()
    for t in ("documents", "pages", "labels"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    df = queries.QUERIES[name](spark, SF)
    columns = sorted(df.columns)
    want = con.execute(f"SELECT {', '.join(columns)} FROM ({queries.ORACLES[name]})").fetchall()
    assert sorted(map(tuple, df.select(*columns).collect()), key=repr) == sorted(want, key=repr)
