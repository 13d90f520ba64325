"""SimHash near-duplicates through deletion variants.

Two 64-bit fingerprints are linked when they differ in at most ``bits`` positions. Instead of
``bits + 1`` exact segments the fingerprint is cut into fewer, longer ones, so that some segment (or
some combination of segments) differs in at most ONE position. For each such segment every position
is wildcarded in turn; the segment with that position blanked is an index key, and two segments at
distance 0 or 1 share such a key. Rows with equal keys meet through one shuffle on the key, are compared in
full (64 bits), and only a spanning set of verified links leaves a key group. Components come from
alternating star contraction, which needs a logarithmic number of rounds.

Equal fingerprints are collapsed before the index is built, so a group of copies, however large,
is one row there. Groups of a key are never expanded into all their pairs: a group is swept from
one pivot at a time, and members already connected are not compared with each other again.
"""

from __future__ import annotations

import itertools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from supportbounds.llm.common import keep, text_of

SEED = 42
_LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))


def fingerprint(text: str, words: int = 4) -> int:
    """The 64-bit fingerprint of one text (as an unsigned integer)."""
    tokens = text.encode("utf-8", "surrogatepass").translate(_LOWER).split()
    if not tokens:
        return 0
    joined = b" ".join(tokens)
    if len(tokens) <= words:
        hashes = [xxhash.xxh64_intdigest(joined, SEED)]
    else:
        ends = np.cumsum([len(t) + 1 for t in tokens])
        starts = [0, *ends[: len(tokens) - words].tolist()]
        stops = (ends[words - 1 :] - 1).tolist()
        digest = xxhash.xxh64_intdigest
        hashes = [digest(joined[a:b], SEED) for a, b in zip(starts, stops, strict=True)]
    return _majority(np.array(hashes, dtype=np.uint64))


def _majority(hashes: np.ndarray) -> int:
    """Bit i is set if it is set in more than half of the hashes; long inputs go through in blocks."""
    ones = np.zeros(64, dtype=np.int64)
    for k in range(0, len(hashes), 1 << 16):
        block = hashes[k : k + (1 << 16)].astype(">u8").view(np.uint8).reshape(-1, 8)
        ones += np.unpackbits(block, axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(ones * 2 > len(hashes)).tobytes(), "big")


def with_fingerprints(docs: DataFrame, text: str = "text", words: int = 4, out: str = "fingerprint_bits") -> DataFrame:
    """All columns of ``docs`` and the fingerprint as a signed 64-bit integer. Null texts count as empty."""

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            values = [fingerprint(t, words) if t else 0 for t in batch.column(batch.schema.get_field_index(text)).to_pylist()]
            signed = pa.array(np.array(values, dtype=np.uint64).view(np.int64))
            yield pa.RecordBatch.from_arrays([*batch.columns, signed], names=[*batch.schema.names, out])

    return docs.mapInArrow(add, StructType([*docs.schema.fields, StructField(out, LongType())]))


def segment_masks(bits: int, segments: int) -> list[int]:
    """Masks over the 64 positions, one for each combination of segments that the pigeonhole argument needs.

    With ``segments`` pieces and at most ``bits`` differences, the ``c`` least-differing pieces have
    at most one difference together, where c is the largest number for which that holds.
    """
    bounds = [round(i * 64 / segments) for i in range(segments + 1)]
    pieces = [((1 << (b - a)) - 1) << a for a, b in itertools.pairwise(bounds)]

    def worst(c: int) -> int:
        # the c smallest of `segments` counts that add up to `bits`, as large as they can be
        return max(sum(sorted(p)[:c]) for p in _partitions(bits, segments))

    fitting = [c for c in range(1, segments + 1) if worst(c) <= 1]
    if not fitting:
        raise ValueError(f"{segments} segments are too few for {bits} differing bits")
    return [sum(chosen) for chosen in itertools.combinations(pieces, max(fitting))]


def _partitions(total: int, parts: int, most: int | None = None) -> Iterator[list[int]]:
    most = total if most is None else most
    if parts == 0:
        if total == 0:
            yield []
        return
    for first in range(min(total, most), -1, -1):
        for rest in _partitions(total - first, parts - 1, first):
            yield [first, *rest]


def segments_for(n: int, bits: int, most: float = 4.0) -> int:
    """The fewest segments with which ``n`` evenly spread fingerprints give keys of ``most`` rows on average, or the most of those that come near."""

    def rows(segments: int) -> float:
        masks = segment_masks(bits, segments)
        return n / 2 ** (min(m.bit_count() for m in masks) - 1)

    possible = []
    for segments in range(1, 9):
        try:
            possible.append((segments, rows(segments)))
        except ValueError:
            continue
    fitting = [s for s, r in possible if r <= most]
    return fitting[0] if fitting else min(possible, key=lambda p: p[1])[0]


def index_keys(fingerprints: DataFrame, bits: int, segments: int) -> DataFrame:
    """One row (key, fp) for each segment combination and wildcard position of each fingerprint.

    The key is a 64-bit mix of the combination's number, the wildcard and the remaining bits. A clash
    of two keys only makes two rows meet that the 64-bit check then parts again.
    """

    def expand(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        masks = segment_masks(bits, segments)
        variants = [(m, 1 << p) for m in masks for p in range(64) if m >> p & 1]
        for batch in batches:
            whole = batch.column(0).to_numpy(zero_copy_only=False).view(np.uint64)
            for at in range(0, len(whole), 4096):
                fp = whole[at : at + 4096]
                for k in range(0, len(variants), 32):
                    keys = [(fp & np.uint64(m & ~w)) ^ np.uint64(_tag(k + i)) for i, (m, w) in enumerate(variants[k : k + 32])]
                    mixed = _mix(np.concatenate(keys))
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(mixed.view(np.int64)), pa.array(np.tile(fp, len(keys)).view(np.int64))], names=["key", "fp"]
                    )

    return fingerprints.select("fp").mapInArrow(expand, "key long, fp long")


def _tag(number: int) -> int:
    return (number + 1) * 0x9E3779B97F4A7C15 & (1 << 64) - 1


def _mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit integers that spreads close values."""
    with np.errstate(over="ignore"):
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _links_of_group(fp: np.ndarray, bits: int) -> list[tuple[int, int]]:
    """Links that span the components of one key group, without going through all its pairs.

    A pivot is compared with every member outside its own component so far; a dense group is
    joined by its first pivot and then only the members left outside are compared on.
    """
    label = np.arange(len(fp))
    order = list(range(len(fp)))
    found: list[tuple[int, int]] = []
    for pivot in order:
        other = label != label[pivot]
        if not other.any():
            break
        near = np.flatnonzero(other & (np.bitwise_count(fp ^ fp[pivot]) <= bits))
        for j in near:
            if label[j] != label[pivot]:
                found.append((pivot, int(j)))
                label[label == label[j]] = label[pivot]
    return found


def links(fingerprints: DataFrame, bits: int = 4, segments: int = 3) -> DataFrame:
    """Verified links (a, b), a < b, that connect distinct fingerprints of one component."""

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held_key, held_fp = np.empty(0, np.int64), np.empty(0, np.uint64)
        for batch in itertools.chain(batches, [None]):
            if batch is None:
                key, fp, whole = held_key, held_fp, len(held_key)
            else:
                key = np.concatenate([held_key, batch.column(0).to_numpy(zero_copy_only=False)])
                fp = np.concatenate([held_fp, batch.column(1).to_numpy(zero_copy_only=False).view(np.uint64)])
                whole = int(np.searchsorted(key, key[-1])) if len(key) else 0  # the last key may go on in the next batch
            held_key, held_fp = key[whole:], fp[whole:]
            a, b = _links_of_run(key[:whole], fp[:whole], bits)
            if len(a):
                low, high = np.minimum(a.view(np.int64), b.view(np.int64)), np.maximum(a.view(np.int64), b.view(np.int64))
                pairs = np.unique(np.stack([low, high], axis=1), axis=0)
                yield pa.RecordBatch.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], names=["a", "b"])

    keys = index_keys(fingerprints, bits, segments)
    sorted_keys = keys.repartition("key").sortWithinPartitions("key")
    return sorted_keys.mapInArrow(compare, "a long, b long").distinct()


def _links_of_run(key: np.ndarray, fp: np.ndarray, bits: int, small: int = 16) -> tuple[np.ndarray, np.ndarray]:
    """Links within all groups of equal keys of a sorted run; short groups all at once, long ones by pivots."""
    if not len(key):
        return fp, fp
    starts = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
    sizes = np.diff(np.r_[starts, len(key)])
    in_small = np.repeat(sizes <= small, sizes)
    a, b = [], []
    for lag in range(1, min(small, int(sizes.max(initial=1)))):
        i = np.flatnonzero((key[lag:] == key[:-lag]) & in_small[lag:])
        i = i[np.bitwise_count(fp[i] ^ fp[i + lag]) <= bits]
        a.append(fp[i])
        b.append(fp[i + lag])
    for start, size in zip(starts[sizes > small], sizes[sizes > small], strict=True):
        group = fp[start : start + size]
        pairs = np.array(_links_of_group(group, bits), dtype=np.int64).reshape(-1, 2)
        a.append(group[pairs[:, 0]])
        b.append(group[pairs[:, 1]])
    return (np.concatenate(a), np.concatenate(b)) if a else (fp[:0], fp[:0])


def components(edges: DataFrame, name: str = "components") -> DataFrame:
    """(node, label) for every node of the undirected ``edges`` (a, b); the label is the least node reachable.

    Large-star and small-star steps in turn: each points neighbours at a local minimum, until every node
    points at the root of its star. Rounds are written to the shared folder, so a lost executor costs one round.
    """
    edges = keep(edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).where("a <> b").distinct(), name)
    before = _state(edges)
    while True:
        both = edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        large = both.join(low, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        low = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(low, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").unionByName(low.select("a", F.col("m").alias("b")))
        edges = keep(small.distinct(), name)
        after = _state(edges)
        if after == before:
            break
        before = after
    roots = edges.select(F.col("b").alias("node")).distinct().select("node", F.col("node").alias("label"))
    return edges.select(F.col("a").alias("node"), F.col("b").alias("label")).unionByName(roots)


def _state(edges: DataFrame) -> tuple:
    """A few numbers that two equal edge sets share (three scalars, whatever the size)."""
    mixed = F.xxhash64("a", "b").cast("decimal(38,0)")
    row = edges.agg(F.count("*"), F.sum(mixed), F.sum(F.col("b").cast("decimal(38,0)"))).first()
    return tuple(row)


def near_duplicates(docs: DataFrame, text: str = "text", key: str = "doc_id", words: int = 4, bits: int = 4, segments: int | None = None) -> DataFrame:
    """All columns of ``docs`` but the text, with fingerprint, component label and the least key of the component.

    Nulls: a null text is empty; an empty text has fingerprint zero and is linked like any other; a null key
    is ignored when the least key of a component is taken (null only if all its keys are). Repeated rows
    have equal fingerprints and so share a component; texts of any length are hashed whole; further columns do not matter. An
    empty table gives an empty result. ``segments``: by default as many as the number of different fingerprints asks for, so that keys stay selective;
    the result does not depend on it.
    """
    prepared = docs.select(F.col(key).alias("__key"), text_of(docs, text).alias("__text"))
    rows = keep(with_fingerprints(prepared, "__text", words, "fp").select("__key", "fp"), "fingerprints")
    labelled = label_fingerprints(rows.select("fp"), bits, segments)
    # one row for each fingerprint first; both sides of each join are written tables, so that Spark can split a hot key
    own = rows.groupBy("fp").agg(F.min("__key").alias("least")).join(labelled, "fp", "left").withColumn("label", F.coalesce("label", "fp"))
    own = keep(own, "labelled-fingerprints")
    least = keep(own.groupBy("label").agg(F.min("least").alias("component_id")), "components-least")
    named = keep(own.select("fp", "label").join(least, "label").select("fp", "component_id"), "fingerprint-components")
    return rows.join(named, "fp").select(F.col("__key").alias(key), F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def label_fingerprints(fps: DataFrame, bits: int = 4, segments: int | None = None) -> DataFrame:
    """(fp, label) for every fingerprint that is linked to another one."""
    distinct = keep(fps.distinct(), "distinct-fingerprints")
    segments = segments or segments_for(distinct.count(), bits)
    return keep(components(links(distinct, bits, segments)).withColumnRenamed("node", "fp"), "labels")


def drop_near_duplicates(docs: DataFrame, text: str = "text", key: str = "doc_id", words: int = 4, bits: int = 4, segments: int | None = None) -> DataFrame:
    """``docs`` with one row left of each component: the one with the least key (rows of one key: any one of them; null keys last)."""
    named = docs.withColumn("__sb_text", text_of(docs, text))
    rows = with_fingerprints(named, "__sb_text", words, "__sb_fp").drop("__sb_text").withColumn("__sb_row", F.monotonically_increasing_id())
    rows = keep(rows, "documents-with-fingerprints")
    light = rows.select(F.col("__sb_fp").alias("fp"), F.struct(F.col(key).isNull().alias("none"), F.col(key).alias("key"), F.col("__sb_row").alias("row")).alias("place"))
    labelled = label_fingerprints(light.select("fp"), bits, segments)
    # one survivor for each fingerprint first, so that the join meets no hot key
    best = light.groupBy("fp").agg(F.min("place").alias("place")).join(labelled, "fp", "left").withColumn("label", F.coalesce("label", "fp"))
    stays = keep(best.groupBy("label").agg(F.min("place").alias("place")).select(F.col("place.row").alias("__sb_row")), "survivors")
    # most rows stay, so the survivors' list grows with the input: a join by sorted keys at every size
    return rows.join(stays.hint("merge"), "__sb_row", "left_semi").select(*docs.columns)
