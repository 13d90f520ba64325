"""Content-addressed store of token ids.

The ids of a document are cut into chunks where a rolling hash of the last few ids meets a condition, so
equal passages give equal chunks wherever they stand. A store is a folder of three Parquet tables:

* ``chunks``   digest (SHA-256 of the ids as little-endian unsigned 16- or 32-bit integers), width, n ids, the ids compressed;
  each digest once
* ``recipes``  one row per document in ascending doc_id order: start, n_tokens, digests of its chunks and where they end, leaf of the Merkle tree
* ``manifest`` one row per recipe part: its rows, tokens and Merkle root
* ``root``     one row: the root over the roots of all parts

Documents are encoded once; chunks move once, to the task that keeps one of each digest. Reading back checks every
chunk against its digest, every part against its root and the parts against the root of the store. Checksums of documents are
combined from those of their chunks (a checksum moved on by the bytes that follow it; the moved ones add up by exclusive or),
so verification moves digests, not ids.

No stage has more than one Python worker for each core, and what a worker keeps is bounded, since workers are used again.
"""

from __future__ import annotations

import contextlib
import ctypes
import hashlib
import itertools
import json
import os
import sys
import zlib
from array import array
from collections.abc import Callable, Iterator
from functools import lru_cache, reduce

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from supportbounds.llm.bpe import PieceCache, TextEncoder
from supportbounds.llm.common import new_folder, remove_folder, text_of
from supportbounds.llm.quality_rules import slices

WINDOW, MASK_BITS, MAX_CHUNK = 12, 9, 4096  # the window is summed up as 8 + 4
#: What a worker keeps and works on at once: encoded pieces (some 65 bytes each, kept from task to task), digests already sent, bytes of text.
PIECES, SEEN, SLICE = 800_000, 50_000, 4_000_000
_TRIM_THRESHOLD, _MMAP_THRESHOLD = -1, -3  # numbers of the C library
_RANDOM = np.random.default_rng(20_24).integers(0, 1 << 63, size=1 << 16, dtype=np.uint64)


def marks(ids: np.ndarray) -> np.ndarray:
    """Places after which a chunk may end: where the hash of the last WINDOW ids has MASK_BITS zeros on top."""
    # the sum over a window from those over its halves: id i places back is shifted by i
    held = {1: _RANDOM[ids & 0xFFFF]}
    for size in (1, 2, 4):
        held[2 * size] = _joined(held[size], held[size], size)
    rolling = _joined(held[8], held[4], 8)
    return np.flatnonzero((rolling >> np.uint64(64 - MASK_BITS)) == 0) + 1


def _joined(near: np.ndarray, far: np.ndarray, size: int) -> np.ndarray:
    out = near.copy()
    out[size:] += far[:-size] << np.uint64(size)
    return out


def cut_points(n: int, marks: list[int]) -> list[int]:
    """Ends of the chunks of a document of ``n`` ids with the given marks.

    A chunk has WINDOW ids at least (so that its mark depends on its own document alone; a rest may be shorter) and
    MAX_CHUNK ids at most.
    """
    ends, start = [], 0
    for mark in [*marks, n]:
        while mark - start > MAX_CHUNK:
            start += MAX_CHUNK
            ends.append(start)
        if mark > start and (mark - start >= WINDOW or mark == n):
            ends.append(mark)
            start = mark
    return ends


def merkle_root(leaves: list[bytes]) -> bytes:
    level = leaves or [b""]
    level = [hashlib.sha256(b"\0" + x).digest() for x in level]
    while len(level) > 1:
        pairs = itertools.zip_longest(level[::2], level[1::2], fillvalue=b"")
        level = [hashlib.sha256(b"\1" + a + b).digest() for a, b in pairs]
    return level[0]


def crc32_combine(first: int, second: int, second_bytes: int) -> int:
    """The crc32 of two byte strings in a row from their own: ``first`` is moved on by as many zero bytes."""
    return int(moved_on(np.array([first]), np.array([second_bytes]))[0]) ^ second


def _multiply(a: int, b: int) -> int:
    """The product of two polynomials over two elements, modulo that of crc32 (bit-reversed)."""
    out = 0
    for i in range(31, -1, -1):
        if a >> i & 1:
            out ^= b
        b = b >> 1 ^ (0xEDB88320 if b & 1 else 0)
    return out


@lru_cache(maxsize=64)
def _step(k: int) -> np.ndarray:
    """For each value of each of the four bytes of a checksum, what it becomes when 2^k zero bytes follow."""
    factor = reduce(lambda f, _: _multiply(f, f), range(k), 0x80000000 >> 8)
    return np.array([[_multiply(factor, v << (8 * b)) for v in range(256)] for b in range(4)], dtype=np.uint32)


def moved_on(crcs: np.ndarray, zero_bytes: np.ndarray) -> np.ndarray:
    """The part that each checksum has in that of its bytes with so many bytes after them."""
    out, left, k = crcs.astype(np.uint32), zero_bytes.astype(np.int64), 0
    while left.any():
        odd = np.flatnonzero(left & 1)
        if len(odd):
            own, table = out[odd], _step(k)
            out[odd] = table[0][own & 255] ^ table[1][own >> 8 & 255] ^ table[2][own >> 16 & 255] ^ table[3][own >> 24]
        left, k = left >> 1, k + 1
    return out


def _byte_letters() -> dict[int, str]:
    """The printable letter that byte-level tokenizer files write for each byte: printable bytes as they are, the others in order from 256 on."""
    plain = {*range(33, 127), *range(161, 173), *range(174, 256)}
    others = (b for b in range(256) if b not in plain)
    return {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(others)}


@lru_cache(maxsize=2)
def _encoder(path: str) -> tuple[Callable[[list[str], int], tuple[np.ndarray, np.ndarray]], int, PieceCache]:
    """Ids of several texts, the largest id, and the table that it fills; loaded once per worker process.

    A plain byte-level tokenizer is taken apart: texts are cut into pieces for many at once, and the
    library's model encodes each different piece. Any other tokenizer encodes text by text.
    """
    os.environ["TOKENIZERS_PARALLELISM"] = "false"  # the tasks are the parallelism
    library = Tokenizer.from_file(path)
    cut = json.loads(library.pre_tokenizer.__getstate__()) if library.pre_tokenizer else {}
    plain = library.normalizer is None and cut.get("type") == "ByteLevel" and cut.get("use_regex") and not cut.get("add_prefix_space")
    special = [t.content for t in library.get_added_tokens_decoder().values()]
    model, letters = library.model, _byte_letters()
    tokenize = model.tokenize
    if hasattr(model, "_resize_cache"):
        model._resize_cache(0)  # pieces that come again are found before the model is asked
    codes = np.array([ord(letters[b]) for b in range(256)], dtype="<u2")

    def encode_all(pieces: list[bytes]) -> list[bytes]:
        text = codes[np.frombuffer(b"".join(pieces), np.uint8)].tobytes().decode("utf-16-le")  # a letter for each byte
        ids, ends, start = array("I"), [0], 0
        for end in itertools.accumulate(map(len, pieces)):
            ids.extend([t.id for t in tokenize(text[start:end])])
            ends.append(len(ids))
            start = end
        raw = ids.tobytes()
        return [raw[4 * a : 4 * b] for a, b in itertools.pairwise(ends)]

    coder = TextEncoder(lambda piece: np.frombuffer(encode_all([piece])[0], np.uint32).tolist(), PIECES, encode_all)

    def whole(text: str) -> np.ndarray:
        return np.array(library.encode(text, add_special_tokens=False).ids, dtype=np.uint32)

    def several(texts: list[str], end_id: int) -> tuple[np.ndarray, np.ndarray]:
        """All ids in one row, each text's followed by the end id, and where each text's begin (and the end)."""
        odd = [not plain or any(s in t for s in special) for t in texts]  # special tokens are found before texts are cut
        if any(odd):
            ids, at = coder.batch([t for t, o in zip(texts, odd, strict=True) if not o])
            others = iter(np.split(ids, at[1:-1]))
            own = [whole(t) if o else next(others) for t, o in zip(texts, odd, strict=True)]
            ids, at = np.concatenate(own), np.concatenate([[0], np.cumsum([len(x) for x in own])])
        else:
            ids, at = coder.batch(texts)
        out = np.full(len(ids) + len(texts), end_id, dtype=np.uint32)
        out[np.arange(len(ids)) + np.repeat(np.arange(len(texts)), np.diff(at))] = ids
        return out, at + np.arange(len(texts) + 1)

    return several, library.get_vocab_size() - 1, coder.pieces


def _give_back(pieces: PieceCache) -> None:
    """Empties what a worker has gathered of long pieces, so that it is small while it serves other stages; the table of short ones has its bound and stays."""
    pieces.old = {}
    pieces.clear()
    pa.default_memory_pool().release_unused()
    _keep_freed(64 << 20)  # what the C library comes to by itself
    if sys.platform == "linux":
        with contextlib.suppress(OSError, AttributeError):  # another C library: it keeps its pages
            ctypes.CDLL(None).malloc_trim(0)


def _keep_freed(most: int) -> None:
    """Lets the C library hold on to so many freed bytes, so that working arrays don't ask the system for new pages in every batch."""
    if sys.platform == "linux":
        with contextlib.suppress(OSError, AttributeError):
            library = ctypes.CDLL(None)
            library.mallopt(_MMAP_THRESHOLD, most // 2)
            library.mallopt(_TRIM_THRESHOLD, most)


def write(docs: DataFrame, folder: str, tokenizer: str, end_id: int = 2, text: str = "text", key: str = "doc_id") -> None:
    """Writes the store of ``docs``.

    Null texts are empty (a document of the end id alone). Rows with equal keys stay apart, in the order in which
    they were read; null keys come first. An empty table gives a store without rows. Texts of any length are encoded
    whole. Keys keep their type. ``tokenizer`` must be readable on every executor.
    """
    spark = docs.sparkSession
    plain = docs.select(F.col(key).alias("doc_id"), F.monotonically_increasing_id().alias("row"), text_of(docs, text).alias("text"))

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids_of, most, pieces = _encoder(tokenizer)
        _keep_freed(256 << 20)
        try:
            yield from chunked(batches, ids_of, most)
        finally:
            _give_back(pieces)

    def chunked(batches: Iterator[pa.RecordBatch], ids_of: Callable, most: int) -> Iterator[pa.RecordBatch]:
        seen: set[bytes] = set()
        width = 2 if max(most, end_id) < 1 << 16 else 4  # by the vocabulary, so that equal ids have equal digests everywhere
        pack = zstandard.ZstdCompressor(level=1).compress
        for batch in batches:
            for part in slices(batch, "text", SLICE):
                ids, at = ids_of(part.column("text").to_pylist(), end_id)
                raw, found = ids.astype(f"<u{width}").tobytes(), marks(ids)
                ends = np.searchsorted(found, at, side="right").tolist()
                bounds, found = at.tolist(), found.tolist()
                digests, sizes, payloads, recipes, ends_of, names = [], [], [], [], [], []
                for i, row in enumerate(part.column("row").to_pylist()):
                    begin, recipe, span, start = bounds[i], [], [], 0
                    n = bounds[i + 1] - begin
                    for end in cut_points(n, [m - begin for m in found[ends[i] : ends[i + 1]] if m < bounds[i + 1]]):
                        chunk = raw[(begin + start) * width : (begin + end) * width]
                        digest = hashlib.sha256(chunk).digest()
                        recipe.append(digest)
                        span.append(end)
                        if digest not in seen:
                            if len(seen) > SEEN:
                                seen.clear()
                            seen.add(digest)
                            digests.append(digest)
                            sizes.append(end - start)
                            payloads.append(pack(chunk))
                        start = end
                    recipes.append(recipe)
                    ends_of.append(span)
                    names.append(b"%d" % row)  # recipes are only to be spread evenly
                c, d = len(digests), part.num_rows
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array(digests + names, pa.binary()), pa.concat_arrays([pa.nulls(c, part.column("doc_id").type), part.column("doc_id")]), pa.concat_arrays([pa.nulls(c, pa.int64()), part.column("row")]),
                        pa.array(np.concatenate([np.array(sizes, np.int64), np.diff(at)])), pa.array([width] * c + [None] * d, pa.int32()), pa.array(payloads + [None] * d, pa.binary()),
                        pa.array([None] * c + recipes, pa.list_(pa.binary())), pa.array([None] * c + ends_of, pa.list_(pa.int32())),
                    ],
                    names=["digest", "doc_id", "row", "n", "width", "payload", "recipe", "ends"],
                )

    kind = plain.schema["doc_id"].dataType.simpleString()
    schema = f"digest binary, doc_id {kind}, row long, n long, width int, payload binary, recipe array<binary>, ends array<int>"
    first = F.row_number().over(Window.partitionBy("digest").orderBy("digest")) == 1
    kept = plain.mapInArrow(encode, schema).withColumn("first", first).where("first").drop("first")
    kept = kept.withColumn("kind", F.when(F.col("payload").isNull(), "recipe").otherwise("chunk"))
    staged = f"{folder}/staged"
    kept.write.partitionBy("kind").option("compression", "none").parquet(staged)
    # the chunks stay where they are; recipes are put in order, and their first form goes
    held = spark.read.schema(schema + ", kind string").parquet(staged).where("kind = 'recipe'").select("doc_id", "row", "n", "recipe", "ends")
    _write_recipes(held, folder, kind)
    remove_folder(spark, f"{staged}/kind=recipe")


def _write_recipes(recipes: DataFrame, folder: str, kind: str) -> None:
    def number(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, start = TaskContext.get().partitionId(), 0
        for batch in batches:
            n = batch.column("n").to_numpy()
            local = start + np.cumsum(n) - n
            start += int(n.sum())
            leaves = [leaf(d, r) for d, r in zip(batch.column("doc_id").to_pylist(), batch.column("recipe").to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), batch.column("row"), pa.array(np.full(len(n), part, np.int32)), pa.array(local), batch.column("n"), batch.column("recipe"), batch.column("ends"), pa.array(leaves, pa.binary())],
                names=["doc_id", "row", "part", "local_start", "n_tokens", "recipe", "ends", "leaf"],
            )

    schema = f"doc_id {kind}, row long, part int, local_start long, n_tokens long, recipe array<binary>, ends array<int>, leaf binary"
    ordered = recipes.repartitionByRange("doc_id", "row").sortWithinPartitions("doc_id", "row").mapInArrow(number, schema)
    ordered.write.option("compression", "zstd").parquet(f"{folder}/recipes")
    written = recipes.sparkSession.read.schema(schema).parquet(f"{folder}/recipes")
    _manifest(written, "leaf").write.option("compression", "zstd").parquet(f"{folder}/manifest")
    spark = recipes.sparkSession
    spark.createDataFrame([(store_root(spark, folder),)], "root string").coalesce(1).write.parquet(f"{folder}/root")


def leaf(doc_id: object, recipe: list[bytes]) -> bytes:
    return hashlib.sha256(str(doc_id).encode() + b":" + b"".join(recipe)).digest()


def _manifest(recipes: DataFrame, *stored: str) -> DataFrame:
    """part, documents, n_tokens, root, first: one row for each recipe part, with the ids that stand before it.

    Leaves are made from ids and digests anew unless the stored column is named.
    """
    columns = ("part", "n_tokens", *stored) if stored else ("part", "n_tokens", "doc_id", "recipe")
    ordered = recipes.select("row", "doc_id", *[c for c in columns if c != "doc_id"]).repartition("part").sortWithinPartitions("part", "doc_id", "row")
    sums = ordered.select(*columns).mapInArrow(_roots_by_part, "part int, documents long, n_tokens long, root binary")
    before = F.coalesce(F.sum("n_tokens").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))  # as many rows as parts
    return sums.withColumn("first", before)


def _roots_by_part(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    current, leaves, tokens = None, [], 0

    def done() -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array([current], pa.int32()), pa.array([len(leaves)], pa.int64()), pa.array([tokens], pa.int64()), pa.array([merkle_root(leaves)], pa.binary())], names=["part", "documents", "n_tokens", "root"])

    for batch in batches:
        if "leaf" in batch.schema.names:
            own = batch.column("leaf").to_pylist()
        else:
            own = [leaf(d, r) for d, r in zip(batch.column("doc_id").to_pylist(), batch.column("recipe").to_pylist(), strict=True)]
        for part, n, one in zip(batch.column("part").to_pylist(), batch.column("n_tokens").to_pylist(), own, strict=True):
            if part != current:
                if current is not None:
                    yield done()
                current, leaves, tokens = part, [], 0
            leaves.append(one)
            tokens += n
    if current is not None:
        yield done()


def chunks(spark: SparkSession, folder: str) -> DataFrame:
    return spark.read.schema("digest binary, n long, width int, payload binary, kind string").parquet(f"{folder}/staged").where("kind = 'chunk'").drop("kind")


def recipes(spark: SparkSession, folder: str) -> DataFrame:
    return spark.read.parquet(f"{folder}/recipes")


def manifest(spark: SparkSession, folder: str) -> DataFrame:
    return spark.read.parquet(f"{folder}/manifest")


def verified_chunks(spark: SparkSession, folder: str) -> DataFrame:
    """digest, n, crc (of the ids as unsigned 32-bit integers), good (the stored ids have this digest and number)."""

    def check(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unpack = zstandard.ZstdDecompressor().decompress
        for batch in batches:
            crc, good = [], []
            for digest, n, width, payload in zip(*(batch.column(c).to_pylist() for c in ("digest", "n", "width", "payload")), strict=True):
                raw = unpack(payload)
                good.append(hashlib.sha256(raw).digest() == digest and len(raw) == n * width)
                crc.append(zlib.crc32(np.frombuffer(raw, dtype=f"<u{width}").astype("<u4").tobytes()))
            yield pa.RecordBatch.from_arrays([batch.column("digest"), batch.column("n"), pa.array(crc, pa.int64()), pa.array(good)], names=["digest", "n", "crc", "good"])

    return chunks(spark, folder).mapInArrow(check, "digest binary, n long, crc long, good boolean")


def read_back(spark: SparkSession, folder: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32, verified: one row per document, from the files alone."""
    held = recipes(spark, folder)
    # as many rows as recipe parts come to the driver
    listed = {r.part: r for r in manifest(spark, folder).collect()}
    again = {r.part: r.root for r in _manifest(held).collect()}
    stored = spark.read.schema("root string").parquet(f"{folder}/root").first()
    whole = stored is not None and stored.root == store_root(spark, folder) and listed.keys() == again.keys()
    parts = [(p, r.first, whole and r.root == again[p]) for p, r in listed.items()]
    sound = spark.createDataFrame(parts, "part int, first long, sound boolean")
    steps = held.select("row", "n_tokens", F.explode(F.arrays_zip("recipe", "ends")).alias("step"))
    steps = steps.select("row", F.col("step.recipe").alias("digest"), (4 * (F.col("n_tokens") - F.col("step.ends"))).alias("after"))
    joined = steps.join(verified_chunks(spark, folder), "digest", "left")
    joined = joined.select("row", "after", F.coalesce("n", F.lit(0)).cast("long").alias("n"), F.coalesce("crc", F.lit(0)).cast("long").alias("crc"), F.coalesce("good", F.lit(False)).alias("good"))

    def move(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            crc = moved_on(batch.column("crc").to_numpy(), batch.column("after").to_numpy())
            yield pa.RecordBatch.from_arrays([batch.column("row"), batch.column("n"), pa.array(crc.astype(np.int64)), batch.column("good")], names=["row", "n", "crc", "good"])

    sums = joined.mapInArrow(move, "row long, n long, crc long, good boolean").groupBy("row")
    sums = sums.agg(F.sum("n").alias("found"), F.bit_xor("crc").alias("ids_crc32"), F.bool_and("good").alias("good"))
    out = held.select("row", "doc_id", "part", "local_start", "n_tokens").join(sums, "row").join(F.broadcast(sound), "part")
    ok = F.col("good") & F.col("sound") & (F.col("found") == F.col("n_tokens"))
    return out.select("doc_id", (F.col("first") + F.col("local_start")).alias("start"), F.col("found").alias("n_tokens"), "ids_crc32", ok.alias("verified"))


def store_root(spark: SparkSession, folder: str) -> str:
    """The root over all parts (as many rows as recipe parts come to the driver)."""
    return merkle_root([bytes(r.root) for r in manifest(spark, folder).orderBy("part").collect()]).hex()


def documents(spark: SparkSession, folder: str, wanted: DataFrame) -> DataFrame:
    """doc_id, ids of the documents whose doc_id is in ``wanted``: only their chunks are moved."""
    steps = recipes(spark, folder).join(wanted.select("doc_id").distinct(), "doc_id", "left_semi").select("row", "doc_id", F.posexplode("recipe").alias("at", "digest"))
    held = steps.join(chunks(spark, folder), "digest").groupBy("row", "doc_id").agg(F.array_sort(F.collect_list(F.struct("at", "width", "payload"))).alias("steps"))

    def join_up(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        unpack = zstandard.ZstdDecompressor().decompress
        for batch in batches:
            ids = [np.concatenate([np.frombuffer(unpack(s["payload"]), dtype=f"<u{s['width']}").astype(np.int64) for s in steps]) for steps in batch.column("steps").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(ids, pa.list_(pa.int64()))], names=["doc_id", "ids"])

    kind = held.schema["doc_id"].dataType.simpleString()
    return held.mapInArrow(join_up, f"doc_id {kind}, ids array<long>")


def round_trip(docs: DataFrame, tokenizer: str, end_id: int = 2, text: str = "text", key: str = "doc_id") -> DataFrame:
    """Writes a store into the shared folder and returns what is read back from it."""
    folder = new_folder(docs.sparkSession, "token-store")
    write(docs, folder, tokenizer, end_id, text, key)
    return read_back(docs.sparkSession, folder)

