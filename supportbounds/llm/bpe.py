"""Byte-level BPE by dynamic programming over prefixes.

For every prefix of a piece there is exactly one token that its encoding can end with. It is found among the
tokens that are suffixes of the prefix (one pass of an Aho-Corasick automaton): the one that may follow the last token
of the prefix before it, where two tokens may stand side by side if no merge across their border
would have come before the merges that made them. The table of last tokens gives the encoding of every
prefix at once, grows by appending, and after an edit needs new entries only until it agrees with the old ones.

Time is linear in the length of a piece, where merging by rank is quadratic for long runs without blanks.
"""

from __future__ import annotations

import base64
import hashlib
import itertools
from array import array
from collections.abc import Callable, Iterable, Iterator
from functools import lru_cache
from itertools import chain

import ahocorasick
import numpy as np
import public_tokenizers
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from supportbounds.llm.common import text_of
from supportbounds.llm.quality_rules import slices

_CACHE = 150_000


class Vocabulary:
    """Ranks of a public rank file, with what the prefix table needs: how each token was made."""

    def __init__(self, ranks: dict[bytes, int]):
        self.ranks = ranks
        self.tokens = {r: b for b, r in ranks.items()}
        self.longest = max(map(len, ranks))
        self.automaton = ahocorasick.Automaton()
        for b, r in ranks.items():
            self.automaton.add_word(b.decode("latin-1"), (len(b), r))
        self.automaton.make_automaton()
        self.made: dict[int, tuple[int, int]] = {}
        self._fits: dict[int, bool] = {}
        for b, r in sorted(ranks.items(), key=lambda x: x[1]):
            if len(b) > 1:
                self.made[r] = self._maker(b, r)
        self._fits.clear()

    @classmethod
    def load(cls, path: str) -> Vocabulary:
        with open(path, "rb") as f:
            return cls({base64.b64decode(b): int(r) for b, r in (line.split() for line in f)})

    def _maker(self, b: bytes, r: int) -> tuple[int, int]:
        """The two tokens whose merge made this one: the split at which both halves can meet."""
        halves = ((self.ranks.get(b[:i]), self.ranks.get(b[i:])) for i in range(1, len(b)))
        for left, right in halves:
            if left is not None and right is not None and left < r and right < r and self._apart(left, right, r):
                return left, right
        raise ValueError(f"token {r} can't be made by merges")

    def fits(self, left: int, right: int) -> bool:
        """Whether ``right`` can follow ``left`` in an encoding."""
        known = self._fits.get(left << 32 | right)
        if known is None:
            if len(self._fits) > 8 * _CACHE:
                self._fits.clear()
            known = self._fits[left << 32 | right] = self._apart(left, right, 1 << 62)
        return known

    def _apart(self, left: int, right: int, before: int) -> bool:
        """Goes back through the merges beside the border, latest first.

        ``before``: only merges of a lower rank could have come earlier than what was undone last. On the
        left side of the border a merge of equal rank comes first (merges go from left to right).
        """
        tokens, ranks, made = self.tokens, self.ranks, self.made
        while True:
            across = ranks.get(tokens[left] + tokens[right])
            if across is not None and across < before:
                return False
            undo_left = left in made and (left > right or right not in made)
            if undo_left:
                before, left = left, made[left][1]
            elif right in made:
                before, right = right + 1, made[right][0]
            else:
                return True


class PrefixTable:
    """The last token of every prefix of a growing piece of bytes."""

    def __init__(self, vocabulary: Vocabulary, piece: bytes = b""):
        self.vocabulary, self.piece = vocabulary, bytearray()
        self.last: list[int] = []  # last[i]: of the prefix of i + 1 bytes
        if piece:
            self.append(piece)

    def append(self, more: bytes) -> None:
        """Adds bytes; what was known before stays valid."""
        done = len(self.piece)
        self.piece += more
        self.last += [-1] * len(more)
        self._fill(done, len(self.piece))

    def _fill(self, start: int, stop: int, settled: Callable[[int], bool] | None = None) -> int:
        """Entries from ``start``; ends early once ``settled(position)``. Returns the first position not filled."""
        reach = max(0, start - self.vocabulary.longest + 1)
        last, fits = self.last, self.vocabulary.fits
        filled = -1
        for end, (length, token) in self.vocabulary.automaton.iter(self.piece[reach:stop].decode("latin-1")):
            i = end + reach
            if i < start or i == filled:
                continue
            if settled and filled >= start and i > filled and settled(filled):
                return filled + 1
            if length > i or fits(last[i - length], token):
                last[i], filled = token, i
        return stop

    def replace(self, start: int, stop: int, new: bytes) -> int:
        """Puts ``new`` in place of piece[start:stop]; returns how many entries were computed anew."""
        tail, old, longest = self.piece[stop:], self.last[stop:], self.vocabulary.longest
        begin_tail = start + len(new)
        self.piece[start:] = new + tail
        self.last[start:] = [-1] * len(new) + [-1] * len(tail)
        run = 0

        def settled(i: int) -> bool:
            # as many equal entries in a row as the longest token has bytes: all that follow are equal too
            nonlocal run
            run = run + 1 if i >= begin_tail and self.last[i] == old[i - begin_tail] else 0
            return run >= longest

        upto = self._fill(start, len(self.piece), settled)
        self.last[upto:] = old[upto - begin_tail :] if upto < len(self.piece) else []
        return upto - start

    def ids(self, length: int | None = None) -> list[int]:
        """The encoding of the first ``length`` bytes (all of them by default)."""
        at, found, tokens = len(self.piece) if length is None else length, [], self.vocabulary.tokens
        while at:
            found.append(self.last[at - 1])
            at -= len(tokens[found[-1]])
        return found[::-1]


class PieceCache(dict):
    """Piece to what is made of it, in two generations: when the young one is full it becomes the old one."""

    def __init__(self, make: Callable, most: int = _CACHE):
        super().__init__()
        self.make, self.most = make, most
        self.old: dict = {}

    def __missing__(self, piece):
        found = self.old.get(piece)
        if found is None:
            found = self.make(piece)
        if len(self) >= self.most:
            self.old = dict(self)
            self.clear()
        self[piece] = found
        return found

    def several(self, pieces: list, make_all: Callable[[list], list]) -> list:
        """What is made of each of these different pieces; the new ones are made together."""
        found = list(map(self.get, pieces))
        missing = [i for i, f in enumerate(found) if f is None]
        for i in missing:
            found[i] = self.old.get(pieces[i])
        new = [i for i in missing if found[i] is None]
        for i, one in zip(new, make_all([pieces[i] for i in new]), strict=True):
            found[i] = one
        if len(self) + len(missing) > self.most:
            self.old = dict(self)
            self.clear()
        self.update((pieces[i], found[i]) for i in missing[-self.most :])
        return found


#: Kinds of characters that the pattern tells apart; _END stands between texts.
_LETTER, _NUMBER, _OTHER, _SPACE, _END = range(5)


@lru_cache(maxsize=1)
def _kinds() -> np.ndarray:
    """The kind of every code point, from the same character properties that the pattern names."""
    table = np.full(0x110000, _OTHER, dtype=np.uint8)
    for start in range(0, 0x110000, 0x1000):
        block = "".join(map(chr, (i for i in range(start, start + 0x1000) if not 0xD800 <= i < 0xE000)))
        for kind, one in ((_LETTER, r"\p{L}"), (_NUMBER, r"\p{N}"), (_SPACE, r"\s")):
            table[[ord(c) for c in regex.findall(one, block)]] = kind
    return table


class Splitter:
    """Cuts many texts at once where the public pattern's matches end.

    The pattern is a fixed list of runs: letters, numbers or other marks, each with one blank before it; white space, of
    which the last character goes with what follows; and seven English endings after an apostrophe. Every border can be told
    from the kinds of a few neighbouring characters, so that borders are found for whole batches in array operations.
    """

    ENDINGS = ("s", "t", "re", "ve", "m", "ll", "d")  # fixed values
    #: The one pattern whose borders these are (a fixed value).
    PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"

    def __init__(self) -> None:
        if public_tokenizers.PATTERN != self.PATTERN:
            raise ValueError("pieces are cut for another pattern than the tokenizers' one")

    def __call__(self, texts: list[str]) -> tuple[pa.Array, np.ndarray]:
        """All pieces (as bytes) in order, and the number of the first piece of each text (and one past the last)."""
        joined = "\0".join(texts)
        cp = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
        kind = _kinds()[cp]
        sizes = np.array([len(t) for t in texts], dtype=np.int64)
        ends = np.cumsum(sizes + 1) - 1  # the place of each separator, and one past the last character
        kind[ends[:-1]] = _END
        n = len(cp)
        if n == 0:
            return pa.array([], pa.binary()), np.zeros(len(texts) + 1, dtype=np.int64)
        space = kind == _SPACE
        border = np.ones(n + 1, dtype=bool)
        inner = border[1:n]
        np.not_equal(kind[1:], kind[:-1], out=inner)
        to_word = space[:-1] & ~space[1:] & (kind[1:] != _END)  # white space before something
        inner &= ~(to_word & (cp[:-1] == 32))
        border[: n - 1] |= to_word
        border[ends[:-1]] = True
        border[ends[:-1] + 1] = True
        for p in np.flatnonzero((cp == 39) & border[:n]).tolist() if (cp == 39).any() else ():
            for ending in self.ENDINGS:
                stop = p + 1 + len(ending)
                if joined.startswith(ending, p + 1):
                    border[p + 1 : stop] = False
                    border[stop] = True
                    break
        data = joined.encode("utf-8", "surrogatepass")
        starts = np.flatnonzero(border)
        if len(data) == n:
            offsets = starts.astype(np.int32)
        else:
            at = np.flatnonzero(np.frombuffer(data, np.int8) >= -64)  # the first byte of each character
            offsets = np.append(at[starts[:-1]], len(data)).astype(np.int32)
        pieces = pa.Array.from_buffers(pa.binary(), len(offsets) - 1, [None, pa.py_buffer(offsets.tobytes()), pa.py_buffer(data)])
        real = np.ones(len(offsets) - 1, dtype=bool)
        separators = np.searchsorted(starts, ends[:-1])
        real[separators] = False
        count = np.concatenate([[0], np.cumsum(real)])
        firsts = np.concatenate([[0], count[separators], [count[-1]]])
        return pieces.filter(pa.array(real)), firsts


def gather(flat: np.ndarray, starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """flat[s : s + n] for all (s, n), in one row."""
    ends = np.cumsum(lengths)
    total = int(ends[-1]) if len(ends) else 0
    kind = np.int32 if max(total, len(flat)) < 1 << 31 else np.int64
    place = np.repeat((starts - ends + lengths).astype(kind), lengths)
    place += np.arange(total, dtype=kind)
    return flat[place]


class PieceTable:
    """Ids of pieces of up to 23 bytes, looked up and added for many at once.

    Bytes and length of such a piece fill three words, which are its key: equal words, equal pieces. Keys and ids stand in
    arrays (some 65 bytes a piece, where a dictionary takes 200), so that a worker can keep them from task to task. When ``most``
    pieces are held, the half that was not asked for longest goes.
    """

    LONGEST = 23
    _FACTORS = tuple(np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9))
    _MASKS = np.array([(1 << 8 * i) - 1 for i in range(9)], dtype=np.uint64)

    def __init__(self, most: int):
        self.most, self.n, self.turn = most, 0, 0
        bits = max(4, (2 * most - 1).bit_length())
        self.shift, self.slots = np.uint64(64 - bits), np.zeros(1 << bits, np.int32)  # number of the piece and one; 0: free
        self.keys, self.used = np.empty((3, most), np.uint64), np.zeros(most, np.int64)
        self.ends, self.ids = np.zeros(most + 1, np.int64), np.empty(8 * most, np.uint32)  # pages that are not written take no memory

    def __len__(self) -> int:
        return self.n

    @classmethod
    def keys_of(cls, data: np.ndarray, starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
        """The three words of each piece; ``data`` must go on for 24 bytes behind every start."""
        words = np.ndarray((len(data) - 7,), "<u8", data, 0, (1,))  # the word at each byte
        keys = np.empty((3, len(starts)), np.uint64)
        for i in range(3):
            np.bitwise_and(words[starts + 8 * i], cls._MASKS[np.clip(lengths - 8 * i, 0, 8)], out=keys[i])
        keys[2] |= lengths.astype(np.uint64) << np.uint64(56)
        return keys

    def _slots(self, keys: np.ndarray) -> np.ndarray:
        a, b, c = self._FACTORS
        mixed = keys[0] * a ^ keys[1] * b ^ keys[2] * c
        mixed ^= mixed >> np.uint64(32)
        return (mixed * a >> self.shift).astype(np.int64)

    def find(self, keys: np.ndarray) -> np.ndarray:
        """The number of each piece, -1 if it is not held."""
        self.turn += 1
        found, left, at = np.full(keys.shape[1], -1, np.int64), np.arange(keys.shape[1]), self._slots(keys)
        while len(left):
            held = self.slots[at].astype(np.int64) - 1
            taken = held >= 0
            left, at, held = left[taken], at[taken], held[taken]
            same = (self.keys[0][held] == keys[0][left]) & (self.keys[1][held] == keys[1][left]) & (self.keys[2][held] == keys[2][left])
            found[left[same]] = held[same]
            left, at = left[~same], at[~same] + 1 & len(self.slots) - 1
        self.used[found[found >= 0]] = self.turn
        return found

    def lengths(self, numbers: np.ndarray) -> np.ndarray:
        return self.ends[numbers + 1] - self.ends[numbers]

    def ids_of(self, numbers: np.ndarray) -> np.ndarray:
        return gather(self.ids, self.ends[numbers], self.lengths(numbers))

    def add(self, keys: np.ndarray, lengths: np.ndarray, ids: np.ndarray) -> None:
        """Different pieces, none of them held; numbers that were found before are void."""
        if self.n + keys.shape[1] > self.most and self.n > self.most // 2:
            self._halve()
        room = self.most - self.n
        if keys.shape[1] > room:
            keys, lengths = keys[:, :room], lengths[:room]
            ids = ids[: int(lengths.sum())]
        self._append(keys, lengths, ids, self.turn)

    def _append(self, keys: np.ndarray, lengths: np.ndarray, ids: np.ndarray, used: int | np.ndarray) -> None:
        first, self.n = self.n, self.n + keys.shape[1]
        self.keys[:, first : self.n], self.used[first : self.n] = keys, used
        before = int(self.ends[first])
        self.ends[first + 1 : self.n + 1] = before + np.cumsum(lengths)
        if before + len(ids) > len(self.ids):
            self.ids = np.concatenate([self.ids[:before], np.empty(before // 2 + len(ids), np.uint32)])
        self.ids[before : before + len(ids)] = ids
        left, at = np.arange(first, self.n), self._slots(keys)
        while len(left):
            free = self.slots[at] == 0
            self.slots[at[free]] = left[free] + 1
            lost = self.slots[at] != left + 1  # to another piece, or to another of these
            left, at = left[lost], at[lost] + 1 & len(self.slots) - 1

    def _halve(self) -> None:
        keep = np.sort(np.argsort(self.used[: self.n], kind="stable")[self.n - self.most // 2 :])
        keys, lengths, ids, used = self.keys[:, keep], self.lengths(keep), self.ids_of(keep), self.used[keep]
        self.slots.fill(0)
        self.n = 0
        self._append(keys, lengths, ids, used)


def _joined(made: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Ids of several pieces in one row, and the number of each one's."""
    return np.frombuffer(b"".join(made), dtype=np.uint32), np.fromiter(map(len, made), dtype=np.int64, count=len(made)) >> 2


class TextEncoder:
    """Ids of many texts from the ids of their pieces; each different piece is looked at once per batch."""

    def __init__(self, encode_piece: Callable[[bytes], Iterable[int]], most: int = _CACHE, encode_all: Callable[[list[bytes]], list[bytes]] | None = None):
        """``encode_all``: the ids (as unsigned 32-bit integers) of each of several pieces, where that is less work than one by one."""
        self.split, self.encode_all = Splitter(), encode_all
        self.pieces = PieceCache(lambda piece: array("I", encode_piece(piece)).tobytes(), min(most, _CACHE))
        self.table = PieceTable(most) if encode_all else None

    def batch(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """All ids in one row, and where each text's begin (and the end)."""
        if not texts:
            return np.zeros(0, np.uint32), np.zeros(1, np.int64)
        pieces, firsts = self.split(texts)
        coded = pieces.dictionary_encode()
        if self.table is not None:
            made, starts, lengths = self._by_table(coded.dictionary)
        else:
            made, lengths = _joined(list(map(self.pieces.__getitem__, coded.dictionary.to_pylist())))
            starts = np.cumsum(lengths) - lengths
        which = coded.indices.to_numpy()
        each = lengths[which]
        ids = gather(made, starts[which], each)
        return ids, np.concatenate([[0], np.cumsum(each)])[firsts]

    def _by_table(self, different: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Ids, and where those of each piece start and how many they are: known ones from the table, then new short ones, then long ones."""
        n, table = len(different), self.table
        if not n:
            return np.zeros(0, np.uint32), np.zeros(0, np.int64), np.zeros(0, np.int64)
        _, offsets, data = different.buffers()
        at = np.frombuffer(offsets, np.int32)[different.offset : different.offset + n + 1].astype(np.int64)
        raw = data.to_pybytes()[: at[-1]] + bytes(24)
        short = np.flatnonzero(np.diff(at) <= table.LONGEST)
        keys = table.keys_of(np.frombuffer(raw, np.uint8), at[short], np.diff(at)[short])
        numbers = table.find(keys)
        known, new = numbers >= 0, np.flatnonzero(numbers < 0)
        fresh, long = short[new], np.flatnonzero(np.diff(at) > table.LONGEST)
        cut = lambda places: [raw[a:b] for a, b in zip(at[places].tolist(), at[places + 1].tolist(), strict=True)]
        parts = [table.ids_of(numbers[known])]
        lengths = np.empty(n, np.int64)
        lengths[short[known]] = table.lengths(numbers[known])
        ids, lengths[fresh] = _joined(self.encode_all(cut(fresh)))
        parts.append(ids)
        table.add(keys[:, new], lengths[fresh], ids)
        ids, lengths[long] = _joined(self.pieces.several(cut(long), self.encode_all))
        parts.append(ids)
        order = np.concatenate([short[known], fresh, long])
        starts = np.empty(n, np.int64)
        starts[order] = np.cumsum(lengths[order]) - lengths[order]
        return np.concatenate(parts), starts, lengths

    def ids(self, text: str) -> list[int]:
        return self.batch([text])[0].tolist()


def piece_encoder(vocabulary: Vocabulary) -> Callable[[bytes], list[int]]:
    """Ids of one match of the pattern; a match that is a token is that token."""

    ranks, suffixes, known, fits = vocabulary.ranks, vocabulary.automaton.iter, vocabulary._fits, vocabulary.fits

    def encode(raw: bytes) -> list[int]:
        whole = ranks.get(raw)
        if whole is not None:
            return [whole]
        # the same table as PrefixTable's, with the start of each last token beside it
        last: list[int] = []
        starts: list[int] = []
        filled = -1
        for end, (length, token) in suffixes(raw.decode("latin-1")):
            if end != filled:
                start = end - length
                if start >= 0:
                    before = last[start]
                    fit = known.get(before << 32 | token)
                    if fit is None:
                        fit = fits(before, token)
                    if not fit:
                        continue
                last.append(token)
                starts.append(start)
                filled = end
        found = []
        at = filled
        while at >= 0:
            found.append(last[at])
            at = starts[at]
        found.reverse()
        return found

    return encode


class EditableText:
    """The encoding of a text that is appended to and edited; only pieces near a change are encoded anew."""

    def __init__(self, vocabulary: Vocabulary, pattern: str, text: str = ""):
        encoder = piece_encoder(vocabulary)
        self.encode, self.match = PieceCache(lambda piece: tuple(encoder(piece.encode("utf-8", "surrogatepass")))), regex.compile(pattern).match
        self.text, self.starts, self.coded = "", [], []
        self.replace(0, 0, text)

    def append(self, more: str) -> int:
        return self.replace(len(self.text), len(self.text), more)

    def replace(self, start: int, stop: int, new: str) -> int:
        """Puts ``new`` in place of text[start:stop]; returns how many pieces were encoded anew."""
        from bisect import bisect_left

        old_starts, old_coded = self.starts, self.coded
        ends = [*old_starts[1:], len(self.text)]
        shift = len(new) - (stop - start)
        self.text = self.text[:start] + new + self.text[stop:]
        # a match looks at most one character beyond its end's neighbour
        keep = bisect_left(ends, start - 1) if old_starts else 0
        at = old_starts[keep] if keep < len(old_starts) else len(self.text) if not self.text[len(self.text) :] and keep and ends[keep - 1] == len(self.text) else (ends[keep - 1] if keep else 0)
        starts, coded, fresh = old_starts[:keep], old_coded[:keep], 0
        while at < len(self.text):
            if at >= start + len(new):
                same = bisect_left(old_starts, at - shift)
                if same < len(old_starts) and old_starts[same] == at - shift and at - shift >= stop:
                    starts += [s + shift for s in old_starts[same:]]
                    coded += old_coded[same:]
                    break
            end = self.match(self.text, at).end()
            starts.append(at)
            coded.append(self.encode[self.text[at:end]])
            at, fresh = end, fresh + 1
        self.starts, self.coded = starts, coded
        return fresh

    def ids(self) -> list[int]:
        return list(chain.from_iterable(self.coded))


@lru_cache(maxsize=2)
def _coder(ranks_path: str) -> tuple[TextEncoder, Strings, Strings]:
    """Loaded once per worker process, with the tables it fills."""
    vocabulary = Vocabulary.load(ranks_path)
    ids = range(max(vocabulary.tokens) + 1)
    return TextEncoder(piece_encoder(vocabulary)), Strings([vocabulary.tokens.get(i, b"") for i in ids]), Strings([b"%d " % i for i in ids])


class Strings:
    """A byte string for each id; those of many ids are joined by one gather."""

    def __init__(self, parts: list[bytes]):
        self.lengths = np.array([len(p) for p in parts], dtype=np.int64)
        self.starts = np.cumsum(self.lengths) - self.lengths
        self.bytes = np.frombuffer(b"".join(parts), dtype=np.uint8)

    def joined(self, ids: np.ndarray) -> bytes:
        step = 1 << 18
        return b"".join(gather(self.bytes, self.starts[ids[k : k + step]], self.lengths[ids[k : k + step]]).tobytes() for k in range(0, len(ids), step))


def encode_and_decode(docs: DataFrame, ranks_path: str, text: str = "text", key: str = "doc_id", with_ids: bool = False) -> DataFrame:
    """key, n_tokens, ids_sha256, decoded_sha256 (and the ids) for each row.

    Null texts are empty (no ids); repeated rows are encoded row by row; texts of any length are encoded whole;
    an empty table gives an empty result. ``ranks_path`` must be readable on every executor.
    """
    key_type = docs.select(F.col(key).alias("key")).schema["key"].dataType

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder, tokens, numbers = _coder(ranks_path)
        for batch in batches:
            for part in slices(batch, "text"):
                ids, at = coder.batch(part.column("text").to_pylist())
                own = [ids[a:b] for a, b in itertools.pairwise(at.tolist())]
                encoded = [hashlib.sha256(numbers.joined(x)[:-1]).hexdigest() for x in own]
                decoded = [hashlib.sha256(tokens.joined(x)).hexdigest() for x in own]
                columns = [part.column("key"), pa.array(np.diff(at)), pa.array(encoded, pa.string()), pa.array(decoded, pa.string())]
                names = ["key", "n_tokens", "ids_sha256", "decoded_sha256"]
                if with_ids:
                    columns.append(pa.array([x.astype(np.int32) for x in own], pa.list_(pa.int32())))
                    names.append("ids")
                yield pa.RecordBatch.from_arrays(columns, names=names)

    schema = f"key {key_type.simpleString()}, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<int>" * with_ids
    return docs.select(F.col(key).alias("key"), text_of(docs, text).alias("text")).mapInArrow(run, schema).withColumnRenamed("key", key)
