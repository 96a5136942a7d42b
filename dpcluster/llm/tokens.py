"""Exact encoding of whole texts with a tokenizer file, many texts at a time.

The UTF-8 bytes of a batch are cut, with array operations, at places where no pre-token can cross.
Each distinct chunk is encoded once, and its ids are copied to where it occurs.  Chunks are found by
a hash and compared byte by byte, so a clash of hashes can't give wrong ids.  Known chunks outlive a
task, as Python workers are reused; when there are too many, those that were met again stay.

Unusual white space, on which regular-expression libraries differ, is kept together with the words
around it, and the tokenizer sees these in one piece.
"""

from __future__ import annotations

import ctypes
import itertools
import os
import re
from collections.abc import Iterable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

#: Known chunks of a worker; each takes some 40 bytes, and its ids.
CACHE_CHUNKS = 1_500_000
#: Bytes that are cut and looked up at once, and the longest chunk that is kept.
AT_ONCE, LONGEST = 1 << 20, 200
#: So many words are encoded as one text.
JOINED = 256

#: Chunks for byte-level tokenizers: a word with the space before it, or a run of white space.
_LIBC = ctypes.CDLL(None)
_SPACED = re.compile(r" ?[^ \t\n\r]+|[ \t\n\r]+(?![^ \t\n\r])|[ \t\n\r]+")
_ODD = re.compile("[" + "".join(map(chr, (11, 12, 28, 29, 30, 31, 133, 160, 5760, *range(8192, 8203), 8232, 8233, 8239, 8287, 12288))) + "]")
_SAFE_CUT = re.compile(rb"[!-~](?= [!-~])")

_IS_SPACE = np.zeros(256, bool)
_IS_SPACE[[9, 10, 13, 32]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
#: Kinds of printable ASCII: 0 space, 1 letters, 2 digits, 3 other marks.
_KINDS = np.full(256, 3, np.uint8)
_KINDS[32] = 0
_KINDS[[*range(65, 91), *range(97, 123)]] = 1
_KINDS[48:58] = 2
_MAY_BE_ODD = np.zeros(256, bool)
_MAY_BE_ODD[[11, 12, 28, 29, 30, 31, 0xC2, 0xE1, 0xE2, 0xE3]] = True
_BASE, _VALUES = 0xD1342543DE82EF95, np.random.default_rng(11).integers(1, 1 << 63, 256, dtype=np.uint64)
_POWERS: list[np.ndarray] = []


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of an odd number and of its inverse modulo 2^64."""
    if not _POWERS or len(_POWERS[0]) < n:
        _POWERS.clear()
        for base in (_BASE, pow(_BASE, -1, 1 << 64)):
            steps = np.full(1 << max(1, n - 1).bit_length(), base, np.uint64)
            steps[0] = 1
            _POWERS.append(np.multiply.accumulate(steps))
    return _POWERS[0][:n], _POWERS[1][:n]


def _ranges(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Places start, start + 1, ... of every range, one after the other."""
    ends = np.cumsum(lengths)
    return np.arange(ends[-1] if len(ends) else 0) + np.repeat(starts - ends + lengths, lengths)


def _odd_bytes(data: np.ndarray) -> np.ndarray:
    """Places of bytes of unusual white space."""
    at = np.flatnonzero(_MAY_BE_ODD[data])
    if not len(at):
        return at
    padded = np.concatenate([data, np.zeros(2, np.uint8)])
    a, b, c = padded[at], padded[at + 1], padded[at + 2]
    two = (a == 0xC2) & ((b == 0x85) | (b == 0xA0))
    low = (c >= 0x80) & (c <= 0x8A) | (c == 0xA8) | (c == 0xA9) | (c == 0xAF)
    three = (a == 0xE1) & (b == 0x9A) & (c == 0x80) | (a == 0xE2) & ((b == 0x80) & low | (b == 0x81) & (c == 0x9F)) | (a == 0xE3) & (b == 0x80) & (c == 0x80)
    return np.concatenate([at[(a < 32) | two | three], at[two | three] + 1, at[three] + 2])


@dataclass
class Encoded:
    """Texts as chunks: their first bytes, byte lengths and numbers of ids; chunks before each text; all ids."""

    starts: np.ndarray
    lengths: np.ndarray
    counts: np.ndarray
    chunks_before: np.ndarray
    ids: np.ndarray

    @property
    def ids_before(self) -> np.ndarray:
        return np.concatenate([[0], np.cumsum(self.counts)])[self.chunks_before]


class Codec:
    """Encodes texts into 32-bit ids."""

    def __init__(self, path: str, cache_chunks: int = CACHE_CHUNKS):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        import json

        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = True
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        before, normal = spec.get("pre_tokenizer") or {}, spec.get("normalizer")
        squeezes = any(x.get("pattern") == {"Regex": r"\s+"} and x.get("content") == " " for x in (normal or {}).get("normalizers", []))
        splits = [x for x in before.get("pretokenizers", []) if x["type"] == "Split" and x.get("invert") and x["behavior"] == "Removed"]
        special_only = all(x.get("special") for x in spec.get("added_tokens", []))
        #: kind of chunks: "words" where the tokenizer drops white space, "spaced" for byte-level ones, or "whole"
        self.kind, self.lowers = "whole", False
        if special_only and squeezes and splits:
            self.kind, self.lowers = "words", {"type": "Lowercase"} in normal["normalizers"]
        elif special_only and normal is None and before.get("type") == "ByteLevel" and before.get("use_regex") and not before.get("add_prefix_space"):
            self.kind = "spaced"
        vocabulary = self.tokenizer.get_vocab(with_added_tokens=False)
        size, self.widths, self.closes = max(vocabulary.values(), default=0) + 1, None, None
        if self.kind == "spaced":  # bytes that each id stands for; one character of an entry is one byte
            self.widths = np.zeros(size, np.int64)
            self.widths[list(vocabulary.values())] = list(map(len, vocabulary))
        elif self.kind == "words" and spec["model"].get("end_of_word_suffix"):  # ids that end a pre-token
            self.closes = np.zeros(size, bool)
            self.closes[[i for w, i in vocabulary.items() if w.endswith(spec["model"]["end_of_word_suffix"])]] = True
        self.limit, self.counted = cache_chunks, {}
        self._forget()

    # --- new chunks ----------------------------------------------------------------------------------

    def _plain(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids and their number for each text."""
        got = [e.ids for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]
        counts = np.fromiter(map(len, got), np.int64, len(got))
        return np.fromiter(itertools.chain.from_iterable(got), np.uint32, int(counts.sum())), counts

    def _grouped(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """As _plain, for words that are encoded many in one text."""
        cut, between = (self._by_width, "") if self.widths is not None else (self._by_close, " ")
        groups = [words[i : i + JOINED] for i in range(0, len(words), JOINED)]
        texts, parts = [between.join(g) for g in groups], []
        for group, text, e in zip(groups, texts, self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)):
            ids = np.array(e.ids, np.uint32)
            ends = cut(group, text, ids)
            parts.append((ids, np.diff(ends, prepend=0)) if ends is not None and ends[-1] == len(ids) else self._plain(group))
        return tuple(np.concatenate(x) for x in zip(*parts)) if parts else (np.zeros(0, np.uint32), np.zeros(0, np.int64))

    def _by_width(self, group: list[str], text: str, ids: np.ndarray):
        """Where the ids of each word end, from the bytes that ids stand for; nothing if that can't be told."""
        ends = np.cumsum([len(w) if w.isascii() else len(w.encode()) for w in group])
        if not len(ids) or int(ids.max()) >= len(self.widths):
            return None
        bounds = np.cumsum(self.widths[ids])
        at = np.minimum(np.searchsorted(bounds, ends), len(bounds) - 1)
        return at + 1 if (bounds[at] == ends).all() else None

    def _by_close(self, group: list[str], text: str, ids: np.ndarray):
        """The same from ids that end a pre-token: runs of letters, single digits, runs of other marks."""
        if not len(ids) or int(ids.max()) >= len(self.closes):
            return None
        kind = np.concatenate([_KINDS[np.frombuffer(text.encode(), np.uint8)], [0]])
        begins = kind[:-1] > 0
        begins[1:] &= (kind[1:-1] != kind[:-2]) | (kind[1:-1] == 2)
        wanted = np.cumsum(begins)[np.cumsum([len(w) + 1 for w in group]) - 2]
        ends = np.flatnonzero(self.closes[ids]) + 1
        return ends[wanted - 1] if len(ends) == wanted[-1] else None

    def encode_new(self, chunks: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """The ids of distinct chunks; how many each has, and from where on."""
        if self.widths is not None:
            easy = [len(c) < LONGEST and len(c) > 1 and c[0] == " " and c[1] not in " \t\n\r" for c in chunks]
        elif self.closes is not None:
            easy = [len(c) < LONGEST and c.isascii() and c.isprintable() and "'" not in c for c in chunks]
        else:
            easy = [False] * len(chunks)
        ids, many = self._grouped([c for c, e in zip(chunks, easy) if e])
        more, few = self._plain([c for c, e in zip(chunks, easy) if not e])
        easy, counts, places = np.array(easy, bool), np.zeros(len(chunks), np.int64), np.zeros(len(chunks), np.int64)
        counts[easy], counts[~easy] = many, few
        places[easy], places[~easy] = np.cumsum(many) - many, len(ids) + np.cumsum(few) - few
        return np.concatenate([ids, more]), counts, places

    def count_chunks(self, chunks: Iterable[str]) -> dict[str, int]:
        """Numbers of ids of single chunks, for texts that are edited."""
        wanted = set(chunks)
        new = [c for c in wanted if c not in self.counted]
        if len(self.counted) + len(new) > 200_000:
            self.counted, new = {}, list(wanted)
        self.counted.update(zip(new, self.encode_new(new)[1].tolist()))
        return self.counted

    # --- cutting -------------------------------------------------------------------------------------

    def cuts(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """First bytes and lengths of the chunks of texts that lie at the offsets."""
        n = len(data)
        if self.kind == "whole":
            filled = offsets[1:] > offsets[:-1]
            return offsets[:-1][filled], np.diff(offsets)[filled]
        space = _IS_SPACE[data]
        begins, ends = (np.zeros(n, bool) for _ in range(2))
        begins[offsets[:-1][offsets[:-1] < n]] = True
        ends[offsets[1:][offsets[1:] > 0] - 1] = True
        before = np.empty(n, bool)  # white space before, in the same text
        before[:1], before[1:] = False, space[:-1]
        before &= ~begins
        if self.kind == "words":
            word = ~space
            starts = np.flatnonzero(word & (before | begins))
            after = np.empty(n, bool)
            after[-1:], after[:-1] = True, space[1:]
            return starts, np.flatnonzero(word & (after | ends)) + 1 - starts
        solid_next = np.empty(n, bool)
        solid_next[-1:], solid_next[:-1] = False, ~space[1:]
        solid_next &= ~ends
        plain_before = np.empty(n, bool)  # a plain space before, which belongs to the word
        plain_before[:1], plain_before[1:] = False, data[:-1] == 32
        start = space & (solid_next | ~before) | ~space & before & ~plain_before | begins
        odd = _odd_bytes(data)
        if len(odd):
            either = space.copy()
            either[odd] = True
            # each run of any white space that holds an unusual one, and what follows it, stays with the word before
            run = np.cumsum(either & ~np.concatenate([[False], (either & ~ends)[:-1]]))
            held = np.zeros(int(run[-1]) + 1, bool)
            held[run[odd]] = True
            glued = either & held[run]
            glued[1:] |= glued[:-1] & ~ends[:-1]
            start &= ~glued | begins
        starts = np.flatnonzero(start)
        return starts, np.diff(starts, append=n)

    def chunks(self, text: str) -> list[str]:
        """Pieces of a short text whose ids, joined, are the ids of the text."""
        if not text:
            return []
        if self.kind == "spaced" and not _ODD.search(text):
            return _SPACED.findall(text)
        data = text.encode("utf-8", "surrogatepass")
        starts, lengths = self.cuts(np.frombuffer(data, np.uint8), np.array([0, len(data)]))
        return [data[a : a + n].decode() for a, n in zip(starts.tolist(), lengths.tolist())]

    # --- many texts ----------------------------------------------------------------------------------

    def _forget(self) -> None:
        self.hashes = np.zeros(0, np.uint64)
        #: of each known chunk: places of its ids and bytes, numbers of both, and how often it was met again
        self.known = np.zeros((5, 0), np.int32)
        self.ids, self.bytes, self.n_ids, self.n_bytes = np.zeros(1 << 16, np.uint32), np.zeros(1 << 18, np.uint8), 0, 0

    def _keep(self) -> None:
        """Drops chunks that were not met again, or all if most were."""
        keep = np.flatnonzero(self.known[4] > 0)
        if len(keep) > self.limit // 2:
            keep = keep[:0]
        old, old_ids, old_bytes, hashes = self.known[:, keep], self.ids, self.bytes, self.hashes[keep]
        self._forget()
        self.hashes = hashes
        ids, data = old_ids[_ranges(old[0], old[1])], old_bytes[_ranges(old[2], old[3])]
        self.known = np.stack([np.cumsum(old[1]) - old[1], old[1], np.cumsum(old[3]) - old[3], old[3], np.zeros(len(keep), np.int32)]).astype(np.int32)
        self._append(ids, data)

    def _append(self, ids: np.ndarray, data: np.ndarray) -> None:
        while self.n_ids + len(ids) > len(self.ids):
            self.ids = np.concatenate([self.ids, np.zeros_like(self.ids)])
        while self.n_bytes + len(data) > len(self.bytes):
            self.bytes = np.concatenate([self.bytes, np.zeros_like(self.bytes)])
        self.ids[self.n_ids : self.n_ids + len(ids)], self.bytes[self.n_bytes : self.n_bytes + len(data)] = ids, data
        self.n_ids, self.n_bytes = self.n_ids + len(ids), self.n_bytes + len(data)

    def _look_up(self, data: np.ndarray, starts: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Numbers of ids of each chunk, and all ids."""
        if not len(starts):
            return np.zeros(0, np.int64), np.zeros(0, np.uint32)
        up, down = _powers(len(data))
        if int(lengths.sum()) == len(data):
            values = _VALUES[data]
        else:  # what lies between words does not count
            values = np.where(_IS_SPACE[data], np.uint64(0), _VALUES[data])
        values *= up
        h = np.add.reduceat(values, starts) * down[starts] ^ lengths.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        found, first, which = np.unique(h, return_index=True, return_inverse=True)
        first_start, first_length = starts[first], lengths[first]
        same = bool((first_length[which] == lengths).all())
        own = _ranges(starts, lengths)
        same = same and bool((data[own] == data[_ranges(first_start[which], lengths)]).all())

        at = np.searchsorted(self.hashes, found)
        hit = np.zeros(len(found), bool)
        if len(self.hashes):
            hit = self.hashes[np.minimum(at, len(self.hashes) - 1)] == found
            mine = self.known[:, at[hit]]
            same = same and bool((mine[3] == first_length[hit]).all()) and bool((self.bytes[_ranges(mine[2], mine[3])] == data[_ranges(first_start[hit], first_length[hit])]).all())
        raw = data.tobytes()
        text = lambda a, n: raw[a : a + n].decode("utf-8", "replace")
        if not same:  # two chunks with one hash
            ids, counts = self._plain([text(a, n) for a, n in zip(starts.tolist(), lengths.tolist())])
            return counts, ids

        new = np.flatnonzero(~hit)
        place, count = np.zeros(len(found), np.int64), np.zeros(len(found), np.int64)
        place[hit], count[hit] = self.known[0, at[hit]], self.known[1, at[hit]]
        self.known[4, at[hit]] += 1
        if len(new):
            ids, count[new], place[new] = self.encode_new([text(a, n) for a, n in zip(first_start[new].tolist(), first_length[new].tolist())])
            place[new] += self.n_ids
            kept = new[first_length[new] <= LONGEST]
            rows = np.stack([place[kept], count[kept], self.n_bytes + np.cumsum(first_length[kept]) - first_length[kept], first_length[kept], np.zeros(len(kept), np.int64)]).astype(np.int32)
            self._append(ids, data[_ranges(first_start[kept], first_length[kept])])
            self.hashes, self.known = np.concatenate([self.hashes, found[kept]]), np.concatenate([self.known, rows], axis=1)
            order = np.argsort(self.hashes, kind="stable")
            self.hashes, self.known = self.hashes[order], self.known[:, order]
        counts = count[which]
        out = self.ids[_ranges(place[which], counts)]
        if len(self.hashes) > self.limit or self.n_ids > 8 * self.limit:
            self._keep()
        return counts, out

    def encode_flat(self, data: np.ndarray, offsets: np.ndarray) -> Encoded:
        """Texts that lie side by side, in runs of bounded size; a long text is cut between two words."""
        raw, bounds, at = None, [int(offsets[0])], int(offsets[0])
        end = int(offsets[-1])
        while at < end:  # runs end with a text, or within a long one where one plain word and space meet another
            stop = int(offsets[np.searchsorted(offsets, at + AT_ONCE, side="right") - 1])
            if stop <= at:
                stop = int(offsets[np.searchsorted(offsets, at, side="right")])
                if self.kind != "whole":
                    raw = data.tobytes() if raw is None else raw
                    cut = _SAFE_CUT.search(raw, at + AT_ONCE, stop)
                    stop = cut.end() if cut else stop
            bounds.append(stop)
            at = stop
        parts, data = [], _LOWER[data] if self.lowers else data
        for a, b in zip(bounds, bounds[1:]):
            lo, hi = np.searchsorted(offsets, a, side="right") - 1, np.searchsorted(offsets, b, side="left")
            starts, lengths = self.cuts(data[a:b], np.clip(offsets[lo : hi + 1], a, b) - a)
            counts, ids = self._look_up(data[a:b], starts, lengths)
            parts.append((starts + a, lengths, counts, ids))
        none = (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.uint32))
        starts, lengths, counts, ids = (np.concatenate(x) for x in zip(*parts, none))
        before = np.searchsorted(starts, offsets, side="left")
        return Encoded(starts, lengths, counts, before, ids)

    def encode(self, texts: list[str | None]) -> list[bytes]:
        """Little-endian 32-bit ids of each text."""
        out: list[bytes] = []
        for column in text_slices(pa.array(texts, pa.string())):
            got = self.encode_flat(*flat(column))
            data, ends = memoryview(got.ids.tobytes()), (4 * got.ids_before).tolist()
            out += [bytes(data[a:b]) for a, b in zip(ends, ends[1:])]
        return out


def flat(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a column of texts and the offsets of its rows; null texts are empty."""
    column = column.cast(pa.large_string())
    if column.null_count:
        column = column.fill_null("")
    offsets = np.frombuffer(column.buffers()[1], np.int64, len(column) + 1, 8 * column.offset) if len(column) else np.zeros(1, np.int64)
    data = np.frombuffer(column.buffers()[2], np.uint8) if column.buffers()[2] else np.zeros(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def text_slices(column: pa.Array, size: int = 4 * AT_ONCE) -> Iterable[pa.Array]:
    """A column of texts in runs of bounded length, one row at least."""
    if not len(column):
        return
    lengths = np.diff(flat(column)[1])
    run = (np.cumsum(lengths) - lengths) // size
    starts = [0, *(np.flatnonzero(np.diff(run)) + 1).tolist(), len(column)]
    for a, b in zip(starts, starts[1:]):
        yield column.slice(a, b - a)


def text_rows(batches, size: int = 4 * AT_ONCE):
    """Record batches with a column ``text`` in runs of bounded length: (rows, texts)."""
    for batch in batches:
        at = 0
        for texts in text_slices(batch.column("text"), size):
            yield batch.slice(at, len(texts)), texts
            at += len(texts)


_CODECS: dict[str, Codec] = {}


def codec(path: str) -> Codec:
    if path not in _CODECS:
        _CODECS[path] = Codec(path)
    return _CODECS[path]


def forget() -> None:
    """Frees the caches of this worker; stages that don't tokenize call it, as workers outlive stages."""
    _CODECS.clear()
    _POWERS.clear()
    trim()


def trim() -> None:
    """Hands freed memory back to the system, which the allocators of Arrow and C keep otherwise."""
    pa.default_memory_pool().release_unused()
    if hasattr(_LIBC, "malloc_trim"):
        _LIBC.malloc_trim(0)


def tokenizer_path(name: str) -> str:
    import public_tokenizers

    return str(public_tokenizers.path(name))


def small_batches(batches, rows: int = 256):
    """Record batches in runs of a few rows, so that few texts are Python objects at a time."""
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)
        del batch
        trim()
