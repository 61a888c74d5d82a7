"""Token ids of whole texts by a public byte-level BPE vocabulary and the tokenizers library.

The library breaks a text into pieces (a run of letters, digits or marks with the space before it, an ending behind an
apostrophe, white space) and merges bytes inside each piece alone. Here the breaks of a whole column of texts are
found in array operations on Arrow's buffer. A worker remembers the ids of the pieces seen so far, found by hash and
compared byte by byte; each new piece goes through the library's model once. Which kind a character is, is asked of
the library itself when it first comes up.

A text that holds a special token goes through the library in one piece, as the library finds those before it breaks;
so does one that is no valid UTF-8 (wrong bytes replaced), and every text where the vocabulary breaks otherwise.
"""

from __future__ import annotations

import json
import os
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

from .scan import AS_IS, U64, WINDOW, slices, span_hashes, text_buffer

#: Longer pieces are not remembered; and so many pieces are, before the memory starts anew.
LONGEST_KEPT, KEPT = 64, 1_500_000
#: Pieces in one call of the library.
GROUP = 64
#: Kinds of characters.
LETTER, DIGIT, MARK, WHITE, BLANK, UNKNOWN = range(6)
#: What a piece of the first three kinds looks like when the character stands between two such.
BESIDE = "a1!"
APOSTROPHE = ord("'")
#: Endings that are pieces of their own behind an apostrophe: of one letter and of two (fixed values).
ENDINGS = ("s", "t", "m", "d"), ("re", "ve", "ll")
#: Bytes before which a text may be cut if a blank stands before them: printable ASCII.
PRINTABLE = np.zeros(256, bool)
PRINTABLE[33:127] = True


def byte_letters() -> dict[int, str]:
    """The letter that a byte-level vocabulary writes for each byte: a printable one of Latin-1 is its own, the others take the letters from U+0100 on."""
    own = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    letter = {b: chr(b) for b in own}
    return letter | {b: chr(0x100 + k) for k, b in enumerate(b for b in range(0x100) if b not in letter)}


class PieceTable:
    """Pieces by their hashes, with their bytes and their ids, in arrays that grow."""

    def __init__(self) -> None:
        self.n, self.bytes_held, self.ids_held = 0, 0, 0
        self.hash, self.start, self.size = np.zeros(1 << 15, U64), np.zeros(1 << 15, np.int64), np.zeros(1 << 15, np.int64)
        self.first, self.count = np.zeros(1 << 15, np.int64), np.zeros(1 << 15, np.int64)
        self.bytes, self.ids = np.zeros(1 << 18, np.uint8), np.zeros(1 << 17, np.uint32)
        self._clear(1 << 17)

    def _clear(self, slots: int) -> None:
        self.keys, self.number = np.zeros(slots, U64), np.full(slots, -1, np.int32)

    def find(self, h: np.ndarray) -> np.ndarray:
        """Number of the piece of each hash, -1 where there is none."""
        last = len(self.keys) - 1
        at = (h & U64(last)).astype(np.int64)
        out = self.number[at]
        left = np.flatnonzero((self.keys[at] != h) & (out >= 0))
        at = at[left]
        while len(left):
            at = (at + 1) & last
            out[left] = self.number[at]
            more = (self.number[at] >= 0) & (self.keys[at] != h[left])
            left, at = left[more], at[more]
        return out

    def _place(self, h: np.ndarray, numbers: np.ndarray) -> None:
        last = len(self.keys) - 1
        at, left = (h & U64(last)).astype(np.int64), np.arange(len(h))
        while len(left):
            free = self.number[at] < 0
            self.number[at[free]], self.keys[at[free]] = numbers[left[free]], h[left[free]]  # of two that want a slot, the last has it
            lost = self.number[at] != numbers[left]
            left, at = left[lost], (at[lost] + 1) & last

    def add(self, h: np.ndarray, pieces: list[bytes], ids: np.ndarray, counts: np.ndarray) -> None:
        """New pieces, each once, with their ids one after another."""
        n, more = self.n, len(h)
        for name in ("hash", "start", "size", "first", "count"):
            held = getattr(self, name)
            if n + more > len(held):
                setattr(self, name, np.concatenate([held, np.zeros(max(len(held), more), held.dtype)]))
        data = np.frombuffer(b"".join(pieces), np.uint8)
        for name, held, new in (("bytes", self.bytes_held, data), ("ids", self.ids_held, ids)):
            pool = getattr(self, name)
            if held + len(new) > len(pool):
                pool = np.concatenate([pool, np.zeros(max(len(pool), len(new)), pool.dtype)])
                setattr(self, name, pool)
            pool[held : held + len(new)] = new
        sizes = np.array([len(p) for p in pieces], np.int64)
        self.hash[n : n + more], self.size[n : n + more], self.count[n : n + more] = h, sizes, counts
        self.start[n : n + more] = self.bytes_held + np.cumsum(sizes) - sizes
        self.first[n : n + more] = self.ids_held + np.cumsum(counts) - counts
        self.n, self.bytes_held, self.ids_held = n + more, self.bytes_held + len(data), self.ids_held + len(ids)
        if 2 * self.n > len(self.keys):
            self._clear(4 * len(self.keys))
            self._place(self.hash[: self.n], np.arange(self.n, dtype=np.int32))
        else:
            self._place(h, np.arange(n, self.n, dtype=np.int32))


class Encoder:
    def __init__(self, path: str) -> None:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.model = Tokenizer(self.tokenizer.model)  # merges alone: what it is given are pieces
        self.special = [t.content.encode() for t in self.tokenizer.get_added_tokens_decoder().values()]
        with open(path, encoding="utf-8") as f:
            told = json.load(f)
        breaks = told.get("pre_tokenizer") or {}
        #: Whether the vocabulary breaks texts as described above.
        self.direct = told.get("normalizer") is None and breaks.get("type") == "ByteLevel" and breaks.get("use_regex", True) and not breaks.get("add_prefix_space")
        self.letters, self.table = byte_letters(), PieceTable()
        vocab = self.tokenizer.get_vocab()
        self.bytes_of = np.zeros(max(vocab.values()) + 1, np.int64)  # of each id: as many as its spelling has letters
        for spelling, i in vocab.items():
            self.bytes_of[i] = len(spelling)
        self.char_kind = np.full(0x110000, UNKNOWN, np.uint8)
        if self.direct:
            for c in range(128):
                self.char_kind[c] = self._kind_of(chr(c))
        self.one, self.two = np.zeros(256, bool), np.zeros((256, 256), bool)
        self.one[[ord(e) for e in ENDINGS[0]]] = True
        for a, b in ENDINGS[1]:
            self.two[ord(a), ord(b)] = True

    def _kind_of(self, c: str) -> int:
        breaks = self.tokenizer.pre_tokenizer.pre_tokenize_str
        return next((k for k, x in enumerate(BESIDE) if len(breaks(x + c + x)) == 1), BLANK if c == " " else WHITE)

    def whole(self, text: str) -> np.ndarray:
        return np.array(self.tokenizer.encode_batch_fast([text], add_special_tokens=False)[0].ids, np.uint32)

    def by_model(self, pieces: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of the pieces, one after another, and how many each has."""
        if not pieces:
            return np.zeros(0, np.uint32), np.zeros(0, np.int64)
        spelled = [p.decode("latin-1").translate(self.letters) for p in pieces]
        groups = [spelled[k : k + GROUP] for k in range(0, len(spelled), GROUP)]
        ids = np.concatenate([np.array(got.ids, np.uint32) for got in self.model.encode_batch_fast(groups, is_pretokenized=True, add_special_tokens=False)])
        ends = np.searchsorted(np.cumsum(self.bytes_of[ids]), np.cumsum([len(p) for p in pieces]), "right")
        return ids, np.diff(ends, prepend=0)

    def kinds(self, data: np.ndarray) -> np.ndarray:
        """The kind of the character that each byte belongs to."""
        kind = self.char_kind[data]
        lead = np.flatnonzero(data >= 0xC0)
        if len(lead):
            b = data[lead].astype(np.int32)
            size = 2 + (b >= 0xE0) + (b >= 0xF0)
            code = b & (0x7F >> size)
            for k in range(1, int(size.max())):
                more = size > k
                code[more] = code[more] << 6 | (data[lead[more] + k] & 0x3F)
            for c in np.unique(code[self.char_kind[code] == UNKNOWN]).tolist():
                self.char_kind[c] = self._kind_of(chr(c))
            found = self.char_kind[code]
            for k in range(int(size.max())):
                more = size > k
                kind[lead[more] + k] = found[more]
        return kind

    def starts(self, data: np.ndarray, opens: np.ndarray) -> np.ndarray:
        """Where the pieces begin; ``opens`` marks where texts do (and the first byte)."""
        kind = self.kinds(data)
        white = kind >= WHITE
        run = np.minimum(kind, WHITE)
        start = opens.copy()
        start[1:] |= run[1:] != run[:-1]
        head = np.flatnonzero(start & ~white & ~opens)
        head = head[white[head - 1]]
        blank = data[head - 1] == 32
        start[head[blank]] = False
        start[head[blank] - 1] = True
        lone = head[~blank] - 1  # the last character of white space before a word stands alone if it is no blank
        for _ in range(3):
            lone = lone - ((data[lone] & 0xC0) == 0x80)
        start[lone] = True
        sign = np.flatnonzero((data == APOSTROPHE) & start)
        if len(sign):
            n = len(data)
            after = np.append(data, np.zeros(2, np.uint8))
            closed = np.append(opens, [True, True])
            size = np.where(self.one[after[sign + 1]], 1, np.where(self.two[after[sign + 1], after[sign + 2]] & ~closed[sign + 2], 2, 0)) * ~closed[sign + 1]
            sign, size = sign[size > 0], size[size > 0]
            start[sign + 1] = False
            rest = (sign + 1 + size)[sign + 1 + size < n]
            start[rest[kind[rest] == LETTER]] = True
        return np.flatnonzero(start)

    def window(self, data: np.ndarray, opens: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Ids of a run of bytes; where its pieces begin; and how many ids stand before each piece, and in all."""
        if self.table.n > KEPT:
            self.table = PieceTable()
        table, n = self.table, len(data)
        a = self.starts(data, opens)
        b = np.append(a[1:], n)
        size = b - a
        h = span_hashes(AS_IS[data], a, b)
        number = table.find(h)
        new = np.flatnonzero((number < 0) & (size <= LONGEST_KEPT))
        if len(new):
            pick = new[np.unique(h[new], return_index=True)[1]]
            pieces = [data[s:e].tobytes() for s, e in zip(a[pick].tolist(), b[pick].tolist())]
            table.add(h[pick], pieces, *self.by_model(pieces))
            number[new] = table.find(h[new])
        held = np.maximum(number, 0)
        same = (number >= 0) & (table.size[held] == size)
        place = np.repeat(table.start[held] - a, size) + np.arange(n)
        if not same.all():
            place[~np.repeat(same, size)] = 0
        odd = np.flatnonzero(table.bytes[place] != data)
        if len(odd):
            same[np.searchsorted(a, odd, "right") - 1] = False
        alone = np.flatnonzero(~same)  # long pieces, and such as share a hash with another
        count, source = table.count[held], table.first[held]
        if len(alone):
            own, own_count = self.by_model([data[s:e].tobytes() for s, e in zip(a[alone].tolist(), b[alone].tolist())])
            count[alone], source[alone] = own_count, 0
        before = np.zeros(len(a) + 1, np.int64)
        np.cumsum(count, out=before[1:])
        place = np.repeat(source - before[:-1], count) + np.arange(before[-1])
        if len(alone):
            theirs = np.zeros(len(a), bool)
            theirs[alone] = True
            theirs = np.repeat(theirs, count)
            place[theirs] = 0
            ids = table.ids[place]
            ids[theirs] = own
        else:
            ids = table.ids[place]
        return ids, a, before

    def column(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts one after another, as the library gives them without special tokens added, and where each
        text's begin (one more than there are texts). Null counts as empty."""
        data, at = text_buffer(column)
        apart = self._apart(column, data, at)
        if len(apart) == len(at) - 1:
            parts = [apart[k] for k in range(len(apart))]
        else:
            ids, ends, before = [], [np.zeros(1, np.int64)], 0
            opens = np.zeros(len(data) + 1, bool)
            opens[at] = True
            for k in apart:  # not broken here: one blank each keeps their place
                data = data.copy() if not data.flags.writeable else data
                data[at[k] : at[k + 1]] = 32
            for lo, hi in cuts(data, at):
                first = opens[lo:hi].copy()
                first[0] = True
                got, a, counts = self.window(data[lo:hi], first)
                ids.append(got)
                inside = at[np.searchsorted(at, lo, "right") : np.searchsorted(at, hi, "right")]
                ends.append(before + counts[np.searchsorted(a, inside - lo)])
                before += len(got)
            flat, ends = np.concatenate(ids) if ids else np.zeros(0, np.uint32), np.concatenate(ends)
            begin = int(np.searchsorted(at, 0, "right")) - 1  # empty texts before the first byte
            ends = np.concatenate([np.zeros(begin, np.int64), ends])
            if not apart:
                return flat, ends
            parts = [apart[k] if k in apart else flat[ends[k] : ends[k + 1]] for k in range(len(at) - 1)]
        out = np.zeros(len(parts) + 1, np.int64)
        np.cumsum([len(p) for p in parts], out=out[1:])
        return (np.concatenate(parts) if parts else np.zeros(0, np.uint32)), out

    def _apart(self, column: pa.Array, data: np.ndarray, at: np.ndarray) -> dict[int, np.ndarray]:
        """Ids of the texts that go through the library in one piece, by their numbers."""
        text = lambda k: data[at[k] : at[k + 1]].tobytes().decode(errors="replace")
        if not self.direct:
            return {k: self.whole(text(k)) for k in range(len(at) - 1)}
        found: set[int] = set()
        raw = data.tobytes()
        for mark in self.special:
            spot = raw.find(mark)
            while spot >= 0:
                found.add(int(np.searchsorted(at, spot, "right")) - 1)
                spot = raw.find(mark, spot + 1)
        try:
            raw.decode()
        except UnicodeDecodeError:
            for k in range(len(at) - 1):
                try:
                    raw[at[k] : at[k + 1]].decode()
                except UnicodeDecodeError:
                    found.add(k)
        return {k: self.whole(text(k)) for k in sorted(found)}

    def ids(self, text: str) -> np.ndarray:
        """uint32 ids of one text."""
        return self.column(pa.array([text], pa.string()))[0]


def cuts(data: np.ndarray, at: np.ndarray, size: int = WINDOW) -> Iterator[tuple[int, int]]:
    """Runs of about ``size`` bytes; each ends where a text ends or, in a longer text, before a blank with a printable
    character behind it, where the library breaks in any case."""
    lo, n = 0, len(data)
    while lo < n:
        hi = lo + size
        if hi >= n:
            hi = n
        else:
            k = int(np.searchsorted(at, hi, "right")) - 1
            if at[k] > lo:
                hi = int(at[k])
            else:
                stop = int(at[k + 1])
                while hi < stop:
                    end = min(stop, hi + 4096)
                    gap = np.flatnonzero((data[hi : end - 1] == 32) & PRINTABLE[data[hi + 1 : end]])
                    if len(gap):
                        hi += int(gap[0])
                        break
                    hi = end if end == stop else end - 1
        yield lo, hi
        lo = hi


_encoders: dict[str, Encoder] = {}


def encoder(path: str) -> Encoder:
    """One encoder per worker and vocabulary file; the file has to exist at that path on every executor."""
    if path not in _encoders:
        _encoders[path] = Encoder(path)
    return _encoders[path]


def ended(source: Iterator[pa.RecordBatch], vocabulary: str, end: int, column: int = 1) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """Each batch with the ids of its texts, ``end`` behind every text, and where each text's ids begin."""
    enc = encoder(vocabulary)
    for batch in slices(source, column):
        ids, at = enc.column(batch.column(column))
        yield batch, np.insert(ids, at[1:], np.uint32(end)), at + np.arange(len(at))


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")
