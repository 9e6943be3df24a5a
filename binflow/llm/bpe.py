"""Byte-level BPE over flat numpy arrays.

``BytePairModel`` reads a tokenizer file of the ``tokenizers`` library (byte-level
pre-tokenizer, BPE model) and reproduces its ids. Texts become one flat array of code
points; pre-token borders come from a class table and comparisons with the neighbours;
the distinct pre-tokens that were not met before are merged together, round by round:
the symbols of all words lie in one array, each pair's rank is found by binary search over
the sorted pair keys, and every word merges its lowest-ranked pair. The model is a plain
picklable object of fixed size (it depends on the vocabulary only), so it may be broadcast.
"""

from __future__ import annotations

import json
from collections.abc import Iterator
from itertools import repeat

import numpy as np

OTHER, LETTER, NUMBER, SPACE, BORDER = 0, 1, 2, 3, 4
NO_RANK = np.int32(2**31 - 1)
#: code points handled at once, and the longest piece of one text
CHUNK = 1 << 20
#: fixed values: the endings that the pre-tokenizer splits off after an apostrophe
SHORT_ENDINGS = ("s", "t", "m", "d")
LONG_ENDINGS = ("re", "ve", "ll")


def byte_letters() -> list[str]:
    """The printable letter that stands for each byte in vocabulary files."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    shifted = iter(range(256, 512))
    return [chr(b if b in set(plain) else next(shifted)) for b in range(256)]


def class_table() -> np.ndarray:
    """Class of each code point as the library's own pattern engine sees it; the last entry is the border."""
    from tokenizers import Regex
    from tokenizers.pre_tokenizers import Split

    points = [p for p in range(0x110000) if not 0xD800 <= p < 0xE000]
    table = np.zeros(0x110001, np.uint8)
    for at in range(0, len(points), 2048):
        block = points[at : at + 2048]
        text = "".join(map(chr, block))
        for pattern, kind in ((r"\p{L}+", LETTER), (r"\p{N}+", NUMBER), (r"\s+", SPACE)):
            found = np.ones(len(block), bool)
            for _, (a, b) in Split(Regex(pattern), "removed").pre_tokenize_str(text):
                found[a:b] = False
            table[np.array(block)[found]] = kind
    table[0x110000] = BORDER
    return table


class BytePairModel:
    """Vocabulary, merge ranks and character classes; ``encode`` and ``decode`` work on batches."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        if (spec.get("pre_tokenizer") or {}).get("type") != "ByteLevel" or spec["pre_tokenizer"].get("add_prefix_space") or spec.get("normalizer"):
            raise ValueError(f"{path}: only byte-level files without normalizer or prefix space are supported")
        letters = byte_letters()
        to_byte = {c: b for b, c in enumerate(letters)}
        self.special = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
        size = max([*model["vocab"].values(), *self.special.values()]) + 1
        pieces = [b""] * size
        for text, i in model["vocab"].items():
            pieces[i] = bytes(to_byte[c] for c in text)
        for text, i in self.special.items():
            pieces[i] = text.encode()
        self.size = size
        self.piece_bytes = np.frombuffer(b"".join(pieces), np.uint8)
        self.piece_len = np.array([len(p) for p in pieces], np.int64)
        self.piece_start = np.cumsum(self.piece_len) - self.piece_len
        vocab = model["vocab"]
        self.byte_ids = np.array([vocab[c] for c in letters], np.int64)
        pairs = [m.split(" ") if isinstance(m, str) else m for m in model["merges"]]
        keys = np.array([vocab[a] * size + vocab[b] for a, b in pairs], np.int64)
        self.merged = np.array([vocab[a + b] for a, b in pairs], np.int64)
        order = np.argsort(keys, kind="stable")
        self.keys, self.ranks = keys[order], order.astype(np.int32)
        self.classes = class_table()
        self.single = self._whole_tokens(pieces, set(vocab.values()))

    def _whole_tokens(self, pieces: list[bytes], ids: set[int]) -> frozenset[bytes]:
        """Vocabulary strings proved, by merging each of them, to encode alone as one token."""
        words = [pieces[i] for i in sorted(ids) if pieces[i]]
        _, counts = self.merge(words)
        return frozenset(w for w, n in zip(words, counts.tolist(), strict=True) if n == 1)

    def pair_ranks(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        key = left * self.size + right
        at = np.searchsorted(self.keys, key)
        at[at == len(self.keys)] = 0
        return np.where(self.keys[at] == key, self.ranks[at], NO_RANK)

    def merge(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of non-empty words, flat, and the number of ids of each."""
        n = len(words)
        if not n:
            return np.empty(0, np.int64), np.empty(0, np.int64)
        lengths = np.fromiter(map(len, words), np.int64, n)
        sym = self.byte_ids[np.frombuffer(b"".join(words), np.uint8)]
        word = np.repeat(np.arange(n), lengths)
        rank = np.full(len(sym), NO_RANK, np.int32)
        inner = np.flatnonzero(word[1:] == word[:-1])
        rank[inner] = self.pair_ranks(sym[inner], sym[inner + 1])
        done_sym, done_word = [], []
        while len(sym):
            starts = np.flatnonzero(np.r_[True, word[1:] != word[:-1]])
            counts = np.diff(np.r_[starts, len(sym)])
            best = np.minimum.reduceat(rank, starts)
            if (best == NO_RANK).any():
                live = np.repeat(best != NO_RANK, counts)
                done_sym.append(sym[~live])
                done_word.append(word[~live])
                sym, word, rank = sym[live], word[live], rank[live]
                counts, best = counts[best != NO_RANK], best[best != NO_RANK]
                if not len(sym):
                    break
            hits = np.flatnonzero(rank == np.repeat(best, counts))
            if len(hits) > 1:  # of overlapping equal pairs every second one merges
                follows = np.r_[False, np.diff(hits) == 1]
                place = np.arange(len(hits))
                hits = hits[(place - np.maximum.accumulate(np.where(follows, 0, place))) % 2 == 0]
            sym[hits] = self.merged[rank[hits]]
            keep = np.ones(len(sym), bool)
            keep[hits + 1] = False
            moved = hits - np.arange(len(hits))
            sym, word, rank = sym[keep], word[keep], rank[keep]
            rank[moved] = NO_RANK
            touched = np.concatenate([moved, moved[moved > 0] - 1])
            touched = touched[touched + 1 < len(sym)]
            touched = touched[word[touched] == word[touched + 1]]
            rank[touched] = self.pair_ranks(sym[touched], sym[touched + 1])
        sym, word = np.concatenate(done_sym), np.concatenate(done_word)
        return sym[np.argsort(word, kind="stable")], np.bincount(word, minlength=n)

    def borders(self, points: np.ndarray) -> np.ndarray:
        """True where a pre-token starts; border symbols start one as well. The array starts and ends with a border."""
        kind = self.classes[points]
        space = points == 32
        blank = kind == SPACE
        before = np.r_[np.uint8(BORDER), kind[:-1]]
        after = np.r_[kind[1:], np.uint8(BORDER)]
        space_before = np.r_[False, space[:-1]]
        start = (kind != before) & ~(space_before & (kind < SPACE))
        start |= blank & (after < SPACE)
        start |= kind == BORDER
        quote = np.flatnonzero((points == 39) & (before != OTHER) & ~space_before)
        if len(quote):
            padded = np.r_[points, np.uint32(0), np.uint32(0)]
            one, two = padded[quote + 1], padded[quote + 2]
            short = np.isin(one, [ord(c) for c in SHORT_ENDINGS])
            long = np.zeros(len(quote), bool)
            for a, b in LONG_ENDINGS:
                long |= (one == ord(a)) & (two == ord(b))
            quote, size = quote[short | long], np.where(short, 1, 2)[short | long]
            start[quote + 1] = False
            rest = quote + 1 + size
            start[rest] |= kind[rest] == LETTER
        return start

    def pre_tokens(self, texts: list[str]) -> tuple[bytes, np.ndarray, np.ndarray, np.ndarray]:
        """UTF-8 bytes of all texts, start and end of each pre-token in them, and the index of its text."""
        border = np.uint32(0x110000).tobytes()
        points = np.frombuffer(border + b"".join(x for t in texts for x in (t.encode("utf-32-le"), border)), np.uint32)
        whole = "".join(texts).encode()
        start = np.flatnonzero(self.borders(points))
        is_border = points[start] == 0x110000
        size = (points < 0x110000).astype(np.int64)
        if len(whole) > len(points):
            size += (points >= 0x80) & (points < 0x110000)
            size += (points >= 0x800) & (points < 0x110000)
            size += (points >= 0x10000) & (points < 0x110000)
        elif len(whole) + len(texts) + 1 != len(points):
            size = self._utf8_sizes(points)
        offset = np.r_[0, np.cumsum(size)][np.r_[start, len(points)]]
        text_of = (np.cumsum(is_border) - 1)[~is_border]
        return whole, offset[:-1][~is_border], offset[1:][~is_border], text_of

    @staticmethod
    def _utf8_sizes(points: np.ndarray) -> np.ndarray:
        real = points < 0x110000
        return real.astype(np.int64) + ((points >= 0x80) & real) + ((points >= 0x800) & real) + ((points >= 0x10000) & real)

    def _segments(self, text: str) -> Iterator[str | int]:
        """Parts of a text that are pre-tokenized on their own, and ids of special strings between them."""
        parts: list[str | int] = [text]
        for content, i in self.special.items():
            if content in text:
                parts = [y for x in parts for y in (_between(x, content, i) if isinstance(x, str) else [x])]
        for x in parts:
            yield from [x] if isinstance(x, int) else _cut(x)

    def batches(self, texts: list[str | None]) -> Iterator[tuple[list[str], list[int], list[tuple[int, int]]]]:
        """Bounded groups of segments: (segments, text index of each, (text index, place, id) of special tokens)."""
        group, of, special, size = [], [], [], 0
        for k, text in enumerate(texts):
            for x in self._segments(text or ""):
                if isinstance(x, int):
                    special.append((k, len(group), x))
                    continue
                group.append(x)
                of.append(k)
                size += len(x)
                if size >= CHUNK:
                    yield group, of, special
                    group, of, special, size = [], [], [], 0
        if group or special:
            yield group, of, special


def _between(text: str, content: str, i: int) -> list[str | int]:
    first, *rest = text.split(content)
    return [x for x in [first, *(y for r in rest for y in (i, r))] if x != ""]


def _cut(text: str) -> Iterator[str]:
    """Pieces of about CHUNK characters, cut only where a space follows something else: a border in any context."""
    at = 0
    while len(text) - at > CHUNK:
        end = at + CHUNK
        while end < len(text) and not (text[end] == " " and not text[end - 1].isspace()):
            end += 1
        yield text[at:end]
        at = end
    yield text[at:] if at else text


class WordTable:
    """A number for each word met so far, found for all words of a batch at once.

    Words of up to 16 bytes are looked up in a direct-mapped table of their packed bytes;
    longer ones, and those that another word displaced, in a dict. ``learn`` gives the
    numbers of words that are in neither. The table is emptied when it reaches its bounds.
    """

    SLOTS = 20

    def __init__(self, learn, most_words: int, most_bytes: int = 16_000_000):
        self.learn, self.most_words, self.most_bytes = learn, most_words, most_bytes
        self.clear()

    def clear(self) -> None:
        n = 1 << self.SLOTS
        self.known: dict[bytes, int] = {}
        self.bytes = 0
        self.low, self.high = np.zeros(n, np.uint64), np.zeros(n, np.uint64)
        self.length, self.value = np.zeros(n, np.uint8), np.zeros(n, np.int32)

    @property
    def full(self) -> bool:
        return len(self.known) > self.most_words or self.bytes > self.most_bytes

    def find(self, whole: bytes, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        n = end - start
        window = np.lib.stride_tricks.sliding_window_view(np.frombuffer(whole + bytes(16), np.uint8), 8)
        mask = np.array([(1 << 8 * k) - 1 for k in range(9)], np.uint64)
        low = np.ascontiguousarray(window[start]).view(np.uint64)[:, 0] & mask[np.minimum(n, 8)]
        long = np.flatnonzero(n > 8)
        high = np.zeros(len(n), np.uint64)
        high[long] = np.ascontiguousarray(window[start[long] + 8]).view(np.uint64)[:, 0] & mask[np.minimum(n[long] - 8, 8)]
        slot = low * np.uint64(0x9E3779B97F4A7C15) + high * np.uint64(0xC2B2AE3D27D4EB4F)
        slot ^= slot >> np.uint64(29)
        slot = (slot * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(64 - self.SLOTS)).astype(np.int64)
        out = self.value[slot].astype(np.int64)
        miss = np.flatnonzero((n > 16) | (self.length[slot] != n) | (self.low[slot] != low) | (self.high[slot] != high))
        if len(miss):
            words = [whole[a:b] for a, b in zip(start[miss].tolist(), end[miss].tolist(), strict=True)]
            out[miss] = np.fromiter(map(self.known.get, words, repeat(-1)), np.int64, len(words))
            new = list(dict.fromkeys(words[i] for i in np.flatnonzero(out[miss] < 0).tolist()))
            if new:
                self.known.update(zip(new, self.learn(new), strict=True))
                self.bytes += sum(map(len, new))
                out[miss] = np.fromiter(map(self.known.__getitem__, words), np.int64, len(words))
            put = miss[n[miss] <= 16]
            at = slot[put]
            last = np.full(len(self.value) if len(at) > 1 << 16 else 0, -1)
            if len(last):  # of the words that want one slot, all fields must come from the same one
                last[at] = put
                put, at = (x := last[last >= 0]), slot[x]
            else:
                at, first = np.unique(at, return_index=True)
                put = put[first]
            self.low[at], self.high[at], self.length[at], self.value[at] = low[put], high[put], n[put], out[put]
        return out


class Encoder:
    """Encodes texts and remembers the ids of the words that it met, up to a bound."""

    def __init__(self, model: BytePairModel, most_words: int = 350_000):
        self.model = model
        self.table = WordTable(self._learn, most_words)
        self._clear()

    def _clear(self) -> None:
        self.table.clear()
        self.flat, self.used = np.empty(1 << 16, np.int32), 0
        self.first, self.number = np.empty(1 << 14, np.int64), np.empty(1 << 14, np.int64)

    def _learn(self, words: list[bytes]) -> range:
        ids, counts = self.model.merge(words)
        base = len(self.table.known)
        while self.used + len(ids) > len(self.flat):
            self.flat = np.r_[self.flat, np.empty_like(self.flat)]
        while base + len(words) > len(self.first):
            self.first, self.number = np.r_[self.first, np.empty_like(self.first)], np.r_[self.number, np.empty_like(self.number)]
        self.flat[self.used : self.used + len(ids)] = ids
        self.first[base : base + len(words)] = self.used + np.cumsum(counts) - counts
        self.number[base : base + len(words)] = counts
        self.used += len(ids)
        return range(base, base + len(words))

    def encode(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
        """All ids, flat, and the number of ids of each text. None is an empty text."""
        out, counts = [np.empty(0, np.int32)], np.zeros(len(texts), np.int64)
        for group, of, special in self.model.batches(texts):
            whole, start, end, seg = self.model.pre_tokens(group)
            if self.table.full:
                self._clear()
            at = self.table.find(whole, start, end)
            number = self.number[at]
            total = int(number.sum())
            ids = self.flat[np.repeat(self.first[at] - np.cumsum(number) + number, number) + np.arange(total)]
            of = np.array(of, np.int64)
            counts += np.bincount(of[seg], number, minlength=len(texts)).astype(np.int64)
            if special:
                ends = np.r_[0, np.cumsum(np.bincount(seg, number, minlength=len(group)).astype(np.int64))]
                ids = np.insert(ids, [ends[place] for _, place, _ in special], [i for _, _, i in special])
                counts += np.bincount([k for k, _, _ in special], minlength=len(texts))
            out.append(ids)
        return np.concatenate(out), counts

    def decode(self, ids: np.ndarray) -> bytes:
        """Bytes of the tokens in a row."""
        m = self.model
        n = m.piece_len[ids]
        return m.piece_bytes[np.repeat(m.piece_start[ids] - np.cumsum(n) + n, n) + np.arange(int(n.sum()))].tobytes()


class Counter:
    """Counts tokens: pre-tokens that are proved single tokens count one, only the rest is merged."""

    def __init__(self, model: BytePairModel, most_words: int = 350_000):
        self.model = model
        self.table = WordTable(self._learn, most_words)

    def _learn(self, words: list[bytes]) -> list[int]:
        rest = [w for w in words if w not in self.model.single]
        merged = dict(zip(rest, self.model.merge(rest)[1].tolist(), strict=True))
        return [merged.get(w, 1) for w in words]

    def count(self, texts: list[str | None]) -> np.ndarray:
        out = np.zeros(len(texts), np.int64)
        for group, of, special in self.model.batches(texts):
            whole, start, end, seg = self.model.pre_tokens(group)
            if self.table.full:
                self.table.clear()
            n = self.table.find(whole, start, end)
            out += np.bincount(np.array(of, np.int64)[seg], n, minlength=len(texts)).astype(np.int64)
            out += np.bincount([k for k, _, _ in special], minlength=len(texts)) if special else 0
        return out
