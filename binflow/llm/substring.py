"""Passages that repeat across documents, by compact windows (operator 7).

The tokens of a document are its word shingles. Under one hash function, a compact window
(l, c, r) stands for all passages that lie in shingles l..r and hold shingle c: their minimum
hash is that of c. The windows are the nodes of the Cartesian tree over the hashes; only
those at least as wide as the shortest passage are kept, about 2 n / width of them. Two
documents that share a passage have windows around it with the same minimum, under every
hash function whose minimum lies in shared text.

Windows with one minimum are joined with the first of them (smallest id, then place): a
task joins its own first and sends on one window for each minimum, so a passage that a third
of all documents hold reaches a reducer once a task. The interval in which both windows
allow the same alignment is the candidate; the words of both sides and around them verify it.

The first window of a minimum need not hold the passage that two later ones share. Where two
or more windows of a minimum differ from the first around it, they are compared with each
other: a window is set against the first one of equal surroundings, and the first ones of all
surroundings meet in one task, with the words around them. A word that no verified repeat
covers can be in a repeat only with an earlier window that holds a shingle with that word, or
the shingles on both sides of it, and as many shingles in all as a repeat must share: these
are looked up and compared, so every repeat is met and what is known already is not met again.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from binflow.llm.common import slices
from binflow.plans.layout import dense_ids
from binflow.storage import forget, materialise, ship_package

SHINGLE, SIMILARITY, MIN_WORDS, HASHES = 5, 0.8, 50, 4
#: windows that a task holds before it joins its own and sends on the rest
HELD = 250_000
#: bytes of word hashes that a task sends on at once
SENT_BYTES = 4_000_000
_WORD = re.compile(rb"[^\x20\x09-\x0d]+")
_SENT = pa.schema([("doc", pa.int64()), ("low", pa.list_(pa.int64())), ("begin", pa.list_(pa.int64())), ("end", pa.list_(pa.int64())), ("other", pa.int64()), ("words", pa.binary())])
_FOUND = pa.schema([("key", pa.int64()), ("doc", pa.int64()), ("low", pa.int64()), ("high", pa.int64()), ("other", pa.int64()), ("words", pa.binary()), ("fresh", pa.binary())])
_FIELDS = "key bigint, doc bigint, c int, l int, r int, other bigint, around bigint"
#: widths of a passage that are looked at on each side of a minimum
REACH = 2
#: bytes of text that are hashed at once, a word more at most
HASHED = 2_000_000
#: words of the windows that are met at once, one key's at least
MET = 1_500_000
#: shingles of windows that are sorted at once
SORTED = 2_000_000
#: places in a table of one key's windows and shingles
TABLE = 16_000_000
#: alignments of two documents up to which it is not asked what words each of them can cover
FEW = 4
_ODD, _BACK = 0x9E3779B97F4A7C15, pow(0x9E3779B97F4A7C15, -1, 1 << 64)
_POWERS: list[np.ndarray] = []
_STEP = np.uint64(_ODD)


def _powers(n: int) -> list[np.ndarray]:
    """Powers 0 to ``n`` of an odd number and of its inverse modulo 2^64."""
    if not _POWERS or len(_POWERS[0]) <= n:
        _POWERS[:] = [np.cumprod(np.r_[np.uint64(1), np.full(n, x, np.uint64)]) for x in (_ODD, _BACK)]
    return _POWERS


def hashed_words(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hashes of the words of all A-Z-lower-cased texts, and where each text's begin (one more than texts)."""
    texts = texts.fill_null("").cast(pa.large_binary())
    offsets = np.frombuffer(texts.buffers()[1], np.int64)[texts.offset : texts.offset + len(texts) + 1] if len(texts) else np.zeros(1, np.int64)
    data = np.frombuffer(texts.buffers()[2], np.uint8)[offsets[0] : offsets[-1]] if offsets[-1] > offsets[0] else np.empty(0, np.uint8)
    bounds = offsets - offsets[0]
    word = _IN_WORD[data]
    first, last = np.empty((2, len(data)), bool)
    first[:1], first[1:] = word[:1], word[1:] & ~word[:-1]
    last[-1:], last[:-1] = word[-1:], word[:-1] & ~word[1:]
    edge = bounds[(bounds > 0) & (bounds < len(data))]
    first[edge], last[edge - 1] = word[edge], word[edge - 1]
    begin, end = np.flatnonzero(first), np.flatnonzero(last) + 1
    out, i = np.empty(len(begin), np.uint64), 0
    while i < len(begin):
        j = max(i + 1, int(np.searchsorted(begin, begin[i] + HASHED, "right")))
        x, y = begin[i:j] - begin[i], end[i:j] - begin[i]
        powers, back = _powers(int(y[-1]))
        sums = np.r_[np.uint64(0), np.cumsum(_BYTES[data[begin[i] : end[j - 1]]] * powers[: y[-1]])]
        out[i:j] = _mixed((sums[y] - sums[x]) * back[x] + (y - x).astype(np.uint64), 9)
        i = j
    return out, np.searchsorted(begin, bounds)


def word_lists(texts: pa.Array) -> list[np.ndarray]:
    """The hashes of each text's words."""
    words, starts = hashed_words(texts)
    return np.split(words, starts[1:-1]) if len(texts) else []


def word_hashes(text: str | None) -> np.ndarray:
    """64-bit hash of each word of the A-Z-lower-cased text."""
    return hashed_words(pa.array([text], pa.string()))[0]


def shingle_hashes(words: np.ndarray, n: int = SHINGLE) -> np.ndarray:
    """Hash of every run of ``n`` words; none if there are fewer."""
    if len(words) < n:
        return np.empty(0, np.uint64)
    out = words[: len(words) - n + 1].astype(np.uint64)
    for k in range(1, n):
        out *= _STEP
        out += words[k : k + len(out)]
    return out


def _mixed(x: np.ndarray, salt: int) -> np.ndarray:
    x = (x ^ np.uint64(salt * 0xD1B54A32D192ED03 & (1 << 64) - 1)) * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(31)
    x *= np.uint64(0x94D049BB133111EB)
    return x ^ x >> np.uint64(29)


#: a number for each byte, one for A-Z and a-z; whether it belongs to a word
_BYTES = _mixed(np.frombuffer(bytes(range(256)).lower(), np.uint8).astype(np.uint64) + np.uint64(1), 10)
_IN_WORD = np.array([not bytes([b]).isspace() for b in range(256)])


def tied_windows(values: np.ndarray, width: int) -> list[tuple[int, int, int]]:
    """(l, c, r) of the Cartesian tree's nodes over ``values`` that span ``width`` shingles at least, in plain code; ``document_windows`` does the same in numpy.

    Where values repeat, each occurrence is the centre of what lies between the last equal one and the next
    smaller one. Of a run of one value only the first is a centre. One pass, whatever the values.
    """
    out: list[tuple[int, int, int]] = []
    open_: list[list[int]] = []  # value, first and last place of a run; values do not fall
    for i, v in enumerate([*values.tolist(), -1]):
        if open_ and open_[-1][0] == v and open_[-1][2] == i - 1:
            open_[-1][2] = i
            continue
        while open_ and open_[-1][0] > v:
            _, c, _ = open_.pop()
            a = open_[-1][2] + 1 if open_ else 0
            if i - a >= width:
                out.append((a, c, i - 1))
        open_.append([v, i, i])
    return out


def _content(shingles: np.ndarray, low: np.ndarray, c: np.ndarray, high: np.ndarray) -> np.ndarray:
    """Hash of what windows hold from ``low`` to before ``high``, around their minimum."""
    powers, back = _powers(len(shingles))
    sums = np.r_[np.uint64(0), np.cumsum(_mixed(shingles, 7) * powers[: len(shingles)])]
    return _mixed((sums[high] - sums[low]) * back[low] + (c - low).astype(np.uint64), 8).view(np.int64)


def centred(values: np.ndarray, begin: np.ndarray, end: np.ndarray, width: int) -> np.ndarray:
    """Rows (l, c, r) of the compact windows of the runs [begin, end) of ``values``, cut to ``REACH`` widths at least on each side.

    Values are told apart by their upper bits; of equal ones the first is the smaller.
    """
    n = len(values)
    bits = max(1, n.bit_length())
    place = np.uint64((1 << bits) - 1)
    inside = np.zeros(n + 1, np.int8)
    long = end - begin >= width
    np.add.at(inside, begin[long], 1)
    np.add.at(inside, end[long] - width + 1, -1)
    starts = np.flatnonzero(np.cumsum(inside[:n]))
    if not len(starts):
        return np.empty((0, 3), np.int64)
    least = [values & ~place | np.arange(n, dtype=np.uint64)]  # of 1, 2, 4... values from each place on
    while 1 << len(least) <= max(width, REACH * width):
        step = 1 << len(least) - 1
        x = least[-1].copy()
        if step < n:
            np.minimum(x[:-step], least[-1][step:], out=x[:-step])
        least.append(x)
    k = width.bit_length() - 1
    at = (np.minimum(least[k][starts], least[k][starts + width - (1 << k)]) & place).astype(np.int64)
    c = at[np.r_[True, at[1:] != at[:-1]]]
    run = (values[c] ^ values[c - 1]) >> np.uint64(bits) == 0
    c = c[~(run & (c > begin[np.searchsorted(begin, c, "right") - 1]))]
    own, l, r = least[0][c], c.copy(), c + 1
    for k in range(len(least) - 1, -1, -1):
        step = 1 << k
        q = l - step
        l = np.where((q >= 0) & (least[k][np.maximum(q, 0)] > own), q, l)
        r = np.where((r + step <= n) & (least[k][np.minimum(r, n - 1)] > own), r + step, r)
    run = np.searchsorted(begin, c, "right") - 1
    l, r = np.maximum(l, begin[run]), np.minimum(r, end[run]) - 1
    good = r - l + 1 >= width
    return np.column_stack([l, c, r])[good]


def document_windows(texts: pa.Array, hashes: int, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Of the windows of all hash functions the text's place, and rows (key, c, l, r, around); the key is the minimum with the function's number in its low bits."""
    words, bounds = hashed_words(texts)
    begin, end = bounds[:-1], np.maximum(bounds[:-1], bounds[1:] - SHINGLE + 1)
    kept = end - begin >= width
    if not kept.any():
        return np.empty(0, np.int64), np.empty((0, 5), np.int64)
    text, begin, end = np.flatnonzero(kept), begin[kept], end[kept]
    shingles, place, out = shingle_hashes(words), [], []
    for f in range(hashes):
        values = _mixed(shingles, f + 1)
        l, c, r = centred(values, begin, end, width).T
        key = (values[c] & ~np.uint64(15) | np.uint64(f)).view(np.int64)
        run = np.searchsorted(begin, c, "right") - 1
        around = _content(shingles, np.maximum(l, c - REACH * width), c, np.minimum(r, c + REACH * width) + 1)
        place.append(text[run])
        out.append(np.column_stack([key, c - begin[run], l - begin[run], r - begin[run], around]))
    return np.concatenate(place), np.concatenate(out)


def _against(rows: np.ndarray, first: np.ndarray, width: int) -> np.ndarray:
    """Candidates of windows (doc, c, l, r) against the first of their key: (doc, shift, from, to, first doc), in the doc's shingles."""
    low = np.maximum(rows[:, 2] - rows[:, 1], first[:, 2] - first[:, 1])
    high = np.minimum(rows[:, 3] - rows[:, 1], first[:, 3] - first[:, 1])
    good = (high - low + 1 >= width) & (rows[:, 0] != first[:, 0])
    rows, first, low, high = rows[good], first[good], low[good], high[good]
    return np.column_stack([rows[:, 0], rows[:, 1] - first[:, 1], rows[:, 1] + low, rows[:, 1] + high, first[:, 0]])


def _batch(key, rows, other) -> pa.RecordBatch:
    """Rows (doc, c, l, r, around), l and r as distances from c, which pack better."""
    columns = [*(pa.array(x.astype(np.int32)) for x in (rows[:, 1], rows[:, 2] - rows[:, 1], rows[:, 3] - rows[:, 1])), other, pa.array(rows[:, 4])]
    return pa.RecordBatch.from_arrays([pa.array(key), pa.array(rows[:, 0]), *columns], ["key", "doc", "c", "l", "r", "other", "around"])


def _groups(key: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of windows sorted by (key, doc, c): the place of each one's first, and of the first one with its surroundings (itself, if that is of its own document)."""
    at = np.arange(len(key))
    new = np.r_[True, key[1:] != key[:-1]] if len(key) else np.empty(0, bool)
    first = np.maximum.accumulate(np.where(new, at, 0))
    order = np.lexsort((at, rows[:, 4], first))
    f, around = first[order], rows[order, 4]
    opens = np.r_[True, (f[1:] != f[:-1]) | (around[1:] != around[:-1])] if len(key) else new
    alike = np.empty(len(key), np.int64)
    alike[order] = order[np.maximum.accumulate(np.where(opens, at, 0))]
    return first, np.where(rows[alike, 0] == rows[:, 0], at, alike)


def _pairs(rows: np.ndarray, first: np.ndarray, alike: np.ndarray, width: int) -> np.ndarray:
    """Candidates of windows against the first of their key, and against the first one with their surroundings."""
    at = np.arange(len(rows))
    one, two = at != first, (at != alike) & (alike != first)
    return np.concatenate([_against(rows[one], rows[first[one]], width), _against(rows[two], rows[alike[two]], width)])


def _widest(pairs: np.ndarray) -> np.ndarray:
    """Candidates of one alignment of two documents as one, from the first place to the last."""
    if not len(pairs):
        return pairs
    pairs = pairs[np.lexsort((pairs[:, 1], pairs[:, 4], pairs[:, 0]))]
    first = np.flatnonzero(np.r_[True, (pairs[1:, [0, 1, 4]] != pairs[:-1, [0, 1, 4]]).any(axis=1)])
    out = pairs[first]
    out[:, 2], out[:, 3] = np.minimum.reduceat(pairs[:, 2], first), np.maximum.reduceat(pairs[:, 3], first)
    return out


def _repeated(key: np.ndarray) -> np.ndarray:
    """Which of sorted keys are there twice or more."""
    out = np.zeros(len(key), bool)
    same = key[1:] == key[:-1]
    out[1:] = same
    out[:-1] |= same
    return out


def _send_on(docs: list[np.ndarray], found: list[np.ndarray], width: int) -> Iterator[pa.RecordBatch]:
    """The windows of each key's first document and the first one of all other surroundings; the candidates of the rest."""
    doc, w = np.concatenate(docs), np.concatenate(found)
    order = np.argsort(w[:, 0])
    lone = np.empty(len(order), bool)
    lone[order] = ~_repeated(w[order, 0])
    yield _batch(w[lone, 0], np.column_stack([doc[lone], w[lone, 1:]]), pa.nulls(int(lone.sum()), pa.int64()))
    doc, w = doc[~lone], w[~lone]
    order = np.lexsort((w[:, 1], doc, w[:, 0]))
    key, rows = w[order, 0], np.column_stack([doc[order], w[order, 1:]])
    first, alike = _groups(key, rows)
    pairs = _widest(_pairs(rows, first, alike, width))
    on = (rows[:, 0] == rows[first, 0]) | (alike == np.arange(len(key)))
    yield _batch(key[on], rows[on], pa.nulls(int(on.sum()), pa.int64()))
    if len(pairs):
        filled = np.column_stack([pairs[:, :4], np.zeros(len(pairs), np.int64)])
        yield _batch(_mixed(pairs[:, 0].view(np.uint64), 5).view(np.int64), filled, pa.array(pairs[:, 4]))


def _windows(hashes: int, width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        docs, found, held = [], [], 0
        for whole in batches:
            for batch in slices(whole, "text"):
                place, w = document_windows(batch.column(1), hashes, width)
                if len(w):
                    docs.append(batch.column(0).to_numpy(zero_copy_only=False)[place])
                    found.append(w)
                    held += len(w)
                if held >= HELD:
                    yield from _send_on(docs, found, width)
                    docs, found, held = [], [], 0
        if held:
            yield from _send_on(docs, found, width)

    return run


def _candidates(width: int):
    def whole(key: np.ndarray, rows: np.ndarray) -> np.ndarray:
        """Candidates of the windows of whole keys; those of a document against itself are to meet the others of their key: (doc, key, from, to, doc, centre)."""
        several = _repeated(key)
        key, rows = key[several], rows[several]
        first, alike = _groups(key, rows)
        pairs = _widest(_pairs(rows, first, alike, width))
        differ = (rows[:, 4] != rows[first, 4]) & (alike == np.arange(len(key)))
        meet = differ & (np.bincount(first[differ], minlength=len(key))[first] > 1)
        doc, c = rows[meet, 0], rows[meet, 1]
        low, high = np.maximum(rows[meet, 2], c - REACH * width), np.minimum(rows[meet, 3], c + REACH * width)
        return np.concatenate([np.column_stack([pairs, np.zeros(len(pairs), np.int64)]), np.column_stack([doc, key[meet], low, high, doc, c])])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come sorted by (key, doc, c); the windows of a batch's last key wait for the next batch."""
        key_left, rows_left = np.empty(0, np.int64), np.empty((0, 5), np.int64)

        def batch_of(out: np.ndarray) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(out[:, k]) for k in range(6)], ["doc", "shift", "low", "high", "other", "centre"])

        for batch in batches:
            lone = np.asarray(batch.column("other").is_null())
            key, *cols = (batch.column(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in ("key", "doc", "c", "l", "r", "around"))
            cols[2:4] = cols[2] + cols[1], cols[3] + cols[1]
            rows, other = np.column_stack(cols), batch.column("other").fill_null(0).to_numpy()
            ready = np.column_stack([rows[:, :4], other, np.zeros(len(rows), np.int64)])[~lone]
            key, rows = np.r_[key_left, key[lone]], np.concatenate([rows_left, rows[lone]])
            before = np.flatnonzero(key != key[-1]) if len(key) else key
            end = int(before[-1]) + 1 if len(before) else 0
            yield batch_of(np.concatenate([ready, whole(key[:end], rows[:end])]))
            key_left, rows_left = key[end:], rows[end:]
        if len(key_left):
            yield batch_of(whole(key_left, rows_left))

    return run


def _places(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """For each of ``a`` the place in ``b`` that it is set against: the same one, else what follows its predecessor's, else the nearest; -1 if none."""
    size = min(len(a), len(b))
    at = np.full(len(a), -1, np.int64)
    same = np.flatnonzero(a[:size] == b[:size])
    at[same] = same
    if len(same) == len(a):
        return at
    left = np.flatnonzero(at < 0)
    order = np.argsort(b, kind="stable")
    low, high = np.searchsorted(b[order], a[left], "left"), np.searchsorted(b[order], a[left], "right")
    lone = high - low == 1
    at[left[lone]] = order[low[lone]]
    several = high - low > 1
    for i, x, y in zip(left[several].tolist(), low[several].tolist(), high[several].tolist(), strict=True):
        follows = at[i - 1] + 1 if i and at[i - 1] >= 0 else len(b)
        if follows < len(b) and b[follows] == a[i]:
            at[i] = follows
        else:
            k = int(np.searchsorted(order[x:y], i))
            at[i] = min(order[x:y][max(0, k - 1) : k + 1].tolist(), key=lambda place: abs(place - i))
    return at


def _joined(x: list[int], y: list[int], similarity: float, n: int) -> list[int] | None:
    """Two passages (from, to, from and to in the other text, equal shingles) as one, if both texts hold them in this order and they are similar."""
    twice = max(0, x[3] - y[2])
    if y[2] <= x[2] or twice >= min(n, y[4]):
        return None
    hits = x[4] + y[4] - twice
    if hits < similarity * (y[1] - x[0] + y[3] - x[2] - hits):
        return None
    return [x[0], y[1], x[2], y[3], hits]


def matching_spans(words: np.ndarray, other: np.ndarray, min_words: int = MIN_WORDS, similarity: float = SIMILARITY, n: int = SHINGLE) -> list[tuple[int, int]]:
    """Word spans [from, to) of a word run that are near-duplicates of a passage of the other run.

    Runs of equal shingles are joined, over words that either side has changed, added or left
    out, while the Jaccard similarity of the joined passages' shingles stays at ``similarity``
    or more; spans of ``min_words`` words are kept.
    """
    at = _places(shingle_hashes(words.astype(np.uint64), n), shingle_hashes(other.astype(np.uint64), n))
    if not coverable(at >= 0, max(1, min_words - n + 1), similarity).any():
        return []
    follows = np.r_[False, (at[1:] == at[:-1] + 1) & (at[:-1] >= 0)] if len(at) else np.empty(0, bool)
    starts = np.flatnonzero((at >= 0) & ~follows)
    ends = np.flatnonzero((at >= 0) & ~np.r_[follows[1:], False]) + 1
    out: list[list[int]] = []
    for a, b in zip(starts.tolist(), ends.tolist(), strict=True):
        new, k = [a, b, int(at[a]), int(at[a]) + b - a, b - a], len(out) - 1
        while k >= 0:
            x = out[k]
            # most are too far away for what they share
            if x[2] < new[2] and (x[4] + new[4]) * (1 + similarity) >= similarity * (new[1] - x[0] + new[3] - x[2]) - 1e-6 and (one := _joined(x, new, similarity, n)):
                new = one
                del out[k]
                k = len(out)
            k -= 1
        out.append(new)
    return [(a, b + n - 1) for a, b, *_ in out if b - a + n - 1 >= min_words]


def merged(spans: list[tuple[int, int, int]]) -> list[tuple[int, int, int]]:
    """Union of overlapping (from, to, source) spans; the smallest source is named."""
    out: list[list[int]] = []
    for a, b, s in sorted(spans):
        if out and a < out[-1][1]:
            out[-1][1], out[-1][2] = max(out[-1][1], b), min(out[-1][2], s)
        else:
            out.append([a, b, s])
    return [tuple(x) for x in out]


def without(text: str, spans: list[tuple[int, int, int]]) -> str:
    """The text without the words of the spans; spans beyond its end (found in another row of the same id) are passed over."""
    raw = text.encode()
    starts = [m.start() for m in _WORD.finditer(raw)] + [len(raw)]
    parts, at = [], 0
    for a, b, _ in spans:
        if a >= len(starts) - 1:
            break
        parts.append(raw[at : starts[a]])
        at = starts[min(b, len(starts) - 1)]
    return b"".join([*parts, raw[at:]]).decode()


def _short(hashes: np.ndarray) -> np.ndarray:
    return (hashes >> np.uint64(32)).astype("<u4")


def _bundles(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Candidates of a batch against one earlier document as one row, so that its text is joined once for all of them."""
    for batch in batches:
        other = batch.column("other").to_numpy(zero_copy_only=False)
        order = np.argsort(other, kind="stable")
        new = np.flatnonzero(np.r_[True, np.diff(other[order]) != 0]) if len(other) else np.empty(0, np.int64)
        offsets = pa.array(np.r_[new, len(other)].astype(np.int32))
        take = pa.array(order)
        lists = [pa.ListArray.from_arrays(offsets, batch.column(c).take(take)) for c in ("doc", "shift", "low", "high")]
        yield pa.RecordBatch.from_arrays([pa.array(other[order[new]]), *lists], ["other", "doc", "shift", "low", "high"])


def _bytes(column: pa.BinaryArray) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of all values, and where each one's begin (one more than values)."""
    offsets = np.frombuffer(column.buffers()[1], np.int32)[column.offset : column.offset + len(column) + 1]
    return np.frombuffer(column.buffers()[2] or b"", np.uint8)[offsets[0] : offsets[-1]], (offsets - offsets[0]).astype(np.int64)


def _lists(column: pa.ListArray) -> list[list]:
    """The lists of whole numbers of a column without nulls, in fewer steps than Arrow's own."""
    ends = np.cumsum(column.value_lengths().to_numpy(zero_copy_only=False)).tolist()
    values = column.flatten().to_numpy(zero_copy_only=False).tolist()
    return [values[a:b] for a, b in zip([0, *ends], ends, strict=False)]


def _asked(column: pa.ListArray) -> list[list[dict]]:
    """The candidates of each document."""
    ends = np.cumsum(column.value_lengths().to_numpy(zero_copy_only=False)).tolist()
    all_ = column.flatten()
    fields = (*(_lists(all_.field(c)) for c in ("low", "begin", "end")), all_.field("other").to_numpy(zero_copy_only=False).tolist(), all_.field("words").to_pylist())
    each = [{"low": low, "begin": begin, "end": end, "other": other, "words": words} for low, begin, end, other, words in zip(*fields, strict=True)]
    return [each[a:b] for a, b in zip([0, *ends], ends, strict=False)]


def _runs(mask: np.ndarray) -> list[tuple[int, int]]:
    """Ranges [from, to) of a boolean array that are set."""
    edges = np.flatnonzero(np.diff(np.r_[False, mask, False]))
    return list(zip(edges[::2].tolist(), edges[1::2].tolist(), strict=True))


def coverable(shared: np.ndarray, width: int, similarity: float) -> np.ndarray:
    """Words that some repeat may cover, when no earlier text has other shingles than the ``shared`` ones: those of ranges of ``width`` shingles or more that hold this part of them."""
    n = len(shared)
    if n < width:
        return np.zeros(n + SHINGLE - 1, bool)
    score = np.zeros(n + 1)
    np.cumsum(shared, out=score[1:])
    score -= similarity * np.arange(n + 1)
    starts = np.minimum.accumulate(np.where(shared, score[:-1], np.inf))
    ends = np.flatnonzero(shared[width - 1 :]) + width
    ends = ends[starts[ends - width] <= score[ends] + 1e-9]
    if not len(ends):
        return np.zeros(n + SHINGLE - 1, bool)
    first = np.searchsorted(-starts, -score[ends] - 1e-9)  # the first range that is good enough up to each end
    return np.cumsum(np.bincount(first, minlength=n + SHINGLE) - np.bincount(ends + SHINGLE - 1, minlength=n + SHINGLE))[:-1] > 0


def _may_gain(at: np.ndarray, several: np.ndarray, fresh: np.ndarray, width: int, similarity: float) -> np.ndarray:
    """Whether a repeat of a window and an earlier one, a row each, may hold ``fresh`` words of the window.

    ``at`` has the place in the earlier window of each of the window's shingles, -1 if it has none; where it holds
    one of them twice, ``several``, the length of its passage is not known and counts as the shingles shared.
    """
    rows, n = at.shape
    if n < width:
        return np.zeros(rows, bool)
    has, share = at >= 0, np.float32(similarity)
    hits = np.zeros((rows, n + 1), np.float32)
    np.cumsum(has, axis=1, dtype=np.float32, out=hits[:, 1:])
    hits = hits[:, :-1]
    theirs = np.where(several[:, None], hits, at) if several.any() else at
    score = (1 + share) * hits - share * (np.arange(n, dtype=np.float32) + theirs)
    least = np.minimum.accumulate(np.where(has, score, np.float32(np.inf)), axis=1)
    ends = np.where(has, score + (1 - share) + np.float32(1e-3), np.float32(-np.inf))
    out = np.zeros(rows, bool)
    runs = _runs(fresh)
    for a, b in runs if len(runs) <= 6 else [(runs[0][0], runs[-1][1])]:
        q = max(width, a - SHINGLE + 2)
        mid = min(max(q, b - 1 + width), n + 1)  # for ends below it the length bounds the first place, from there on the last fresh word does
        if mid > q:
            out |= (ends[:, q - 1 : mid - 1] >= least[:, q - width : mid - width]).any(axis=1)
        if mid <= n:
            out |= ends[:, mid - 1 :].max(axis=1) >= least[:, b - 1]
    return out


def _numbers(doc: np.ndarray, begins: np.ndarray, words: np.ndarray, bounds: np.ndarray, place: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Shingles of windows by key: the number of each (-1 if the windows of one document hold it only), the windows that hold each number, in order, their places in them, and where each number's begin.

    They are sorted in parts of their hashes; beside the words, 12 bytes a shingle, 8 for one that several documents hold, and one part are in memory.
    """
    values = np.empty(int(place[-1]), np.uint64)
    for i in range(0, len(doc), 4096):
        upper = min(i + 4096, len(doc))
        own = words[bounds[i] : bounds[upper]]
        window = np.repeat(np.arange(i, upper), np.diff(bounds[i : upper + 1]))
        all_ = shingle_hashes(own.astype(np.uint64))
        start = np.flatnonzero(window[: len(all_)] == window[SHINGLE - 1 :])
        values[place[i] : place[upper]] = _mixed(all_[start] ^ _mixed(begins.astype(np.uint64)[window[start]], 11), 12)
    number = np.full(len(values), -1, np.int32)
    parts = 1 + len(values) // SORTED
    held, places, firsts, ids, at = [], [], [], 0, 0
    for part in range(parts):
        chosen = np.flatnonzero(values % np.uint64(parts) == part) if parts > 1 else np.arange(len(values))
        order = chosen[np.argsort(values[chosen], kind="stable")]
        v = values[order]
        w = (np.searchsorted(place, order, "right") - 1).astype(np.int32)
        opens = np.flatnonzero(np.r_[True, v[1:] != v[:-1]]) if len(v) else np.empty(0, np.int64)
        ends = np.r_[opens[1:], len(v)][: len(opens)]
        several = doc[w[opens]] != doc[w[ends - 1]]
        count = (ends - opens)[several]
        kept = np.repeat(several, ends - opens)
        number[order[kept]] = np.repeat(np.arange(ids, ids + len(count), dtype=np.int32), count)
        held.append(w[kept])
        places.append((order[kept] - place[w[kept]]).astype(np.int32))
        firsts.append(at + np.r_[0, np.cumsum(count)][:-1])
        ids, at = ids + len(count), at + int(count.sum())
    return number, np.concatenate(held), np.concatenate(places), np.concatenate(firsts).astype(np.int64)


def _unfit(mask: np.ndarray, n: int, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Stretches [from, to) of ``n`` shingles in which no two are both ends of a repeat with a word of ``mask``: those too short for a repeat, and those that hold no such word."""
    x = np.arange(max(1, n - width + 2))
    at = np.r_[-1, np.flatnonzero(mask), n + SHINGLE - 1]
    a, b = at[:-1] + 1, at[1:] - SHINGLE + 1
    long = b > a
    return np.r_[x, a[long]], np.r_[np.minimum(x + width - 1, n), b[long]]


def _met(key: np.ndarray, doc: np.ndarray, low: np.ndarray, fresh: np.ndarray, words: np.ndarray, bounds: np.ndarray, min_words: int, similarity: float) -> Iterator[tuple[int, int, int, int]]:
    """(doc, from, to, earlier doc) of repeats that hold fresh words, among windows sorted by (key, doc).

    The words and the fresh ones among them lie from ``bounds`` on. A repeat that holds a fresh
    word is a range of the window's shingles with this word, as long as a repeat and similar
    enough. What ranges are possible is first told from the shingles that any earlier window
    of the key holds, then, for some earlier windows at a time, from those that each one
    holds; those with a possible range are compared, until all words are covered that can be.
    """
    width = min_words - SHINGLE + 1
    size = np.maximum(np.diff(bounds) - SHINGLE + 1, 0)
    place = np.r_[0, np.cumsum(size)]
    opens = np.r_[True, key[1:] != key[:-1]]
    begins = np.flatnonzero(opens)[np.cumsum(opens) - 1]
    number, w, inside, first = _numbers(doc, begins, words, bounds, place)
    upto = np.r_[first[1:], len(w)]
    opens = np.r_[True, (key[1:] != key[:-1]) | (doc[1:] != doc[:-1])]
    earlier = np.flatnonzero(opens)[np.cumsum(opens) - 1]
    kind = np.int16 if len(size) and size.max() < 1 << 15 else np.int32
    inside = inside.astype(kind)
    slot = np.zeros(len(first) + 1, np.int32)  # the last one is that of shingles that no other document holds

    def spread(a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """All numbers of the ranges [a, b)."""
        ends = np.cumsum(b - a)
        return np.arange(ends[-1] if len(ends) else 0) + np.repeat(a - (ends - (b - a)), b - a)

    def holders(ids: np.ndarray, j: int, after: int) -> np.ndarray:
        """Windows of other documents before ``j`` and behind ``after`` that hold one of the shingles."""
        out = np.unique(w[spread(first[ids], upto[ids])])
        return out[np.searchsorted(out, after, "right") : np.searchsorted(out, earlier[j])]

    def partners(j: int, ids: np.ndarray, shared: np.ndarray, mask: np.ndarray, after: int) -> np.ndarray:
        """Windows behind ``after`` that may hold a repeat of ``j`` with a word of ``mask``: they share enough of it, and a shingle outside of any stretch in which no such repeat fits."""
        mine = np.unique(ids[shared])
        most = upto[mine] - first[mine]
        # whoever shares ``need`` of them shares one of all but the ``need`` - 1 most frequent
        need = max(1, int(np.ceil(similarity * width - 1e-9)) - (int(shared.sum()) - len(mine)))
        rare = mine[np.argsort(most, kind="stable")][: max(0, len(mine) - need + 1)]
        sums = np.zeros(len(ids) + 1, np.int64)
        np.cumsum(np.where(shared, (upto - first)[np.where(shared, ids, 0)], 0), out=sums[1:])
        x, y = _unfit(mask, len(ids), width)
        k = int(np.argmax(sums[y] - sums[x]))
        outside = shared.copy()
        outside[x[k] : y[k]] = False
        ends = np.unique(ids[outside])
        least = sorted((int((upto[m] - first[m]).sum()), i, m) for i, m in enumerate((rare, ends)))
        if least[0][0] >= earlier[j] - max(begins[j], after + 1):
            return np.arange(max(begins[j], after + 1), earlier[j])
        out = holders(least[0][2], j, after)
        if len(out) > 64 and least[1][0] < earlier[j] - begins[j]:
            out = np.intersect1d(out, holders(least[1][2], j, after), assume_unique=True)
        return out

    told = np.searchsorted(np.sort(w[first]), np.arange(len(doc) + 1))  # shingles of the windows before each one
    table, column, twice, owner = np.empty((0, 0), kind), np.full(len(first), -1, np.int32), {}, -1

    def looked_up(j: int, mine: np.ndarray, where: np.ndarray, tried: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Where windows of the key hold the shingles of ``j``, and whether they hold one of them twice, by a table (window, shingle) that stays for the next ones of the key."""
        nonlocal table, owner
        begin = int(begins[j])
        new = mine[column[mine] < 0]
        if owner != begin or len(twice[None]) + len(new) >= table.shape[1]:
            if owner >= 0:
                column[twice[None]] = -1
            owner, new = begin, mine
            twice.clear()
            twice[None] = []
            n = int(np.searchsorted(begins, begin, "right")) - begin
            table = np.full((n, min(TABLE // n, int(told[begin + n] - told[begin])) + 1), -1, kind)
        if len(new):
            column[new] = np.arange(len(twice[None]), len(twice[None]) + len(new)) + 1  # the first one stays empty
            twice[None] += new.tolist()
            at = spread(first[new], upto[new])
            ids_ = np.repeat(new, upto[new] - first[new])
            table[w[at] - begin, column[ids_]] = inside[at]
            again = np.flatnonzero((w[at[1:]] == w[at[:-1]]) & (ids_[1:] == ids_[:-1]))
            cuts = np.flatnonzero(ids_[again][1:] != ids_[again][:-1]) + 1
            twice.update((int(ids_[x[0]]), np.unique(w[at[x]]) - begin) for x in np.split(again, cuts) if len(x))
        several = np.zeros(len(table), bool)
        if len(twice) > 1:
            for x in mine.tolist():
                if x in twice:
                    several[twice[x]] = True
        return table[tried[:, None] - begin, np.r_[0, column[mine]][where]], several[tried - begin]

    # a repeat begins and ends with shared shingles, so its fresh words lie between the outermost ones
    leading = np.r_[doc[w[first]], np.iinfo(np.int64).max] if len(first) else np.array([np.iinfo(np.int64).max])
    sums = np.zeros(len(fresh) + 1, np.int32)
    np.cumsum(fresh, out=sums[1:])
    some = []
    for i in range(0, len(doc), 4096):
        upper = min(i + 4096, len(doc))
        window = np.repeat(np.arange(i, upper), size[i:upper])
        at = np.flatnonzero(leading[number[place[i] : place[upper]]] < doc[window])
        known = np.bincount(window[at] - i, minlength=upper - i)
        last = np.cumsum(known)
        good = np.flatnonzero(known >= max(1, similarity * width - 1e-9))
        a, b = (at[x] + place[i] - place[good + i] + bounds[good + i] for x in (last[good] - known[good], last[good] - 1))
        some.append(good[sums[b + SHINGLE] > sums[a]] + i)
    for j in np.concatenate(some).tolist() if some else []:
        a, b, own = int(place[j]), int(place[j + 1]), words[bounds[j] : bounds[j + 1]]
        ids = number[a:b]
        shared = leading[ids] < doc[j]
        mask = fresh[bounds[j] : bounds[j + 1]].astype(bool) & coverable(shared, width, similarity)
        if not mask.any():
            continue
        mine, mine_at = np.unique(ids[shared], return_inverse=True)
        others = partners(j, ids, shared, mask, -1)
        slot[mine] = np.arange(1, len(mine) + 1)
        where = np.zeros(b - a, np.int64)
        where[shared] = mine_at + 1
        known_to, done, step, uncovered = set(), 0, 16, int(mask.sum())
        while done < len(others) and mask.any():
            if mask.sum() < uncovered:
                uncovered = int(mask.sum())
                others, done = partners(j, ids, shared, mask, int(others[done - 1])), 0
            tried = others[done : done + step]
            done, step = done + step, min(2 * step, 4096)
            # many are looked up at once, where the key has room for a table
            far = len(tried) > 64 and TABLE // int(np.searchsorted(begins, begins[j], "right") - begins[j]) > len(mine)
            for part in np.split(tried, range(1024, len(tried), 1024)):
                if far:
                    at, several = looked_up(j, mine, where, part)
                else:
                    row = np.repeat(np.arange(len(part)), size[part])
                    theirs = spread(place[part], place[part + 1])
                    mark = slot[number[theirs]]
                    hit = np.flatnonzero(mark)
                    at = np.full((len(part), len(mine) + 1), -1, kind)
                    at[row[hit], mark[hit]] = theirs[hit] - place[part][row[hit]]
                    several = np.bincount(row[hit], minlength=len(part)) > (at >= 0).sum(axis=1)
                    at = at[:, where]
                left = np.flatnonzero(_may_gain(at, several, mask, width, similarity))
                while len(left):
                    gain = (at[left] >= 0) @ np.convolve(mask, np.ones(SHINGLE), "valid")
                    left, gained = left[np.argsort(-gain, kind="stable")], False
                    for k in left.tolist():
                        left = left[1:]
                        i = int(part[k])
                        marks = np.where(slot[number[place[i] : place[i + 1]]] > 0, number[place[i] : place[i + 1]], -1)
                        ends = np.flatnonzero(marks >= 0)
                        # windows that hold the same of this one's shingles at the same distances are compared once
                        alike = (int(ends[0]) if len(mine) < len(mine_at) or several[k] else 0, marks[ends[0] : ends[-1] + 1].tobytes())
                        if alike in known_to:
                            continue
                        known_to.add(alike)
                        for s, e in matching_spans(own, words[bounds[i] : bounds[i + 1]], min_words, similarity):
                            if mask[s:e].any():
                                mask[s:e], gained = False, True
                                yield int(doc[j]), int(low[j]) + s, int(low[j]) + e, int(doc[i])
                        if gained:
                            break
                    if gained:
                        left = np.sort(left[_may_gain(at[left], several[left], mask, width, similarity)]) if mask.any() else left[:0]
                if not mask.any():
                    break
        slot[mine] = 0


def _meet(min_words: int, similarity: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come sorted by (key, doc); the windows of some keys are held at a time, those of the last one until its end."""
        held: list[pa.RecordBatch] = []
        size = 0

        def settled(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            key, doc, low = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("key", "doc", "low"))
            words, bounds = _bytes(batch.column("words"))
            bits, begin = _bytes(batch.column("fresh"))
            bounds, sizes = bounds // 4, 8 * np.diff(begin)
            inside = np.arange(8 * len(bits)) - np.repeat(8 * begin[:-1], sizes) < np.repeat(np.diff(bounds), sizes)
            out = list(_met(key, doc, low, np.unpackbits(bits)[inside], words.view("<u4"), bounds, min_words, similarity))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*out, strict=True)], ["doc", "low", "high", "other"])

        for batch in batches:
            held.append(batch)
            size += batch.column("words").nbytes // 4
            key = batch.column("key").to_numpy(zero_copy_only=False)
            if size < MET or not len(key):
                continue
            whole = pa.concat_batches(held)
            key = whole.column("key").to_numpy(zero_copy_only=False)
            before = np.flatnonzero(key != key[-1])
            if len(before):
                end = int(before[-1]) + 1
                yield from settled(whole.slice(0, end))
                held[:] = [whole.slice(end)]
                size = held[0].column("words").nbytes // 4
        if sum(x.num_rows for x in held):
            yield from settled(pa.concat_batches(held))

    return run


def _passages(min_words: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Word hashes of the earlier document's side of every candidate, and of ``min_words`` words around it, where the sides may be out of step; candidates of one document whose sides overlap share them."""
        rows, sent = [], 0
        for whole in batches:
            for batch in slices(whole, "text"):
                for words, other, *lists in zip(map(_short, word_lists(batch.column("text"))), batch.column("other").to_pylist(), *(_lists(batch.column(c)) for c in ("doc", "shift", "low", "high")), strict=True):
                    sides = []
                    for doc, shift, low, high in zip(*lists, strict=True):
                        low -= min(min_words, low, low - shift)
                        sides.append((doc, low - shift, min(len(words), high - shift + SHINGLE + min_words), low))
                    sides.sort()
                    at = 0
                    while at < len(sides):
                        doc, begin, upto, _ = sides[at]
                        end = at + 1
                        while end < len(sides) and sides[end][0] == doc and sides[end][1] < upto:
                            upto = max(upto, sides[end][2])
                            end += 1
                        rows.append((doc, [x[3] for x in sides[at:end]], [x[1] - begin for x in sides[at:end]], [x[2] - begin for x in sides[at:end]], other, words[begin:upto].tobytes()))
                        sent += len(rows[-1][-1]) + 200 + 100 * (end - at)
                        at = end
                        if sent > SENT_BYTES:
                            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), _SENT, strict=True)], _SENT.names)
                            rows, sent = [], 0
        if rows:
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), _SENT, strict=True)], _SENT.names)

    return run


def _spread(n: int) -> np.ndarray:
    """0 to n - 1: the ends first, then the middles of what is left."""
    return np.argsort([i and n - 1 - i and -(i & -i) or -n for i in range(n)], kind="stable")


def find_spans(words: np.ndarray, asked: list[dict], min_words: int, similarity: float) -> list[tuple[int, int, int]]:
    """Verified (from, to, source) spans of a document's 32-bit word hashes against the words of its candidates.

    Sources go in order, the candidates of one from far apart to near. One is passed over where all words that
    it can cover lie already within one span each, of this source or a smaller one, which ``merged`` would name.
    """
    spans: list[tuple[int, int, int]] = []
    shingles, width = shingle_hashes(words.astype(np.uint64)), min_words - SHINGLE + 1
    covered = np.zeros((2, len(words)), bool)  # words of spans, and those that have the word before in one span with them
    sources: dict[int, list] = {}
    for x in asked:
        sources.setdefault(x["other"], []).append(x)
    for source, xs in sorted(sources.items()):
        texts = [np.frombuffer(x["words"], "<u4") for x in xs]
        tries = sorted((low, k, begin, end) for k, x in enumerate(xs) for low, begin, end in zip(x["low"], x["begin"], x["end"], strict=True))
        can = np.ones(len(words), bool)
        if len(tries) > FEW:
            can = coverable(np.isin(shingles, np.concatenate([shingle_hashes(x.astype(np.uint64)) for x in texts])), width, similarity)
        both = can[1:] & can[:-1]
        for i in _spread(len(tries)).tolist():
            low, k, begin, end = tries[i]
            upto = min(len(words), low + end - begin + min_words)
            if not (can[low:upto] & ~covered[0, low:upto]).any() and not (both[low : upto - 1] & ~covered[1, low + 1 : upto]).any():
                continue
            for a, b in matching_spans(words[low:upto], texts[k][begin:end], min_words, similarity):
                spans.append((low + a, low + b, source))
                covered[0, low + a : low + b] = covered[1, low + a + 1 : low + b] = True
    return spans


def _verify(min_words: int, similarity: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Verified spans (no key), and with key the windows that are to meet others: place, words and which of them no verified span covers; ``high`` 1 if there are none."""
        for whole in batches:
            for batch in slices(whole, "text"):
                out = []
                for short, doc, asked in zip(map(_short, word_lists(batch.column("text"))), batch.column("k").to_pylist(), _asked(batch.column("asked")), strict=True):
                    spans = merged(find_spans(short, [x for x in asked if x["words"] is not None], min_words, similarity))
                    out += [(None, doc, a, b, s, None, None) for a, b, s in spans]
                    fresh = np.ones(len(short), np.uint8)
                    for a, b, _ in spans:
                        fresh[a:b] = 0
                    for x in asked:
                        if x["words"] is None:
                            low, end = x["low"][0], min(len(short), x["end"][0] + SHINGLE)
                            if end - low >= min_words:
                                own = fresh[low:end]
                                out.append((x["begin"][0], doc, low, int(not own.any()), None, short[low:end].tobytes(), np.packbits(own).tobytes()))
                if out:
                    yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*out, strict=True), _FOUND, strict=True)], _FOUND.names)

    return run


def _merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Union of a document's overlapping spans."""
    for batch in batches:
        lists = [merged([(x["low"], x["high"], x["other"]) for x in spans]) for spans in batch.column("spans").to_pylist()]
        out = pa.array([[{"low": a, "high": b, "other": s} for a, b, s in spans] for spans in lists], pa.list_(pa.struct([("low", pa.int64()), ("high", pa.int64()), ("other", pa.int64())])))
        yield pa.RecordBatch.from_arrays([batch.column("doc"), out], ["doc", "spans"])


def _numbered(docs: DataFrame, id_col: str) -> tuple[DataFrame, DataFrame | None]:
    """Rows with a whole number ``__doc`` that orders them as the id does, and the table (id, number) where the id is no whole number."""
    if dict(docs.dtypes)[id_col] in ("tinyint", "smallint", "int", "bigint"):
        return docs.withColumn("__doc", F.col(id_col).cast("bigint")), None
    names = materialise(dense_ids(docs.where(F.col(id_col).isNotNull()).select(F.col(id_col).alias("__id")).distinct(), ["__id"]).withColumnRenamed("vid", "__doc"), "names")
    return docs.join(names, F.col(id_col) == F.col("__id"), "left").drop("__id"), names


def _spans(docs: DataFrame, text_col: str, min_words: int, similarity: float, hashes: int) -> DataFrame:
    """(doc, spans) of the documents that repeat something; ``docs`` has ``__doc``. Written to the shared folder.

    Candidates of a document are bounded by its own windows, so what is collected for one
    document is bounded by its length. The candidates, and what is found, are written on the
    way, so that of the windows, the texts and the words sent not all lie on the disks at once.
    """
    ship_package(docs.sparkSession)
    width = min_words - SHINGLE + 1
    rows = docs.where("__doc is not null").select(F.col("__doc").alias("k"), F.col(text_col).alias("text"))
    windows = rows.mapInArrow(_windows(hashes, width), _FIELDS)
    ordered = windows.repartition("key").sortWithinPartitions("key", "doc", "c")
    pairs = ordered.mapInArrow(_candidates(width), "doc bigint, shift bigint, low bigint, high bigint, other bigint, centre bigint")
    pairs = pairs.repartition("doc", "other").groupBy("doc", "other", "shift", "centre").agg(F.min("low").alias("low"), F.max("high").alias("high"))
    pairs = materialise(pairs, "pairs", free=True)
    bundles = pairs.where("doc <> other").sortWithinPartitions("other", "doc").mapInArrow(_bundles, "other bigint, doc array<bigint>, shift array<bigint>, low array<bigint>, high array<bigint>")
    sided = bundles.join(rows, bundles["other"] == rows["k"]).select("doc", "shift", "low", "high", "other", "text")
    sent = sided.mapInArrow(_passages(min_words), "doc bigint, low array<bigint>, begin array<bigint>, end array<bigint>, other bigint, words binary")
    meeting = pairs.where("doc = other").select("doc", F.struct(F.array("low").alias("low"), F.array("shift").alias("begin"), F.array("high").alias("end"), "other", F.lit(None).cast("binary").alias("words")).alias("x"))
    each = sent.select("doc", F.struct("low", "begin", "end", "other", "words").alias("x")).union(meeting)
    asked = each.groupBy("doc").agg(F.collect_list("x").alias("asked"))
    verified = rows.join(asked, rows["k"] == asked["doc"]).select("k", "text", "asked")
    found = materialise(verified.mapInArrow(_verify(min_words, similarity), "key bigint, doc bigint, low bigint, high bigint, other bigint, words binary, fresh binary"), "found", free=True)
    forget(pairs)
    late = found.where("key is not null")
    open_ = late.groupBy("key").agg(F.min("high").alias("covered"), F.min("doc").alias("first"), F.max("doc").alias("last")).where("covered = 0 and first < last").select("key")
    late = late.join(open_.hint("merge"), "key", "left_semi").select("key", "doc", "low", "words", "fresh").repartition("key").sortWithinPartitions("key", "doc", "low")
    spans = found.where("key is null").select("doc", "low", "high", "other").union(late.mapInArrow(_meet(min_words, similarity), "doc bigint, low bigint, high bigint, other bigint"))
    lists = spans.groupBy("doc").agg(F.collect_list(F.struct("low", "high", "other")).alias("spans"))
    out = materialise(lists.mapInArrow(_merge, "doc bigint, spans array<struct<low: bigint, high: bigint, other: bigint>>"), "spans", free=True)
    forget(found)
    return out


def repeated_passages(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_words: int = MIN_WORDS, similarity: float = SIMILARITY, hashes: int = HASHES) -> DataFrame:
    """(id, start_word, end_word, source_id): passages that an earlier document holds as well.

    Words are runs of other than ASCII white space, A-Z lower-cased; ``end_word`` is
    exclusive; "earlier" is a smaller id (of any type that can be ordered), so of every repeated
    passage the copy in the smallest id is not reported. Passages have ``min_words`` words at
    least and a Jaccard similarity of five-word shingles of ``similarity`` at least to an
    earlier passage whose words come in the same order, some changed, added or left out;
    overlapping finds are one. Null, empty and short texts, rows with a null id and empty
    tables have none. Rows with one id are looked up with each other's candidates, verified on
    their own text. Other columns are not used. The words of one text at a time (some 80 bytes each)
    are in a task's memory, so very long texts cost memory in proportion to their length.
    """
    numbered, names = _numbered(docs.select(id_col, text_col), id_col)
    spans = _spans(numbered, text_col, min_words, similarity, hashes).select("doc", F.inline("spans")).select("doc", F.col("low").cast("int").alias("start_word"), F.col("high").cast("int").alias("end_word"), F.col("other").alias("source"))
    if names is None:
        return spans.select(F.col("doc").alias(id_col), "start_word", "end_word", F.col("source").alias("source_id"))
    mine = names.select(F.col("__doc").alias("doc"), F.col("__id").alias(id_col))
    theirs = names.select(F.col("__doc").alias("source"), F.col("__id").alias("source_id"))
    return spans.join(mine, "doc").join(theirs, "source").select(id_col, "start_word", "end_word", "source_id")


def remove_repeated(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_words: int = MIN_WORDS, similarity: float = SIMILARITY, hashes: int = HASHES) -> DataFrame:
    """All rows and columns of ``docs``, the texts without the passages that ``repeated_passages`` reports.

    The table of spans holds only documents that repeat something. It grows with the rows, so
    it is joined by a shuffle at every size.
    """
    numbered, _ = _numbered(docs, id_col)
    spans = _spans(numbered, text_col, min_words, similarity, hashes)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            row = batch.column("row")
            texts = row.field(text_col).to_pylist()
            for i, spans in enumerate(batch.column("spans").to_pylist()):
                if texts[i] and spans:
                    texts[i] = without(texts[i], [(x["low"], x["high"], x["other"]) for x in spans])
            fields = [pa.array(texts, f.type) if f.name == text_col else row.field(f.name) for f in row.type]
            yield pa.RecordBatch.from_arrays(fields, [f.name for f in row.type])

    rows = numbered.select(F.col("__doc").alias("k"), F.struct(*docs.columns).alias("row"))
    joined = rows.join(spans.hint("merge"), rows["k"] == spans["doc"], "left").select("row", "spans")
    return joined.mapInArrow(run, docs.schema)
