"""Removal of repeated byte spans: a collection Burrows-Wheeler transform built column by column.

A byte goes if a string of WIDTH bytes that covers it also starts earlier. Only passages that may repeat need
sorting, and they are found first: in each window of WIDTH bytes the least hash of its GRAM-byte strings marks an
anchor, so equal windows have equal anchors, and anchors that occur once are done with. What is left are segments:
runs of windows with one anchor, grouped by it. Equal segments, by 128 bits of hash, collapse onto their first;
where a group still has different ones, the segments of many groups form a collection whose transform is built from their last column
to their first, one symbol of each segment a round, together with the common prefixes of neighbours in its order;
windows that are neighbours there with a common prefix of WIDTH bytes are the repeats. A collection holds some
COLLECTION bytes, so its transform and prefixes stay in memory and need no files.

A group of more than HOT segments is cut into parts of HOT; windows that are first in their part then meet again,
as 128-bit hashes, in an aggregate over all parts.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from liveindex.llm import common as C

WIDTH, GRAM = 100, 24
REACH = WIDTH - GRAM + 1
SIDE = (WIDTH - GRAM) // 2
#: Segments of one part of a group, and bytes of segments that one transform is built over.
HOT, COLLECTION = 4096, 1 << 21
_PIECE, _PLACE = 1 << 22, 24
C_BYTES = 1 << 21
_LEAST = -(1 << 63)


def segments(raw: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(text, first window, windows, anchor hash) of all runs of windows with one anchor, in order.

    The anchor of a window is its GRAM-byte string of the least hash, the leftmost if several are equal; what it
    is depends on the window's bytes alone."""
    out = []
    for base in range(0, max(0, raw.size - WIDTH + 1), _PIECE):
        data = raw[base : base + _PIECE + WIDTH - 1]
        total = np.zeros(data.size + 1, np.uint64)
        np.cumsum(C._BYTE[data] * C.powers(C._BASE, data.size), out=total[1:])
        n = data.size - GRAM + 1
        grams = C.mix((total[GRAM:] - total[:n]) * C.powers(C._INVERSE, n))
        least = ((grams >> np.uint64(_PLACE)) << np.uint64(_PLACE)) | np.arange(n, dtype=np.uint64)
        have = 1
        while have < REACH:
            step = min(have, REACH - have)
            least = np.minimum(least[: least.size - step], least[step:])
            have += step
        anchor = (least & np.uint64((1 << _PLACE) - 1)).astype(np.int64)
        # Windows that cross into the next text are none.
        at = np.arange(anchor.size) + base
        text = np.repeat(np.arange(len(off) - 1), np.diff(off))[at] if at.size else at
        good = at + WIDTH <= off[text + 1]
        new = np.ones(anchor.size, bool)
        new[1:] = (anchor[1:] != anchor[:-1]) | (text[1:] != text[:-1])
        heads = np.flatnonzero(good & new)
        stops = np.flatnonzero(good & np.append(new[1:] | ~good[1:], True)) if anchor.size else heads
        out.append((text[heads], at[heads] - off[text[heads]], stops - heads + 1, grams[anchor[heads]]))
    if not out:
        return (np.zeros(0, np.int64),) * 3 + (np.zeros(0, np.uint64),)
    return tuple(np.concatenate(c) for c in zip(*out, strict=True))


class _Ranks:
    """How often a symbol stands before a place of a transform, for many places at once."""

    STEP = 128

    def __init__(self, symbols: np.ndarray, kinds: int, cells: np.ndarray) -> None:
        self.rows = -(-symbols.size // self.STEP)
        padded = np.full((self.rows + 1) * self.STEP, 255, np.uint8)
        padded[: symbols.size] = symbols
        self.blocks = padded.reshape(-1, self.STEP)
        counts = np.bincount(cells[: symbols.size] + symbols, minlength=self.rows * kinds).reshape(-1, kinds)
        self.before = np.zeros((self.rows + 1, kinds), np.int32)
        np.cumsum(counts, axis=0, dtype=np.int32, out=self.before[1:])

    def of(self, symbol: np.ndarray, place: np.ndarray) -> np.ndarray:
        block, inside = place // self.STEP, place % self.STEP
        same = (self.blocks[block] == symbol[:, None]) & (np.arange(self.STEP) < inside[:, None])
        return self.before[block, symbol] + np.count_nonzero(same, axis=1)

    def last(self, symbol: np.ndarray, place: np.ndarray, rank: np.ndarray) -> np.ndarray:
        """Where a symbol stands last before a place, if it stands there rank > 0 times."""
        block = place // self.STEP
        low, high = np.zeros_like(block), block + 1
        same = self.before[block, symbol] < rank
        low[same] = block[same]
        while (open_ := high - low > 1).any():
            middle = (low + high) // 2
            less = self.before[middle, symbol] < rank
            low, high = np.where(open_ & less, middle, low), np.where(open_ & ~less, middle, high)
        is_it = (self.blocks[low] == symbol[:, None]) & (np.arange(self.STEP) < (place - low * self.STEP)[:, None])
        return low * self.STEP + self.STEP - 1 - np.argmax(is_it[:, ::-1], axis=1)

    def next(self, symbol: np.ndarray, place: np.ndarray, rank: np.ndarray) -> np.ndarray:
        """Where a symbol that stands at a place, and rank times before it, stands next, if it does."""
        block = place // self.STEP
        low, high = block.copy(), np.full_like(block, self.rows - 1)
        same = self.before[block + 1, symbol] > rank + 1
        high[same] = block[same]
        while (low < high).any():
            middle = (low + high) // 2
            reached = self.before[middle + 1, symbol] > rank + 1
            low, high = np.where(reached, low, np.minimum(middle + 1, high)), np.where(reached, middle, high)
        is_it = (self.blocks[low] == symbol[:, None]) & (np.arange(self.STEP) > (place - low * self.STEP)[:, None])
        return low * self.STEP + np.argmax(is_it, axis=1)


class _Least:
    """The least value over ranges of places, for many ranges at once."""

    STEP = 128

    def __init__(self, values: np.ndarray) -> None:
        rows = -(-values.size // self.STEP)
        padded = np.full(rows * self.STEP, 255, np.uint8)
        padded[: values.size] = values
        self.blocks = padded.reshape(-1, self.STEP)
        self.powers = [self.blocks.min(axis=1)]
        while (half := 1 << len(self.powers) - 1) * 2 <= rows:
            self.powers.append(np.minimum(self.powers[-1][:-half], self.powers[-1][half:]))

    def _inside(self, block: np.ndarray, low: np.ndarray, high: np.ndarray) -> np.ndarray:
        at = np.arange(self.STEP)
        return np.where((at > low[:, None]) & (at <= high[:, None]), self.blocks[block], np.uint8(255)).min(axis=1)

    def of(self, low: np.ndarray, high: np.ndarray) -> np.ndarray:
        """Of the places after low, up to high."""
        a, b = low // self.STEP, high // self.STEP
        out = self._inside(b, low - b * self.STEP, high - b * self.STEP)
        far = np.flatnonzero(a < b)
        if far.size:
            out[far] = np.minimum(out[far], self._inside(a[far], low[far] - a[far] * self.STEP, np.full(far.size, self.STEP)))
            n = b - a - 1
            for k, least in enumerate(self.powers):
                some = np.flatnonzero((n >> k) == 1)
                out[some] = np.minimum(out[some], np.minimum(least[a[some] + 1], least[b[some] - (1 << k)]))
        return out


def _longer(ranks: _Ranks, least: _Least, prefixes: np.ndarray, letter: np.ndarray, place: np.ndarray, rank: np.ndarray, total: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Common prefixes of new suffixes with those that will stand before and after them.

    Those begin with the same letter and go on with the suffixes of the nearest places of that letter; so the prefix
    is one longer than the least between the places, or nothing where the letter has no such place."""
    symbols = ranks.blocks.reshape(-1)
    out = np.zeros((2, letter.size), np.uint8)
    for side, have, beside in ((0, rank > 0, np.maximum(place - 1, 0)), (1, total[letter] > rank + 1, place + 1)):
        close = have & (symbols[beside] == letter)
        out[side, close] = prefixes[(place + side)[close]] + 1
        some = np.flatnonzero(have & ~close)
        if some.size:
            args = letter[some], place[some], rank[some]
            between = least.of(place[some], ranks.next(*args)) if side else least.of(ranks.last(*args), place[some])
            out[side, some] = between + 1
    return np.minimum(out[0], WIDTH), np.minimum(out[1], WIDTH)


def transform(data: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray, int, np.ndarray]:
    """Burrows-Wheeler transform of a collection: symbols, the bytes they stand for, the number of sequences, and of
    each place the common prefix with the one before, WIDTH at most.

    Symbol 0 ends each sequence, and ends are never equal. A round extends each sequence's suffix by one byte to the
    left: the place of the longer suffix follows from how many symbols before the shorter one's place are smaller or
    equal, and the new symbols and prefixes are merged with the old in one pass."""
    bytes_ = np.unique(data)
    symbol = (np.searchsorted(bytes_, data) + 1).astype(np.uint8)
    kinds, m = bytes_.size + 1, starts.size
    ends = starts + sizes
    cells = np.arange(m + data.size) // _Ranks.STEP * kinds
    out, prefixes = symbol[ends - 1].copy(), np.zeros(m, np.uint8)
    who, place = np.arange(m), np.arange(m)
    for done in range(1, int(sizes.max(initial=0)) + 1):
        keep = sizes[who] >= done
        who, place = who[keep], place[keep]
        letter = symbol[ends[who] - done]
        ranks = _Ranks(out, kinds, cells)
        totals = np.bincount(out, minlength=kinds)
        rank = ranks.of(letter, place)
        before, after = _longer(ranks, _Least(prefixes), prefixes, letter, place, rank, totals)
        totals[0] = m  # as many suffixes begin with an end as there are sequences
        smaller = np.concatenate(([0], np.cumsum(totals)[:-1]))
        place = smaller[letter] + rank
        front = np.where(sizes[who] > done, symbol[np.maximum(ends[who] - done - 1, 0)], 0).astype(np.uint8)
        merged = np.empty(out.size + who.size, np.uint8)
        old = np.ones(merged.size, bool)
        old[place] = False
        merged[place], merged[old] = front, out
        out, merged = merged, np.empty(merged.size + 1, np.uint8)
        merged[:-1][old] = prefixes
        merged[place + 1] = after
        merged[place] = before
        prefixes = merged[:-1]
    return out, bytes_, m, prefixes


def order(symbols: np.ndarray, m: int, sizes: np.ndarray) -> np.ndarray:
    """Rank of each sequence's suffixes, by following the transform from the ends: row = sequence, column = length."""
    by = np.argsort(symbols, kind="stable")
    by = by[int(np.count_nonzero(symbols == 0)) :]
    follow = np.zeros(symbols.size, np.int64)
    follow[by] = m + np.arange(by.size)
    most = int(sizes.max(initial=0))
    out = np.zeros((m, most + 1), np.int64)
    out[:, 0] = np.arange(m)
    for k in range(1, most + 1):
        out[:, k] = follow[out[:, k - 1]]
    return out


def _classes(data: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(sequence, window, class) of all windows, in the order of the transform; equal windows have one class."""
    within = np.concatenate([np.arange(a, a + n) for a, n in zip(starts.tolist(), sizes.tolist(), strict=True)])
    data, starts = data[within], np.cumsum(sizes) - sizes
    symbols, _, m, prefixes = transform(data, starts, sizes)
    rank = order(symbols, m, sizes)
    counts = sizes - WIDTH + 1
    sequence = np.repeat(np.arange(m), counts)
    window = np.arange(sequence.size) - np.repeat(np.cumsum(counts) - counts, counts)
    at = rank[sequence, sizes[sequence] - window]
    by = np.argsort(at)
    # Between equal windows all suffixes begin with them, so that the prefix with the one before tells them.
    return sequence[by], window[by], np.cumsum(prefixes[at[by]] < WIDTH) - 1


def _sides(anchor: np.ndarray, data: np.ndarray, off: np.ndarray, group: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of each segment, the first byte and the end of the part whose windows another of its group may hold.

    A window has SIDE bytes before its anchor or SIDE after it, so equal windows have equal bytes there. A segment
    whose sides no other has keeps nothing; one with a single shared side keeps the windows that reach over it."""
    sizes = np.diff(off)
    total = np.zeros(data.size + 1, np.uint64)
    np.cumsum(C._BYTE[data] * C.powers(C._BASE, data.size), out=total[1:])
    inverse = C.powers(C._INVERSE, data.size + 1)
    string = lambda a, n: C.mix((total[a + n] - total[a]) * inverse[a])
    count = sizes - GRAM + 1
    row = np.repeat(np.arange(sizes.size), count)
    at = np.arange(row.size) - np.repeat(np.cumsum(count) - count, count) + off[row]
    hit = np.flatnonzero(string(at, GRAM) == anchor.view(np.uint64)[row])
    # Windows of a segment have one anchor: the leftmost place of it that all of them reach.
    hit = hit[(at[hit] - off[row[hit]] >= sizes[row[hit]] - WIDTH) & (at[hit] - off[row[hit]] <= WIDTH - GRAM)]
    place = np.zeros(sizes.size, np.int64)
    place[row[hit][::-1]] = at[hit][::-1]
    ends = off[1:]
    low, high = off[:-1].copy(), ends.copy()
    shared = []
    for can, a in ((place - off[:-1] >= SIDE, place - SIDE), (ends - place - GRAM >= SIDE, place + GRAM)):
        side = np.zeros(sizes.size, bool)
        some = np.flatnonzero(can)
        key = C.mix(string(a[some], SIDE) ^ C.mix(group[some].view(np.uint64)))
        _, which, many = np.unique(key, return_inverse=True, return_counts=True)
        side[some] = many[which] > 1
        shared.append(side)
    left, right = shared
    # Without a shared left side only windows with fewer than SIDE bytes before the anchor are left, and so on.
    low = np.where(left, low, np.maximum(low, place - SIDE + 1))
    high = np.where(right, high, np.minimum(high, place + GRAM + SIDE - 1))
    none = ~(left | right) | (high - low < WIDTH)
    return np.where(none, 0, low), np.where(none, 0, high)


FOUND = "doc_id long, rid long, begin long, windows long, wa long, wb long"
_NAMES = ["doc_id", "rid", "begin", "windows", "wa", "wb"]


def repeats(group: np.ndarray, anchor: np.ndarray, doc: np.ndarray, begin: np.ndarray, hot: np.ndarray, data: np.ndarray, off: np.ndarray) -> tuple[list[np.ndarray], list[np.ndarray]]:
    """Which windows of the segments of some whole groups start earlier elsewhere in their group.

    Returns (segment, first window, windows) of runs to remove, and (segment, window) of windows of hot groups that
    are first among these segments."""
    sizes = np.diff(off)
    _, which, many = np.unique(group, return_inverse=True, return_counts=True)
    mixed = np.flatnonzero(many[which] > 1)
    lone = np.flatnonzero((many[which] == 1) & hot)
    runs = [np.zeros((0, 3), np.int64)]
    left = [np.stack((np.repeat(lone, n := sizes[lone] - WIDTH + 1), np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)), 1)]
    low, high = _sides(anchor, data, off, group) if mixed.size else (mixed, mixed)
    if mixed.size:
        # Windows of hot groups that no part of theirs shares still have to meet those of other parts.
        for a, b in ((off[:-1][mixed], np.where(high[mixed] > 0, low[mixed] + WIDTH - 1, off[1:][mixed])), (np.where(high[mixed] > 0, high[mixed] - WIDTH + 1, off[1:][mixed]), off[1:][mixed])):
            n = np.where(hot[mixed], np.maximum(b - a - WIDTH + 1, 0), 0)
            left.append(np.stack((np.repeat(mixed, n), np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n) + np.repeat(a - off[:-1][mixed], n)), 1))
        mixed = mixed[high[mixed] > 0]
    if mixed.size:
        sequence, window, kind = _classes(data, low[mixed], (high - low)[mixed])
        window = window + (low - off[:-1])[mixed][sequence]
        who = mixed[sequence]
        best = np.lexsort((begin[who] + window, doc[who], kind))
        head = np.ones(best.size, bool)
        head[1:] = kind[best][1:] != kind[best][:-1]
        source = best[np.maximum.accumulate(np.where(head, np.arange(best.size), 0))]
        other = (doc[who[best]] != doc[who[source]]) | (begin[who[best]] + window[best] != begin[who[source]] + window[source])
        removed = best[other]
        removed = removed[np.lexsort((window[removed], who[removed]))]
        w, s = window[removed], who[removed]
        start = np.ones(s.size, bool)
        start[1:] = (s[1:] != s[:-1]) | (w[1:] != w[:-1] + 1)
        heads = np.flatnonzero(start)
        runs.append(np.stack((s[heads], w[heads], np.diff(np.append(heads, s.size))), 1))
        stay = best[~other & hot[who[best]]]
        left.append(np.stack((who[stay], window[stay]), 1))
    return runs, left


def _found(parts: list[tuple]) -> pa.RecordBatch:
    group = np.concatenate([p[0] for p in parts])
    doc, rid, begin, hot = (np.concatenate([p[k] for p in parts]) for k in (1, 2, 3, 4))
    data = np.concatenate([p[5] for p in parts])
    off = np.concatenate(([0], np.cumsum(np.concatenate([p[6] for p in parts]))))
    runs, left = repeats(group, np.concatenate([p[7] for p in parts]), doc, begin, hot, data, off)
    runs, left = np.concatenate(runs), np.concatenate(left)
    at = off[left[:, 0]] + left[:, 1]
    wa = C.span_hashes(data, at, at + WIDTH)
    wb = C.span_hashes(data ^ 0xFF, at, at + WIDTH)
    s = np.concatenate((runs[:, 0], left[:, 0]))
    none = np.arange(s.size) < len(runs)
    hashes = [pa.array(np.concatenate((np.zeros(len(runs), np.int64), C.signed(w))), mask=none) for w in (wa, wb)]
    return pa.RecordBatch.from_arrays([pa.array(doc[s]), pa.array(rid[s]), pa.array(begin[s] + np.concatenate((runs[:, 1], left[:, 1]))), pa.array(np.concatenate((runs[:, 2], np.ones(len(left), np.int64)))), *hashes], names=_NAMES)


def _sorted_out(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Repeats of segments that come ordered by (anchor, part); whole groups are gathered up to COLLECTION bytes."""
    parts: list[tuple] = []
    held = 0
    for batch in batches:
        if not batch.num_rows:
            continue
        anchor, part = (batch.column(k).to_numpy() for k in ("anchor", "part"))
        group = C.signed(C.mix(anchor.view(np.uint64)) + part.astype(np.uint64))
        raw, off = C.flat(batch.column("bytes").cast(pa.large_binary()).view(pa.large_string()))
        columns = [group, *(batch.column(k).to_numpy() for k in ("doc_id", "rid", "begin")), batch.column("hot").to_numpy(zero_copy_only=False)]
        at = 0
        while at < group.size:
            room = max(0, COLLECTION - held)
            end = min(group.size, max(at + 1, int(np.searchsorted(off, off[at] + room, side="right")) - 1))
            while end < group.size and group[end] == group[end - 1]:
                end += 1
            if held and held >= COLLECTION and group[at] != parts[-1][0][-1]:
                yield _found(parts)
                parts, held = [], 0
                continue
            if held and group[at] == parts[-1][0][-1]:  # the rest of an open group, whatever its size
                end = at + int(np.argmax(np.append(group[at:] != group[at], True)))
            parts.append((*(c[at:end] for c in columns), raw[off[at] : off[end]], np.diff(off[at : end + 1]), anchor[at:end]))
            held += int(off[end] - off[at])
            at = end
    if parts:
        yield _found(parts)


ANCHORED = "deal long, again boolean, anchor long, content long, doc_id long, rid long, place long"


def _again(anchor: np.ndarray, content: np.ndarray, doc: np.ndarray, place: np.ndarray) -> np.ndarray:
    """Which segments repeat an earlier one of the same slice: those go nowhere near their anchor's others, so that a
    passage of many documents meets itself once a slice."""
    out = np.zeros(anchor.size, bool)
    key = C.mix(anchor.view(np.uint64) ^ C.mix(content.view(np.uint64)))
    _, which, times = np.unique(key, return_inverse=True, return_counts=True)
    some = np.flatnonzero(times[which] > 1)
    order = some[np.lexsort((place[some], doc[some], content[some], anchor[some]))]
    new = np.ones(order.size, bool)
    new[1:] = (anchor[order][1:] != anchor[order][:-1]) | (content[order][1:] != content[order][:-1])
    lead = order[np.maximum.accumulate(np.where(new, np.arange(order.size), 0))]
    out[order] = (doc[order] != doc[lead]) | (place[order] != place[lead])
    return out


def _anchored(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for piece in C.pieces(batch, "text"):
            raw, off = C.flat(piece.column("text"))
            text, begin, windows, anchor = segments(raw, off)
            content = C.signed(C.span_hashes(raw, off[text] + begin, off[text] + begin + windows + WIDTH - 1))
            anchor, place = C.signed(anchor), begin << 8 | windows
            doc, rid = (piece.column(c).to_numpy()[text] for c in ("doc_id", "rid"))
            again = _again(anchor, content, doc, place)
            deal = np.where(again, C.signed(C.mix(doc.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + place.astype(np.uint64))), anchor)
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in (deal, again, anchor, content, doc, rid, place)], names=["deal", "again", "anchor", "content", "doc_id", "rid", "place"])


SHARED = "anchor long, part long, doc_id long, rid long, place long"


def _shared(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """From segments ordered by (anchor, content, doc_id, place): those that repeat the first of their content,
    with a null part, which holds for those that come as repeats already; and the first of each content whose anchor
    has another content, with the part it falls in.

    Content and anchor together are 128 bits of hash. What the next batch needs is one row: the last first."""
    lead = None  # anchor, content, doc_id, rid, place, number of its content within the anchor
    for batch in batches:
        repeat = batch.column("again").to_numpy(zero_copy_only=False)
        columns = [batch.column(c).to_numpy() for c in ("anchor", "content", "doc_id", "rid", "place")]
        if repeat.any():
            late = [c[repeat] for c in columns]
            yield _rows([(late[0], np.full(late[0].size, -1), *late[2:])])
            columns = [c[~repeat] for c in columns]
        anchor, content, doc, rid, place = columns
        if not anchor.size:
            continue
        new = np.ones(anchor.size, bool)
        new[1:] = (anchor[1:] != anchor[:-1]) | (content[1:] != content[:-1])
        if lead is not None:
            new[0] = lead[0] != anchor[0] or lead[1] != content[0]
        heads = np.flatnonzero(new)
        source = np.maximum.accumulate(np.where(new, np.arange(anchor.size), -1))
        lead_doc, lead_place = (np.where(source >= 0, column[source], lead[k] if lead is not None else 0) for column, k in ((doc, 2), (place, 4)))
        again = np.flatnonzero(~new & ((doc != lead_doc) | (place != lead_place)))
        out = [(anchor[again], np.full(again.size, -1), doc[again], rid[again], place[again])]
        if heads.size:
            columns = [c[heads] for c in (anchor, content, doc, rid, place)]
            count = np.zeros(heads.size, np.int64)
            if lead is not None:
                columns = [np.concatenate(([v], c)) for v, c in zip(lead, columns, strict=False)]
                count = np.concatenate(([lead[5]], count))
            same = np.append(False, columns[0][1:] == columns[0][:-1])
            index = np.arange(same.size)
            index = index - np.maximum.accumulate(np.where(same, 0, index))
            index[: int(np.argmin(np.append(same[1:], False))) + 1] += count[0]
            shared = (index > 0) | np.append(same[1:], False)
            pick = np.flatnonzero(shared[:-1])
            out.append((columns[0][pick], index[pick] // HOT, *(c[pick] for c in columns[2:])))
            lead = (*(c[-1] for c in columns), int(index[-1]))
        yield _rows(out)
    if lead is not None and lead[5] > 0:
        yield _rows([(np.array([lead[0]]), np.array([lead[5] // HOT]), *(np.array([v]) for v in lead[2:5]))])


def _rows(parts: list[tuple]) -> pa.RecordBatch:
    anchor, part, doc, rid, place = (np.concatenate(c).astype(np.int64) for c in zip(*parts, strict=True))
    return pa.RecordBatch.from_arrays([pa.array(anchor), pa.array(part, mask=part < 0), pa.array(doc), pa.array(rid), pa.array(place)], names=["anchor", "part", "doc_id", "rid", "place"])


def _zipped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Texts packed for the shuffle."""
    for batch in batches:
        for piece in C.pieces(batch, "text"):
            packed = [pa.compress(t.as_buffer(), "zstd", asbytes=True) for t in piece.column("text")]
            yield pa.RecordBatch.from_arrays([piece.column("doc_id"), piece.column("rid"), pc.binary_length(piece.column("text")).cast(pa.int64()), pa.array(packed, pa.binary())], names=["doc_id", "rid", "size", "packed"])


def _unpacked(batch: pa.RecordBatch) -> Iterator[tuple[int, bytes]]:
    """(row, text) of a batch, one at a time."""
    for k, (data, size) in enumerate(zip(batch.column("packed"), batch.column("size").to_pylist(), strict=True)):
        yield k, pa.decompress(data.as_buffer(), size, "zstd", asbytes=True)


def _cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        found = batch.column("found")
        held, size = [], 0
        for k, text in _unpacked(batch):
            rows = found[k].values
            place = rows.field("place").to_numpy()
            begin, windows = place >> 8, place & 0xFF
            pieces = [text[b : b + n + WIDTH - 1] for b, n in zip(begin.tolist(), windows.tolist(), strict=True)]
            held.append(pa.RecordBatch.from_arrays([rows.field("anchor"), rows.field("part"), rows.field("hot"), pa.repeat(batch.column("doc_id")[k], len(pieces)), pa.repeat(batch.column("rid")[k], len(pieces)), pa.array(begin), pa.array(pieces, pa.binary())], names=["anchor", "part", "hot", "doc_id", "rid", "begin", "bytes"]))
            size += sum(map(len, pieces))
            if size > C_BYTES:
                yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]
                held, size = [], 0
        if held:
            yield from pa.Table.from_batches(held).combine_chunks().to_batches()


def covered(begin: np.ndarray, windows: np.ndarray) -> np.ndarray:
    """Maximal (begin, end) byte runs covered by windows that begin in the given runs."""
    by = np.argsort(begin, kind="stable")
    low, high = begin[by], begin[by] + windows[by] + WIDTH - 1
    high = np.maximum.accumulate(high)
    new = np.ones(low.size, bool)
    new[1:] = low[1:] > high[:-1]
    heads = np.flatnonzero(new)
    return np.stack((low[heads], high[np.append(heads[1:], low.size) - 1]), 1)


def _removed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        out: list[tuple] = []
        for k, text in _unpacked(batch):
            place = batch.column("runs")[k].values.to_numpy()
            spans = covered(place >> 8, place & 0xFF)
            at, kept = 0, []
            for low, high in spans.tolist():
                kept.append(text[at:low])
                at = high
            kept.append(text[at:])
            rest = b"".join(kept)
            out.append((len(rest), len(spans), hashlib.sha256(rest).hexdigest(), rest, spans[:, 0].tolist(), spans[:, 1].tolist()))
        if out:
            n, spans, digest, rest, low, high = zip(*out, strict=True)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("rid"), pa.array(n, pa.int64()), pa.array(spans, pa.int64()), pa.array(digest), pa.array(rest, pa.binary()), pa.array(low, pa.list_(pa.int64())), pa.array(high, pa.list_(pa.int64()))], names=["doc_id", "rid", "n_kept", "n_spans", "kept_sha256", "kept", "span_begins", "span_ends"])


def remove_repeats(df: DataFrame, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept_sha256, kept, span_begins, span_ends), a row for each row of df.

    kept: the bytes that stay, as binary (a character may lose its first bytes); null where nothing goes, as then
    all of them stay. Texts are compared as UTF-8 and whole, null as empty; texts of fewer than WIDTH bytes lose
    nothing. A row without doc_id comes before all others. Rows of one doc_id are versions of one document: equal
    rows start nowhere earlier than each other and so keep what either keeps. An empty table gives an empty result;
    other columns play no part.
    """
    spark = df.sparkSession
    rows = C.narrow(df, doc_id=doc_id, text=text).select(F.coalesce(F.col("doc_id").cast("long"), F.lit(_LEAST)).alias("doc_id"), F.coalesce(F.col("text"), F.lit("")).alias("text"))
    # Where a doc_id repeats, the text tells its versions apart.
    repeated = not rows.groupBy("doc_id").count().where("count > 1").isEmpty()
    rows = rows.withColumn("rid", F.xxhash64("text") if repeated else F.lit(0).cast("long"))
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    long = rows.where(F.octet_length("text") >= WIDTH)
    anchored = long.mapInArrow(_anchored, ANCHORED)
    shared = C.saved(anchored.repartition(parts, "deal").drop("deal").sortWithinPartitions("anchor", "content", "doc_id", "place").mapInArrow(_shared, SHARED), "shared-anchors")
    large = shared.where("part > 0").select("anchor").distinct()
    split = not large.isEmpty()
    marked = shared.where("part is not null").withColumn("hot", F.lit(False))
    if split:
        marked = marked.drop("hot").join(large.withColumn("hot", F.lit(True)), "anchor", "left").withColumn("hot", F.coalesce("hot", F.lit(False)))
    mine = marked.groupBy("doc_id", "rid").agg(F.collect_list(F.struct("anchor", "part", "hot", "place")).alias("found"))
    packed = "doc_id long, rid long, size long, packed binary"
    texts = long.mapInArrow(_zipped, packed)
    if repeated:
        texts = texts.dropDuplicates(["doc_id", "rid"])
    cut = texts.join(mine, ["doc_id", "rid"]).mapInArrow(_cut, "anchor long, part long, hot boolean, doc_id long, rid long, begin long, bytes binary")
    found = C.saved(cut.repartition(parts, "anchor", "part").sortWithinPartitions("anchor", "part").mapInArrow(_sorted_out, FOUND), "repeats")
    runs = shared.where("part is null").select("doc_id", "rid", "place").unionAll(found.where("wa is null").select("doc_id", "rid", (F.shiftleft("begin", 8) + F.col("windows")).alias("place")))
    if split:
        first = found.where("wa is not null")
        least = first.groupBy("wa", "wb").agg(F.min(F.struct("doc_id", "begin")).alias("least"))
        runs = runs.unionAll(first.join(least, ["wa", "wb"]).where(F.struct("doc_id", "begin") != F.col("least")).select("doc_id", "rid", (F.shiftleft("begin", 8) + F.col("windows")).alias("place")))
    runs = runs.groupBy("doc_id", "rid").agg(F.collect_list("place").alias("runs"))
    edited = texts.join(runs, ["doc_id", "rid"]).mapInArrow(_removed, "doc_id long, rid long, n_kept long, n_spans long, kept_sha256 string, kept binary, span_begins array<long>, span_ends array<long>")
    whole = rows.select("doc_id", "rid", F.octet_length("text").cast("long").alias("n_bytes"), F.sha2("text", 256).alias("sha"))
    out = whole.join(edited, ["doc_id", "rid"], "left")
    return out.select(
        F.when(F.col("doc_id") != _LEAST, F.col("doc_id")).alias("doc_id"), "n_bytes", (F.col("n_bytes") - F.coalesce("n_kept", "n_bytes")).alias("n_removed"), F.coalesce("n_spans", F.lit(0)).cast("long").alias("n_spans"),
        F.coalesce("kept_sha256", "sha").alias("kept_sha256"), "kept", "span_begins", "span_ends")
