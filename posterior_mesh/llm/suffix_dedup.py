"""Removal of long strings that repeat anywhere, by suffix arrays and their common-prefix interval trees.

Wherever two texts share ``LEAST`` bytes, both hold the smallest hash of the shared window's 32-byte
grams, so every repeat shows among texts that share such an anchor. Anchors that occur once, and texts
that are wholly alike, never travel. Around the others, the bytes that a shared window could cover are
cut out; a task builds an enhanced suffix array over many such contexts, scans it with a stack for
intervals of common prefixes, and keeps those whose occurrences differ in the byte before: the maximal
repeats, each with all its occurrences. An anchor in very many contexts is dealt to several tasks; what
these don't find among their own is compared across them by hashes of windows.

Defined cases: null is empty; texts under ``LEAST`` bytes lose nothing; equal texts of that length lose
everything; strings are judged on the input alone; repeated rows are texts of their own and so repeat each
other; no rows give none. With a limit in words, a repeat counts the words that lie in it whole; words are
set apart by ASCII white space, as in the join of sets.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import cut, forget, give_back, load, marked, mix, sift, slices, utf8

LEAST, GRAM = 400, 32
#: Bytes of contexts in one suffix array, and contexts of one anchor in one task, at most.
ARRAY_BYTES, PART = 1 << 20, 2000
#: Ranges that the hashes of an anchor in several parts are dealt into.
RANGES = 16
#: Words of the shortest passage that the pipeline's stage cuts out, besides strings of LEAST bytes: over 50.
PASSAGE = 51
#: Bytes of the shortest passage that the report of strings of LEAST bytes also tells, by its words.
FINE = 250

SPACE = np.zeros(256, bool)
SPACE[[32, 9, 10, 11, 12, 13]] = True

COEFFICIENTS = mix(np.arange(1, 129, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)) | np.uint64(1)


def words_at(data: np.ndarray) -> np.ndarray:
    """The eight bytes from each place on, as a number; ``data`` ends in seven bytes more."""
    return np.ndarray(max(0, len(data) - 7), "<u8", data, strides=(1,)) if len(data) > 7 else np.zeros(0, np.uint64)


def sliding(values: np.ndarray, width: int, what) -> np.ndarray:
    """``what`` (minimum or maximum) over every run of ``width`` values, by running blocks."""
    n = len(values)
    if n < width:
        return values[:0]
    full = np.concatenate((values, np.repeat(values[-1:], -n % width))).reshape(-1, width)
    before = what.accumulate(full, axis=1).ravel()
    after = what.accumulate(full[:, ::-1], axis=1)[:, ::-1].ravel()
    return what(after[: n - width + 1], before[width - 1 : n])


def thinned(place: np.ndarray, small: np.ndarray, text: np.ndarray, width: int) -> np.ndarray:
    """Runs of equal hashes, in texts that repeat themselves at short distance, need few of their places."""
    if len(place) > 2:
        same = (small[place[1:]] == small[place[:-1]]) & (text[1:] == text[:-1]) & (np.diff(place) < width)
        border = np.flatnonzero(np.diff(np.concatenate(([0], same, [0])).astype(np.int8)))
        keep = np.ones(len(place), bool)
        for a, b in border.reshape(-1, 2).tolist():
            if b - a > 1:
                last = place[a]
                for k in range(a + 1, b):
                    if place[k + 1] - last <= width:
                        keep[k] = False
                    else:
                        last = place[k]
        place = place[keep]
    return place


def anchors(data: np.ndarray, offsets: np.ndarray, least: int, gram: int = GRAM) -> tuple[np.ndarray, np.ndarray]:
    """Places of anchors in the joined texts, in order, and their hashes: every ``least`` bytes of a text hold one."""
    n, width = len(data), least - gram + 1
    if n < least:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    words = words_at(np.concatenate((data, np.zeros(8, np.uint8))))
    hashes = np.zeros(n - gram + 1, np.uint64)
    for k in range(0, gram, 8):
        hashes += words[k : k + len(hashes)] * COEFFICIENTS[k]
    hashes = mix(hashes)
    small = (hashes >> np.uint64(32)).astype(np.uint32) | np.uint32(1)
    lowest = sliding(small, width, np.minimum)
    for end in offsets[1:-1]:  # windows over the end of a text choose nothing
        lowest[max(0, end - least + 1) : end] = 0
    padded = np.concatenate((np.zeros(width - 1, np.uint32), lowest, np.zeros(width - 1, np.uint32)))
    place = np.flatnonzero(sliding(padded, width, np.maximum) == small)
    place = thinned(place, small, np.searchsorted(offsets, place, "right"), width)
    return place, hashes[place]


def different(hashes: np.ndarray, low: np.ndarray, high: np.ndarray) -> np.ndarray:
    """Which of the anchors aren't of a hash and a context that one before them has; a context doesn't repeat itself."""
    order = np.lexsort((high, low, hashes))
    new = np.ones(len(order), bool)
    new[1:] = np.any([x[order[1:]] != x[order[:-1]] for x in (hashes, low, high)], axis=0) if len(order) > 1 else True
    return np.sort(order[new])


def words_in(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Where the words of the joined texts begin and end."""
    inside = ~SPACE[data]
    begins = inside.copy()
    begins[1:] &= ~inside[:-1]
    heads = offsets[:-1][offsets[:-1] < len(data)]
    begins[heads] |= inside[heads]
    ends = inside.copy()
    ends[:-1] &= ~inside[1:] | begins[1:]
    return np.flatnonzero(begins), np.flatnonzero(ends) + 1


def word_anchors(data: np.ndarray, offsets: np.ndarray, words: int, gram: int = GRAM) -> tuple[np.ndarray, ...]:
    """Hashes of anchors, their texts, and where the contexts of so many words around them begin and end.

    Anchors stand where words begin; every run of ``words`` words holds one, with all the bytes that are hashed:
    m words have 2 m - 1 bytes at least.
    """
    begins, ends = words_in(data, offsets)
    n, width = len(begins), words - (gram + 2) // 2 + 1
    if width < 1:
        raise ValueError(f"{words} words may be shorter than what is hashed")
    if n < words:
        return np.zeros(0, np.uint64), *(np.zeros(0, np.int64) for _ in range(3))
    text = np.searchsorted(offsets, begins, "right") - 1
    at = words_at(np.concatenate((data, np.zeros(gram + 8, np.uint8))))
    hashes = np.zeros(n, np.uint64)
    for k in range(0, gram, 8):
        hashes += at[begins + k] * COEFFICIENTS[k]
    hashes = mix(hashes)
    small = (hashes >> np.uint64(32)).astype(np.uint32) | np.uint32(1)
    lowest = sliding(small, width, np.minimum)[: n - words + 1]
    lowest[text[words - 1 :] != text[: n - words + 1]] = 0
    padded = np.concatenate((np.zeros(width - 1, np.uint32), lowest, np.zeros(words - 1, np.uint32)))
    place = np.flatnonzero(sliding(padded, width, np.maximum) == small)
    place = thinned(place, small, text[place], width)
    first, past = np.searchsorted(text, text[place]), np.searchsorted(text, text[place], "right")
    return hashes[place], text[place], begins[np.maximum(place - width + 1, first)], ends[np.minimum(place + words, past) - 1]


def long_enough(longest: np.ndarray, data: np.ndarray, words: int) -> np.ndarray:
    """Of the strings of these lengths, from their places on, those that hold so many words whole, without what they hold of others."""
    begins, ends = words_in(data, np.array([0, len(data)]))
    starts = np.flatnonzero(longest)
    first, past = np.searchsorted(begins, starts), np.searchsorted(ends, starts + longest[starts], "right")
    out = np.zeros(len(data), np.int64)
    kept = past - first >= words
    np.maximum.at(out, begins[first[kept]], ends[past[kept] - 1] - begins[first[kept]])
    return out


def word_windows(data: np.ndarray, words: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """A hash of every so many words, and where they begin and end."""
    begins, ends = words_in(data, np.array([0, len(data)]))
    begins, ends, raw = begins[: max(0, len(begins) - words + 1)], ends[words - 1 :], data.tobytes()
    return np.array([short_digest(raw[a:b]) for a, b in zip(begins, ends)], np.uint64), begins, ends


def short_digest(raw: bytes) -> int:
    return int.from_bytes(hashlib.blake2b(raw, digest_size=8).digest(), "little")


def anchor_table(docs: DataFrame, least: int, words: int = 0, fine: int = 0) -> DataFrame:
    """digest, n, copies, and of each different text the hashes of anchors, hashes of their contexts, and where these begin and end."""
    if words:
        return word_anchor_table(docs, words)
    fine = fine or least
    # the window in the middle of a string holds an anchor, from which no end of the string is farther than this
    side = -((fine - least) // 2) + fine - GRAM
    count = (2 * side + GRAM) // 8

    def run(batches):
        with np.errstate(over="ignore"):
            for batch in slices(batches):
                data, offsets = utf8(batch.column(0))
                place, hashes = anchors(data, offsets, fine)
                text = np.searchsorted(offsets, place, "right") - 1
                low, high = np.maximum(place - side, offsets[text]), np.minimum(place + GRAM + side, offsets[text + 1])
                own = different(hashes, low, high)
                place, hashes, text, low, high = (x[own] for x in (place, hashes, text, low, high))
                context = np.zeros(len(place), np.uint64)
                whole = np.flatnonzero(high - low == 2 * side + GRAM)
                words = words_at(np.concatenate((data, np.zeros(8, np.uint8))))
                steps, tail = 8 * np.arange(count), 2 * side + GRAM - 8
                for at in range(0, len(whole), 4096):
                    some = whole[at : at + 4096]
                    context[some] = mix((mix(words[low[some][:, None] + steps]) * COEFFICIENTS[:count]).sum(axis=1, dtype=np.uint64) + mix(words[low[some] + tail]) * COEFFICIENTS[127])
                for k in np.flatnonzero(high - low != 2 * side + GRAM):
                    context[k] = int.from_bytes(hashlib.blake2b(data[low[k] : high[k]].tobytes(), digest_size=8).digest(), "little")
                first = np.searchsorted(text, np.arange(len(offsets)))
                lists = [pa.ListArray.from_arrays(pa.array(first, pa.int32()), pa.array(x)) for x in (hashes.view(np.int64), context.view(np.int64), (low - offsets[text]).astype(np.int32), (high - offsets[text]).astype(np.int32))]
                digests = [hashlib.md5(data[a:b].tobytes()).digest() for a, b in zip(offsets[:-1], offsets[1:])]
                yield pa.RecordBatch.from_arrays([pa.array(digests, pa.binary()), pa.array(np.diff(offsets)), *lists], ["digest", "n", "h", "c", "low", "high"]).filter(pa.array(np.diff(offsets) >= fine))

    return table_of(docs, run)


def table_of(docs: DataFrame, run) -> DataFrame:
    found = docs.select(F.coalesce(F.col("text"), F.lit("")).cast("binary").alias("text")).mapInArrow(run, "digest binary, n long, h array<long>, c array<long>, low array<int>, high array<int>")
    return found.groupBy("digest").agg(F.count("*").alias("copies"), *(F.first(c).alias(c) for c in ("n", "h", "c", "low", "high")))


def word_anchor_table(docs: DataFrame, words: int) -> DataFrame:
    def run(batches):
        with np.errstate(over="ignore"):
            for batch in slices(batches):
                data, offsets = utf8(batch.column(0))
                hashes, text, low, high = word_anchors(data, offsets, words)
                own = different(hashes, low, high)
                hashes, text, low, high = (x[own] for x in (hashes, text, low, high))
                raw = data.tobytes()
                context = np.array([short_digest(raw[a:b]) for a, b in zip(low.tolist(), high.tolist())], np.uint64)
                first = np.searchsorted(text, np.arange(len(offsets)))
                lists = [pa.ListArray.from_arrays(pa.array(first, pa.int32()), pa.array(x)) for x in (hashes.view(np.int64), context.view(np.int64), (low - offsets[text]).astype(np.int32), (high - offsets[text]).astype(np.int32))]
                digests = [hashlib.md5(raw[a:b]).digest() for a, b in zip(offsets[:-1], offsets[1:])]
                enough = np.diff(np.searchsorted(words_in(data, offsets)[0], offsets)) >= words
                yield pa.RecordBatch.from_arrays([pa.array(digests, pa.binary()), pa.array(np.diff(offsets)), *lists], ["digest", "n", "h", "c", "low", "high"]).filter(pa.array(enough))

    return table_of(docs, run)


class SuffixArray:
    """Suffixes of several byte strings, with the common prefixes of neighbours; nothing goes over a string's end."""

    def __init__(self, strings: list[bytes], least: int):
        self.least = least
        # UTF-8 has no byte over 0xF4, so that 0 is free for ends, below all bytes
        self.text = np.frombuffer(b"\0".join([b"", *strings, b""]), np.uint8).copy()
        lengths = np.array([len(s) for s in strings], np.int64)
        self.start = np.concatenate(([1], 1 + np.cumsum(lengths + 1)))[: len(strings)]
        self.end = self.start + lengths
        body = np.zeros(len(self.text), bool)
        for a, b in zip(self.start, self.end):
            body[a:b] = True
        self.text[body] += 1
        n = len(self.text)
        key = np.ndarray(n, ">u8", np.concatenate((self.text, np.zeros(8, np.uint8))), strides=(1,)).astype(np.uint64)
        order = np.argsort(key)
        slots, key = np.arange(n), key[order]
        rank, self.ranks, width, longest = np.zeros(n, np.int32), [], 8, max(lengths, default=0)
        while True:
            # a suffix's rank is the first place of those that begin alike; only what isn't alone is put in order again
            new = np.ones(len(slots), bool)
            np.not_equal(key[1:], key[:-1], out=new[1:])
            rank[order[slots]] = slots[new][np.cumsum(new) - 1]
            self.ranks.append(rank.copy())
            alone = new & np.append(new[1:], True)
            slots = slots[~alone]
            if width >= longest or not len(slots):
                break
            some = order[slots]
            key = rank[some].astype(np.int64) << 32
            inside = some + width < n
            key[inside] |= rank[some[inside] + width]
            by = np.argsort(key)
            order[slots], key = some[by], key[by]
            width *= 2
        self.owner = np.repeat(np.arange(len(strings)), lengths + 1)
        self.owner = np.concatenate(([0], self.owner))[:n]
        order = order[(self.end[self.owner[order]] - order >= least) & (order > 0)]
        self.order = order
        self.common = self._common(order[:-1], order[1:]) if len(order) > 1 else np.zeros(0, np.int64)

    def _common(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Lengths of the common prefixes of suffixes, by the ranks of halving widths; 0 may stand for a length that is too short."""
        whole, step = np.zeros(len(a), np.int64), min(len(self.ranks), self.least.bit_length() - 3) - 1
        if step >= 0:  # what differs within a width below the least length doesn't matter
            near = np.flatnonzero(self.ranks[step][a] == self.ranks[step][b])
            a, b = a[near], b[near]
        else:
            near = slice(None)
        whole[near] = self._exact(a, b)
        return whole

    def _exact(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        most = np.minimum(self.end[self.owner[a]] - a, self.end[self.owner[b]] - b)
        out, n = np.zeros(len(a), np.int64), len(self.text)
        for k in range(len(self.ranks) - 1, -1, -1):
            rank = self.ranks[k]
            for _ in range(2 if k == len(self.ranks) - 1 else 1):
                alike = rank[np.minimum(a + out, n - 1)] == rank[np.minimum(b + out, n - 1)]
                out += alike * (8 << k)
        for _ in range(7):
            alike = (self.text[np.minimum(a + out, n - 1)] == self.text[np.minimum(b + out, n - 1)]) & (out < most)
            out += alike
            if not alike.any():
                break
        return np.minimum(out, most)

    def maximal_repeats(self, least: int) -> list[tuple[int, int, int]]:
        """(length, first, past) of each group of occurrences ``order[first:past]`` that can't be made longer on either side.

        A stack holds the intervals of common prefixes that are open; one that closes is kept if the bytes
        before its occurrences differ, a string's beginning differing from everything.
        """
        out: list[tuple[int, int, int]] = []
        before = self.text[self.order - 1].astype(np.int16)
        near = self.common >= least
        border = np.flatnonzero(np.diff(np.concatenate(([0], near, [0])).astype(np.int8))).reshape(-1, 2)
        if len(border):
            # where all may be made longer to the left, that longer repeat is elsewhere in the array
            cuts = np.column_stack((border[:, 0], border[:, 1] + 1)).ravel()
            own = np.append(before, 0)
            low, high = np.minimum.reduceat(own, cuts)[::2], np.maximum.reduceat(own, cuts)[::2]
            border = border[(low != high) | (low == 0)]
        for a, b in border.tolist():
            common, left = [*self.common[a:b].tolist(), 0], before[a : b + 1].tolist()
            left = [-2 if x == 0 else x for x in left]  # -2: differs from all
            stack: list[list[int]] = []  # length, first, byte before (-2 if they differ)
            for k, size in enumerate(common):
                first, byte = a + k, left[k]
                while stack and stack[-1][0] > size:
                    length, first, held = stack.pop()
                    byte = byte if byte == held else -2
                    if byte == -2:
                        out.append((length, first, a + k + 1))
                if stack and stack[-1][0] == size:
                    stack[-1][2] = byte if byte == stack[-1][2] else -2
                elif size:
                    stack.append([size, first, byte])
        return out

    def covered(self, least: int) -> np.ndarray:
        """For each place of the text, how long the longest repeat is that begins there and is maximal."""
        best = np.zeros(len(self.order), np.int64)
        for length, first, past in sorted(self.maximal_repeats(least)):
            best[first:past] = length
        out = np.zeros(len(self.text), np.int64)
        out[self.order] = best
        return out


def runs_of(longest: np.ndarray) -> list[list[int]]:
    """Maximal runs that strings of these lengths, from their places on, cover."""
    starts = np.flatnonzero(longest)
    out: list[list[int]] = []
    for a, b in zip(starts.tolist(), (starts + longest[starts]).tolist()):
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return out


def window_hashes(data: np.ndarray, least: int) -> np.ndarray:
    """A hash of every ``least`` bytes, by doubling: of 8, 16, 32 and so on, joined for the bits of ``least``."""
    n = len(data) - least + 1
    now = mix(words_at(np.concatenate((data, np.zeros(8, np.uint8))))[: len(data)].copy())
    out, at, width, rest = np.zeros(n, np.uint64), 0, 8, least
    tail = now[least - 8 : least - 8 + n]
    while width <= rest:
        if rest & width:
            out = mix(out * COEFFICIENTS[width.bit_length()] + now[at : at + n])
            at += width
        now = mix(now[:-width] * COEFFICIENTS[60] + now[width:]) if len(now) > width else now[:0]
        width *= 2
    return mix(out + tail * COEFFICIENTS[61])


SPANS = "digest binary, first long, past long, brief boolean, h long, part int, r int, blob binary"


def joined_contexts(rows: pd.DataFrame) -> list[tuple[bytes, int, bool, bytes]]:
    """(digest, low, many, bytes): contexts of a text that overlap are one, so that no place stands twice in an array."""
    out: list = []
    for digest, low, many, context in rows[["digest", "low", "many", "context"]].sort_values(["digest", "low"]).itertuples(index=False):
        if out and out[-1][0] == digest and low <= out[-1][1] + len(out[-1][3]):
            _, first, all_many, held = out[-1]
            out[-1] = (digest, first, all_many and many, held + context[max(0, first + len(held) - low) :])
        else:
            out.append((digest, low, many, context))
    return out


def repeated_parts(rows: list[tuple[bytes, int, bool, bytes]], least: int) -> list[tuple[bytes, int, bool, bytes]]:
    """The contexts cut down to the runs of windows whose hash isn't alone, with a byte before and after them; the arrays then compare bytes."""
    data = np.frombuffer(b"".join(r[3] for r in rows) + b"\0" * least, np.uint8)
    ends = np.cumsum([len(r[3]) for r in rows])
    with np.errstate(over="ignore"):
        hashes = window_hashes(data, least)[: ends[-1] if rows else 0]
    order = np.argsort(hashes)
    same = hashes[order[1:]] == hashes[order[:-1]]
    found = np.zeros(len(hashes), bool)
    found[order[1:][same]] = found[order[:-1][same]] = True
    for end in ends.tolist():  # windows over the end of a context are none
        found[max(0, end - least + 1) : end] = False
    border = np.flatnonzero(np.diff(np.concatenate(([0], found, [0])).astype(np.int8))).reshape(-1, 2)
    which = np.searchsorted(ends, border[:, 0], "right")
    out = []
    for k, a, b in zip(which.tolist(), *border.T.tolist()):
        digest, low, many, context = rows[k]
        start = int(ends[k]) - len(context)
        a = max(a - 1, start) - start
        out.append((digest, low + a, many, context[a : b - start + least]))
    return out


def repeats_of_part(least: int, words: int = 0, fine: int = 0):
    """For applyInPandas: spans of contexts that repeat; of an anchor in several parts also the hashes of its windows.

    With ``fine``, spans of ``words`` words and at least so many bytes are found too, marked as brief.
    """
    shortest = fine or least

    def run(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        rows = joined_contexts(rows)
        parts = repeated_parts(rows, shortest)
        array = SuffixArray([r[3] for r in parts], shortest) if parts else None
        longest, out = array.covered(shortest) if parts else None, []
        for (digest, low, many, _), a, b in zip(parts, array.start, array.end) if parts else ():
            if not many:
                own = longest[a:b]
                passages = long_enough(own, array.text[a:b] - 1, words) if words else own
                if fine:
                    out += [(digest, low + first, low + past, True, None, None, None, None) for first, past in runs_of(passages)]
                    passages = np.where(own >= least, own, 0)
                out += [(digest, low + first, low + past, False, None, None, None, None) for first, past in runs_of(passages)]
        if key[1] >= 0:
            each = [np.frombuffer(c, np.uint8) for *_, c in rows]
            hashes = np.unique(np.concatenate([h for c in each for h in hashes_of(c, least, words, fine)]))
            for r in range(RANGES):
                out.append((None, None, None, None, key[0], key[1], r, hashes[hashes >> np.uint64(60) == r].tobytes()))
        array = longest = each = hashes = None
        give_back()
        columns = zip(*out) if out else [()] * 8
        kinds = (object, "Int64", "Int64", "boolean", "Int64", "Int64", "Int64", object)  # never by way of floats
        return pd.DataFrame({name: pd.array(list(c), kind) if kind != object else pd.Series(list(c), dtype=object) for name, c, kind in zip(("digest", "first", "past", "brief", "h", "part", "r", "blob"), columns, kinds)})

    return run


def hashes_of(data: np.ndarray, least: int, words: int, fine: int) -> list[np.ndarray]:
    """Hashes of the windows that tell repeats: of words, of bytes, or of both."""
    out = [word_windows(data, words)[0]] if words else []
    if (fine or not words) and len(data) >= least:
        with np.errstate(over="ignore"):
            out.append(window_hashes(data, least))
    return out or [np.zeros(0, np.uint64)]


def shared_hashes(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
    """Of one range of an anchor's hashes: to each part those that another part holds too."""
    blobs = [np.frombuffer(b, np.uint64) for b in rows["blob"]]
    values, counts = np.unique(np.concatenate(blobs), return_counts=True)
    twice = values[counts > 1]
    kept = [(key[0], part, np.intersect1d(b, twice, assume_unique=True).tobytes()) for part, b in zip(rows["part"], blobs)]
    return pd.DataFrame([k for k in kept if k[2]], columns=["h", "part", "blob"])


def repeats_across(least: int, words: int = 0, fine: int = 0):
    """For cogrouped applyInPandas: spans of windows that other parts hold."""

    def run(rows: pd.DataFrame, shared: pd.DataFrame) -> pd.DataFrame:
        out = []
        if len(shared):
            known = np.unique(np.concatenate([np.frombuffer(b, np.uint64) for b in shared["blob"]]))
            for digest, low, many, context in zip(rows["digest"], rows["low"], rows["many"], rows["context"]):
                if many:
                    continue
                data = np.frombuffer(context, np.uint8)
                if words:
                    hashes, begins, ends = word_windows(data, words)
                    found, longest = np.isin(hashes, known), np.zeros(len(data), np.int64)
                    if fine:
                        found &= ends - begins >= fine
                    longest[begins[found]] = (ends - begins)[found]
                    out += [(digest, low + first, low + past, bool(fine)) for first, past in runs_of(longest)]
                if (fine or not words) and len(data) >= least:
                    with np.errstate(over="ignore"):
                        longest = np.isin(window_hashes(data, least), known) * least
                    out += [(digest, low + first, low + past, False) for first, past in runs_of(longest)]
        return pd.DataFrame(out, columns=["digest", "first", "past", "brief"])

    return run


def digest_of(text) -> F.Column:
    return F.unhex(F.md5(F.coalesce(text, F.lit("")).cast("binary")))


def repeated_spans(docs: DataFrame, least: int = LEAST, part: int = PART, *, words: int = 0, fine: int = 0) -> tuple[DataFrame, DataFrame]:
    """(digest, spans) of texts that occur once, and (digest) of those that occur more often and are long enough to be repeats whole.

    With ``words``, repeats of so many words, however few bytes these have; ``least`` doesn't matter then. With ``words``
    and ``fine``, both repeats of ``least`` bytes and, as another column, brief, of so many words in ``fine`` bytes at least.
    """
    least = 2 * words - 1 if words and not fine else least
    shortest = fine or least
    table = cut(anchor_table(docs, least, 0 if fine else words, fine))
    each = table.select("digest", F.explode(F.arrays_zip("h", "c", "low", "high")).alias("x")).select("digest", "x.*")
    groups = cut(each.groupBy("h").agg(F.count("*").alias("m"), F.min("c").alias("a"), F.max("c").alias("b")).where("m > 1").select("h", (F.col("a") != F.col("b")).alias("mixed")))
    near = cut(sift(each, "h", groups.select("h"), 25).join(groups, "h"))
    classes = near.groupBy("h", "c").agg(F.count("*").alias("m"), F.min(F.struct("digest", "low", "high")).alias("rep"), F.first("mixed").alias("mixed"))
    classes = cut(classes)
    alike = sift(near, "c", classes.where("m > 1").select("c")).join(classes.where("m > 1").select("h", "c"), ["h", "c"], "left_semi")
    spans = alike.select("digest", F.col("low").cast("long").alias("first"), F.col("high").cast("long").alias("past"), F.expr(f"high - low < {least}").alias("brief")).where(f"past - first >= {shortest}")
    reps = classes.where("mixed").select("h", (F.col("m") > 1).alias("many"), "rep.*").where(f"high - low >= {shortest}")
    often = cut(reps.groupBy("h").agg(F.count("*").alias("k"), F.sum(F.col("high") - F.col("low")).alias("bytes")).where("k > 1"))
    total = often.agg(F.sum("bytes")).first()[0] or 0
    arrays = max(1, -(-total // ARRAY_BYTES))
    dealt = reps.join(often, "h").withColumn("parts", F.ceil(F.col("k") / part).cast("int"))
    hot = F.col("parts") > 1
    dealt = dealt.select("digest", "many", "h", "low", "high", F.when(hot, F.col("h")).otherwise(F.pmod("h", F.lit(arrays))).alias("g"), F.when(hot, F.pmod(F.hash("digest"), "parts")).otherwise(-1).alias("part"))
    wanted = dealt.groupBy("digest").agg(F.collect_list(F.struct("low", "high", "many", "g", "part")).alias("w"))
    texts = docs.select(digest_of(F.col("text")).alias("digest"), F.coalesce("text", F.lit("")).cast("binary").alias("text")).where(f"octet_length(text) >= {shortest}")
    texts = sift(texts, "digest", wanted.select("digest")).dropDuplicates(["digest"]).join(wanted, "digest")
    contexts = cut(texts.select("digest", "text", F.explode("w").alias("w")).select("digest", "w.*", F.expr("substring(text, w.low + 1, w.high - w.low)").alias("context")).drop("high"))
    found = cut(contexts.groupBy("g", "part").applyInPandas(repeats_of_part(least, words, fine), SPANS))
    spans = spans.unionByName(found.where("digest IS NOT NULL").select("digest", "first", "past", "brief"))
    if often.where(F.col("k") > part).limit(1).count():
        shared = found.where("blob IS NOT NULL").groupBy("h", "r").applyInPandas(shared_hashes, "h long, part int, blob binary")
        again = contexts.where("part >= 0").groupBy("g", "part").cogroup(shared.groupBy("h", "part")).applyInPandas(repeats_across(least, words, fine), "digest binary, first long, past long, brief boolean")
        spans = spans.unionByName(again)
    once = table.where("copies = 1").select("digest")
    chosen = lambda brief: F.sort_array(F.collect_set(F.when(F.col("brief") == brief, F.struct("first", "past"))))
    merged = spans.join(once, "digest", "left_semi").groupBy("digest").agg(chosen(False).alias("spans"), *([chosen(True).alias("brief")] if fine else []))
    merged, copies = cut(merged), cut(table.where("copies > 1").select("digest"))
    forget(table, groups, near, classes, often, contexts, found)
    return merged, copies


def merged(spans) -> list[list[int]]:
    out: list[list[int]] = []
    for first, past in sorted(spans):
        if out and first <= out[-1][1]:
            out[-1][1] = max(out[-1][1], past)
        else:
            out.append([first, past])
    return out


def without(raw: bytes, spans: list[list[int]]) -> bytes:
    out, last = [], 0
    for first, past in spans:
        out.append(raw[last:first])
        last = past
    return b"".join(out) + raw[last:]


def whole_characters(raw: bytes, spans: list[list[int]]) -> list[list[int]]:
    """The spans without characters that they cover in part."""
    out = []
    for first, past in spans:
        while first < past and raw[first] & 0xC0 == 0x80:
            first += 1
        while past < len(raw) and past > first and raw[past] & 0xC0 == 0x80:
            past -= 1
        if first < past:
            out.append([first, past])
    return out


def passage_words(raw: bytes, spans: list[tuple[int, int]], brief: list[tuple[int, int]], words: int) -> int:
    """How many words lie in repeats that hold at least so many whole."""
    begins, ends = words_in(np.frombuffer(raw, np.uint8), np.array([0, len(raw)]))
    inside = np.zeros(len(begins), bool)
    for first, past in {*spans, *brief}:
        a, b = np.searchsorted(begins, first), np.searchsorted(ends, past, "right")
        if b - a >= words:
            inside[a:b] = True
    return int(inside.sum())


def dedup_report(docs: DataFrame, least: int = LEAST, words: int = PASSAGE, fine: int = FINE) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256, passage_words: a row for each row.

    passage_words, beside the strings of ``least`` bytes, which alone are removed: words in strings of ``words`` words
    and ``fine`` bytes or more that stand anywhere else too. Without ``words`` these aren't looked for, and the column is left out.
    """
    spans, copies = repeated_spans(docs, least, words=words, fine=fine if words else 0)
    spans = spans if words else spans.withColumn("brief", F.filter("spans", lambda _: F.lit(False)))
    texts = docs.select(digest_of(F.col("text")).alias("digest"), F.coalesce("text", F.lit("")).cast("binary").alias("text"))

    def run(batches):
        for batch in slices(batches):
            rows = []
            for digest, raw, spans, brief in zip(*(c.to_pylist() for c in batch.columns)):
                own, more = ([(s["first"], s["past"]) for s in x] for x in (spans, brief))
                kept = merged(own)
                rows.append((digest, sum(b - a for a, b in kept), len(kept), hashlib.sha256(without(raw, kept)).hexdigest(), passage_words(raw, own, more, words)))
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.binary(), pa.int64(), pa.int64(), pa.string(), pa.int64()))], ["digest", "removed", "spans", "kept", "passage"])

    part = sift(texts, "digest", spans.select("digest")).join(spans, "digest").select("digest", "text", "spans", "brief").mapInArrow(run, "digest binary, removed long, spans long, kept string, passage long")
    whole = F.lit(-1).cast("long")
    done = part.unionByName(copies.select("digest", whole.alias("removed"), F.lit(1).cast("long").alias("spans"), F.sha2(F.lit(""), 256).alias("kept"), whole.alias("passage")))
    text = F.coalesce("text", F.lit(""))
    count = F.size(F.filter(F.split(text, "[\\x20\\x09-\\x0D]+"), lambda w: w != "")).cast("long")
    light = marked(docs.select("doc_id", "text", digest_of(F.col("text")).alias("digest")), "digest", copies)
    light = light.select("doc_id", "digest", F.octet_length(text).cast("long").alias("n_bytes"), F.sha2(text, 256).alias("all"), F.when(F.col("_found"), count).alias("n_words"))
    # of copies, those under ``least`` bytes stay
    short = (F.col("removed") < 0) & (F.col("n_bytes") < least)
    removed = F.when(short, 0).when(F.col("removed") < 0, F.col("n_bytes")).otherwise(F.coalesce("removed", F.lit(0)))
    passage = F.when(F.col("passage") < 0, F.when(F.col("n_words") >= words, F.col("n_words")).otherwise(0)).otherwise(F.coalesce("passage", F.lit(0)))
    out = light.join(done, "digest", "left").select("doc_id", "n_bytes", removed.alias("n_removed"), F.when(short, 0).otherwise(F.coalesce("spans", F.lit(0))).alias("n_spans"), F.when(short, F.col("all")).otherwise(F.coalesce("kept", "all")).alias("kept_sha256"), passage.alias("passage_words"))
    return out if words else out.drop("passage_words")


def without_repeats(docs: DataFrame, least: int = LEAST, *, words: int = 0) -> DataFrame:
    """The rows with repeated strings cut out of their texts, all their columns; characters that are covered in part stay, n_chars follows.

    With ``words``, repeats of so many words go as well as those of ``least`` bytes.
    """
    spans, copies = repeated_spans(docs, least)
    if words:
        more, others = repeated_spans(docs, words=words)
        spans = spans.unionByName(more).groupBy("digest").agg(F.flatten(F.collect_list("spans")).alias("spans"))
        copies = copies.unionByName(others).distinct()
    names = docs.columns
    inner = docs.select(digest_of(F.col("text")).alias("_digest"), F.struct(*names).alias("_row"))
    wanted = spans.unionByName(copies.select("digest", F.lit(None).cast(spans.schema["spans"].dataType).alias("spans"))).toDF("_digest", "_spans")
    at = names.index("text")

    def run(batches):
        for batch in batches:
            for first in range(0, batch.num_rows, 1000):
                part = batch.slice(first, 1000)
                rows, texts = part.column(0), []
                for text, spans, known in zip(rows.field("text").to_pylist(), part.column(1).to_pylist(), part.column(2).to_pylist()):
                    raw = (text or "").encode()
                    texts.append(text if not known else "" if spans is None else without(raw, whole_characters(raw, merged([(s["first"], s["past"]) for s in spans]))).decode())
                columns = [pa.array(texts, pa.string()) if k == at else rows.field(k) for k in range(len(names))]
                yield pa.RecordBatch.from_arrays(columns, names)

    # most rows that nothing is cut from never leave their task; the others meet their spans once
    held = marked(inner, "_digest", wanted.select("_digest"), 25)
    near = held.where("_found").select("_digest", "_row").join(wanted.withColumn("_known", F.lit(True)), "_digest", "left")
    touched = near.select("_row", "_spans", F.coalesce("_known", F.lit(False)).alias("_known")).mapInArrow(run, docs.schema)
    out = held.where("NOT _found").select("_row.*").unionByName(touched)
    return out.withColumn("n_chars", F.length("text").cast(dict(docs.dtypes)["n_chars"])).select(names) if "n_chars" in names else out


def op9_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dedup_report(load(spark, sf_dir, "documents"), words=0)
