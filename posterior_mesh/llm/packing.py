"""Packing of token pieces into sequences: dominance reduction, then best fit over the rest.

The plan is made from the histogram of piece lengths, which has at most ``capacity`` rows whatever
the number of pieces. First, sets of one or two lengths that dominate every other filling for their
longest piece are fixed and taken out, as often as they occur (the reduction of Martello and Toth);
the rest goes longest first into the fullest open sequence that takes it. Pieces then get their places
by their rank within their length.

Defined cases: a null or empty text is the closing id alone; ties of length are ordered by doc_id,
piece and digest; repeated rows each get a place; no rows give no sequences.
"""

from __future__ import annotations

import re
import zlib
from bisect import bisect_left, insort
from collections import Counter
from functools import lru_cache
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import cut, load, slices

CAPACITY = 4096
CLOSING = (1).to_bytes(4, "little")
#: Words that a worker remembers; twice as many at most.
MEMO = 300_000
# Characters that end words for the tokenizer, and those that only Python's split() takes for white space.
ONLY_HERE = "\x1c\x1d\x1e\x1f"
#: A text with one of these is cut at white space alone: < begins the special strings, the dotted I gets a mark in lower case,
#: and beyond Latin script lower case may depend on what stands around. White space beyond ASCII is here too.
ODD = re.compile("[^\x00-\x1b\x20-;=-\x84\x86-\x9f\xa1-\u012f\u0131-\u024f]")
#: Marks that begin a token of their own, for they stand after a letter or digit, and end a word.
MARKS = re.compile(r"""[.,!?;:$%*#=+&@~^()[\]{}"`/\\_-](?<=[^\W_].)[.,!?;:$%*#=+&@~^()[\]{}"`/\\_-]*(?=\s|$)""")


class WordIds:
    """Ids of texts by the tokenizer, a word at a time: its vocabulary never joins what white space parts."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.known: dict[str, bytes] = {}
        words = self.tokenizer.get_vocab(with_added_tokens=True)
        self.ends = np.zeros(max(words.values()) + 1, bool)
        self.ends[[k for w, k in words.items() if w.endswith("</w>")]] = True

    def _parted(self, text: str) -> str:
        """The text with white space between what may be encoded alone."""
        return " ".join(self._cut(text)) if ODD.search(text) else MARKS.sub(r" \g<0>", text.lower())

    def _cut(self, text: str) -> list[str]:
        if any(c in text for c in ONLY_HERE):
            for i, c in enumerate(ONLY_HERE):
                text = text.replace(c, chr(0xF0000 + i))
            words = text.split()
            for i, c in enumerate(ONLY_HERE):
                words = [w.replace(chr(0xF0000 + i), c) for w in words]
            return words
        return text.split()

    def _encode(self, words: list[str]) -> None:
        """Encode many words as one text; the places of the tokens tell whose they are."""
        encoded = self.tokenizer.encode(" ".join(words), add_special_tokens=False)
        places = np.array(encoded.offsets, np.int64).reshape(-1, 2)[:, 0]
        starts = np.cumsum([0, *(len(w) + 1 for w in words)])
        self._keep(words, np.array(encoded.ids, "<u4"), np.searchsorted(places, starts))

    def _encode_letters(self, words: list[str]) -> None:
        """As ``_encode``, of words that are letters alone: each has one token that ends a word, its last."""
        ids = np.array(self.tokenizer.encode_batch_fast([" ".join(words)], add_special_tokens=False)[0].ids, "<u4")
        ends = np.flatnonzero(self.ends[ids]) + 1
        if len(ends) == len(words):
            self._keep(words, ids, np.concatenate(([0], ends)))
        else:  # a letter whose lower case has marks
            self._encode(words)

    def _keep(self, words: list[str], ids: np.ndarray, ends: np.ndarray) -> None:
        raw, ends = ids.tobytes(), (4 * ends).tolist()
        for w, a, b in zip(words, ends, ends[1:]):
            self.known[w] = raw[a:b]

    def _learn(self, words: set[str]) -> None:
        letters = [w for w in words if w.isalpha()]
        for encode, some in ((self._encode_letters, letters), (self._encode, list(words.difference(letters)))):
            for at in range(0, len(some), 1000):
                encode(some[at : at + 1000])

    def ids(self, texts: list[str]) -> list[bytes]:
        """The ids of each text as little-endian unsigned 32-bit numbers. Each word is looked up once for all texts."""
        parted = pc.ascii_split_whitespace(pa.array([self._parted(t) for t in texts], pa.large_string()))
        coded = parted.flatten().dictionary_encode()
        words = coded.dictionary.to_pylist()
        if len(self.known) > 2 * MEMO:
            self.known = dict(list(self.known.items())[MEMO:])
        self.known[""] = b""
        self._learn(set(words).difference(self.known))
        own = list(map(self.known.__getitem__, words))
        flat, sizes = np.frombuffer(b"".join(own), "<u4"), np.fromiter(map(len, own), np.int64, len(own)) // 4
        which = coded.indices.to_numpy()
        each = sizes[which]
        past = np.concatenate(([0], np.cumsum(each)))
        raw = flat[np.repeat((np.cumsum(sizes) - sizes)[which] - past[:-1], each) + np.arange(past[-1])].tobytes()
        ends = (4 * past[parted.offsets.to_numpy() - parted.offsets[0].as_py()]).tolist()
        return [raw[a:b] for a, b in zip(ends, ends[1:])]


@lru_cache(1)
def word_ids(path: str) -> WordIds:
    return WordIds(path)


def token_pieces(docs: DataFrame, path: str, capacity: int = CAPACITY) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32: each document's ids and the closing id, cut only where they exceed the capacity."""

    def run(batches):
        for batch in slices(batches, most=3 << 20):
            rows = []
            for doc, ids in zip(batch.column(0).to_pylist(), word_ids(path).ids(batch.column(1).to_pylist())):
                ids += CLOSING
                for k, at in enumerate(range(0, len(ids), 4 * capacity)):
                    piece = ids[at : at + 4 * capacity]
                    rows.append((doc, k, at // 4, len(piece) // 4, zlib.crc32(piece)))
            kinds = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], ["doc_id", "piece", "start", "length", "ids_crc32"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, piece int, start long, length long, ids_crc32 long")


def dominating_sets(counts: dict[int, int], capacity: int) -> tuple[list[tuple[tuple[int, ...], int]], dict[int, int]]:
    """Sets of lengths that some best packing holds, each with how often, and what is left.

    For the longest piece: alone if nothing goes with it; with a piece that fills it up exactly; or
    with the longest that goes with it, if no two pieces do.
    """
    left = {n: c for n, c in counts.items() if c}
    lengths = sorted(left)
    fixed: list[tuple[tuple[int, ...], int]] = []
    for long in sorted(left, reverse=True):
        while left.get(long):
            room = capacity - long
            small = [n for n in lengths[:3] if left[n] > (n == long)]
            own = left[long]
            if not small or small[0] > room:
                chosen, times = (long,), own
            else:
                exact = left.get(room, 0) if room != long else own // 2
                best = room if exact else lengths[max(0, bisect_left(lengths, room + 1) - 1)]
                if best == long and own < 2:
                    best = lengths[lengths.index(best) - 1] if lengths.index(best) else 0
                least = small[0]
                spare = left[least] - (least == long)
                second = least if spare >= 2 else next((n for n in lengths if n != least and left[n] > (n == long)), capacity + 1)
                if not best or not exact and least + second <= room:
                    break
                chosen, times = (long, best), min(own, left[best]) if best != long else own // 2
            fixed.append((chosen, times))
            for n in chosen:
                left[n] -= times
                if not left[n]:
                    del left[n]
                    lengths.remove(n)
    return fixed, left


def best_fit(counts: dict[int, int], capacity: int) -> list[tuple[Counter, int]]:
    """Fillings of sequences and how often each is used; longest first, into the fullest that takes it, whole runs at a time."""
    free: list[int] = []  # rooms of open sequences, in order
    open_: dict[int, list[tuple[tuple, int]]] = {}
    for n in sorted(counts, reverse=True):
        left = counts[n]
        while left:
            k = bisect_left(free, n)
            if k < len(free):
                room = free[k]
                filling, times = open_[room].pop()
                if not open_[room]:
                    del open_[room]
                    free.pop(k)
                put = min(room // n, left)
                used = min(times, left // put)
                if used < times:
                    add(open_, free, room, filling, times - used)
            else:
                room, filling = capacity, ()
                put = min(capacity // n, left)
                used = left // put
            add(open_, free, room - put * n, (*filling, (n, put)), used)
            left -= put * used
    return [(Counter(dict(filling)), times) for group in open_.values() for filling, times in group]


def add(open_: dict, free: list, room: int, filling: tuple, times: int) -> None:
    if room not in open_:
        open_[room] = []
        insort(free, room)
    open_[room].append((filling, times))


def plan(counts: dict[int, int], capacity: int = CAPACITY) -> list[tuple[int, int, int, int, int]]:
    """(length, first rank, past rank, first sequence, offset): pieces of a length, by rank, go one to a sequence at that offset."""
    if any(not 0 < n <= capacity for n in counts):
        raise ValueError(f"lengths must be 1 to {capacity}")
    fixed, left = dominating_sets(counts, capacity)
    fillings = [(Counter(chosen), times) for chosen, times in fixed] + best_fit(left, capacity)
    rows, ranks, sequence = [], Counter(), 0
    for filling, times in fillings:
        at = 0
        for n, put in sorted(filling.items(), reverse=True):
            for _ in range(put):
                rows.append((n, ranks[n], ranks[n] + times, sequence, at))
                ranks[n] += times
                at += n
        sequence += times
    return rows


#: Ranks within a length are counted in so many parts at least, so that a frequent length isn't one task, and for so many pieces more in one more.
PARTS, PART_PIECES = 64, 1 << 20
#: Pieces of one length meet the steps of their plan by runs of so many ranks.
RUN = 256


def pack(pieces: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """The pieces with sequence_id and offset."""
    spark = pieces.sparkSession
    held = cut(pieces)
    counts = {r["length"]: r["n"] for r in held.groupBy("length").agg(F.count("*").alias("n")).collect()}  # at most `capacity` rows
    parts = max(PARTS, sum(counts.values()) // PART_PIECES)
    held = held.withColumn("part", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32"), F.lit(parts)))
    by_part = held.groupBy("length", "part").agg(F.count("*").alias("n"))
    before = by_part.withColumn("before", F.sum("n").over(W.partitionBy("length").orderBy("part")) - F.col("n")).drop("n")
    rank = F.row_number().over(W.partitionBy("length", "part").orderBy("doc_id", "piece", "ids_crc32", "start"))
    ranked = held.withColumn("rank", rank - 1).join(before, ["length", "part"]).withColumn("rank", F.col("rank") + F.col("before"))
    steps = spark.createDataFrame(plan(counts, capacity), "length long, first long, past long, sequence long, offset long")
    runs = steps.withColumn("run", F.explode(F.expr(f"sequence(first DIV {RUN}, (past - 1) DIV {RUN})")))
    placed = ranked.withColumn("run", F.expr(f"rank DIV {RUN}")).join(runs, ["length", "run"]).where("first <= rank AND rank < past")
    return placed.selectExpr("doc_id", "piece", "start", "length", "ids_crc32", "sequence + rank - first AS sequence_id", "offset")


def pack_documents(docs: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    import public_tokenizers

    return pack(token_pieces(docs, public_tokenizers.path("word_bpe_49k.json"), capacity), capacity)


def op10_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(load(spark, sf_dir, "documents"))
