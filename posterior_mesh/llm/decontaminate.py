"""Benchmark decontamination with a generalised suffix automaton over the words of the test items.

A document's words run through the automaton once; at each word it knows the longest run of words
that ends there and occurs in an item. A window is ``WINDOW`` words of an item, or a whole shorter
item; words inside an occurrence of a window are hit.

Defined cases: null and wordless texts have no words and no hits; wordless items match nothing;
repeated item ids count once; words of items without an id are hit, and these items count as one but
have no part in the hash of ids; repeated rows each give a row; an empty benchmark hits nothing. The
benchmark reaches the executors as one automaton of at most ``MOST_WORDS`` words; a larger benchmark
is dealt into several, and the documents run through them one after the other without a shuffle.
"""

from __future__ import annotations

import hashlib
import pickle
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import load, slices

WORD = re.compile(rb"[0-9a-z\x80-\xff]+")  # of bytes in lower case; all bytes of other characters are over 0x7F
WINDOW = 13
MOST_WORDS = 500_000


class Automaton:
    """All substrings of all items. After ``seal``, ``items[v]`` are the items with a window that ends a match in state v."""

    def __init__(self, window: int = WINDOW):
        self.window, self.words = window, {}
        self.next: list[dict[int, int]] = [{}]
        self.link, self.length, self.home = [-1], [0], [set()]
        self.short: dict[int, dict[int, set]] = {}
        self.least = window

    def _state(self, length: int, link: int, step: dict[int, int], home: set) -> int:
        self.next.append(step)
        self.link.append(link)
        self.length.append(length)
        self.home.append(home)
        return len(self.next) - 1

    def _split(self, p: int, word: int, q: int) -> int:
        """A state for the strings of q that p's longest and the word make."""
        new = self._state(self.length[p] + 1, self.link[q], dict(self.next[q]), set())
        self.link[q] = new
        while p >= 0 and self.next[p].get(word) == q:
            self.next[p][word] = new
            p = self.link[p]
        return new

    def add(self, item, words: list[bytes]) -> None:
        last = 0
        for raw in words:
            word = self.words.setdefault(raw, len(self.words))
            p, q = last, self.next[last].get(word)
            if q is not None:
                last = q if self.length[q] == self.length[p] + 1 else self._split(p, word, q)
            else:
                last = self._state(self.length[p] + 1, 0, {}, set())
                while p >= 0 and word not in self.next[p]:
                    self.next[p][word] = last
                    p = self.link[p]
                if p >= 0:
                    q = self.next[p][word]
                    self.link[last] = q if self.length[q] == self.length[p] + 1 else self._split(p, word, q)
            self.home[last].add(item)
        if 0 < len(words) < self.window:
            self.least = min(self.least, len(words))
            self.whole.append((item, words))

    whole: list

    def build(self, items) -> Automaton:
        self.whole = []
        for item, words in items:
            self.add(item, words)
        order = sorted(range(1, len(self.next)), key=self.length.__getitem__, reverse=True)
        for v in order:  # who holds a state's strings also holds their suffixes
            self.home[self.link[v]] |= self.home[v]
        ends: dict[int, list] = {}
        for item, words in self.whole:
            v = 0
            for w in words:
                v = self.next[v][self.words[w]]
            ends.setdefault(v, []).append((len(words), item))
        self.items: list = [()] * len(self.next)
        self.ends: list = [()] * len(self.next)
        for v in reversed(order):
            up = self.link[v]
            self.items[v] = () if self.length[v] < self.window else tuple(self.home[v]) if self.length[up] < self.window else self.items[up]
            self.ends[v] = self.ends[up] + tuple(ends.get(v, ()))
        self.home = []
        return self

    def scan(self, words: list[bytes]) -> tuple[list[list[int]], set]:
        """Runs of hit words [first, past), in order and apart, and the items found."""
        known = np.fromiter(map(self.words.get, words, (-1 for _ in words)), np.int64, len(words))
        border = np.flatnonzero(np.diff(np.concatenate(([0], known >= 0, [0])).astype(np.int8)))
        spans: list[list[int]] = []
        found: set = set()
        step, link, length, window = self.next, self.link, self.length, self.window
        for first, past in border.reshape(-1, 2).tolist():
            if past - first < self.least:
                continue
            state = size = 0
            for at, word in enumerate(known[first:past].tolist(), first + 1):
                to = step[state].get(word)
                while to is None and state:
                    state = link[state]
                    size = length[state]
                    to = step[state].get(word)
                if to is None:
                    size = 0
                    continue
                state, size = to, size + 1
                hit = 0
                if size >= window:
                    hit = size
                    found.update(self.items[state])
                for n, item in self.ends[state]:
                    if n <= size:
                        hit = max(hit, n)
                        found.add(item)
                if hit:
                    start = at - hit
                    while spans and spans[-1][0] >= start:
                        spans.pop()
                    if spans and spans[-1][1] >= start:
                        spans[-1][1] = at
                    else:
                        spans.append([start, at])
        return spans, found


def words_of(text: bytes) -> list[bytes]:
    return WORD.findall(text.lower())


def automata(benchmark: DataFrame, window: int = WINDOW, most: int = MOST_WORDS) -> list[Automaton]:
    """One automaton, or as many as the words of the benchmark need."""
    out, held, seen = [], [], 0
    rows = benchmark.select("item_id", F.col("text").cast("binary").alias("text")).where("text IS NOT NULL").orderBy("item_id")
    for item, text in rows.toLocalIterator():
        words = words_of(bytes(text))
        if held and seen + len(words) > most:
            out, held, seen = [*out, Automaton(window).build(held)], [], 0
        held.append((item, words))
        seen += len(words)
    return [*out, Automaton(window).build(held)]


def find_contamination(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, most: int = MOST_WORDS) -> DataFrame:
    """doc_id, n_words, spans (hit words, [first, past)), items (ids as strings, sorted, null last)."""
    spark = docs.sparkSession
    now = docs.select("doc_id", F.col("text").cast("binary").alias("text"), F.lit(None).cast("long").alias("n_words"), F.lit(None).cast("array<array<int>>").alias("spans"), F.lit(None).cast("array<string>").alias("items"))
    for automaton in automata(benchmark, window, most):
        sent = spark.sparkContext.broadcast(pickle.dumps(automaton, 5))

        def run(batches, sent=sent):
            of = pickle.loads(sent.value)
            for batch in slices(batches):
                n, spans, items = [], [], []
                for text, old, before in zip(batch.column(1).to_pylist(), batch.column(3).to_pylist(), batch.column(4).to_pylist()):
                    words = words_of(text)
                    hit, found = of.scan(words)
                    n.append(len(words))
                    spans.append(merged([*(old or []), *hit]) if old else hit)
                    items.append(sorted({*(before or []), *(None if i is None else str(i) for i in found)}, key=lambda i: (i is None, i or "")))
                columns = [batch.column(0), batch.column(1), pa.array(n, pa.int64()), pa.array(spans, pa.list_(pa.list_(pa.int32()))), pa.array(items, pa.list_(pa.string()))]
                yield pa.RecordBatch.from_arrays(columns, ["doc_id", "text", "n_words", "spans", "items"])

        now = now.mapInArrow(run, "doc_id long, text binary, n_words long, spans array<array<int>>, items array<string>")
    return now.drop("text")


def merged(spans: list) -> list[list[int]]:
    out: list[list[int]] = []
    for first, past in sorted(spans):
        if out and first <= out[-1][1]:
            out[-1][1] = max(out[-1][1], past)
        else:
            out.append([first, past])
    return out


#: A document is contaminated if its hit words are one in so many, or more.
ONE_IN = 20


def verdicts(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256, contaminated."""
    hit = F.aggregate("spans", F.lit(0).cast("long"), lambda n, s: n + s[1] - s[0])
    return find_contamination(docs, benchmark).select(
        "doc_id", "n_words", hit.alias("n_hit"), F.size("items").cast("long").alias("n_items"), F.sha2(F.concat_ws(",", F.array_sort("items")), 256).alias("items_sha256"), ((hit > 0) & (ONE_IN * hit >= F.col("n_words"))).alias("contaminated"))


def without_spans(text: str, spans: list[list[int]]) -> str:
    """The text without the hit words and what stands between them."""
    raw = text.encode()
    at = [m.span() for m in WORD.finditer(raw.lower())]
    kept, last = [], 0
    for first, past in spans:
        kept.append(raw[last : at[first][0]])
        last = at[past - 1][1]
    return (b"".join(kept) + raw[last:]).decode()


def decontaminate(docs: DataFrame, benchmark: DataFrame, remove_spans: bool = False) -> DataFrame:
    """The documents that aren't contaminated, all their columns; with ``remove_spans``, hit words are cut out of those kept.

    Coverage is judged on the rows themselves, so no join is needed and repeated ids don't matter.
    """
    spark, names = docs.sparkSession, docs.columns
    sent = [spark.sparkContext.broadcast(pickle.dumps(a, 5)) for a in automata(benchmark)]
    at = names.index("text")

    def run(batches):
        of = [pickle.loads(s.value) for s in sent]
        for batch in slices_keeping_nulls(batches):
            keep, texts = [], []
            for text in batch.column(at).to_pylist():
                words = words_of((text or "").encode())
                spans = merged([s for a in of for s in a.scan(words)[0]])
                hit = sum(b - a for a, b in spans)
                keep.append(not hit or ONE_IN * hit < len(words))
                texts.append(without_spans(text, spans) if hit and remove_spans else text)
            if remove_spans:
                batch = batch.set_column(at, batch.schema.field(at), pa.array(texts, batch.schema.field(at).type))
            yield batch.filter(pa.array(keep, pa.bool_()))

    return docs.mapInArrow(run, docs.schema)


def slices_keeping_nulls(batches, most: int = 1 << 12):
    for batch in batches:
        for first in range(0, batch.num_rows, most):
            yield batch.slice(first, most)


def op7_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return verdicts(load(spark, sf_dir, "documents"), load(spark, sf_dir, "benchmark"))


#: The same by windows as strings, for DuckDB.
OP7_SQL = """
WITH d AS (SELECT doc_id, regexp_extract_all(coalesce(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), ''), '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+') AS w FROM documents),
i AS (SELECT item_id, regexp_extract_all(coalesce(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), ''), '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+') AS w FROM benchmark),
iw AS (SELECT DISTINCT item_id, least(13, len(w)) AS n, array_to_string(w[p : p + least(13, len(w)) - 1], ' ') AS s FROM (SELECT item_id, w, unnest(range(1, len(w) - least(13, len(w)) + 2)) AS p FROM i WHERE len(w) > 0)),
k AS (SELECT DISTINCT n FROM iw),
dw AS (SELECT doc_id, n, p, array_to_string(w[p : p + n - 1], ' ') AS s FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS p FROM d, k WHERE len(w) >= n)),
m AS (SELECT dw.doc_id, dw.p, dw.n, iw.item_id FROM dw JOIN iw USING (n, s)),
h AS (SELECT doc_id, count(DISTINCT q) AS n_hit FROM (SELECT DISTINCT doc_id, unnest(range(p, p + n)) AS q FROM m) GROUP BY doc_id),
t AS (SELECT doc_id, count(*) AS n_items, string_agg(x, ',' ORDER BY x) AS s FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS x FROM m) GROUP BY doc_id)
SELECT d.doc_id, CAST(len(d.w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
       sha256(coalesce(t.s, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(d.w) AS contaminated
FROM d LEFT JOIN h USING (doc_id) LEFT JOIN t USING (doc_id)
"""
