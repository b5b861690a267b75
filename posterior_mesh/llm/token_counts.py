"""Exact token counts of every prefix of a text, by dynamic programming over its prefixes.

A byte-pair encoding of a piece is valid exactly if each pair of neighbouring tokens encodes
to itself. So the last token of a prefix is the one token that ends there and agrees with the
last token of the prefix before it, and the count is that prefix's count plus one. The table of
a text holds, for each code point, how the count changes when the point is appended; its running
sum answers any question about truncation or budgets without encoding again.

Defined cases: a null or empty text has no tokens and an empty table; repeated rows each give
a row; other columns of the input are ignored.
"""

from __future__ import annotations

import json
from functools import lru_cache
from itertools import accumulate, chain, pairwise

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession

from .common import load, slices

# White space of the tokenizer's pattern, its pieces, and its special string.
WHITE = "\t-\r \x85\xa0  -     　"
PIECES = rf"'s|'t|'re|'ve|'m|'ll|'d| ?\p{{L}}+| ?\p{{N}}+| ?[^{WHITE}\p{{L}}\p{{N}}]+|[{WHITE}]+(?![^{WHITE}])|[{WHITE}]+"
SPECIAL = "<|endoftext|>"

#: Chunks and pieces that a worker remembers; the older half goes when there are twice as many.
MEMO = 300_000


class PrefixTable:
    """Tables of prefixes for one byte-level vocabulary file."""

    def __init__(self, path: str):
        model = json.load(open(path, encoding="utf-8"))["model"]
        letters = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b]
        letter = {chr(b): b for b in letters} | {chr(256 + i): b for i, b in enumerate(sorted({*range(256)} - {*letters}))}
        as_bytes = lambda token: bytes(letter[c] for c in token)
        token = {as_bytes(k): v for k, v in model["vocab"].items()}
        #: Ranks of merges by their two tokens; for each token its last merge's rank and halves.
        self.rank, self.made = {}, {v: (-1, v, v) for v in token.values()}
        for rank, merge in enumerate(model["merges"]):
            a, b = (as_bytes(x) for x in (merge.split(" ") if isinstance(merge, str) else merge))
            self.rank[token[a] << 20 | token[b]] = rank
            self.made[token[a + b]] = (rank, token[a], token[b])
        self.ends: dict = {}  # tokens by their bytes from the last to the first
        for raw, number in token.items():
            node = self.ends
            for byte in reversed(raw):
                node = node.setdefault(byte, {})
            node[-1] = number
        self.pieces = regex.compile(PIECES)
        self.safe = regex.compile(rf"(?<=[^{WHITE}]) (?=[^{WHITE}])")
        self.wide = regex.compile(rf"[{WHITE}] | [{WHITE}]")
        self.odd = regex.compile(rf"[{WHITE}']|{regex.escape(SPECIAL)}")
        self.agreed: dict[int, bool] = {}
        self.piece: dict[str, bytes] = {}
        self.chunk: dict[str, bytes] = {}

    def _agree(self, left: int, right: int) -> bool:
        """Whether two tokens side by side stay as they are.

        Undo their merges from the latest on; they don't stay if what faces each other at the
        border would have been merged before a merge that was undone. Of equal merges the left
        one comes first.
        """
        made, rank, before = self.made, self.rank, 1 << 30
        while True:
            if rank.get(left << 20 | right, 1 << 30) < before:
                return False
            (a, _, inner), (b, outer, _) = made[left], made[right]
            if a < 0 and b < 0:
                return True
            if a > b:
                before, left = a, inner
            else:
                before, right = b + 1, outer

    def learn(self, pieces: set[str]) -> None:
        """Fill in the tables of pieces, in order, so that each goes on from the prefix it shares with the last."""
        agreed, ends, piece_of = self.agreed, self.ends, self.piece
        if len(agreed) > 4 * MEMO:
            agreed.clear()
        raw, last, count, change = b"", [-1], [0], bytearray()
        for piece in sorted(pieces):
            old, raw = raw, piece.encode()
            n, same = len(raw), 0
            for x, y in zip(old, raw):
                if x != y:
                    break
                same += 1
            del last[same + 1 :], count[same + 1 :], change[same:]
            for end in range(same, n):
                node, found, at = ends, [], end + 1
                while at:
                    at -= 1
                    node = node.get(raw[at])
                    if node is None:
                        break
                    if -1 in node:
                        found.append((at, node[-1]))
                while found:
                    at, number = found.pop()
                    if at:
                        key = last[at] << 20 | number
                        fits = agreed.get(key)
                        if fits is None:
                            fits = agreed[key] = self._agree(last[at], number)
                        if not fits:
                            continue
                    last.append(number)
                    more = count[at] + 1
                    change.append((more - count[end]) & 255)
                    count.append(more)
                    break
            if n == len(piece):
                piece_of[piece] = bytes(change)
            else:
                at, out = 0, bytearray()
                for c in piece:
                    k = len(c.encode())
                    out.append((count[at + k] - count[at]) & 255)
                    at += k
                piece_of[piece] = bytes(out)

    def of_piece(self, piece: str) -> list[int]:
        """Counts after each code point of one piece, from none on."""
        if piece not in self.piece:
            self.learn({piece})
        return [0, *accumulate(x - 256 if x > 127 else x for x in self.piece[piece])]

    def plain(self, text: str) -> int:
        return sum(self.of_piece(p)[-1] for p in self.pieces.findall(text))

    def counts(self, text: str) -> list[int]:
        """Counts after each code point of any text, from none on, as if the text ended there."""
        out, before, parts = [0], 0, text.split(SPECIAL)
        for k, part in enumerate(parts):
            if k:  # a special string: while it is incomplete it is ordinary text, joined to what stands before it
                tail = self.pieces.findall(parts[k - 1])[-3:]
                keep, tail = before - sum(self.of_piece(p)[-1] for p in tail), "".join(tail)
                out += [keep + self.plain(tail + SPECIAL[:i]) for i in range(1, len(SPECIAL))]
                before += 1
                out.append(before)
            last = ""
            for piece in self.pieces.findall(part):
                own = self.of_piece(piece)
                more = [before + n for n in own[1:]]
                if last and last.isspace() and piece[0].isspace():  # white space at the end of a prefix stays together
                    more[0] = before - self.of_piece(last)[-1] + self.of_piece(last + piece[0])[-1]
                elif piece in ("'re", "'ve", "'ll"):
                    more[1] = before + self.of_piece("'")[-1] + self.of_piece(piece[1])[-1]
                out += more
                before, last = before + own[-1], piece
        return out

    def _of_chunks(self, chunks: list[str]) -> list[bytes]:
        """Tables of chunks that a text is cut into, each with its leading space if it has one."""
        plain = {c: [c] if c[1:].isalpha() and (c[0] == " " or c[0].isalpha()) else self.pieces.findall(c) for c in chunks if not self.odd.search(c, int(c[0] == " "))}
        self.learn({p for ps in plain.values() for p in ps if p not in self.piece})
        of = self.piece
        return [b"".join([of[p] for p in plain[c]]) if c in plain else bytes((b - a) & 255 for a, b in pairwise(self.counts(c))) for c in chunks]

    def changes(self, texts: list[str]) -> list[bytes]:
        """The table of each text: the change of the count at each code point, a signed byte each.

        Between two characters that aren't white space, a single space always begins a piece, so the
        text is cut there and the tables of the parts follow each other.
        """
        cuts = []
        for text in texts:
            plain = text[:1] != " " and text[-1:] != " " and not self.wide.search(text)
            cuts.append(text.split(" ") if plain else self.safe.split(text))
        if len(self.piece) > MEMO:
            self.piece = {}
        if len(self.chunk) > 2 * MEMO:
            self.chunk = dict(list(self.chunk.items())[MEMO:])
        new = [w for w in set(chain.from_iterable(c[1:] for c in cuts)) if w not in self.chunk]
        self.chunk.update(zip(new, self._of_chunks([" " + w for w in new])))
        heads = self._of_chunks([c[0] or " " for c in cuts])
        of = self.chunk
        return [(head if c[0] else b"") + b"".join([of[w] for w in c[1:]]) for head, c in zip(heads, cuts)]


@lru_cache(1)
def table(path: str) -> PrefixTable:
    return PrefixTable(path)


def longest_prefix(changes: bytes, budget: int) -> int:
    """Code points of the longest prefix of at most ``budget`` tokens."""
    fits = np.flatnonzero(np.cumsum(np.frombuffer(changes, np.int8), dtype=np.int64) <= budget)
    return int(fits[-1]) + 1 if len(fits) else 0


def tokens_at(changes: bytes, points: int) -> int:
    """Tokens of the prefix of so many code points."""
    return int(np.frombuffer(changes, np.int8)[:points].sum(dtype=np.int64))


def prefix_tables(docs: DataFrame, path: str, budget: int, store: bool = True) -> DataFrame:
    """doc_id, n_bytes, n_tokens, prefix_chars (longest prefix within the budget), and with ``store`` the table itself."""

    def run(batches):
        for batch in slices(batches, most=3 << 20):
            texts, rows = batch.column(1).to_pylist(), []
            for text, changes in zip(texts, table(path).changes(texts)):
                running = np.cumsum(np.frombuffer(changes, np.int8), dtype=np.int64)
                total = int(running[-1]) if len(running) else 0
                fits = len(text) if total <= budget and (not len(running) or running.max() <= budget) else longest_prefix(changes, budget)
                rows.append((len(text.encode()), total, fits, changes))
            n, total, fits, changes = zip(*rows)
            columns = [batch.column(0), pa.array(n, pa.int64()), pa.array(total, pa.int64()), pa.array(fits, pa.int64())]
            yield pa.RecordBatch.from_arrays(columns + [pa.array(changes, pa.binary())] * store, ["doc_id", "n_bytes", "n_tokens", "prefix_chars", "changes"][: 4 + store])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_bytes long, n_tokens long, prefix_chars long" + ", changes binary" * store)


#: Tokens above which a text counts as over the limit.
LIMIT = 1024


def op1_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    counted = prefix_tables(load(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"), LIMIT, store=False)
    return counted.selectExpr("doc_id", "n_bytes", "n_tokens", f"n_tokens > {LIMIT} AS over_limit", "prefix_chars")
