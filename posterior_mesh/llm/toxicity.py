"""Toxicity by a weighted lexicon, matched with Aho-Corasick over folded text.

Folding lower-cases, drops invisible characters, and maps homoglyphs, compatibility forms and digit
substitutions to letters. The lexicon is learned: words and word stems that toxic rows hold far more
often than others, near copies counted once, each with its log odds as weight. Exception phrases (an entry inside a harmless phrase) cancel the
matches that they cover. A text's weight per word goes through a fitted logistic curve.

Defined cases: null, empty and wordless texts have weight 0; with no toxic or no other labelled row
the lexicon is empty and all scores are 0; repeated rows each give a row.
"""

from __future__ import annotations

import pickle
import re
import unicodedata
from collections import Counter
from functools import lru_cache
from math import log

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import held_out, load, slices
from .models import apart, fit_logistic, sample_of

# Look-alike letters of other scripts, and digits and signs that stand for letters.
HOMOGLYPHS = dict(zip("аеорсухіјѕԁһкмтвнαεορυικτνß", "aeopcyxijsdhkmtbhaeopuiktvs"))
SUBSTITUTES = dict(zip("013457@$!|", "oieasta" + "sil"))
EXCEPTIONS = ("clown fish", "trash can", "scum line")

LETTERS = re.compile(r"[^\W\d_]+")
#: Letters of a stem.
SHORTEST, LONGEST = 3, 12


class Folding(dict):
    """For str.translate: one character to its folded form, worked out once."""

    def __missing__(self, point: int) -> str:
        c = chr(point)
        plain = unicodedata.normalize("NFKC", c)
        out = "".join(HOMOGLYPHS.get(x, x) for x in plain.lower())
        if unicodedata.category(c) == "Cf":
            out = ""
        self[point] = out
        return out


FOLD = Folding()
TO_LETTERS = str.maketrans(SUBSTITUTES)
ONE_AS_L = TO_LETTERS | {ord("1"): "l"}
#: A digit or sign stands for a letter only beside letters.
INSIDE = re.compile(r"(?<=[a-z])[013457@$!|]+(?=[a-z])|(?<![a-z0-9@$!|])[013457@$]+(?=[a-z])|(?<=[a-z])[013457@$]+(?![a-z0-9])")


def fold(text: str, letters: dict = TO_LETTERS) -> str:
    text = text.lower() if text.isascii() else text.translate(FOLD)
    return INSIDE.sub(lambda m: m[0].translate(letters), text)


def stems_of(text: str) -> set[str]:
    """The beginnings of a folded text's words, of ``SHORTEST`` letters on; a whole word ends in a space."""
    words = {w for w in LETTERS.findall(fold(text)) if len(w) >= SHORTEST}
    return {w[:n] for w in words for n in range(SHORTEST, min(len(w), LONGEST) + 1)} | {w + " " for w in words}


def learn_lexicon(texts: list[str], toxic: np.ndarray, least: int = 4, share: float = 0.01, odds: float = 1.5, evidence: float = 18.0) -> dict[str, float]:
    """Words and stems with their log odds of being in a toxic text.

    An entry is in ``least`` toxic texts and a ``share`` of them, has log odds of ``odds`` and a likelihood
    ratio of ``evidence`` against equal frequency. Of entries that begin alike the one with most evidence
    stays, and the longer of almost equals, so a stem stands for all its endings.
    """
    keep = np.zeros(len(texts), bool)
    for kind in (0, 1):
        of = np.flatnonzero(toxic == kind)
        keep[of] = apart([texts[i] for i in of])
    n = [int((keep & (toxic == k)).sum()) for k in (0, 1)]
    if not min(n):
        return {}
    found = Counter(x for i in np.flatnonzero(keep & (toxic == 1)) for x in stems_of(texts[i]))
    found = {x: a for x, a in found.items() if a >= max(least, share * n[1])}
    other: Counter = Counter()
    for i in np.flatnonzero(keep & (toxic == 0)):
        other.update(stems_of(texts[i]) & found.keys())
    ranked = []
    for x, a in found.items():
        b, part = other[x], n[1] / sum(n)
        weight = log((a + 0.5) / (n[1] + 1)) - log((b + 0.5) / (n[0] + 1))
        ratio = 2 * (a * log(a / ((a + b) * part)) + (b * log(b / ((a + b) * (1 - part))) if b else 0))
        if weight >= odds and ratio >= evidence:
            ranked.append((-round(log(ratio) / 0.03), -len(x), x, weight))
    lexicon: dict[str, float] = {}
    for _, _, x, weight in sorted(ranked):
        if not any(x.startswith(y) or y.startswith(x) for y in lexicon):
            lexicon[x] = round(weight, 6)
    return lexicon


def learn_exceptions(texts: list[str], toxic: np.ndarray, lexicon: dict[str, float], least: int = 3) -> tuple[str, ...]:
    """Pairs of words around an entry's match that ``least`` texts hold, none of them toxic and near copies counted once."""
    found: tuple[Counter, Counter] = (Counter(), Counter())
    for kind in (0, 1):
        of = [t for t, x in zip(texts, toxic) if x == kind]
        # what one toxic text holds isn't harmless, so toxic copies needn't be told apart
        for text in (t for t, own in zip(of, apart(of) if kind == 0 else np.ones(len(of), bool)) if own):
            folded = fold(text)
            words = [m.span() for m in LETTERS.finditer(folded)]
            hit = [f"{folded[a:b]} " in lexicon or any(folded[a : a + n] in lexicon for n in range(SHORTEST, min(b - a, LONGEST) + 1)) for a, b in words]
            pairs = zip(words, words[1:], hit, hit[1:])
            found[kind].update({folded[a:d] for (a, b), (c, d), left, right in pairs if left != right and folded[b:c] == " "})
    return tuple(sorted(x for x, n in found[0].items() if n >= least and not found[1][x]))


class Matcher:
    """Aho-Corasick over the lexicon and the exception phrases; matches begin where a word does."""

    def __init__(self, lexicon: dict[str, float], exceptions: tuple[str, ...] = EXCEPTIONS):
        import ahocorasick

        self.automaton = ahocorasick.Automaton()
        for entry, weight in lexicon.items():
            word = entry.rstrip()
            self.automaton.add_word(word, (len(word), weight, word != entry))
        for phrase in exceptions:
            self.automaton.add_word(phrase, (len(phrase), None, True))
        self.empty = not lexicon
        self.automaton.make_automaton()

    def weigh(self, text: str) -> tuple[float, int]:
        """Summed weights of the matches outside exception phrases, and how many words the text has; 1 is read as i or as l."""
        weight, words = self._weigh(fold(text))
        return (max(weight, self._weigh(fold(text, ONE_AS_L))[0]) if "1" in text else weight), words

    def _weigh(self, folded: str) -> tuple[float, int]:
        words = folded.count(" ") + folded.count("\n") + 1
        if self.empty:
            return 0.0, words
        hits, spared = [], []
        for last, (n, weight, whole) in self.automaton.iter(folded):
            first, past = last - n + 1, last + 1
            if (first and folded[first - 1].isalnum()) or (whole and past < len(folded) and folded[past].isalnum()):
                continue
            (spared if weight is None else hits).append((first, past, weight))
        if spared:
            hits = [h for h in hits if not any(a <= h[0] and h[1] <= b for a, b, _ in spared)]
        return sum(h[2] for h in hits), words


def density(weight: float, words: int) -> float:
    """The feature of a text: its weight per 100 words, on a log scale; very short texts count as 12 words."""
    return log(1 + 100 * weight / max(words, 12))


def fit(docs: DataFrame, labels: DataFrame, rows: int = 1500, exceptions: tuple[str, ...] = EXCEPTIONS) -> dict:
    """Lexicon, exceptions and curve from at most ``rows`` labelled rows of each class outside the test fold; ``exceptions`` are given ones."""
    known = sample_of(docs, labels, "toxic", rows)
    texts, toxic = known["text"].tolist(), known["label"].to_numpy(np.int64)
    lexicon = learn_lexicon(texts, toxic)
    exceptions = tuple({*exceptions, *learn_exceptions(texts, toxic, lexicon)})
    matcher = Matcher(lexicon, exceptions)
    x = np.array([density(*matcher.weigh(t)) for t in texts])[:, None] if texts else np.zeros((0, 1))
    if len({*toxic}) < 2 or not lexicon:
        return {"lexicon": lexicon, "exceptions": exceptions, "curve": (0.0, -30.0)}
    own = np.where(toxic == 1, len(toxic) / (2 * max(1, toxic.sum())), len(toxic) / (2 * max(1, (1 - toxic).sum())))
    w = fit_logistic(x, toxic, 1e-4, own)
    return {"lexicon": lexicon, "exceptions": exceptions, "curve": (float(w[0]), float(w[1]))}


@lru_cache(1)
def opened(raw: bytes) -> tuple[Matcher, tuple[float, float]]:
    model = pickle.loads(raw)
    return Matcher(model["lexicon"], model["exceptions"]), model["curve"]


def score_texts(texts: list[str | None], raw: bytes) -> np.ndarray:
    matcher, (slope, constant) = opened(raw)
    x = np.array([density(*matcher.weigh(t)) if t else 0.0 for t in texts])
    return 1 / (1 + np.exp(-np.clip(slope * x + constant, -30, 30)))


def score(docs: DataFrame, model: dict) -> DataFrame:
    """doc_id, score, weight per word unseen: one row for each row."""
    raw = pickle.dumps(model)

    def run(batches):
        for batch in slices(batches):
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(score_texts(batch.column(1).to_pylist(), raw), pa.float64())], ["doc_id", "score"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, score double")


def without_toxic(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The rows that score under 0.5, all their columns."""
    raw, at = pickle.dumps(fit(docs, labels)), docs.columns.index("text")

    def run(batches):
        for batch in batches:
            for first in range(0, batch.num_rows, 2000):
                part = batch.slice(first, 2000)
                yield part.filter(pa.array(score_texts(part.column(at).to_pylist(), raw) < 0.5))

    return docs.mapInArrow(run, docs.schema)


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    scored = score(docs, fit(docs, load(spark, sf_dir, "labels")))
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
