"""The queries' columns against plain Python, whole pipeline runs against brute force, and odd tables."""

import hashlib
import random
import re
import zlib
from collections import Counter

import pytest

from posterior_mesh.llm import chat_format, decontaminate, language_id, media_columns, models, ngram_join, packing, quality, suffix_dedup, token_counts, toxicity

TOKENIZERS = pytest.importorskip("public_tokenizers")
DOCS = "doc_id long, text string, lang string, source string, n_chars long, n_tokens int, key string, digest string, spans int"


def sha(text: bytes) -> str:
    return hashlib.sha256(text).hexdigest()


def docs_of(spark, texts, first=0):
    return spark.createDataFrame([(i, t, "en", "s", None, 0, "x", "d", 1) for i, t in enumerate(texts, first)], DOCS)


def stored(spark, folder, **tables):
    for name, df in tables.items():
        df.write.parquet(f"{folder}/{name}.parquet")
    return str(folder)


@pytest.fixture(scope="module")
def odd_texts():
    rng = random.Random(8)
    long = " ".join("".join(rng.choice("abcdefghij") for _ in range(6)) for _ in range(160_000))
    return [None, "", " ", "!?", "Ünïcode 漢字 <|endoftext|> I'll", "same text", "same text", "x" * 5000, long]


def test_media_of_every_text(spark, tmp_path, odd_texts):
    got = sorted(media_columns.op2_media_columns(spark, stored(spark, tmp_path, documents=docs_of(spark, odd_texts))).collect())
    for row, text in zip(got, odd_texts, strict=True):
        raw = (text or "").encode()
        payload = raw + bytes(-len(raw) % 64 if raw else 64)
        assert (row["n_bytes"], row["payload_bytes"], row["payload_sha256"], row["tail_crc32"]) == (len(raw), len(payload), sha(payload), zlib.crc32(payload[-64:]))
        file = media_columns.write_matroska(payload)
        assert (row["media_bytes"], row["media_sha256"]) == (len(file), sha(file))
    assert got[5][1:] == got[6][1:]


def test_counts_and_pieces_of_every_text(spark, tmp_path, odd_texts):
    from tokenizers import Tokenizer

    folder = stored(spark, tmp_path, documents=docs_of(spark, odd_texts))
    library = Tokenizer.from_file(TOKENIZERS.path("byte_bpe_50k.json"))
    want = [len(library.encode(t or "", add_special_tokens=False).ids) for t in odd_texts]
    got = sorted(token_counts.op1_token_counts(spark, folder).collect())
    assert [(r["n_bytes"], r["n_tokens"], r["over_limit"]) for r in got] == [(len((t or "").encode()), n, n > 1024) for t, n in zip(odd_texts, want)]
    library, want = Tokenizer.from_file(TOKENIZERS.path("word_bpe_49k.json")), []
    for i, t in enumerate(odd_texts):
        ids = [*library.encode(t or "", add_special_tokens=False).ids, 1]
        want += [(i, k // 4096, k, len(p := ids[k : k + 4096]), zlib.crc32(b"".join(x.to_bytes(4, "little") for x in p))) for k in range(0, len(ids), 4096)]
    rows = packing.op10_best_fit_packing(spark, folder).collect()
    assert sorted((r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in rows) == want
    ends = {}
    for r in sorted(rows, key=lambda r: (r["sequence_id"], r["offset"])):
        assert r["offset"] == ends.get(r["sequence_id"], 0)
        ends[r["sequence_id"]] = r["offset"] + r["length"]
    assert max(ends.values()) <= 4096


def test_digests_of_conversations(spark, tmp_path):
    rng, said, talks = random.Random(6), f"{chat_format.END}{chat_format.START}assistant ok", []
    bits = ["a word ", "<|", "\\", "<\\|", "|>", "<", "\n", chat_format.START, chat_format.END, "ü 漢 ", ""]
    for conv in range(12):
        talks.append((conv, 0, "system" if conv % 2 else "user", "be brief"))
        talks += [(conv, k, rng.choice(["user", "assistant"]), rng.choice([None, "".join(rng.choices(bits, k=rng.randint(0, 300)))])) for k in range(1, rng.randint(2, 30))]
    frame = spark.createDataFrame([(*t, "x") for t in talks], "conv_id long, turn long, role string, text string, w string")
    got = {r["conv_id"]: r for r in chat_format.op6_chat_format(spark, stored(spark, tmp_path, conversations=frame)).collect()}
    talks += [(-1, 0, "user", said), (-1, 1, "assistant", said)]
    assert {*got} == {t[0] for t in talks}
    for conv, row in got.items():
        turns = [(role, text or "") for c, _, role, text in talks if c == conv]
        loss = "".join(text for role, text in turns if role == "assistant")
        assert (row["n_turns"], row["turns_sha256"]) == (len(turns), sha("".join(f"{r}\n{t}\n" for r, t in turns).encode()))
        assert (row["loss_chars"], row["loss_sha256"]) == (len(loss), sha(loss.encode())) and row["formatted_chars"] > 0


def test_classes_of_a_sample_have_no_bound(spark):
    rows = [(i, f"text {i}", f"l{i % 230:03}") for i in range(2300)] + [(9000, "y" * 50_000, "l000")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    got = models.sample_of(docs, docs, "lang", rows=5)
    assert got["label"].nunique() == 230 and got.groupby("label").size().max() <= 5
    assert models.sample_of(docs, docs, "lang", rows=5, chars=30).groupby("label")["text"].apply(lambda t: t.str.len().sum()).max() <= 30


def test_exceptions_are_learned_from_clean_rows():
    rng = random.Random(1)
    word = lambda: "".join(rng.choice("abcdefghij") for _ in range(6))
    filler = lambda: " ".join(word() for _ in range(30))
    texts = [f"{filler()} you moron {filler()}" for _ in range(30)] + [f"{filler()} moron valley {filler()}" for _ in range(5)] + [filler() for _ in range(30)]
    toxic = [1] * 30 + [0] * 35
    import numpy as np

    learned = toxicity.learn_exceptions(texts, np.array(toxic), {"moron ": 4.0})
    assert learned == ("moron valley",)
    matcher = toxicity.Matcher({"moron ": 4.0}, learned)
    assert matcher.weigh("off to moron valley")[0] == 0 and matcher.weigh("a moron in a valley")[0] == 4


def test_a_view_without_evidence_labels_nothing():
    import numpy as np

    rng = np.random.default_rng(2)
    y = (rng.random(400) < 0.85).astype(float)
    low, high = quality.sure_logits(1.7 + 0.3 * rng.normal(size=400), y)
    assert low < 0.5 and high > 3  # beyond what such logits reach
    low, high = quality.sure_logits(4 * y - 2 + rng.normal(size=400), y)
    assert -2.5 < low < high < 3


def brute_cut(texts: list[str], least: int = 400, words: int = 51) -> list[str]:
    """Without strings of ``least`` characters, and runs of ``words`` words, that stand anywhere else too."""
    at = [[m.span() for m in re.finditer(r"\S+", t)] for t in texts]
    spans = [[(i, i + least) for i in range(len(t) - least + 1)] for t in texts]
    runs = [[(w[i][0], w[i + words - 1][1]) for i in range(len(w) - words + 1)] for w in at]
    out = []
    seen = [Counter(t[a:b] for t, own in zip(texts, of) for a, b in own) for of in (spans, runs)]
    for k, t in enumerate(texts):
        gone = {i for of, n in zip((spans, runs), seen) for a, b in of[k] if n[t[a:b]] > 1 for i in range(a, b)}
        out.append("".join(c for i, c in enumerate(t) if i not in gone))
    return out


def test_pipeline_against_brute_force(spark, tmp_path):
    import corpus_pipeline

    rng = random.Random(21)
    word = lambda: "".join(rng.choice("bcdfghjklm") for _ in range(6))
    words = lambda n: [word() for _ in range(n)]
    item, passage, base = words(40), words(60), words(200)
    near = [*base[:100], word(), *base[101:]]
    texts = {k: " ".join(words(80)) for k in range(300, 330)}  # clean
    texts |= {k: " ".join([*words(20), "moron", "moron", *words(20)]) for k in range(100, 200)}
    texts |= {k: " ".join(words(60)) for k in range(200, 300)}
    texts |= {1: " ".join(base), 2: " ".join(near), 3: " ".join(base)}
    texts |= {k: " ".join([*words(150), *passage, *words(150)]) for k in (4, 5)}
    texts |= {6: " ".join([*words(100), *item, *words(100)]), 7: "", 8: None}
    docs = spark.createDataFrame([(k, t, "en", "s", None) for k, t in sorted(texts.items())], "doc_id long, text string, lang string, source string, n_chars long")
    labels = spark.createDataFrame([(k, int(k < 200)) for k in range(100, 300)], "doc_id long, toxic int")
    bench = spark.createDataFrame([(1, " ".join(item))], "item_id long, text string")
    folder = stored(spark, tmp_path, documents=docs, labels=labels, benchmark=bench)
    held = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        held = stage(spark, held, folder)
        assert held.columns == docs.columns, name
    kept = {r["doc_id"]: r["text"] for r in held.collect()}
    gone = {k for k, t in texts.items() if t and "moron" in t} | {2, 3, 6}
    want = {k: t for k, t in texts.items() if k not in gone}
    # the contaminated text goes after the cut, and shares nothing with others
    want = dict(zip(want, brute_cut([t or "" for t in want.values()])))
    assert all(" ".join(passage) not in want[k] and len(want[k]) > 2000 for k in (4, 5))
    assert {k: t or "" for k, t in kept.items()} == want
    packed = corpus_pipeline.run(spark, folder).collect()
    assert {r["doc_id"] for r in packed} == want.keys() and all(r["length"] <= 4096 for r in packed)


def test_empty_tables_and_null_ids(spark):
    none, labels = docs_of(spark, []), spark.createDataFrame([], "doc_id long, toxic int, quality int")
    bench = spark.createDataFrame([], "item_id long, text string")
    assert token_counts.prefix_tables(none, TOKENIZERS.path("byte_bpe_50k.json"), 1).count() == 0
    assert toxicity.without_toxic(none, labels).count() == 0 and quality.score(none, quality.fit(none, labels)).count() == 0
    assert language_id.identify(none, language_id.fit(none)).count() == 0 and decontaminate.decontaminate(none, bench).count() == 0
    assert ngram_join.one_of_each(none).count() == 0 and suffix_dedup.without_repeats(none, words=51).count() == 0
    lone = spark.createDataFrame([(None, "a b c d e f", "en", "s", None, 0, "x", "d", 1), (3, "g h i j k l", "en", "s", None, 0, "x", "d", 1)], DOCS)
    assert sorted(r["text"] for r in suffix_dedup.without_repeats(lone, words=51).collect()) == ["a b c d e f", "g h i j k l"]
    assert decontaminate.decontaminate(lone, bench).count() == 2 and packing.pack_documents(lone).count() == 2
