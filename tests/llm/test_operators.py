"""Small tables with nulls, empty and repeated rows, against the libraries and brute force."""

import random
import re
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest

from posterior_mesh.llm import chat_format, decontaminate, language_id, media_columns, ngram_join, packing, suffix_dedup, token_counts, toxicity

TOKENIZERS = pytest.importorskip("public_tokenizers")
DOCS = "doc_id long, text string, lang string, source string, n_chars long, n_tokens int, key string"


def rows_of(texts):
    return [(i, t, "en", "s", None, 0, "x") for i, t in enumerate(texts)]


def docs_of(spark, texts):
    return spark.createDataFrame(rows_of(texts), DOCS)


def test_prefix_tables_are_exact():
    from tokenizers import Tokenizer

    path, rng = TOKENIZERS.path("byte_bpe_50k.json"), random.Random(3)
    library, table = Tokenizer.from_file(path), token_counts.PrefixTable(path)
    bits = ["a", "the", " ", "  ", "\n", "'re", "'l", "!", "<|endoftext|>", "<|end", "é", "漢", "12", "\t", "ing", "Don't", "🙂", " ", "　"]
    for _ in range(150):
        text = "".join(rng.choice(bits) for _ in range(rng.randint(0, 12)))
        want = [len(library.encode(text[:i], add_special_tokens=False).ids) for i in range(1, len(text) + 1)]
        changes = table.changes([text])[0]
        assert np.cumsum(np.frombuffer(changes, np.int8)).tolist() == want
        fits = [i for i, n in enumerate(want, 1) if n <= 3]
        assert token_counts.longest_prefix(changes, 3) == (fits[-1] if fits else 0)


def test_token_counts_of_odd_rows(spark):
    got = token_counts.prefix_tables(docs_of(spark, [None, "", "a b", "a b"]), TOKENIZERS.path("byte_bpe_50k.json"), 1).collect()
    assert [(r["n_bytes"], r["n_tokens"], r["prefix_chars"]) for r in got] == [(0, 0, 0), (0, 0, 0), (3, 2, 1), (3, 2, 1)]


def test_matroska_round_trip():
    for n in (64, 512, 4096, 4160, 70000):
        payload = random.Random(n).randbytes(n)
        file = media_columns.write_matroska(payload)
        assert media_columns.payload_of(file) == payload
        found = media_columns.parse_matroska(file)
        assert found["tracks"][0]["depth"] == 8 and all(file[at : at + 4] == bytes.fromhex("1f43b675") for _, _, at in found["cues"])
    for kind in (1, 3):
        frames = [bytes([k]) * n for k, n in enumerate((3, 600, 255, 40))]
        data = memoryview(media_columns.laced(frames, kind))
        assert [bytes(data[a : a + n]) for a, n in media_columns.frames_of(data, 0, len(data), kind)] == frames
    with pytest.raises(ValueError):
        media_columns.parse_matroska(media_columns.write_matroska(bytes(64))[:-5])


def test_windows_keep_every_turn(spark):
    talks = [(1, 0, "system", "be brief"), (1, 1, "user", "q " * 400), (1, 2, "assistant", r"a <|im_end|> \ <\| b"), (1, 3, "user", None), (1, 4, "assistant", "z " * 300), (2, 0, None, "x"), (2, 0, None, "x")]
    turns = spark.createDataFrame(talks, "conv_id long, turn long, role string, text string")
    windows = chat_format.format_windows(turns)
    got = {r["conv_id"]: r for r in chat_format.read_back(windows).collect()}
    assert got[1]["n_turns"] == 5 and got[2]["n_turns"] == 2 and got[1]["loss_chars"] == len(talks[2][3]) + len(talks[4][3])
    later = [r for r in windows.collect() if r["window"] > 0]
    assert later and all(r["formatted"].startswith("<|im_start|>system\n") for r in later)


def test_spans_of_benchmark(spark):
    items = [(1, " ".join(f"w{i}" for i in range(20))), (2, "tiny item"), (3, None), (4, "!!")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    texts = [None, "", "a Tiny ITEM b", " ".join(f"w{i}" for i in range(3, 17)), " ".join(f"w{i}" for i in range(12)), "x " * 300 + "tiny item"]
    for most in (500_000, 3):
        got = [r for r in decontaminate.find_contamination(docs_of(spark, texts), bench, most=most).collect()]
        assert [(r["n_words"], r["spans"], r["items"]) for r in got] == [(0, [], []), (0, [], []), (4, [[1, 3]], ["2"]), (14, [[0, 14]], ["1"]), (12, [], []), (302, [[300, 302]], ["2"])]
    assert [r["doc_id"] for r in decontaminate.decontaminate(docs_of(spark, texts), bench).collect()] == [0, 1, 4, 5]


def brute_components(texts, words, percent):
    sets = []
    for t in texts:
        w = re.findall(r"[^\x20\x09-\x0D]+", (t or "").lower())
        sets.append({tuple(w[i : i + words]) for i in range(len(w) - words + 1)} if len(w) >= words else {tuple(w)} if w else set())
    up = list(range(len(texts)))
    for _ in texts:
        for i, a in enumerate(sets):
            for j, b in enumerate(sets):
                if a and b and 100 * len(a & b) >= percent * len(a | b):
                    up[i] = up[j] = min(up[i], up[j])
    return [(len(s), u) for s, u in zip(sets, up)]


@pytest.mark.parametrize("options", [{}, {"part_sets": 4}])
def test_links_against_all_pairs(spark, options):
    rng = random.Random(5)
    word = lambda: "".join(rng.choice("abcdef") for _ in range(4))
    passage = [word() for _ in range(30)]
    texts = [None, "", "  ", "one two", "One  Two", "three"]
    for _ in range(8):
        base = [word() for _ in range(rng.randint(20, 150))]
        for _ in range(rng.randint(1, 6)):
            own = list(base)
            for _ in range(rng.randint(0, 3)):
                own[rng.randrange(len(own))] = word()
            texts.append(" ".join(own + passage * rng.randint(0, 1)))
    got = sorted(ngram_join.similarity_components(docs_of(spark, texts), **options).collect())
    assert [(r["n_shingles"], r["component_id"]) for r in got] == brute_components(texts, 4, 85)


@pytest.mark.parametrize("options", [{"part_sets": 2}, {"part_sets": 40, "part_items": 200}])
def test_links_between_parts_of_a_block(spark, options, monkeypatch):
    # sets near the threshold, most without a common smallest hash: blocks of many components, in parts
    asked, across = [], ngram_join.across_parts
    monkeypatch.setattr(ngram_join, "across_parts", lambda *args: asked.append(1) or across(*args))
    monkeypatch.setattr(ngram_join, "COUNTERS", ngram_join.COUNTERS[:1])
    rng = random.Random(23)
    word = lambda: "".join(rng.choice("abcdef") for _ in range(4))
    texts = []
    for _ in range(3):
        base = [word() for _ in range(90)]
        for _ in range(16):
            own = list(base)
            for _ in range(rng.randint(1, 2)):
                own[rng.randrange(len(own))] = word()
            texts.append(" ".join(own))
    want = brute_components(texts, 4, 85)
    assert 3 < len({u for _, u in want}) < len(texts)
    got = sorted(ngram_join.similarity_components(docs_of(spark, texts), **options).collect())
    assert [(r["n_shingles"], r["component_id"]) for r in got] == want and asked


def test_items_without_an_id_are_hit_as_in_sql(spark):
    item, other = ("w%d " * 20 % tuple(range(20))).strip(), ("v%d " * 20 % tuple(range(20))).strip()
    docs, benchmark = docs_of(spark, [item, f"{item} {other}", "free"]), spark.createDataFrame([(None, item), (7, other)], "item_id long, text string")
    got = sorted(decontaminate.verdicts(docs, benchmark).collect())
    assert [(r["n_hit"], r["n_items"], r["contaminated"]) for r in got] == [(20, 1, True), (40, 2, True), (0, 0, False)]
    assert got[0]["items_sha256"] == got[2]["items_sha256"] != got[1]["items_sha256"]
    import duckdb

    with duckdb.connect() as db:
        db.execute("CREATE TABLE documents (doc_id BIGINT, text VARCHAR); CREATE TABLE benchmark (item_id BIGINT, text VARCHAR)")
        db.executemany("INSERT INTO documents VALUES (?, ?)", [(0, item), (1, f"{item} {other}"), (2, "free")])
        db.executemany("INSERT INTO benchmark VALUES (?, ?)", [(None, item), (7, other)])
        assert sorted(db.execute(decontaminate.OP7_SQL).fetchall()) == [tuple(r) for r in got]
    assert [r["text"] for r in decontaminate.decontaminate(docs, benchmark).collect()] == ["free"]


@pytest.mark.parametrize("n", [1, 2, 3, 4])
def test_sets_of_a_slice_with_few_words(spark, n):
    text = " ".join("abcd"[:n])
    rows = ngram_join.similarity_components(docs_of(spark, [text]), 4, 85).collect()
    assert [(r["n_shingles"], r["component_id"]) for r in rows] == [(1, 0)]
    assert [len(s) for s in ngram_join.shingle_sets(pa.array([text]), 5)] == [1]


def brute_removed(texts, least):
    seen = Counter(b[i : i + least] for b in texts for i in range(len(b) - least + 1))
    out = []
    for b in texts:
        hit = np.zeros(len(b), bool)
        for i in range(len(b) - least + 1):
            if seen[b[i : i + least]] > 1:
                hit[i : i + least] = True
        out.append(int(hit.sum()))
    return out


@pytest.mark.parametrize("part", [2000, 3])
def test_repeats_against_all_windows(spark, part, monkeypatch):
    monkeypatch.setattr(suffix_dedup.repeated_spans, "__defaults__", (400, part))
    rng = random.Random(9)
    text = lambda n: "".join(rng.choice("abcdé ") for _ in range(n))
    shared = [text(500), text(395), text(900)]
    texts = [None, "", "ab" * 600, "ab" * 600, text(2000)]
    texts += [" ".join(f"{w} " * 11 for w in ("orshea", "the.", "intihe", "onen", "with", "of", "thedwhha", "and", "so", "lyon")), "x" * 399 + "y" * 399]
    texts += [text(rng.randint(0, 300)) + rng.choice(shared) + text(rng.randint(0, 300)) for _ in range(14)]
    got = sorted(suffix_dedup.dedup_report(docs_of(spark, texts)).collect())
    assert [r["n_removed"] for r in got] == brute_removed([(t or "").encode() for t in texts], 400)


@pytest.mark.parametrize("part", [2000, 3])
def test_passage_words_of_the_report(spark, part, monkeypatch):
    monkeypatch.setattr(suffix_dedup.repeated_spans, "__defaults__", (400, part))
    rng = random.Random(13)
    words = lambda n: " ".join("".join(rng.choice("abcdefghij") for _ in range(rng.randint(4, 6))) for _ in range(n))
    passage, shorter, long = words(55), words(50), words(90)
    texts = [f"{words(40)} {mid} {words(40)}" for mid in (passage,) * 8 + (shorter,) * 2 + (long,) * 2] + [words(60)] * 2 + [words(100), None, ""]
    got = sorted(suffix_dedup.dedup_report(docs_of(spark, texts)).collect())
    assert 250 <= len(passage) < 400 <= len(long)
    assert [r["passage_words"] for r in got] == [55] * 8 + [0] * 2 + [90] * 2 + [60] * 2 + [0] * 3
    assert [r["n_removed"] > 0 for r in got] == [False] * 10 + [True] * 2 + [len(texts[12]) >= 400] * 2 + [False] * 3


@pytest.mark.parametrize("part", [2000, 3])
def test_stage_cuts_passages_of_over_fifty_words(spark, part, monkeypatch):
    import corpus_pipeline

    monkeypatch.setattr(suffix_dedup.repeated_spans, "__defaults__", (400, part))
    rng = random.Random(11)
    words = lambda n, least=4: " ".join("".join(rng.choice("abcdefghij") for _ in range(rng.randint(least, 6))) for _ in range(n))
    passage, shorter, brief, whole = words(51), words(50), " ".join(rng.choice("abcdefghijklmnopqrst") for _ in range(51)), words(51)
    parts = [(words(40), mid, words(40)) for mid in (passage,) * 8 + (shorter, shorter, brief, brief)]
    assert len(passage) < 400 and len(brief) == 101
    docs = docs_of(spark, [*(" ".join(p) for p in parts), whole, whole, words(30), None, ""])
    got = [r["text"] for r in sorted(corpus_pipeline.suffix_array_dedup(spark, docs, "").collect())]
    assert got[:14] == [*(f"{a}  {c}" if mid != shorter else f"{a} {mid} {c}" for a, mid, c in parts), "", ""]


def test_contexts_of_templates_have_hashes_of_their_own(spark):
    rng = random.Random(4)
    place = []
    while 368 not in place:  # an anchor whose context is the whole text
        base = bytearray(rng.choice(b"abcdefghijkl") for _ in range(768))
        place, _ = suffix_dedup.anchors(np.frombuffer(bytes(base), np.uint8), np.array([0, 768]), 400)
    texts = []
    for a, b in [(7, 15), (15, 31), (23, 47), (7, 63), (31, 95), (39, 103)]:  # bytes that are eighth in their words
        for x in range(48, 58):
            for y in range(48, 58):
                one = bytearray(base)
                one[a], one[b] = x, y
                texts.append(bytes(one).decode())
    texts = sorted({*texts})
    table = suffix_dedup.anchor_table(docs_of(spark, texts), 400).selectExpr("explode(arrays_zip(c, low, high)) AS x").where("x.high - x.low = 768").select("x.c")
    hashes = [r["c"] for r in table.collect()]
    assert len(hashes) == len({*hashes}) == len(texts)


def test_maximal_repeats_have_all_occurrences():
    array = suffix_dedup.SuffixArray([b"xabcdeabcdy", b"zabcdq"], 4)
    found = {(n, tuple(sorted(array.order[a:b].tolist()))) for n, a, b in array.maximal_repeats(4)}
    assert found == {(4, (2, 7, 14))}


def test_packing_is_whole_and_tight(spark):
    rng = random.Random(2)
    counts = Counter(rng.randint(1, 100) for _ in range(3000))
    rows = packing.plan(dict(counts), 100)
    assert Counter({n: sum(b - a for m, a, b, *_ in rows if m == n) for n in counts}) == counts
    used = Counter()
    for n, a, b, sequence, offset in rows:
        for k in range(b - a):
            used[sequence + k] += n
    assert max(used.values()) <= 100 and len(used) <= 1.02 * -(-sum(n * c for n, c in counts.items()) // 100) + 1
    got = packing.pack_documents(docs_of(spark, [None, "", "hello world", "hello world"])).collect()
    assert sorted((r["doc_id"], r["length"]) for r in got) == [(0, 1), (1, 1), (2, 3), (3, 3)] and len({(r["sequence_id"], r["offset"]) for r in got}) == 4
    assert packing.pack_documents(docs_of(spark, [])).count() == 0


def test_toxicity_folds_and_spares(spark):
    matcher = toxicity.Matcher({"clown ": 5.0, "idiot": 5.0})
    assert matcher.weigh("You id10t")[0] == 5 and matcher.weigh("a c1оwn")[0] == 5 and matcher.weigh("a clown fish")[0] == 0 and matcher.weigh("idiots")[0] == 5 and matcher.weigh("clownish")[0] == 0
    labels = spark.createDataFrame([], "doc_id long, toxic int")
    assert toxicity.without_toxic(docs_of(spark, [None, "", "x"]), labels).count() == 3


def test_language_of_odd_rows(spark):
    texts = ["the house and the tree"] * 20 + ["das haus und der baum"] * 20 + [None, "", "123 !!"]
    rows = [(i, t, "en" if i < 20 else "de" if i < 40 else None) for i, t in enumerate(texts)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    got = {r["doc_id"]: r["lang_pred"] for r in language_id.identify(docs, language_id.fit(docs)).collect()}
    assert got[0] == "en" and got[25] == "de" and {got[40], got[41], got[42]} == {"und"}


def test_repeats_of_the_query_have_the_columns_and_rows_of_its_sql(spark, sf):
    import duckdb

    from posterior_mesh.llm.queries import OP9_SQL

    got = suffix_dedup.op9_suffix_dedup(spark, sf)
    with duckdb.connect() as db:
        db.execute(f"CREATE VIEW documents AS SELECT * FROM '{sf}/documents.parquet'")
        want = db.execute(OP9_SQL)
        assert got.columns == [c[0] for c in want.description]
        assert sorted(tuple(r) for r in got.collect()) == sorted(want.fetchall())


def test_passages_of_over_fifty_words_stay_under_400_bytes(spark, tmp_path):
    import duckdb

    from posterior_mesh.llm.queries import OP9_SQL

    rng = random.Random(17)
    words = lambda n: " ".join("".join(rng.choice("abcdefghij") for _ in range(rng.randint(4, 6))) for _ in range(n))
    passages = [words(90)[:n] + "z" for n in (398, 399)]
    texts = [f"{words(40)} {k}{passage}{k} {words(40)}" for passage in passages for k in range(6)]
    docs_of(spark, texts).write.parquet(str(tmp_path / "documents.parquet"))
    got = sorted(suffix_dedup.op9_suffix_dedup(spark, str(tmp_path)).collect())
    assert [len(p) for p in passages] == [399, 400] and all(len(p.split()) > 50 for p in passages)
    assert [(r["n_removed"], r["n_spans"]) for r in got] == [(0, 0)] * 6 + [(400, 1)] * 6
    with duckdb.connect() as db:
        db.execute(f"CREATE VIEW documents AS SELECT * FROM '{tmp_path}/documents.parquet/*.parquet'")
        assert [tuple(r) for r in got] == sorted(db.execute(OP9_SQL).fetchall())
