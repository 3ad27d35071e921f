"""Each operator against brute force, an exact round trip or held-out accuracy, with nulls, empty tables, ties and clashing names."""

import os
import random
import re
import time
import zlib

import duckdb
import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from deltamp.llm import chat, decontaminate, language, licences, main_text, near_duplicates, neighbours, packing, quality, queries, token_counts, tokenfsm
from deltamp.llm.common import dealt, hot_keys
from deltamp.llm.components import components

PATH = public_tokenizers.path("byte_bpe_50k.json")
SF = "/root/testdata/sf0.001"
DOCS = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SF}/documents.parquet")


def _docs(spark, texts):
    return spark.createDataFrame([(i, t, None, None, None) for i, t in enumerate(texts)], DOCS)


ODD = [None, "", " ", "a", "A", "!!!", "x " * 3000, "same text here", "same text here", "é1 日本 'S don't"]


@pytest.mark.parametrize("name", ["op3_chat", "op7_licences", "op8_near_duplicates", "op10_decontamination"])
def test_sql_twins(spark, name):
    got = queries.QUERIES[name](spark, SF).toPandas()
    c = duckdb.connect()
    for t in ("documents", "benchmark", "conversations"):
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    want = c.sql(queries.ORACLE[name]).df()[list(got.columns)]
    key = list(got.columns)
    assert got.astype(str).sort_values(key).values.tolist() == want.astype(str).sort_values(key).values.tolist()


def test_language(spark, docs):
    held = F.crc32(F.col("doc_id").cast("string")) % 4 == 2
    model = language.fit(docs, ~held)
    got = language.score(docs, model).where(held).toPandas()
    assert (got["lang"] == got["lang_pred"]).mean() > 0.95 and set(docs.columns) < set(got.columns)
    odd = {r.doc_id: r for r in language.score(_docs(spark, ODD).withColumn("score", F.lit("clash")), model).collect()}
    assert all(odd[i].lang_pred == "und" and odd[i].score == 0 for i in (0, 1, 2, 5)) and odd[7].score == odd[8].score and 0 < odd[3].score <= 1
    none = language.fit(docs.limit(0), F.lit(True))
    assert {r.lang_pred for r in language.score(docs.limit(3), none).collect()} == {"und"}
    assert language.score(docs.limit(0), model).count() == 0


@pytest.mark.parametrize("learned", [["en"], ["de", "en", "es"]])
def test_language_stage_rejects_what_was_not_learned(spark, docs, learned):
    """Texts in a language left out and of random words go, labelled texts stay, whatever the number of languages."""
    import corpus_pipeline as p

    r = random.Random(5)
    noise = [(10**9 + i, " ".join("".join(r.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(r.randint(3, 9))) for _ in range(r.choice((5, 50, 300)))), None, "noise", 0) for i in range(60)]
    texts = docs.where("text IS NOT NULL AND lang IS NOT NULL").select("doc_id", "text", F.when(F.col("lang").isin(learned), F.col("lang")).alias("lang"), F.when(F.col("lang").isin(learned), "learned").when(F.col("lang") == "fr", "left out").alias("source"), "n_chars").where("source IS NOT NULL")
    all_ = texts.unionByName(spark.createDataFrame(noise, DOCS)).cache()
    before, after = ({x.source: x["count"] for x in f.groupBy("source").count().collect()} for f in (all_, p.language_id(spark, all_, SF)))
    assert after["learned"] >= 0.98 * before["learned"] and after.get("left out", 0) <= 0.05 * before["left out"] and "noise" not in after


def test_language_kernel_is_the_presence_kernel():
    texts = ["abab", "abc", "xyz", ""]
    raw, at, _ = pa_text = __import__("deltamp.llm.textbuf", fromlist=["x"]).utf8(pa.array(texts))
    grams, ends, has = language.presence(raw, at)
    index, rows = language.blended(grams, ends)
    got = [set(index[rows == i].tolist()) for i in range(4)]
    plain = lambda t: {(n, (t + "\0\0")[i : i + n]) for n in (1, 2, 3) for i in range(len(t))}
    for i in range(4):
        for j in range(4):
            assert len(got[i] & got[j]) == len(plain(texts[i]) & plain(texts[j]))
    assert has.tolist() == [True, True, True, False] and pa_text is not None


def test_any_script_and_any_number_of_languages(spark, monkeypatch):
    """300 languages, each with letters of its own from all over the code points, and one text of a language repeated often."""
    letters = [chr(c) for c in range(0x4E00, 0x4E00 + 900)]
    text = lambda k, r: "".join(r.choice(letters[3 * k : 3 * k + 3] + [" "]) for _ in range(40)) + letters[3 * k]
    r = random.Random(3)
    rows = [(10 * k + i, text(k, r), f"l{k:03}", None, 0) for k in range(300) for i in range(3)] + [(1, text(0, random.Random(1)), "l000", None, 0)] * 500
    train = spark.createDataFrame(rows, DOCS)
    model = language.fit(train, F.lit(True))
    assert len(model.languages) == 300 and model.mix is not None
    new = [text(k, r) for k in range(300)]
    names = language.predict(pa.array(new), model)[0]
    assert sum(a == f"l{k:03}" for k, a in enumerate(names)) >= 150  # 256 landmarks can't tell all 300 apart
    monkeypatch.setattr(language, "PER_LANGUAGE", 2)
    monkeypatch.setattr(language, "FIT_BYTES", 300 * 200)
    picked = language.sample(train, F.lit(True), "lang", "text", "doc_id").groupBy("label").count().collect()
    assert len(picked) == 300 and {x["count"] for x in picked} <= {1, 2}


def test_quality(spark, docs):
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    model = quality.fit(docs, labels, F.lit(True))
    got = quality.score(docs, model).join(labels.groupBy("doc_id").agg(F.min("quality").alias("q")), "doc_id").toPandas()
    assert (got["q"] == got["predicted"]).mean() > 0.9
    odd = [r.score for r in quality.score(_docs(spark, ODD), model).orderBy("doc_id").collect()]
    assert all(0 <= s <= 1 for s in odd) and odd[0] == odd[1] and odd[7] == odd[8]
    assert quality.score(docs.limit(2), quality.fit(docs, labels.limit(0), F.lit(True))).first().score == pytest.approx(0.5)


def test_additive_model_learns_an_interaction():
    r = np.random.default_rng(0)
    x = r.random((3000, 3))
    y = ((x[:, 0] > 0.5) ^ (x[:, 1] > 0.5)).astype(float)
    m = quality.train(x[:2000], y[:2000])
    assert ((m.scores(x[2000:]) > 0.5) == (y[2000:] == 1)).mean() > 0.9 and {m.pairs[0][0], m.pairs[0][1]} == {0, 1}


def test_token_counts(spark, docs):
    tk = Tokenizer.from_file(PATH)
    r = random.Random(1)
    alphabet = [*"abcstremdvl ''''   \n\t\r é1½!.-—*日\U0001f600́", "<|endoftext|>", "'re", "'ll", "tion"]
    texts = [*ODD, *("".join(r.choice(alphabet) for _ in range(r.randint(0, 40))) for _ in range(1500)), "'s a'v e'", "\n \n  x", "word word\n" * 200_000, "y" * 3000]
    got = token_counts.count_tokens(_docs(spark, texts), PATH).orderBy("doc_id").toPandas()["n_tokens"].tolist()
    want = [0 if t is None else len(tk.encode(t, add_special_tokens=False).ids) for t in texts]
    assert got == want


def test_chunked_scan_is_the_sequential_run():
    r = np.random.default_rng(2)
    symbols = r.integers(0, 12, 5000).astype(np.uint8)
    symbols[100:900] = 7
    to, mark = tokenfsm.splitter()
    state, want = tokenfsm._START, []
    for c in symbols:
        want.append(mark[state, c])
        state = to[state, c]
    assert tokenfsm.scan(symbols).tolist() == want


def test_packing(spark):
    tk = Tokenizer.from_file(PATH)
    r = random.Random(4)
    texts = [*ODD, "<|endoftext|> a\0b", *(" ".join(r.choice("alpha be gamma délta x".split()) for _ in range(r.choice((3, 40, 400, 3000)))) for _ in range(60))]
    got = packing.pack_documents(_docs(spark, texts), PATH).toPandas()
    for i, t in enumerate(texts):
        ids = np.array([*tk.encode(t or "", add_special_tokens=False).ids, 0], "<u4")
        g = got[got["doc_id"] == i].sort_values("piece")
        assert g["length"].sum() == len(ids) and g["start"].tolist() == (g["length"].cumsum() - g["length"]).tolist() and g["length"].max() <= 2048
        assert all(p.ids_crc32 == zlib.crc32(ids[p.start : p.start + p.length].tobytes()) for p in g.itertuples())
    s = got.sort_values(["sequence_id", "offset"]).groupby("sequence_id")
    assert ((s["length"].cumsum() - got.loc[s["length"].cumsum().index, "length"]) == got.loc[s["length"].cumsum().index, "offset"]).all()
    assert s["length"].sum().max() <= 2048 and s.ngroups <= np.ceil(got["length"].sum() / 2048) * 1.1 + 1
    assert packing.pack_documents(_docs(spark, ["a"]).limit(0), PATH).count() == 0


def test_plan_fills_every_slot_once():
    histogram = {2048: 3, 1500: 7, 600: 9, 300: 50, 7: 1000, 1: 5}
    used = {}
    slots = packing.plan(histogram)
    for n, c in histogram.items():
        mine = slots[slots[:, 0] == n]
        for rank in range(c):
            s = mine[np.searchsorted(mine[:, 1], rank, "right") - 1]
            k = rank - s[1]
            used.setdefault(int(s[2] + k // s[3]), []).append((int(s[4] + k % s[3] * n), n))
    for places in used.values():
        at = 0
        for offset, n in sorted(places):
            assert offset == at
            at += n
        assert at <= 2048


def _brute(texts, words, percent):
    sets = []
    for t in texts:
        w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        sets.append({tuple(w[i : i + words]) for i in range(max(1, len(w) - words + 1))} if w else set())
    root = list(range(len(texts)))
    find = lambda i: i if root[i] == i else find(root[i])
    for i in range(len(texts)):
        for j in range(i):
            both = len(sets[i] & sets[j])
            if both and 100 * both >= percent * (len(sets[i]) + len(sets[j]) - both):
                a, b = sorted((find(i), find(j)))
                root[b] = a
    return [(len(sets[i]), find(i)) for i in range(len(texts))]


@pytest.mark.parametrize(("words", "rows", "items"), [(2, 512, 100_000), (2, 4, 500), (5, 6, 1000)])
def test_near_duplicates(spark, monkeypatch, words, rows, items):
    """A group of copies that drift from one base, so that links are partial; also in many blocks, and for the pipeline's five words."""
    monkeypatch.setattr(near_duplicates, "BLOCK_ROWS", rows)
    monkeypatch.setattr(near_duplicates, "BLOCK_ITEMS", items)
    r = random.Random(9)
    base = [f"w{r.randint(0, 10**6)}" for _ in range(120)]
    drift = lambda n: " ".join(f"v{r.randint(0, 10**6)}" if k in hit else w for hit in [set(r.sample(range(120), n))] for k, w in enumerate(base))
    texts = [*ODD, *(drift(r.randint(0, 12)) for _ in range(60)), " ".join(base).upper(), "  ".join(base) + "\n", *(" ".join(f"u{r.randint(0, 10**6)}" for _ in range(50)) for _ in range(10))]
    got = {x.doc_id: x for x in near_duplicates.near_duplicates(_docs(spark, texts), words, 80).collect()}
    for i, (n, c) in enumerate(_brute(texts, words, 80)):
        assert (got[i].n_shingles, got[i].component_id, got[i].kept) == (n, c, c == i)
    assert near_duplicates.near_duplicates(_docs(spark, ["a"]).limit(0)).count() == 0


def test_hot_keys_are_dealt_over_salts(spark):
    left = spark.range(5000).selectExpr("id", "CASE WHEN id < 3000 THEN 7 ELSE id END AS k")
    right = spark.range(4000).selectExpr("id AS k", "id * 2 AS v")
    hot = hot_keys(left.groupBy("k").agg(F.count("*").alias("rows")), "k", 5000)
    assert [(r.k, r._salts) for r in hot.collect()] == [(7, 47)]
    plain = lambda d: sorted(map(tuple, d.select("k", "id", "v").collect()), key=str)
    for how in ("inner", "left"):
        assert plain(dealt(left, right, "k", hot, "id", how)) == plain(left.join(right, "k", how))
    shares = dealt(left, right, "k", hot, "id").where("k = 7").count()
    assert shares == 3000


def test_the_sequential_test_keeps_its_promise():
    """Wrong prunes at the threshold stay below the looks' posterior bounds; unlike pairs go."""
    looks = len(near_duplicates.least_equal(80))
    assert near_duplicates.wrongly_pruned(0.8, 80) < looks * near_duplicates.MISS * 2
    assert near_duplicates.wrongly_pruned(0.4, 80) > 0.99
    r = np.random.default_rng(1)
    left = r.integers(0, 256, (400, near_duplicates.HASHES), dtype=np.uint8)
    right = np.where(r.random(left.shape) < np.repeat([0.9, 0.3], 200)[:, None], left, r.integers(0, 256, left.shape, dtype=np.uint8)).astype(np.uint8)
    every = np.arange(400)
    assert near_duplicates.survivors(left, right, every, every, 80).tolist() == list(range(200))


def test_rows_of_one_id_and_of_none_are_documents_of_their_own(spark):
    """Repeated and null ids in the operator and in the pipeline's stage, against brute force over the rows."""
    import corpus_pipeline as p

    r = random.Random(11)
    text = lambda n: " ".join(f"w{r.randint(0, 10**6)}" for _ in range(n))
    a, b, c = text(40), text(40), text(40)
    rows = [(1, a), (1, b), (1, c), (None, text(30)), (None, text(30)), (None, b + " x"), (7, a + " y"), (7, text(20)), (9, c), (9, c), (None, "q r s t u v"), (None, "q r s t u v"), (3, None), (3, "")]
    rows += [(5, text(25)) for _ in range(12)]
    docs = spark.createDataFrame([(i, t, "l", "s", k) for k, (i, t) in enumerate(rows)], DOCS)
    truth = _brute([t for _, t in rows], 5, 80)
    members = {}
    for k, (_, root) in enumerate(truth):
        members.setdefault(root, []).append(k)
    want = []
    for k, (n, root) in enumerate(truth):
        ids = [rows[m][0] for m in members[root] if rows[m][0] is not None]
        want.append((rows[k][0], n, min(ids) if ids else None))
    got = near_duplicates.near_duplicates(docs, 5, 80).collect()
    plain = lambda x: sorted(map(str, x))
    assert plain((g.doc_id, g.n_shingles, g.component_id) for g in got) == plain(want)
    assert sum(g.kept for g in got) == len(members)
    left = p.near_dedup(spark, docs, SF).collect()
    assert len(left) == len(members) and {truth[x.n_chars][1] for x in left} == set(members)
    for x in left:  # the row of the smallest id stays
        ids = [rows[m][0] for m in members[truth[x.n_chars][1]] if rows[m][0] is not None]
        assert x.doc_id == (min(ids) if ids else None)


def test_components_of_a_large_star(spark):
    """A hub with the largest id and one with the smallest; both are hot keys."""
    edges = [(100_000, i) for i in range(1, 1500)] + [(0, i) for i in range(2000, 3500)]
    got = {x.node: x.root for x in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {**{i: 1 for i in range(2, 1500)}, 100_000: 1, **{i: 0 for i in range(2000, 3500)}}


def test_components(spark):
    r = random.Random(1)
    edges = [(r.randint(0, 80), r.randint(0, 80)) for _ in range(60)] + [(100 + i, 101 + i) for i in range(15)]
    root = {n: n for e in edges for n in e}
    for _ in range(100):
        for a, b in edges:
            root[a] = root[b] = min(root[a], root[b])
    got = {x.node: x.root for x in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {n: c for n, c in root.items() if n != c}


def test_decontamination(spark):
    item = "one two three four five six seven eight nine ten eleven"
    bench = spark.createDataFrame([(1, item), (2, "Short item"), (3, None), (4, " ".join(item.split()[1:])), (5, "!")], "item_id long, text string")
    texts = [None, "", f"x {item.upper()}, y", "one two three four five six seven eight nine", "a short, ITEM b", f"{item} {item}"]
    docs = _docs(spark, [*texts, texts[2]])
    got = {r.doc_id: (r.n_words, len(r.hits), r["items"]) for r in decontaminate.scan(docs, bench).collect()}
    assert got == {0: (0, 0, []), 1: (0, 0, []), 2: (13, 11, ["1", "4"]), 3: (9, 0, []), 4: (4, 2, ["2"]), 5: (22, 22, ["1", "4"]), 6: (13, 11, ["1", "4"])}
    assert sorted(r.doc_id for r in decontaminate.remove_documents(docs, bench).collect()) == [0, 1, 3]
    left = {r.doc_id: r.text for r in decontaminate.remove_spans(docs, bench).collect()}
    assert left[2] == "x, y" and left[4] == "a b" and left[3] == texts[3] and left[0] is None
    assert decontaminate.scan(docs, bench.limit(0)).where("size(hits) > 0").count() == 0


def test_chat(spark):
    rows = [(1, 0, "user", "hi"), (1, 1, "assistant", "yo"), (2, 0, "user", "hi"), (2, 1, "assistant", "yo"), (2, 2, "user", "ok"), (3, 0, "user", "hi"), (3, 1, "assistant", "yo"), (3, 2, "user", "ok"), (4, 0, "user", "other"), (5, 0, None, None), (5, 0, None, None), (None, 0, "user", "hi"), (6, None, "user", "no turn")]
    rows += [(7, t, "user", str(t)) for t in range(200)] + [(8, t, "user", str(t)) for t in range(150)]
    got = {r.conv_id: (r.n_turns, r.rendered) for r in chat.format_chats(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")).collect()}
    assert set(got) == {2, 4, 5, 6, 7} and got[5] == (1, "<||>\n<|end|>\n") and got[7][0] == 200
    assert got[2] == (3, "<|user|>\nhi<|end|>\n<|assistant|>\nyo<|end|>\n<|user|>\nok<|end|>\n")


def test_licences(spark):
    mit = licences.KNOWN[0][1]
    one_line = "Copyright (c) 2020 Some One " + mit.replace("\n", " ")
    bsd = "BSD text\n\nCopyright (c) 2001-2020, Some One <a@b.c>\nAll rights reserved.\n\n" + licences._BSD2 % licences._BSD3
    texts = [f"Copyright (c) 2020 Someone\n\n{mit}", mit.upper().replace(",", " ,").replace("SUBLICENSE", "sublicence"), "x\nLicenced under the Apache Licence, version 2.0\ny", None, "All rights reserved.", one_line, bsd, bsd.split("\n", 2)[2], mit + " or not", ""]
    docs = _docs(spark, [*texts, texts[0]])
    got = {r.doc_id: (r.text_licence, r.line_licences) for r in licences.scan(docs).collect()}
    assert got[0][0] == got[1][0] == got[5][0] == got[10][0] == "MIT" and got[2] == (None, ["Apache-2.0"]) and got[3] == got[4] == got[9] == (None, [])
    assert got[6][0] is None and got[7][0] == "BSD-3-Clause" and got[8][0] is None
    assert licences.scan(docs.limit(0)).count() == 0


@pytest.mark.skipif(not os.path.isdir("/usr/share/common-licenses"), reason="needs a system's folder of licence texts")
def test_whole_licence_texts(spark):
    """Whole texts as a system keeps them, with other case, spacing and notices; a text that lacks a paragraph is none."""
    texts = {}
    for file, name in (("Apache-2.0", "Apache-2.0"), ("GPL-3", "GPL-3.0"), ("LGPL-2.1", "LGPL-2.1"), ("MPL-2.0", "MPL-2.0"), ("BSD", "BSD-3-Clause")):
        with open(f"/usr/share/common-licenses/{file}", encoding="utf-8") as f:
            texts[name] = f.read()
    rows = [t for x in texts.values() for t in (x, "Copyright (c) 2024 Some One\n\n" + x.upper().replace("\n", "\r\n  "), x[: len(x) // 2])]
    got = {r.doc_id: r.text_licence for r in licences.scan(_docs(spark, rows)).collect()}
    assert [got[i] for i in range(len(rows))] == [n for name in texts for n in (name, name, None)]


def test_main_text(spark):
    model = main_text.trained()
    wrong = total = 0
    for blocks, labels in main_text.labelled_pages(60, seed=77):
        got = main_text.viterbi([model.emission(b) for b in blocks], model)
        wrong, total = wrong + sum(a != b for a, b in zip(got, labels)), total + len(labels)
    assert wrong < 0.01 * total
    pages = spark.read.parquet(f"{SF}/pages.parquet")
    for r in main_text.extract(pages).collect():
        inner = re.search(r"<article>(.*)</article>", r.html, re.S)[1]
        assert r.text == " ".join(__import__("html").unescape(re.sub(r"<[^>]*>", " ", inner)).split())
    odd = spark.createDataFrame([(1, None), (2, ""), (3, "<"), (4, "<div class='x"), (5, "<!-- a"), (6, "<script>"), (7, "<p" * 500)], "page_id long, html string")
    assert {r.text for r in main_text.extract(odd, model).collect()} <= {"", "<"}


@pytest.mark.parametrize("start", ["<html><head><title>T</title>", "<head><meta charset=x><link href=y><style>p {}</style>\n", "<head><title>T</title><br>", "<head><title>T</title><svg><text>no</text></svg>", "<html><head><title>T</title></head><body>", "<title>T</title><body><head>"])
def test_a_head_may_lack_its_end(start):
    """Every block of the page is found, with and without </head> and <body>; the head itself gives none."""
    found = [b.text for b in main_text.Scanner().blocks(f"{start}<p>One <b>two</b>.<div>Three</div>")]
    assert found == ["One two.", "Three"]
    assert [b.text for b in main_text.Scanner().blocks(f"{start}plain text<p>next")] == ["plain text", "next"]


def test_page_without_head_end_and_body_keeps_its_text(spark):
    page = "<div class='menu'><a href=/>Home</a></div><article>" + "<p>A sentence of some length that stands in the article, with a full stop.</p>" * 6 + "</article>"
    pages = spark.createDataFrame([(1, f"<html><head><title>T</title></head><body>{page}</body></html>"), (2, f"<html><head><title>T</title>{page}")], "page_id long, html string")
    full, short = (r.text for r in main_text.extract(pages).orderBy("page_id").collect())
    assert full == short and short.count("A sentence") == 6


@pytest.mark.parametrize("part", ["<p", "<p ", "<a x='", '<a x="', "<", "<div class=a", "<li></li>", "&#9", "<!-", "</p", "<b>", "<div class=q%d>"])
def test_malformed_megabyte_takes_seconds(part):
    """1 MB of each, after deep nesting and before a closing mark too."""
    text = "".join(part % i for i in range(60_000)) if "%d" in part else part * (1_000_000 // len(part))
    extractor = main_text.Extractor(main_text.trained())
    for page in (text, "<ul><li><ul>" + "<div>" * 20_000 + text, text + "'>\">"):
        began = time.perf_counter()
        extractor.text(page)
        assert time.perf_counter() - began < 8


def test_references_of_any_length():
    blocks = main_text.Scanner().blocks(f"<p>a&#{'9' * 6000};b&#x{'0' * 9000}41;c&#{'0' * 5000}65;</p>")
    assert blocks[0].text == "a\ufffdbAcA"


HAND_PAGES = {
    "blog": """<html><head><title>t</title></head><body><div id="wrapper"><div id="header"><h1><a href="/">My blog</a></h1><p>Just another weblog</p></div>
      <div id="nav"><ul><li><a href=/a>Home</a></li><li><a href=/b>About</a></li></ul></div><div class="post"><h2>KEEP1 A walk</h2><p>KEEP2 We went out early, before the sun had come up.</p>
      <p>KEEP3 It rained &amp; rained.</p></div><div class="comments"><h3>2 comments</h3><div class="comment"><p>Nice walk, thanks for sharing it with all of us.</p></div></div>
      <div id="footer"><p>&copy; 2020 Someone. All rights reserved.</p></div></div></body></html>""",
    "news": """<!doctype html><body><header><p>The paper</p></header><nav><a href=1>World</a> <a href=2>Sport</a></nav><main><h1>KEEP1 Bridge opens</h1><p>KEEP2 The bridge was opened on Monday, said the mayor.</p>
      <div class="advert"><p>Buy two, get one free, this week only!</p></div><p>KEEP3 Thousands came to see it.</p><ul><li>KEEP4 It is long.</li></ul></main><aside class="related"><p>More stories that you may like to read.</p></aside><footer>Contact us</footer></body>""",
    "docs": """<body><div class="sidebar"><ul><li><a href=x>Install</a><li><a href=y>Use</a></ul></div><section class="content"><h1>KEEP1 Install</h1><p>KEEP2 Run the setup and wait until it has ended.
      <blockquote>KEEP3 Note that it may take a while.</blockquote><table><tr><td>KEEP4 one<td>KEEP5 two</table></section><div class="cookie-notice"><p>We use cookies to make this site work better for you.</p><button>OK</button></div></body>""",
}


@pytest.mark.parametrize("name", sorted(HAND_PAGES))
def test_layouts_without_an_article_element(name):
    """Pages written by hand: every marked block is found, and nothing else."""
    found = main_text.Extractor(main_text.trained()).text(HAND_PAGES[name])
    marks = re.findall(r"KEEP\d", HAND_PAGES[name])
    assert re.findall(r"KEEP\d", found) == marks
    for other in ("weblog", "Home", "sharing", "reserved", "World", "free", "stories", "Contact", "Install Use", "cookies"):
        assert other not in found


def test_viterbi_is_the_best_of_all_labelings():
    r = np.random.default_rng(5)
    for n in (1, 2, 6):
        m = main_text.Model(step=r.normal(size=(2, 2)), start=r.normal(size=2))
        e = r.normal(size=n).tolist()
        worth = lambda y: m.start[y[0]] + sum(x for x, k in zip(e, y) if k) + sum(m.step[a, b] for a, b in zip(y, y[1:]))  # noqa: B023, E731
        every = [[k >> i & 1 for i in range(n)] for k in range(2**n)]
        assert worth(main_text.viterbi(e, m)) == pytest.approx(max(map(worth, every)))


def test_neighbours(spark):
    r = np.random.default_rng(6)
    x = r.normal(size=(600, 8))
    x[50:60] = x[0]
    rows = [(i, [float(v) for v in vec]) for i, vec in enumerate(x)] + [(600, None), (601, [0.0] * 8), (602, [float("nan")] * 8), (603, [1.0, None, *[0.0] * 6]), (604, [1.0])]
    index = neighbours.build(spark.createDataFrame(rows, "vec_id long, embedding array<double>"))
    for share, floor in ((1.0, 1.0), (None, 0.9)):
        got = neighbours.search(index, F.col("id") % 100 == 0, 10, share).toPandas()
        found = 0
        for q, g in got.groupby("query_id"):
            d = np.sqrt(np.add.accumulate((x - x[q]) ** 2, axis=1)[:, -1])
            d[q] = np.inf
            found += len(set(np.lexsort((np.arange(600), d))[:10]) & set(g["vec_id"]))
            assert np.array_equal(d[g["vec_id"]], g["score"]) and sorted(g["rank"]) == list(range(1, 11))
        assert set(got["query_id"]) == {0, 100, 200, 300, 400, 500} and found / 60 >= floor
    assert neighbours.search(neighbours.build(spark.createDataFrame([], "vec_id long, embedding array<double>")), F.lit(True)).count() == 0


def test_neighbours_of_a_larger_table(spark, monkeypatch):
    """Clustered, spread and equal vectors with the shipped settings, in small groups: recall against brute force, less than half of the rows read."""
    monkeypatch.setattr(neighbours, "PART", 300)
    monkeypatch.setattr(neighbours, "BLOCK", 20)
    r = np.random.default_rng(7)
    centres = r.normal(size=(60, 16)) * 3
    x = np.concatenate([centres[r.integers(0, 60, 5000)] + r.normal(size=(5000, 16)) * 0.4, r.normal(size=(1000, 16)) * 3, np.repeat(centres[:1], 2000, 0)])
    x = x[r.permutation(len(x))]
    index = neighbours.build(spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>"))
    got = neighbours.search(index, F.col("id") % 100 == 0).toPandas()
    found = 0
    for q, g in got.groupby("query_id"):
        d = np.sqrt(np.add.accumulate((x - x[q]) ** 2, axis=1)[:, -1])
        d[q] = np.inf
        found += len(set(np.lexsort((np.arange(len(x)), d))[:10]) & set(g["vec_id"]))
        assert np.array_equal(d[g.sort_values("rank")["vec_id"]], g.sort_values("rank")["score"])
    assert got["query_id"].nunique() == 80 and found / 800 >= 0.9 and index.share < 0.6


def test_columns_of_any_name_come_through(spark, docs):
    """Columns called like the operators' own ones keep their values."""
    names = ("_p", "_k", "_h", "_hits", "_quality", "_good", "_language", "_sure", "_cover", "_gone")
    more = docs.select("*", *(F.lit(c).alias(c) for c in names))
    bench = spark.read.parquet(f"{SF}/benchmark.parquet")
    import corpus_pipeline as p

    for out in (p.quality(spark, more, SF), p.language_id(spark, more, SF), decontaminate.remove_documents(more, bench), decontaminate.remove_spans(more, bench), p.near_dedup(spark, more.limit(30), SF)):
        assert out.columns == more.columns
        assert out.select(*names).distinct().collect() == [tuple(names)]


def _words(text):
    return [w for w in re.split(r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or "")) if w]


def test_pipeline_stages_against_brute_force(spark, docs):
    """Each stage on all that its predecessor kept, with nulls, empty texts and repeated rows, against plain Python."""
    import corpus_pipeline as p

    extra = [(10**9 + i, t, None, "odd", None) for i, t in enumerate(ODD)] + [(10**9 + 50, ODD[8], None, "odd", None)]
    kept = docs.unionByName(spark.createDataFrame(extra, DOCS)).cache()
    items = [_words(r.text) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    windows = {tuple(w[i : i + min(10, len(w))]) for w in items if w for i in range(len(w) - min(10, len(w)) + 1)}
    for name, stage in p.STAGES[:-1]:
        rows = kept.orderBy("doc_id").collect()
        texts = [r.text for r in rows]
        if name == "quality":
            m = quality.fit(kept, spark.read.parquet(f"{SF}/labels.parquet"), F.lit(True))
            want = [r for r, s in zip(rows, m.scores(quality.features(pa.array(texts, pa.string()))), strict=True) if s >= 0.3]
        elif name == "language":
            names, _, cover = language.predict(pa.array(texts, pa.string()), language.fit(kept, F.lit(True)))
            want = [r for r, n, c in zip(rows, names, cover, strict=True) if n != "und" and c >= p.COVER]
        elif name == "near_duplicates":
            want = [rows[i] for i, (_, root) in enumerate(_brute(texts, 5, 80)) if i == root]
        else:
            grams = [{tuple(w[i : i + n]) for n in {len(x) for x in windows} for i in range(len(w) - n + 1)} for w in map(_words, texts)]
            want = [r for r, g in zip(rows, grams, strict=True) if not g & windows]
        before, kept = kept, stage(spark, kept, SF).cache()
        assert kept.columns == docs.columns and sorted(kept.collect(), key=str) == sorted(want, key=str), name
        assert 0 < kept.count() < before.count(), name
        assert stage(spark, docs.limit(0), SF).count() == 0
    assert p.STAGES[-1][1](spark, kept, SF).select("doc_id").distinct().count() == kept.count()


def test_op1_and_op2_queries_against_the_plain_models(spark, docs):
    """Splits and results of the registered queries against the models run over all texts in one process."""
    rows = docs.orderBy("doc_id").collect()
    texts = pa.array([r.text for r in rows], pa.string())
    fold = lambda n: [zlib.crc32(str(r.doc_id).encode()) % n for r in rows]
    names, scores, _ = language.predict(texts, language.fit(docs, F.crc32(F.col("doc_id").cast("string")) % 4 != 2))
    got = queries.QUERIES["op1_language"](spark, SF).orderBy("doc_id").collect()
    assert [tuple(r) for r in got] == [(r.doc_id, f == 2, n, s) for r, f, n, s in zip(rows, fold(4), names, scores.tolist(), strict=True)]
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    m = quality.fit(docs, labels, F.crc32(F.col("doc_id").cast("string")) % 5 != 0)
    plain = [sum([m.base, *(t[b] for t, b in zip(m.tables, bins)), *(t[m.coarse[i][bins[i]], m.coarse[j][bins[j]]] for i, j, t in m.pairs)]) for bins in m.bins(quality.features(texts)).tolist()]
    got = queries.QUERIES["op2_quality"](spark, SF).orderBy("doc_id").collect()
    assert [(r.doc_id, r.held_out) for r in got] == [(r.doc_id, f == 0) for r, f in zip(rows, fold(5), strict=True)]
    assert np.allclose([r.score for r in got], 1 / (1 + np.exp(-np.array(plain)))) and all(r.predicted == (r.score >= 0.3) for r in got)


def test_empty_tables_and_repeated_rows(spark):
    none = _docs(spark, ["a"]).limit(0)
    assert token_counts.count_tokens(none, PATH).count() == 0 and decontaminate.scan(none, spark.createDataFrame([(1, "a")], "item_id long, text string")).count() == 0
    assert chat.format_chats(spark.createDataFrame([], "conv_id long, turn long, role string, text string")).count() == 0
    assert main_text.extract(spark.createDataFrame([], "page_id long, html string")).count() == 0
    model = quality.train(np.empty((0, len(quality.FEATURES))), np.empty(0))
    assert quality.score(none, model).count() == 0
    twice = spark.createDataFrame([(1, "<p>x", "k"), (1, "<p>x", "k")], "page_id long, html string, text string")
    assert len({tuple(r) for r in main_text.extract(twice).collect()}) == 1 and main_text.extract(twice).count() == 2
