import hashlib
import itertools
import random
import time

import duckdb
import numpy as np
import pytest

import corpus_pipeline
from skyweave.llm import byte_bpe, decontaminate, html_extract, language_id, near_dup, quality_rules, registry, substring_dedup, token_counts, toxicity, warc
from skyweave.llm import common as C

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, empty and repeated texts, ties, a very long word and an extra column with a clashing name."""
    base = " ".join(f"w{i}" for i in range(60))
    rows = [(1, None, "en", None, 0, "x"), (2, "", None, "s", 0, "x"), (3, base, "en", "s", 1, "y"), (3, base, "en", "s", 1, "y"), (4, base.upper(), "en", "s", 1, None), (None, "alone here", "de", "s", 2, None), (5, "a" * 5000, "en", "s", 3, None), (6, " \t\n ", "en", "s", 4, None), (7, base + " tail", "en", "s", 5, None), (8, "tiny text", "fr", "t", 1, None), (9, "don't  stop\n\nnow  é 日本 123", "en", "s", 1, None)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, _rest string")


@pytest.mark.parametrize("name", sorted(registry.SQL))
def test_sql(spark, name):
    con = duckdb.connect()
    for t in ("documents", "pages"):
        con.sql(f"create view {t} as select * from '{SF}/{t}.parquet'")
    want = con.sql(registry.SQL[name])
    cols = want.columns
    got = sorted(map(str, registry.QUERIES[name](spark, SF).select(*cols).toArrow().to_pylist()))
    assert got == sorted(map(str, want.to_arrow_table().to_pylist()))


def test_substring_edges(spark, odd):
    got = {r.doc_id: r for r in substring_dedup.deduplicate(odd, 20).collect()}
    assert got[1].n_words == 0 and got[1].text is None and got[2].text == ""
    assert got[3].n_removed == 0  # equal rows do not repeat each other
    assert got[7].n_removed == 60 and got[7].text == "tail" and [tuple(x) for x in got[7].removed] == [(0, 60)]
    assert got[4].n_removed == 0 and got[9].n_removed == 0
    assert substring_dedup.deduplicate(odd.limit(0), 20).count() == 0


def test_near_dup_edges(spark, odd):
    got = {r.doc_id: r for r in near_dup.near_duplicates(odd, 4, 80).collect()}
    assert got[3].component_id == got[4].component_id == got[7].component_id == 3
    assert got[1].n_shingles == 0 and got[1].kept and got[8].n_shingles == 1 and got[None].kept
    assert near_dup.near_duplicates(odd.limit(0)).count() == 0


def test_near_dup_hot_keys_change_nothing(spark):
    rng = random.Random(8)
    base = [str(rng.randrange(10**6)) for _ in range(90)]
    docs = [(i, " ".join(w if rng.random() > 0.01 else str(rng.randrange(10**6)) for w in base)) for i in range(60)]
    docs += [(100 + i, " ".join(str(rng.randrange(10**6)) for _ in range(40))) for i in range(20)]
    keyed = spark.createDataFrame(docs, "doc_id long, text string").repartition(3)
    want = sorted(near_dup._components(keyed, 4, 80).collect())
    assert len({r.component for r in want}) < 40
    for least, block in ((8, 4), (20, 30), (8, 4096)):
        assert sorted(near_dup._components(keyed, 4, 80, least, block).collect()) == want


def test_hot_keys_are_all_found(spark):
    rng = np.random.default_rng(3)
    sig = rng.integers(0, 1 << 16, (900, near_dup.PARTS), dtype=np.uint16)
    sig[:, : near_dup._CUT[3]] = sig[0, : near_dup._CUT[3]]  # every row shares the keys of three chunks
    sig[:300, near_dup._CUT[5] : near_dup._CUT[6]] = 7
    reps = spark.createDataFrame([(i, bytearray(s.tobytes())) for i, s in enumerate(sig)], "rep long, sig binary").repartition(5)
    key, n = np.unique(near_dup.chunk_keys(sig), return_counts=True)
    for least, most in ((200, 1 << 20), (200, 1500), (600, 1500)):
        found, blocks = near_dup.hot_keys(reps, 900, least, 50, most)
        bound = max(least, -(-4 * 900 * near_dup.PARTS // most))
        assert set(key[n >= bound]) <= set(found) <= set(key[n >= bound / 2]) and len(found) <= most / 2
        assert all(b >= n[np.searchsorted(key, k)] / 50 for k, b in zip(found, blocks))


def test_near_dup_against_brute_force(spark):
    rng = random.Random(4)
    docs = []
    for _ in range(30):
        base = [str(rng.randrange(10**6)) for _ in range(rng.randrange(8, 120))]
        for _ in range(rng.randrange(1, 7)):
            w = list(base)
            for _ in range(rng.randrange(0, 4)):
                w[rng.randrange(len(w))] = str(rng.randrange(10**6))
            docs.append((len(docs), " ".join(w)))
    sets = [{tuple(t.split()[i : i + 4]) for i in range(len(t.split()) - 3)} for _, t in docs]
    root = list(range(len(docs)))
    find = lambda x: x if root[x] == x else find(root[x])
    for i in range(len(docs)):
        for j in range(i):
            if 100 * len(sets[i] & sets[j]) >= 80 * len(sets[i] | sets[j]):
                a, b = sorted((find(i), find(j)))
                root[b] = a
    got = {r.doc_id: r.component_id for r in near_dup.near_duplicates(spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    assert got == {i: find(i) for i in range(len(docs))}


def test_blocks_of_large_groups(spark, monkeypatch):
    monkeypatch.setattr(near_dup, "CLUSTER_BLOCK", 3)
    rows = [(i, " ".join([f"a{k}" for k in range(100)] + [f"z{i}"])) for i in range(12)]
    got = near_dup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert {r.component_id for r in got} == {0}


def test_exchange_width_changes_no_result(spark, odd, monkeypatch):
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text").unionByName(odd.select("doc_id", "text"))
    ways = (lambda: substring_dedup.deduplicate(docs, 20), lambda: near_dup.near_duplicates(docs), lambda: byte_bpe.digests(docs))
    plain = [sorted(map(str, w().collect())) for w in ways]
    assert C.exchange_width(docs) == 4 and C.exchange_width(odd.limit(0)) == 4
    monkeypatch.setattr(C, "PART_BYTES", 40_000)
    size = sum(len((r.text or "").encode()) for r in docs.collect())
    assert C.exchange_width(docs) == -(-size // 40_000) > 4 and C.exchange_width(docs, 100) == -(-(size + 100 * docs.count()) // 40_000)
    assert [sorted(map(str, w().collect())) for w in ways] == plain


def test_connected(spark):
    edges = [(i + 1, i) for i in range(1, 40)] + [(100, 50), (100, 70), (7, 7)]
    got = {r.node: r.root for r in C.connected(spark, spark.createDataFrame(edges, "u long, v long")).collect()}
    assert got == {**{i: 1 for i in range(1, 41)}, 50: 50, 70: 50, 100: 50}


def test_bpe(spark, odd):
    enc = byte_bpe.encoder(byte_bpe.default_ranks())
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text").unionByName(odd.select("doc_id", "text").where("doc_id > 3").selectExpr("doc_id + 1000000 as doc_id", "text"))
    text = {r.doc_id: r.text for r in docs.collect()}
    for r in byte_bpe.digests(docs).collect():
        ids = enc.encode_ordinary(text[r.doc_id] or "")
        assert r.n_tokens == len(ids)
        assert r.ids_sha256 == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest()
        assert r.decoded_sha256 == hashlib.sha256((text[r.doc_id] or "").encode()).hexdigest()
    back = byte_bpe.decode(byte_bpe.encode(odd)).collect()
    assert sorted((r.doc_id or 0, r.text) for r in back) == sorted((r.doc_id or 0, r.text or "") for r in odd.collect())


def test_warc_small_splits(spark):
    pages = spark.read.parquet(f"{SF}/pages.parquet")
    extra = spark.createDataFrame([(10**6, None, None), (10**6 + 1, "u\n", ""), (10**6 + 2, "u", "WARC/1.1\r\n\r\n" * 50), (None, "n", "x")], "page_id long, url string, html string")
    both = pages.select("page_id", "url", "html").unionByName(extra)
    files = warc.write(both, C.scratch(spark, "t"), part_bytes=20_000)
    got = warc.read(spark, files, split_bytes=3_000, chunk=1_000).collect()
    assert len(got) == both.count()
    html = {r.page_id: (r.html or "") for r in both.collect()}
    assert all(r.record_type == "revisit" or bytes(r.payload) == html[r.page_id].encode() for r in got)
    assert {r.page_id: r.refers_to for r in got if r.record_type == "revisit"}[10**6 + 1] == 10**6


def test_toxicity(spark, odd):
    rng = random.Random(1)
    words = [f"w{i}" for i in range(300)]
    rows = []
    for i in range(600):
        s = [" ".join(rng.choices(words, k=12)) for _ in range(5)]
        if i % 5 == 0:
            s[rng.randrange(5)] += " vilest"
        rows.append((i, ". ".join(s) + ".", int(i % 5 == 0)))
    docs = spark.createDataFrame([r[:2] for r in rows], "doc_id long, text string")
    labels = spark.createDataFrame([(r[0], r[2]) for r in rows] + [(None, 1), (3, None)], "doc_id long, toxic int")
    model = toxicity.train(docs, labels, exclude=C.held_out(4, 2))
    got = {r.doc_id: r for r in toxicity.score(docs, model, 0.3, "doc_id").collect()}
    assert sum(got[i].predicted == y for i, _, y in rows) >= 595
    r = got[0]
    assert "vilest" in rows[0][1][r.worst_span[0] : r.worst_span[1]]
    assert toxicity.score(odd, model, 0.3, *odd.columns).count() == odd.count()
    empty = toxicity.train(docs.limit(0), labels.limit(0))
    assert {r.score for r in toxicity.score(odd, empty, 0.3, "doc_id").collect()} == {0.0}


def test_quality_statistics():
    t = "a b c d e a b c d e x\nline\nline\n#$ é"
    n, chars, sym, dup, rep, _ = quality_rules.statistics(t.encode())
    assert (n, chars, sym, dup) == (15, 11 + 8 + 2 + 1, 2, 1)
    w = t.split()
    g = [tuple(w[i : i + 5]) for i in range(len(w) - 4)]
    hit = {i + k for i in range(len(g)) if g.count(g[i]) > 1 for k in range(5)}
    assert rep == len(hit)
    assert quality_rules.statistics(None) == (0, 0, 0, 0, 0, 0)


def test_quality_edges(spark, odd):
    got = quality_rules.judge(odd).collect()
    assert len(got) == odd.count() and all(not r.kept for r in got if r.base_failed)
    assert quality_rules.judge(odd.limit(0)).count() == 0


def test_language(spark, odd):
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text", "lang")
    model = language_id.train(docs.where(~C.held_out(3, 1)))
    got = language_id.predict(docs, model, "doc_id", "lang").where(C.held_out(3, 1)).collect()
    assert np.mean([r.lang == r.lang_pred for r in got]) > 0.97
    edge = {r.doc_id: r for r in language_id.predict(odd, model, "doc_id").collect()}
    assert edge[1].lang_pred == edge[2].lang_pred == edge[6].lang_pred == "und"
    none = language_id.train(docs.limit(0))
    assert {r.lang_pred for r in language_id.predict(odd, none, "doc_id").collect()} == {"und"}


def _ways(word, known, size):
    """All segmentations of a marked word, as lists of piece ids; single characters always have one."""
    if not word:
        return [[]]
    out = []
    for k in range(1, len(word) + 1):
        i = known.get(word[:k], size if k == 1 else None)
        if i is not None:
            out += [[i, *rest] for rest in _ways(word[k:], known, size)]
    return out


def _vocabulary():
    path = language_id.P.default_model()
    names, _, types = language_id.P.vocabulary(path)
    return path, {p: i for i, (p, t) in enumerate(zip(names, types)) if t == 1}, len(names)


WORDS = ["the", "Ocean", "über", "日本語", "representa", "q" * 9, "x"]


@pytest.mark.parametrize("short", [20, 2])
def test_forward_sums_all_segmentations(monkeypatch, short):
    """Of the whole vocabulary, by the block way and by the way of long words."""
    monkeypatch.setattr(language_id, "SHORT", short)
    path, known, size = _vocabulary()
    p = np.random.default_rng(0).dirichlet(np.ones(size + 1), 2)
    got = language_id.likelihoods(WORDS, np.log(p), path)
    for k in range(2):
        assert np.allclose(got[:, k], [np.log(sum(np.prod(p[k, w]) for w in _ways("▁" + x, known, size))) for x in WORDS])


@pytest.mark.parametrize("short", [20, 2])
def test_expected_counts(monkeypatch, short):
    monkeypatch.setattr(language_id, "SHORT", short)
    path, known, size = _vocabulary()
    want, times = np.zeros(size + 1), np.arange(1.0, len(WORDS) + 1)
    for word, n in zip(WORDS, times):
        ways = _ways("▁" + word, known, size)
        odds = np.array([float(size) ** -len(w) for w in ways])
        for w, q in zip(ways, odds / odds.sum()):
            np.add.at(want, w, n * q)
    assert np.allclose(language_id.expected(WORDS, times, path), want, atol=1e-12)


def test_long_words_do_not_underflow():
    path, known, size = _vocabulary()
    logp = np.log(np.random.default_rng(0).dirichlet(np.ones(size + 1), 2))
    word = "information" * 700
    one, two = language_id.likelihoods([word, word * 2], logp, path)
    assert np.isfinite(two).all() and np.allclose(two, 2 * one, rtol=0.01)
    total = language_id.expected([word], np.ones(1), path)
    sizes = np.zeros(size + 1)
    for p, i in known.items():
        sizes[i] = len(p)
    sizes[size] = 1
    assert np.isclose(total @ sizes, len(word) + 1)  # every character is in one piece


def test_language_of_long_and_marked_texts(spark):
    rows = [(1, "die " * 3 + "Straße" * 300, "de"), (2, "the " * 3 + "information" * 300, "en"), (3, "ความ ที่", None), (4, "12 - !?", "en")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = language_id.train(docs)
    got = {r.doc_id: r for r in language_id.predict(docs.withColumn("score", C.F.lit("x")), model, "doc_id").collect()}
    assert got[1].lang_pred == "de" and got[2].lang_pred == "en" and got[4].lang_pred == "und" and got[3].lang_pred in ("de", "en")
    assert language_id.letters("ที่".encode()) == "ที่"


def test_token_counts_against_library(spark, odd):
    import sentencepiece as spm
    from sentencepiece import sentencepiece_model_pb2 as pb

    path = token_counts.P.default_model()
    m = pb.ModelProto()
    m.ParseFromString(token_counts.P.model_bytes(path))
    m.trainer_spec.model_type = pb.TrainerSpec.UNIGRAM
    lib = spm.SentencePieceProcessor(model_proto=m.SerializeToString())
    words = sorted({w for r in spark.read.parquet(f"{SF}/documents.parquet").select("text").limit(20).collect() for w in (r.text or "").split()})[:500]
    for w in words:
        best = lib.nbest_encode_as_pieces(w, 2)[0]
        assert token_counts.count_text(w, path) == sum(1 if lib.piece_to_id(p) else len(p.encode()) for p in best), w
    assert {r.doc_id: r.n_tokens for r in token_counts.counted(odd).collect()}[1] == 0


def test_suffix_array():
    rng = np.random.default_rng(1)
    for _ in range(50):
        x = rng.integers(0, 3, rng.integers(1, 40))
        sa, lcp = html_extract.suffix_array(x)
        order = sorted(range(len(x)), key=lambda i: list(x[i:]))
        assert list(sa) == order
        for i in range(1, len(x)):
            a, b = order[i - 1], order[i]
            k = 0
            while a + k < len(x) and b + k < len(x) and x[a + k] == x[b + k]:
                k += 1
            assert lcp[i] == k


def test_html(spark):
    page = "<html><head><title>T</title><script>var a='<p>';</script></head><body><nav><a>Home</a></nav><article><h1>A &amp; B</h1><p>one<br>two  <b>three</b><p>four<div class='ad'>buy</div><ul><li>x<li>y</ul></article><div id=comments>c</div><footer>f</footer>"
    assert [t for k, t in html_extract.blocks(page) if k == html_extract.MAIN] == ["A & B", "one", "two three", "four", "x", "y"]
    shared = "<div>common words that stand on every page of this host</div>"
    rows = [(i, "http://h.org/x", f"<body>{shared}<p>unique text number {i} of words{i} and more{i}</p></body>") for i in range(4)] + [(9, None, None), (10, "", "")]
    got = {r.page_id: r.text for r in html_extract.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert got[2] == "unique text number 2 of words2 and more2" and got[9] == got[10] == ""


def test_html_unique_runs_outside_main(spark):
    shared = "<div>common words that stand on every page of this host</div>"
    rows = [(i, "http://h.org/x", f"<body><nav>menu{i}</nav>{shared}<article>inside {i}</article><div>a unique passage beside it number{i}</div></body>") for i in range(3)]
    got = {r.page_id: r.text for r in html_extract.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert got == {i: f"inside {i}\na unique passage beside it number{i}" for i in range(3)}


def test_html_shards_equal_one_array(spark):
    """Passages shared by two pages only, short blocks inside longer ones, null and repeated ids, on a host in many shards."""
    rng = random.Random(5)
    words = [f"w{i}" for i in range(400)]
    passages = [" ".join(rng.choices(words, k=rng.choice((1, 2, 5, 8, 11, 30)))) for _ in range(40)]
    rows = []
    for i in range(60):
        parts = [rng.choice(passages) + rng.choice(("", " " + rng.choice(words), f" own{i}")) for _ in range(4)] + [" ".join(rng.choices(words, k=12))]
        rows.append((None if i % 9 == 0 else -1 if i == 7 else i // 2 if i % 5 == 0 else i, "http://h.org/" if i % 4 else "http://other.org/", ("<main>inside</main>" if i % 3 == 0 else "") + "".join(f"<div>{x}</div>" for x in parts)))
    df = spark.createDataFrame([*rows, rows[0], rows[1]], "page_id long, url string, html string")
    one, many = (sorted(map(str, html_extract.extract(df, most_pages=n).collect())) for n in (500, 3))
    assert many == one and len(one) == 62
    pair = "a passage of ten words that only two pages share"
    far = [(i, "http://h.org/", f"<p>{pair if i in (0, 599) else f'page {i} alone'}</p>") for i in range(600)]
    got = {r.page_id: r.text for r in html_extract.extract(spark.createDataFrame(far, "page_id long, url string, html string")).collect()}
    assert got[0] == got[599] == "" and got[5] == "page 5 alone"


def test_decontamination(spark, odd):
    bench = spark.createDataFrame([(1, "A train leaves Paris with 120 riders and after 3 stops it has 45 riders left how many got off"), (2, ""), (3, None)], "item_id long, text string")
    docs = spark.createDataFrame([(1, "intro words. a train leaves Paris with 90 riders and after 7 stops it has 33 riders left how many got off end"), (2, "a train leaves late"), (3, None), (4, "")], "doc_id long, text string")
    got = {r.doc_id: list(r["items"]) for r in decontaminate.mark(docs, bench).collect()}
    assert got == {1: [1], 2: [], 3: [], 4: []}
    assert decontaminate.clean(odd, bench).count() == odd.count()


@pytest.mark.parametrize(
    "item, doc",
    [
        ("A train travels 60 kilometers in 2 hours; how far in 5?", "A train travels 80 miles in 3 hours; how far in 7?"),
        ("The box (5) weighs 12, and the other box weighs 7; what is the sum?", "The box 6 weighs 14 and the other box weighs 9 what is the sum?"),
        ("A bag of rice of 5kg costs 12 euros so what does 8kg cost here", "A bag of rice of 6 pounds costs 14 dollars so what does 9 pounds cost here"),
        ("Alice has 3 red apples and eats 2 of them. Alice then buys 9 more.", "Bob has 5 red apples and eats 4 of them. Bob then buys 8 more."),
        ("There are 3 cats and 4 dogs in a house with 9 birds in cages", "There are 5 cats and 5 dogs in a house with 5 birds in cages"),
    ],
)
def test_decontamination_of_new_parameters(spark, item, doc):
    bench = spark.createDataFrame([(1, item)], "item_id long, text string")
    docs = spark.createDataFrame([(1, doc), (2, "another sentence with 5 cats, 7 miles and Bob in it; does it share the frame of any question?")], "doc_id long, text string")
    assert {r.doc_id: list(r["items"]) for r in decontaminate.mark(docs, bench).collect()} == {1: [1], 2: []}


def test_decontamination_keeps_scrambled_slots(spark):
    bench = spark.createDataFrame([(1, "so we count 4 red and 4 blue and 4 green pens")], "item_id long, text string")
    docs = spark.createDataFrame([(1, "so we count 6 red and 6 blue and 6 green pens"), (2, "so we count 6 red and 7 blue and 8 green pens")], "doc_id long, text string")
    assert {r.doc_id: list(r["items"]) for r in decontaminate.mark(docs, bench).collect()} == {1: [1], 2: []}


@pytest.mark.parametrize("most", [100_000, 0])
def test_decontamination_judges_rows(spark, monkeypatch, most):
    """Repeated and null ids on both sides, broadcast or shuffled."""
    monkeypatch.setattr(decontaminate, "MOST_TEXTS", most)
    q, other = "what is the smallest whole number that leaves a rest of one here", "tell us why the old bridge over the wide river was never built again"
    bench = spark.createDataFrame([(7, q), (7, other), (None, q), (None, None), (8, "...")], "item_id long, text string")
    rows = [(1, q), (1, "clean"), (None, other), (None, "clean too"), (2, q), (2, q), (3, None), (4, "")]
    docs = spark.createDataFrame([(*r, "mine", 5) for r in rows], "doc_id long, text string, items string, k1 int")
    got = sorted((str(r.doc_id), str(r.text), str(r["items"]), r.k1) for r in decontaminate.mark(docs, bench).collect())
    want = {q: [7, None], other: [7]}
    assert got == sorted((str(i), str(t), str(want.get(t, [])), 5) for i, t in rows)
    assert decontaminate.clean(docs, bench).count() == 4 and decontaminate.clean(docs, bench).columns == docs.columns
    assert decontaminate.clean(docs, bench.limit(0)).count() == len(rows) and decontaminate.clean(docs.limit(0), bench).count() == 0


def test_decontamination_against_brute_force(spark):
    """Every text of the tables against every item by windows of template words, without hashes; and texts made of parts of items."""
    bench = spark.read.parquet(f"{SF}/benchmark.parquet")
    items = [(r.item_id, r.text) for r in bench.collect()]
    rng = random.Random(8)
    docs = [(r.doc_id, r.text) for r in spark.read.parquet(f"{SF}/documents.parquet").collect()]
    for k in range(40):
        words = rng.choice(items)[1].split()
        lo, n = rng.randrange(len(words)), rng.randrange(5, 40)
        docs.append((10**6 + k, "Well then " + " ".join(str(int(w) + 3) if w.isdigit() else w for w in words[lo : lo + n]) + " and so on"))

    def read(text):
        tokens, values, initial = decontaminate.template(text.encode())
        return [(t, values) for t, _ in decontaminate.readings(tokens, initial)]

    want = {}
    known = [(i, read(t)) for i, t in items]
    for doc_id, text in docs:
        mine = [(t, v, {}) for t, v in read(text or "")] if text else []
        hit = set()
        for i, item in known:
            n = min(8, len(item[0][0]))
            cover = set()
            for (a, av), (b, bv, at) in ((x, y) for x in item for y in mine):
                if n not in at:
                    at[n] = {}
                    for d in range(len(b) - n + 1):
                        at[n].setdefault(tuple(b[d : d + n]), []).append(d)
                for s in range(len(a) - n + 1):
                    if all(x[0] == "<" for x in a[s : s + n]):
                        continue
                    for d in at[n].get(tuple(a[s : s + n]), ()):
                        if decontaminate.consistent(av[s:], 0, bv[d:], 0, a[s:], n):
                            cover |= set(range(s, s + n))
            size = len(item[0][0])
            run = max((sum(1 for _ in g) for _, g in itertools.groupby(sorted(cover), key=lambda x, c=itertools.count(): x - next(c))), default=0)
            if size and (len(cover) >= 0.6 * size or run >= 13):
                hit.add(i)
        want[doc_id] = sorted(hit)
    got = {r.doc_id: list(r["items"]) for r in decontaminate.mark(spark.createDataFrame(docs, "doc_id long, text string"), bench).collect()}
    assert got == want and sum(map(bool, want.values())) > 20


def test_pipeline(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "near_duplicates", "substring_dedup", "decontamination", "byte_bpe"]
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = C.cut(stage(spark, docs, SF))
        assert out.columns == docs.columns and 0 < out.count() <= docs.count(), name
        docs = out
    assert byte_bpe.digests(docs).count() == docs.count()


def _by_hand_mcd(x, share=0.75, first=2, more=2):
    """Moments of the last step for one group, in numpy."""
    Q = quality_rules
    floor, h = np.diag(np.square(Q.FLOOR)), int(np.ceil(share * len(x)))
    lower = lambda v: np.sort(v, axis=0)[max(0, -(-len(v) // 2) - 1)]
    m = lower(x)
    s = np.maximum(1.4826 * lower(np.abs(x - m)), Q.FLOOR)
    z = (x - m) / s
    u = z / np.sqrt((z * z).sum(axis=1, keepdims=True) + 1e-18)
    both = np.outer(s, s)
    now = [(m, c * both + floor) for c in (np.eye(4), 4 * u.T @ u / len(x), np.cov(np.tanh(z).T, bias=True))]
    far = lambda m, c: np.einsum("ij,jk,ik->i", x - m, np.linalg.inv(c), x - m)
    for k in range(first + more):
        made = []
        for m, c in now:
            d = far(m, c)
            near = x[d <= np.sort(d)[h - 1] * (1 + 1e-9)]
            made.append((near.mean(axis=0), np.cov(near.T, bias=True) * Q.consistency(share) + floor))
        now = [min(made, key=lambda e: np.linalg.det(e[1]))] if k == first - 1 else made
    near = x[far(*now[0]) <= Q.chi2_quantile(0.975, 4)]
    return near.mean(axis=0), np.cov(near.T, bias=True) * Q.consistency(0.975)


@pytest.mark.parametrize("most", [50_000, 0])
def test_robust_estimates_against_numpy(spark, monkeypatch, most):
    """Groups of several sizes, one constant, and all documents together; broadcast or shuffled."""
    Q = quality_rules
    monkeypatch.setattr(Q, "MOST_GROUPS", most)
    rng = np.random.default_rng(6)
    groups = {"a": rng.standard_normal((301, 4)) * (0.2, 1, 2, 1), "b": rng.standard_normal((40, 4)) + 3, "c": np.ones((7, 4)), "d": rng.standard_normal((2, 4))}
    groups["a"][:40] += 9
    rows = [(g, "s", 0, *map(float, v)) for g, x in groups.items() for v in x] + [("", "", 1, *map(float, v)) for x in groups.values() for v in x]
    got = {r.lang: r for r in Q.robust(spark.createDataFrame(rows, "lang string, source string, common int, x0 double, x1 double, x2 double, x3 double")).collect()}
    for g, x in [*groups.items(), ("", np.concatenate(list(groups.values())))]:
        m, c = _by_hand_mcd(x)
        assert got[g].n == len(x)
        assert np.allclose([got[g][f"m{i}"] for i in range(4)], m) and np.allclose([[got[g][f"c{min(i, j)}{max(i, j)}"] for j in range(4)] for i in range(4)], c / Q.consistency(0.975)), g


def test_nearest_is_exact(spark):
    d = [0.0, 0.0, 1e-12, 1.0, 1.0, 1.0, 1.00001, 2.0, 1e9, 5.0]
    for share, want in ((0.05, 2), (0.2, 2), (0.3, 3), (0.4, 6), (0.65, 7), (0.8, 8), (0.9, 9), (1.0, 10)):
        near = spark.createDataFrame([("g", len(d), x) for x in d], "g string, n int, d2 double")
        assert quality_rules.nearest(near, ["g"], share, True).count() == want, share


QUALITY_SQL = r"""
WITH w AS (SELECT doc_id, coalesce(text, '') AS t, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS ws FROM documents),
g AS (SELECT doc_id, s, array_to_string(ws[s:s+4], ' ') AS k FROM w, unnest(range(1, len(ws) - 3)) AS u(s)),
r AS (SELECT doc_id, s FROM (SELECT *, count(*) OVER (PARTITION BY doc_id, k) AS n FROM g) WHERE n > 1),
c AS (SELECT doc_id, count(DISTINCT p) AS n FROM r, unnest(range(s, s + 5)) AS v(p) GROUP BY doc_id),
l AS (SELECT doc_id, count(*) - count(DISTINCT x) AS n FROM w, unnest(string_split(t, chr(10))) AS u(x) WHERE regexp_matches(x, '[^\x20\x09-\x0D]') GROUP BY doc_id)
SELECT w.doc_id, CAST(len(ws) AS BIGINT) AS n_words, CAST(length(array_to_string(ws, '')) AS BIGINT) AS word_chars, CAST(length(regexp_replace(t, '[^#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols,
CAST(coalesce(l.n, 0) AS BIGINT) AS n_dup_lines, CAST(coalesce(c.n, 0) AS BIGINT) AS n_repeat_words, len(ws) < 10 OR 100 * coalesce(c.n, 0) > 20 * len(ws) AS base_failed
FROM w LEFT JOIN c USING (doc_id) LEFT JOIN l USING (doc_id)"""


def test_quality_base_columns_against_sql(spark):
    con = duckdb.connect()
    con.sql(f"create view documents as select * from '{SF}/documents.parquet'")
    want = con.sql(QUALITY_SQL)
    got = registry.QUERIES["op4_quality_rules"](spark, SF)
    assert sorted(map(str, got.select(*want.columns).toArrow().to_pylist())) == sorted(map(str, want.to_arrow_table().to_pylist()))


def test_quality_verdict_is_the_distance_alone(spark):
    rows = [(i, " ".join(f"{random.Random(i * 50 + k).choice('abcdefgh') * 5}{k}{i}" for k in range(40)), "en", "s") for i in range(60)]
    rows += [(100, " ".join(f"#$%{k}&" for k in range(40)), "en", "s"), (101, "alone in its group and yet like the others in all of its counts", "fr", "t")]
    got = {r.doc_id: r for r in quality_rules.judge(spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")).collect()}
    assert not got[100].kept and not got[100].base_failed and got[101].kept and all(got[i].kept for i in range(60))
    assert all(r.kept == (not r.base_failed and r.distance <= 30) for r in got.values())


def test_toxicity_gradient_by_differences():
    rng = np.random.default_rng(2)
    z, doc = rng.standard_normal(9), np.array([0, 0, 1, 1, 1, 2, 3, 3, 3])
    y, cost = np.array([1.0, 0, 1, 0]), np.array([0.5, 2.0, 1.0, 1.0])
    g, at = toxicity.gradient(z, doc, y, cost)
    p = 1 / (1 + np.exp(-z))
    want = [1 - np.prod(1 - p[doc == k]) for k in range(4)]
    assert np.isclose(at, np.sum(cost * np.where(y > 0, np.log(want), np.log1p(-np.array(want)))) / 4)
    for i in range(9):
        step = np.zeros(9)
        step[i] = 1e-6
        assert np.isclose(g[i], (toxicity.gradient(z + step, doc, y, cost)[1] - toxicity.gradient(z - step, doc, y, cost)[1]) / 2e-6, atol=1e-6)


def test_toxicity_fits_whole_texts_within_bounds(spark, monkeypatch):
    rows = [(i, f"text {i} " * 10, i % 2) for i in range(40)] + [(100, "long " * 4000, 1), (101, "again " * 200, 0), (101, "again " * 300, 0)]
    docs = spark.createDataFrame([r[:2] for r in rows], "doc_id long, text string")
    labels = spark.createDataFrame([(i, y) for i, _, y in rows] + [(5, 1), (7, 1), (500, 0)], "doc_id long, toxic int")
    got = []
    monkeypatch.setattr(toxicity, "fit", lambda rows, counts: got.append((rows, counts)))
    toxicity.train(docs, labels)
    toxicity.train(docs, labels, most_bytes=6000)
    toxicity.train(docs, labels, most_bytes=900)
    (every, counts), (some, same), (few, _) = got
    assert sorted(every) == sorted((t.encode(), y) for _, t, y in rows) and counts == same == (23, 23)
    assert sorted(some) == sorted((t.encode(), y) for i, t, y in rows if i != 100)
    assert 8 <= len(few) < 40 and set(few) <= set(every) and all(sum(len(t) + 16 for t, y in few if y == k) <= 900 for k in (0, 1))
    assert toxicity.train(docs, labels, most_bytes=10).weight is None


def test_toxicity_scores_by_hand(spark, odd):
    """Every score is the noisy-or of its sentences' logistic scores, words counted once a sentence."""
    model = toxicity.Model(np.random.default_rng(3).standard_normal(1 << toxicity.BITS) * 0.3, -2.0)
    text = {r.doc_id: r.text for r in odd.where("doc_id is not null").collect()}
    for r in toxicity.score(odd, model, 0.3, "doc_id").where("doc_id is not null").collect():
        raw = (text[r.doc_id] or "").encode()
        keep = 1.0
        for lo, hi in toxicity.sentences(raw):
            z = -2.0 + sum(model.word(w) for w in set(raw[lo:hi].split()))
            keep *= 1 - 1 / (1 + np.exp(-np.clip(z, -30, 30)))
        assert np.isclose(r.score, 1 - keep) and r.predicted == int(r.score >= 0.3)


def test_bpe_by_plain_merging(spark):
    """Ranks read from the file, the lowest-ranked neighbours merged again and again, without the library."""
    import base64

    import public_tokenizers
    import regex

    with open(byte_bpe.default_ranks(), "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}

    def merge(raw):
        parts = [raw[i : i + 1] for i in range(len(raw))]
        while len(parts) > 1:
            best = min(range(len(parts) - 1), key=lambda i: ranks.get(parts[i] + parts[i + 1], 1 << 40))
            if parts[best] + parts[best + 1] not in ranks:
                break
            parts[best : best + 2] = [parts[best] + parts[best + 1]]
        return [ranks[p] for p in parts]

    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{SF}/documents.parquet").where("length(text) < 3000").limit(60).collect()]
    rows += [(10**6, "don't  stop\n\n now é日本 12345 \t x"), (10**6 + 1, " "), (10**6 + 2, "zqxj" * 40), (10**6 + 3, None)]
    want = {i: [k for m in regex.findall(public_tokenizers.PATTERN, t or "") for k in merge(m.encode())] for i, t in rows}
    got = {r.doc_id: r.ids_sha256 for r in byte_bpe.digests(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {i: hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest() for i, ids in want.items()}


def test_token_counts_on_texts(spark):
    """Whole texts by a plain Viterbi over all of their characters at once, without an automaton or words; among equals the path that came first stays."""
    path = token_counts.P.default_model()
    names, scores, types = token_counts.P.vocabulary(path)
    piece = {p: s for p, s, t in zip(names, scores, types) if t == 1}
    unknown, widest = min(piece.values()) - 10, max(map(len, piece))

    def plain(text):
        w = token_counts.marked(text)
        best = [(0.0, 0)] + [None] * len(w)
        for i in range(len(w)):
            for k in range(1, min(widest, len(w) - i) + 1):
                s, n = (piece[w[i : i + k]], 1) if w[i : i + k] in piece else (unknown, len(w[i].encode())) if k == 1 else (None, 0)
                if s is not None and (best[i + k] is None or round(best[i][0] + s, 9) > round(best[i + k][0], 9)):
                    best[i + k] = (best[i][0] + s, best[i][1] + n)
        return best[-1][1]

    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{SF}/documents.parquet").where("length(text) < 2500").limit(40).collect()]
    rows += [(10**6, "a  b   c"), (10**6 + 1, "日本 x\ny"), (10**6 + 2, ""), (10**6 + 3, None), (10**6 + 4, "ab" * 300)]
    got = {r.doc_id: r.n_tokens for r in token_counts.counted(spark.createDataFrame([(*r, 1) for r in rows], "doc_id long, text string, n_tokens int")).collect()}
    assert got == {i: plain(t) if t else 0 for i, t in rows}


def test_repeats_against_brute_force():
    rng = random.Random(3)
    for _ in range(60):
        pages = [[[rng.choice("abc") for _ in range(rng.randrange(1, 9))] for _ in range(rng.randrange(0, 3))] for _ in range(4)]
        ids_ = [0, 1, rng.choice((1, 2)), 3]
        got = html_extract.repeated(pages, ids_, 3)
        for k, page in enumerate(pages):
            for j, block in enumerate(page):
                want = np.zeros(len(block), bool)
                for lo in range(len(block)):
                    for hi in range(lo + 1, len(block) + 1):
                        if hi - lo >= 3 or (lo, hi) == (0, len(block)):
                            if any(i != ids_[k] and any(b[x : x + hi - lo] == block[lo:hi] for x in range(len(b) - hi + lo + 1)) for i, p in zip(ids_, pages) for b in p):
                                want[lo:hi] = True
                assert (got[k][j] == want).all()


@pytest.mark.parametrize(
    "page, want",
    [
        ('<p title="the hidden door">keep me</p>', "keep me"),
        ('<p data-id="share" aria-invalid="ad">x</p>', "x"),
        ("<p class=it's>hello</p>", "hello"),
        ("<p hidden>no</p><p>yes</p><p hidden=until-found>found</p>", "yes\nfound"),
        ("<div style='color:red; display:none'>n</div>y", "y"),
        ('<p class="a>b" id=c>t</p> 1 < 2 <3', "t\n1 < 2 <3"),
        ('<div class="has-sidebar"><main class="with-nav">m</main></div>', "m"),
        ("<form id=whole><input>x<article>a<form>f</form></article></form>", "a"),
        ("<section id=comments><article class=comment>c</article></section><p>t", "t"),
        ('<p>open <b class="never closed>gone', "open"),
    ],
)
def test_html_markup(page, want):
    b = html_extract.blocks(page)
    main = any(k == html_extract.MAIN for k, _ in b)
    assert "\n".join(t for k, t in b if k == (html_extract.MAIN if main else html_extract.OUTSIDE)) == want


def test_html_takes_time_in_proportion():
    for part in ('<a b="', "<a b='\"", "<b><p></i>", "<!", "<x ", "&#"):
        t = time.perf_counter()
        html_extract.blocks(part * 100_000)
        assert time.perf_counter() - t < 20, part


def test_html_clashing_columns_and_long_pages(spark):
    rows = [(1, "http://h.org/", "<main>" + "<p>word " * 50_000 + "</main>", "t", 1), (1, "http://h.org/", None, "t", 2)]
    got = html_extract.extract(spark.createDataFrame(rows, "page_id long, url string, html string, text string, host int")).collect()
    assert sorted(r.n_chars for r in got) == [0, 50_000 * 5 - 1]
    assert html_extract.extract(spark.createDataFrame(rows, "page_id long, url string, html string, text string, host int").limit(0)).count() == 0


def test_warc_decides_each_row(spark):
    rows = [(1, "u", "same"), (2, "u", "same"), (1, "u", "other"), (None, "u", "same"), (None, "v", "alone"), (None, "w", "alone"), (3, None, None), (3, None, ""), (4, "u", "other")]
    df = spark.createDataFrame([(*r, "x") for r in rows], "page_id long, url string, html string, record_type string")
    got = warc.read(spark, warc.write(df, C.scratch(spark, "t"))).collect()
    seen = sorted((str(r.page_id), r.record_type, str(r.refers_to), bytes(r.payload).decode() if r.payload is not None else "-", r.payload_digest) for r in got)
    d = {t: warc.base32_sha1(t.encode()) for t in ("same", "other", "alone", "")}
    assert seen == sorted([("1", "response", "None", "same", d["same"]), ("2", "revisit", "1", "-", d["same"]), ("1", "response", "None", "other", d["other"]), ("None", "revisit", "1", "-", d["same"]), ("None", "response", "None", "alone", d["alone"]), ("None", "response", "None", "alone", d["alone"]), ("3", "response", "None", "", d[""]), ("3", "response", "None", "", d[""]), ("4", "revisit", "1", "-", d["other"])])
    empty = warc.write(df.limit(0), C.scratch(spark, "t"))
    assert warc.read(spark, empty).count() == 0


def test_warc_finds_a_changed_payload():
    raw = warc.record(5, "u", b"a long payload", None, None, False)
    assert warc.parse(raw)[:5] == (5, "u", "response", 14, warc.base32_sha1(b"a long payload"))
    with pytest.raises(ValueError, match="digest"):
        warc.parse(raw.replace(b"long", b"lung"))
    with pytest.raises(ValueError, match="bytes"):
        warc.parse(raw[:-12])


def test_warc_of_other_writers(spark, tmp_path):
    body = b"HTTP/1.0 200 OK\r\ncontent-type:text/html\r\nX-Long: a\r\n b\r\n\r\n<p>x"
    raw = [
        b"WARC/1.0\r\nwarc-type: warcinfo\r\nWARC-Record-ID:<urn:uuid:1-2>\r\nContent-Length: 9\r\n\r\nsoftware:\r\n\r\n",
        b"WARC/1.0\r\nWARC-TYPE: response\r\nWarc-Record-Id: <urn:uuid:3-4>\r\nWARC-Target-URI: http://h/\r\nContent-Type: application/http\r\nCONTENT-LENGTH: %d\r\n\r\n%s\r\n\r\n" % (len(body), body),
        b"WARC/1.0\r\nWARC-Type: revisit\r\nWARC-Record-ID: <urn:uuid:5-6>\r\nWARC-Refers-To: <urn:uuid:3-4>\r\nWARC-Payload-Digest: sha1:ABC\r\nContent-Length: 0\r\n\r\n\r\n\r\n",
    ]
    path = str(tmp_path / "a.warc.gz")
    data = b"".join(warc.member(r) for r in raw)
    with open(path, "wb") as f:
        f.write(data)
    files = spark.createDataFrame([(path, len(data))], "path string, length long")
    got = {r.record_type: r for r in warc.read(spark, files, split_bytes=100).collect()}
    assert len(got) == 3 and all(r.page_id is None for r in got.values())
    assert bytes(got["response"].payload) == b"<p>x" and got["response"].payload_bytes == 4 and got["response"].url == "http://h/"
    assert (got["revisit"].payload_digest, got["revisit"].refers_to_id, got["revisit"].payload) == ("ABC", "<urn:uuid:3-4>", None)
    assert bytes(got["warcinfo"].payload) == b"software:" and got["warcinfo"].record_id == "<urn:uuid:1-2>"


def test_rows_that_share_an_id(spark):
    """Null and repeated ids are told apart by their texts; equal rows stay one document."""
    base = " ".join(f"w{i}" for i in range(60))
    rows = [(None, base), (None, "some other text " + base), (5, "short one"), (5, base), (5, base), (6, base + " tail"), (7, None), (8, "")]
    df = spark.createDataFrame([(*r, "en", "s", 1) for r in rows], "doc_id long, text string, lang string, source string, n_chars long")
    got = substring_dedup.deduplicate(df, 20).collect()
    assert sorted(r.n_removed for r in got) == [0, 0, 0, 0, 60, 60, 60, 60]
    near = sorted((str(r.doc_id), r.n_shingles, str(r.component_id), r.kept) for r in near_dup.near_duplicates(df, 4, 80).collect())
    assert [x for x in near if x[0] == "5"] == [("5", 1, "5", True), ("5", 57, "None", False), ("5", 57, "None", False)]
    kept = corpus_pipeline.drop_near_duplicates(spark, df, SF).collect()
    assert sorted(str(r.text) for r in kept if r.text) == sorted([min((base, "some other text " + base), key=lambda t: spark.sql("select xxhash64(:t)", {"t": t}).first()[0]), "short one"])
    assert len(kept) == 4


def test_connected_with_hubs(spark, monkeypatch):
    monkeypatch.setattr(C, "HOT", 10)
    edges = [(0, i) for i in range(1, 300)] + [(1000, i) for i in range(300, 600)] + [(5, 1000)] + [(2000 + i, 2001 + i) for i in range(30)]
    got = {r.node: r.root for r in C.connected(spark, spark.createDataFrame(edges, "u long, v long")).collect()}
    assert got == {**{i: 0 for i in [*range(600), 1000]}, **{2000 + i: 2000 for i in range(31)}}


def test_stages_against_brute_force(spark):
    """The stages that have a plain definition, each on its own input."""
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    rows = {r.doc_id: r for r in docs.collect()}
    words = {i: (r.text or "").encode().lower().split() for i, r in rows.items()}
    sets = {i: {tuple(w[k : k + 5]) for k in range(len(w) - 4)} or ({tuple(w)} if w else set()) for i, w in words.items()}
    root = {i: i for i in rows}
    find = lambda x: x if root[x] == x else find(root[x])
    for i, j in itertools.combinations(sorted(rows), 2):
        if sets[i] and 100 * len(sets[i] & sets[j]) >= 80 * len(sets[i] | sets[j]):
            a, b = sorted((find(i), find(j)))
            root[b] = a
    got = {r.doc_id: r for r in corpus_pipeline.drop_near_duplicates(spark, docs, SF).collect()}
    assert set(got) == {i for i in rows if find(i) == i} and all(got[i] == rows[i] for i in got)
    seen, want = set(), {}
    for i in sorted(rows):
        w = (rows[i].text or "").encode().split()
        gone = [False] * len(w)
        for k in range(len(w) - 19):
            x = tuple(w[k : k + 20])
            if x in seen:
                gone[k : k + 20] = [True] * 20
            seen.add(x)
        left = [x for x, g in zip(w, gone) if not g]
        if left or not w:
            want[i] = b" ".join(left).decode() if any(gone) else rows[i].text
    got = {r.doc_id: r for r in corpus_pipeline.remove_repeats(spark, docs, SF).collect()}
    assert {i: r.text for i, r in got.items()} == want
    assert all(r.n_chars == len(r.text) for i, r in got.items() if r.text != rows[i].text)
    marked = {r.doc_id for r in decontaminate.mark(docs, spark.read.parquet(f"{SF}/benchmark.parquet")).where("size(items) > 0").collect()}
    assert {r.doc_id for r in corpus_pipeline.drop_contaminated(spark, docs, SF).collect()} == set(rows) - marked
    model = toxicity.train(docs, spark.read.parquet(f"{SF}/labels.parquet"))
    bad = {r.doc_id for r in toxicity.score(docs, model, 0.3, "doc_id").where("score >= 0.3").collect()}
    assert {r.doc_id for r in corpus_pipeline.drop_toxic(spark, docs, SF).collect()} == set(rows) - bad


def test_stages_take_odd_rows(spark, odd):
    for name, stage in corpus_pipeline.STAGES:
        assert stage(spark, odd, SF).count() <= odd.count(), name
        assert stage(spark, odd.limit(0), SF).count() == 0, name


def test_word_kinds_by_the_short_way_and_hashes_with_words():
    """Words of letters skip the number's pattern with the same reading; a template's hashes are those of its tokens."""
    import re

    from skyweave.llm import decontaminate as D

    def long_way(raw):
        m = D.NUMBER.fullmatch(raw)
        unit = m and m[2] and m[2].lower()
        if m is not None and (unit is None or unit in D.UNITS):
            return D.DIGITS, m[1].lower(), raw[-1] in ".!?:", unit
        bare = re.sub(r"^[\W_]+|[\W_]+$", "", raw)
        ends = raw[-1] in ".!?:"
        return D.BLANK if not bare else D.CAPITAL if bare[0].isupper() and not bare.isupper() else D.LAST if ends else D.PLAIN, bare.lower(), ends, None

    words = "a A Ab aB AB ab, Ab. AB! ab: ab; a? ab.. (ab) ab's _ab ab_ 1 12km 3.5kg. $4 5% km km. \u00c4ra \u00e4ra. \u00b2 a\u00b2 \u0130x, \u1e9e. \u01c5a \u4e2d\u6587 \u0661 x\u0301 . , - \u2014 a-b 7Up 7 up".split()
    assert [D._read(w) for w in words] == [long_way(w) for w in words]
    text = (" ".join(words) + " In 3 km Anna Berg ran 5km. Then 7 Bob paid $4 for 2 kg.").encode()
    tokens, values, initial, h = D.hashed_template(text)
    assert (tokens, values, initial) == D.template(text) and h.tolist() == D.hashes(tokens).tolist()
    assert D.hashed_template(None)[3].tolist() == []
