"""Operators against slower forms of the same definition, and on odd tables."""

import itertools
import re
import sys
from pathlib import Path

import numpy as np
import pyarrow as pa
import pytest

sys.path.insert(0, str(Path(__file__).parent))

from entitygraph.llm import decontaminate, html_text, near_copies, packing, pii, quality, simhash, suffix_dedup, token_files, toxicity, vector_join

KIND = "doc_id long, text string, lang string, bucket string, rank long, mark long, n int, kind int"


def table(spark, rows):
    """Rows of (id, text), with columns whose names the operators use themselves."""
    return spark.createDataFrame([(i, t, "en", "x", 1, 2, 3, 4) for i, t in rows], KIND)


def rng_words(seed, n, vocabulary=4000):
    r = np.random.default_rng(seed)
    return " ".join(f"w{k}" for k in r.integers(0, vocabulary, n))


# ---- factorisation machine
def test_pairs_of_features_one_by_one():
    model = quality.FactorisationMachine()
    r = np.random.default_rng(0)
    model.w, model.v, model.bias = r.normal(size=model.n), r.normal(size=model.v.shape), 0.3
    texts = pa.array(["one two three two", "", "A b. C d!\nA b.", "x " * 50])
    borders, slots, stats = quality.features(texts)
    got = model.score(borders, slots, stats)
    for i in range(len(texts)):
        words = slots[borders[i] : borders[i + 1]]
        x = {int(k): 1 / np.sqrt(len(words)) for k in words} | {(1 << quality.WORD_BITS) + k: z for k, z in enumerate(np.clip(stats[i], -4, 4))}
        raw = model.bias + sum(model.w[k] * v for k, v in x.items())
        raw += sum(model.v[a] @ model.v[b] * x[a] * x[b] for a, b in itertools.combinations(x, 2))
        assert got[i] == pytest.approx(1 / (1 + np.exp(-np.clip(raw, -30, 30))), rel=1e-9)


# ---- decontamination
def least_edits(pattern, text):
    row = np.zeros(len(text) + 1, int)
    for i, p in enumerate(pattern, 1):
        new = np.empty_like(row)
        new[0] = i
        for j, t in enumerate(text, 1):
            new[j] = min(row[j] + 1, new[j - 1] + 1, row[j - 1] + (p != t))
        row = new
    return row.min()


def test_regions_against_all_substrings():
    r = np.random.default_rng(3)
    letters = lambda n: "".join("abcdefgh "[k] for k in r.integers(0, 9, n))
    items = [(i, letters(int(r.integers(20, 150)))) for i in range(6)]
    segments = decontaminate.Segments(items)
    texts = []
    for k in range(24):
        own = list(items[k % 6][1])
        for _ in range(k % 8):
            at = int(r.integers(0, len(own)))
            if k % 3 == 0:
                own[at] = "z"
            elif k % 3 == 1:
                del own[at]
            else:
                own.insert(at, "y")
        texts.append(letters(30) + "".join(own) + letters(20))
    for text in texts:
        data = decontaminate.normalised(np.frombuffer(text.encode(), np.uint8))
        joined = np.append(data, np.zeros(decontaminate.Q, np.uint8))
        t, s, d = segments.regions(joined, np.array([0]))
        good = segments.aligned(joined, np.zeros(len(t), int), np.full(len(t), len(data)), s, d) <= segments.edits[s] if len(t) else np.empty(0, bool)
        want = {k for k in range(len(segments.texts)) if least_edits(segments.texts[k].tolist(), data.tolist()) <= segments.edits[k]}
        assert set(np.unique(s[good]).tolist() if len(t) else []) == want


def test_short_items_and_odd_rows(spark):
    bench = spark.createDataFrame([(1, "Yes, sir!"), (2, "!!"), (3, None), (None, "Yes, sir!"), (1, "other words here")], "item_id long, text string")
    rows = [(1, "he said: yes sir."), (2, "yes sirree"), (3, "!!"), (None, "yes sir"), (4, None), (5, ""), (1, "nothing"), (6, "yes sir " * 20000)]
    got = sorted((r["doc_id"], r["item_id"]) for r in decontaminate.contaminated_pairs(table(spark, rows), bench).collect())
    assert got == [(1, 1), (6, 1)]
    kept = decontaminate.drop_contaminated(table(spark, rows), bench)
    assert kept.count() == 5 and kept.columns == table(spark, []).columns
    assert decontaminate.drop_contaminated(table(spark, rows), bench.limit(0)).count() == len(rows)


# ---- toxicity
def test_all_maximal_segments():
    """The definition: split at the best segment, and the same left and right of it."""
    def by_definition(scores, base=0):
        best = max(((sum(scores[i:j]), i - j, i, j) for i in range(len(scores)) for j in range(i + 1, len(scores) + 1)), default=(0,))
        if best[0] <= 0:
            return []
        top, _, i, j = best
        return [*by_definition(scores[:i], base), (base + i, base + j, top), *by_definition(scores[j:], base + j)]

    r = np.random.default_rng(1)
    for _ in range(200):
        scores = [float(x) for x in r.normal(-0.3, 2, int(r.integers(1, 25)))]
        got = toxicity.segments(scores)
        want = sorted(by_definition(scores))
        assert [(a, b) for a, b, _ in sorted(got)] == [(a, b) for a, b, _ in want]
        assert [v for *_, v in sorted(got)] == pytest.approx([v for *_, v in want])


def test_stretches_of_drift_are_one_step():
    model = toxicity.ToxicityModel({"bad": (2.0, 9.0), "nice": (-1.5, -6.0)})
    text = "a bad b c bad bad nice d e f g h bad " * 3
    words = text.split()
    whole = toxicity.segments([model.value(w) for w in words])
    (n, spans), = model.passages(pa.array([text]))
    assert n == len(words) and [(a, b) for a, b, _ in spans] == [(a, b) for a, b, _ in whole] and [v for *_, v in spans] == pytest.approx([v for *_, v in whole])
    assert model.passages(pa.array(["", None, "plain words"])) == [(0, []), (0, []), (2, [])]


def test_calibration():
    model = toxicity.ToxicityModel({"bad": (2.0, 9.0)}, rate=0.7, scale=0.2, slope=0.5, base=-1.0)
    assert model.expected(3.0, 50) == pytest.approx(0.2 * 50 * np.exp(-2.1))
    strong = model.probability(np.array([-1000.0, 0.0, 5.0, 40.0, 80.0, 1e4, 1e6]))
    assert (np.diff(strong) > 0).all() and strong[1] == pytest.approx(1 / (1 + np.e)) and 0 < strong[0] and strong[-1] < 1


def test_rejects_only_what_leans(spark):
    docs = [(i, ("vile slur words " if i % 3 == 0 else "quiet river stones ") * 5 + rng_words(i, 20)) for i in range(90)]
    labels = spark.createDataFrame([(i, int(i % 3 == 0)) for i in range(90)], "doc_id long, toxic int")
    rows = [*docs, (None, "vile slur words " * 5), (500, None), (501, ""), (502, "vile slur words " * 20000), (502, "quiet")]
    kept = {r["doc_id"] for r in toxicity.drop_toxic(table(spark, rows), labels).collect()}
    assert {i for i, _ in docs if i % 3} | {None, 500, 501} == kept


# ---- near copies
def test_near_copies_of_the_table(spark):
    """All pairs at a similarity of 0.8 of five-word shingles, by an index of all shingles."""
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text")
    rows = [(r["doc_id"], r["text"]) for r in docs.collect()]
    sets = {i: set(simhash.shingle_hashes((t or "").encode(), 5).tolist()) for i, t in rows}
    same = {i: " ".join((t or "").encode().lower().decode().split()) for i, t in rows}
    where = {}
    for i, s in sets.items():
        for h in s:
            where.setdefault(h, []).append(i)
    pairs = {p for x in where.values() for p in itertools.combinations(sorted(x), 2)}
    parent = {i: i for i, _ in rows}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    byword = {}
    for i, w in same.items():
        byword.setdefault(w, []).append(i)
    links = [(a, b) for a, b in pairs if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])] + [(x[0], y) for x in byword.values() for y in x[1:]]
    for a, b in links:
        a, b = sorted((root(a), root(b)))
        parent[b] = a
    got = {r["doc_id"]: r["component_id"] for r in near_copies.near_copy_components(docs).collect()}
    assert got == {i: root(i) for i, _ in rows}


# ---- packing
def test_stretches_of_the_curve(spark):
    rows = [(i, rng_words(i % 30, 40 + 13 * (i % 7))) for i in range(200)] + [(900 + i, "the same text again and again " * 10) for i in range(150)] + [(5, "twice"), (5, "twice")]
    pieces = packing.pack(table(spark, rows), range_ids=400).collect()
    from tokenizers import Tokenizer

    from entitygraph.llm.tokens import vocabulary

    whole, want = Tokenizer.from_file(vocabulary()), {}
    for i, t in rows:
        want[i] = want.get(i, 0) + len(whole.encode(t, add_special_tokens=False).ids) + 1
    total = {}
    for p in pieces:
        total[p["doc_id"]] = total.get(p["doc_id"], 0) + p["length"]
    assert total == want
    seq = {}
    for p in pieces:
        seq.setdefault(p["sequence_id"], []).append((p["offset"], p["length"]))
    for spans in seq.values():
        at = 0
        for start, n in sorted(spans):
            assert start == at
            at += n
        assert at & at - 1 == 0 and at <= 4096
    kept = spark.createDataFrame([(int(k), i, 50) for i, k in enumerate(sorted([7 << 30] * 60 + list(range(0, 1 << 40, 1 << 34))))], "key long, doc_id long, n long")
    placed, stretches = packing._ranges(kept, 300)
    got = placed.groupBy("stretch").sum("n").collect()
    assert len(got) > 8 and max(r[1] for r in got) <= 1500 and max(r[0] for r in got) < stretches
    order = [(r["key"], r["stretch"]) for r in placed.where(f"key != {7 << 30}").orderBy("key").collect()]
    assert order == sorted(order, key=lambda x: (x[1], x[0]))


def test_whole_tokenizer_where_the_file_states_other_rules(spark):
    from tokenizers import Tokenizer

    from entitygraph.llm.tokens import WordEncoder, vocabulary

    other = WordEncoder(vocabulary("byte_bpe_50k.json"))
    texts = ["Hello there,  World's 12", "", "naïve\n\nlines"]
    offsets, ids = other.encode(pa.array(texts), 7)
    whole = Tokenizer.from_file(vocabulary("byte_bpe_50k.json"))
    assert not other.by_words
    assert [ids[a:b].tolist() for a, b in zip(offsets[:-1], offsets[1:])] == [[*whole.encode(t, add_special_tokens=False).ids, 7] for t in texts]


def test_words_of_every_plain_character():
    from entitygraph.llm.tokens import WordEncoder, vocabulary

    own = WordEncoder(vocabulary())
    some = [chr(c) for c in [*range(0x21, 0x7F), *range(0xA1, 0x250)]]
    texts = [f"a{c}b1{c}{c.upper()} {c}{c}'S don{c}'ll x<|{c}" for c in some] + ["two  spaces", "tab\tin", "İx ǅ ß"]
    offsets, ids = own.encode(pa.array(texts))
    assert own.by_words
    for i, t in enumerate(texts):
        assert ids[offsets[i] : offsets[i + 1]].tolist() == own.whole.encode(t, add_special_tokens=False).ids, t


# ---- PII
def test_spans_that_no_base_rule_finds(spark):
    rows = [(i, f"Call +1 (5{i % 10}8) 555-64{i % 90 + 10} or write a{i}@b{i}.org, token = \"{'0a1b2c3d4e' * 3}{i:010d}\" now 4111 1111 1111 1111") for i in range(40)]
    extra = [
        (1000, "Call (578) 555-6437 now"), (1001, "me.too (at) site (dot) org"), (1002, 'password = "hunter2x99"'), (1003, "pay 4111.1111.1111.1111"), (1004, "number 5554443332 and 2024-10-11"),
        (1005, "commit 9fceb02d0ae598e95dc970b74767f19372d61af8 done"), (1006, "card 4111.1111.1111.1112"), (None, "mail a@b.com"), (7, "x a@b.com y"), (7, "see to see at all"), (8, None), (9, ""),
    ]
    df = table(spark, rows + extra)
    clean = {}
    for r in pii.redact(df).collect():
        clean.setdefault(r["doc_id"], []).append(r["text"])
    assert clean[1000] == ["Call [PHONE] now"] and clean[1001] == ["[EMAIL]"] and clean[1002] == ['password = "[SECRET]"'] and clean[1003] == ["pay [CARD]"]
    assert clean[1004] == ["number 5554443332 and 2024-10-11"] and clean[1005][0].startswith("commit 9fceb") and clean[1006] == ["card 4111.1111.1111.1112"]
    assert clean[None] == ["mail [EMAIL]"] and {"x [EMAIL] y", "see to see at all"} <= set(clean[7]) and None in clean[8] and "" in clean[9]
    added = pii.pii_spans(df).where("not base").count()
    assert added >= 44 and pii.redact(df).columns == df.columns
    assert pii.pii_spans(table(spark, [])).count() == 0


def test_pieces_across_chunks(spark, monkeypatch):
    monkeypatch.setattr(pii, "CHUNK", 7)
    text = "😀 mail x@y.zz and a.b@c.de, or +1 (578) 555-6437 then 10.0.0.1 end 😀 no more"
    (row,) = pii.redact(table(spark, [(1, text)])).collect()
    assert row["text"] == "😀 mail [EMAIL] and [EMAIL], or [PHONE] then [IP] end 😀 no more"


# ---- pages
def plain_main(html):
    """Another reader of simple pages: drops elements by a stack of open tags, keeps what is left of the article."""
    import html as h

    html = re.sub(r"(?s)<(script|style|nav|footer|aside)\b.*?</\1>", " ", html)
    html = re.sub(r'(?s)<(div|ul) class="(?:ads|comments|menu)">[^<]*(?:<p>[^<]*</p>)*</\1>', " ", html)
    return " ".join(h.unescape(re.sub(r"(?i)</?(?:p|div|article|section|h1|ul|li|br|body)\b[^>]*>", " ", html)).split())


def test_pages_against_another_reader(spark):
    rows, want = [], {}
    for i in range(40):
        r = np.random.default_rng(i)
        say = lambda n: rng_words(int(r.integers(1 << 30)), n)  # noqa: B023, E731
        inner = "".join(f"<p>{say(30)} &amp; more</p>" + ('<div class="ads">buy this</div>' if k % 2 else "") for k in range(4))
        wrap = ["<article>{}</article>", '<div class="post-{}">{{}}</div>'.format(i), '<div class="search-results discussion"><section>{}</section></div>'][i % 3]
        html = f'<body><nav><ul><li>Home</li></ul></nav>{wrap.format("<h1>Title</h1>" + inner)}<div class="comments"><p>{say(20)}</p></div><aside>side</aside><footer>foot</footer></body>'
        rows.append((i, f"http://h{i % 3}.example/{i}", html))
        want[i] = plain_main(html)
    got = {r["page_id"]: r["text"] for r in html_text.extract_pages(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert got == want


def test_odd_pages(spark):
    deep, broken = "<div>a " * 20000, "<div class='x><p>one<b>two</i></div></p></span>three <a href=\"q"
    rows = [(1, None, deep), (1, None, deep), (2, "u", broken), (3, "u", "<p>" + "word " * 100000), (None, "u", "<p>x"), (4, None, None)]
    got = [(r["page_id"], len(r["text"]), r["n_chars"]) for r in html_text.extract_pages(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()]
    assert len(got) == 6 and all(a == b for _, a, b in got) and sorted(a for i, a, _ in got if i == 1) == [39999, 39999] and (3, 499999, 499999) in got
    assert html_text.extract_pages(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


# ---- empty tables, repeated and missing ids
def test_empty_tables(spark):
    none = table(spark, [])
    assert suffix_dedup.suffix_dedup(none).count() == simhash.simhash_components(none).count() == near_copies.near_copy_components(none).count() == 0
    vectors = spark.createDataFrame([], "vec_id long, embedding array<double>, label int")
    assert vector_join.embedding_near_dedup(vectors).count() == 0
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert toxicity.drop_toxic(none, labels).count() == 0 and quality.quality_scores(none, quality.fit_quality(none, labels)).count() == 0
    from entitygraph.shared import new_path

    path = new_path(spark, "no-tokens")
    token_files.write_token_files(none, path, 1)
    assert token_files.read_token_files(spark, path).count() == 0


def test_repeated_and_missing_ids(spark):
    long = rng_words(1, 200)
    rows = [(1, long), (1, long), (None, long), (2, long + " end"), (None, None)]
    got = simhash.simhash_components(table(spark, rows)).collect()
    assert len(got) == 5 and {r["component_id"] for r in got if r["doc_id"] in (1, 2)} == {1}
    kept = near_copies.drop_near_copies(table(spark, rows)).collect()
    assert sorted((r["doc_id"] or 0) for r in kept) == [0, 0, 1, 1]
    from entitygraph.shared import new_path

    path = new_path(spark, "tokens")
    token_files.write_token_files(table(spark, rows), path, 1)
    back = token_files.read_token_files(spark, path).orderBy("start").collect()
    assert [r["doc_id"] for r in back] == [1, 1, 2] and back[0]["ids_crc32"] == back[1]["ids_crc32"]


def test_pipeline_stages(spark, tmp_path):
    """Each stage on its own input: odd rows, an empty table, and copies, toxic, leaked and private texts among them."""
    import corpus_pipeline
    import shutil

    sf = str(tmp_path)
    for t in ("labels", "benchmark"):
        shutil.copy(f"/root/testdata/sf0.001/{t}.parquet", f"{sf}/{t}.parquet")
    item = spark.read.parquet(f"{sf}/benchmark.parquet").orderBy("item_id").first()["text"]
    rows = [(10_001, rng_words(1, 120)), (10_002, rng_words(1, 120)), (10_003, item), (10_004, "write to a.b@c.org now"), (10_005, None), (None, "no id but x@y.org"), (10_006, "")]
    docs = spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    stages = dict(corpus_pipeline.STAGES)
    near = {r["doc_id"] for r in stages["simhash_near_dedup"](spark, docs, sf).collect()}
    assert 10_001 in near and 10_002 not in near and None in near
    leaked = {r["doc_id"] for r in stages["decontamination"](spark, docs, sf).collect()}
    assert 10_003 not in leaked and {10_001, None} <= leaked
    texts = {r["doc_id"]: r["text"] for r in stages["pii"](spark, docs, sf).collect()}
    assert texts[10_004] == "write to [EMAIL] now" and texts[None] == "no id but [EMAIL]"
    assert stages["toxicity"](spark, docs, sf).count() == len(rows)
    empty = docs.limit(0)
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, empty, sf)
        assert out.count() == 0 and (name == "packing" or out.columns == docs.columns)
    docs.write.parquet(f"{sf}/documents.parquet")
    pieces = corpus_pipeline.run(spark, sf).collect()
    assert {p["doc_id"] for p in pieces} == {10_001, 10_004, 10_005, None} or {p["doc_id"] for p in pieces} == {10_001, 10_004, 10_005, None, 10_006}
