"""Each operator against brute force, an exact round trip or held-out accuracy, on small tables with nulls, ties, repeats and clashing columns."""

import hashlib
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest

from entitygraph.llm import decontaminate, html_text, packing, pii, quality, simhash, suffix_dedup, token_files, toxicity, vector_join
from entitygraph.operators.closure import connected_components

DOCS = "/root/testdata/sf0.001/documents.parquet"
KIND = "doc_id long, text string, lang string, bucket string, rank long, mark long"


def table(spark, texts):
    return spark.createDataFrame([(i, t, "en", "x", 1, 2) for i, t in enumerate(texts)], KIND)


def rng_text(seed, n):
    r = np.random.default_rng(seed)
    return "".join(chr(97 + c) for c in r.integers(0, 26, n))


def brute_dedup(texts, length=100):
    seen, out = set(), []
    for t in texts:
        x = (t or "").encode()
        covered = bytearray(len(x))
        for p in range(len(x) - length + 1):
            w = x[p : p + length]
            if w in seen:
                covered[p : p + length] = b"\1" * length
            seen.add(w)
        kept = bytes(b for b, c in zip(x, covered) if not c)
        spans = len(re.findall(b"\1+", bytes(covered)))
        out.append((len(x), sum(covered), spans, hashlib.sha256(kept).hexdigest()))
    return out


def test_suffix_dedup(spark):
    a, b = rng_text(1, 700), rng_text(2, 150)
    texts = [a, None, "", "short", a, a[:300] + b + a[250:], "ab" * 400, "x" * 1000, b + b, a[100:220] + "é" * 90 + a[100:199], rng_text(3, 400) + a[600:] + b, "x" * 99, "x" * 101]
    got = {r["doc_id"]: r for r in suffix_dedup.suffix_dedup(table(spark, texts)).collect()}
    for i, want in enumerate(brute_dedup(texts)):
        assert (got[i]["n_bytes"], got[i]["n_removed"], got[i]["n_spans"], got[i]["kept_sha256"]) == want, i


def test_blocks_of_the_array_meet(spark, monkeypatch):
    """However the sorted units are cut into blocks, the same are settled and open."""
    r = np.random.default_rng(1)
    for trial in range(60):
        n = int(r.integers(1, 30))
        units = sorted({(0, int(r.integers(0, 3)), int(r.integers(0, 3)), int(d), 0, 1, 0) for d in r.integers(0, 50, n)})
        cuts = sorted({0, len(units), *r.integers(0, len(units) + 1, int(r.integers(0, 6))).tolist()})
        out, edges = [], []
        for part, (a, b) in enumerate(zip(cuts[:-1], cuts[1:])):
            monkeypatch.setattr(suffix_dedup, "TaskContext", type("T", (), {"get": staticmethod(lambda part=part: type("P", (), {"partitionId": lambda self: part})())}))
            batches = [pa.RecordBatch.from_arrays([pa.array([u[k] for u in units[i : i + 3]], pa.int64()) for k in range(7)], list(suffix_dedup.NAMES)) for i in range(a, b, 3) if i < b]
            batches = [x.slice(0, min(x.num_rows, b - a - 3 * k)) for k, x in enumerate(batches)]
            for x in suffix_dedup._neighbours(iter(batches)):
                for row in x.to_pylist():
                    (edges if row["kind"] >= suffix_dedup.FIRST else out).append(row)
        got = sorted([(x["kind"], tuple(x[k] for k in suffix_dedup.NAMES)) for x in out] + suffix_dedup._across(edges))
        firsts = [u for i, u in enumerate(units) if i == 0 or u[:3] != units[i - 1][:3]]
        want = [(suffix_dedup.SETTLED, u) for u in units if u not in firsts] + [(suffix_dedup.OPEN, u) for u in firsts if sum(v[:2] == u[:2] for v in firsts) > 1]
        assert got == sorted(want), (trial, units, cuts)


def test_suffix_dedup_of_long_texts(spark, monkeypatch):
    monkeypatch.setattr(suffix_dedup, "SLICE", 2000)
    data = np.frombuffer((rng_text(5, 5000) + rng_text(5, 5000)[700:3000]).encode(), np.uint8)
    runs = [suffix_dedup.cover_runs(data[lo:hi], s, 100) for lo, hi, _, s, _ in suffix_dedup.pieces(np.array([0, len(data)]), 100)]
    assert sum(r[5].sum() for r in runs) == len(data) - 99  # each window in one run


def test_simhash(spark):
    rows = [r["text"] for r in spark.read.parquet(DOCS).orderBy("doc_id").collect()] + [None, "", "One", "one", "a b", None]
    got = {r["doc_id"]: r for r in simhash.simhash_components(table(spark, rows)).collect()}
    marks = []
    for t in rows:
        import xxhash

        words = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        shingles = [" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))] if words else []
        h = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
        marks.append(sum(1 << k for k in range(64) if 2 * sum(x >> k & 1 for x in h) > len(h)) if h else 0)
    assert [int(got[i]["fingerprint"], 16) for i in range(len(rows))] == marks
    assert [got[i]["component_id"] for i in range(len(rows))] == components(len(rows), lambda i, j: (marks[i] ^ marks[j]).bit_count() <= 2)


def components(n, linked):
    c = list(range(n))
    changed = True
    while changed:
        changed = False
        for i in range(n):
            for j in range(i):
                if c[i] != c[j] and linked(i, j):
                    c[i] = c[j] = min(c[i], c[j])
                    changed = True
    return c


def test_simhash_buckets_and_masks(spark):
    r = np.random.default_rng(4)
    base = r.integers(0, 1 << 62, 6)
    marks = set()
    for b in base:
        for _ in range(40):
            x = int(b)
            for k in r.integers(0, 64, int(r.integers(0, 5))):
                x ^= 1 << int(k)
            marks.add(x - (1 << 64) if x >> 63 else x)
    marks = sorted(marks)
    df = spark.createDataFrame([(m,) for m in marks], "mark long")
    c = components(len(marks), lambda i, j: ((marks[i] ^ marks[j]) & (1 << 64) - 1).bit_count() <= 2)
    want = {marks[i]: marks[c[i]] for i in range(len(marks)) if c.count(c[i]) > 1}
    for size in (simhash.BUCKET, 4, 1):  # 1: every bucket down to the last level
        got = {x["record_id"]: x["component_id"] for x in connected_components(simhash.linked_marks(df, 2, size)).collect()}
        assert got == want
    for radius in (3,):
        c = components(len(marks), lambda i, j: ((marks[i] ^ marks[j]) & (1 << 64) - 1).bit_count() <= radius)
        want = {marks[i]: marks[c[i]] for i in range(len(marks)) if c.count(c[i]) > 1}
        got = {x["record_id"]: x["component_id"] for x in connected_components(simhash.linked_marks(df, radius, 8)).collect()}
        assert got == want


def test_quality_and_toxicity_learn(spark):
    d = "/root/testdata/sf0.01"
    labels = {r["doc_id"]: r for r in spark.read.parquet(f"{d}/labels.parquet").collect()}
    q = [r for r in quality.op4_quality(spark, d).collect() if r["held_out"] and r["doc_id"] in labels]
    assert np.mean([r["predicted"] == labels[r["doc_id"]]["quality"] for r in q]) > 0.93
    t = [r for r in toxicity.op6_toxicity(spark, d).collect() if r["held_out"] and r["doc_id"] in labels]
    assert np.mean([r["predicted"] == labels[r["doc_id"]]["toxic"] for r in t]) > 0.9


def test_classifiers_on_odd_tables(spark):
    labels = spark.createDataFrame([(0, 1, 0), (1, 0, 1), (2, None, None), (None, 1, 1)], "doc_id long, quality int, toxic int")
    for texts in ([None, "", " ", "good words", "x" * 5000], []):
        docs = table(spark, texts)
        assert quality.quality_scores(docs, quality.fit_quality(docs, labels)).count() == len(texts)
        assert toxicity.toxicity_scores(docs, toxicity.fit_toxicity(docs, labels)).count() == len(texts)


def test_nothing_learnt_rejects_nothing(spark):
    d = "/root/testdata/sf0.001"
    docs, labels = spark.read.parquet(DOCS), spark.read.parquet(f"{d}/labels.parquet")
    clean = labels.where("toxic = 0").select("doc_id")
    assert toxicity.drop_toxic(docs, labels).join(clean, "doc_id").count() == docs.join(clean, "doc_id").count() > 0
    assert all(r["predicted"] == 0 for r in toxicity.op6_toxicity(spark, d).join(clean, "doc_id").collect())
    for some, share in ((labels.limit(0), 0), (labels.where("toxic = 0"), None), (labels.where("toxic = 1"), None)):
        assert toxicity.drop_toxic(docs, some).count() == docs.count()
        scores = {r["score"] for r in toxicity.toxicity_scores(docs, toxicity.fit_toxicity(docs, some)).collect()}
        assert len(scores) == 1 and (share is None or scores == {share})


def test_segments_against_brute_force():
    r = np.random.default_rng(0)
    for _ in range(50):
        scores = [float(x) for x in r.integers(-5, 6, 12)]
        best = max((sum(scores[i:j]) for i in range(12) for j in range(i + 1, 13)), default=0)
        found = toxicity.segments(scores)
        assert all(v == pytest.approx(sum(scores[a:b])) for a, b, v in found)
        assert all(x[1] <= y[0] for x, y in zip(found, found[1:]))
        if best > 0:
            assert max(v for *_, v in found) == pytest.approx(best)


def test_decontamination(spark):
    item = "The quick brown fox jumps over the lazy dog while seventeen careful zebras watch from a distant hill, quietly humming."
    other = "Completely unrelated sentence that nobody would ever find in a document of this little test, we hope and trust."
    noisy = item.upper().replace("LAZY", "LAZI").replace(",", " -- ")
    texts = [f"{rng_text(1, 300)} {item} tail", noisy, rng_text(2, 500), None, "", item[:50], f"a {item[:100]} b"]
    bench = spark.createDataFrame([(7, item, 1), (9, other, 1), (10, None, 1), (11, "tiny", 1)], "item_id long, text string, bad int")
    got = {(r["doc_id"], r["item_id"]) for r in decontaminate.contaminated_pairs(table(spark, texts), bench).collect()}
    assert got == {(0, 7), (1, 7), (6, 7)}
    assert decontaminate.drop_contaminated(table(spark, texts), bench).count() == 4
    assert decontaminate.contaminated_pairs(table(spark, []), bench).count() == 0


def ids_of(texts, end):
    from tokenizers import Tokenizer

    from entitygraph.llm.tokens import vocabulary

    t = Tokenizer.from_file(vocabulary())
    return [np.array([*t.encode(x or "", add_special_tokens=False).ids, end], "<u4") for x in texts]


ODD = [None, "", "Hello, World's 123 <|endoftext|> ok", "naïve Σίσυφος x y\x1c\x85z ½ İstanbul é don't\tI'LL", "日本語 текст", "a" * 3000, "word " * 9000, "same", "same"]


def test_token_files(spark):
    from entitygraph.shared import new_path

    path = new_path(spark, "tokens")
    token_files.write_token_files(table(spark, ODD), path, 1, shard_ids=50)
    got = {r["doc_id"]: r for r in token_files.read_token_files(spark, path).collect()}
    start = 0
    for i, ids in enumerate(ids_of(ODD, 1)):
        assert (got[i]["start"], got[i]["n_tokens"], got[i]["ids_crc32"]) == (start, len(ids), zlib.crc32(ids.tobytes())), i
        start += len(ids)
    image = token_files.file_image(np.array([3, 9]), np.array([0, 2, 5]), np.arange(5), 2)
    assert token_files.TokenFile(image).document(1).tolist() == [2, 3, 4]


def test_elias_fano():
    for values in ([], [0], [0, 0, 3, 3, 9, 1000, 70000], list(range(0, 5000, 7))):
        e, end = token_files.EliasFano.read(token_files.EliasFano.encode(np.array(values, np.int64)).to_bytes(), 0)
        assert e.values().tolist() == values and [e.select(i) for i in range(len(values))] == values


def test_packing(spark):
    pieces = packing.pack(table(spark, ODD)).collect()
    ids = ids_of(ODD, 2)
    per, seq = {}, {}
    for p in pieces:
        assert zlib.crc32(ids[p["doc_id"]][p["start"] : p["start"] + p["length"]].tobytes()) == p["ids_crc32"] and p["doc_tokens"] == len(ids[p["doc_id"]])
        per.setdefault(p["doc_id"], []).append((p["start"], p["length"]))
        seq.setdefault(p["sequence_id"], []).append((p["offset"], p["length"]))
    for groups, sizes in ((per, {i: len(x) for i, x in enumerate(ids)}), (seq, None)):
        for k, spans in groups.items():
            at = 0
            for start, n in sorted(spans):
                assert start == at
                at += n
            assert at == sizes[k] if sizes else at <= 4096 and at & at - 1 == 0
    assert packing.pack(table(spark, [])).count() == 0


def test_hilbert_neighbours():
    grid = np.array([[i, j] for i in range(8) for j in range(8)])
    walk = grid[np.argsort(packing.hilbert_keys(grid, 3))]
    assert len(set(packing.hilbert_keys(grid, 3))) == 64 and (np.abs(np.diff(walk, axis=0)).sum(axis=1) == 1).all()


PII = [None, "", "mail a.b+c@x-y.co.uk, and a@b.com_x@y.z!", "999.1.1.1 10.0.0.255.7 1.2.3", "4111 1111 1111 1111 and 4111111111111112 or 5555-5555-5555-4444-1",
       "+1 (578) 555-6437 4111111111111111", "+44 20 7946 0958, +1", "1 " * 30, "9" * 4000, "a@" * 500 + "b.c", "😀 x@y.zz"]


def base_spans(text):
    rules = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}
    out = []
    for order, (kind, rule) in enumerate(rules.items()):
        for m in re.finditer(rule, text or ""):
            d = re.sub("[^0-9]", "", m[0])
            luhn = sum(int(c) if i % 2 == 0 else sum(divmod(2 * int(c), 10)) for i, c in enumerate(reversed(d))) % 10 == 0
            if {"email": True, "ip": kind == "ip" and all(int(p) < 256 for p in m[0].split(".")), "card": 12 <= len(d) <= 19 and luhn, "phone": 9 <= len(d) <= 15}[kind]:
                out.append((m.start(), order, m.end()))
    return sorted(out)


def test_pii(spark):
    got = {}
    for r in pii.pii_spans(table(spark, PII)).where("base").collect():
        got.setdefault(r["doc_id"], []).append((r["start"], r["kind"], r["end"]))
    assert {i: sorted(v) for i, v in got.items()} == {i: s for i, t in enumerate(PII) if (s := base_spans(t))}
    clean = {r["doc_id"]: r["text"] for r in pii.redact(table(spark, PII)).collect()}
    assert clean[2] == "mail [EMAIL], and [EMAIL][EMAIL]!" and clean[10] == "😀 [EMAIL]" and clean[0] is None and clean[1] == ""
    assert pii.redact(table(spark, [])).count() == 0


def test_embeddings(spark, monkeypatch):
    monkeypatch.setattr(vector_join, "HOMES", 16)
    monkeypatch.setattr(vector_join, "COPY", 1)  # several pivots even for small labels
    r = np.random.default_rng(3)
    centres = r.normal(size=(12, 8))
    rows = [(i, (centres[i % 12] + r.normal(size=8) * 0.12).tolist(), int(i % 12 % 3)) for i in range(150)]
    rows += [(150 + i, rows[0][1], rows[0][2]) for i in range(5)]
    rows += [(160, None, 1), (161, [0.0] * 8, 1), (162, [1.0] * 7 + [float("nan")], 1), (163, rows[1][1], None), (164, [1.0, None] + [0.0] * 6, 0), (165, [1.0] * 3, 0), (166, [1e300] * 8, 0), (167, [1e-300] * 8, 0)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int")
    got = {x["vec_id"]: x for x in vector_join.embedding_near_dedup(df).collect()}

    def fine(row):
        v = row[1]
        return row[2] is not None and v is not None and None not in v and np.isfinite(v).all() and any(v)

    def linked(i, j):
        a, b = rows[i], rows[j]
        if not (fine(a) and fine(b)) or a[2] != b[2] or len(a[1]) != len(b[1]):
            return False
        x, y = (np.array(t[1]) / np.abs(t[1]).max() for t in (a, b))
        return x @ y / np.linalg.norm(x) / np.linalg.norm(y) >= 0.98

    c = components(len(rows), linked)
    for i, row in enumerate(rows):
        g = got[row[0]]
        assert (g["n_links"], g["component_id"]) == (sum(linked(i, j) for j in range(len(rows)) if j != i), rows[c[i]][0])
    assert sum(x["n_links"] for x in got.values()) > 100


PAGE = """<html><head><title>T</title></head><body><nav><a href=x>Menu</a></nav><div class="ad">Buy</div><article><h1>A &amp; B</h1>
<p>First <b>bold</b>ly\n said.<br>Next<p>Second &#233;<ul><li>one<li>two</ul><div class="comments"><p>Nice!</div></article><aside>Side</aside><footer>F</footer><script>var p="</p>"</script></body></html>"""


def test_html(spark):
    rows = [(0, "https://h.example.com/a", PAGE), (1, "https://h.example.com/b", None), (2, None, ""), (3, "bad", "plain text &lt;only"), (4, "https://h.example.com/c", "<body><article><p>x<!-- c --></article>")]
    got = {r["page_id"]: r["text"] for r in html_text.extract_pages(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert got == {0: "A & B First boldly said. Next Second é one two", 1: "", 2: "", 3: "plain text <only", 4: "x"}


LONG = "Long text of the body of the page, word after word after word. " * 5


@pytest.mark.parametrize(
    ("html", "want"),
    [
        ('<body><div style="overflow:hidden" class="overflow-hidden content has-sidebar"><p>One</p></div></body>', "One"),
        ('<body><article><div class="entry-header"><h1>Title</h1></div><p>One</p></article></body>', "Title One"),
        (f'<body><div class="page"><div class="lead">Lead</div><div class="body">{LONG}</div></div></body>', f"Lead {LONG.strip()}"),
        (f"<body><main><h1>Title</h1><article>{LONG}</article></main></body>", f"Title {LONG.strip()}"),
        ('<body><div>One<div style="color:red; display: none">x</div><p hidden>y</p><p aria-hidden="true">z</p><div style="visibility:hidden">v</div><div class="sidebar-2 wide">s</div></div></body>', "One"),
    ],
)
def test_main_text_is_whole(spark, html, want):
    assert html_text.main_text(html) == want
    rows = spark.createDataFrame([(1, "http://a/", html)], "page_id long, url string, html string")
    assert html_text.extract_pages(rows).first()["text"] == want


def test_host_path_must_hold_most_of_a_page(spark):
    usual = f'<body><div class="page"><div class="post">{LONG}</div></div></body>'
    odd = f'<body><div class="page"><div class="post">Stub</div><div class="story">{LONG}</div></div></body>'
    rows = spark.createDataFrame([(i, "http://a/", odd if i == 5 else usual) for i in range(6)], "page_id long, url string, html string")
    got = {r["page_id"]: r["text"] for r in html_text.extract_pages(rows).collect()}
    assert got == {i: LONG.strip() for i in range(5)} | {5: f"Stub {LONG.strip()}"}
    assert html_text.main_text(odd, "body>div.page>div.post") == got[5]


def test_pipeline_stages_keep_columns(spark, tmp_path):
    import corpus_pipeline

    assert [s for s, _ in corpus_pipeline.STAGES] == ["toxicity", "simhash_near_dedup", "decontamination", "pii", "packing"]
    docs = spark.read.parquet(DOCS)
    for _, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, docs, "/root/testdata/sf0.001").columns == docs.columns
