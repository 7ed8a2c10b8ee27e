import hashlib
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from negseq.llm import bpe_pieces, chat, embedding_dedup, fingerprint, html_text, minhash_dedup, mixing, substring_dedup, toxicity, warc

DOCS = "doc_id long, text string, lang string, source string, n_chars long, key string, runs long, id long"


def docs_of(spark, rows):
    """(doc_id, text, source) and columns whose names clash with inner ones."""
    return spark.createDataFrame([(i, t, "en", s, len(t or ""), "k", 1, 7) for i, t, s in rows], DOCS)


def words(rng, n, vocabulary=60):
    return [f"w{rng.randrange(vocabulary)}" for _ in range(n)]


def some_docs(rng):
    base = words(rng, 120)
    near = base[:60] + ["x"] + base[61:]
    rows = [(0, " ".join(base), "a"), (1, " ".join(near), "a"), (2, " ".join(base), None), (3, None, "b"), (4, "", "b"), (5, "one two", "b"), (6, " ".join(["la"] * 90), "c"), (7, " \t\n ", "c")]
    rows += [(8 + k, " ".join(words(rng, rng.randrange(1, 200))), rng.choice("abc")) for k in range(12)]
    return rows + [rows[0], rows[5]]


def brute_substrings(rows, width=20):
    split = {i: (t or "").encode().split() for i, t, _ in rows}
    seen, out = {}, {}
    for i in sorted(split):
        w = split[i]
        cover = [False] * len(w)
        for s in range(len(w) - width + 1):
            k = tuple(w[s : s + width])
            if k in seen:
                cover[s : s + width] = [True] * width
            else:
                seen[k] = (i, s)
        kept = [x for x, c in zip(w, cover, strict=True) if not c]
        out[i] = (len(w), len(w) - len(kept), hashlib.sha256(b" ".join(kept)).hexdigest())
    return out


@pytest.mark.parametrize("seed", [1, 2])
def test_substrings(spark, seed):
    rows = some_docs(random.Random(seed))
    got = substring_dedup.substring_dedup(docs_of(spark, rows).repartition(3), with_text=False).collect()
    want = brute_substrings(rows)
    assert len(got) == len(rows)
    for r in got:
        assert (r["n_words"], r["n_removed"], r["kept_sha256"]) == want[r["doc_id"]]
    assert substring_dedup.substring_dedup(docs_of(spark, []), with_text=False).count() == 0


def brute_groups(rows, shingle, percent):
    table = bytes.maketrans(bytes(range(65, 91)), bytes(range(97, 123)))
    sets = {}
    for i, t, _ in rows:
        w = (t or "").encode().translate(table).split()
        sets[i] = frozenset(tuple(w[k : k + shingle]) for k in range(len(w) - shingle + 1)) or (frozenset([tuple(w)]) if w else frozenset())
    label = {i: i for i in sets}
    for a in sets:
        for b in sets:
            if a < b and sets[a] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                x, y = sorted((label[a], label[b]))
                label = {k: x if v == y else v for k, v in label.items()}
    return {i: (len(sets[i]), label[i]) for i in sets}


def test_near_copies(spark):
    rng = random.Random(4)
    rows = some_docs(rng)
    base = words(rng, 150, 500)
    rows += [(100 + k, " ".join(x if rng.random() > 0.015 else "y" for x in base), "a") for k in range(25)]
    got = minhash_dedup.minhash_dedup(docs_of(spark, rows), shingle=3, percent=85).collect()
    want = brute_groups(rows, 3, 85)
    assert len(got) == len(rows)
    for r in got:
        assert (r["n_shingles"], r["component_id"], r["kept"]) == (*want[r["doc_id"]], want[r["doc_id"]][1] == r["doc_id"])
    assert minhash_dedup.minhash_dedup(docs_of(spark, [])).count() == 0
    nulls = minhash_dedup.minhash_dedup(docs_of(spark, [(None, "a b c d e f", "a"), (1, "a b c d e f", "a")])).collect()
    assert sorted(((r["doc_id"], r["component_id"], r["kept"]) for r in nulls), key=str) == [(1, 1, True), (None, None, True)]


def test_near_copies_recall(spark):
    """Pairs just over the threshold are found, and those just under it are not linked."""
    rng = random.Random(21)
    rows, want = [], {}
    for k in range(300):
        n = rng.randrange(150, 400)
        a = [f"v{rng.randrange(10**6)}" for _ in range(n)]
        b, low = a[:], 0.85
        while True:
            c = b[:]
            c[rng.randrange(n)] = f"u{rng.randrange(10**6)}"
            x, y = ({tuple(t[i : i + 3]) for i in range(n - 2)} for t in (a, c))
            s = len(x & y) / len(x | y)
            if s < low:
                break
            b = c
        rows += [(2 * k, " ".join(a), "a"), (2 * k + 1, " ".join(b if k % 3 else c), "a")]
        want[2 * k + 1] = 2 * k if k % 3 else 2 * k + 1
    got = {r["doc_id"]: r["component_id"] for r in minhash_dedup.minhash_dedup(docs_of(spark, rows), shingle=3, percent=85).collect()}
    assert {i: got[i] for i in want} == want


def test_near_copies_of_a_large_group(spark, monkeypatch):
    """A group alike about the threshold, so that hubs leave buckets open and the rarest shingles decide, in several parts."""
    monkeypatch.setattr(minhash_dedup, "PART", 8)
    rng = random.Random(5)
    base = words(rng, 120, 5000)
    rows = [(k, " ".join(x if rng.random() > 0.03 else f"y{rng.randrange(9)}" for x in base), "a") for k in range(160)]
    got = minhash_dedup.minhash_dedup(docs_of(spark, rows), shingle=3, percent=85).collect()
    want = brute_groups(rows, 3, 85)
    assert {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in got} == want and len({c for _, c in want.values()}) > 3


def test_toxicity(spark):
    rng = random.Random(6)
    plain = [" ".join(words(rng, 60, 300)) for _ in range(160)]
    bad = [t if k % 4 else t[:100] + f" vile{rng.choice('abcdef')} slur " + t[100:] for k, t in enumerate(plain)]
    rows = [(k, t, "a") for k, t in enumerate(bad)] + [(900, None, None), (901, "", "a"), (None, "slur", "a"), (0, bad[0], "a")]
    labels = spark.createDataFrame([(k, 1, int(k % 4 == 0)) for k in range(120)] + [(0, 1, 1), (5, None, None)], "doc_id long, quality int, toxic int")
    model = toxicity.fit(docs_of(spark, rows), labels, F.lit(True))
    got = toxicity.score(docs_of(spark, rows), model).collect()
    assert len(got) == len(rows)
    for r in got:
        assert 0 <= r["score"] <= 1
        if r["doc_id"] is not None and r["doc_id"] < 160:
            assert (r["score"] >= 0.5) == (r["doc_id"] % 4 == 0)
        elif r["doc_id"] is not None:
            assert r["score"] < 0.5
    none = toxicity.fit(docs_of(spark, []), labels.limit(0), F.lit(True))
    assert toxicity.score(docs_of(spark, rows[:2]), none).count() == 2


@pytest.mark.parametrize("kind", ["no toxic row", "no clean row", "null labels", "empty table", "unknown ids"])
def test_toxicity_without_both_classes(spark, tmp_path, kind):
    import corpus_pipeline

    rows = [(k, f"some plain words {k}", "a") for k in range(6)] + [(7, None, "a"), (None, "", "a")]
    given = {"no toxic row": [(k, 0, 0) for k in range(6)], "no clean row": [(k, 0, 1) for k in range(6)], "null labels": [(k, None, None) for k in range(6)], "empty table": [], "unknown ids": [(k, 0, k % 2) for k in range(100, 120)]}[kind]
    labels = spark.createDataFrame(given, "doc_id long, quality int, toxic int")
    docs = docs_of(spark, rows)
    assert all(r["score"] < 1e-9 for r in toxicity.score(docs, toxicity.fit(docs, labels, F.lit(True))).collect())
    labels.write.parquet(str(tmp_path / "labels.parquet"))
    assert corpus_pipeline.toxicity_stage(spark, docs, str(tmp_path)).count() == len(rows)


def test_no_evidence_is_not_toxic():
    slope, offset = toxicity._logistic(np.zeros(10), np.array([1] * 9 + [0]))
    assert toxicity.Model({}, 1.0, 0.0, slope, offset).score(0.0) < 0.5


def test_segments():
    m = toxicity.Model({}, 1.0, 0.0)
    rng = random.Random(7)
    for _ in range(200):
        s = [rng.choice([-2.0, -1.0, 1.0, 3.0]) for _ in range(rng.randrange(1, 14))]
        got = m.segments(s)
        best = max([sum(s[a:b]) for a in range(len(s)) for b in range(a + 1, len(s) + 1)])
        assert (max((x for *_, x in got), default=0) == max(best, 0)) and all(b <= c for (_, b, _), (c, _, _) in zip(got, got[1:], strict=False))


def brute_distinct(words, scores, first, end):
    """Best segment by trying all, then left and right of it."""
    best, at = 0.0, None
    for a in range(first, end):
        seen, total = set(), 0.0
        for b in range(a, end):
            total += toxicity.COST if scores[b] > 0 and words[b] in seen else scores[b]
            seen.add(words[b])
            if total > best + 1e-9:
                best, at = total, (a, b + 1)
    return [] if at is None else [*brute_distinct(words, scores, first, at[0]), (*at, round(best, 6)), *brute_distinct(words, scores, at[1], end)]


def test_distinct_segments():
    rng = random.Random(11)
    for k in range(600):
        weight = {w: rng.uniform(0.3, 3) for w in "abcdef"[: rng.randrange(1, 7)]}
        text = [rng.choice([*weight, *"." * rng.randrange(1, 12)]) for _ in range(rng.randrange(1, 60))]
        scores = [weight.get(w, toxicity.COST) for w in text]
        got = [(a, b, round(s, 6)) for a, b, s in toxicity.distinct_segments(text, scores, 0, len(text))]
        want = brute_distinct(text, scores, 0, len(text))
        assert max((s for *_, s in got), default=0) == max((s for *_, s in want), default=0), (text, scores)
        assert got == want, (text, scores)


def test_toxic_passage_after_scattered_words():
    """Words that occurred far apart before, and the same passage twice, are passages still; one word over and over is none."""
    bad = [f"vile{k}" for k in range(8)]
    m = toxicity.Model({w: 3.0 for w in bad}, 0.5, 0.0)
    filler = ["plain"] * 200
    scattered = [x for w in bad for x in [w, *filler]]
    text = [*scattered, *bad, *filler, *bad, *filler]
    e, found = m.evidence(*m.row(" ".join(text), {}))
    at = len(scattered)
    assert e > 0 and [(a, b) for a, b, _ in found] == [(at, at + 8), (at + 208, at + 216)]
    assert m.evidence(*m.row(" ".join(["vile1"] * 3000), {})) == (0.0, [])
    assert toxicity.distinct_segments(["plain"], [toxicity.COST], 0, 1, -5.0) == []


PAGES = "page_id long, url string, html string, id long, digest string"


def test_warc(spark):
    rows = [(1, "http://a/ b", "<p>é</p>", 1, ""), (2, None, None, 1, ""), (3, "u", "", 1, ""), (4, "u", "<p>é</p>", 1, ""), (5, "u", "WARC/1.1\r\n\r\n" * 3, 1, "")]
    got = {r["page_id"]: r for r in warc.round_trip(spark.createDataFrame(rows, PAGES)).collect()}
    assert {k: (r["record_type"], r["refers_to"]) for k, r in got.items()} == {1: ("response", None), 2: ("response", None), 3: ("revisit", 2), 4: ("revisit", 1), 5: ("response", None)}
    for i, _, html, *_ in rows:
        data = (html or "").encode()
        assert got[i]["payload_bytes"] == len(data) and got[i]["payload_digest"] == warc.base32_sha1(data)
    assert warc.round_trip(spark.createDataFrame([], PAGES)).count() == 0


def test_arc_versions():
    for version in (1, 2):
        bodies = [b"x\ny", b"", b"http://fake 1.1.1.1 20200101000000 text/html 5\n"]
        data = warc.arc_header(version, "f.arc") + b"".join(warc.arc_record(version, f"http://h/{i} q", b) for i, b in enumerate(bodies))
        got = list(warc.parse_arc(data))
        assert [r["body"] for r in got] == bodies and got[0]["url"] == "http://h/0 q"
        head, block = next(warc.parse_warc(warc.convert(data, [None] * 3, ["0", "1", "2"])[0]))
        assert block == bodies[0] and head["WARC-Date"] == "2020-01-01T00:00:00Z" and head["WARC-Type"] == "response"
    with pytest.raises(ValueError):
        list(warc.parse_arc(warc.arc_header(1, "f") + b"u 0.0.0.0 20200101000000 t 99\nshort"))


def test_fingerprints(spark):
    rng = random.Random(8)
    rows = [r for r in some_docs(rng)[:-2]]
    got = {r["doc_id"]: r for r in fingerprint.edited(docs_of(spark, rows)).collect()}
    order = sorted(rows, key=lambda r: r[0])
    for k, (i, t, _) in enumerate(order):
        t, n = t or "", order[(k + 1) % len(order)][1] or ""
        half = len(t) // 2
        text = t[: len(t) - half] + n[:half]
        assert got[i]["n_chars"] == len(t) and got[i]["edited_sha256"] == hashlib.sha256(text.encode()).hexdigest()
        assert 0 <= got[i]["near_edited"] <= 1
    assert got[0]["fingerprint"] == got[2]["fingerprint"] != got[1]["fingerprint"]
    assert fingerprint.edited(docs_of(spark, [])).count() == 0
    # likeness follows the true similarity
    a = words(rng, 400, 10_000)
    b = a[:300] + words(rng, 100, 10_000)
    f = fingerprint.fingerprints(docs_of(spark, [(1, " ".join(a), "a"), (2, " ".join(b), "a")])).orderBy("doc_id").select("bins")
    x = f.agg(F.collect_list("bins").alias("l")).select(F.get("l", F.lit(0)).alias("p"), F.get("l", F.lit(1)).alias("q"))
    assert abs(x.select(fingerprint.likeness("p", "q")).first()[0] - 296 / 496) < 0.18


def test_html(spark):
    page = "<html><head><title>t</title><script>var x='<p>no</p>';</script></head><body><nav><ul><li><a href='/'>Home</a></li></ul></nav><div class=\"ad\">Buy now</div><article><h1>A &amp; B</h1><p>One  two&nbsp;three<p><b>Four<br></article><section class='comments'><p>me too</p></section><footer>&copy; x</footer></body></html>"
    rows = [(1, "u", page, 1, ""), (2, None, None, 1, ""), (3, "u", "", 1, ""), (4, "u", "<p>only < text", 1, ""), (5, "u", "<<<>>>&&<", 1, ""), (1, "u", page, 1, "")]
    got = html_text.extract_text(spark.createDataFrame(rows, PAGES)).collect()
    assert len(got) == 6
    by = {r["page_id"]: r["text"] for r in got}
    assert by[1] == "A & B\nOne two three\nFour" and by[2] == by[3] == ""
    assert all(r["n_chars"] == len(r["text"]) for r in got)
    assert html_text.extract_text(spark.createDataFrame([], PAGES)).count() == 0
    plain = page.replace("article", "div")
    assert html_text.extract(plain, html_text.fit([page])) == "A & B\nOne two three\nFour"


def html_page(rng, mark, junk):
    """A page with its text in p and h2, links and loose words around it, and the text that is to come out."""
    said = [" ".join(words(rng, rng.randrange(8, 40))) for _ in range(rng.randrange(2, 9))]
    body = "".join(f"<h2>{t}</h2>" if k % 4 == 0 else f"<p class='sharp navy commentary'>{t}</p>" for k, t in enumerate(said))
    loose = lambda: "".join(f"<span>{' '.join(words(rng, rng.randrange(1, 6)))}</span><br>" for _ in range(junk))
    return f"<body><nav><a>x y z</a></nav>{loose()}<{mark}>{body}</{mark}>{loose()}<footer>f f</footer></body>", "\n".join(said)


def test_html_by_learnt_weights():
    """Held-out pages, with and without the mark, where what stands beside the content is no known boilerplate."""
    rng = random.Random(14)
    weights = html_text.fit([html_page(rng, "article", 4)[0] for _ in range(60)])
    for mark in ("article", "main", "div", "section"):
        for _ in range(40):
            page, said = html_page(rng, mark, 4)
            assert html_text.extract(page, weights) == said, page


def test_html_in_linear_time():
    import time

    for page in ('<a "' * 60_000, '<b "x>y" ' * 60_000, "<a '>" * 60_001, "<div><p>" * 30_000 + "x", "<!--" * 60_000, "<p>" + "long " * 400_000):
        began = time.process_time()
        text = html_text.extract(page, html_text.PLAIN)
        assert time.process_time() - began < 8, page[:9]
    assert text == ("long " * 400_000).strip()
    assert html_text.extract("<p>a</p><p>only < text <b", html_text.PLAIN) == "a\nonly < text <b"
    assert html_text.extract("<p title='a > b'>x</p><p title=\"it's\">y</p>", html_text.PLAIN) == "x\ny"


def brute_links(rows, cosine):
    good = {i: (np.array(v), lab) for i, v, lab in rows if lab is not None and v and all(x is not None and np.isfinite(x) for x in v) and any(v)}
    label, n = {i: i for i, *_ in rows}, dict.fromkeys((i for i, *_ in rows), 0)
    for a, (va, la) in good.items():
        for b, (vb, lb) in good.items():
            if a < b and la == lb and len(va) == len(vb) and va @ vb / np.linalg.norm(va) / np.linalg.norm(vb) >= cosine:
                n[a], n[b] = n[a] + 1, n[b] + 1
                x, y = sorted((label[a], label[b]))
                label = {k: x if v == y else v for k, v in label.items()}
    return {i: (n[i], label[i], label[i] == i) for i, *_ in rows}


@pytest.mark.parametrize(("noise", "block", "cell"), [(0.25, 16, 20), (0.12, 7, 10), (0.05, 4096, 4096), (0.6, 10, 8)])
def test_embeddings(spark, monkeypatch, noise, block, cell):
    """Small blocks and cells, so that balls, cores, guests, open cells and several blocks all occur."""
    rng = np.random.default_rng(9)
    center = rng.normal(size=(6, 8))
    rows = [(k, [float(np.float32(x)) for x in center[k % 6] + noise * rng.normal(size=8)], int(k % 2)) for k in range(200)]
    rows += [(200 + k, [float(np.float32(x)) for x in rng.normal(size=8)], k % 2) for k in range(80)]
    rows += [(300, rows[0][1], 0), (301, rows[0][1], 1), (302, None, 0), (303, [0.0] * 8, 0), (304, [float("nan")] * 8, 0), (305, rows[0][1], None), (306, [1.0, None] * 4, 0), (307, [], 0), (308, [1.0, 2.0], 0), (309, [float("inf")] * 8, 1)]
    df = spark.createDataFrame([(*r, 5) for r in rows], "vec_id long, embedding array<float>, label int, rep int")
    monkeypatch.setattr(embedding_dedup, "BLOCK", block)
    monkeypatch.setattr(embedding_dedup, "CELL", cell)
    for pivot_rows in (20_000, 120):
        got = {r["vec_id"]: r for r in embedding_dedup.embedding_dedup(df, 0.93, pivot_rows=pivot_rows).collect()}
        assert {i: (r["n_links"], r["component_id"], r["kept"]) for i, r in got.items()} == brute_links(rows, 0.93)
    assert embedding_dedup.embedding_dedup(df.limit(0)).count() == 0


def test_embedding_copies(spark):
    """Balls prune: of groups of copies among many far vectors, a vector costs about one copy, and a hot group is not compared."""
    rng = np.random.default_rng(3)
    center = rng.normal(size=(30, 64))
    near = [center[0 if k % 2 else k % 30] + 0.03 * rng.normal(size=64) for k in range(900)]
    far = list(rng.normal(size=(900, 64)))
    classes = spark.createDataFrame([(0, 64, [float(x) for x in v], k * 1_000_003, 1) for k, v in enumerate(near + far)], "label long, size int, v array<double>, rep long, weight long")
    placed = embedding_dedup.cells(classes, 0.93).cache()
    assert placed.count() <= 1.1 * 1800 and placed.select("cell").distinct().count() >= 16
    assert placed.where("core").count() > 0.8 * 900


def test_mixing(spark):
    rng = random.Random(10)
    rows = [(k, " ".join(words(rng, rng.randrange(0, 40))), rng.choice(["a", "b", "c", "d", None])) for k in range(300)] + [(400, None, "z"), (401, "", "z")]
    got = mixing.mix(docs_of(spark, rows)).collect()
    size = {i: len((t or "").encode().split()) for i, t, _ in rows}
    names = sorted({s for *_, s in rows if s is not None}) + [None]
    total = {s: sum(size[i] for i, _, x in rows if x == s) for s in names}
    weight = {s: (5, 2, 1)[k % 3] for k, s in enumerate(names)}
    target, free, left = {}, set(names), float(sum(total.values()))
    while free:
        level = left / sum(weight[s] for s in free)
        over = {s for s in free if level * weight[s] > 3 * total[s]}
        if not over:
            target |= {s: level * weight[s] for s in free}
            break
        for s in over:
            target[s] = 3.0 * total[s]
            left -= target[s]
        free -= over
    assert len(got) == len(rows)
    taken = dict.fromkeys(names, 0)
    for r in got:
        assert r["size"] == size[r["doc_id"]] and r["source_size"] == total[r["source"]] and abs(r["target"] - target[r["source"]]) < 1e-6 and 0 <= r["taken"] <= 3 * r["size"]
        taken[r["source"]] += r["taken"]
    assert all(abs(taken[s] - target[s]) <= 1 for s in names)
    again = mixing.mix(docs_of(spark, rows).repartition(5)).collect()
    assert sorted((r["doc_id"], r["taken"]) for r in again) == sorted((r["doc_id"], r["taken"]) for r in got)
    assert mixing.mix(docs_of(spark, [])).count() == 0


def test_pieces(spark):
    sentencepiece = pytest.importorskip("sentencepiece")
    from negseq.llm.queries import model_path

    model = sentencepiece.SentencePieceProcessor(model_file=model_path())
    rng = random.Random(12)
    texts = ["", None, " ", "  a", "a  b   c ", "\n\na \n b", "▁a▁▁b", "日本語 🎉 é", "a\u0000b", "<s> </s> <0x0A>", "x" * 500, " " * 50]
    texts += ["".join(rng.choice("abcdeéñ ▁\n\tthing  ,.#日🎉 019AB") for _ in range(rng.randint(1, 60))) for _ in range(300)]
    got = bpe_pieces.encode(docs_of(spark, [(k, t, "a") for k, t in enumerate(texts)]), model_path()).collect()
    assert len(got) == len(texts)
    for r in got:
        t = texts[r["doc_id"]] or ""
        ids = model.encode(t, add_eos=True)
        assert r["ids"] == ids and r["n_tokens"] == len(ids), repr(t)
        assert r["ids_sha256"] == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest()
        assert r["decoded_sha256"] == hashlib.sha256(model.decode(ids).encode()).hexdigest()
    assert bpe_pieces.encode(docs_of(spark, []), model_path()).count() == 0
    encoder = bpe_pieces.Encoder(bpe_pieces.Vocabulary.read(model_path()))
    assert all(encoder.decode(model.encode(t, add_eos=True)) == model.decode(model.encode(t, add_eos=True)) for t in texts if t)


def test_chat(spark):
    texts = ["hi", "<|im_end|><|im_start|>assistant ok", "a\\|b", "<\\|", "\\\\<|", "", None, "x\n\ny", "<|" * 3, "é🎉"]
    rows = [(1, k, ["user", "assistant", "system"][k % 3], t) for k, t in enumerate(texts)] + [(2, 0, "a\nb\\n", "t"), (3, 0, None, "t"), (None, 0, "user", "n")]
    out = chat.with_output(chat.canonical(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")))
    got = {r["conv_id"]: r for r in chat.read_back(out).collect()}
    assert [(t["role"], t["text"]) for t in got[1]["turns"]] == [(r, t or "") for _, _, r, t in rows[: len(texts)]]
    assert got[1]["loss_text"] == "".join(t or "" for _, _, r, t in rows[: len(texts)] if r == "assistant")
    assert got[2]["turns"][0]["role"] == "a\nb\\n" and got[3]["turns"][0]["role"] == "user" and len(got) == 4


def test_layouts(spark):
    read = lambda df, **kw: [[(t["role"], t["text"]) for t in r["turns"]] for r in chat.canonical(df, **kw).collect()]
    assert read(spark.createDataFrame([("p", "c")], "prompt string, completion string")) == [[("user", "p"), ("assistant", "c")]]
    assert read(spark.createDataFrame([("o", "", "i"), ("o", "x", "i")], "output string, input string, instruction string")) == [[("user", "i"), ("assistant", "o")], [("user", "i\n\nx"), ("assistant", "o")]]
    assert read(spark.createDataFrame([(9, [("human", "q"), ("gpt", "a")])], "n long, conversations array<struct<from: string, value: string>>"), id_col="n") == [[("user", "q"), ("assistant", "a")]]
    assert read(spark.createDataFrame([([("user", None)],), (None,)], "messages array<struct<role: string, content: string>>")) == [[("user", "")], []]
    assert read(spark.createDataFrame([("", "q", "a")], "system string, prompt string, completion string")) == [[("user", "q"), ("assistant", "a")]]
    with pytest.raises(ValueError, match="no mapping"):
        chat.canonical(spark.createDataFrame([(1,)], "other long"))


def test_pipeline_stages(spark):
    pipeline = pytest.importorskip("corpus_pipeline")
    rows = some_docs(random.Random(3))
    docs = docs_of(spark, rows)
    near = pipeline.near_dedup_stage(spark, docs, "")
    want = {c for _, c in brute_groups(rows, 5, 80).values()}
    assert {r["doc_id"] for r in near.collect()} == want and near.columns == list(pipeline.COLUMNS)
    cut = pipeline.substring_stage(spark, docs.dropDuplicates(["doc_id"]), "").collect()
    brute = brute_substrings(rows)
    assert {r["doc_id"] for r in cut} == {i for i, (n, gone, _) in brute.items() if n > gone or gone == 0}
    assert all(r["n_chars"] == len(r["text"] or "") for r in cut)
    mixed = pipeline.mixing_stage(spark, docs.dropDuplicates(["doc_id"]), "")
    plan = {r["doc_id"]: r["taken"] for r in mixing.mix(docs.dropDuplicates(["doc_id"])).collect()}
    got = {}
    for r in mixed.collect():
        got[r["doc_id"]] = got.get(r["doc_id"], 0) + len(r["text"].encode().split())
    assert got == {i: n for i, n in plan.items() if n}


def test_very_long_texts(spark):
    """One document of 1.5 million characters among short ones, in every operator on texts."""
    rng = random.Random(17)
    passage = words(rng, 40, 10**6)
    long = " ".join([*words(rng, 120_000, 50_000), *passage, *words(rng, 120_000, 50_000)])
    rows = [(1, long, "a"), (2, "x " + " ".join(passage) + " y", "a"), (3, long, "b"), (4, "short", "b"), (5, None, None)]
    docs = docs_of(spark, rows)
    cut = {r["doc_id"]: r for r in substring_dedup.substring_dedup(docs, with_text=False).collect()}
    want = brute_substrings(rows)
    assert {i: (r["n_words"], r["n_removed"], r["kept_sha256"]) for i, r in cut.items()} == want and want[2][1] == 40
    assert {r["doc_id"]: r["component_id"] for r in minhash_dedup.minhash_dedup(docs).collect()} == {1: 1, 2: 2, 3: 1, 4: 4, 5: 5}
    assert {r["doc_id"]: r["size"] for r in mixing.mix(docs).collect()} == {i: n for i, (n, *_) in want.items()}
    print_ = {r["doc_id"]: r for r in fingerprint.edited(docs).collect()}
    assert print_[1]["fingerprint"] == print_[3]["fingerprint"] and print_[1]["n_chars"] == len(long)
    model = toxicity.Model({"short": 8.0}, 1.0, 0.0)
    assert toxicity.score(docs, model).count() == 5
    sentencepiece = pytest.importorskip("sentencepiece")
    from negseq.llm.queries import model_path

    ids = sentencepiece.SentencePieceProcessor(model_file=model_path()).encode(long, add_eos=True)
    got = {r["doc_id"]: r for r in bpe_pieces.encode(docs, model_path(), with_ids=False).collect()}
    assert got[1]["ids_sha256"] == got[3]["ids_sha256"] == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest() and got[1]["n_tokens"] == len(ids)


def test_warc_revisits_name_their_record(spark):
    """Several ARC records an archive; the revisit's reference is the id of the response, read from the archive itself."""
    arc = warc.arc_header(1, "f") + warc.arc_record(1, "http://a", b"same") + warc.arc_record(1, "http://b", b"same")
    first, second = (head for r in warc.convert(arc, [None, ("7", "http://a")], ["7", "8"]) for head, _ in warc.parse_warc(r))
    assert second["WARC-Refers-To"] == first["WARC-Record-ID"] and second["WARC-Refers-To-Target-URI"] == first["WARC-Target-URI"] and second["WARC-Refers-To-Date"] == first["WARC-Date"]
