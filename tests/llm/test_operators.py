import hashlib
import math
import random
from collections import Counter
from itertools import combinations

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from cleantrain.llm import decontaminate, html_main_text, language_id, license_scan, line_windows, mtree, probminhash, queries, sentencepiece_lattice, token_rollup, url_filter
from cleantrain.llm.common import words_of

DOCS = "doc_id long, text string, lang string, source string, n_chars long, starts int, items string, class_id int"


def docs_frame(spark, rows):
    """Documents with extra columns whose names clash with the operators' own."""
    return spark.createDataFrame([(i, t, "en", "s", None if t is None else len(t), 1, "x", 2) for i, t in rows], DOCS)


EDGE = [(1, None), (2, ""), (3, " \n\t "), (4, "one"), (5, "word " * 30_000), (6, "twice"), (6, "twice"), (7, "€ñ 漢字 ▁ ok")]


@pytest.fixture(scope="module")
def db(small):
    c = duckdb.connect()
    for t in ("documents", "pages", "benchmark", "embeddings", "labels"):
        c.sql(f"create view {t} as select * from '{small}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_query_equals_sql(spark, small, db, name):
    got, want = queries.queries()[name](spark, small).toPandas(), db.sql(queries.oracle_sql()[name]).df()
    rows = lambda f: sorted(map(repr, f[sorted(want.columns)].astype(object).where(f[sorted(want.columns)].notna(), None).values.tolist()))
    assert sorted(got.columns) == sorted(want.columns) and rows(got) == rows(want)


# 1


def test_licences_equal_the_reference_on_held_out_text(spark):
    lines = ["Licensed under the Apache License, Version 2.0.", "Released under the MIT License.", "He lost his driving licence after the trip.", "", "Licensed under the GNU General Public License, version 3.", "redistribution of wealth"]
    rows = [*EDGE, (10, "\n".join(lines)), (11, lines[0]), (12, "prose\n" + lines[1])]
    got = license_scan.scan_licences(docs_frame(spark, rows)).collect()
    want = {i: ",".join(sorted({license_scan.classify(x)[0] for x in (t or "").split("\n")} - {"unknown"})) for i, t in rows}
    assert len(got) == len(rows) and all(r.families == want[r.doc_id] for r in got)
    assert want[10] == "apache-2.0,gpl,mit"


def test_licence_classifier_is_accurate_on_held_out_copies():
    held = license_scan._examples(random.Random(99), 2)
    names = [*license_scan.TEMPLATES, "unknown"]
    found = [license_scan.classify(" ".join(t))[0] == names[k] or names[k] != "unknown" and license_scan.classify(" ".join(t))[0] == "unknown" for t, k in held]
    assert np.mean(found) > 0.97


def test_no_licence_line_is_lost_before_it_is_scored(spark):
    lines = ["All rights reserved.", *(t for ts in license_scan.TEMPLATES.values() for t in ts)]
    got = license_scan.licence_paragraphs(docs_frame(spark, [(1, "\n".join(["some prose", *lines]))])).collect()
    want = {i: license_scan.classify(x)[0] for i, x in enumerate(lines, 1)}
    assert {r.position: r.family for r in got} == want and want[1] == "proprietary" and "unknown" not in want.values()


def test_notices_worded_unlike_the_templates_are_found():
    kinds = {"creative-commons": ["Licensed under CC BY-NC 4.0.", "License: CC-BY-NC 3.0", "Licensed under CC BY-ND 2.0.", "CC BY-SA 4.0"], "proprietary": ["All rights reserved.", "Copyright 2020 Foo. All rights reserved."], "mit": ["Released under the MIT License."], "gpl": ["This work is licensed under the GNU General Public License, version 3."], "apache-2.0": ["Licensed under the Apache License, Version 2.0."]}
    assert {t: license_scan.classify(t)[0] for ts in kinds.values() for t in ts} == {t: f for f, ts in kinds.items() for t in ts}
    held = [(t, k) for t, k in license_scan._examples(random.Random(99), 2) if k < len(license_scan.TEMPLATES)]
    names = list(license_scan.TEMPLATES)
    assert np.mean([license_scan.classify(" ".join(t))[0] == names[k] for t, k in held]) > 0.9
    assert license_scan.classify("He asked for two of the old things.")[0] == license_scan.classify("of the")[0] == "unknown"


def test_licences_of_an_empty_table(spark):
    assert license_scan.scan_licences(docs_frame(spark, [(1, "x")]).limit(0)).count() == 0


# 2


def test_languages_of_the_documents(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    got = language_id.identify_documents(docs).join(docs.select("doc_id", "lang"), "doc_id")
    assert got.where("language = lang").count() >= 0.99 * docs.count() and got.where("rejected").count() == 0


def test_four_kinds_of_evidence_equal_brute_force(spark, small):
    """Every page's posterior is made again by a loop over all other pages that share its host, parent, declared language or suffix."""
    from urllib.parse import urlsplit

    model = language_id.train(spark.read.parquet(f"{small}/documents.parquet").select("text", "lang"))
    pages = spark.read.parquet(f"{small}/pages.parquet").select("page_id", "url", "html").limit(120)
    odd = [(10**6, "https://De.example.com/x", "<html lang=de><p>das</p>"), (10**6 + 1, "https://fr.example.com/", "<html lang='fr'><p>le</p>"), (10**6 + 2, None, None), (10**6 + 3, "no url", "<p>the</p>")]
    pages = pages.union(spark.createDataFrame(odd, pages.schema)).persist()
    found = language_id.page_evidence(pages)
    for r in found.join(pages.select(F.col("page_id").cast("string").alias("page_id"), "url"), "page_id").collect():
        host = urlsplit(r.url or "").hostname
        labels = (host or "").split(".")
        assert (r.host, r.parent, r.suffix) == (host, ".".join(labels[-2:]) if len(labels) > 1 else None, labels[-1] if len(labels) > 1 else None)
    rows = language_id.text_scores(found, model).collect()
    n, soft, logs = len(language_id.LANGUAGES) + 1, np.array([r.soft for r in rows]), np.array([r.logs for r in rows])
    smoothing, start = language_id.SMOOTHING, np.array([0.99 / (n - 1)] * (n - 1) + [0.01])
    base = (soft.sum(0) + smoothing * start) / (soft.sum() + smoothing)

    def others(i: int, name: str, towards: np.ndarray) -> np.ndarray:
        value = rows[i][name]
        rest = sum((soft[k] for k, r in enumerate(rows) if k != i and value is not None and r[name] == value), np.zeros(n))
        return (rest + smoothing * towards) / (rest.sum() + smoothing)

    got = {r.page_id: r for r in language_id.identify(found, model).collect()}
    assert len(got) == len(rows) == pages.count()
    for i, r in enumerate(rows):
        total = logs[i] + np.log(others(i, "host", others(i, "parent", base))) + np.log(others(i, "declared", base)) + np.log(others(i, "suffix", base)) - 2 * np.log(base)
        p = np.exp(total - total.max())
        p /= p.sum()
        best = (*language_id.LANGUAGES, "und")[int(p.argmax())] if r.n_letters else "und"
        assert got[r.page_id].language == best and abs(got[r.page_id].probability - (p.max() if r.n_letters else 1.0)) < 1e-6
    pages.unpersist()


def test_held_out_text_without_evidence(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    model = language_id.train(docs.where("doc_id % 2 = 0"))
    none = F.lit(None).cast("string")
    rows = docs.where("doc_id % 2 = 1").select("doc_id", "text", none.alias("declared"), none.alias("suffix"), none.alias("host"), none.alias("parent"))
    got = language_id.identify(rows, model).join(docs.select("doc_id", "lang"), "doc_id")
    assert got.where("language = lang").count() >= 0.97 * got.count()


def test_language_edge_cases(spark):
    frame = docs_frame(spark, [*EDGE, (9, "1234 5678 !!"), (None, "the end")])
    got = language_id.identify_documents(frame)
    assert got.count() == frame.count()
    assert {r.doc_id for r in got.where("rejected").collect()} >= {1, 2, 3, 9}
    kept = language_id.keep_identified(frame)
    assert kept.columns == frame.columns and kept.where("doc_id is null").count() == 1
    assert language_id.keep_identified(frame.limit(0)).count() == 0


def test_host_evidence_decides_short_texts(spark):
    rows = [(i, "der die das und nicht mit ein wort auf dem weg nach haus", "de", "h") for i in range(40)] + [(i, "the and of to in that it was for on with one word", "en", "g") for i in range(40, 80)] + [(90, "a", None, "h")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    assert language_id.identify_documents(docs).where("doc_id = 90").first().language == "de"


# 3


def test_urls_equal_every_rule_tried(spark):
    import re

    urls = [None, "", "nourl", "http://a\nb.com/en/1", "http://a.com\n/en/1", "http://com\n/en/", "http://example.com/en/7", "HTTP://A.EXAMPLE.COM/en/77?x", "http://a.com/en/", "http://com/en/x", "http://notexample.net/de/8", "https://x.example.net/de/8/9#y", "ftp://b.org/es/q", "http://a.org/ads/x", "http://a.b/ads/policy", "http://q.casino.z/", "http://a.com:80/en/", "x://://y/login", "http://a.b/poker", "http://É.org/es/"]
    pages = spark.createDataFrame(list(enumerate(urls)) + [(3, urls[3])], "page_id long, url string").withColumn("host", F.lit(1))
    got = sorted(url_filter.judge_urls(pages).collect())
    assert len(got) == len(urls) + 1
    low = str.maketrans(url_filter.UPPER, url_filter.LOWER)
    for r in got:
        url = urls[r.page_id]
        m = re.match(r"(?s)^.*?://([^/?#]*)([^?#]*)", url or "")
        host, path = (m[1].translate(low), m[2]) if m else ("", "")
        listed = [x for x in url_filter.LISTED if host and re.search(x.host_regex, host) and re.search(x.target_regex, path)]
        patterns = [x for x in url_filter.PATTERNS if url and re.search(x.target_regex, url.translate(low))]
        best = min(listed, key=lambda x: (-len(x.name), x.name), default=None)
        verdict = best.verdict if best else "allow" if not patterns or any(x.verdict == "allow" for x in patterns) else "block"
        assert (r.host, r.path, r.rule, r.verdict) == (host, path, best.name if best else None, verdict), url


def test_rules_have_the_contracts_words(spark):
    import duckdb

    words = {"com/en/": "block", "example.com/en/7": "allow", "net/de/": "allow", "example.net/de/8": "block", "org/es/": "block"}
    assert {r.name: r.verdict for r in url_filter.LISTED} == words
    urls = [f"http://www.{r}x" for r in words] + ["http://a.net/de/ads/"]  # a rule outranks a pattern
    pages = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string")
    want = [(k, *pair) for k, pair in enumerate([*words.items(), ("net/de/", "allow")])]
    assert sorted((r.page_id, r.rule, r.verdict) for r in url_filter.judge_urls(pages).collect()) == want
    db = duckdb.connect()
    db.register("pages", pages.toPandas())
    assert sorted((r[0], r[3], r[4]) for r in db.sql(url_filter.judge_sql()).fetchall()) == want


# 4


def test_automaton_equals_brute_force():
    rng = random.Random(1)
    for _ in range(400):
        letters = [b"a", b"b", b"c"][: rng.randint(1, 3)]
        window = rng.choice([2, 3, 10])
        items = [(str(i), [rng.choice(letters) for _ in range(rng.choice([0, 1, 3, 8, 14]))]) for i in range(rng.randint(1, 5))]
        doc = [rng.choice([*letters, b"z"]) for _ in range(rng.randint(0, 30))]
        starts, ends, found = decontaminate.SuffixAutomaton(items, window).scan(doc)
        hit, names = set(), set()
        for k, (_, x) in enumerate(items):
            m = min(window, len(x))
            for i in range(len(x) - m + 1 if m else 0):
                for j in range(len(doc) - m + 1):
                    if doc[j : j + m] == x[i : i + m]:
                        hit |= set(range(j, j + m))
                        names.add(k)
        assert sorted(hit) == [i for a, b in zip(starts, ends, strict=True) for i in range(a, b)] and names == found


def test_spans_are_cut_and_mostly_contaminated_documents_go(spark, monkeypatch):
    item = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda"
    bench = spark.createDataFrame([("i1", item), ("i2", "short one here"), (None, "nothing"), ("i3", None), ("i4", "rare words that never occur in any of these texts at all")], "item_id string, text string")
    clean = "This text, on the other hand, is clean! " * 8
    rows = [*EDGE, (20, clean), (21, clean + item.upper() + ". " + clean), (22, item + " x"), (23, "say short, one; HERE then " + clean)]
    frame = docs_frame(spark, rows)
    for bound in (decontaminate.AUTOMATON_WORDS, 8):  # one automaton, and several in turn
        monkeypatch.setattr(decontaminate, "AUTOMATON_WORDS", bound)
        out = {r.doc_id: r for r in decontaminate.decontaminate(frame, bench).collect()}
        assert set(out) == {i for i, _ in rows} - {22} and all(out[i].text == t for i, t in rows if i < 21)
        assert "ALPHA" not in out[21].text and out[21].text.count("clean!") == 16 and out[21].n_chars == len(out[21].text)
        report = {r.doc_id: r for r in decontaminate.contamination_report(frame, bench).collect()}
        assert (report[21].n_hit, report[21].items_sha256) == (11, hashlib.sha256(b"i1").hexdigest())
        assert report[23].n_hit == 3 and report[1].n_words == 0 and not report[20].contaminated
    assert decontaminate.decontaminate(frame.limit(0), bench).count() == 0


# 5


def test_pieces_equal_the_library_and_round_trip(spark, small):
    import sentencepiece

    library = sentencepiece.SentencePieceProcessor(model_file=sentencepiece_lattice.MODEL_FILE)
    docs = spark.read.parquet(f"{small}/documents.parquet").select("doc_id", "text").union(docs_frame(spark, [(1000, None), (1001, ""), (1002, "  two  spaces \nend "), (1003, "x" * 500 + " 漢字Ümlaut 12.5€"), (1004, "a"), (1005, "Don't stop: e.g. (this) one...")]).select("doc_id", "text"))
    coded = {r.doc_id: (list(r.ids), r.decoded, r.n_tokens) for r in sentencepiece_lattice.decode(sentencepiece_lattice.encode(docs)).collect()}
    for r in docs.collect():
        ids, decoded, n = coded[r.doc_id]
        assert ids == (library.encode(r.text) if r.text else []) and decoded == (r.text or "") and n == len(ids)


def test_viterbi_fold_equals_all_paths(spark):
    rng = random.Random(3)
    names = sorted({"".join(rng.choice("abc") for _ in range(rng.randint(1, 4))) for _ in range(25)} | {"▁", "▁a", "a", "b"})
    table = sentencepiece_lattice.PieceTable([(p, i + 300, -rng.random() * 5 - 1) for i, p in enumerate(names)], {}, 0, False)
    units = sorted({"▁" + "".join(rng.choice("abcd") for _ in range(rng.randint(1, 7))) for _ in range(30)})
    got = {r.unit: r.ids for r in sentencepiece_lattice.unit_dictionary(spark.createDataFrame([(u,) for u in units], "unit string"), table).collect()}
    score = {i: s for _, i, s in table.pieces}
    for u in units:
        best = -math.inf
        for mask in range(2 ** (len(u) - 1)):
            cuts = [0, *[i + 1 for i in range(len(u) - 1) if mask >> i & 1], len(u)]
            parts = [u[a:b] for a, b in zip(cuts, cuts[1:], strict=False)]
            if all(p in table.find or len(p) == 1 for p in parts):
                best = max(best, sum(table.find[p][1] if p in table.find else table.fallback for p in parts))
        assert math.isclose(sum(score.get(i, table.fallback) for i in got[u]), best)


def _merged(table, unit):
    """Byte-pair merges one by one: the best score first, then the leftmost."""
    parts = list(unit)
    while True:
        ready = [(-table.find[a + b][1], i) for i, (a, b) in enumerate(zip(parts, parts[1:], strict=False)) if a + b in table.find]
        if not ready:
            return [table.find[p][0] if len(p) > 1 else -1 - ord(p) for p in parts]
        i = min(ready)[1]
        parts[i : i + 2] = [parts[i] + parts[i + 1]]


@pytest.mark.parametrize("seed", [1, 2, 3])
def test_merge_fold_equals_merges_one_by_one(spark, seed):
    rng = random.Random(seed)
    names = sorted({"".join(rng.choice("abc") for _ in range(rng.randint(2, 5))) for _ in range(30)} | {"▁▁", "▁▁▁", "▁a"})
    rng.shuffle(names)
    pieces = [(p, i + 300, -1e9 if set(p) == {"▁"} else -float(i // (3 if seed == 3 else 1))) for i, p in enumerate(names)]  # not made of better parts, and with ties
    table = sentencepiece_lattice.PieceTable(pieces, {}, 0, True)
    units = sorted({"▁" * rng.randint(1, 6) + "".join(rng.choice("abcd") for _ in range(rng.choice([3, 9, 20, 61, 62, 63, 64, 65, 130]))) for _ in range(60)})
    got = {r.unit: r.ids for r in sentencepiece_lattice.unit_dictionary(spark.createDataFrame([(u,) for u in units], "unit string"), table).collect()}
    for u in units:
        assert got.get(u, [-1 - ord(c) for c in u]) == _merged(table, u), u


def test_unigram_models_equal_the_library(spark):
    import struct

    import sentencepiece

    def varint(n):
        return bytes([n]) if n < 128 else bytes([n & 127 | 128]) + varint(n >> 7)

    def field(k, body):
        return varint(k << 3 | 2) + varint(len(body)) + body

    rng = random.Random(8)
    words = sorted({"".join(rng.choice("abcde") for _ in range(rng.randint(2, 5))) for _ in range(60)})
    pieces = [("<unk>", 0.0, 2), ("▁", -3.0, 1), *((c, -4.0 - k / 7, 1) for k, c in enumerate("abcde")), *((p, -5 - rng.random() * 4, 1) for w in words for p in dict.fromkeys((w, "▁" + w)))]
    body = b"".join(field(1, field(1, p.encode()) + varint(2 << 3 | 5) + struct.pack("<f", s) + varint(3 << 3) + varint(kind)) for p, s, kind in pieces)
    model = body + field(2, varint(3 << 3) + varint(1)) + field(3, field(1, b"identity") + varint(3 << 3) + varint(1) + varint(4 << 3) + varint(0) + varint(5 << 3) + varint(1))
    library, table = sentencepiece.SentencePieceProcessor(model_proto=model), sentencepiece_lattice.PieceTable.of_model(model)
    assert not table.merges
    units = sorted({"".join(rng.choice("abcde") for _ in range(rng.randint(1, 14))) for _ in range(50)})
    got = {r.unit: r.ids for r in sentencepiece_lattice.unit_dictionary(spark.createDataFrame([("▁" + u,) for u in units], "unit string"), table).collect()}
    ids = lambda u: [table.find[chr(-1 - i)][0] if i < 0 else i for i in got["▁" + u]]
    assert {u: ids(u) for u in units} == {u: library.encode(u) for u in units}
    with pytest.raises(ValueError):
        sentencepiece_lattice.PieceTable.of_model(body + field(3, varint(4 << 3) + varint(1)))


def test_long_units_and_odd_rows_round_trip(spark):
    import sentencepiece

    library = sentencepiece.SentencePieceProcessor(model_file=sentencepiece_lattice.MODEL_FILE)
    big = 1234567890123456789
    rows = [(None, "word" * 200), (None, " " * 300 + "x"), (big, "ACGT" * 40), (big, "😀😀a𝒳 ▁ b"), (7, None), (7, ""), (8, "again"), (8, "again")]
    got = sentencepiece_lattice.encode(spark.createDataFrame(rows, "doc_id long, text string"), decoded=True).collect()
    want = [(i, library.encode(t) if t else [], (t or "").replace("▁", " ")) for i, t in rows]
    assert sorted(map(repr, ((r.doc_id, r.ids, r.decoded) for r in got))) == sorted(map(repr, want))


# 6


@pytest.mark.parametrize(
    "page, text",
    [
        (None, ""),
        ("", ""),
        ("just text &amp; more", "just text & more"),
        ("<html><body><nav><a href=x>Home</a></nav><article><h1>T</h1><p><b>One, two.<br><p>Three&nbsp;four &lt;x&gt;</p></article><footer>f</footer>", "T\nOne, two.\nThree four <x>"),
        ("<body class='has-sidebar'><div class=content><p>Long, good, text of the page here.<p>And, more, of it.</div><div class='comments'><p>Nice, post, indeed, friend, of mine.</div><div id=cookie-notice>We use, cookies, here, now, always.</div>", "Long, good, text of the page here.\nAnd, more, of it."),
        ("<article><p>A<script>var t='</p>';</script>B</p><form><input>Send</form><aside>x</aside></article>", "AB"),
    ],
)
def test_main_text(page, text):
    assert html_main_text.main_text(page) == text


def test_pages_keep_the_article(spark, small):
    import html
    import re

    got = {r.page_id: r for r in html_main_text.extract_main_text(spark.read.parquet(f"{small}/pages.parquet")).collect()}
    for r in spark.read.parquet(f"{small}/pages.parquet").collect():
        body = re.sub(r"<[^>]*>", "", re.sub(r"</?(?:p|h1)>", "\0", re.search(r"<article>(.*?)</article>", r.html, re.S)[1]).replace("<br>", " "))
        want = "\n".join(x for x in (" ".join(html.unescape(b).split()) for b in body.split("\0")) if x)
        assert got[r.page_id].text == want and got[r.page_id].n_chars == len(want)


# 7


def _shingles(text):
    w = words_of(text)
    return Counter(tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))) if w else Counter()


def _similarity(a, b):
    return sum(1 / sum(max(a.get(j, 0) / a[i], b.get(j, 0) / b[i]) for j in a.keys() | b.keys()) for i in a if i in b)


def test_classes_equal_brute_force(spark):
    rng = random.Random(4)
    word = lambda: "".join(rng.choice("abcdefghij") for _ in range(4))
    base = [[word() for _ in range(60)] for _ in range(12)]
    texts = [*[" ".join(b) for b in base], base and " ".join(base[0]).upper(), " ".join(base[1] * 2)]
    for b in base:
        for changes in (1, 1, 2, 6, 12):
            c = list(b)
            for _ in range(changes):
                c[rng.randrange(60)] = word()
            texts.append(" ".join(c))
    rows = [(100 + i, t) for i, t in enumerate(texts)] + EDGE
    got = {r.doc_id: r for r in probminhash.near_duplicates(docs_frame(spark, rows)).collect()}
    ids, bags = [i for i, _ in rows], [_shingles(t) for _, t in rows]
    parent = {i: i for i in ids}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for (i, a), (j, b) in combinations(zip(ids, bags, strict=True), 2):
        if a and b and _similarity(a, b) >= 0.8:
            p, q = find(i), find(j)
            parent[max(p, q)] = min(p, q)
    assert {i: got[i].class_id for i in ids} == {i: find(i) for i in ids}
    kept = probminhash.keep_one(docs_frame(spark, rows))
    assert kept.columns == docs_frame(spark, rows).columns and {r.doc_id for r in kept.collect()} == {i for i in ids if find(i) == i}
    assert probminhash.near_duplicates(docs_frame(spark, rows).limit(0)).count() == 0


def test_signatures_estimate_probability_jaccard():
    rng = np.random.default_rng(1)
    a = {i: int(rng.integers(1, 4)) for i in range(200)}
    b = {i + 40: int(rng.integers(1, 4)) for i in range(200)}
    code = probminhash.mix(np.array([*a, *b], np.uint64) + np.uint64(7))
    s = probminhash.signatures(np.repeat([0, 1], 200), code, np.array([*a.values(), *b.values()], float), 2, 4096)
    exact = _similarity(a, b)
    pack = lambda m: (np.array(sorted(m), np.uint32), np.array([m[k] for k in sorted(m)], float))
    assert abs((s[0] == s[1]).mean() - exact) < 0.04 and abs(probminhash.probability_jaccard(pack(a), pack(b)) - exact) < 1e-9


def test_large_groups_are_joined_over_blocks(spark, monkeypatch):
    monkeypatch.setattr(probminhash, "BLOCK", 8)
    rng = random.Random(6)
    base, chain = [f"w{i}" for i in range(80)], []
    for i in range(40):  # each a small step from the last, far from the first
        base = list(base)
        base[(2 * i) % 80] = f"x{i}"
        chain.append((i, " ".join(base)))
    rng.shuffle(chain)
    assert probminhash.near_duplicates(docs_frame(spark, chain)).select("class_id").distinct().count() == 1


# 8


def test_later_windows_go_and_nothing_is_lost(spark):
    a = "l1\nl2\nl3\nl4"
    rows = [*EDGE, (10, a), (11, "start\n" + a + "\nend"), (12, a), (13, "x\nx\nx\nx\nx"), (14, "\n\n\n\n"), (15, "\n\n\n\n"), (None, a)]
    frame = docs_frame(spark, rows)
    report = {r.doc_id: r for r in line_windows.dedup_report(frame).collect()}
    assert (report[10].n_removed, report[11].text, report[12].text, report[13].text, report[15].n_removed) == (0, "start\nend", "", "x", 0)
    out = line_windows.dedup_lines(frame)
    kept = {r.doc_id: r for r in out.collect()}
    assert out.columns == frame.columns and 12 not in kept and kept[11].n_chars == 9 and kept[None].text == a and kept[1].text is None and kept[2].text == ""
    assert out.count() == len(rows) - 1 and line_windows.dedup_lines(frame.limit(0)).count() == 0


def test_rows_that_share_a_doc_id_keep_their_own_lines(spark):
    rows = [(5, "zz\na1\na2\na3"), (5, "only\nunique one\nunique two\nunique three"), (1, "a1\na2\na3")]
    assert sorted(r.text for r in line_windows.dedup_lines(docs_frame(spark, rows)).collect()) == ["a1\na2\na3", rows[1][1], "zz"]


# 9


def test_rollup_of_nothing_and_of_deletes_first(spark, tmp_path):
    rollup = token_rollup.TokenRollup(spark, f"file://{tmp_path}/rollup")
    big = 1234567890123456789
    assert rollup.commit("01", deletes=spark.createDataFrame([(1,)], "doc_id long")) and not rollup.committed("1")
    assert rollup.commit("1", upserts=docs_frame(spark, [(1, "x")]).limit(0)) and rollup.totals().count() == 0
    assert rollup.commit("2", upserts=docs_frame(spark, [(big, "one two"), (None, "three")]))
    assert rollup.commit("3", deletes=spark.createDataFrame([(big,)], "doc_id long"))
    assert {r.n_docs for r in rollup.totals().collect()} == {1}


def test_rollup_follows_changes_and_batches_commit_once(spark, tmp_path):
    rollup = token_rollup.TokenRollup(spark, f"file://{tmp_path}/rollup")
    assert rollup.totals().count() == 0
    first = docs_frame(spark, [*EDGE, (10, "hello world"), (None, "kept for ever")])
    assert rollup.commit("b1", upserts=first) and not rollup.commit("b1", upserts=first)
    change = docs_frame(spark, [(10, "hello"), (50, "new text here")])
    assert rollup.commit("b2", upserts=change, deletes=spark.createDataFrame([(6,), (999,)], "doc_id long"))
    final = docs_frame(spark, [r for r in EDGE if r[0] != 6] + [(None, "kept for ever"), (10, "hello"), (50, "new text here")])
    want = token_rollup.count_tokens(final).groupBy("source", "lang", "tokenizer").agg(F.count("*").alias("n_docs"), F.sum("n_tokens").alias("n_tokens"), F.sum("n_bytes").alias("n_bytes"))
    assert sorted(rollup.totals().collect()) == sorted(want.collect())


def test_token_counts_equal_the_library(spark, small):
    import base64
    from pathlib import Path

    import tiktoken

    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, Path(token_rollup.TOKENIZER_FILE).read_bytes().splitlines())}
    library = tiktoken.Encoding("t", pat_str=token_rollup.PATTERN, mergeable_ranks=ranks, special_tokens={})
    total = sum(len(library.encode_ordinary(r.text)) for r in spark.read.parquet(f"{small}/documents.parquet").collect())
    got = queries.op9_token_counts(spark, small)
    assert got.where("tokenizer like 'byte%'").agg(F.sum("n_tokens")).first()[0] == total


# 10


def test_top_k_edge_cases_and_ties(spark, monkeypatch):
    monkeypatch.setattr(mtree, "CELL_ROWS", 64)
    monkeypatch.setattr(mtree, "LEAF_ROWS", 8)
    monkeypatch.setattr(mtree, "QUERY_ROWS", 4)
    rng = np.random.default_rng(2)
    rows = [(i, rng.integers(-3, 4, 6).astype(float).tolist()) for i in range(300)] + [(500, None), (520, [1.0, None, 1.0, 1.0, 1.0, 1.0]), (540, [float("nan")] * 6), (560, [1.0, 2.0]), (561, [3.0, 4.0]), (580, [])]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = {}
    for r in mtree.top_k(frame).collect():
        got.setdefault(r.query_id, []).append((r["rank"], r.vec_id, r.score))
    good = {i: np.floor(64 * np.array(v)) for i, v in rows if v and all(x is not None and math.isfinite(x) for x in v)}
    for q in [i for i in good if i % 20 == 0]:
        want = sorted(((-int(good[q] @ v), i) for i, v in good.items() if i != q and len(v) == len(good[q])))[:20]
        assert sorted(got[q]) == [(k, i, -s) for k, (s, i) in enumerate(want, 1)]
    assert set(got) == {i for i in good if i % 20 == 0} and mtree.top_k(frame.limit(0)).count() == 0


def test_bounds_spare_work_in_clustered_data():
    rng = np.random.default_rng(3)
    centers = rng.normal(size=(16, 8)) * 300
    x = np.floor(centers[rng.integers(0, 16, 2000)] + rng.normal(size=(2000, 8)) * 5)
    bound = float((x * x).sum(1).max())
    _, _, work = mtree.Cell(np.arange(2000), x, bound).search(np.arange(0, 2000, 20), x[::20], bound, 5)
    assert work["rows"] < 0.75 * 100 * 2000


def test_ids_beside_nulls_and_values_too_large(spark):
    big = 1234567890123456789
    vectors = spark.createDataFrame([(None, [1.0, 2.0]), (big, [1.0, 2.0]), (20, [1.0, 1.0]), (21, [1e17, 1.0]), (22, [1e307, 1.0]), (23, [1e7, 1.0])], "vec_id long, embedding array<double>")
    assert sorted((r.query_id, r.vec_id, r.score) for r in mtree.top_k(vectors).collect()) == [(20, 23, 640000000 * 64 + 4096), (20, big, 64 * 64 * 3)]
    docs = docs_frame(spark, [(None, "the end of it"), (big, "the end of it")])
    bench = spark.createDataFrame([("i", "the end of it")], "item_id string, text string")
    assert {r.doc_id for r in decontaminate.contamination_report(docs, bench).collect()} == {None, big}
    assert {r.doc_id for r in language_id.identify_documents(docs).collect()} == {None, big}
    pages = spark.createDataFrame([(None, "u", "<p>x</p>"), (big, "u", "<p>y</p>")], "page_id long, url string, html string")
    assert {r.page_id for r in html_main_text.extract_main_text(pages).collect()} == {None, big}


# the pipeline


def test_pipeline_equals_its_stages_by_hand(spark, small):
    import corpus_pipeline

    docs = spark.read.parquet(f"{small}/documents.parquet")
    out = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before, out = out, stage(spark, out, small)
        assert out.columns == docs.columns, name
        assert out.join(before.select("doc_id"), "doc_id", "left_anti").count() == 0
    bench = spark.read.parquet(f"{small}/benchmark.parquet")
    assert decontaminate.contamination_report(out, bench).where("contaminated").count() == 0
    final = corpus_pipeline.run(spark, small)
    assert sorted(r.doc_id for r in final.collect()) == sorted(r.doc_id for r in out.collect())
    assert set(final.columns) == {"doc_id", "n_tokens", "ids"}


def test_main_text_keeps_inline_words_and_reads_malformed_pages_fast():
    import time

    assert html_main_text.main_text("<article><p>The mass is <math><mi>m</mi></math> grams, and <label>so</label> on.</p></article>") == "The mass is m grams, and so on."
    assert html_main_text.main_text("<body><div class='widget'><p>The only text, of this page.</p></div></body>") == "The only text, of this page."
    for page in ("<a " * 100_000, "<b>" * 50_000 + "</i>" * 50_000, "<!" * 100_000, "<li>" * 50_000):
        began = time.process_time()
        html_main_text.main_text(page)
        assert time.process_time() - began < 20, page[:8]


def test_main_text_of_several_sections_without_an_article():
    long = "<p>" + "a, b, c, " + "x" * 291 + "</p>"
    page = f"<html><body><div id=nav><a href=/>Home</a></div><div id=post><h3>Title</h3><div class=part>{long * 5}</div><div class=part><p>One short paragraph.</p></div><ul><li>An item</li></ul><div><a href=/n>Next page of links</a></div><p>Short end.</p>bare tail</div></body></html>"
    got = html_main_text.main_text(page).split("\n")
    assert got[0] == "Title" and got[6:] == ["One short paragraph.", "An item", "Short end.", "bare tail"] and len(got) == 10


def test_queries_never_pass_through_the_driver(spark, tmp_path, monkeypatch):
    rng = np.random.default_rng(3)
    rows = [(int(i), [float(v) for v in rng.integers(-6, 7, 4) / 64]) for i in range(900)]
    table = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    want = []
    x = {i: np.floor(64 * np.array(v)).astype(int) for i, v in rows}
    for q in range(0, 900, 20):
        order = sorted((-int(x[q] @ v), i) for i, v in x.items() if i != q)[:20]
        want += [(q, k, i, -s) for k, (s, i) in enumerate(order, 1)]
    # Many small cells and groups, so that bounds are carried over and parts are not full.
    for name, value in (("CELL_ROWS", 40), ("GROUP_ROWS", 12), ("PART_CELLS", 3), ("MIN_UNITS", 4), ("QUERY_ROWS", 5)):
        monkeypatch.setattr(mtree, name, value)
    found = mtree.top_k(table)
    assert "Broadcast" not in found._jdf.queryExecution().executedPlan().toString()
    assert sorted((r.query_id, r.rank, r.vec_id, r.score) for r in found.collect()) == want
