import base64
import gzip
import hashlib
import itertools
import random
import re
import urllib.parse
import zlib

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from semjoin.llm import decontaminate, htmltext, licences, packing, quality, secrets, sharding, simhash, toxicity

SF = "/root/testdata/sf0.001"
DOC = "doc_id long, text string, lang string, source string, n_chars long, fp string, n int, __n_words int"


@pytest.fixture(scope="module")
def docs(spark):
    """Nulls, empty texts, a long text, repeated rows, extra columns with names that clash."""
    rng, words = random.Random(1), "the of and running over green hills with seven quick foxes near old stone walls".split()
    text = lambda n: " ".join(rng.choice(words) for _ in range(n))
    base = text(300)
    rows = [(1, base), (2, base + " "), (3, base.replace("green", "blue", 1)), (4, text(80) + "\n" + text(5)), (5, None), (6, ""), (7, text(30_000)), (8, base), (8, base), (None, base), (9, "One two."), (10, "!!! ??? ***")]
    return spark.createDataFrame([(i, t, None if i == 4 else "en", None, None, "x", 1, 2) for i, t in rows], DOC)


@pytest.fixture(scope="module")
def no_docs(spark):
    return spark.createDataFrame([], DOC)


def slow_fingerprint(text, n=3):
    words = re.findall(rb"[^\x20\x09-\x0D]+", (text or "").encode().translate(bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))))
    if not words:
        return 0
    h = [xxhash.xxh64_intdigest(b" ".join(words[i : i + n]), 42) for i in range(max(1, len(words) - n + 1))]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def slow_components(values):
    """Smallest id reachable over links of two bits."""
    ids = sorted(values)
    root = {i: i for i in ids}
    changed = True
    while changed:
        changed = False
        for i, j in itertools.combinations(ids, 2):
            if (values[i] ^ values[j]).bit_count() <= 2 and root[i] != root[j]:
                root[i] = root[j] = min(root[i], root[j])
                changed = True
    return root


def test_simhash_equals_brute_force(spark, docs, no_docs):
    rows = docs.select("doc_id", "text").collect()
    got = simhash.near_duplicates(docs).collect()
    assert len(got) == len(rows)
    want = {r["doc_id"]: slow_fingerprint(r["text"]) for r in rows}
    ids = {i: v for i, v in want.items() if i is not None}
    root = slow_components(ids)
    for r in got:
        assert r["fp"] % 2**64 == want[r["doc_id"]]
        assert r["component_id"] == root[1 if r["doc_id"] is None else r["doc_id"]]
    assert simhash.near_duplicates(no_docs).collect() == []


def test_hot_buckets_lose_no_link(spark):
    rng = random.Random(5)
    centre, values = rng.getrandbits(64), set()
    while len(values) < 400:
        v = centre
        for _ in range(rng.randint(0, 4)):
            v ^= 1 << rng.randrange(64)
        values.add(v if rng.random() < 0.9 else rng.getrandbits(64))
    values = sorted(values)
    want = slow_components(dict(enumerate(values)))
    fps = spark.createDataFrame([(simhash._signed(v),) for v in values], "fp long")
    for limit in (3, 250, 20_000):
        parent = {v: v for v in values}

        def find(x):
            while parent[x] != x:
                x = parent[x]
            return x

        for r in simhash.close_edges(fps, group_limit=limit).collect():
            assert (r["a"] % 2**64 ^ r["b"] % 2**64).bit_count() <= 2
            a, b = find(r["a"] % 2**64), find(r["b"] % 2**64)
            parent[max(a, b)] = min(a, b)
        assert {i: find(v) for i, v in enumerate(values)} == {i: values[want[i]] for i in want}


def test_first_of_group(docs):
    kept = sorted(r["doc_id"] for r in simhash.first_of_group(docs).where("doc_id is not null").collect())
    assert 1 in kept and 2 not in kept and 8 not in kept and 7 in kept and 5 in kept and 6 not in kept


def test_boundaries_equal_brute_force():
    rng = random.Random(2)
    for _ in range(30):
        lengths = sorted(rng.sample(range(1, 40), rng.randint(1, 8)))
        counts = [rng.randint(1, 9) for _ in lengths]
        k = rng.randint(1, 4)
        pad = lambda bounds: sum(c * (min(b for b in bounds if b >= n) - n) for n, c in zip(lengths, counts, strict=True))  # noqa: B023, E731
        best = min(pad((*c, lengths[-1])) for r in range(min(k, len(lengths))) for c in itertools.combinations(lengths[:-1], r))
        bounds, padding = packing.best_boundaries(lengths, counts, k)
        assert padding == best == pad(bounds) and len(bounds) <= k


def test_pack(spark, docs, no_docs):
    got = packing.pack(docs, max_len=64, max_buckets=3, token_budget=256).collect()
    words = sum(len((r["text"] or "").split()) for r in docs.collect())
    assert sum(r["n_tokens"] for r in got) == words
    batches = {}
    for r in got:
        assert r["n_tokens"] <= r["padded_len"] and (r["n_tokens"] == 64 or True)
        batches.setdefault((r["bucket"], r["padded_len"]), {}).setdefault(r["batch"], []).append(r["slot"])
    for (_, length), by in batches.items():
        room = max(1, 256 // max(1, length))
        assert sorted(by) == list(range(len(by)))
        assert all(sorted(s) == list(range(room if b < len(by) - 1 else len(s))) and len(s) <= room for b, s in by.items())
    assert packing.pack(no_docs).collect() == []


def slow_quality(text):
    text = text or ""
    words = re.findall(r"[^\x20\x09-\x0D]+", text)
    grams = [tuple(words[i : i + 3]) for i in range(len(words) - 2)]
    hit = {j for i, g in enumerate(grams) if grams.count(g) > 1 for j in (i, i + 1, i + 2)}
    lines = [x for x in text.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    return len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in text), len(lines) - len(set(lines)), len(hit)


def test_quality_features_equal_brute_force(spark):
    rng = random.Random(4)
    texts = [None, "", " \n\t", "a b c a b c", "x\nx\n y\n\nx", "é ü z ### |<>"] + [" ".join(rng.choice("abcdé") for _ in range(n)) + rng.choice(["", "\nq q q\nq q q"]) for n in range(1, 60)]
    docs = spark.createDataFrame([(i, t, "en") for i, t in enumerate(texts)], "doc_id long, text string, lang string")
    labels = spark.createDataFrame([], "doc_id long, quality int")
    for r in quality.quality(docs, labels).collect():
        want = slow_quality(texts[r["doc_id"]])
        assert tuple(r)[1:6] == want
        assert r["base_failed"] == (want[0] < 50 or 100 * want[4] > 50 * want[0]) and r["kept"] == (not r["base_failed"])


def test_cutoffs_keep_their_promise(spark):
    docs, labels = spark.read.parquet(f"{SF}/../sf0.1/documents.parquet"), spark.read.parquet(f"{SF}/../sf0.1/labels.parquet")
    got = quality.quality(docs, labels)
    good = got.where("not base_failed").join(labels.where("quality = 1"), "doc_id").join(docs.select("doc_id", "lang"), "doc_id")
    shares = good.groupBy("lang").agg(F.avg((~F.col("kept")).cast("int")).alias("lost")).collect()
    assert shares and all(r["lost"] <= 0.10 for r in shares)
    bad = got.join(labels.where("quality = 0"), "doc_id").agg(F.avg((~F.col("kept")).cast("int"))).first()[0]
    assert bad > 0.5


def test_binomial_tail(spark):
    from math import comb

    rows = [(20, 3, 0.1), (100, 0, 0.05), (50, 50, 0.3)]
    for n, k, p in rows:
        got = spark.range(1).select(quality.binomial_tail(F.lit(n).cast("long"), F.lit(k).cast("long"), p)).first()[0]
        assert got == pytest.approx(sum(comb(n, i) * p**i * (1 - p) ** (n - i) for i in range(k + 1)), rel=1e-9)


def test_shards(spark, docs, no_docs):
    for n_rows, shards in ((0, 3), (1, 8), (5, 2), (97, 8), (1000, 7)):
        got = sharding.shard(spark.range(n_rows).selectExpr("id as doc_id", "cast(id as string) as text", "1 as slot"), shards).collect()
        assert sorted(r["slot"] * shards + r["shard"] for r in got) == list(range(n_rows))
    rows = sharding.shard(docs).collect()
    texts = {r["doc_id"]: (r["text"] or "").encode() for r in docs.collect()}
    assert all(r["size"] == len(texts[r["doc_id"]]) + 1 and r["text_crc32"] == zlib.crc32(texts[r["doc_id"]]) for r in rows)
    assert sharding.shard(docs.repartition(5)).select("doc_id", "text_crc32", "shard", "slot").distinct().count() == len(rows)
    assert sharding.shard(no_docs).collect() == []


def test_licences(spark, no_docs):
    notice = "Licensed under the Apache License, Version 2.0."
    rows = [(1, "a/LICENSE", notice), (2, "a/b/x.py", "plain words here"), (3, "a/b/COPYING", "Released under the MIT License."), (4, "a/b/c/y.py", "more plain words"), (5, "z/w.py", "# Licensed under the Apache License, Version 2.0.\ncode and more code that goes on for longer than the notice above does in words"), (6, "z/v.py", "the license of poetry"), (7, None, None)]
    docs = spark.createDataFrame(rows, "doc_id long, path string, text string")
    got = {r["doc_id"]: (r["licence"], r["how"]) for r in licences.licences(docs, F.col("path")).collect()}
    assert got == {1: ("Apache-2.0", "own"), 2: ("MIT", "inherited"), 3: ("MIT", "own"), 4: ("MIT", "inherited"), 5: ("Apache-2.0", "own"), 6: (None, "none"), 7: (None, "none")}
    assert licences.licences(no_docs, F.lit("a/b")).collect() == []


def test_decontamination(spark, no_docs):
    item = "A train leaves the station at 40 km per hour and reaches Paris after 3 hours, how far is Paris from the first station of the line"
    changed = item.replace("40", "75").replace("Paris", "Madrid").replace("3 hours", "9 hours")
    mixed = item.replace("reaches Paris", "reaches Rome")
    rows = [(1, "Before it. " + item + " and after."), (2, "x " + changed), (3, mixed), (4, "A train leaves the station at noon"), (5, None), (6, ""), (1, item)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    bench = spark.createDataFrame([(7, item), (8, None), (9, "tiny 4 words here")], "item_id long, text string")
    got = sorted((r["doc_id"], r["item_id"], r["changed_slots"] > 0) for r in decontaminate.leaks(docs, bench).collect())
    assert got == [(1, 7, False), (1, 7, False), (2, 7, True)]
    assert sorted(tuple(r)[:2] for r in decontaminate.leaks(docs, bench, max_windows=5).collect()) == [x[:2] for x in got]
    assert decontaminate.leaks(no_docs, bench).collect() == [] == decontaminate.leaks(docs, bench.where("false")).collect()
    assert sorted(r["doc_id"] for r in decontaminate.without_leaks(docs, bench).collect()) == [3, 4, 5, 6]


def test_decontamination_finds_all_passages(spark):
    docs, bench = spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/benchmark.parquet")
    want = {tuple(r) for r in docs.join(F.broadcast(bench.withColumnRenamed("text", "p")), F.contains("text", "p")).select("doc_id", "item_id").collect()}
    assert want and want <= {tuple(r)[:2] for r in decontaminate.leaks(docs, bench).collect()}


def base_spans(text):
    out = [(*m.span(), 0) for m in re.finditer(r"([pP][aA][sS][sS][wW][oO][rR][dD]|[pP][aA][sS][sS][wW][dD]|[sS][eE][cC][rR][eE][tT]|[tT][oO][kK][eE][nN]|[aA][pP][iI]_?[kK][eE][yY])[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", text) if len(m[2]) >= 6]
    out += [(*m.span(), 1) for m in re.finditer(r"AKIA[A-Z0-9]+", text) if len(m[0]) >= 20]
    out += [(*m.span(), 2) for m in re.finditer(r"[0-9a-f]+", text) if len(m[0]) >= 24]
    return sorted(out, key=lambda x: (x[0], x[2]))


def test_secret_base_spans():
    rng = random.Random(9)
    parts = ["password = abc123def", "Token:'x'", "api_key=secret=ABCDEFG", "ſecret=abcdefgh", "AKIA" + "Z9" * 9, "AKIAshort", "0123456789abcdef" * 2, "deadbeef", "é", "%%%", "APIKEY = \"q.w-e_r=t\"", "tokentoken==abcdef"]
    for _ in range(300):
        text = rng.choice(["", " ", "ü"]).join(rng.choice(parts) for _ in range(rng.randint(0, 6)))
        base, every = secrets.secrets_in(text)
        assert base == base_spans(text)
        assert [x for x in every if "@" not in x[2]] == [(s, e, secrets.KINDS[k]) for s, e, k in base]


def test_nested_secrets():
    inner = "password=hunter2hunter2"
    b64 = lambda b: base64.b64encode(b).decode()
    for text, name, blob in (
        ("see " + b64(inner.encode()) + " ok", "assign@base64", b64(inner.encode())),
        ("see " + b64(gzip.compress(inner.encode(), mtime=0)) + " ok", "assign@base64+gzip", b64(gzip.compress(inner.encode(), mtime=0))),
        ("see " + b64(b64(inner.encode()).encode()) + " ok", "assign@base64+base64", b64(b64(inner.encode()).encode())),
        ("see password%3Dhunter2hunter2 ok", "assign@url", "password%3Dhunter2hunter2"),
        ("see " + "".join(f"\\u{ord(c):04x}" for c in inner) + " ok", "assign@unicode", "".join(f"\\u{ord(c):04x}" for c in inner)),
        ("see " + urllib.parse.quote(b64(gzip.compress(zlib.compress(inner.encode()), mtime=0)), safe="") + "%20 ok", "assign@url+base64+gzip+zlib", urllib.parse.quote(b64(gzip.compress(zlib.compress(inner.encode()), mtime=0)), safe="")),
    ):
        spans = [x for x in secrets.secrets_in(text)[1] if x[2] == name]
        assert spans, (name, secrets.secrets_in(text)[1])
        start = text.index(blob)
        assert start <= spans[0][0] and spans[0][1] <= start + len(blob) + 3
    loop = "%2525" * 50
    assert secrets.secrets_in(loop) == ([], [])


def test_secret_query(spark):
    docs = spark.createDataFrame([(1, None), (2, ""), (3, "token = abcdef123 " + "f" * 30), (3, "x")], "doc_id long, text string")
    got = secrets.scan_documents(docs).collect()
    assert [len(r["base"]) for r in got] == [0, 0, 2, 0]
    assert hashlib.sha256(b"").hexdigest().startswith("e3b0c442")


def test_toxicity(spark):
    docs, labels = (spark.read.parquet(f"{SF}/../sf0.1/{t}.parquet") for t in ("documents", "labels"))
    model = toxicity.fit(docs, labels, max_train=3000)
    got = toxicity.score(docs, model).where("held_out").join(labels, "doc_id").collect()
    hits = sum(r["predicted"] == 1 and r["toxic"] == 1 for r in got)
    assert hits >= 0.75 * sum(r["toxic"] for r in got) and sum(r["predicted"] == 1 and r["toxic"] == 0 for r in got) <= 0.02 * len(got)
    odd = spark.createDataFrame([(1, None), (2, ""), (None, "x")], "doc_id long, text string")
    scores = [r["score"] for r in toxicity.score(odd, model).collect()]
    assert len(scores) == 3 and all(0 <= s <= 1 for s in scores)
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2) for r in got)


def test_counterfactual_penalty_lowers_identity_weights():
    rng, known, rows = random.Random(0), toxicity.Features(), []
    terms = toxicity._next_terms()
    for _ in range(600):
        toxic = rng.random() < 0.5
        words = {rng.choice(["lorem", "ipsum", "dolor"])} | ({"muslim"} if rng.random() < (0.9 if toxic else 0.1) else set()) | ({"idiot"} if toxic and rng.random() < 0.7 else set())
        own, other = toxicity.features_of(words, known), toxicity.features_of(toxicity.swapped(words, terms), known)
        rows.append((int(toxic), np.array(sorted(own)), np.array(sorted(other - own)), np.array(sorted(own - other))))
    weight = lambda m, w: sum(m[1].get(i, 0.0) for i in known[w])
    plain, fair = toxicity.train(rows, fairness=0.0), toxicity.train(rows, fairness=20.0)
    assert abs(weight(fair, "muslim")) < 0.5 * abs(weight(plain, "muslim")) and weight(fair, "idiot") > 1
    assert toxicity.train([])[1] == {}


PAGE = """<!DOCTYPE html><html><head><title>T</title><style>p{}</style><script>var t="</p>";</script></head><body>
<header><h1>Site name</h1></header><nav><ul><li><a href=/a>One</a><li><a href=/b>Two</a></ul></nav><div class="cookie-notice">We use cookies on this page</div>
<article><h1>Head &amp; line</h1><p>First <b>bold</b> text<br>next   line <a href=x>with link</a>.<p>Second&nbsp;part &lt;b&gt; goes on and on with many words to read.</p><form><input><label>Mail</label></form><div class="ad">Buy now</div></article>
<aside>Side words</aside><div id="comments"><h3>Comments</h3><p>Reader says a lot of things here, more and more and more.</p></div><footer>&copy; 2024</footer></body></html>"""


def test_html():
    assert htmltext.main_text(PAGE) == "Head & line First bold text next line with link. Second part <b> goes on and on with many words to read."
    plain = PAGE.replace("article>", "div>").replace("<article", "<div")
    assert htmltext.main_text(plain) == htmltext.main_text(PAGE)
    assert htmltext.main_text("") == "" and htmltext.main_text("just text") == "just text" and htmltext.main_text("<p>a<p>b") == "a b"
    assert htmltext.main_text("<body><div><p>cut off <b>here") == "cut off here"


def test_html_on_pages(spark, no_docs):
    pages = spark.read.parquet(f"{SF}/pages.parquet")
    for r in htmltext.extract(pages).join(pages.select("page_id", "html"), "page_id").collect():
        body = re.sub(r"<[^>]+>", lambda m: m[0] if m[0] in ("<b>", "</b>") else " ", re.search(r"<article>(.*?)(?:</article>|\Z)", r["html"], re.S)[1])
        import html as h

        want = " ".join(h.unescape(re.sub(r"</?b>", "", body)).split())
        assert r["text"] == want and r["n_chars"] == len(want)
    odd = spark.createDataFrame([(1, None, None)], "page_id long, url string, html string")
    assert [tuple(r) for r in htmltext.extract(odd).collect()] == [(1, None, "", 0)]


def test_bucket_program_in_linear_memory():
    """Random histograms against a dense program, and as many lengths as a table of all pairs could not hold."""
    rng = np.random.default_rng(5)
    for _ in range(40):
        n, most = int(rng.integers(1, 60)), int(rng.integers(1, 9))
        lengths, counts = np.sort(rng.choice(500, n, replace=False)), rng.integers(1, 1000, n)
        pad = [[int(sum(counts[x] * (lengths[j] - lengths[x]) for x in range(i, j + 1))) for j in range(n)] for i in range(n)]
        best = pad[0]
        totals = [best[-1]]
        for _ in range(1, most):
            best = [min([pad[0][j], *[best[i - 1] + pad[i][j] for i in range(1, j + 1)]]) for j in range(n)]
            totals.append(best[-1])
        assert packing.best_boundaries(list(map(int, lengths)), list(map(int, counts)), most)[1] == min(totals)
    bounds, _ = packing.best_boundaries(list(range(1, 60_001)), [1] * 60_000, 8)
    assert len(bounds) == 8 and bounds[-1] == 60_000
