import itertools
import random

from semjoin.llm import similar, simhash


def shingles(text, n=5):
    w = (text or "").lower().split()
    return {tuple(w[i : i + n]) for i in range(max(1, len(w) - n + 1))} if w else set()


def jaccard(a, b):
    return 1.0 if a == b else len(a & b) / len(a | b)


def slow_groups(texts, threshold=0.8):
    sets = {i: shingles(t) for i, t in texts.items()}
    links = [(i, j) for i, j in itertools.combinations(sorted(texts), 2) if jaccard(sets[i], sets[j]) >= threshold]
    root, was = {i: i for i in texts}, None
    while root != was:
        was = dict(root)
        for i, j in links:
            root[i] = root[j] = min(root[i], root[j])
    return root


def links_of(docs):
    """similar_links() between ids."""
    rows = simhash.numbered(docs.where("doc_id is not null").select("doc_id", "text"))
    links = similar.similar_links(docs, rows)
    ids = rows.select("n", "__id")
    named = links.join(ids.withColumnsRenamed({"n": "a", "__id": "x"}), "a").join(ids.withColumnsRenamed({"n": "b", "__id": "y"}), "b")
    return named.where("x <> y").selectExpr("least(x, y) as a", "greatest(x, y) as b").distinct()


def edited(rng, words, n):
    out = list(words)
    for at in rng.sample(range(len(out)), n):
        out[at] = f"new{rng.random()}"
    return " ".join(out)


def test_links_equal_brute_force_on_planted_copies(spark):
    rng = random.Random(3)
    vocabulary = [f"w{i}" for i in range(400)]
    texts, i = {}, 0
    for g in range(40):
        base = [rng.choice(vocabulary) for _ in range(rng.randint(6, 400))]
        for n in (0, 0, *(k for k in (1, 2, 3, 8, 20) if k < len(base))):
            texts[i], i = edited(rng, base, n), i + 1
    texts |= {i: "", i + 1: None, i + 2: " \n", i + 3: "One two", i + 4: "one TWO", i + 5: "É a b c d", i + 6: "e a b c d"}
    docs = spark.createDataFrame([(k, t, 1) for k, t in texts.items()] + [(None, texts[0], 1), (0, texts[0], 1)], "doc_id long, text string, keys int")
    links = links_of(docs)
    found = {(r.a, r.b) for r in links.collect()}
    assert all(jaccard(shingles(texts[a]), shingles(texts[b])) >= 0.8 for a, b in found)
    want = slow_groups(texts)
    got = {k: k for k in texts} | {r.node: r.root for r in simhash.components(links).collect()}
    assert got == want
    kept = sorted(r.doc_id for r in simhash.first_of_group(docs).where("doc_id is not null").distinct().collect())
    assert set(kept) <= {k for k in texts if want[k] == k} and kept[0] == 0
    assert simhash.first_of_group(docs).where("doc_id is null").count() == 1


def test_a_large_group_and_very_long_texts(spark):
    """A block that holds a third of all rows, all of them different; texts alike in parts alone stay apart."""
    rng = random.Random(4)
    base = [f"w{rng.randrange(2000)}" for _ in range(200)]
    long = [f"v{rng.randrange(9000)}" for _ in range(60_000)]
    rows = [(i, edited(rng, base, 1)) for i in range(300)] + [(300 + i, " ".join(f"x{rng.randrange(5000)}" for _ in range(60))) for i in range(600)]
    rows += [(900, " ".join(long)), (901, edited(rng, long, 200)), (902, " ".join(long[:30_000]))]
    kept = {r.doc_id for r in simhash.first_of_group(spark.createDataFrame(rows, "doc_id long, text string")).select("doc_id").collect()}
    assert kept == {0, *range(300, 901), 902}


def test_groups_near_the_threshold_equal_brute_force(spark):
    """Many different texts at about 0.8 in shared blocks: representatives alone would leave some of them apart."""
    rng = random.Random(5)
    texts = {}
    for g in range(3):
        base = [f"w{rng.randrange(3000)}" for _ in range(120)]
        texts |= {100 * g + i: edited(rng, base, rng.choice((1, 2, 2, 3))) for i in range(90)}
    docs = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    found = {k: k for k in texts} | {r.node: r.root for r in simhash.components(links_of(docs)).collect()}
    want = slow_groups(texts)
    assert len(set(want.values())) > 3 and found == want


def test_remaining_links_in_parts_and_whole(spark):
    """From no links at all, one block's members end in the groups of brute force, however the block is dealt."""
    rng = random.Random(6)
    base = [f"w{rng.randrange(3000)}" for _ in range(100)]
    texts = {i: edited(rng, base, rng.choice((1, 2, 3))) for i in range(60)}
    docs = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    sets = docs.select("doc_id", similar.shingle_set(similar.words_of(docs["text"])).alias("s"))
    large = docs.selectExpr("7L as key", "doc_id as id")
    none, want = spark.createDataFrame([], "a long, b long"), slow_groups(texts)
    for mass in (10**6, 1500):
        links = similar.remaining_links(large, none, sets, 0.8, mass)
        assert {k: k for k in texts} | {r.node: r.root for r in simhash.components(links).collect()} == want
        assert mass < 10**6 or links.count() == len(texts) - len(set(want.values()))


def test_empty_table(spark):
    docs = spark.createDataFrame([], "doc_id long, text string")
    assert links_of(docs).count() == 0 and simhash.first_of_group(docs).count() == 0


def test_block_keys_agree_for_equal_sets_only():
    a, b = similar.shingle_hashes(b"a b c d e f g"), similar.shingle_hashes(b"A B C D E F G")
    assert similar.block_keys(a) == similar.block_keys(b) and len(similar.block_keys(a)) == similar.BLOCKS
    assert not set(similar.block_keys(a)) & set(similar.block_keys(similar.shingle_hashes(b"q r s t u v w")))
    assert similar.block_keys(similar.shingle_hashes(b"")) == []


def test_rows_are_told_apart_not_ids(spark):
    """Of two texts with one id, only the one that repeats another text goes; of equal rows one stays."""
    rng = random.Random(7)
    one, two, three = (" ".join(f"{x}{rng.randrange(4000)}" for _ in range(80)) for x in "abc")
    rows = [(1, one, "x"), (2, one + " end", "x"), (2, two, "y"), (3, three, "p"), (3, three, "p"), (3, three, "q"), (None, one, "n")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, __row string")
    got = sorted((str(r.doc_id), r.text) for r in simhash.first_of_group(docs).collect())
    assert got == sorted([("1", one), ("2", two), ("3", three), ("None", one)])
    assert simhash.first_of_group(docs).columns == docs.columns
