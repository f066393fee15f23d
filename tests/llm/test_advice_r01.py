
import random
import string

import numpy as np

from rulelattice.llm import exact_dedup, quality_rules, secret_scan, sentence_spans, shingle_join


def jaccard_groups(rows):
    """The smallest id of each component of texts whose five-word shingles are alike at 0.8, by all pairs."""
    def shingles(text):
        words = (text or "").encode().lower().split()
        return {b" ".join(words[i : i + 5]) for i in range(max(1, len(words) - 4))}

    sets = [shingles(t) for _, t in rows]
    label = list(range(len(rows)))

    def top(i):
        while label[i] != i:
            i = label[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            if 5 * len(sets[i] & sets[j]) >= 4 * len(sets[i] | sets[j]):
                a, b = top(i), top(j)
                label[max(a, b)] = min(a, b)
    least = {}
    for i, (d, _) in enumerate(rows):
        least[top(i)] = min(least.get(top(i), d), d)
    return set(least.values())


def edited(rng, words, changes):
    """Words with so many of them replaced, at places far from each other."""
    out = list(words)
    for at in rng.sample(range(5, len(words) - 5, 6), changes):
        out[at] = f"new{rng.randrange(10**9)}"
    return out


def test_pipeline_near_stage_links_alike_texts_only(spark):
    import corpus_pipeline

    rng = random.Random(11)
    rows = []
    for _ in range(12):
        base = [f"w{rng.randrange(3000)}" for _ in range(200)]
        chain = base
        rows.append(base)
        for changes in (1, 3, 4, 5, 8):
            rows.append(edited(rng, base, changes))
        for _ in range(3):
            chain = edited(rng, chain, 3)
            rows.append(chain)
    shared = [f"s{i}" for i in range(60)]
    rows += [[f"w{rng.randrange(3000)}" for _ in range(12)] + shared for _ in range(25)]
    texts = [(i, " ".join(r)) for i, r in enumerate(rows)] + [(900, "one two"), (901, "One  two"), (902, "one three"), (903, ""), (904, None), (905, " ")]
    rng.shuffle(texts)
    docs = spark.createDataFrame(texts, "doc_id long, text string")
    assert {r["doc_id"] for r in corpus_pipeline.near_stage(spark, docs, "").collect()} == jaccard_groups(texts)


def test_pipeline_near_stage_on_given_table(spark):
    import corpus_pipeline

    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    before = exact_dedup.drop_copies(quality_rules.keep_good(docs)).select("doc_id", "text")
    rows = [tuple(r) for r in before.collect()]
    want = jaccard_groups(rows)
    assert len(want) < len(rows)
    assert {r["doc_id"] for r in corpus_pipeline.near_stage(spark, spark.createDataFrame(rows, before.schema), "").collect()} == want


def test_pairs_across_components_in_blocks(monkeypatch):
    rng = np.random.default_rng(3)
    h, root, n = rng.integers(0, 5, 60), rng.integers(0, 4, 60), rng.integers(8, 12, 60)
    th = np.arange(60)
    want = {(i, j) for i in range(60) for j in range(i) if h[i] == h[j] and root[i] != root[j] and 5 * min(n[i], n[j]) >= 4 * max(n[i], n[j])}
    for at_once in (1, 7, 10_000):
        monkeypatch.setattr(shingle_join, "ROWS_AT_ONCE", at_once)
        got = [(max(a, b), min(a, b)) for x, y in shingle_join.across(h, root, th, n) for a, b in zip(x.tolist(), y.tolist(), strict=True)]
        assert len(got) == len(set(got)) and set(got) == want


def test_op7_short_spans_and_scripts_without_blanks(spark):
    short = "Yes. No. Maybe so."
    lines = "\n".join(c * 60 for c in "甲乙丙丁")
    docs = spark.createDataFrame([(1, short), (2, "Well then. " + short), (3, lines), (4, "新しい\n" + lines)], "doc_id long, text string")
    got = {r["doc_id"]: (r["text"], r["n_removed"], r["n_spans"]) for r in sentence_spans.drop_repeats(docs).collect()}
    assert got == {1: (short, 0, 0), 2: ("Well then. ", 3, 1), 3: (lines, 0, 0), 4: ("新しい\n", 4, 1)}


HEX = string.hexdigits[:16]
BASE64 = string.ascii_letters + string.digits + "+/"


def drawn(rng, alphabet, length):
    return "".join(rng.choice(alphabet) for _ in range(length))


def test_op6_named_values_and_upper_case_hex(spark):
    rng = random.Random(4)
    named = [(f"AWS_SECRET_ACCESS_KEY={drawn(rng, BASE64, 40)} end", 22, 62) for _ in range(40)]
    named += [(f"sig={drawn(rng, BASE64[:62], 40)}", 4, 44) for _ in range(40)]
    named += [(f"private_key={drawn(rng, BASE64, 42)}==", 12, 56) for _ in range(40)]
    upper = [(f"id {drawn(rng, HEX.upper(), n)} end", 3, 3 + n) for n in (20, 40, 64) for _ in range(40)]
    rows = [(i, t) for i, (t, _, _) in enumerate(named + upper)]
    got = {r["doc_id"]: r["spans"] for r in secret_scan.scan(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    hits = [got[i] == f"random:{a}:{b}" for i, (_, a, b) in enumerate(named + upper)]
    for at in range(0, len(hits), 40):
        assert sum(hits[at : at + 40]) >= 34, (rows[at], sum(hits[at : at + 40]))


def test_op6_finds_short_keys_and_leaves_words_alone(spark):
    rng = random.Random(8)
    alphabets = (HEX.upper(), string.ascii_lowercase, string.ascii_uppercase + "234567", string.digits + string.ascii_lowercase, string.digits + string.ascii_uppercase, BASE64[:62], BASE64)
    words = "the nation other water people through right little house great before sentence different country between thought picture again animal mother answer".split()
    rows = [drawn(rng, a, n) for a in alphabets for n in (20, 32, 40) for _ in range(60)]
    text = [how(sep.join(rng.sample(words, 4))) for sep, how in (("", str.lower), ("", str.upper), ("_", str.lower), ("_", str.upper), ("/", str.title)) for _ in range(60)]
    text += [f"{rng.randrange(1990, 2030)}-{rng.randrange(10, 13)}-{rng.randrange(10, 29)}/{rng.randrange(10**10, 10**11)}" for _ in range(60)]
    docs = spark.createDataFrame(list(enumerate(rows + text)), "doc_id long, text string")
    got = {r["doc_id"]: r["n_random"] for r in secret_scan.scan(docs).collect()}
    found = [sum(got[i] == 1 for i in range(at, at + 60)) for at in range(0, len(rows), 60)]
    assert min(found) >= 50, found
    assert sum(got[i] > 0 for i in range(len(rows), len(rows) + len(text))) <= 4
