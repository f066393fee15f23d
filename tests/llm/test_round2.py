"""Keys of odd URLs, the randomness battery against plain formulas, very long texts, and the whole pipeline by all pairs."""

import hashlib
import math
import random
import re
import string

import pytest

from rulelattice.llm import bpe, exact_dedup, langid, quality_rules, secret_scan, sentence_spans, shingle_join, warc

# Revisits ------------------------------------------------------------------------------------------------------


def key_of(url):
    url = None if url is None else url.strip(" \t\n\x0b\x0c\r")
    if not url:
        return None
    m = re.match(r"[A-Za-z][A-Za-z0-9+.-]*://([^/?#]*)([^?#]*)(?:\?([^#]*))?", url)
    host = re.sub(":(80|443)$", "", re.sub(r"^www\.", "", m[1].lower())) if m else ""
    if not host:
        return ":" + url.split("#")[0]
    asked = sorted(p for p in (m[3] or "").split("&") if p and not re.match(r"(utm_[a-z]+|ref|fbclid|gclid|sessionid)(=|$)", p))
    return host + m[2].rstrip("/") + ("?" + "&".join(asked) if asked else "")


def resolved(records):
    """Status and response of each revisit, by a look at all records."""
    weak = lambda e: None if e is None else re.sub("^W/", "", e)
    out = []
    for ident, kind, url, ts, etag, seen, _, digest in records:
        if (kind or "").lower() != "revisit":
            continue
        key = key_of(url)
        before = [r for r in records if (r[1] or "").lower() == "response" and key is not None and key_of(r[2]) == key and ts is not None and r[3] is not None and r[3] < ts]
        if not before:
            out.append((ident, key, "no_response", None))
            continue
        full = max(before, key=lambda r: (r[3], r[0]))
        pairs = [(weak(etag), weak(full[4])), (seen, full[5]), (digest, full[7])]
        agreed = next((a == b for a, b in pairs if a is not None and b is not None), None)
        out.append((ident, key, {None: "unchecked", True: "resolved", False: "changed"}[agreed], full[0]))
    return sorted(out)


@pytest.mark.parametrize("width", [1, 7, 1000])
def test_op3_equals_brute_force_on_odd_urls(spark, width):
    rng = random.Random(width)
    urls = ["http://a.org/x", "HTTPS://www.A.org:443/x/", "a.org/x", " a.org/x ", "a.org/x#top", "mailto:x@y", "not a url", "", "  ", None, "http://a.org/x?b=2&a=1&utm_source=q", "http://a.org/x?a=1&b=2#f", "http:///x", "//a.org/x"]
    pick = lambda *xs: rng.choice(xs)
    records = [(i, pick("response", "revisit", "Revisit", "request", None), rng.choice(urls), pick(None, *range(12)), pick(None, '"e"', 'W/"e"', '"f"'), pick(None, "mon", "tue"), pick(None, {"A": "1"}), pick(None, "d1", "d2")) for i in range(300)]
    df = spark.createDataFrame(records, warc.RECORD)
    got = sorted((r["record_id"], r["url_key"], r["status"], r["response_id"]) for r in warc.resolve_revisits(df, width).collect())
    assert got == resolved(records)


# Secrets -------------------------------------------------------------------------------------------------------


def p_value(body, battery):
    plain = re.sub("=+$", "", body).translate(str.maketrans("-_", "+/"))
    if re.fullmatch("[0-9]*", plain):
        return None
    found = next((e for e in secret_scan.ENCODINGS if re.search(e[1], plain)), None)
    if found is None or len(plain) < 2:
        return None
    alphabet, n, k = found[2], len(plain), len(found[2])
    scores, mean, deviation = secret_scan.text_like(alphabet, found[3])
    at = [alphabet.index(c) for c in plain]
    chi = k / n * sum(plain.count(c) ** 2 for c in alphabet) - n
    high = [a >= k / 2 for a in at]
    h = sum(high)
    runs = 1 + sum(a != b for a, b in zip(high, high[1:]))
    expected = 1 + 2 * h * (n - h) / n
    spread = math.sqrt(max((expected - 1) * (expected - 2) / (n - 1), 0))
    serial = sum((a - (k - 1) / 2) * (b - (k - 1) / 2) for a, b in zip(at, at[1:])) / math.sqrt(n - 1) / ((k * k - 1) / 12)
    z = max((n * mean - sum(scores[a] for a in at)) / (deviation * math.sqrt(n)), (chi - (k - 1)) / math.sqrt(2 * (k - 1)) - battery.uneven_margin, (abs(runs - expected) / spread if spread > 0 else 99.0) - battery.runs_margin, abs(serial) - battery.serial_margin)
    return n, math.erfc(-z / math.sqrt(2)) / 2


def added_spans(text, battery):
    base = [(m.start(), m.end()) for shape, group, least in ((secret_scan.ASSIGN, 2, 6), ("AKIA[A-Z0-9]+", 0, 20), ("[0-9a-f]+", 0, 24)) for m in re.finditer(shape, text) if len(m.group(group)) >= least]
    free = [m for m in re.finditer(secret_scan.TOKEN, text) if not any(a < m.end() and m.start() < b for a, b in base)]
    held = [(m, v) for m in free if (v := p_value(m.group(), battery)) is not None]
    if not held:
        return []
    mean = sum(v[0] for _, v in held) / len(held)
    qs = [v[1] * mean / v[0] for _, v in held]
    bound = max((q for i, q in enumerate(sorted(qs), 1) if q <= battery.discovery_rate * i / len(qs)), default=-1)
    return [f"random:{m.start()}:{m.end()}" for (m, _), q in zip(held, qs, strict=True) if q <= bound]


def test_op6_method_spans_equal_plain_formulas(spark):
    rng = random.Random(21)
    alphabets = [string.hexdigits[:16], "0123456789ABCDEF", string.ascii_lowercase, string.ascii_uppercase + "234567", string.ascii_letters + string.digits, string.ascii_letters + string.digits + "+/", "ab", "0123456789"]
    words = "the nation other water people through right little house great before sentence different country between thought".split()

    def token():
        if rng.random() < 0.4:
            return rng.choice(["", "_", "-", "/"]).join(rng.sample(words, 5))
        made = "".join(rng.choice(a) for a in [rng.choice(alphabets)] for _ in range(rng.choice([19, 20, 24, 32, 40, 64, 200])))
        return rng.choice(["", "key=", "token: "]) + made + rng.choice(["", "", "=", "=="])

    texts = [" ".join(token() if rng.random() < 0.5 else rng.choice(words) for _ in range(rng.randint(0, 12))) for _ in range(250)]
    got = {r["doc_id"]: r["spans"] for r in secret_scan.scan(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    found = 0
    for i, t in enumerate(texts):
        mine = [s for s in got[i].split(",") if s.startswith("random")]
        assert mine == added_spans(t, secret_scan.Battery()), (t, got[i])
        found += len(mine)
    assert found > 100


def test_op6_tail_is_accurate(spark):
    from pyspark.sql import functions as F

    rows = spark.createDataFrame([(i / 10,) for i in range(-80, 81)], "z double").select("z", secret_scan.normal_below(F.col("z")).alias("p")).collect()
    for r in rows:
        want = math.erfc(-r["z"] / math.sqrt(2)) / 2
        assert abs(r["p"] - want) < 1e-7 and (r["z"] > 0 or abs(r["p"] - want) < 0.02 * want)


# Very long texts -----------------------------------------------------------------------------------------------


@pytest.fixture(scope="module")
def long_text():
    rng = random.Random(3)
    words = ["".join(rng.choice(string.ascii_lowercase) for _ in range(rng.randint(2, 9))) for _ in range(4000)]
    return " ".join(rng.choice(words) + (".\n" if rng.random() < 0.1 else "") for _ in range(170_000))


def test_texts_of_a_megabyte(spark, long_text):
    assert len(long_text) > 1_000_000
    cut_at = len(long_text) // 2
    rows = [(1, long_text, "en"), (2, "Own start.\n" + long_text[cut_at:], "en"), (2, "Own start.\n" + long_text[cut_at:], "en"), (3, long_text.replace("a", "a", 1) + " end", "de"), (4, None, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    gone = {r["doc_id"]: r for r in sentence_spans.drop_repeats(docs).collect()}
    assert gone[1]["n_removed"] == 0 and gone[3]["n_removed"] >= gone[3]["n_sentences"] - 1 and gone[2]["n_removed"] >= gone[2]["n_sentences"] - 2
    assert {r["doc_id"] for r in shingle_join.one_of_each(docs).collect()} == {1, 2, 4}
    assert {r["doc_id"]: r["n_random"] for r in secret_scan.scan(docs).collect()}[1] == 0
    assert langid.fit(docs).labels == ["en"]  # the sample takes no text of more than LONGEST bytes, here those of 1 and 3
    predicted = {r["doc_id"]: r["lang_pred"] for r in langid.predict(docs, langid.train(["the house", "das Haus"] * 20, ["en", "de"] * 20)).collect()}
    assert predicted[4] == "und" and predicted[1] in ("en", "de")


def test_op10_long_pre_tokens():
    tokens = {bytes([b]) for b in range(256)} | {b"ab", b"ba", b"aab", b"abab", b"baba", b"aaaa"}
    replay = bpe.Replay({t: i for i, t in enumerate(sorted(tokens, key=lambda t: (len(t) > 1, t[::-1])))}, r".+")

    def slowly(word):
        parts = [bytes([b]) for b in word]
        while True:
            best = min(((replay.ranks.get(parts[i] + parts[i + 1], 1 << 40), i) for i in range(len(parts) - 1)), default=(1 << 40, 0))
            if best[0] == 1 << 40:
                return [replay.ranks[p] for p in parts]
            parts[best[1] : best[1] + 2] = [parts[best[1]] + parts[best[1] + 1]]

    rng = random.Random(6)
    for n in (0, 1, 2, 50, 400):
        word = bytes(rng.choice(b"aab") for _ in range(n))
        assert replay.alone(word) == slowly(word)
    whole = bytes(rng.choice(b"ab") for _ in range(200_000))
    flat = replay.alone(whole)
    assert b"".join(replay.bytes_of[i] for i in flat) == whole


# The pipeline --------------------------------------------------------------------------------------------------


def test_pipeline_by_jaccard_over_all_pairs(spark):
    import corpus_pipeline
    from tests.llm.test_advice_r01 import jaccard_groups

    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    good = {r["doc_id"] for r in quality_rules.judge(docs).where("kept").collect()}
    kept = {}
    for r in docs.collect():
        if r["doc_id"] in good:
            key = re.sub("[\x20\x09-\x0d]+", "", r["text"])
            kept[key] = min(kept.get(key, (0, 1 << 60)), (-len(r["text"]), r["doc_id"]))
    stay = {d for _, d in kept.values()}
    want = jaccard_groups([(r["doc_id"], r["text"]) for r in docs.collect() if r["doc_id"] in stay])
    assert {r["doc_id"] for r in corpus_pipeline.run(spark, "/root/testdata/sf0.001").collect()} == want


def test_near_tables_grow_slowly_and_keep_their_recall():
    for texts in (0, 1, 100, 10**5, 10**8, 10**11):
        tables, bits = shingle_join.tables_for(texts)
        assert texts / 2**bits <= shingle_join.CROWD or bits == 4
        assert (1 - (1 - shingle_join.EDGE) ** bits) ** tables <= 1 - shingle_join.RECALL + 1e-12
    assert shingle_join.tables_for(10**11)[0] < 40 * shingle_join.tables_for(10**5)[0]


def test_digests_are_those_of_the_kept_text(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    from rulelattice.llm import registry

    texts = {r["doc_id"]: r for r in sentence_spans.drop_repeats(docs).collect()}
    for r in registry.op7_sentence_spans(spark, "/root/testdata/sf0.001").collect():
        assert r["kept_sha256"] == hashlib.sha256(texts[r["doc_id"]]["text"].encode()).hexdigest()
    assert exact_dedup.drop_copies(docs).count() <= docs.count()
