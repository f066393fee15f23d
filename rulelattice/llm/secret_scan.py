"""Secret scan: three base patterns, and a battery of randomness tests for other tokens.

A token is a run of 20 or more characters of the base64 alphabets, with the ``=`` that pad it, that no
base span touches; an ``=`` inside, as after a name, parts two tokens. Its encoding is inferred from
the characters it uses. Three tests look at its symbols:

* chi-squared uniformity over the alphabet;
* the Wald-Wolfowitz runs test above and below the alphabet's middle;
* lag-one serial correlation.

A token is a secret if it is unlike ordinary text and like random symbols by each test. Each of these claims
has a p-value: that of ordinary text is how seldom tokens of that length are so much likelier as evenly drawn
symbols (the log-likelihood ratio, whose mean and deviation grow with the length); those of the three tests are
of being ``Battery``'s margin or more away from random, in standard deviations of the test. Where all claims must
hold, the largest of the four is the token's p-value. Over the tokens of a document the
false-discovery rate is controlled by the weighted Benjamini-Hochberg step-up, with weights in proportion to
the lengths. Only built-in column functions are used, and positions are counted in code points.

Edge cases: a null text is empty and has no span; repeated rows are scanned each; overlapping spans
are all listed, and merged where a text is masked; an empty table gives an empty result.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rulelattice.llm.common import let

#: The base patterns in the order in which their kinds are listed.
ASSIGN = r"""([Pp][Aa][Ss][Ss][Ww][Oo][Rr][Dd]|[Pp][Aa][Ss][Ss][Ww][Dd]|[Ss][Ee][Cc][Rr][Ee][Tt]|[Tt][Oo][Kk][Ee][Nn]|[Aa][Pp][Ii]_?[Kk][Ee][Yy])["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ASSIGN_LENGTH = 6
ACCESS = "AKIA[A-Z0-9]{16,}"
HEX = "[0-9a-f]{24,}"
TOKEN = "[A-Za-z0-9+/_-]{20,}(?:=+(?![A-Za-z0-9+/_=-]))?|[A-Za-z0-9+/_-]{19}=+(?![A-Za-z0-9+/_=-])|[A-Za-z0-9+/_-]{18}==+(?![A-Za-z0-9+/_=-])"
KINDS = ("assign", "access", "hex", "random")
#: Letters in ordinary text, in thousandths: half as in the documents at sf0.1, half as in Python's English help, 5 at least.
LETTERS = dict(zip("abcdefghijklmnopqrstuvwxyz", (78, 16, 30, 35, 152, 17, 14, 61, 72, 5, 5, 36, 16, 95, 66, 15, 5, 62, 58, 104, 30, 6, 9, 6, 11, 5), strict=True))
#: Alphabets of the encodings, with the shares of lower-case and upper-case letters, digits
#: and marks that a token made of ordinary words or numbers has in them.
ENCODINGS = (
    ("hex", "^[0-9a-f]*[0-9][0-9a-f]*$", "0123456789abcdef", (0.05, 0, 0.95, 0)),
    ("upper_hex", "^[0-9A-F]*[0-9][0-9A-F]*$", "0123456789ABCDEF", (0, 0.05, 0.95, 0)),
    ("lower", "^[a-z]+$", "abcdefghijklmnopqrstuvwxyz", (1, 0, 0, 0)),
    ("base32", "^[A-Z2-7]+$", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567", (0, 0.9, 0.1, 0)),
    ("lower_digits", "^[0-9a-z]+$", "0123456789abcdefghijklmnopqrstuvwxyz", (0.9, 0, 0.1, 0)),
    ("upper_digits", "^[0-9A-Z]+$", "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZ", (0, 0.9, 0.1, 0)),
    ("lower_marks", "^[0-9a-z+/]*[a-z][0-9a-z+/]*$", "0123456789abcdefghijklmnopqrstuvwxyz+/", (0.75, 0, 0.1, 0.15)),
    ("upper_marks", "^[0-9A-Z+/]*[A-Z][0-9A-Z+/]*$", "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZ+/", (0, 0.75, 0.1, 0.15)),
    ("alphanumeric", "^[0-9A-Za-z]+$", "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz", (0.7, 0.2, 0.1, 0)),
    ("base64", "^[0-9A-Za-z+/]+$", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/", (0.55, 0.2, 0.1, 0.15)),
)


def text_like(alphabet: str, shares: tuple[float, ...]) -> tuple[list[float], float, float]:
    """Log of how much likelier each symbol is in a random token than in ordinary text, and in text its mean and deviation."""
    kinds = [0 if x.islower() else 1 if x.isupper() else 2 if x.isdigit() else 3 for x in alphabet]
    weights = [LETTERS.get(x.lower(), 1) for x in alphabet]
    sums = [sum(w for w, k in zip(weights, kinds, strict=True) if k == kind) for kind in range(4)]
    seen = [shares[k] * w / sums[k] for w, k in zip(weights, kinds, strict=True)]
    scores = [-math.log(len(alphabet) * f) for f in seen]
    mean = sum(f * x for f, x in zip(seen, scores, strict=True))
    return scores, mean, math.sqrt(sum(f * (x - mean) ** 2 for f, x in zip(seen, scores, strict=True)))


@dataclass(frozen=True)
class Battery:
    #: Share of false ones among the tokens found in a document.
    discovery_rate: float = 0.001
    #: Standard deviations from a random token at which each test takes one as not random.
    uneven_margin: float = 7.1
    runs_margin: float = 6.4
    serial_margin: float = 6.4


#: Elements that a running sum adds one by one; longer arrays are summed in blocks of so many.
BLOCK = 256


def starts_of(lengths: Column) -> Column:
    """Sum of all elements before each one; no element is added more than ``BLOCK`` times."""
    def total(a: Column) -> Column:
        return F.aggregate(a, F.lit(0), lambda x, y: x + y)

    def with_blocks(n: Column, sums: Column) -> Column:
        before = F.transform(F.sequence(F.lit(0), F.size(sums) - 1), lambda b: total(F.slice(sums, 1, b)))
        return let(before, lambda done: F.transform(F.sequence(F.lit(0), n - 1), lambda i: F.get(done, F.floor(i / BLOCK).cast("int")) + total(F.slice(lengths, (F.floor(i / BLOCK) * BLOCK + 1).cast("int"), (i % BLOCK).cast("int")))))

    n = F.size(lengths)
    blocks = F.transform(F.sequence(F.lit(0), F.floor((n - 1) / BLOCK).cast("int")), lambda b: total(F.slice(lengths, b * BLOCK + 1, BLOCK)))
    return F.when(n == 0, F.array().cast("array<int>")).otherwise(let(blocks, lambda sums: with_blocks(n, sums)))


_SPAN = "struct<start:int,kind:int,end:int,body:string>"


def _nothing() -> Column:
    return F.array().cast(f"array<{_SPAN}>")


def matches(text: Column, pattern: str, kind: int, group: int = 0) -> Column:
    """Structs (start, kind, end, body) of a pattern's matches; body is the asked group."""
    shape = F.lit(pattern)

    def placed(parts: Column) -> Column:
        steps = F.zip_with(parts["gaps"], parts["found"], lambda g, m: F.length(g) + F.coalesce(F.length(m), F.lit(0)))
        def spans(at: Column) -> Column:
            made = F.transform(parts["found"], lambda m, i: F.struct((F.get(at, i) + F.length(F.get(parts["gaps"], i))).alias("start"), F.lit(kind).alias("kind"), (F.get(at, i) + F.length(F.get(parts["gaps"], i)) + F.length(m)).alias("end"), F.get(parts["bodies"], i).alias("body")))
            return made.cast(f"array<{_SPAN}>")
        return let(steps, lambda s: let(starts_of(s), spans))

    parts = F.struct(F.split(text, pattern).alias("gaps"), F.regexp_extract_all(text, shape, F.lit(0)).alias("found"), F.regexp_extract_all(text, shape, F.lit(group)).alias("bodies"))
    return F.when(F.rlike(text, shape), let(parts, placed)).otherwise(_nothing())


def base_spans(text: Column) -> Column:
    assign = F.filter(matches(text, ASSIGN, 0, 2), lambda s: F.length(s["body"]) >= ASSIGN_LENGTH)
    return F.sort_array(F.concat(assign, matches(text, ACCESS, 1), matches(text, HEX, 2)))


#: Coefficients of a published approximation of the normal distribution's tail (error under 7.5e-8).
TAIL = (0.319381530, -0.356563782, 1.781477937, -1.821255978, 1.330274429)


def normal_below(z: Column) -> Column:
    """Standard normal distribution function, accurate in the lower tail in proportion to its size."""
    def of(t: Column) -> Column:
        poly = F.lit(0.0)
        for c in reversed(TAIL):
            poly = (poly + c) * t
        return F.exp(-z * z / 2) / math.sqrt(2 * math.pi) * poly

    return let(1 / (1 + 0.2316419 * F.abs(z)), lambda t: F.when(z < 0, of(t)).otherwise(1 - of(t)))


def token_tests(body: Column, battery: Battery) -> Column:
    """Struct (n, p) of a token: symbols and combined p-value; null where no encoding fits."""
    plain = F.translate(F.regexp_replace(body, "=+$", ""), "-_", "+/")
    chosen = None
    for _, shape, alphabet, shares in ENCODINGS:
        scores, mean, deviation = text_like(alphabet, shares)
        row = F.struct(plain.alias("s"), F.lit(alphabet).alias("a"), F.lit(float(len(alphabet))).alias("k"), F.array(*map(F.lit, scores)).alias("w"), F.lit(mean).alias("m"), F.lit(deviation).alias("d"))
        fits = F.rlike(plain, F.lit(shape))
        chosen = F.when(fits, row) if chosen is None else chosen.when(fits, row)
    chosen = F.when(F.rlike(plain, F.lit("^[0-9]*$")), F.lit(None)).otherwise(chosen)

    def tested(c: Column) -> Column:
        n = F.length(c["s"]).cast("double")
        counts = F.transform(F.split(c["a"], ""), lambda x: n - F.length(F.replace(c["s"], x, F.lit(""))))
        squares = F.aggregate(counts, F.lit(0.0), lambda a, x: a + x * x)
        places = F.transform(F.split(c["s"], ""), lambda x: (F.instr(c["a"], x) - 1).cast("double"))

        def ordered(v: Column) -> Column:
            x, k = v["x"], c["k"]
            chi = k / n * v["sq"] - n
            free = k - 1
            likelier = F.aggregate(x, F.lit(0.0), lambda a, y: a + F.get(c["w"], y.cast("int")))
            high = F.aggregate(x, F.lit(0.0), lambda a, y: a + F.when(y >= k / 2, 1.0).otherwise(0.0))
            runs = 1 + F.aggregate(F.transform(x, lambda y, i: F.when((i > 0) & ((y >= k / 2) != (F.get(x, F.greatest(i - 1, F.lit(0))) >= k / 2)), 1.0).otherwise(0.0)), F.lit(0.0), lambda a, y: a + y)
            serial = F.aggregate(F.transform(x, lambda y, i: F.when(i > 0, (y - free / 2) * (F.get(x, F.greatest(i - 1, F.lit(0))) - free / 2)).otherwise(0.0)), F.lit(0.0), lambda a, y: a + y)

            def closed(r: Column) -> Column:
                mean = 1 + 2 * r["high"] * (n - r["high"]) / n
                spread = F.sqrt((mean - 1) * (mean - 2) / (n - 1))
                runs_off = F.when(spread > 0, F.abs(r["runs"] - mean) / spread).otherwise(F.lit(99.0))
                claims = F.array(
                    (n * c["m"] - r["likelier"]) / (c["d"] * F.sqrt(n)),
                    (r["chi"] - free) / F.sqrt(2 * free) - battery.uneven_margin,
                    runs_off - battery.runs_margin,
                    F.abs(r["serial"] / F.sqrt(n - 1) / ((k * k - 1) / 12)) - battery.serial_margin,
                )
                return F.struct(n.alias("n"), let(F.array_max(claims), normal_below).alias("p"))
            return let(F.struct(chi.alias("chi"), likelier.alias("likelier"), high.alias("high"), runs.alias("runs"), serial.alias("serial")), closed)

        return let(F.struct(squares.alias("sq"), places.alias("x")), ordered)

    return let(chosen, lambda c: F.when(c.isNotNull() & (F.length(c["s"]) >= 2), tested(c)))


def random_spans(text: Column, base: Column, battery: Battery) -> Column:
    free = F.filter(matches(text, TOKEN, 3), lambda t: ~F.exists(base, lambda b: (b["start"] < t["end"]) & (t["start"] < b["end"])))
    scored = F.transform(free, lambda t: F.struct(t.alias("t"), token_tests(t["body"], battery).alias("v")))
    valid = F.filter(scored, lambda s: s["v"].isNotNull())

    def discovered(all_: Column) -> Column:
        m = F.size(all_)
        mean = F.aggregate(all_, F.lit(0.0), lambda a, s: a + s["v"]["n"]) / m
        def weighted(mean_: Column) -> Column:
            return F.transform(all_, lambda s: F.struct((s["v"]["p"] * mean_ / s["v"]["n"]).alias("q"), s.alias("s")))
        def stepped(ws: Column) -> Column:
            qs = F.sort_array(F.transform(ws, lambda w: w["q"]))
            bound = let(qs, lambda q: F.array_max(F.transform(q, lambda x, i: F.when(x <= battery.discovery_rate * (i + 1) / m, x))))
            return let(bound, lambda b: F.filter(ws, lambda w: w["q"] <= b))
        chosen = let(mean, lambda v: let(weighted(v), stepped))
        return F.transform(chosen, lambda w: w["s"]["t"])

    return let(valid, lambda v: F.when(F.size(v) > 0, discovered(v)).otherwise(_nothing()))


def scanned(text: Column, battery: Battery) -> Column:
    """Struct of the base spans and of all spans, each in order."""
    def both(base: Column) -> Column:
        added = random_spans(text, base, battery)
        return F.struct(base.alias("base"), F.sort_array(F.concat(base, added)).alias("all"))
    return let(base_spans(text), both)


def spelt(spans: Column) -> Column:
    names = F.array(*map(F.lit, KINDS))
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.get(names, s["kind"]), s["start"].cast("string"), s["end"].cast("string"))), ",")


def scan(docs: DataFrame, battery: Battery = Battery(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document with counts by kind, a digest of the base spans, and all spans."""
    found = docs.select(F.col(id_col), scanned(F.coalesce(F.col(text_col), F.lit("")), battery).alias("_s"))

    def closed(s: Column) -> Column:
        count = lambda k: F.size(F.filter(s["all"], lambda x: x["kind"] == k)).cast("long")
        return F.struct(*[count(i).alias(f"n_{k}") for i, k in enumerate(KINDS)], F.sha2(spelt(s["base"]), 256).alias("base_sha256"), spelt(s["all"]).alias("spans"))

    return found.select(id_col, let(F.col("_s"), closed).alias("_r")).select(id_col, "_r.*")


def masked_text(text: Column, spans: Column) -> Column:
    """The text with every span, overlapping ones as one, replaced by ``[SECRET]``."""
    start = F.struct(F.lit(0).alias("at"), F.array().cast("array<string>").alias("parts"))

    def step(state: Column, s: Column) -> Column:
        fresh = s["start"] >= state["at"]
        piece = F.array(F.substr(text, state["at"] + 1, F.greatest(s["start"] - state["at"], F.lit(0))), F.lit("[SECRET]"))
        return F.struct(F.greatest(state["at"], s["end"]).alias("at"), F.when(fresh, F.concat(state["parts"], piece)).otherwise(state["parts"]).alias("parts"))

    return let(F.aggregate(spans, start, step), lambda done: F.concat(F.array_join(done["parts"], ""), F.substr(text, done["at"] + 1)))


def mask(docs: DataFrame, battery: Battery = Battery(), text_col: str = "text") -> DataFrame:
    """All documents with their columns; secrets in the text are masked, a null text stays null."""
    text = F.col(text_col)
    clean = let(scanned(F.coalesce(text, F.lit("")), battery), lambda s: F.when(text.isNull() | (F.size(s["all"]) == 0), text).otherwise(masked_text(text, s["all"])))
    return docs.withColumn(text_col, clean)
