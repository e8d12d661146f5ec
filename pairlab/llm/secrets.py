"""Secret scans in DataFrame functions: fixed patterns, and a battery of randomness tests for all other tokens.

Patterns (kinds assign, access, hex) are matched leftmost and without overlap, kind by kind.  Beyond them
every run of ``least`` or more characters of the base64 alphabets is a token.  Its encoding is inferred from
the characters it uses (ENCODINGS).  The battery has three statistics: chi-squared of the characters' counts, runs (of
character classes, or about the middle of a one-class alphabet) and the serial correlation of neighbours.  Each is
held against two laws:

* Uniform characters of the encoding: the three two-sided p-values, joined by Fisher's method, must not reject it (``fair``).
* Words and identifiers: fewer coincidences, more class runs and less alternation of vowels than they have each give a
  one-sided p-value; Fisher's method joins them to the token's p-value.  The constants below set this law.  Where an encoding has
  ``enough`` tokens that are surely not uniform, their means and spreads of the three scores widen it (never narrow it).

Tokens of one encoding and length class are tested together: the threshold for the p-value controls the false-discovery rate
at ``rate`` (Benjamini and Hochberg) from counts over all documents, binned by a tenth of a decade.  Discoveries that
may be uniform are spans of kind random, unless a base span overlaps.  Decimal numbers are never discovered.

Defined results: null text is empty and has no spans; rows that repeat get equal results; extra columns of any
name stay as they are; an empty table gives an empty result; a text costs in proportion to its length, a token
its length times the alphabet.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pairlab.llm.scratch import materialize

#: The three base patterns; the words of the first in either case.
ASSIGN = (
    "([pP][aA][sS][sS][wW][oO][rR][dD]|[pP][aA][sS][sS][wW][dD]|[sS][eE][cC][rR][eE][tT]|[tT][oO][kK][eE][nN]|[aA][pP][iI]_?[kK][eE][yY])"
    "[\"']?\\x20*[:=]\\x20*[\"']?([A-Za-z0-9+/_.=-]+)"
)
#: Runs are matched whole, so a least length in the pattern drops the same ones as a filter behind it.
ACCESS = "AKIA[A-Z0-9]{12,}"
HEX = "[0-9a-f]{32,}"
KINDS = ("assign", "access", "hex", "random")
#: Letters' chances to coincide twice and three times in words, share of class changes in identifiers, correlation of neighbouring vowels.
COINCIDE, COINCIDE3, CHANGE, VOWELS = 0.066, 0.0055, 0.25, -0.3
STRATA = (24, 32, 48, 64)
TOKEN = "[A-Za-z0-9+/_=-]{%d,}"


def _let(value: Column, body) -> Column:
    """body(value) with value evaluated once."""
    return F.element_at(F.transform(F.array(value), body), 1)


def _upper(z: Column) -> Column:
    """P(normal > z), with a relative error of about 1 % in the tail; null for null."""

    def tail(a: Column) -> Column:
        phi = F.exp(-a * a / 2) * 0.3989422804014327
        far = phi / (a + 1 / (a + 2 / (a + 3 / (a + 4 / (a + 5)))))
        t = 1 / (1 + 0.2316419 * a)
        near = phi * t * (0.319381530 + t * (-0.356563782 + t * (1.781477937 + t * (-1.821255978 + t * 1.330274429))))
        return F.when(a > 3, far).otherwise(near)

    return _let(z, lambda x: F.when(x.isNotNull(), F.greatest(F.when(x >= 0, tail(x)).otherwise(1 - tail(-x)), F.lit(1e-200))))


def _spans(text: Column, found: Column, pattern: str, kind: int, keep) -> Column:
    """array<struct<start,kind,stop>> of the matches that keep(match, second group) accepts in a text in which found holds,
    from the lengths of what lies between matches. They are folded in pieces of 256, so the cost is linear."""
    pieces, match = F.split(text, pattern, -1), F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    group = F.regexp_extract_all(text, F.lit(pattern), F.lit(2)) if kind == 0 else match
    rows = F.zip_with(F.arrays_zip(match.alias("m"), group.alias("g")), F.slice(pieces, 1, F.greatest(F.size(pieces) - 1, F.lit(0))), lambda x, p: F.struct(F.length(p).alias("gap"), F.length(x["m"]).alias("n"), keep(x["m"], x["g"]).alias("ok")))
    empty = F.array().cast("array<struct<start:int,kind:int,stop:int>>")

    def piece(part: Column, start: Column) -> Column:
        return F.aggregate(
            part,
            F.struct(start.alias("at"), empty.alias("out")),
            lambda acc, x: F.struct(
                (acc["at"] + x["gap"] + x["n"]).alias("at"),
                F.when(x["ok"], F.concat(acc["out"], F.array(F.struct((acc["at"] + x["gap"]).alias("start"), F.lit(kind).alias("kind"), (acc["at"] + x["gap"] + x["n"]).alias("stop"))))).otherwise(acc["out"]).alias("out"),
            ),
            lambda acc: acc["out"],
        )

    def walked(parts: Column) -> Column:
        length = F.transform(parts, lambda part: F.aggregate(part, F.lit(0), lambda acc, x: acc + x["gap"] + x["n"]))
        starts = F.aggregate(
            length, F.struct(F.lit(0).alias("at"), F.array().cast("array<int>").alias("out")),
            lambda acc, x: F.struct((acc["at"] + x).alias("at"), F.concat(acc["out"], F.array(acc["at"])).alias("out")), lambda acc: acc["out"],
        )
        return F.flatten(F.zip_with(parts, starts, piece))

    cut = lambda all: F.transform(F.sequence(F.lit(0), F.floor(F.size(all) / 256).cast("int")), lambda k: F.slice(all, k * 256 + 1, F.lit(256)))
    return F.when(found, _let(_let(rows, cut), walked)).otherwise(empty)


def _kind_of(c: Column, classes: str) -> Column:
    return F.instr(F.lit(classes), c) > 0


_LOWER, _CAPS, _DIGITS = "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789"
#: Pattern of the whole token and alphabet; the first that fits is a token's encoding. -_ read as +/, and padding is left out.
ENCODINGS = (
    ("[0-9]+", _DIGITS), ("[0-9a-f]+", _DIGITS + "abcdef"), ("[0-9A-F]+", _DIGITS + "ABCDEF"), ("[A-Z2-7]+", _CAPS + "234567"), ("[a-z]+", _LOWER), ("[A-Z0-9]+", _CAPS + _DIGITS),
    ("[a-z0-9]+", _DIGITS + _LOWER), ("[A-Za-z]+", _CAPS + _LOWER), ("[A-Za-z0-9]+", _DIGITS + _CAPS + _LOWER), (".*", _CAPS + _LOWER + _DIGITS + "+/"),
)
SCORES = ("chi", "runs", "serial")


def _classes(alphabet: str) -> list[float]:
    """Shares of its classes, or halves of a one-class alphabet."""
    share = [sum(c in k for c in alphabet) / len(alphabet) for k in (_LOWER, _CAPS, _DIGITS, "+/")]
    share = [s for s in share if s]
    return share if len(share) > 1 else [0.5, 0.5]


def _table(values: list) -> Column:
    return F.array(*(F.lit(float(v)) for v in values))


def _at(values: list, k: Column) -> Column:
    return F.element_at(_table(values), k + 1)


def _figures(token: Column) -> Column:
    """struct<enc, n, fair (p-value of uniformity), chi, runs, serial (scores against words; null: does not apply)> of a token."""
    text = F.regexp_replace(F.translate(token, "-_", "+/"), "=+", "")
    enc = F.lit(len(ENCODINGS) - 1)
    for k, (pattern, _) in reversed(list(enumerate(ENCODINGS[:-1]))):
        enc = F.when(text.rlike(f"^{pattern}$"), k).otherwise(enc)
    chars = F.filter(F.split(text, ""), lambda c: c != "")
    squares = lambda items: F.aggregate(F.array_distinct(items), F.lit(0.0), lambda acc, c: acc + F.pow(F.size(F.filter(items, lambda y: y == c)).cast("double"), F.lit(2)))
    total = lambda items: F.aggregate(items, F.lit(0.0), lambda acc, y: acc + y)
    pairs = lambda items, f: F.zip_with(F.slice(items, 1, F.greatest(F.size(items) - 1, F.lit(0))), F.slice(items, 2, F.size(items)), f)
    share = [_classes(a) for _, a in ENCODINGS]
    many = [len([s for s in (_LOWER, _CAPS, _DIGITS, "+/") if set(s) & set(a)]) > 1 for _, a in ENCODINGS]
    turn = [1 - sum(q * q for q in s) for s in share]
    twice = [1 - 2 * sum(q * q for q in s) + sum(q**3 for q in s) - p * p for s, p in zip(share, turn)]  # covariance of neighbouring turns

    def counted(x: Column) -> Column:
        chars, enc = x["chars"], x["enc"]
        order = F.element_at(F.array(*(F.lit(a) for _, a in ENCODINGS)), enc + 1)
        return F.struct(
            enc.alias("enc"), F.size(chars).cast("double").alias("n"), F.length(order).cast("double").alias("a"), squares(chars).alias("squares"), squares(F.transform(chars, F.lower)).alias("folded"),
            F.transform(chars, lambda c: F.instr(order, c) - (F.length(order) + 1) / 2).alias("codes"),
            F.transform(chars, lambda c: F.when(_kind_of(c, _LOWER), 1).when(_kind_of(c, _CAPS), 2).when(_kind_of(c, _DIGITS), 3).otherwise(4)).alias("kind"),
            F.transform(chars, lambda c: _kind_of(F.lower(c), "aeiouy").cast("double")).alias("vowel"),
        )

    def summed(x: Column) -> Column:
        codes, vowel = x["codes"], x["vowel"]
        classes = F.element_at(F.array(*map(F.lit, many)), x["enc"] + 1)
        return F.struct(
            *(x[k].alias(k) for k in ("enc", "n", "a", "squares", "folded")), classes.alias("many"),
            F.when(classes, total(pairs(x["kind"], lambda y, z: (y != z).cast("double")))).otherwise(total(pairs(codes, lambda y, z: ((y > 0) != (z > 0)).cast("double")))).alias("turns"),
            total(pairs(codes, lambda y, z: y * z)).alias("lagged"), F.size(F.filter(x["kind"], lambda y: y <= 2)).alias("letters"), (total(vowel) / x["n"]).alias("share"),
            total(pairs(vowel, lambda y, z: y * z)).alias("together"), (total(vowel) * 2 - F.element_at(vowel, 1) - F.element_at(vowel, -1)).alias("ends"),
        )

    def tested(x: Column) -> Column:
        n, a, share, enc = x["n"], x["a"], x["share"], x["enc"]
        # against uniform characters
        spread = 2 / (9 * (a - 1))
        chi = (F.pow(F.greatest((a * x["squares"] / n - n) / (a - 1), F.lit(0.0)), F.lit(1 / 3)) - (1 - spread)) / F.sqrt(spread)
        p = _at(turn, enc)
        runs = (x["turns"] - (n - 1) * p) / F.sqrt(F.greatest((n - 1) * p * (1 - p) + 2 * (n - 2) * _at(twice, enc), F.lit(1e-9)))
        serial = x["lagged"] / ((a * a - 1) / 12 * F.sqrt(n - 1))
        # against words
        deviation = F.sqrt(2 * n * n * COINCIDE + 4 * n * n * n * (COINCIDE3 - COINCIDE * COINCIDE))
        changes = (x["turns"] - 0.5 - (n - 1) * CHANGE) / F.sqrt((n - 1) * CHANGE * (1 - CHANGE))
        product = x["together"] - share * x["ends"] + (n - 1) * share * share
        vowels = (product / (n * share * (1 - share)) - VOWELS) * F.sqrt(n)
        return F.struct(
            enc.alias("enc"), n.cast("int").alias("n"), _fisher(*(2 * _upper(F.abs(z)) for z in (chi, runs, serial))).alias("fair"), ((n + n * (n - 1) * COINCIDE - x["folded"]) / deviation).alias("chi"),
            F.when(x["many"], changes).alias("runs"), F.when((share > 0) & (share < 1) & (2 * x["letters"] > n), vowels).alias("serial"),
        )

    none = F.lit(None).cast("struct<enc:int,n:int,fair:double,chi:double,runs:double,serial:double>")
    some = _let(_let(_let(F.struct(chars.alias("chars"), enc.alias("enc")), counted), summed), tested)
    return F.when(F.length(text) >= 4, some).otherwise(none)


def _fisher(*p: Column) -> Column:
    """Joint p-value of independent p-values of which the null ones do not count."""
    half, k = F.lit(0.0), F.lit(0)
    for x in p:
        half, k = half - F.coalesce(F.log(F.least(x, F.lit(1.0))), F.lit(0.0)), k + x.isNotNull().cast("int")
    value = lambda h: F.exp(-h["h"]) * F.when(h["k"] == 3, 1 + h["h"] + h["h"] * h["h"] / 2).when(h["k"] == 2, 1 + h["h"]).otherwise(1.0)
    return _let(F.struct(half.alias("h"), k.alias("k")), value)


def _stratum(n: Column) -> Column:
    out = F.lit(len(STRATA))
    for k, upto in reversed(list(enumerate(STRATA))):
        out = F.when(n < upto, k).otherwise(out)
    return out


def _word_p(f: Column, law: dict[int, list[float]]) -> Column:
    """p-value against words; law: (centre, scale) of each score by encoding, one list of six numbers."""
    plain = [0.0, 1.0] * len(SCORES)
    of = lambda k: _at([law.get(e, plain)[k] for e in range(len(ENCODINGS))], f["enc"])
    return F.when(f["enc"] > 0, _fisher(*(_upper((f[s] - of(2 * k)) / of(2 * k + 1)) for k, s in enumerate(SCORES)))).otherwise(1.0)


def fit(docs: DataFrame, rate: float = 0.01, least: int = 20, enough: int = 50) -> tuple[dict[int, list[float]], list[float]]:
    """The words' law by encoding, and the largest p-value that counts as a discovery by encoding and length class (flat);
    both from the tokens of all documents."""
    pattern = TOKEN % least
    text = F.coalesce("text", F.lit(""))
    tokens = docs.filter(text.rlike(pattern)).select(F.explode(F.regexp_extract_all(text, F.lit(pattern), F.lit(0))).alias("token"))
    tokens = materialize(tokens.select(_figures(F.col("token")).alias("f")).filter("f is not null").select("f.*"), "tokens")
    odd = tokens.filter("fair < 1e-3").groupBy("enc").agg(F.count("*").alias("n"), *(f(s).alias(f"{s}_{k}") for s in SCORES for k, f in (("c", F.avg), ("s", F.stddev_samp))))
    law = {r["enc"]: [y for s in SCORES for y in (max(0.0, r[f"{s}_c"] or 0.0), max(1.0, r[f"{s}_s"] or 0.0))] for r in odd.collect() if r["n"] >= enough}  # ten encodings
    cell = F.col("enc") * (len(STRATA) + 1) + _stratum(F.col("n"))
    f = F.struct("enc", *SCORES)
    bins = tokens.select(cell.alias("cell"), _word_p(f, law).alias("p")).groupBy("cell", F.floor(F.least(-F.log10(F.greatest("p", F.lit(1e-30))), F.lit(30.0)) * 10).cast("int").alias("bin")).agg(F.count("*").alias("c"))
    counts: dict[int, dict[int, int]] = {}
    for r in bins.collect():  # at most fifty classes of 301 bins
        counts.setdefault(r["cell"], {})[r["bin"]] = r["c"]
    out = [0.0] * (len(ENCODINGS) * (len(STRATA) + 1))
    for k, by in counts.items():
        every, seen = sum(by.values()), 0
        for b in sorted(by, reverse=True):
            seen += by[b]
            if every * 10 ** (-b / 10) <= rate * seen:
                out[k] = 10 ** (-b / 10)
    return law, out


def scan(docs: DataFrame, rate: float = 0.01, least: int = 20, fair: float = 1e-4) -> DataFrame:
    """row (a struct of all columns of docs), base and found: arrays of struct<start, kind (place in KINDS), stop> by start,
    then kind; base holds the patterns' spans, found also those of the tests."""
    law, limit = fit(docs, rate, least)
    text = F.coalesce("text", F.lit(""))
    pattern = TOKEN % least
    assign = _spans(text, text.rlike("[pP][aA][sS][sS][wW]|[sS][eE][cC][rR][eE][tT]|[tT][oO][kK][eE][nN]|[aA][pP][iI]_?[kK][eE][yY]"), ASSIGN, 0, lambda m, g: F.length(g) >= 8)
    access = _spans(text, text.contains("AKIA"), ACCESS, 1, lambda m, g: F.lit(True))
    hexed = _spans(text, text.rlike("[0-9a-f]{32}"), HEX, 2, lambda m, g: F.lit(True))

    def random(m: Column, g: Column) -> Column:
        judged = lambda f: F.coalesce((_word_p(f, law) <= _at(limit, f["enc"] * (len(STRATA) + 1) + _stratum(f["n"]))) & (f["fair"] >= fair), F.lit(False))
        return _let(_figures(m), judged)

    more = _spans(text, text.rlike(pattern), pattern, 3, random)
    out = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("row"), F.array_sort(F.concat(assign, access, hexed)).alias("base"), more.alias("more"))
    free = F.filter("more", lambda s: ~F.exists("base", lambda b: (b["start"] < s["stop"]) & (s["start"] < b["stop"])))
    return out.select("row", "base", F.when(F.size("more") == 0, F.col("base")).otherwise(F.array_sort(F.concat("base", free))).alias("found"))


def _joined(spans: str) -> Column:
    kinds = F.array(*map(F.lit, KINDS))
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.element_at(kinds, s["kind"] + 1), s["start"].cast("string"), s["stop"].cast("string"))), ",")


def digests(docs: DataFrame, **options) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base_sha256, spans, n_random of every document."""
    found = scan(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), **options)
    count = lambda k, c="base": F.size(F.filter(c, lambda s: s["kind"] == k)).cast("long")
    return found.select("row.doc_id", count(0).alias("n_assign"), count(1).alias("n_access"), count(2).alias("n_hex"), F.sha2(_joined("base"), 256).alias("base_sha256"), _joined("found").alias("spans"), count(3, "found").alias("n_random"))


def redact(docs: DataFrame, mask: str = "[secret]", **options) -> DataFrame:
    """docs with every found span of text replaced by mask (overlapping spans by one); all other columns as they are."""
    found = scan(docs, **options)
    text = F.col("row.text")
    cut = F.aggregate(
        "found",
        F.struct(F.lit(0).alias("at"), F.array().cast("array<string>").alias("out")),
        lambda acc, s: F.struct(
            F.greatest(acc["at"], s["stop"]).alias("at"),
            F.when(s["start"] >= acc["at"], F.concat(acc["out"], F.array(F.substring(text, acc["at"] + 1, s["start"] - acc["at"]), F.lit(mask)))).otherwise(acc["out"]).alias("out"),
        ),
        lambda acc: F.array_join(F.concat(acc["out"], F.array(F.substring(text, acc["at"] + 1, F.length(text)))), ""),
    )
    clean = F.when(F.size("found") == 0, text).otherwise(cut)
    return found.select(*(clean.alias(c) if c == "text" else F.col(f"row.`{c}`") for c in docs.columns))
