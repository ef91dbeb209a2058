"""Secret scans: fixed patterns, and strings that a battery of randomness tests can't tell from random ones.

Fixed patterns find assignments, access keys and hexadecimal runs. Beside them, every run of encoding
characters that is long enough and has both letters and digits is a candidate. Its encoding is the
smallest alphabet that holds it, and tests ask whether its symbols are independent and uniform over
that alphabet: chi-squared of the symbol counts and of digits, cases and signs, runs above and below
the middle, and serial correlation at lag one. They give one p-value (Bonferroni). Among the candidates of a length band
the Benjamini-Hochberg rule rejects, at a set false-discovery rate, those that aren't random; the rest
are reported. Bands are powers of two of the length, so short strings, on which the tests have less
power, don't share a threshold with long ones. Everything is DataFrame expressions; only counts by band
and p-value step leave a task.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from contrast.llm.common import bind, materialise

# The patterns of the base rules, and the least length of what must be long enough.
ASSIGN = r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ASSIGN_LEAST = 12
ACCESS = r"AKIA[A-Z0-9]{14,}"
HEX = r"[0-9a-f]{16,}"
#: Words of which an assignment has one, in lower case.
ASSIGN_WORDS = ("passw", "secret", "token", "api")

KINDS = ("assign", "access", "hex", "random")
LEAST = 20
CANDIDATE = rf"(?<![A-Za-z0-9+/_-])(?=[A-Za-z0-9+/_-]{{{LEAST}}})(?=[A-Za-z+/_-]*[0-9])(?=[0-9+/_-]*[A-Za-z])[A-Za-z0-9+/_-]++"
DIGITS, LOWER, UPPER = "0123456789", "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
#: Pattern of a whole string and alphabet, from the smallest.
ENCODINGS = (
    ("hex", "^[0-9a-f]+$", DIGITS + LOWER[:6]),
    ("hex upper", "^[0-9A-F]+$", DIGITS + UPPER[:6]),
    ("base32", "^[A-Z2-7]+$", UPPER + "234567"),
    ("base36", "^[0-9a-z]+$", DIGITS + LOWER),
    ("base36 upper", "^[0-9A-Z]+$", DIGITS + UPPER),
    ("base62", "^[0-9A-Za-z]+$", DIGITS + UPPER + LOWER),
    ("base64", "^[0-9A-Za-z+/_-]+$", UPPER + LOWER + DIGITS + "+/"),
)
#: False-discovery rate of the rejections, and the steps that log10 of a p-value is counted in.
RATE, STEPS, MOST = 0.05, 8, 400
#: Numbers that are summed one by one.
PIECE = 64


def _plus(a: Column, b: Column) -> Column:
    return a + b


def before(values: Column, both=_plus, levels: int = 3) -> Column:
    """For each of an array of numbers from 0 on, the sum (or what else `both` makes of two) of those before it.

    Sums run within pieces of PIECE numbers, and in the same way over the pieces, so that no array
    grows by one number at a time: the work is in proportion to the numbers, as long as they are fewer
    than PIECE to the power of levels.
    """
    none = F.array().cast("array<int>")
    begin = F.struct(F.lit(0).alias("at"), none.alias("out"))

    def summed(piece: Column) -> Column:
        return F.aggregate(piece, begin, lambda a, v: F.struct(both(a["at"], v).alias("at"), F.concat(a["out"], F.array(a["at"])).alias("out")))

    def of(given: Column) -> Column:
        if levels == 1:
            return summed(given)["out"]
        pieces = F.transform(piece_starts(given), lambda k: summed(F.slice(given, k + 1, F.lit(PIECE))))
        shifted = lambda parts, after: F.flatten(F.zip_with(parts, after, lambda p, a: F.transform(p["out"], lambda v: both(v, a))))
        joined = lambda parts: bind(before(F.transform(parts, lambda p: p["at"]), both, levels - 1), lambda after: shifted(parts, after))
        return F.when(F.size(given) <= PIECE, summed(given)["out"]).otherwise(bind(pieces, joined))

    return bind(values, of)


def piece_starts(values: Column) -> Column:
    """Where the pieces of an array begin, from 0; one piece of an empty array."""
    return F.transform(F.sequence(F.lit(0), F.greatest(F.lit(0), F.floor((F.size(values) - 1) / PIECE).cast("int"))), lambda k: k * PIECE)


def found(text: Column, pattern: str, kind: int, least: Column | None = None) -> Column:
    """array of (start, kind, end, token) of the leftmost non-overlapping matches; text must not be null.

    The pieces that a split leaves tell where the matches between them begin. least: lengths, one for
    each match, and those under ASSIGN_LEAST go, after all have been laid out.
    """
    matches = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))

    def laid(x: Column) -> Column:
        """x: the lengths of what stands before each match, and the matches."""
        tokens, gaps = x["tokens"], x["gaps"]
        begins = lambda after: F.zip_with(F.zip_with(after, gaps, lambda a, g: a + g), tokens, lambda at, t: F.struct(at.alias("start"), F.lit(kind).alias("kind"), (at + F.length(t)).alias("end"), t.alias("token")))
        return bind(before(F.zip_with(gaps, tokens, lambda g, t: g + F.length(t))), begins)

    gaps = lambda found: F.transform(F.slice(F.split(text, pattern), 1, F.size(found)), lambda p: F.length(p))
    spans = bind(matches, lambda found: bind(F.struct(gaps(found).alias("gaps"), found.alias("tokens")), laid))
    if least is not None:
        spans = F.transform(F.filter(F.arrays_zip(spans.alias("span"), least.alias("n")), lambda x: x["n"] >= ASSIGN_LEAST), lambda x: x["span"])
    return spans


def base_spans(text: Column) -> Column:
    """The spans of the three fixed patterns, by start and kind; a cheap look first passes most texts by."""
    empty = F.array().cast("array<struct<start:int,kind:int,end:int,token:string>>")
    some = lambda when, spans: F.when(when, spans).otherwise(empty)
    low = F.lower(text)
    named = low.contains(ASSIGN_WORDS[0])
    for word in ASSIGN_WORDS[1:]:
        named |= low.contains(word)
    lengths = F.transform(F.regexp_extract_all(text, F.lit(ASSIGN), F.lit(2)), lambda v: F.length(v))
    return F.array_sort(F.concat(some(named, found(text, ASSIGN, 0, lengths)), some(text.contains("AKIA"), found(text, ACCESS, 1)), some(text.rlike(HEX), found(text, HEX, 2))))


def upper_tail(z: Column) -> Column:
    """P(Z >= z) of a normal variable, by a rational approximation with an error of some 1e-7 of the density."""
    a = F.abs(z)
    t = 1 / (1 + 0.2316419 * a)
    series = t * (0.319381530 + t * (-0.356563782 + t * (1.781477937 + t * (-1.821255978 + t * 1.330274429))))
    tail = F.exp(-a * a / 2) / math.sqrt(2 * math.pi) * series
    return F.when(z >= 0, tail).otherwise(1 - tail)


def gamma_tail(chi: Column, mean: Column, shape: Column) -> Column:
    """Upper tail of a gamma variable: its cube root is nearly normal."""
    return upper_tail((F.pow(chi / mean, F.lit(1 / 3)) - (1 - 1 / (9 * shape))) / F.sqrt(1 / (9 * shape)))


def class_tail(token: Column, alphabet: Column) -> Column:
    """p-value of chi-squared over digits, lower case, upper case and signs, as far as the alphabet has them."""
    share = lambda s, letters: F.length(F.regexp_replace(s, f"[^{letters}]", "")).cast("double")
    cells = F.array(*(F.struct(share(token, c).alias("n"), (share(alphabet, c) / F.length(alphabet)).alias("p")) for c in ("0-9", "a-z", "A-Z", "+/")))

    def of(held: Column) -> Column:
        term = lambda a, x: a + F.pow(x["n"] - F.length(token) * x["p"], F.lit(2.0)) / (F.length(token) * x["p"])
        mean = F.greatest(F.size(held) - 1, F.lit(1)).cast("double")
        return gamma_tail(F.aggregate(held, F.lit(0.0), term), mean, mean / 2)

    return bind(F.filter(cells, lambda x: x["p"] > 0), of)


def battery(token: Column) -> Column:
    """The p-value of a candidate: how likely a random string of its encoding is as odd in one of the ways.

    Chi-squared has its exact mean and variance for few symbols and a gamma tail by cubes. A string
    whose symbols all lie on one side, or are all the same, has the p-value of that.
    """
    token = F.translate(token, "-_", "+/")
    alphabet = None
    for _, pattern, letters in ENCODINGS:
        hit = token.rlike(pattern)
        alphabet = F.when(hit, F.lit(letters)) if alphabet is None else alphabet.when(hit, F.lit(letters))
    alphabet = alphabet.otherwise(F.lit(ENCODINGS[-1][2]))

    def of(x: Column) -> Column:
        """x: token, alphabet, codes."""
        n, k = F.length(x["token"]).cast("double"), F.length(x["alphabet"]).cast("double")
        squares = F.aggregate(F.split(x["alphabet"], ""), F.lit(0.0), lambda a, c: a + F.when(F.length(c) == 0, 0.0).otherwise(F.pow(F.length(x["token"]) - F.length(F.replace(x["token"], c, F.lit(""))), F.lit(2.0))))
        chi, mean = k / n * squares - n, k - 1
        shape = mean * n / (2 * (n - 1))  # of a gamma variable with the same mean and variance
        high = F.transform(x["codes"], lambda c: (2 * c >= k).cast("double"))
        rest = lambda a: F.slice(a, 2, F.size(a))
        most = lambda a: F.slice(a, 1, F.size(a) - 1)
        total = lambda a: F.aggregate(a, F.lit(0.0), lambda s, v: s + v)
        runs = 1 + total(F.zip_with(most(high), rest(high), lambda a, b: F.abs(a - b)))
        n1 = total(high)
        cross = 2 * n1 * (n - n1)
        spread = cross * (cross - n) / (n * n * (n - 1))
        p_runs = F.when(spread > 0, 2 * upper_tail(F.abs(runs - cross / n - 1) / F.sqrt(spread))).otherwise(F.pow(F.lit(2.0), 1 - n))
        lagged = lambda d: F.struct(total(F.zip_with(most(d), rest(d), lambda u, v: u * v)).alias("lagged"), total(F.transform(d, lambda v: v * v)).alias("power"))
        moments = bind(total(x["codes"]) / n, lambda centre: bind(F.transform(x["codes"], lambda c: c - centre), lagged))
        serial = lambda m: F.when(m["power"] > 0, 2 * upper_tail(F.abs(m["lagged"] / m["power"] + 1 / n) * F.sqrt(n))).otherwise(F.lit(0.0))
        p_serial = bind(moments, serial)
        return F.least(F.lit(1.0), 4 * F.least(gamma_tail(chi, mean, shape), class_tail(x["token"], x["alphabet"]), p_runs, p_serial))

    codes = lambda x: F.transform(F.filter(F.split(x["token"], ""), lambda c: F.length(c) > 0), lambda c: (F.position(c, x["alphabet"]) - 1).cast("double"))
    return bind(F.struct(token.alias("token"), alphabet.alias("alphabet")), lambda x: bind(F.struct(x["token"].alias("token"), x["alphabet"].alias("alphabet"), codes(x).alias("codes")), of))


def candidates(text: Column) -> Column:
    """array of (start, kind, end, band, step) of the runs that the battery judges; step counts -log10 p."""
    empty = F.array().cast("array<struct<start:int,kind:int,end:int,band:int,step:int>>")
    band = lambda x: F.floor(F.log2(F.length(x["token"]).cast("double"))).cast("int")
    step = lambda x: F.least(F.lit(MOST), F.floor(-F.log10(F.greatest(battery(x["token"]), F.lit(1e-60))) * STEPS)).cast("int")
    judged = F.transform(found(text, CANDIDATE, 3), lambda x: F.struct(x["start"].alias("start"), x["kind"].alias("kind"), x["end"].alias("end"), band(x).alias("band"), step(x).alias("step")))
    return F.when(text.rlike(CANDIDATE), judged).otherwise(empty)


def rejection_steps(docs: DataFrame, text: str = "text", rate: float = RATE) -> DataFrame:
    """One row, `cuts map<int, int>`: for each length band, the step from which candidates are rejected.

    The Benjamini-Hochberg rule on p-values rounded up to their step; a band in which nothing is
    rejected has no entry. At most MOST + 1 rows of a band meet in one task.
    """
    each = docs.select(F.explode(candidates(F.coalesce(F.col(text), F.lit("")))).alias("c")).groupBy("c.band", "c.step").agg(F.count(F.lit(1)).alias("n"))
    downto = Window.partitionBy("band").orderBy(F.col("step").desc()).rowsBetween(Window.unboundedPreceding, 0)
    tested = each.select("*", F.sum("n").over(downto).alias("above"), F.sum("n").over(Window.partitionBy("band")).alias("all"))
    cut = tested.where(F.pow(F.lit(10.0), -F.col("step") / STEPS) <= rate * F.col("above") / F.col("all")).groupBy("band").agg(F.min("step").alias("step"))
    return cut.agg(F.map_from_entries(F.collect_list(F.struct("band", "step"))).alias("cuts"))


def scanned(docs: DataFrame, text: str = "text", rate: float = RATE) -> DataFrame:
    """docs with `base` and `secrets`: arrays of (start, kind, end), by start and kind.

    Code points, end exclusive; kind is the place in KINDS. `secrets` has the base spans and the
    random strings that touch none of them. A null text is empty. Rows are judged one by one, by
    thresholds that all rows give. Result columns replace columns of their names.
    """
    cuts = materialise(rejection_steps(docs, text, rate), "rejection_steps")
    plain = docs.drop("base", "secrets", "__base", "__more", "__cuts", "__text")
    looked = plain.select("*", F.coalesce(F.col(text), F.lit("")).alias("__text"), cuts.scalar().alias("__cuts"))
    spans = looked.select("*", base_spans(F.col("__text")).alias("__base"), candidates(F.col("__text")).alias("__more"))
    slim = lambda a: F.transform(a, lambda x: F.struct(x["start"].alias("start"), x["kind"].alias("kind"), x["end"].alias("end")))
    free = lambda x: ~F.exists(F.col("__base"), lambda b: (b["start"] < x["end"]) & (b["end"] > x["start"]))
    kept = F.filter("__more", lambda x: free(x) & (x["step"] < F.coalesce(F.try_element_at(F.col("__cuts"), x["band"]), F.lit(MOST + 1))))
    return spans.select("*", slim(F.col("__base")).alias("base"), F.array_sort(F.concat(slim(F.col("__base")), slim(kept))).alias("secrets")).drop("__base", "__more", "__cuts", "__text")


def listed(spans: Column) -> Column:
    """kind:start:end of each, comma-joined."""
    kinds = F.array(*(F.lit(k) for k in KINDS))
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", F.get(kinds, x["kind"]), x["start"].cast("string"), x["end"].cast("string"))), ",")


def count_of(spans: Column, kind: str) -> Column:
    return F.size(F.filter(spans, lambda x: x["kind"] == KINDS.index(kind))).cast("long")


def redacted(text: Column, spans: Column, mark: str = "[secret]") -> Column:
    """text with each span, or overlapping spans together, replaced by a mark; without spans it is unchanged.

    Spans are by start. Stretches of PIECE spans are cut out of the text first and what stays out of these,
    so a text isn't walked from its begin for each span.
    """

    def stretch(marks: Column) -> Column:
        def cut(part: Column) -> Column:
            begin = part[0]["at"]
            own = F.substr(text, begin + 1, F.greatest(F.lit(0), F.element_at(part, -1)["start"] - begin))
            kept = lambda whole: F.transform(part, lambda x: F.when(x["start"] >= x["at"], F.concat(F.substr(whole, x["at"] - begin + 1, x["start"] - x["at"]), F.lit(mark))).otherwise(""))
            return F.array_join(bind(own, kept), "")

        rest = F.substr(text, F.array_max(F.transform(marks, lambda x: x["end"])) + 1)
        return F.concat(F.array_join(F.transform(piece_starts(marks), lambda k: bind(F.slice(marks, k + 1, F.lit(PIECE)), cut)), ""), rest)

    def placed(given: Column) -> Column:
        ends = F.transform(given, lambda x: x["end"])
        return bind(F.zip_with(given, before(ends, F.greatest), lambda x, at: F.struct(x["start"].alias("start"), x["end"].alias("end"), at.alias("at"))), stretch)

    return F.when(F.size(spans) == 0, text).otherwise(bind(spans, placed))
