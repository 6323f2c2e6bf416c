"""Secret scanning with a randomness battery and false-discovery control.

Fixed patterns give the base spans. Every run of LEAST characters or more that
could hold a token, in a base span or clear of them, is tested. An encoding is
inferred from the characters used, and over its alphabet come a chi-squared test
of uniformity, a runs test about the alphabet's middle and a lag-one serial
correlation. Their joint p-value (Fisher) must not reject randomness. Against
the opposite null, that a run is ordinary writing over the same alphabet, two
statistics give the p-value that enters the false-discovery control: the
chi-squared statistic's lower tail, and the runs of one class of character
(digits, small, capital letters), of which ordinary writing has few; these two
are joined the same way. That control is length-aware: p-values are divided by
weights that grow with length, averaging one, and the Benjamini-Hochberg step-up
runs over a histogram of -log10 p with a fixed number of bins, so no sort of all
candidates is needed.

A discovery clear of the base spans is a span of kind `random`; one in a base
span confirms it. Base spans stay, confirmed or not.

Everything is built-in SQL functions. Candidates are written once to the shared
folder; only one threshold reaches the driver.

Defined cases: a null text is empty; an empty text has no spans; repeated rows
give equal results; extra columns, whatever their names, are ignored by the scan
and kept by the redaction; with no candidates the threshold admits none; an
empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from annspark.llm import spans as S
from annspark.llm.rows import packed, unpacked
from annspark.plans.session import stage
from annspark.sources.tables import table

# The contract's three base patterns, in linear-time form.
_KEYWORD = "(?:[Pp][Aa][Ss][Ss][Ww][Oo][Rr][Dd]|[Pp][Aa][Ss][Ss][Ww][Dd]|[Ss][Ee][Cc][Rr][Ee][Tt]|[Tt][Oo][Kk][Ee][Nn]|[Aa][Pp][Ii]_?[Kk][Ee][Yy])"
ASSIGN = _KEYWORD + r"""["']?\x20*+[:=]\x20*+["']?[A-Za-z0-9+/_.=-]++"""
_BEFORE_VALUE = "^" + _KEYWORD + r"""["']?\x20*+[:=]\x20*+["']?"""
BASE = {
    "assign": (ASSIGN, f"length(regexp_replace(m.value, {S._quoted(_BEFORE_VALUE)}, '')) >= 12"),
    "access": (r"AKIA[A-Z0-9]++", "length(m.value) >= 18"),
    "hex": (r"(?<![0-9a-f])[0-9a-f]{16,}+", "true"),
}
#: Least characters of a candidate: a whole run of characters that encodings use.
LEAST = 12
CANDIDATE = rf"(?<![A-Za-z0-9+/_-])[A-Za-z0-9+/_-]{{{LEAST},}}+={{0,2}}+"

# Encodings by the characters used, their alphabets, and how far ordinary
# writing over each is from uniform (alphabet size times the sum of squared frequencies,
# less one). Ordinary numbers are as uniform as random ones.
_LOW, _UP, _DIG = "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789"
ENCODINGS = (
    ("decimal", "^[0-9]+$", _DIG, 0.0),
    ("hex", "^[0-9a-f]+$", _DIG + "abcdef", 0.5),
    ("HEX", "^[0-9A-F]+$", _DIG + "ABCDEF", 0.5),
    ("lower", "^[a-z]+$", _LOW, 0.7),
    ("upper", "^[A-Z]+$", _UP, 0.7),
    ("base32", "^[A-Z2-7]+$", _UP + "234567", 1.1),
    ("base36", "^[0-9a-z]+$", _LOW + _DIG, 1.3),
    ("BASE36", "^[0-9A-Z]+$", _UP + _DIG, 1.3),
    ("letters", "^[A-Za-z]+$", _UP + _LOW, 2.4),
    ("base62", "^[0-9A-Za-z]+$", _UP + _LOW + _DIG, 3.0),
    ("base64", "", _UP + _LOW + _DIG + "+/", 3.2),
)
#: Ordinary writing changes its class of character at most this often between neighbours.
CLASS_CHANGES = 0.15
RANDOM_LEVEL = 0.001
DISCOVERY_RATE = 0.01
#: Histogram of -log10 p: bins of 1/20, 600 of them.
BINS_PER_DECADE, BINS = 20, 600
FULL_LENGTH = 64
KINDS = {"assign": "assign", "access": "access", "hex": "hex"}
MARKS = {k: "[SECRET]" for k in (*KINDS, "random")}

# Coefficients of the normal upper tail (a classic polynomial, error under 1e-7).
_TAIL = (0.319381530, -0.356563782, 1.781477937, -1.821255978, 1.330274429)


def _upper(z: str) -> str:
    """SQL: the chance that a standard normal variable exceeds ``z``, at least 1e-15."""
    t = f"(1 / (1 + 0.2316419D * abs({z})))"
    poly = " + ".join(f"{c}D * pow({t}, {i})" for i, c in enumerate(_TAIL, 1))
    tail = f"(exp(-{z} * {z} / 2) * 0.3989422804014327D * ({poly}))"
    return f"greatest(1e-15D, if({z} >= 0, {tail}, 1 - {tail}))"


def _list(items: list[str]) -> str:
    return f"array({', '.join(items)})"


def battery(candidates: str) -> Column:
    """Each span of ``candidates`` with encoding, n, chi, p_random and p_text."""
    enc = "CASE " + " ".join(f"WHEN t.v RLIKE '{rx}' THEN {i}" for i, (_, rx, *_) in enumerate(ENCODINGS) if rx) + f" ELSE {len(ENCODINGS) - 1} END"
    names, alphabets, deltas = (_list(x) for x in zip(*[(f"'{e}'", f"'{a}'", f"{d}D") for e, _, a, d in ENCODINGS]))
    pairs = "zip_with(slice(t.xs, 1, size(t.xs) - 1), slice(t.xs, 2, size(t.xs) - 1), (x, y) -> {})"
    add = "(a, x) -> a + x"
    classes = f"translate(t.v, '{_UP + _LOW + _DIG}+/', '{'U' * 26 + 'L' * 26 + 'D' * 10}')"
    steps = [
        # The symbols, with the URL-safe forms folded and padding dropped.
        {"start": "t.start", "end": "t.end", "v": "translate(rtrim('=', t.value), '-_', '+/')"},
        {"e": enc, "classes": classes},
        {"n": "double(length(t.v))", "k": f"double(length({alphabets}[t.e]))", "d": f"{deltas}[t.e]", "encoding": f"{names}[t.e]",
         "xs": f"transform(split(t.v, ''), x -> double(locate(x, {alphabets}[t.e]) - 1))",
         "pairs": "greatest(1D, double(length(t.classes)) - 1)", "changes": "greatest(0D, double(regexp_count(t.classes, 'U+|L+|D+')) - 1)"},
        {"chi": "t.k / t.n * aggregate(array_distinct(split(t.v, '')), 0D, (a, x) -> a + pow(double(length(t.v) - length(replace(t.v, x, ''))), 2)) - t.n",
         "n1": "double(size(filter(t.xs, x -> x >= t.k / 2)))",
         "runs": f"1D + aggregate({pairs.format('if((x >= t.k / 2) <> (y >= t.k / 2), 1D, 0D)')}, 0D, {add})",
         "mean": f"aggregate(t.xs, 0D, {add}) / t.n", "often": "t.changes / t.pairs"},
        {"mu": "2 * t.n1 * (t.n - t.n1) / t.n",
         "corr": f"aggregate({pairs.format('(x - t.mean) * (y - t.mean)')}, 0D, {add}) / greatest(1e-9D, aggregate(t.xs, 0D, (a, x) -> a + pow(x - t.mean, 2)))"},
        {"z1": "(pow(t.chi / (t.k - 1), 1D / 3) - 1 + 2D / (9 * (t.k - 1))) / sqrt(2D / (9 * (t.k - 1)))",
         "z2": "if(t.mu > 1, abs(t.runs - 1 - t.mu) / sqrt(t.mu * (t.mu - 1) / (t.n - 1)), 9D)",
         "z3": "abs(t.corr + 1 / t.n) * sqrt(t.n)",
         "zt": "(t.chi - (t.k - 1) - t.n * t.d) / sqrt(2 * (t.k - 1) + 4 * t.n * t.d)",
         # How unlikely so many changes of class are in ordinary writing: the bound by large deviations.
         "rare": f"if(t.often <= {CLASS_CHANGES}D, 0D, t.pairs * (t.often * ln(t.often / {CLASS_CHANGES}D) + if(t.often < 1, (1 - t.often) * ln((1 - t.often) / {1 - CLASS_CHANGES}D), 0D)))"},
        {"s": f"-ln({_upper('t.z1')}) - ln(least(1D, 2 * {_upper('t.z2')})) - ln(least(1D, 2 * {_upper('t.z3')}))", "u": f"t.rare - ln({_upper('(-t.zt)')})"},
        {"p_random": "exp(-t.s) * (1 + t.s + t.s * t.s / 2)", "p_text": "exp(-t.u) * (1 + t.u)"},
    ]
    out, known = f"`{candidates}`", []
    for step in steps:
        known = [f"t.{f} AS {f}" for f in dict.fromkeys(k.split(" AS ")[1] for k in known)]
        out = f"transform({out}, t -> struct({', '.join([*known, *(f'{e} AS {f}' for f, e in step.items())])}))"
        known += [f"t.{f} AS {f}" for f in step]
    fields = ("start", "end", "n", "encoding", "chi", "p_random", "p_text")
    return F.expr(f"transform({out}, t -> struct({', '.join(f't.{f} AS {f}' for f in fields)}))")


def scan(docs: DataFrame) -> DataFrame:
    """doc_id, base (sorted spans) and tested (every candidate, with in_base), for every row."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    return _scanned(rows, "text").select("doc_id", "base", "tested")


def _scanned(rows: DataFrame, text: str) -> DataFrame:
    """``rows`` with base and tested columns."""
    found = S.with_spans(rows, text, BASE | {"candidate": (CANDIDATE, "true")})
    found = found.select(*rows.columns, S.merged(KINDS).alias("base"), battery("candidate").alias("tested"))
    inside = "transform(tested, t -> struct(t.*, exists(base, b -> b.start < t.end AND t.start < b.end) AS in_base))"
    fields = ("start", "end", "n", "encoding", "chi", "p_random", "p_text")
    return found.select(*rows.columns, "base", F.expr(inside.replace("t.*", ", ".join(f"t.{f} AS {f}" for f in fields))).alias("tested"))


def _weight(n: Column, mean: float) -> Column:
    return F.least(n, F.lit(float(FULL_LENGTH))) / F.lit(mean)


def _bin(t_n: Column, p_text: Column, mean: float) -> Column:
    """The histogram bin of a candidate: -log10 of its p-value over its weight."""
    score = -F.log10(F.greatest(p_text, F.lit(1e-300))) + F.log10(_weight(t_n, mean))
    return F.floor(F.least(F.lit(float(BINS)), F.greatest(F.lit(0.0), score * BINS_PER_DECADE))).cast("int")


def threshold(tested: DataFrame, rate: float = DISCOVERY_RATE) -> tuple[float, float]:
    """(mean capped length, least histogram bin accepted) over all candidates in ``tested``."""
    each = tested.select(F.explode("tested").alias("t")).select("t.n", "t.p_random", "t.p_text")
    mean = each.agg(F.avg(F.least("n", F.lit(float(FULL_LENGTH))))).first()[0]
    if mean is None:
        return 1.0, float("inf")
    # Runs that aren't random stay in the count of tests but can't be discoveries.
    bins = each.groupBy(_bin(F.col("n"), F.col("p_text"), mean).alias("bin")).agg(F.count("*").alias("n"), F.count_if(F.col("p_random") >= RANDOM_LEVEL).alias("hits")).collect()
    total, seen, best = sum(b.n for b in bins), 0, float("inf")  # at most BINS + 1 rows
    for b in sorted(bins, key=lambda b: -b.bin):
        seen += b.hits
        if total * 10 ** (-b.bin / BINS_PER_DECADE) <= rate * seen:
            best = float(b.bin)
    return mean, best


def _judged(scanned: DataFrame, mean: float, least: float) -> DataFrame:
    """``scanned`` with found (the tested candidates that are discoveries) and all_spans."""
    own = scanned.columns
    found = F.filter("tested", lambda t: (t["p_random"] >= RANDOM_LEVEL) & (_bin(t["n"], t["p_text"], mean) >= F.lit(least)))
    judged = scanned.select(*own, found.alias("found"))
    extra = F.transform(
        F.filter("found", lambda t: ~t["in_base"]), lambda m: F.struct(m["start"].alias("start"), F.lit(len(KINDS)).alias("k"), m["end"].alias("end"), F.lit("random").alias("kind"))
    )
    return judged.select(*own, "found", F.array_sort(F.concat("base", extra)).alias("all_spans"))


def redact(docs: DataFrame) -> DataFrame:
    """``docs`` with every secret in text replaced by a mark, and n_chars renewed; null texts stay null.

    The rows are written once with their spans and tested runs, so that texts
    are scanned once and not again when the threshold is known.
    """
    rows = docs.select(packed(docs), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    scanned = stage(_scanned(rows, "text").select("row", "base", "tested"), "secret-rows")
    at = _judged(scanned, *threshold(scanned.select("tested"))).select("row", "all_spans")
    found, old = F.size("all_spans") > 0, at["row"]
    marked = at.select("row", "all_spans", F.coalesce(old["text"].cast("string"), F.lit("")).alias("text"))
    marked = marked.select("row", found.alias("found"), F.when(old["text"].isNotNull(), S.replaced("text", "all_spans", MARKS)).alias("text"))
    renewed = {"text": F.col("text"), "n_chars": F.when(F.col("found"), F.length("text").cast("long")).otherwise(old["n_chars"]) if "n_chars" in docs.columns else None}
    return marked.select(*unpacked(marked, docs.columns, renewed))


def op3_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract: doc_id, n_assign, n_access, n_hex, base_sha256, spans.

    Further columns: how many runs were tested, base runs confirmed and runs
    added; and the battery of each run that lies in a base span or is a
    discovery, as encoding:start:end:p_random:p_text:discovery.
    """
    scanned = stage(scan(table(spark, sf_dir, "documents")), "secret-scan")
    mean, least = threshold(scanned.where(F.size("tested") > 0).select("tested"))
    judged = _judged(scanned, mean, least)
    count = lambda kind: F.size(F.filter("base", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    shown = "filter(tested, t -> t.in_base OR array_contains(transform(found, f -> f.start), t.start))"
    each = "concat_ws(':', t.encoding, t.start, t.end, format_string('%.3e', t.p_random), format_string('%.3e', t.p_text), if(array_contains(transform(found, f -> f.start), t.start), 1, 0))"
    return judged.select(
        "doc_id", *[count(k) for k in KINDS], F.sha2(S.joined(F.col("base")), 256).alias("base_sha256"), S.joined(F.col("all_spans")).alias("spans"),
        F.size("tested").cast("long").alias("n_tested"), F.size(F.filter("found", lambda t: t["in_base"])).cast("long").alias("n_confirmed"),
        F.size(F.filter("found", lambda t: ~t["in_base"])).cast("long").alias("n_random"), F.expr(f"array_join(transform({shown}, t -> {each}), ',')").alias("battery"),
    )
