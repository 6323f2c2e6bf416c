"""Personal data: fixed patterns, and bootstrapped contextual extraction.

Fixed patterns give the base spans. They are also the seeds: what stands around
each seed induces lexical patterns of four forms (one word before it, two words
before it, the words on both sides, and a label with its punctuation).
Identifier-like tokens that the fixed patterns miss (other ways to write numbers
and addresses, told apart by shape) stand in such contexts too. Patterns and
instances form a bipartite graph that Spark scores in rounds: a pattern's
confidence is the mean score of the distinct instances it introduces that have
one, times its precision, the share of all its occurrences in the corpus that
introduce an instance of that kind; an instance's score is a noisy-or over its
confident patterns. Seeds keep score one. Tokens of the right shape behind a
confident pattern become spans of kind `found_<kind>`.

Only patterns that introduce at least MIN_SEEDS different seeds and instances of
a confident score are scored, so copies of one document add nothing; each round
admits those that have got so many. Precision is bounded first: a pattern's
occurrences in the texts that hold any instance are at most those in the corpus,
so a pattern that is too common there is settled by that bound, and only what
remains is counted over all texts. The graph has one row for each pattern and
instance, whatever their occurrences, which also levels hot keys. Everything is
built-in SQL functions; tables of a round are written to the shared folder.

Defined cases: a null text is empty; repeated rows give equal results; rows
without a doc_id are treated like others; with no confident pattern nothing is
added; extra columns, whatever their names, are ignored by the scan and kept by
the redaction; an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from annspark.llm import spans as S
from annspark.llm.rows import packed, unpacked
from annspark.plans.session import stage
from annspark.plans.skew import join_hot_apart
from annspark.sources.tables import table

# The contract's four base patterns, in linear-time form.
_DIGITS = "length(regexp_replace(m.value, '[^0-9]', ''))"
EMAIL = r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++"
IP = r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++"
CARD = r"(?<![0-9])(?<![0-9][\x20-])[0-9](?:[\x20-]?[0-9]){11,18}+(?![\x20-]?[0-9])"
PHONE = r"\+[0-9][\x20().0-9-]+[0-9]"
BASE = {
    "email": (EMAIL, "true"),
    "ip": (IP, "forall(split(m.value, '[.]'), p -> length(ltrim('0', p)) <= 3 AND coalesce(try_cast(right(concat('000', ltrim('0', p)), 3) AS int), 0) <= 255)"),
    "card": (CARD, r"luhn_check(regexp_replace(m.value, '[\\x20-]', ''))"),
    "phone": (PHONE, f"{_DIGITS} BETWEEN 9 AND 15"),
}
KINDS = {k: k for k in BASE}
FOUND = {k: f"found_{k}" for k in BASE}
MARKS = {k: f"[{k.upper()}]" for k in BASE} | {f"found_{k}": f"[{k.upper()}]" for k in BASE}

#: Identifier-like tokens: addresses with a spelt or plain at-sign, and number groups.
CANDIDATE = (
    r"(?<![A-Za-z0-9._%+@-])(?:[A-Za-z0-9._%+-]++(?:\x20?[(\[]at[)\]]\x20?|@)[A-Za-z0-9-]++(?:(?:\.|\x20?[(\[]dot[)\]]\x20?)[A-Za-z0-9-]++)*+"
    r"|[(]?[0-9]++(?:[).\x20/:-]{1,2}[(]?[0-9]++)*+)"
)
#: SQL: the kind whose shape a candidate m has, or null.
SHAPE = (
    "CASE WHEN m.value RLIKE '@|[(\\\\[]at[)\\\\]]' THEN 'email' "
    "WHEN m.value RLIKE '^[0-9]+(?:[.:][0-9]+){3,7}$' THEN 'ip' "
    f"WHEN {_DIGITS} BETWEEN 12 AND 19 THEN 'card' "
    f"WHEN {_DIGITS} BETWEEN 7 AND 11 THEN 'phone' END"
)
MIN_SEEDS = 3
CONFIDENT = 0.5
ROUNDS = 3
#: Patterns are broadcast for the count of their occurrences up to this many; beyond it they are joined by shuffle.
BROADCAST_PATTERNS = 100_000


#: An instance may be written in so many words; a pattern of both sides is counted over gaps up to this.
GAP_WORDS = 4
_SPACE = "[\\\\x20\\\\x09-\\\\x0D]"
_LABEL = "(?<!\\\\p{L})\\\\p{L}{1,20}[:=#]"


def _words(text: str) -> str:
    """SQL: the words of ``text`` in lower case."""
    return f"filter(split(lower({text}), '{_SPACE}+'), w -> w <> '')"


def contexts(m: str) -> str:
    """SQL: the patterns, each with its form, that the place of the span ``m`` gives; words that the kept context cuts give none."""
    whole = f"(length({m}.left) < {S.LEFT})"
    spaced = f"{m}.left RLIKE '{_SPACE}$'"
    right = f"nullif(regexp_extract(lower({m}.right), '^{_SPACE}+([^{_SPACE[1:-1]}]+){_SPACE}', 1), '')"
    label = f"nullif(regexp_extract(lower({m}.left), '({_LABEL}){_SPACE}?$', 1), '')"
    return (
        f"transform(array({_words(f'{m}.left')}), w -> filter(array("
        f"CASE WHEN {spaced} AND (size(w) >= 2 OR size(w) = 1 AND {whole}) THEN concat('one|', element_at(w, -1)) END, "
        f"CASE WHEN {spaced} AND (size(w) >= 3 OR size(w) = 2 AND {whole}) THEN concat('two|', element_at(w, -2), ' ', element_at(w, -1)) END, "
        f"CASE WHEN {spaced} AND (size(w) >= 2 OR size(w) = 1 AND {whole}) THEN concat('both|', element_at(w, -1), ' ', {right}) END, "
        f"concat('label|', {label})), p -> p IS NOT NULL))[0]"
    )


#: SQL by form: every occurrence in ``text``, whose words are ``w``, of any pattern of the form.
OCCURRENCES = {
    "one": "transform(w, x -> concat('one|', x))",
    "two": "zip_with(slice(w, 1, greatest(0, size(w) - 1)), slice(w, 2, greatest(0, size(w) - 1)), (a, b) -> concat('two|', a, ' ', b))",
    "both": "concat(" + ", ".join(f"zip_with(slice(w, 1, greatest(0, size(w) - {g + 1})), slice(w, {g + 2}, greatest(0, size(w) - {g + 1})), (a, b) -> concat('both|', a, ' ', b))" for g in range(1, GAP_WORDS + 1)) + ")",
    "label": f"transform(regexp_extract_all(lower(text), '{_LABEL}', 0), x -> concat('label|', x))",
}


def _scanned(rows: DataFrame, text: str) -> DataFrame:
    """``rows`` with base spans and with places: (kind, patterns, value, seed, start, end)."""
    found = S.with_spans(rows, text, BASE | {"candidate": (CANDIDATE, f"{SHAPE} IS NOT NULL")})
    based = found.select(*rows.columns, *BASE, "candidate", S.merged(KINDS).alias("base"))
    clear = based.select(*rows.columns, *BASE, "base", S.clear_of("candidate", "base").alias("clear"))
    place = lambda kind, seed: f"named_struct('kind', {kind}, 'patterns', {contexts('m')}, 'value', lower(m.value), 'seed', {seed}, 'start', m.start, 'end', m.end)"
    parts = [f"transform(`{k}`, m -> {place(repr(k), 1)})" for k in BASE] + [f"transform(clear, m -> {place(SHAPE, 0)})"]
    return clear.select(*rows.columns, "base", F.expr(f"filter(concat({', '.join(parts)}), p -> size(p.patterns) > 0)").alias("places"))


def _key() -> Column:
    return F.sha2(F.concat_ws("/", F.col("doc_id").cast("string"), F.col("text").cast("string")), 256)


def scan(docs: DataFrame) -> DataFrame:
    """doc_id, key (a hash of id and text), base spans and places of every row, and the text where it has places."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"), _key().alias("key"))
    return _scanned(rows, "text").select("doc_id", "key", "base", "places", F.when(F.size("places") > 0, F.col("text")).alias("text"))


def occurrences(docs: DataFrame, patterns: DataFrame, forms: list[str]) -> DataFrame:
    """(pattern, n): how often each pattern of ``patterns(pattern)``, all of ``forms``, stands in all texts."""
    text = docs.select(F.col("text").cast("string").alias("text"))
    words = text.select("text", F.expr(_words("text")).alias("w"))
    every = words.select(F.explode(F.expr(f"concat({', '.join(OCCURRENCES[f] for f in forms)})")).alias("pattern"))
    n = patterns.count()
    side = F.broadcast(patterns) if n <= BROADCAST_PATTERNS else patterns
    return every.join(side, "pattern", "left_semi").groupBy("pattern").agg(F.count("*").alias("n"))


def with_precision(docs: DataFrame, scanned: DataFrame, able: DataFrame, confident: float) -> DataFrame:
    """``able(pattern, kind, times)`` with precision and counted: whether all texts were counted, or the bound settles it."""
    rows = able.select("pattern", "kind", "times")
    out = None
    for texts, last in ((scanned.where("text IS NOT NULL"), False), (docs, True)):
        forms = [r.form for r in rows.select(F.substring_index("pattern", "|", 1).alias("form")).distinct().collect()]  # at most four
        if not forms:
            break
        counted = occurrences(texts, rows.select("pattern").distinct(), sorted(forms))
        precision = F.col("times") / F.greatest(F.col("times"), F.coalesce("n", F.lit(0)))
        rows = stage(rows.join(counted, "pattern", "left").select("pattern", "kind", "times", precision.alias("precision")), "pii-precision")
        done = rows if last else rows.where(F.col("precision") < confident)
        done = done.withColumn("counted", F.lit(last))
        out = done if out is None else out.unionByName(done)
        rows = rows.where(F.col("precision") >= confident).select("pattern", "kind", "times")
    return out if out is not None else able.select("pattern", "kind", "times", F.lit(0.0).alias("precision"), F.lit(False).alias("counted")).limit(0)


def _confidence(edges: DataFrame, patterns: DataFrame) -> DataFrame:
    """(pattern, kind, support, times, precision, counted, confidence): the mean score of the labelled instances, times the precision."""
    return edges.join(patterns, ["pattern", "kind"]).groupBy("pattern", "kind").agg(
        F.sum("seed").alias("support"), F.max("patterns_times").alias("times"), F.max("precision").alias("precision"), F.max("counted").alias("counted"),
        (F.avg("score") * F.max("precision")).alias("confidence"),
    )


def scored_patterns(docs: DataFrame, scanned: DataFrame, min_seeds: int = MIN_SEEDS, rounds: int = ROUNDS, confident: float = CONFIDENT) -> DataFrame:
    """Every pattern with enough known instances: its kind, support, times, precision, confidence and whether it is confident.

    Where ``counted`` is false the precision is the bound over texts with
    instances, and the confidence a bound too.
    """
    places = scanned.select(F.explode("places").alias("p")).select(F.explode("p.patterns").alias("pattern"), "p.kind", F.xxhash64("p.value").alias("instance"), "p.seed")
    edges = places.groupBy("pattern", "kind", "instance").agg(F.max("seed").alias("seed"), F.count("*").alias("times"))
    # An instance without a label has no score yet.
    edges = stage(edges.withColumn("score", F.when(F.col("seed") == 1, 1.0)), "pii-edges")
    patterns = None
    for _ in range(rounds):
        able = edges.groupBy("pattern", "kind").agg(F.sum((F.coalesce("score", F.lit(0.0)) >= confident).cast("int")).alias("known"), F.sum("times").alias("times")).where(F.col("known") >= min_seeds)
        if patterns is not None:
            able = able.join(patterns, ["pattern", "kind"], "left_anti")
        able = stage(able.select("pattern", "kind", "times"), "pii-patterns")
        new = with_precision(docs, scanned, able, confident).withColumnRenamed("times", "patterns_times")
        patterns = stage(new if patterns is None else patterns.unionByName(new), "pii-scored")
        sure = _confidence(edges, patterns).where(F.col("counted") & (F.col("confidence") >= confident)).select("pattern", "kind", "confidence")
        instances = edges.where("seed = 0").join(sure, ["pattern", "kind"]).groupBy("instance", "kind").agg((1 - F.exp(F.sum(F.log(1 - 0.9 * F.col("confidence"))))).alias("new"))
        instances = stage(instances, "pii-instances")
        if not instances.take(1):
            break
        edges = stage(edges.join(instances, ["instance", "kind"], "left").withColumn("score", F.when(F.col("seed") == 1, 1.0).otherwise(F.coalesce("new", "score"))).drop("new"), "pii-edges")
    return stage(_confidence(edges, patterns).withColumn("confident", F.col("counted") & (F.col("confidence") >= confident)), "pii-confidence")


def evidence(scanned: DataFrame, scored: DataFrame) -> DataFrame:
    """(key, added, n_scored, support, confidence) of each text with places in scored patterns.

    added: the spans behind confident patterns; n_scored: places in scored
    patterns; support and confidence: those of the best pattern at any of them.
    """
    name = F.concat_ws("/", "kind", "pattern").alias("name")
    places = scanned.select("key", F.explode("places").alias("p")).select("key", "p.kind", "p.start", "p.end", "p.seed", F.explode("p.patterns").alias("pattern"))
    sides = scored.select(name, "times", "support", "confidence", "confident")
    hits = join_hot_apart(places.select("key", "kind", "start", "end", "seed", name), sides, "name", "times")
    rank = F.expr("CASE kind " + " ".join(f"WHEN '{k}' THEN {len(KINDS) + i}" for i, k in enumerate(FOUND)) + " END")
    span = F.struct(F.col("start"), rank.alias("k"), F.col("end"), F.concat(F.lit("found_"), F.col("kind")).alias("kind"))
    best = F.max(F.struct("confidence", "support"))
    each = hits.groupBy("key", "start", "end", "kind").agg(F.max(F.when(F.col("confident") & (F.col("seed") == 0), span)).alias("span"), best.alias("best"))
    return each.groupBy("key").agg(
        F.collect_set("span").alias("added"), F.count("*").alias("n_scored"), F.max("best").alias("best")
    ).select("key", "added", "n_scored", F.col("best.support").alias("support"), F.col("best.confidence").alias("confidence"))


def with_all_spans(docs: DataFrame, scanned: DataFrame) -> DataFrame:
    """doc_id, base, all_spans (base and discovered) and the evidence columns, for each row of ``scanned`` (a written table)."""
    found = evidence(scanned, scored_patterns(docs, scanned))
    none = F.expr("cast(array() AS array<struct<start: bigint, k: int, end: bigint, kind: string>>)")
    rows = scanned.select("doc_id", "key", "base", F.size("places").cast("long").alias("n_places")).join(found, "key", "left")
    return rows.select(
        "doc_id", "key", "base", F.array_sort(F.concat("base", F.coalesce("added", none))).alias("all_spans"), "n_places",
        F.coalesce("n_scored", F.lit(0)).cast("long").alias("n_scored"), F.coalesce("support", F.lit(0)).cast("long").alias("support"), F.coalesce("confidence", F.lit(0.0)).alias("confidence"),
    )


def redact(docs: DataFrame) -> DataFrame:
    """``docs`` with every base and discovered span in text replaced by its kind's mark, and n_chars renewed; null texts stay null."""
    scanned = stage(scan(docs), "pii-scan")
    marked = stage(with_all_spans(docs, scanned).where(F.size("all_spans") > 0).select("key", "all_spans").dropDuplicates(["key"]), "pii-marked")
    rows = docs.select(packed(docs), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"), _key().alias("key"))
    at = rows.join(marked, "key", "left")
    found, old = F.col("all_spans").isNotNull(), at["row"]
    text = F.when(old["text"].isNotNull(), F.when(found, S.replaced("text", "all_spans", MARKS)).otherwise(F.col("text")))
    renewed = {"text": text}
    if "n_chars" in docs.columns:
        renewed["n_chars"] = F.when(found, F.length(text).cast("long")).otherwise(old["n_chars"])
    return at.select(*unpacked(at, docs.columns, renewed))


def op4_contextual_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract: doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans.

    Further columns: n_places (identifier-like places in a context), n_scored
    (those in scored patterns), support and confidence of the best such pattern,
    and n_found (spans added).
    """
    docs = table(spark, sf_dir, "documents")
    found = with_all_spans(docs, stage(scan(docs), "pii-scan"))

    def count(kind: str) -> Column:
        return F.size(F.filter("base", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")

    return found.select(
        "doc_id", *[count(k) for k in KINDS], F.sha2(S.joined(F.col("base")), 256).alias("base_sha256"), S.joined(F.col("all_spans")).alias("spans"),
        "n_places", "n_scored", "support", F.round("confidence", 6).alias("confidence"), (F.size("all_spans") - F.size("base")).cast("long").alias("n_found"),
    )
