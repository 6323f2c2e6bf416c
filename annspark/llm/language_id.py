"""Language identification of whole, possibly mixed texts.

Each word's script (from fixed character ranges) first narrows the candidate
languages to those whose training text uses that script. Each candidate scores
the word: a smoothed word frequency where the word was seen in training, a
character-trigram model elsewhere. Viterbi over the words, with a penalty for
each switch, labels spans; a text's language is the one with most letters.

Training: rows with a text and a language whose crc32(doc_id) mod 4 is not 2.
The fit is on a bounded sample of them: about SAMPLE_ROWS rows (chosen by a hash
of the id) of each of the LANGUAGES labels that have most rows. Every word of
those rows counts. Prediction reads whole texts of every row and nothing but text.

Most texts are proved monolingual without a walk: if for no other language the
score lead over the best one rises by more than the penalty within any stretch,
no path with a switch can win. Only the rest runs the full recursion.

Defined cases: null texts and texts without letters (Unicode category L) are `und` with score 0; a
text whose letters all belong to scripts no language uses gets the commonest
language with score 0; ties go to the language that sorts first; with nothing to
learn from, every text is `und`; repeated rows give equal results; extra columns
pass through untouched in the filter and are dropped in the prediction.
"""

from __future__ import annotations

import math
import re
from bisect import bisect_right
from collections import Counter, defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from annspark.plans.session import ship_package
from annspark.sources.tables import table

#: Bounds of the labelled rows that the model is fitted on.
SAMPLE_ROWS, LANGUAGES = 400, 200
SWITCH_PENALTY = 12.0
#: A word's score is cut at so much below its best language.
WORD_FLOOR = -6.0
#: A language uses a script that has at least this share of its training letters.
SCRIPT_SHARE = 0.02
#: The filter keeps texts in which the winner has at least this share of the letters.
KEEP_SCORE = 0.3
UNDETERMINED = "und"
CACHE_ENTRIES = 60_000

# First and last code point of common scripts' letters.
SCRIPT_RANGES = (
    (0x0041, 0x024F, "latin"), (0x0250, 0x02AF, "latin"), (0x0370, 0x03FF, "greek"), (0x0400, 0x052F, "cyrillic"),
    (0x0530, 0x058F, "armenian"), (0x0590, 0x05FF, "hebrew"), (0x0600, 0x06FF, "arabic"), (0x0750, 0x077F, "arabic"),
    (0x0900, 0x097F, "devanagari"), (0x0980, 0x09FF, "bengali"), (0x0A00, 0x0A7F, "gurmukhi"), (0x0A80, 0x0AFF, "gujarati"),
    (0x0B80, 0x0BFF, "tamil"), (0x0C00, 0x0C7F, "telugu"), (0x0C80, 0x0CFF, "kannada"), (0x0D00, 0x0D7F, "malayalam"),
    (0x0E00, 0x0E7F, "thai"), (0x0E80, 0x0EFF, "lao"), (0x1000, 0x109F, "myanmar"), (0x10A0, 0x10FF, "georgian"),
    (0x1100, 0x11FF, "hangul"), (0x1200, 0x137F, "ethiopic"), (0x1780, 0x17FF, "khmer"), (0x1E00, 0x1EFF, "latin"),
    (0x1F00, 0x1FFF, "greek"), (0x3040, 0x309F, "kana"), (0x30A0, 0x30FF, "kana"), (0x3400, 0x4DBF, "han"),
    (0x4E00, 0x9FFF, "han"), (0xAC00, 0xD7AF, "hangul"), (0xF900, 0xFAFF, "han"), (0x20000, 0x2FA1F, "han"),
)
_STARTS = [r[0] for r in SCRIPT_RANGES]
_LETTERS = regex.compile(r"\p{L}+")


def script_of(ch: str) -> str:
    """The script of one letter, `other` outside the table."""
    i = bisect_right(_STARTS, ord(ch)) - 1
    return SCRIPT_RANGES[i][2] if i >= 0 and ord(ch) <= SCRIPT_RANGES[i][1] else "other"


class Model:
    """Word and trigram scores of each language: matrices with a row for each word, trigram and script."""

    def __init__(self, counts: list[tuple[str, str, int]]):
        self.langs = sorted({c[0] for c in counts})
        at = {x: i for i, x in enumerate(self.langs)}
        n = len(self.langs)
        if not n:
            return
        words: dict[str, list[float]] = defaultdict(lambda: [0.0] * n)
        grams: dict[str, list[float]] = defaultdict(lambda: [0.0] * n)
        contexts: dict[str, list[float]] = defaultdict(lambda: [0.0] * n)
        scripts = [Counter() for _ in range(n)]
        for lang, word, count in counts:
            i = at[lang]
            words[word][i] += count
            scripts[i][script_of(word[0])] += count * len(word)
            padded = f" {word} "
            for k in range(len(padded) - 2):
                grams[padded[k : k + 3]][i] += count
                contexts[padded[k : k + 2]][i] += count
        total = np.array([sum(w[i] for w in words.values()) for i in range(n)])
        self.prior = int(total.argmax()) if n else 0
        #: Which languages use a script; the last row is for scripts none uses.
        self.scripts = {s: i for i, s in enumerate(sorted({s for c in scripts for s in c}))}
        allowed = [[c[s] >= SCRIPT_SHARE * max(1, sum(c.values())) for c in scripts] for s in self.scripts]
        self.allowed = np.array([*allowed, [False] * n], bool)
        size = max(1, len(words))
        seen = {w: c for w, c in words.items() if max(c) >= 2}
        self.words = {w: i for i, w in enumerate(seen)}
        self.word_scores = np.log((np.array(list(seen.values())).reshape(-1, n) + 0.5) / (total + 0.5 * size)).astype(np.float32)
        letters = max(30, len({g[2] for g in grams}))
        self.grams = {g: i for i, g in enumerate(grams, 1)}
        above = np.array(list(grams.values())).reshape(-1, n) + 0.2
        below = np.array([contexts[g[:2]] for g in grams]).reshape(-1, n) + 0.2 * letters
        #: The first row is for trigrams that training never saw.
        self.gram_scores = np.concatenate([np.full((1, n), math.log(1 / letters)), np.log(above / below)]).astype(np.float32)
        self._script: dict[str, int] = {}

    def script_row(self, ch: str) -> int:
        got = self._script.get(ch)
        if got is None:
            got = self._script[ch] = self.scripts.get(script_of(ch), len(self.scripts))
        return got

    def scores(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Log scores of lower-case words, the best candidate at zero, and whether any language uses the script.

        A word whose script no language uses scores zero for all.
        """
        at = np.array([self.words.get(w, -1) for w in words], np.int64)
        out = np.empty((len(words), len(self.langs)), np.float32)
        out[at >= 0] = self.word_scores[at[at >= 0]]
        new = np.flatnonzero(at < 0)
        if len(new):
            get, flat, ends = self.grams.get, [], []
            for i in new.tolist():
                w = f" {words[i]} "
                ends.append(len(flat))
                flat += [get(a + b + c, 0) for a, b, c in zip(w, w[1:], w[2:])]
            out[new] = np.add.reduceat(self.gram_scores[flat], ends, axis=0)
        allowed = self.allowed[[self.script_row(w[0]) for w in words]]
        known = allowed.any(axis=1)
        out = np.where(allowed, out, -np.inf)
        best = out.max(axis=1, initial=-np.inf, keepdims=True)
        out = np.maximum(np.where(known[:, None], out - np.where(known[:, None], best, 0), 0), WORD_FLOOR)
        return out, known


def viterbi(scores: np.ndarray, penalty: float) -> np.ndarray:
    """The best language at each word; ties go to the first language and to staying."""
    n, k = scores.shape
    back = np.empty((n, k), np.int16)
    total = scores[0].tolist()
    rows = scores.tolist()
    own = list(range(k))
    for t in range(1, n):
        top = max(total)
        lead = total.index(top)
        row, link, new = rows[t], own[:], [0.0] * k
        for j in own:
            if total[j] >= top - penalty:
                new[j] = total[j] + row[j]
            else:
                link[j] = lead
                new[j] = top - penalty + row[j]
        back[t] = link
        total = new
    path = np.empty(n, np.int64)
    path[-1] = total.index(max(total))
    for t in range(n - 1, 0, -1):
        path[t - 1] = back[t, path[t]]
    return path


class Labeller:
    """Scores words through a bounded cache and labels texts."""

    def __init__(self, model: Model, penalty: float = SWITCH_PENALTY):
        self.model, self.penalty = model, penalty
        self._reset()

    def _reset(self) -> None:
        k = len(self.model.langs)
        self.index: dict[str, int] = {}
        self.table = np.zeros((1024, k), np.float32)
        self.letters = np.zeros(1024, np.int64)
        self.known = np.zeros(1024, bool)

    def _add(self, tokens: list[str]) -> None:
        """Rows of summed word scores for new tokens; a token without letters has no letters."""
        words: list[str] = []
        owner: list[int] = []
        for j, token in enumerate(tokens):
            if token.isalpha():
                words.append(token.lower())
                owner.append(j)
            else:
                parts = _LETTERS.findall(token.lower())
                words += parts
                owner += [j] * len(parts)
        first, n = len(self.index), len(tokens)
        while first + n > len(self.table):
            self.table = np.concatenate([self.table, np.zeros_like(self.table)])
            self.letters = np.concatenate([self.letters, np.zeros_like(self.letters)])
            self.known = np.concatenate([self.known, np.zeros_like(self.known)])
        self.index.update(zip(tokens, range(first, first + n)))
        rows = slice(first, first + n)
        if not words:
            return
        scores, known = self.model.scores(words)
        at = np.array(owner)
        total = np.stack([np.bincount(at, scores[:, i], n) for i in range(scores.shape[1])], axis=1)
        self.table[rows] = np.maximum(total - total.max(axis=1, keepdims=True), WORD_FLOOR)
        self.letters[rows] = np.bincount(at, list(map(len, words)), n)
        self.known[rows] = np.bincount(at, known, n) > 0

    def rows(self, tokens: list[str]) -> np.ndarray:
        got = list(map(self.index.get, tokens))
        if None in got:
            self._add(list(dict.fromkeys(t for t, g in zip(tokens, got) if g is None)))
            got = list(map(self.index.get, tokens))
        return np.array(got, np.int64)

    def label(self, text: str | None) -> tuple[str, float, np.ndarray | None, np.ndarray | None]:
        """(language, score, path over the tokens that hold letters, those tokens' positions)."""
        langs = self.model.langs
        tokens = (text or "").split()
        if not tokens or not langs:
            return UNDETERMINED, 0.0, None, None
        if len(self.index) > CACHE_ENTRIES:
            self._reset()
        rows = self.rows(tokens)
        letters = self.letters[rows]
        at = np.flatnonzero(letters)
        if not len(at):
            return UNDETERMINED, 0.0, None, None
        rows, letters = rows[at], letters[at]
        scores = self.table[rows]
        total = np.cumsum(scores, axis=0, dtype=np.float64)
        best = int(total[-1].argmax())
        lead = total - total[:, best : best + 1]
        low = np.minimum(np.minimum.accumulate(lead, axis=0), 0)
        # One language throughout wins if no stretch of another gains more than a switch costs, and no first and last
        # stretch together do: a path that leaves the best language out pays one switch less than it has stretches.
        gain = (lead - np.concatenate([np.zeros((1, len(langs))), low[:-1]])).max()
        ends = lead.max() + (lead[-1] - low[-1]).max()
        if gain <= self.penalty and (len(langs) < 3 or ends <= self.penalty):
            path = np.full(len(at), best)
        else:
            path = viterbi(scores, self.penalty)
        known = self.known[rows]
        by = np.bincount(path, weights=letters * known, minlength=len(langs))
        if not by.any():
            return langs[self.model.prior], 0.0, path, at
        lang = int(by.argmax())
        return langs[lang], float(by[lang] / letters.sum()), path, at

    def spans(self, text: str | None) -> list[tuple[int, int, str]]:
        """(start, end, language) in code points; each span covers whole words of one language."""
        _, _, path, at = self.label(text)
        if path is None:
            return []
        places = [m.span() for m in re.finditer(r"\S+", text)]
        if len(places) != len(text.split()):  # separators that are not white space to the pattern
            places, p = [], 0
            for t in text.split():
                p = text.index(t, p)
                places.append((p, p + len(t)))
                p += len(t)
        out: list[tuple[int, int, str]] = []
        for lang, i in zip(path.tolist(), at.tolist()):
            s, e = places[i]
            name = self.model.langs[lang]
            if out and out[-1][2] == name:
                out[-1] = (out[-1][0], e, name)
            else:
                out.append((s, e, name))
        return out


def is_held_out(doc_id: F.Column) -> F.Column:
    return F.coalesce(F.crc32(doc_id.cast("string")) % 4 == 2, F.lit(False))


def fit(docs: DataFrame, sample_rows: int = SAMPLE_ROWS, languages: int = LANGUAGES) -> Model:
    """Learn from a bounded sample of the labelled rows that aren't held out."""
    may = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("lang").cast("string").alias("lang"), F.col("text").cast("string").alias("text")).where(
        F.col("lang").isNotNull() & F.col("text").isNotNull() & ~is_held_out(F.col("doc_id"))
    )
    labels = may.groupBy("lang").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "lang").limit(languages).collect()
    if not labels:
        return Model([])
    rates = F.create_map(*[F.lit(x) for r in sorted(labels) for x in (r.lang, min(1.0, sample_rows / r.n))])
    chosen = may.where(F.pmod(F.xxhash64("doc_id"), F.lit(1_000_000)) < F.try_element_at(rates, F.col("lang")) * 1_000_000)
    words = chosen.select("lang", F.explode(F.expr(r"regexp_extract_all(lower(text), '\\p{L}+', 0)")).alias("word"))
    counts = words.groupBy("lang", "word").agg(F.count("*").alias("n")).toArrow()
    return Model(list(zip(*(counts.column(c).to_pylist() for c in ("lang", "word", "n")))))


def predict(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, lang_pred, score for every row, from the text alone."""
    ship_package(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(model)  # bounded by the sample of the fit

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        labeller = Labeller(shared.value)
        for batch in batches:
            got = [labeller.label(t.as_py()) for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array([g[0] for g in got], pa.string()), pa.array([g[1] for g in got], pa.float64())],
                ["doc_id", "lang_pred", "score"],
            )

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, lang_pred string, score double")


def label_spans(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id and spans (start, end, lang) in code points of every row."""
    ship_package(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        labeller = Labeller(shared.value)
        kind = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64()), ("lang", pa.string())]))
        for batch in batches:
            got = [[dict(zip(("start", "end", "lang"), s)) for s in labeller.spans(t.as_py())] for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(got, kind)], ["doc_id", "spans"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, spans array<struct<start: long, end: long, lang: string>>")


def keep_identified(docs: DataFrame, model: Model, least: float = KEEP_SCORE) -> DataFrame:
    """The rows, with all their columns, whose language is determined with a score of at least ``least``.

    Only the text goes to Python and one flag a row comes back; the other
    columns wait in the JVM.
    """
    ship_package(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(model)

    @F.arrow_udf("boolean")
    def identified(texts: Iterator[pa.Array]) -> Iterator[pa.Array]:
        labeller = Labeller(shared.value)
        for batch in texts:
            got = (labeller.label(t.as_py()) for t in batch)
            yield pa.array([g[0] != UNDETERMINED and g[1] >= least for g in got], pa.bool_())

    return docs.where(identified(F.col("text").cast("string")))


def op2_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract: doc_id, held_out, lang_pred, score."""
    docs = table(spark, sf_dir, "documents")
    return predict(docs, fit(docs)).select("doc_id", is_held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")
