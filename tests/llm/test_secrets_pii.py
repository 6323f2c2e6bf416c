import hashlib
import math
import random
from collections import Counter, defaultdict
from statistics import NormalDist

import regex
from pytest import approx
from pyspark.sql import functions as F

from annspark.llm import pii, secrets
from annspark.llm import spans as S
from annspark.plans.session import stage


def luhn(d):
    total = 0
    for i, c in enumerate(reversed(d)):
        n = int(c) * (1 + i % 2)
        total += n - 9 * (n > 9)
    return total % 10 == 0


def digits(s):
    return regex.sub("[^0-9]", "", s)


# The contracts' patterns as they are written.
SECRET = [
    ("assign", r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", lambda m: len(m[2]) >= 12),
    ("access", r"AKIA[A-Z0-9]+", lambda m: len(m[0]) >= 18),
    ("hex", r"[0-9a-f]+", lambda m: len(m[0]) >= 16),
]
PERSONAL = [
    ("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", lambda m: True),
    ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", lambda m: all(int(p) <= 255 for p in m[0].split("."))),
    ("card", r"[0-9]([\x20-]?[0-9])+", lambda m: 12 <= len(digits(m[0])) <= 19 and luhn(digits(m[0]))),
    ("phone", r"\+[0-9][\x20().0-9-]+[0-9]", lambda m: 9 <= len(digits(m[0])) <= 15),
]


def wanted(text, kinds):
    return sorted((m.start(), k, name, m.end()) for k, (name, p, ok) in enumerate(kinds) for m in regex.finditer(p, text or "") if ok(m))


def digest(spans):
    return hashlib.sha256(",".join(f"{n}:{s}:{e}" for s, _, n, e in spans).encode()).hexdigest()


def fuzz(parts, n, seed, longest=14):
    rng = random.Random(seed)
    return [(i, "".join(rng.choice(parts) for _ in range(rng.randint(0, longest))), "en", "s") for i in range(n)]


SECRET_PARTS = ["password", "Passwd", "SECRET", "token", "api_key", "APIKEY", "=", ":", " ", "  ", '"', "'", "abcdefghijkl", "0123456789ab", "AKIA", "AKIAABCDEFGHIJKLMN", "ffff", "0" * 16, "é", "😀", "-", ".", "Z9"]
PERSONAL_PARTS = ["a", "bob", "@", ".", "_", "x-y", "example", "com", "1", "12", "255", "256", "0007", "4111", "1111", "-", " ", "+", "(", ")", "é", "😀", "4111 1111 1111 1111", "+1 555 010 0000", "\n"]


def check(spark, folder, run, kinds, rows):
    got = {r["doc_id"]: r for r in run(spark, folder).collect()}
    for i, t, *_ in rows:
        want = wanted(t, kinds)
        assert got[i]["base_sha256"] == digest(want), (t, want, got[i])
        assert {f"{n}:{s}:{e}" for s, _, n, e in want} <= set(got[i]["spans"].split(","))  | {""}
        assert [got[i][f"n_{k}"] for k, *_ in kinds] == [sum(w[2] == k for w in want) for k, *_ in kinds]
    return got


def test_secret_base_matches_patterns(spark, docs_of, folder_of):
    rows = fuzz(SECRET_PARTS, 600, 3)
    check(spark, folder_of("documents", docs_of(rows)), secrets.op3_secret_scan, SECRET, rows)


def test_personal_base_matches_patterns(spark, docs_of, folder_of):
    rows = fuzz(PERSONAL_PARTS, 800, 4, 20)
    check(spark, folder_of("documents", docs_of(rows)), pii.op4_contextual_pii, PERSONAL, rows)


def test_long_runs_stay_linear(spark, docs_of, folder_of):
    rows = [(1, "1" * 60_000, "en", "s"), (2, "a." * 30_000, "en", "s"), (3, "1 " * 30_000, "en", "s"), (4, "f" * 60_000, "en", "s"), (5, "A1b" * 20_000, "en", "s"), (6, "+1" + " " * 40_000, "en", "s"), (7, "a@b.c " * 2000, "en", "s")]
    folder = folder_of("documents", docs_of(rows))
    check(spark, folder, secrets.op3_secret_scan, SECRET, rows)
    check(spark, folder, pii.op4_contextual_pii, PERSONAL, rows)


def battery(value):
    """encoding, chi-squared, p_random and p_text of one run, from their definitions."""
    v = value.rstrip("=").translate(str.maketrans("-_", "+/"))
    name, _, alphabet, d = next(e for e in secrets.ENCODINGS if regex.search(e[1] or "^", v))
    n, k = len(v), len(alphabet)
    chi = sum((c - n / k) ** 2 / (n / k) for c in Counter(v).values()) + (k - len(set(v))) * n / k
    xs = [alphabet.index(c) for c in v]
    high = [x >= k / 2 for x in xs]
    runs, mu = 1 + sum(a != b for a, b in zip(high, high[1:])), 2 * sum(high) * (n - sum(high)) / n
    mean = sum(xs) / n
    corr = sum((x - mean) * (y - mean) for x, y in zip(xs, xs[1:])) / max(1e-9, sum((x - mean) ** 2 for x in xs))
    tail = lambda z: max(1e-15, NormalDist().cdf(-z))
    h = 2 / (9 * (k - 1))
    z = [((chi / (k - 1)) ** (1 / 3) - 1 + h) / h**0.5, abs(runs - 1 - mu) / (mu * (mu - 1) / (n - 1)) ** 0.5 if mu > 1 else 9, abs(corr + 1 / n) * n**0.5]
    joint = tail(z[0]) * min(1, 2 * tail(z[1])) * min(1, 2 * tail(z[2]))
    s = -math.log(joint)
    classes = ["U" if c.isupper() else "L" if c.islower() else "D" for c in v if c.isalnum()]
    pairs, changes = max(1, len(classes) - 1), sum(a != b for a, b in zip(classes, classes[1:]))
    f, t = changes / pairs, secrets.CLASS_CHANGES
    rare = pairs * (f * math.log(f / t) + (0 if f == 1 else (1 - f) * math.log((1 - f) / (1 - t)))) if f > t else 0
    u = rare - math.log(tail(-(chi - (k - 1) - n * d) / (2 * (k - 1) + 4 * n * d) ** 0.5))
    return name, n, chi, math.exp(-s) * (1 + s + s * s / 2), math.exp(-u) * (1 + u)


ALPHABETS = ["0123456789", "0123456789abcdef", "0123456789ABCDEF", "etaoinshr", "ETAOINSHR", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567", "abcdefgh0123456789", "ABCDEFGH0189", "ABCxyz", "ABCDEFabcdef0189", "ABCDabcd0189+/", "aaab", "-_Az09"]


def test_battery_matches_its_definitions(spark, docs_of):
    rng = random.Random(5)
    values = ["".join(rng.choice(a) for _ in range(rng.choice([12, 13, 20, 40, 64, 200]))) + rng.choice(["", "", "=", "=="]) for a in ALPHABETS for _ in range(12)]
    rows = [(i, f"x {v} y", "en", "s") for i, v in enumerate(values)]
    got = {r.doc_id: r.tested for r in secrets.scan(docs_of(rows)).collect()}
    names = set()
    for i, v in enumerate(values):
        (t,) = got[i]
        name, n, chi, p_random, p_text = battery(v)
        names.add(name)
        assert (t.start, t.end, t.encoding, t.n) == (2, 2 + len(v), name, n), v
        assert t.chi == approx(chi) and t.p_random == approx(p_random, 0.02, 1e-14) and t.p_text == approx(p_text, 0.02, 1e-14), (v, t)
    assert names == {e[0] for e in secrets.ENCODINGS}


def test_step_up_matches_its_definition(spark):
    rng = random.Random(8)
    rows = [(float(rng.choice([12, 20, 40, 90])), rng.random() ** 8, rng.random() * (0.002 if i % 3 else 1e-9)) for i in range(3000)] + [(30.0, 0.5, rng.random()) for _ in range(9000)]
    df = spark.createDataFrame([([r],) for r in rows], "tested array<struct<n: double, p_random: double, p_text: double>>")
    mean, least = secrets.threshold(df)
    want = sum(min(n, secrets.FULL_LENGTH) for n, *_ in rows) / len(rows)
    assert mean == approx(want)
    bins = [max(0, min(secrets.BINS, math.floor(secrets.BINS_PER_DECADE * -math.log10(p / (min(n, secrets.FULL_LENGTH) / want))))) for n, _, p in rows]
    best = [b for b in set(bins) if len(rows) * 10 ** (-b / secrets.BINS_PER_DECADE) <= secrets.DISCOVERY_RATE * sum(c >= b and r[1] >= secrets.RANDOM_LEVEL for c, r in zip(bins, rows))]
    assert best and least == min(best)
    assert secrets.threshold(df.limit(0)) == (1.0, float("inf"))


def test_base_spans_are_tested_too(spark, docs_of, folder_of):
    rng = random.Random(3)
    rows = [(i, "set token=" + "".join(rng.choice("0123456789abcdef") for _ in range(40)) + " now", "en", "s") for i in range(30)]
    rows += [(100, "password=internationalisation and the understanding of it", "en", "s")]
    got = {r.doc_id: r for r in secrets.op3_secret_scan(spark, folder_of("documents", docs_of(rows))).collect()}
    assert sum(got[i].n_confirmed for i in range(30)) >= 25 and all(got[i].battery.startswith("hex:10:50:") and got[i].n_random == 0 for i in range(30))
    assert got[100].spans == "assign:0:29" and got[100].n_confirmed == 0 and got[100].n_tested == 2 and got[100].battery.startswith("lower:9:29:")


def test_random_tokens_are_found_and_plain_ones_left(spark, docs_of, folder_of):
    rng = random.Random(9)
    alphabet = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789"
    rows = [(i, "a line with " + "".join(rng.choice(alphabet) for _ in range(44)) + " inside", "en", "s") for i in range(40)]
    plain = ["einstaueinkeitlichlich2 war da", "src/main/java/org/apache/spark2/sql/catalyst", "aaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaa1", "version-2-of-the-internationalisation-layer", "123456789012345678901234567890"]
    rows += [(100 + i, t, "en", "s") for i, t in enumerate(plain)]
    got = {r.doc_id: r.spans for r in secrets.op3_secret_scan(spark, folder_of("documents", docs_of(rows))).collect()}
    hits = [i for i in range(40) if got[i] == "random:12:56"]
    assert len(hits) >= 36
    assert all("random" not in got[100 + i] for i in range(len(plain)))


def test_redactions(docs_of):
    rows = [(1, "x password=abcdefghijklmnop y", "en", "s"), (2, None, "en", "s"), (3, "clean text", "en", "s"), (4, "mail é bob@example.com now", "en", "s")]
    docs = docs_of(rows)
    got = {r.doc_id: r for r in secrets.redact(docs).collect()}
    assert got[1].text == "x [SECRET] y" and got[1].n_chars == len(got[1].text) and got[2].text is None and got[3].text == "clean text" and got[3].n_chars == 10
    assert secrets.redact(docs).columns == docs.columns
    masked = {r.doc_id: r for r in pii.redact(docs).collect()}
    assert masked[4].text == "mail é [EMAIL] now" and masked[4].n_chars == 18 and masked[2].text is None and masked[3].text == "clean text"


def test_extra_columns_with_the_names_used_inside(spark):
    names = ["base", "candidate", "tested", "found", "all_spans", "added", "assign", "access", "hex", "candidate__raw", "assign__at", "__text", "row", "places", "clear", "email", "ip", "key", "a.b"]
    rows = [(1, "x password=abcdefghijklmnop y bob@example.com", "en", "s", 45, *names), (2, None, None, None, None, *names)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, " + ", ".join(f"`{n}` string" for n in names))
    for op, text in ((secrets, "x [SECRET] y bob@example.com"), (pii, "x password=abcdefghijklmnop y [EMAIL]")):
        got = {r[0]: tuple(r) for r in op.redact(docs).collect()}
        assert got == {1: (1, text, "en", "s", len(text), *names), 2: rows[1]}
        assert op.scan(docs).count() == 2


def test_found_identifiers_are_masked(docs_of):
    rows = [(i, f"hello there you can call me at +1 (555) 010-00{i:02d} any time", "en", "s") for i in range(8)] + [(20, "so call me at (555) 999-1234 then", "en", "s")]
    assert {r.doc_id: r.text for r in pii.redact(docs_of(rows)).collect()}[20] == "so call me at [PHONE] then"


def test_overlapping_spans_are_replaced_once(spark):
    df = spark.createDataFrame([("0123456789", [(2, 0, 5, "a"), (4, 1, 7, "b")])], "t string, s array<struct<start: bigint, k: int, end: bigint, kind: string>>")
    assert df.select(S.replaced("t", "s", {"a": "[A]", "b": "[B]"}).alias("r")).first().r == "01[A]789"


def test_patterns_discover_unseen_identifiers(docs_of):
    rows = [(i, f"hello there you can call me at +1 (555) 010-00{i:02d} any time", "en", "s") for i in range(8)]
    rows += [(20, "so call me at (555) 999-1234 then", "en", "s"), (21, "in the year 2024 there were 1234567 of the things", "en", "s"), (22, None, None, None)]
    rows += [(23, "of the +1 (555) 010-0077 and of the 12345678 and of the of the of the of the", "en", "s")]
    docs = docs_of(rows)
    scanned = stage(pii.scan(docs), "t")
    found = {r.doc_id: r.s for r in pii.with_all_spans(docs, scanned).select("doc_id", S.joined(F.col("all_spans")).alias("s")).collect()}
    assert found[20] == "found_phone:14:28" and found[21] == "" and "found" not in found[23]


def test_bootstrap_reaches_beyond_the_seeds(docs_of):
    # Three seeds and four unseen numbers behind one pattern; a second pattern has only numbers that the first one found, and one more.
    rows = [(i, f"please just call me at +1 (555) 010-00{i:02d} any time", "en", "s") for i in range(3)]
    rows += [(10 + i, f"please just call me at (555) 999-123{i} any time", "en", "s") for i in range(4)]
    rows += [(20 + i, f"and my office line (555) 999-123{i} is open", "en", "s") for i in range(3)] + [(30, "and my office line (555) 888-7777 is open", "en", "s")]
    rows += [(31, "the other year (555) 777-6666 is alone", "en", "s")]
    docs = docs_of(rows)
    scanned = stage(pii.scan(docs), "t")
    found = {r.doc_id: r.s for r in pii.with_all_spans(docs, scanned).select("doc_id", S.joined(F.col("all_spans")).alias("s")).collect()}
    assert all("found_phone" in found[i] for i in (10, 11, 12, 13, 20, 21, 22, 30)) and found[31] == ""


def shape(v):
    n = len(digits(v))
    if regex.search(r"@|[(\[]at[)\]]", v):
        return "email"
    if regex.search(r"^[0-9]+(?:[.:][0-9]+){3,7}$", v):
        return "ip"
    return "card" if 12 <= n <= 19 else "phone" if 7 <= n <= 11 else None


def induced(text, start, end):
    """The patterns of one place, from the text around it."""
    left, right = text[:start].lower(), text[end:].lower()
    out, w = [], left.split()
    if left[-1:].isspace() and w:
        out += ["one|" + w[-1]] + (["two|" + " ".join(w[-2:])] if len(w) > 1 else [])
        m = regex.match(r"\s+(\S+)\s", right)
        out += [f"both|{w[-1]} {m[1]}"] if m else []
    m = regex.search(r"(?<!\p{L})(\p{L}{1,20}[:=#])\s?$", left)
    return out + (["label|" + m[1]] if m else [])


def all_occurrences(text):
    w = text.lower().split()
    yield from ("one|" + x for x in w)
    yield from (f"two|{a} {b}" for a, b in zip(w, w[1:]))
    yield from (f"both|{a} {b}" for g in range(1, pii.GAP_WORDS + 1) for a, b in zip(w, w[g + 1 :]))
    yield from ("label|" + x for x in regex.findall(r"(?<!\p{L})\p{L}{1,20}[:=#]", text.lower()))


def bootstrap(texts):
    """Brute force: {(pattern, kind): (support, confidence or its bound, confident)} and {text number: found spans}."""
    places = []
    for t, text in enumerate(texts):
        base = wanted(text, PERSONAL)
        places += [(t, kind, text[s:e].lower(), 1, s, e) for s, _, kind, e in base]
        for m in regex.finditer(pii.CANDIDATE.replace(r"\x20", " "), text):
            if shape(m[0]) and not any(s < m.end() and m.start() < e for s, _, _, e in base):
                places.append((t, shape(m[0]), m[0].lower(), 0, *m.span()))
    seeds, times, with_places = {}, Counter(), set()
    for t, kind, value, seed, s, e in places:
        for p in induced(texts[t], s, e):
            with_places.add(t)
            seeds[p, kind, value] = max(seed, seeds.get((p, kind, value), 0))
            times[p, kind] += 1
    score = {(k, v): 1.0 for (p, k, v), seed in seeds.items() if seed}
    owned = lambda p, k, v: 1.0 if seeds[p, k, v] else score.get((k, v)) if (k, v, "new") in score else None
    near, whole = (Counter(p for t in some for p in all_occurrences(texts[t])) for some in (with_places, range(len(texts))))
    precision = {}
    def confidence(key):
        own = [x for (p, k, v) in seeds if (p, k) == key and (x := owned(p, k, v)) is not None]
        return sum(own) / len(own) * precision[key][0]
    for _ in range(pii.ROUNDS):
        known = Counter((p, k) for (p, k, v) in seeds if (owned(p, k, v) or 0) >= pii.CONFIDENT)
        for key in [key for key, n in known.items() if n >= pii.MIN_SEEDS and key not in precision]:
            bound = times[key] / max(times[key], near[key[0]])
            precision[key] = (times[key] / max(times[key], whole[key[0]]), True) if bound >= pii.CONFIDENT else (bound, False)
        sure = {key: c for key in precision if precision[key][1] and (c := confidence(key)) >= pii.CONFIDENT}
        miss = defaultdict(lambda: 1.0)
        for (p, k, v), seed in seeds.items():
            if not seed and (p, k) in sure:
                miss[k, v] *= 1 - 0.9 * sure[p, k]
        if not miss:
            break
        for (k, v), x in miss.items():
            score[k, v], score[k, v, "new"] = 1 - x, True
    out = {key: (sum(seed for (p, k, v), seed in seeds.items() if (p, k) == key), confidence(key), precision[key][1] and confidence(key) >= pii.CONFIDENT) for key in precision}
    found = defaultdict(set)
    for t, kind, value, seed, s, e in places:
        if not seed and any(out.get((p, kind), (0, 0, False))[2] for p in induced(texts[t], s, e)):
            found[t].add(f"found_{kind}:{s}:{e}")
    return out, found


def test_the_graph_by_brute_force(docs_of):
    rng = random.Random(12)
    heads = ["please call me at ", "reach us: tel: ", "office tel:", "mail to ", "the host is ", "of the ", "in ", "my number ", "id "]
    def thing():
        n = lambda k: "".join(rng.choice("0123456789") for _ in range(k))
        phones, mails = [f"+1 ({n(3)}) 555-{n(4)}", f"({n(3)}) 555-{n(4)}", f"{n(3)}-{n(4)}"], [f"bob{n(2)} [at] mail.example", f"bob{n(2)}@mail.example.com"]
        value = rng.choice([*phones, *mails, f"10.{n(1)}.{n(2)}.7", f"10.{n(1)}.{n(2)}.7.9", n(16)])
        own = heads[0] if value in phones else heads[3] if value in mails else heads[4]
        return (own if rng.random() < 0.6 else rng.choice(heads)) + value
    texts = [" ".join(thing() + rng.choice([" any time", " today please", "", " and of the day"]) + "." * rng.randint(0, 1) for _ in range(rng.randint(1, 3))) for _ in range(150)]
    texts += ["of the day in the year", "my number is up", "in of in of in the", "tel: none, tel: none"] * 3
    want, found = bootstrap(texts)
    docs = docs_of([(i, t, "en", "s") for i, t in enumerate(texts)])
    scanned = stage(pii.scan(docs), "t")
    got = {(r.pattern, r.kind): (r.support, r.confidence, r.confident) for r in pii.scored_patterns(docs, scanned).collect()}
    assert got.keys() == want.keys() and len({p.split("|")[0] for p, _ in want}) == 4
    for key, (support, c, sure) in want.items():
        assert got[key][0] == support and got[key][1] == approx(c, 1e-6) and got[key][2] == sure, key
    assert {sure for *_, sure in want.values()} == {True, False} and found
    spans = {r.doc_id: {x for x in r.s.split(",") if x.startswith("found")} for r in pii.with_all_spans(docs, scanned).select("doc_id", S.joined(F.col("all_spans")).alias("s")).collect()}
    assert spans == {i: found.get(i, set()) for i in range(len(texts))}


def test_edges(edge, empty, spark, folder_of):
    d, e = folder_of("documents", edge), folder_of("documents", empty)
    for run in (secrets.op3_secret_scan, pii.op4_contextual_pii):
        assert run(spark, d).count() == 10 and run(spark, e).count() == 0
    assert secrets.redact(edge).count() == 10 and secrets.redact(empty).count() == 0
