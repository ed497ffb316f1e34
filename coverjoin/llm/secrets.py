"""Secret scans: candidates by pattern, false positives removed by a random forest, in Spark's own expressions only.

A candidate is a vendor-style key, a private key block, or a run of at least 12 key characters. The forest looks at its length and
make-up, its character transitions (log odds of character pairs), how much of it dictionary words cover, whether it stands
in a path, and the words next to it. It is trained on labelled findings - given by the caller, or the built-in generated
ones - in the driver, on at most ``LABELLED`` of them, and becomes one column expression.
"""

from __future__ import annotations

import random
import string

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import native
from .common import named, plain

LABELLED = 6000
#: Characters of the text looked at before and behind a candidate, and the shortest candidate.
BEFORE, AFTER, LEAST = 48, 24, 12
EDGE = r"(?:[A-Z]+ )*PRIVATE KEY-----"
#: From a BEGIN line to its END line, however far, but not past another BEGIN; where the END is missing, the lines of key characters.
BLOCK = rf"-----BEGIN {EDGE}(?:[^-]*+(?:-(?!----(?:BEGIN|END) {EDGE})[^-]*+)*+-----END {EDGE}|(?:(?:\s|\\[nr])++[A-Za-z0-9+/=]{{16,}}+)++)"
CANDIDATE = BLOCK + r"|eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}|(?<![A-Za-z0-9_+-])[A-Za-z0-9_+-][A-Za-z0-9_+/-]{11,}={0,2}"
VENDOR = r"^(?:(?:AKIA|ASIA)[0-9A-Z]{16}|gh[pousr]_[A-Za-z0-9]{30,}|xox[abprs]-[A-Za-z0-9-]{20,}|AIza[A-Za-z0-9_-]{30,}|sk_live_[A-Za-z0-9]{20,}|glpat-[A-Za-z0-9_-]{20,}|-----BEGIN[\s\S]*|eyJ[A-Za-z0-9_-]+\.[A-Za-z0-9_-]+\..*)$"
NEAR = r"(?i)(?:pass(?:word|wd|phrase)?|pwd|secret|token|api[_-]?key|access[_-]?key|auth|credentials?|bearer|private[_-]?key|client[_-]?secret)[\"']?\s*(?:=|:|=>|:=|\bis\b)?\s*[\"']?$"
FAR = r"(?i)(?:commit|sha-?\d*|md5|checksum|digest|etag|uuid|guid|build|version|revision|blob|tree|image|hash|id)[\"']?\s*(?:=|:|\bis\b)?\s*[\"']?$"
#: Words that benign identifiers are made of.
WORDS = "about access account action address admin after agent alpha answer array audio before beta block board body bridge browser buffer build button cache call card center change channel chart check child class clear click client cloud code color column command common component config connect content context control core count create current custom data database date default delete design detail device dialog directory display document domain double download driver edit element email enable engine error event example export factory field file filter final folder font format frame function global graph group handle header height hidden history home host image import index inner input insert install instance item label language layout left length level library light limit line link list load local lock login main manager map master media member memory menu message meta method mode model module mouse name network node null number object open option order output owner package page panel parent parser path pattern phone picker place player plugin point port position post prefix print process product profile project property provider proxy public query queue random read record region register remote remove render report request reset resource response result return right root route scale schema screen script search section select sender server service session setting shape share shell signal simple size source space stack start state status stop storage store stream string style submit switch system table target task template test text theme thread time title toggle tool total track tree type unit update upload user util value variable version video view web width window word work worker wrapper write your".split()
#: Letters, then upper case, digit, other: the classes of the transition table.
SYMBOLS = 29
PIECE = 512


def _code(c: Column) -> Column:
    return F.when(c.between("a", "z"), F.ascii(c) - 97).when(c.between("A", "Z"), 26).when(c.between("0", "9"), 27).otherwise(28)


def features(token: Column, before: Column, after: Column, odds: list[float]) -> Column:
    """The forest's inputs, an array of doubles in the order of FEATURES. ``odds``: log odds of each pair of classes."""
    table = F.array(*(F.lit(round(x, 4)) for x in odds))

    def use(t: Column) -> Column:
        n = F.length(t).cast("double")
        share = lambda p: F.length(F.regexp_replace(t, p, "")) / n
        runs = F.length(F.regexp_replace(t, "[a-z]+|[A-Z]+|[0-9]+|[^A-Za-z0-9]+", "x")) / n
        # in pieces, so that a long token is never an array of its characters; a piece's pairs start with the last character before it
        def pair_sums(pieces: Column) -> Column:
            def pairs(p: Column, i: Column) -> Column:
                joined = F.concat(F.when(i > 0, F.right(F.element_at(pieces, F.greatest(i, F.lit(1))), F.lit(1))).otherwise(""), p)
                return F.element_at(F.transform(F.array(F.transform(native.chars(joined), _code)), odd), 1)

            return F.struct(F.transform(pieces, pairs).alias("sums"), F.size(F.array_distinct(F.flatten(F.transform(pieces, lambda p: F.array_distinct(native.chars(p)))))).alias("distinct"))

        def odd(codes: Column) -> Column:
            two = F.zip_with(F.slice(codes, 1, F.size(codes) - 1), F.slice(codes, 2, F.size(codes) - 1), lambda a, b: F.element_at(table, a * SYMBOLS + b + 1))
            return F.aggregate(two, F.lit(0.0), lambda a, x: a + x)

        by_piece = F.element_at(F.transform(F.array(native.matches(t, rf"[\s\S]{{1,{PIECE}}}")), pair_sums), 1)
        trans = F.aggregate(by_piece["sums"], F.lit(0.0), lambda a, x: a + x) / F.greatest(n - 1, F.lit(1.0))
        covered = 1 - F.length(F.regexp_replace(F.lower(t), "|".join(sorted(WORDS, key=len, reverse=True)), "")) / n
        flag = lambda c: c.cast("int").cast("double")
        return F.array(
            n, share("[^0-9]"), share("[^A-Z]"), share("[^a-z]"), runs, by_piece["distinct"] / n, trans, covered,
            flag(t.rlike("^[0-9a-f]+$|^[0-9A-F]+$")), flag(t.rlike(r"^[0-9a-fA-F]{8}(-[0-9a-fA-F]{4}){3}-[0-9a-fA-F]{12}$")), flag(t.rlike(VENDOR)),
            F.length(F.regexp_replace(t, "[^/]", "")) / n, flag(before.rlike(r"(?:[/\\.]|https?:\S*)$")), flag(after.rlike(r"^(?:[/\\(]|\.[a-z]{1,5}\b)")),
            flag(before.rlike(NEAR)), flag(before.rlike(FAR)),
        )

    return F.element_at(F.transform(F.array(token), use), 1)


FEATURES = ("length", "digits", "upper", "lower", "runs", "distinct", "transitions", "words", "hex", "uuid", "vendor", "slashes", "path_before", "path_after", "near", "far")


def generated_findings(n: int = 4000, seed: int = 7) -> list[tuple[str, str, str, int]]:
    """Labelled findings (token, before, after, label) drawn from rules: keys and passwords next to and away from words that
    announce them, web tokens and key blocks of any length, and the usual false alarms - identifiers, long words, paths, digests,
    UUIDs, placeholders, embedded files."""
    r = random.Random(seed)
    pick = lambda a, k: "".join(r.choice(a) for _ in range(k))
    hexa, b64, up = "0123456789abcdef", string.ascii_letters + string.digits + "+/", string.ascii_uppercase + "234567"
    syllables = ["th", "er", "in", "on", "an", "re", "ed", "ti", "es", "or", "en", "at", "st", "nd", "ing", "ion", "ble", "ment", "sch", "keit", "ung", "eau", "eux", "aire", "tre", "que", "os", "mente", "aci", "lla", "ver", "pf"]
    say = ["password=", "passwd: ", "token = \"", "secret: '", "api_key = \"", "API_KEY=", "auth: ", "client_secret=", "Bearer ", "access_key: ", "pwd = '"]
    dull = ["the ", "and with ", ". ", "and see ", "\n", "of it, ", "(", "word "]
    calm = ["commit ", "sha256: ", "md5 = ", "checksum: ", "etag: \"", "build ", "version: ", "uuid = ", "image: ", "hash: ", "id: "]
    out = []
    for _ in range(n):
        x = r.random()
        if x < 0.12:
            out.append((r.choice(["AKIA", "ASIA"]) + pick(up, 16), r.choice(dull + say), " and", 1))
        elif x < 0.18:
            out.append((r.choice(["ghp_" + pick(b64[:62], 36), "xoxb-" + pick("0123456789", 12) + "-" + pick(b64[:62], 24), "AIza" + pick(b64[:62], 35), "sk_live_" + pick(b64[:62], 24), "glpat-" + pick(b64[:62], 20)]), r.choice(dull + say), " ", 1))
        elif x < 0.36:
            out.append((pick(hexa, r.choice([16, 18, 20, 24, 32, 32, 40, 40, 48, 64])), r.choice(say), r.choice(["\"", "'", " ", "\n"]), 1))
        elif x < 0.48:
            out.append((pick(b64, r.randint(16, 64)) + r.choice(["", "", "=", "=="]), r.choice(say), r.choice(["\"", " ", "\n"]), 1))
        elif x < 0.64:
            w = pick(syllables, r.randint(5, 12))
            out.append((r.choice([w, w, w.upper(), w.title()]), r.choice(dull + say[:1] + ["!! ", "*** "]), r.choice([" ", ".", ", ", "!!", "###"]), 0))
        elif x < 0.72:
            w = [r.choice(WORDS) for _ in range(r.randint(2, 5))]
            out.append((r.choice(["_".join(w), "-".join(w), w[0] + "".join(v.title() for v in w[1:]), "".join(v.title() for v in w)]).ljust(12, "s"), r.choice(dull + say), r.choice(["(", " ", ".py", " = "]), 0))
        elif x < 0.80:
            out.append(("/".join(r.choice([r.choice(WORDS), pick(syllables, 3), pick(hexa, 8)]) for _ in range(r.randint(3, 6))).ljust(12, "/"), r.choice(["https://x.org/", "./", "src/", "in ", "C:\\"]), r.choice([".py", ".html", " ", "/"]), 0))
        elif x < 0.88:
            out.append((pick(hexa, r.choice([32, 40, 64])), r.choice(calm), r.choice([" ", "\n", "\""]), 0))
        elif x < 0.93:
            out.append(("-".join(pick(hexa, k) for k in (8, 4, 4, 4, 12)), r.choice(calm + dull + say[:2]), " ", 0))
        elif x < 0.96:
            out.append((pick("0123456789", r.randint(12, 20)), r.choice(dull + calm), " ", 0))
        else:
            out.append((r.choice(["x" * r.randint(12, 40), "your_api_key_here", "changeme_changeme", "-" * r.randint(12, 60), "_" * 20, "example_secret_value", "0" * 32, "a" * 40, "your-token-goes-here", "+" * 16]), r.choice(say), "\"", 0))
    url = b64[:62] + "-_"
    lines = lambda k: "\n".join(pick(b64, 64) for _ in range(k))
    for _ in range(n // 40):
        out.append(("eyJ" + pick(url, r.randint(10, 1500)) + "." + pick(url, r.randint(20, 3000)) + "." + pick(url, r.choice([43, 86, 342])), r.choice(dull + say), r.choice([" ", "\"", "\n"]), 1))
        kind = r.choice(["", "RSA ", "EC ", "OPENSSH ", "ENCRYPTED "])
        out.append((f"-----BEGIN {kind}PRIVATE KEY-----\n{lines(r.randint(1, 200))}\n-----END {kind}PRIVATE KEY-----", r.choice(dull + say), "\n", 1))
        out.append((pick(b64, r.randint(65, 800)), r.choice(say), r.choice(["\"", " ", "\n"]), 1))
        out.append((pick(b64, r.randint(100, 12000)), r.choice(["data:image/png;base64,", "base64,", *dull]), r.choice(["\"", ")", " "]), 0))
        out.append((r.choice(["/", "-", "_"]).join(r.choice(WORDS) for _ in range(r.randint(20, 200))), r.choice(["https://x.org/", "in ", *dull]), r.choice([".html", " "]), 0))
        out.append((r.choice("x=-_0a+") * r.randint(60, 3000), r.choice(dull + say), " ", 0))
    return out


def pair_odds(rows: list[tuple[str, str, str, int]]) -> list[float]:
    """From the first 512 characters of each labelled finding, so that a few long ones do not outweigh the rest; only here."""
    code = lambda c: ord(c) - 97 if "a" <= c <= "z" else 26 if "A" <= c <= "Z" else 27 if "0" <= c <= "9" else 28
    n = np.ones((2, SYMBOLS * SYMBOLS))
    for t, _, _, y in rows:
        cs = [code(c) for c in t[:512]]
        for a, b in zip(cs, cs[1:]):
            n[y, a * SYMBOLS + b] += 1
    p = n / n.sum(axis=1, keepdims=True)
    return list(np.log(p[1] / p[0]))


def _grow(x: np.ndarray, y: np.ndarray, rng: np.random.Generator, depth: int, least: int, tries: int):
    if depth == 0 or len(y) < 2 * least or y.min() == y.max():
        return float((y.sum() + 0.5) / (len(y) + 1))
    best = None
    for f in rng.choice(x.shape[1], tries, replace=False):
        order = np.argsort(x[:, f], kind="stable")
        v, c = x[order, f], np.cumsum(y[order])
        k = np.arange(1, len(y))
        ok = (v[1:] > v[:-1]) & (k >= least) & (len(y) - k >= least)
        if ok.any():
            p, q = c[:-1] / k, (c[-1] - c[:-1]) / (len(y) - k)
            gini = np.where(ok, k * p * (1 - p) + (len(y) - k) * q * (1 - q), np.inf)
            i = int(gini.argmin())
            if best is None or gini[i] < best[0]:
                best = (gini[i], int(f), float((v[i] + v[i + 1]) / 2))
    if best is None:
        return float((y.sum() + 0.5) / (len(y) + 1))
    _, f, at = best
    low = x[:, f] <= at
    return (f, at, _grow(x[low], y[low], rng, depth - 1, least, tries), _grow(x[~low], y[~low], rng, depth - 1, least, tries))


def train(spark: SparkSession, labelled: list[tuple[str, str, str, int]] | None = None, trees: int = 24, depth: int = 7, least: int = 4, seed: int = 11) -> tuple[list, list[float]]:
    """(forest, pair odds). Features of the labelled findings come from the same expressions as those of the scan."""
    rows = (labelled or generated_findings())[:LABELLED]
    odds = pair_odds(rows)
    df = spark.createDataFrame([(i, *r) for i, r in enumerate(rows)], "i int, token string, before string, after string, label int")
    got = df.select("i", features(F.col("token"), F.col("before"), F.col("after"), odds).alias("x"), "label").orderBy("i").collect()
    x, y = np.array([g["x"] for g in got]), np.array([g["label"] for g in got], float)
    rng = np.random.default_rng(seed)
    forest = []
    for _ in range(trees):
        take = rng.integers(0, len(y), len(y))
        forest.append(_grow(x[take], y[take], rng, depth, least, max(2, int(np.sqrt(x.shape[1])) + 1)))
    return forest, odds


def probability(x: Column, forest: list) -> Column:
    """Mean vote of the trees, each a nest of conditions on the array of features."""
    def walk(node) -> Column:
        if isinstance(node, float):
            return F.lit(round(node, 4))
        f, at, low, high = node
        return F.when(x[f] <= at, walk(low)).otherwise(walk(high))

    out = walk(forest[0])
    for t in forest[1:]:
        out = out + walk(t)
    return out / len(forest)


def contexts(found: Column, between: Column) -> Column:
    """(before, after) of each match: the BEFORE and AFTER characters of the text around it, other matches included. Each gap and
    match has 12 characters together at least, so four of them before and two behind are enough, and no text is walked from its start."""
    tails = F.transform(found, lambda m, i: F.right(F.concat(F.right(F.element_at(between, i + 1), F.lit(BEFORE)), F.right(m, F.lit(BEFORE))), F.lit(BEFORE)))
    heads = F.transform(found, lambda m, i: F.left(F.concat(F.left(m, F.lit(AFTER)), F.left(F.element_at(between, i + 2), F.lit(AFTER))), F.lit(AFTER)))

    def use(x: Column) -> Column:
        def one(m: Column, i: Column) -> Column:
            low = F.greatest(i - BEFORE // LEAST, F.lit(0))
            before = F.concat(F.array_join(F.slice(x["tails"], low + 1, i - low), ""), F.right(F.element_at(between, i + 1), F.lit(BEFORE)))
            after = F.concat(F.left(F.element_at(between, i + 2), F.lit(AFTER)), F.array_join(F.slice(x["heads"], i + 2, F.lit(AFTER // LEAST)), ""))
            return F.struct(F.right(before, F.lit(BEFORE)).alias("before"), F.left(after, F.lit(AFTER)).alias("after"))

        return F.transform(found, one)

    return F.element_at(F.transform(F.array(F.struct(tails.alias("tails"), heads.alias("heads"))), use), 1)


def scan(docs: DataFrame, model: tuple[list, list[float]], text: str = "text", findings: str = "findings", redacted: str | None = None, least: float = 0.5, mask: str = "[SECRET]") -> DataFrame:
    """Add ``findings``, an array of (start, secret, score) in text order (start counts characters from 0), and, if named,
    ``redacted``: the text with each secret replaced by ``mask``. A null text has none and stays null. Columns of those
    names are replaced, others pass. Nothing is shuffled; texts without candidates are only scanned."""
    forest, odds = model
    docs, to = plain(docs)
    t = F.col(to[text])
    struct = "array<struct<start:int,secret:string,score:double>>"
    some = t.rlike(CANDIDATE)
    df = docs.withColumn("_m", F.when(some, native.matches(t, CANDIDATE)).otherwise(F.array().cast("array<string>")))
    df = df.withColumn("_g", F.when(some, native.gaps(t, CANDIDATE)).otherwise(F.array().cast("array<string>")))
    df = df.withColumn("_c", F.when(some, contexts(F.col("_m"), F.col("_g"))).otherwise(F.array().cast("array<struct<before:string,after:string>>")))
    seen = F.transform(F.arrays_zip("_m", "_c"), lambda p: F.struct(features(p["_m"], p["_c"]["before"], p["_c"]["after"], odds).alias("x")))
    df = df.withColumn("_s", F.transform(seen, lambda s: probability(s["x"], forest)))
    # running lengths: the gaps and matches before each match
    lens = F.zip_with(F.transform("_g", lambda g: F.length(g)), F.transform("_m", lambda m: F.length(m)), lambda a, b: F.struct(F.coalesce(a, F.lit(0)).alias("g"), F.coalesce(b, F.lit(0)).alias("m")))
    starts = F.aggregate(lens, F.struct(F.lit(0).alias("at"), F.array().cast("array<int>").alias("all")), lambda a, x: F.struct((a["at"] + x["g"] + x["m"]).alias("at"), F.concat(a["all"], F.array(a["at"] + x["g"])).alias("all")))["all"]
    hit = F.exists("_s", lambda s: s >= least)
    found = F.filter(F.zip_with(F.zip_with("_m", "_s", lambda m, s: F.struct(m.alias("m"), s.alias("s"))), F.slice(starts, F.lit(1), F.size("_m")), lambda p, at: F.struct(at.alias("start"), p["m"].alias("secret"), p["s"].alias("score"))), lambda x: x["score"] >= least)
    df = df.withColumn("_f", F.when(F.coalesce(hit, F.lit(False)), found).otherwise(F.array().cast(struct)))
    if redacted:
        clean = native.weave(F.col("_g"), F.zip_with("_m", "_s", lambda m, s: F.when(s >= least, F.lit(mask)).otherwise(m)))
        df = df.withColumn("_r", F.when(F.size("_f") > 0, clean).otherwise(t))
    return named(df, to, {findings: "_f"} | ({redacted: "_r"} if redacted else {}))
