"""Operators that SQL cannot express, against plain Python of their own; and every registered query over a small folder of tables."""

import datetime
import hashlib
import math
import os
import random
import re
import sys
import zlib
from fractions import Fraction
from pathlib import Path

import numpy as np
import pytest
from pyspark.sql import functions as F

sys.path.insert(0, str(Path(__file__).resolve().parents[1]))
from coverjoin.llm import pii, queries, secrets, toxicity  # noqa: E402

WORD = re.compile(r"[^\x20\x09-\x0D]+")
M32 = 0xFFFFFFFF


# -- toxicity


def plain_grams(text):
    b, out = b" " + (text or "").encode().lower() + b" ", set()
    for n in toxicity.GRAMS:
        for i in range(len(b) - n + 1):
            h = 0
            for c in b[i : i + n]:
                h = ((h ^ c) * 0x01000193) & M32
                h ^= h >> 15
            out.add(((h * 0x9E3779B1) & M32) >> (32 - toxicity.BITS))
    return out


def plain_classifier(rows, features, ridge=0.5):
    """Weights by gram and bias at the optimum, by Newton's method on a dense matrix."""
    sets, y = [plain_grams(t) for t, _ in rows], np.array([v for _, v in rows], float)
    p, n = y.sum(), len(y) - y.sum()
    ratio, gain = {}, {}
    for g in set().union(*sets):
        a, b = (sum(g in s for s, v in zip(sets, y) if v == c) for c in (1, 0))
        ratio[g] = math.log(((a + 1) / (p + 2)) / ((b + 1) / (n + 2)))
        gain[g] = abs(a / p - b / n) * abs(ratio[g])
    kept = sorted(gain, key=lambda g: (-gain[g], g))[:features]
    x = np.array([[ratio[g] * (g in s) for g in kept] + [1.0] for s in sets])
    w, pull = np.zeros(len(kept) + 1), np.diag([ridge] * len(kept) + [0.0])
    for _ in range(50):
        q = 1 / (1 + np.exp(-x @ w))
        w -= np.linalg.solve((x * (q * (1 - q))[:, None]).T @ x + pull, x.T @ (q - y) + pull @ w)
    return {g: ratio[g] * v for g, v in zip(kept, w)}, w[-1]


def test_toxicity_against_a_plain_classifier(spark):
    rng = random.Random(21)
    rows = [(" ".join(rng.choice(["calm", "river", "stone", "Vile", "GRIM", "odd"][: 3 + 3 * y]) for _ in range(rng.randint(1, 9))), y) for y in (0, 1) for _ in range(25)]
    rows += [("", 0), ("é vile \U0001f600", 1)]
    # every gram is a feature, so that equal gains do not matter
    model = toxicity.train(spark.createDataFrame(rows, "text string, label int"), features=1 << 14, steps=4000)
    weight, bias = plain_classifier(rows, 1 << 14)
    texts = [t for t, _ in rows] + [None, "vile " * 3000, "unseen text"]
    got = toxicity.score(spark.createDataFrame(list(enumerate(texts)), "i int, text string"), model).orderBy("i").collect()
    for r, t in zip(got, texts):
        own = sum(float(model.weight[g]) for g in plain_grams(t)) + model.bias
        assert abs(r["score"] - 1 / (1 + math.exp(-own))) < 1e-9
        best = sum(weight.get(g, 0.0) for g in plain_grams(t)) + bias
        assert abs(r["score"] - 1 / (1 + math.exp(-best))) < 2e-3


# -- secrets


def plain_features(t, before, after, odds):
    n, code = len(t), lambda c: ord(c) - 97 if "a" <= c <= "z" else 26 if "A" <= c <= "Z" else 27 if "0" <= c <= "9" else 28
    count = lambda p: len(re.findall(p, t)) / n
    left = re.sub("|".join(sorted(secrets.WORDS, key=len, reverse=True)), "", t.lower())
    yes = lambda p, s: float(bool(re.search(p, s)))
    return [
        float(n), count("[0-9]"), count("[A-Z]"), count("[a-z]"), count("[a-z]+|[A-Z]+|[0-9]+|[^A-Za-z0-9]+"), len(set(t)) / n,
        sum(round(odds[code(a) * 29 + code(b)], 4) for a, b in zip(t, t[1:])) / max(n - 1, 1), 1 - len(left) / n,
        yes("^(?:[0-9a-f]+|[0-9A-F]+)$", t), yes("^[0-9a-fA-F]{8}(-[0-9a-fA-F]{4}){3}-[0-9a-fA-F]{12}$", t), yes(secrets.VENDOR, t),
        t.count("/") / n, yes(r"(?:[/\\.]|https?:\S*)$", before), yes(r"^(?:[/\\(]|\.[a-z]{1,5}\b)", after), yes(secrets.NEAR, before), yes(secrets.FAR, before),
    ]


def plain_vote(node, x):
    while not isinstance(node, float):
        f, at, low, high = node
        node = low if x[f] <= at else high
    return round(node, 4)


def plain_secrets(text, model):
    forest, odds = model
    out = []
    for m in re.finditer(secrets.CANDIDATE, text or ""):
        x = plain_features(m[0], text[max(0, m.start() - secrets.BEFORE) : m.start()], text[m.end() : m.end() + secrets.AFTER], odds)
        p = sum(plain_vote(t, x) for t in forest) / len(forest)
        if p >= 0.5 - 1e-9:
            out.append((m.start(), m[0], p))
    return out


def secret_texts():
    rng = random.Random(3)
    found = secrets.generated_findings(200, seed=41)
    return ["".join(b + t + a + rng.choice([" some words ", "\n", "; "]) for t, b, a, _ in rng.sample(found, rng.randint(1, 6))) for _ in range(60)] + ["", None, "nothing here"]


@pytest.fixture(scope="module")
def forest(spark):
    return secrets.train(spark)


def test_secrets_against_a_plain_forest(spark, forest):
    model, texts = forest, secret_texts()
    got = secrets.scan(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), model, redacted="clean").orderBy("doc_id").collect()
    seen = 0
    for r, t in zip(got, texts):
        want = plain_secrets(t, model)
        assert [(f["start"], f["secret"]) for f in r["findings"]] == [w[:2] for w in want]
        assert all(abs(f["score"] - w[2]) < 1e-9 for f, w in zip(r["findings"], want))
        clean = t
        for at, s, _ in reversed(want):
            clean = clean[:at] + "[SECRET]" + clean[at + len(s) :]
        assert r["clean"] == clean
        seen += len(want)
    assert seen > 50


# -- pseudonyms


def number(*parts):
    return int(hashlib.sha256("|".join(map(str, parts)).encode()).hexdigest()[:15], 16)


def plain_pair(x, y, a, b, key, tweak):
    for i in range(pii.ROUNDS):
        if i % 2 == 0:
            x = (x + number(key, tweak, i, y)) % a
        else:
            y = (y + number(key, tweak, i, x)) % b
    return x, y


def plain_chars(value, mask, key, tweak):
    classes = {"d": "0123456789", "n": "23456789", "a": "abcdefghijklmnopqrstuvwxyz", "A": "ABCDEFGHIJKLMNOPQRSTUVWXYZ"}
    h = len(value) // 2
    l, lm, r, rm = value[:h], mask[:h], value[h:], mask[h:]
    for i in range(pii.ROUNDS):
        new = ""
        for j, (c, m) in enumerate(zip(l, lm)):
            k = int(hashlib.sha256(f"{key}|{tweak}|{i}|{r}|{j // 15}".encode()).hexdigest()[4 * (j % 15) :][:4], 16)
            new += classes[m][(classes[m].index(c) + k) % len(classes[m])] if m in classes else c
        l, lm, r, rm = r, rm, new, lm
    return l + r


def into(value, digits):
    it = iter(digits)
    return "".join(next(it) if c.isdigit() else c for c in value)


def luhn(d, odd):
    return sum(sum(divmod(int(c) * (2 if i % 2 == odd else 1), 10)) for i, c in enumerate(reversed(d)))


def plain_pseudonym(kind, v, key):
    d = re.sub(r"\D", "", v)
    if kind == "card":
        if luhn(d, 1) % 10:
            return None
        new = plain_chars(d[:-1], "d" * (len(d) - 1), key, "card")
        return into(v, new + str(-luhn(new, 0) % 10))
    if kind == "phone":
        return into(v, d[:-10] + plain_chars(d[-10:], "nddndddddd", key, "phone"))
    if kind == "email":
        own, domain = v.split("@")
        mask = "".join("d" if c.isdigit() else "a" if c.islower() else "A" if c.isupper() else "-" for c in own)
        return f"{plain_chars(own, mask, key, 'email')}@{domain}"
    if kind == "ssn":
        areas = [a for a in range(1, 900) if a != 666]
        a, g, s = map(int, v.split("-"))
        if a not in areas or not g or not s:
            return None
        x, y = plain_pair(areas.index(a) * 99 + g - 1, s - 1, 898 * 99, 9999, key, "ssn")
        return f"{areas[x // 99]:03d}-{x % 99 + 1:02d}-{y + 1:04d}"
    if kind == "ip":
        o = v.split(".")
        if any(int(x) > 255 or str(int(x)) != x for x in o):
            return None
        o = [*map(int, o)]
        x, y = plain_pair(o[0] * 256 + o[1], o[2] * 256 + o[3], 65536, 65536, key, "ip")
        return ".".join(map(str, (x // 256, x % 256, y // 256, y % 256)))
    form = f"%Y{v[4]}%m{v[4]}%d" if not v[4].isdigit() else "%m/%d/%Y" if v[2] == "/" else f"%d{v[2]}%m{v[2]}%Y"
    try:
        k = (datetime.datetime.strptime(v, form) - datetime.datetime(1900, 1, 1)).days
    except ValueError:
        return None
    if not 0 <= k < 17 * 4297:
        return None
    x, y = plain_pair(k // 4297, k % 4297, 17, 4297, key, "date")
    return (datetime.datetime(1900, 1, 1) + datetime.timedelta(days=x * 4297 + y)).strftime(form)


def personal_values():
    rng = random.Random(17)
    digits = lambda n: "".join(rng.choice("0123456789") for _ in range(n))
    out = []
    for i in range(12):
        body = "4" + digits(14)
        card = body + str(-luhn(body, 0) % 10)
        out += [("card", " ".join(card[k : k + 4] for k in (0, 4, 8, 12))), ("card", card), ("card", card[:-1] + str((int(card[-1]) + 1) % 10))]
        out.append(("phone", rng.choice(["+1 ({}) {}-{}", "{}.{}.{}", "{}-{}-{}"]).format(f"{rng.randint(200, 999)}", f"{rng.randint(200, 999)}", digits(4))))
        out.append(("email", f"{rng.choice(['Al', 'b', 'mixed.Case_9'])}{i}@mail{i}.example.org"))
        out.append(("ssn", f"{rng.choice([1, 665, 666, 667, 899, 900, 0]):03d}-{rng.randint(0, 2):02d}-{rng.randint(1, 9999):04d}"))
        out.append(("ip", f"{rng.randint(0, 300)}.{rng.randint(0, 255)}.{rng.choice(['01', '7'])}.{rng.randint(0, 255)}"))
        y, m, d = rng.randint(1890, 2105), rng.randint(1, 13), rng.randint(1, 31)
        out.append(("date", rng.choice([f"{y}-{m:02d}-{d:02d}", f"{y}/{m:02d}/{d:02d}", f"{m:02d}/{d:02d}/{y}", f"{d:02d}.{m:02d}.{y}", f"{d:02d}-{m:02d}-{y}"])))
    return [*out, ("date", "1900-02-29"), ("date", "2000-02-29"), ("date", "2099-12-31"), ("date", "1900-01-01")]


def test_pseudonyms_against_a_plain_feistel_network(spark):
    values = personal_values()
    rows = [(i, f"see {v} there") for i, (_, v) in enumerate(values)]
    got = pii.pseudonymise(spark.createDataFrame(rows, "doc_id long, text string"), "some key").orderBy("doc_id").collect()
    kinds = set()
    for r, (kind, v) in zip(got, values):
        new = plain_pseudonym(kind, v, "some key")
        assert r["text"] == f"see {v if new is None else new} there", (kind, v)
        assert [(f["kind"], f["value"], f["pseudonym"]) for f in r["findings"]] == ([] if new is None else [(kind, v, new)])
        kinds.add((kind, new is None))
    assert {k for k, none in kinds if not none} == set(pii.KINDS) and {k for k, none in kinds if none} >= {"card", "ssn", "ip", "date"}


# -- the registered queries


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    """Tables with nulls, empty texts, copies, near copies, a long text and a source that holds most rows."""
    rng = random.Random(77)
    at, vocabulary = tmp_path_factory.mktemp("tables"), [f"word{i}" for i in range(400)]
    texts = [" ".join(rng.choice(vocabulary) for _ in range(rng.randint(15, 60))) for _ in range(30)]
    near = [t.replace(t.split()[7], "Changed", 1) for t in texts[:6]]
    shared = " ".join(f"common{i}" for i in range(60))
    texts += [*near, *near, texts[0], texts[0].upper(), None, "", "  \t ", "one", "one", "two words", f"start {shared} end", f"other {shared}", "tail " + texts[9]]
    texts += ["long text " + " ".join(rng.choice(vocabulary) for _ in range(20000)), *secret_texts()[:5], *(f"see {v} there" for _, v in personal_values()[:20])]
    toxic = [i for i in range(len(texts)) if i % 4 == 0]
    texts = [f"zotplague {t} snarkwort" if i in toxic and t and len(t) > 60 else t for i, t in enumerate(texts)]
    docs = [(3 * i + 1, t, None if i % 7 == 0 else "en", None if i == 11 else "hot" if i % 3 else f"s{i % 5}", None if t is None else len(t)) for i, t in enumerate(texts)]
    spark.createDataFrame(docs, "doc_id long, text string, lang string, source string, n_chars long").repartition(3).write.parquet(f"{at}/documents.parquet")
    spark.createDataFrame([(d[0], int(i in toxic)) for i, d in enumerate(docs)], "doc_id long, toxic int").write.parquet(f"{at}/labels.parquet")
    base = [[rng.gauss(0, 1) for _ in range(16)] for _ in range(60)]
    vectors = base + [[x + rng.gauss(0, 0.01) for x in v] for v in base[:25]] + base[:10] + [[x * 3.5 for x in v] for v in base[:5]] + [None, [0.0] * 16, [1.0, None] + [0.0] * 14, [float("nan")] + [1.0] * 15, [float("inf")] + [1.0] * 15]
    spark.createDataFrame([(5 * i, v, None if i % 9 == 4 else i % 2) for i, v in enumerate(vectors)], "vec_id long, embedding array<float>, label int").write.parquet(f"{at}/embeddings.parquet")
    pages = [None, "", "a" * 99, "a" * 99, "é" * 50, "é" * 50, "b" * 100, "b" * 100, "b" * 100, "<p>" + "text " * 40000, "<p>x</p>" * 20]
    spark.createDataFrame([(100 - i, f"http://x.org/{i}" if i % 4 else None, h) for i, h in enumerate(pages)], "page_id long, url string, html string").write.parquet(f"{at}/pages.parquet")
    return str(at)


def rows_of(spark, folder, name):
    return [r.asDict() for r in queries.QUERIES[name](spark, folder).collect()]


def documents(spark, folder):
    return {r["doc_id"]: r for r in spark.read.parquet(f"{folder}/documents.parquet").collect()}


@pytest.mark.parametrize("name", sorted(set(queries.ORACLES) - {"op8_cap_filters"}))
def test_registered_queries_equal_their_sql(spark, folder, name):
    import duckdb

    con = duckdb.connect()
    for t in ("documents", "embeddings", "pages"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{folder}/{t}.parquet/*.parquet'")
    want = con.sql(queries.ORACLES[name])
    df = queries.QUERIES[name](spark, folder).select(*want.columns)
    assert sorted(map(repr, map(tuple, df.collect()))) == sorted(map(repr, want.fetchall()))


def test_registered_cap_filters(spark, folder):
    """Its SQL computes cosines of all pairs and so stops at a null component: all pairs in Python instead."""
    rows = {r["vec_id"]: r for r in spark.read.parquet(f"{folder}/embeddings.parquet").collect()}
    fit = {i: np.array(r["embedding"], float) for i, r in rows.items() if r["embedding"] and None not in r["embedding"] and np.isfinite(r["embedding"]).all() and any(r["embedding"])}
    links = {i: {j for j, w in fit.items() if j != i and rows[i]["label"] is not None and rows[i]["label"] == rows[j]["label"] and float(v @ w) / math.sqrt(float(v @ v) * float(w @ w)) >= 0.98} for i, v in fit.items()}
    low = {i: i for i in rows}
    for _ in rows:
        low = {i: min([low[i], *(low[j] for j in links.get(i, ()))]) for i in low}
    got = rows_of(spark, folder, "op8_cap_filters")
    assert sorted((r["vec_id"], r["n_links"], r["component_id"], r["kept"]) for r in got) == sorted((i, len(links.get(i, ())), low[i], low[i] == i) for i in rows)
    assert sum(map(len, links.values())) > 20


@pytest.mark.skipif(not os.path.exists(queries.MODEL), reason="no vocabulary file")
def test_registered_pieces(spark, folder):
    import sentencepiece as sp

    library, docs = sp.SentencePieceProcessor(model_file=queries.MODEL), documents(spark, folder)
    got = rows_of(spark, folder, "op1_sentencepiece")
    assert sorted(r["doc_id"] for r in got) == sorted(docs)
    for r in got:
        text = docs[r["doc_id"]]["text"]
        if text is not None:
            assert r["ids"] == library.encode(text) and r["n_ids"] == len(r["ids"]) and r["round_trip"]


def test_registered_neighbours(spark, folder):
    vectors = {r["vec_id"]: r["embedding"] for r in spark.read.parquet(f"{folder}/embeddings.parquet").collect()}
    fit = {i: np.array(v, float) for i, v in vectors.items() if v and None not in v and np.isfinite(v).all() and any(v)}
    cosine = lambda a, b: float(a @ b / math.sqrt(float(a @ a) * float(b @ b)))
    got, hits, total = {}, 0, 0
    for r in rows_of(spark, folder, "op3_neighbours"):
        got.setdefault(r["query_id"], {})[r["rank"]] = (r["vec_id"], r["score"])
    assert set(got) == {i for i in fit if i % 50 == 0}
    for q, found in got.items():
        assert sorted(found) == [1, 2, 3, 4, 5] and q not in {v for v, _ in found.values()}
        assert all(abs(s - cosine(fit[q], fit[v])) < 1e-12 for v, s in found.values())
        assert [found[k] for k in range(1, 6)] == sorted(found.values(), key=lambda p: (-p[1], p[0]))
        best = sorted((-cosine(fit[q], v), i) for i, v in fit.items() if i != q)[:5]
        hits, total = hits + sum(-s <= found[5][1] + 1e-12 or i in {v for v, _ in found.values()} for s, i in best), total + 5
    assert hits >= 0.9 * total


def plain_targets(sizes, weights):
    """Shares by weight in exact fractions; the sources that stop are found one at a time, the tightest first."""
    order = sorted((s for s in sizes if sizes[s]), key=lambda s: Fraction(3 * sizes[s], weights[s]))
    left, out = Fraction(sum(sizes.values())), dict.fromkeys(sizes, Fraction(0))
    for k, s in enumerate(order):
        share = left * weights[s] / sum(weights[x] for x in order[k:])
        out[s] = min(share, Fraction(3 * sizes[s]))
        left -= out[s]
    return out


def test_registered_mix(spark, folder):
    docs, got = documents(spark, folder), rows_of(spark, folder, "op4_source_mix")
    size = {i: len(WORD.findall(d["text"] or "")) for i, d in docs.items()}
    sources = sorted({d["source"] for d in docs.values() if d["source"] is not None}, key=lambda s: s.encode()) + [None]
    of = {s: sum(size[i] for i, d in docs.items() if d["source"] == s) for s in sources}
    target = plain_targets(of, {s: (5, 2, 1)[k % 3] for k, s in enumerate(sources)})
    assert sorted(r["doc_id"] for r in got) == sorted(docs)
    taken = dict.fromkeys(sources, 0)
    for r in got:
        s = docs[r["doc_id"]]["source"]
        assert r["size"] == size[r["doc_id"]] and r["source_size"] == of[s] and math.isclose(r["target"], target[s], abs_tol=1e-6)
        assert 0 <= r["taken"] <= 3 * r["size"]
        taken[s] += r["taken"]
    assert all(abs(taken[s] - target[s]) <= 1 for s in sources)
    assert sorted(map(repr, got)) == sorted(map(repr, rows_of(spark, folder, "op4_source_mix")))


def test_registered_toxicity(spark, folder):
    docs, got = documents(spark, folder), rows_of(spark, folder, "op5_toxicity")
    assert sorted(r["doc_id"] for r in got) == sorted(docs)
    for r in got:
        assert r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1) and 0 <= r["score"] <= 1 and r["predicted"] == int(r["score"] >= 0.7)
    right = [r["predicted"] == int("zotplague" in (docs[r["doc_id"]]["text"] or "")) for r in got if r["held_out"]]
    assert sum(right) >= 0.8 * len(right)


def test_registered_secrets_and_pseudonyms(spark, folder, forest):
    docs, model = documents(spark, folder), forest
    sha = lambda t: None if t is None else hashlib.sha256(t.encode()).hexdigest()
    got = rows_of(spark, folder, "op6_secrets")
    assert sorted(r["doc_id"] for r in got) == sorted(docs)
    for r in got:
        text = docs[r["doc_id"]]["text"]
        want = plain_secrets(text, model)
        for at, s, _ in reversed(want):
            text = text[:at] + "[SECRET]" + text[at + len(s) :]
        assert r["n_secrets"] == len(want) and r["redacted_sha256"] == sha(text)
    plain = {f"see {v} there": plain_pseudonym(k, v, queries.PII_KEY) or v for k, v in personal_values()[:20]}
    got = {r["doc_id"]: r for r in rows_of(spark, folder, "op7_pii")}
    assert sorted(got) == sorted(docs)
    for i, d in docs.items():
        if d["text"] in plain:
            assert got[i]["text_sha256"] == sha(f"see {plain[d['text']]} there")
        elif d["text"] is None or not re.search(r"\d{3}|@", d["text"]):
            assert got[i]["n_found"] == 0 and got[i]["text_sha256"] == sha(d["text"])


def test_spark_sum_of_checks_is_plain(spark):
    """The Luhn sums that validation and new check digits use."""
    rows = [("".join(random.Random(i).choice("0123456789") for _ in range(12 + i % 8)),) for i in range(60)]
    for r in spark.createDataFrame(rows, "d string").select("d", pii.luhn_sum(F.col("d"), False).alias("a"), pii.luhn_sum(F.col("d"), True).alias("b")).collect():
        assert (r["a"], r["b"]) == (luhn(r["d"], 1), luhn(r["d"], 0))
