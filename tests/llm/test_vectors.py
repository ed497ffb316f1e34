import hashlib
import random
import sys
from pathlib import Path

import numpy as np
import pytest

sys.path.insert(0, str(Path(__file__).resolve().parents[1]))
from coverjoin.llm import ann, caps, warc  # noqa: E402

SCHEMA = "vec_id long, embedding array<float>, label int, v string, id long"


def vectors(spark, rows):
    return spark.createDataFrame([(i, None if e is None else [None if x is None else float(x) for x in e], y, "clash", -1) for i, e, y in rows], SCHEMA)


def sample(seed, n=300, dim=24):
    rng = np.random.default_rng(seed)
    x = rng.standard_normal((n, dim)).astype(np.float32)
    for i in range(60):
        x[n - 1 - i] = x[i % 7] + (rng.standard_normal(dim) * rng.choice([0.01, 0.05, 0.12])).astype(np.float32)
    rows = [(i, x[i].tolist(), int(i % 3) if i % 11 else None) for i in range(n)]
    rows += [(n, x[0].tolist(), 0), (n + 1, x[0].tolist(), 0), (n + 2, (x[0] * 2).tolist(), 0), (n + 3, [0.0] * dim, 0), (n + 4, None, 0), (n + 5, [float("nan")] + [1.0] * (dim - 1), 0), (n + 6, [None] + [1.0] * (dim - 1), 0), (n + 7, [float("inf")] + [1.0] * (dim - 1), 0), (n + 8, [1.0, 2.0], 0), (n + 9, [2.0, 4.0], 0), (n + 10, [], 0)]
    return rows


def usable(e):
    return bool(e) and all(v is not None and np.isfinite(v) for v in e) and any(e)


def cosine(a, b):
    a, b = np.array(a), np.array(b)
    return float(a @ b / np.sqrt((a @ a) * (b @ b)))


def test_neighbours_recall_and_ties(spark):
    rows = sample(1)
    df = vectors(spark, rows)
    got = {}
    for r in ann.nearest(df, df.filter("vec_id % 5 = 0"), block=64).collect():
        got.setdefault(r["query_id"], {})[r["rank"]] = (r["vec_id"], r["score"])
    live = {i: e for i, e, _ in rows if usable(e)}
    hit = total = 0
    for q in (i for i in live if i % 5 == 0):
        best = sorted((-round(cosine(live[q], e), 12), i) for i, e in live.items() if i != q and len(e) == len(live[q]))[:5]
        mine = [got[q][k][0] for k in sorted(got[q])]
        assert len(mine) == len(best) and all(abs(s - cosine(live[q], live[v])) < 1e-9 for v, s in got[q].values())
        hit, total = hit + len(set(mine) & {i for _, i in best}), total + len(best)
    assert hit / total >= 0.95 and set(got) == {i for i in live if i % 5 == 0}
    assert [got[300][k][0] for k in (1, 2)] == [0, 301]
    assert ann.nearest(df.limit(0), df).count() == 0 == ann.nearest(df, df.limit(0)).count()


@pytest.mark.parametrize("block", [1536, 6])
def test_near_vectors_against_all_pairs(spark, monkeypatch, block):
    monkeypatch.setattr(caps, "BLOCK", block)
    rows = sample(2)
    root = {i: i for i, _, _ in rows}
    links = dict.fromkeys(root, 0)

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    live = [(i, np.array(e), y) for i, e, y in rows if usable(e) and y is not None]
    for k, (i, a, y) in enumerate(live):
        for j, b, z in live[k + 1 :]:
            if y == z and len(a) == len(b) and cosine(a, b) >= 0.98:
                links[i], links[j] = links[i] + 1, links[j] + 1
                x, w = find(i), find(j)
                root[max(x, w)] = min(x, w)
    got = {r["vec_id"]: (r["n_links"], r["component_id"], r["kept"]) for r in caps.near_duplicates(vectors(spark, rows)).collect()}
    assert got == {i: (links[i], find(i), find(i) == i) for i in root} and sum(links.values()) > 50
    assert caps.near_duplicates(vectors(spark, rows).limit(0)).count() == 0


def test_every_vector_gets_filters():
    code = caps.Code(24, 16, 20)
    x = np.random.default_rng(3).standard_normal((200, 24))
    sizes = [len(code.decode(v / np.linalg.norm(v))) for v in x]
    assert min(sizes) >= 10 and 10 < np.mean(sizes) < 80


def test_warc_round_trip(spark, tmp_path):
    rng = random.Random(4)
    long = "<p>" + "ä" * 200 + "</p>"
    rows = [(i, f"http://x.org/{i}", "".join(rng.choice("abc é\r\n") for _ in range(rng.randint(0, 400)))) for i in range(10, 60)]
    rows += [(1, "http://a b\nc", long), (2, None, long), (3, "u", None), (4, "u", ""), (5, "u", "short"), (6, "u", "short"), (70, "u", long), (70, "v", "y" * 150), (71, "w", "y" * 150), (99, "u", "z" * 3_000_000)]
    df = spark.createDataFrame([(*r, "clash") for r in rows] + [(None, "u", "lost", "x")], "page_id long, url string, html string, id string")
    at = f"file://{tmp_path}/one"
    done = warc.write(df, at, roll_bytes=4000)
    got = warc.read(done).collect()
    first = {}
    for i, _, h in sorted(rows, key=lambda r: r[0]):
        first.setdefault((h or "").encode(), i)
    assert len(got) == len(rows) and done.count() > 3
    want = sorted((i, len(b), hashlib.sha256(b).hexdigest(), *(("revisit", first[b]) if len(b) >= 100 and first[b] < i else ("response", None))) for i, b in ((i, (h or "").encode()) for i, _, h in rows))
    assert sorted((r["page_id"], r["payload_bytes"], r["payload_digest"], r["record_type"], r["refers_to"]) for r in got) == sorted(want, key=lambda r: r[:3]) or sorted(map(repr, ((r["page_id"], r["payload_bytes"], r["payload_digest"], r["record_type"], r["refers_to"]) for r in got))) == sorted(map(repr, want))
    assert all(bytes(r["payload"]) == next((h or "").encode() for i, _, h in rows if i == r["page_id"] and hashlib.sha256((h or "").encode()).hexdigest() == r["payload_digest"]) for r in got if r["record_type"] == "response")
    again = warc.write(df.repartition(5), f"file://{tmp_path}/two", roll_bytes=4000)
    assert sorted(r["sha256"] for r in done.collect()) == sorted(r["sha256"] for r in again.collect())
    assert not list(tmp_path.glob("one/_temporary*")) and list(tmp_path.glob("one/_manifest/*"))
    assert warc.read(warc.write(df.limit(0), f"file://{tmp_path}/none")).count() == 0


def test_damaged_archives_raise(spark, tmp_path):
    df = spark.createDataFrame([(1, "u", "x" * 500), (2, "u", "y" * 500)], "page_id long, url string, html string")
    done = warc.write(df, f"file://{tmp_path}/a")
    f = next(tmp_path.glob("a/*/*.warc.gz"))
    f.write_bytes(f.read_bytes()[:-20])
    with pytest.raises(Exception):
        warc.read(done).collect()


def folder_bytes(at) -> dict:
    return {p.name: p.read_bytes() for p in at.rglob("*.warc.gz")}


def test_a_folder_written_again_holds_the_new_rows_only(spark, tmp_path):
    at = f"file://{tmp_path}/w"
    pages = lambda x: spark.range(40).selectExpr("id AS page_id", "concat('u', id) AS url", f"concat('{x} ', id, repeat('y', 200)) AS html")
    for x in ("old", "new", "new"):
        told = warc.write(pages(x), at, shards=3)
        got = {r["page_id"]: bytes(r["payload"]).decode() for r in warc.read(told).collect()}
        assert got == {i: f"{x} {i}{'y' * 200}" for i in range(40)}
    assert warc.read(warc.current(spark, at)).count() == 40
    assert sorted(p.name for p in (tmp_path / "w").iterdir() if not p.name.startswith("archives-")) == ["_manifest"]
    assert len([p for p in (tmp_path / "w").iterdir() if p.name.startswith("archives-")]) == 1
    # an archive that is not the manifest's
    some = next((tmp_path / "w").rglob("*.warc.gz"))
    other = warc.write(pages("third"), f"file://{tmp_path}/x", shards=3)
    some.write_bytes(next((tmp_path / "x").rglob(some.name)).read_bytes())
    with pytest.raises(Exception, match="not the file of the manifest"):
        warc.read(told, body=False).count()
    assert other.count() == 3


def test_shards_depend_on_the_rows_alone(spark, tmp_path):
    pages = spark.range(40000).selectExpr("id * id AS page_id", "concat('u', id) AS url", "concat(id % 30000, repeat('z', 120)) AS html")
    pages.write.parquet(f"file://{tmp_path}/p")
    pages = spark.read.parquet(f"file://{tmp_path}/p")
    told = warc.write(pages, f"file://{tmp_path}/a", shards=7)
    warc.write(pages.orderBy("url").repartition(5), f"file://{tmp_path}/b", shards=7)
    a, b = (folder_bytes(tmp_path / x) for x in "ab")
    assert len(a) == 7 and a == b
    assert {r["records"] for r in told.collect()} == {5715, 5710}
    assert warc.read(told, body=False).filter("record_type = 'revisit'").count() == 10000
