import os
import random
import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).resolve().parents[1]))
import corpus_pipeline  # noqa: E402
from coverjoin.llm import mix, toxicity  # noqa: E402
from test_texts import brute_groups, words  # noqa: E402

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


@pytest.mark.skipif(not os.path.exists(corpus_pipeline.MODEL), reason="no vocabulary file")
def test_pipeline_against_plain_python(spark, tmp_path):
    import sentencepiece as sp

    rng = random.Random(1)
    vocabulary = [f"word{i}" for i in range(300)]
    rows, labels = [], []
    for i in range(120):
        w = [rng.choice(vocabulary) for _ in range(rng.randint(20, 60))]
        if i % 4 == 0:
            w[3:3] = ["zotplague", "snarkwort"]
        if i % 5 == 1:
            w.append("password=df8d805e67d533b%03x" % i)
        rows.append((i, " ".join(w), "en", f"s{i % 3}", 0))
        labels.append((i, 1, int(i % 4 == 0)))
    rows += [(200, rows[1][1], "en", "s1", 0), (201, rows[2][1] + " end", "en", "s2", 0), (202, None, "en", None, None), (203, "", None, "s0", 0)]
    rows = [(*r[:4], len(r[1] or "")) for r in rows]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    docs, kept = spark.read.parquet(f"{tmp_path}/documents.parquet"), {}
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, docs, str(tmp_path))
        if k < 4:
            assert out.columns == COLUMNS
        out.write.parquet(f"{tmp_path}/stage{k}")
        docs = spark.read.parquet(f"{tmp_path}/stage{k}")
        kept[name] = docs.collect()
    toxic = {i for i, _, t in labels if t}
    assert {r["doc_id"] for r in kept["toxicity"]} == {r[0] for r in rows} - toxic
    groups = brute_groups([(r["doc_id"], r["text"]) for r in kept["toxicity"]], 5)
    assert {r["doc_id"] for r in kept["minhash"]} == {i for i, g in groups.items() if g[2]} and not {200, 201} & {r["doc_id"] for r in kept["minhash"]}
    assert all("df8d805e67d533b" not in (r["text"] or "") for r in kept["secrets"]) and len(kept["secrets"]) == len(kept["minhash"])
    sizes = {}
    for r in kept["secrets"]:
        sizes[r["source"]] = sizes.get(r["source"], 0) + len(words(r["text"]))
    want = mix.targets(sizes, mix.default_weights(list(sizes)))
    for s in sizes:
        assert sum(len(words(r["text"])) for r in kept["mix"] if r["source"] == s) == min(round(want[s]), 3 * sizes[s])
    lib = sp.SentencePieceProcessor(model_file=corpus_pipeline.MODEL)
    assert sorted((r["doc_id"], r["ids"]) for r in kept["sentencepiece"]) == sorted((r["doc_id"], lib.encode(r["text"])) for r in kept["mix"])
    assert sorted(map(repr, corpus_pipeline.run(spark, str(tmp_path)).collect())) == sorted(map(repr, kept["sentencepiece"]))
    assert toxicity.BITS == 20
