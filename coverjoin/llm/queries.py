"""The registered queries of the training-data operators: thin digests over each operator's own output."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op4_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Words that the mix takes of each document, from the operator's spans."""
    from .mix import mix

    sources, _, spans, sized = mix(_table(spark, sf_dir, "documents"))
    taken = spans.groupBy("row").agg(F.sum(F.col("to_word") - F.col("from_word")).alias("taken"))
    return (
        sized.join(taken, "row", "left")
        .select(F.col("key").alias("doc_id"), "size", "source", F.coalesce("taken", F.lit(0)).alias("taken"))
        .join(F.broadcast(sources.withColumnRenamed("source", "s")), F.col("source").eqNullSafe(F.col("s")))
        .select("doc_id", "size", "source_size", "target", "taken")
    )


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import toxicity as t

    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    model = t.train(t.training_rows(docs, _table(spark, sf_dir, "labels")))
    return t.score(docs, model).select("doc_id", t.held_out().alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"))


def op1_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ids of each text, and whether decoding them gives the text back (a mark in the text itself counts as a space)."""
    from . import pieces as p

    table = p.load(MODEL)
    docs = _table(spark, sf_dir, "documents").select("doc_id", F.xxhash64(F.translate("text", p.SPACE, " ")).alias("h"), "text")
    both = p.decode(p.encode(docs, table, keep_text=False), table)
    return both.select("doc_id", F.size("ids").alias("n_ids"), "ids", (F.xxhash64("decoded") == F.col("h")).alias("round_trip"))


def op6_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import secrets as s

    found = s.scan(_table(spark, sf_dir, "documents").select("doc_id", "text"), s.train(spark), redacted="redacted")
    return found.select("doc_id", F.size("findings").alias("n_secrets"), "findings", F.sha2("redacted", 256).alias("redacted_sha256"))


def op7_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .pii import pseudonymise

    done = pseudonymise(_table(spark, sf_dir, "documents").select("doc_id", "text"), PII_KEY)
    return done.select("doc_id", F.size("findings").alias("n_found"), "findings", F.sha2("text", 256).alias("text_sha256"))


def op2_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .minhash import near_duplicates

    return near_duplicates(_table(spark, sf_dir, "documents"), shingle=2)


def op3_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .ann import nearest

    rows = _table(spark, sf_dir, "embeddings")
    return nearest(rows, rows.filter("vec_id % 50 = 0"))


def op8_cap_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .caps import near_duplicates

    return near_duplicates(_table(spark, sf_dir, "embeddings"))


def op9_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import warc

    back = warc.read(warc.write(_table(spark, sf_dir, "pages")), body=False)
    return back.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op10_substrings(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .substrings import dedup

    done = dedup(_table(spark, sf_dir, "documents").select("doc_id", "text"))
    return done.select("doc_id", "n_words", "n_removed", F.sha2("kept_text", 256).alias("kept_sha256"))


#: Vocabulary file; it stays where it is.
MODEL = "/opt/tokenizers/piece_bpe_32k.model"
#: For tests only: a deployment passes its own secret key.
PII_KEY = "test key, not a secret"

QUERIES = {f.__name__: f for f in (op1_sentencepiece, op2_minhash, op3_neighbours, op4_source_mix, op5_toxicity, op6_secrets, op7_pii, op8_cap_filters, op9_warc, op10_substrings)}
#: DuckDB SQL where it can say the same. Components are closures of the links, which small tables allow.
CLOSURE = """u AS (SELECT x AS a, y AS b FROM e UNION SELECT y, x FROM e), r(a, b) AS (SELECT a, b FROM u UNION SELECT r.a, u.b FROM r JOIN u ON u.a = r.b), c AS (SELECT a, min(b) AS low FROM r GROUP BY a)"""
WORDS = r"regexp_extract_all({}, '[^\x20\x09-\x0D]+')"

ORACLES: dict[str, str] = {
    "op2_minhash": f"""WITH RECURSIVE d AS (SELECT doc_id, {WORDS.format("translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')")} AS w FROM documents),
    s AS (SELECT DISTINCT doc_id, w[k] || ' ' || w[k + 1] AS g FROM d, unnest(range(1, len(w))) AS t(k) UNION SELECT doc_id, w[1] FROM d WHERE len(w) = 1),
    n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
    p AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY ALL),
    e AS (SELECT x, y FROM p JOIN n AS nx ON nx.doc_id = x JOIN n AS ny ON ny.doc_id = y WHERE 100 * c >= 80 * (nx.n + ny.n - c)), {CLOSURE}
    SELECT d.doc_id, coalesce(n, 0) AS n_shingles, least(d.doc_id, coalesce(low, d.doc_id)) AS component_id, d.doc_id <= coalesce(low, d.doc_id) AS kept
    FROM d LEFT JOIN n ON n.doc_id = d.doc_id LEFT JOIN c ON c.a = d.doc_id""",
    "op8_cap_filters": f"""WITH RECURSIVE v AS (SELECT vec_id AS id, label AS l, CAST(embedding AS DOUBLE[]) AS m FROM embeddings),
    k AS (SELECT * FROM v WHERE l IS NOT NULL AND len(list_filter(m, lambda z: z IS NULL OR NOT isfinite(z))) = 0 AND len(list_filter(m, lambda z: z <> 0)) > 0),
    e AS (SELECT a.id AS x, b.id AS y FROM k a JOIN k b ON a.l = b.l AND a.id < b.id AND len(a.m) = len(b.m) WHERE list_cosine_similarity(a.m, b.m) >= 0.98), {CLOSURE},
    n AS (SELECT a, count(*) AS n FROM u GROUP BY a)
    SELECT v.id AS vec_id, coalesce(n, 0) AS n_links, least(v.id, coalesce(low, v.id)) AS component_id, v.id <= coalesce(low, v.id) AS kept FROM v LEFT JOIN n ON n.a = v.id LEFT JOIN c ON c.a = v.id""",
    "op9_warc": """WITH p AS (SELECT page_id, coalesce(encode(html), ''::BLOB) AS b FROM pages),
    q AS (SELECT page_id, octet_length(b) AS n, sha256(b) AS d, min(page_id) OVER (PARTITION BY sha256(b)) AS f FROM p)
    SELECT page_id, CAST(n AS BIGINT) AS payload_bytes, d AS payload_digest, CASE WHEN n >= 100 AND f < page_id THEN 'revisit' ELSE 'response' END AS record_type, CASE WHEN n >= 100 AND f < page_id THEN f END AS refers_to FROM q""",
    "op10_substrings": f"""WITH d AS (SELECT doc_id, {WORDS.format("coalesce(text, '')")} AS w FROM documents),
    x AS (SELECT doc_id, k, array_to_string(w[k : k + 12], ' ') AS g FROM d, unnest(range(1, len(w) - 11)) AS t(k)),
    f AS (SELECT g, min(doc_id) AS m FROM x GROUP BY g),
    c AS (SELECT DISTINCT x.doc_id, k + j AS i FROM x JOIN f USING (g), unnest(range(13)) AS t(j) WHERE m < x.doc_id),
    v AS (SELECT doc_id, i, w[i] AS s FROM d, unnest(range(1, len(w) + 1)) AS t(i)),
    z AS (SELECT v.doc_id, count(c.i) AS gone, string_agg(CASE WHEN c.i IS NULL THEN s END, ' ' ORDER BY v.i) AS kept FROM v LEFT JOIN c ON c.doc_id = v.doc_id AND c.i = v.i GROUP BY v.doc_id)
    SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(gone, 0) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256 FROM d LEFT JOIN z USING (doc_id)""",
}
