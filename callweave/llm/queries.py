"""The operators' registered queries, each over its whole table, and their SQL where SQL can say the same."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from callweave.llm import ann, bpe, html_content, linededup, mixing, neardup_vectors, quality, secrets, simhash, warc
from callweave.llm.common import table

MIX = {"budget_share": 0.8, "weights": {"domain": {"d0": 2.0, "d3": 0.5}, "lang": {"en": 3.0, "de": 2.0}}, "max_epochs": 2, "seed": 17}


def domain_of(source):
    """Domain of a source: d0..d3 by the number in its name."""
    return F.concat(F.lit("d"), F.pmod(F.coalesce(F.try_to_number(F.nullif(F.regexp_extract(source, r"(\d{1,9})", 1), F.lit("")), F.lit("999999999")), F.lit(0)).cast("int"), F.lit(4)).cast("string"))


def op1_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    docs = table(spark, sf_dir, "documents")
    return bpe.encode_texts(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN, keep_ids=False)


def op2_warc_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.archive_roundtrip(table(spark, sf_dir, "pages"))


def op3_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.scan_secrets(table(spark, sf_dir, "documents"))


def op4_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_content.extract_main_text(table(spark, sf_dir, "pages"))


def op5_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    mixed = mixing.mix(table(spark, sf_dir, "documents"), domain_of(F.col("source")), keep=["doc_id", "lang", "source"], **MIX)
    return mixed.select("doc_id", "lang", "source", F.col("__domain").alias("domain"), F.col("__tokens").alias("tokens"), F.col("__epoch").alias("epoch"))


def op6_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ann.search(table(spark, sf_dir, "embeddings"))


def op7_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    cleaned = linededup.drop_boilerplate(table(spark, sf_dir, "documents"))
    return cleaned.select("doc_id", "n_lines", "n_dropped", "text")


def op8_vector_dups(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup_vectors.vector_groups(table(spark, sf_dir, "embeddings"))


def op9_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return quality.score_quality(docs, quality.train_quality(docs, table(spark, sf_dir, "labels")))


def op10_simhash_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.simhash_groups(table(spark, sf_dir, "documents"))


QUERIES = {f.__name__: f for f in (op1_byte_bpe, op2_warc_roundtrip, op3_secret_scan, op4_main_text, op5_source_mix, op6_nearest, op7_line_dedup, op8_vector_dups, op9_quality, op10_simhash_groups)}


def _secret_sql() -> str:
    quote = lambda p: p.replace("'", "''")
    each = " UNION ALL ".join(f"SELECT doc_id, source, text, '{k}' AS kind, unnest(regexp_extract_all(text, '{quote(p)}', 0)) AS hit FROM documents" for k, p in secrets.PATTERNS.items())
    forest = secrets.grow_forest(secrets.labelled_findings())
    features = ", ".join(f"{sql} AS {name}" for name, sql in secrets.duck_features().items())
    cands = " ".join(f"WHEN '{k}' THEN regexp_replace(hit, '{quote(p)}', '', 'g')" for k, p in secrets.AROUND.items())
    chars = secrets.CONTEXT_CHARS
    return f"""
        WITH hits AS (SELECT doc_id, source, text, kind, hit, count(*) AS n FROM ({each}) GROUP BY ALL),
        cands AS (SELECT *, CASE kind {cands} ELSE hit END AS cand, string_split(text, hit) AS parts FROM hits),
        near AS (SELECT *, array_to_string([right(p, {chars}) for p in parts[:len(parts) - 1]] || [CASE WHEN kind = 'assigned' THEN left(hit, length(hit) - length(cand)) ELSE '' END] || [left(p, {chars}) for p in parts[2:]], ' ') AS before FROM cands),
        feats AS (SELECT doc_id, kind, cand, n, {features} FROM near),
        scored AS (SELECT doc_id, kind, cand, n, CASE WHEN kind = 'private_key' THEN 1000 ELSE ({secrets.forest_sql(forest)}) // {len(forest)} END AS score FROM feats)
        SELECT doc_id, kind, cand, CAST(n AS INTEGER) AS n, CAST(score AS INTEGER) AS score, score >= 500 AS is_secret FROM scored"""


def mix_sql(docs: str = "documents", share: float = MIX["budget_share"], weights=MIX["weights"], max_epochs: int = MIX["max_epochs"], seed: int = MIX["seed"], columns: str = "doc_id, lang, source, domain, tokens, epoch") -> str:
    """The mixing operator in SQL; documents of a leaf in one window, as only a check can afford."""
    weight = lambda level: "CASE " + " ".join(f"WHEN {level} = '{k}' THEN {v}" for k, v in sorted(weights.get(level, {}).items())) + " ELSE 1.0 END" if weights.get(level) else "1.0"
    parts, above = [], "SELECT {share} * sum(cap) / {epochs} AS budget FROM leaves".format(share=share, epochs=float(max_epochs))
    parts.append(f"root AS ({above})")
    for depth, level in enumerate(mixing.LEVELS):
        path, up = list(mixing.LEVELS[: depth + 1]), list(mixing.LEVELS[:depth])
        link = f"JOIN given{depth - 1} g USING ({', '.join(up)})" if up else "CROSS JOIN root g"
        part = f"PARTITION BY {', '.join(up)}" if up else ""
        parts.append(f"""n{depth} AS (SELECT x.*, least(g.budget, sum(cap) OVER ({part})) AS budget FROM (SELECT {', '.join(path)}, sum(cap) AS cap, CAST({weight(level)} AS DOUBLE) AS w FROM leaves GROUP BY {', '.join(path)}) x {link})""")
        parts.append(f"""p{depth} AS (SELECT *, (budget - coalesce(sum(cap) OVER ({part} ORDER BY cap / w, {level} ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0.0)) / sum(w) OVER ({part} ORDER BY cap / w, {level} ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS price FROM n{depth})""")
        parts.append(f"""given{depth} AS (SELECT {', '.join(path)}, CASE WHEN cap / w <= price THEN cap ELSE w * max(CASE WHEN cap / w > price THEN price END) OVER ({part}) END AS budget FROM p{depth})""")
    return f"""
        WITH named AS (SELECT *, 'd' || CAST(coalesce(try_cast(nullif(regexp_extract(source, '(\\d{{1,9}})', 1), '') AS INTEGER), 0) % 4 AS VARCHAR) AS domain,
            CAST(len(regexp_extract_all(coalesce(text, ''), '[^ \\t\\n\\x0b\\f\\r]+')) AS BIGINT) AS tokens FROM {docs}),
        leaves AS (SELECT domain, lang, source, sum(tokens) AS tokens, CAST(sum(tokens) * {max_epochs} AS DOUBLE) AS cap FROM named GROUP BY ALL),
        {', '.join(parts)},
        plan AS (SELECT domain, lang, source, l.tokens AS total, budget, CASE WHEN l.tokens = 0 THEN 1 ELSE CAST(floor(budget / greatest(l.tokens, 1) + 1e-9) AS INTEGER) END AS whole FROM leaves l JOIN given2 USING (domain, lang, source)),
        rests AS (SELECT *, floor(budget - whole * total + 1e-6) AS rest FROM plan),
        placed AS (SELECT n.*, r.whole, r.rest, md5('{seed}:' || whole || ':' || doc_id) AS k FROM named n JOIN rests r USING (domain, lang, source)),
        sums AS (SELECT *, sum(tokens) OVER (PARTITION BY domain, lang, source ORDER BY k) AS upto FROM placed),
        taken AS (SELECT *, unnest(range(0, whole + CASE WHEN upto <= rest AND rest > 0 THEN 1 ELSE 0 END)) AS e FROM sums)
        SELECT {columns.replace('epoch', 'CAST(e AS INTEGER) AS epoch')} FROM taken"""


ORACLES = {
    "op2_warc_roundtrip": f"""
        WITH p AS (SELECT page_id, coalesce(url, '') AS url, coalesce(html, '') AS h FROM pages),
        d AS (SELECT page_id, url, CAST(octet_length(encode(h)) AS BIGINT) AS payload_bytes, sha256(h) AS payload_digest FROM p),
        f AS (SELECT *, CASE WHEN payload_bytes >= {warc.LEAST_SHARED} THEN min(page_id) OVER (PARTITION BY payload_digest) ELSE page_id END AS first_id FROM d)
        SELECT page_id, payload_bytes, payload_digest, CASE WHEN first_id < page_id THEN 'revisit' ELSE 'response' END AS record_type,
            CASE WHEN first_id < page_id THEN first_id END AS refers_to, url FROM f""",
    "op3_secret_scan": _secret_sql(),
    "op5_source_mix": mix_sql(),
    "op7_line_dedup": f"""
        WITH lines AS (SELECT doc_id, source, unnest(string_split(text, chr(10))) AS line, unnest(range(len(string_split(text, chr(10))))) AS pos FROM documents),
        totals AS (SELECT source, count(*) AS pages FROM documents GROUP BY source),
        held AS (SELECT source, trim(line) AS mark, count(DISTINCT doc_id) AS n FROM lines WHERE trim(line) <> '' GROUP BY ALL),
        bad AS (SELECT source, mark FROM held JOIN totals USING (source) WHERE n >= {linededup.LEAST_PAGES} AND n > {linededup.RATIO} * pages),
        kept AS (SELECT l.doc_id, l.pos, l.line, b.mark IS NOT NULL AS gone FROM lines l LEFT JOIN bad b ON l.source = b.source AND trim(l.line) = b.mark)
        SELECT doc_id, CAST(count(*) AS INTEGER) AS n_lines, CAST(count(*) FILTER (gone) AS INTEGER) AS n_dropped,
            coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (NOT gone), '') AS text FROM kept GROUP BY doc_id""",
    "op8_vector_dups": """
        WITH RECURSIVE v AS (SELECT vec_id, label, CAST(embedding AS DOUBLE[]) AS x FROM embeddings),
        links AS (SELECT a.vec_id AS a, b.vec_id AS b FROM v a JOIN v b ON a.label = b.label AND a.vec_id <> b.vec_id WHERE list_cosine_similarity(a.x, b.x) >= 0.93),
        reach AS (SELECT vec_id AS a, vec_id AS b FROM embeddings UNION SELECT r.a, l.b FROM reach r JOIN links l ON r.b = l.a),
        comp AS (SELECT a AS vec_id, min(b) AS component_id FROM reach GROUP BY a),
        deg AS (SELECT a AS vec_id, count(*) AS n FROM links GROUP BY a)
        SELECT vec_id, CAST(coalesce(n, 0) AS BIGINT) AS n_links, component_id, vec_id = component_id AS kept FROM comp LEFT JOIN deg USING (vec_id)""",
}
