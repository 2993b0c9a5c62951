import hashlib

import corpus_pipeline as cp
from pyspark.sql import functions as F

from callweave.llm import linededup, quality
from callweave.llm.common import cut, table
from callweave.llm.queries import MIX, mix_sql
from tests.conftest import DATA
from tests.helpers import same_rows
from tests.llm.test_near_copies import plain_kept
from tests.llm.test_text_operators import ODD, docs_of


def test_stage_by_stage_against_plain_versions(spark, duck):
    docs = table(spark, DATA, "documents")
    accepted = cut(cp.keep_quality(spark, docs, DATA))
    scored = quality.score_quality(docs, quality.train_quality(docs, table(spark, DATA, "labels")))
    assert {r[0] for r in accepted.select("doc_id").collect()} == {r[0] for r in scored.where("predicted = 1").select("doc_id").collect()}

    cleaned = cut(cp.strip_boilerplate(spark, accepted, DATA))
    rows = accepted.collect()
    pages, held = {}, {}
    for r in rows:
        pages[r["source"]] = pages.get(r["source"], 0) + 1
        for mark in {x.strip(" ") for x in r["text"].split("\n")} - {""}:
            held[r["source"], mark] = held.get((r["source"], mark), 0) + 1
    bad = {k for k, n in held.items() if n >= linededup.LEAST_PAGES and n > linededup.RATIO * pages[k[0]]}
    want = {r["doc_id"]: "\n".join(x for x in r["text"].split("\n") if (r["source"], x.strip(" ")) not in bad) for r in rows}
    got = {r["doc_id"]: r for r in cleaned.collect()}
    assert {i: r["text"] for i, r in got.items()} == want and all(r["n_chars"] == len(r["text"]) for r in got.values())

    single = cut(cp.drop_near_copies(spark, cleaned, DATA))
    assert {r[0] for r in single.select("doc_id").collect()} == plain_kept(list(want.items()))

    mixed = cut(cp.mix_sources(spark, single, DATA))
    duck.register("single_rows", single.toPandas())
    sql = mix_sql("single_rows", MIX["budget_share"], MIX["weights"], 1, MIX["seed"], columns="doc_id")
    assert same_rows(mixed.select("doc_id"), duck, sql) < single.count()

    encoded = cp.encode(spark, mixed, DATA)
    texts = {r["doc_id"]: r["text"] for r in mixed.collect()}
    assert {r["doc_id"]: r["decoded_sha256"] for r in encoded.collect()} == {i: hashlib.sha256(t.encode()).hexdigest() for i, t in texts.items()}
    assert cp.run(spark, DATA).drop("ids").exceptAll(encoded.drop("ids")).isEmpty()


def test_stages_take_odd_and_empty_tables(spark):
    for rows in (ODD, []):
        docs = docs_of(spark, rows)
        for _, stage in cp.STAGES[:-1]:
            out = stage(spark, docs, DATA)
            assert out.columns == docs.columns and out.count() <= len(rows)
        assert cp.STAGES[-1][1](spark, docs, DATA).count() == len(rows)


def test_stages_call_operators_in_order():
    assert len(cp.STAGES) == 5 and cp.ORACLE_SQL is None


def test_clean_documents_stay(spark):
    docs, labels = table(spark, DATA.replace("0.001", "0.01"), "documents"), table(spark, DATA.replace("0.001", "0.01"), "labels")
    good = docs.join(labels.where("quality = 1"), "doc_id", "left_semi")
    kept = cp.keep_quality(spark, docs, DATA.replace("0.001", "0.01"))
    assert good.join(kept, "doc_id", "left_anti").count() <= 0.01 * good.count()
    assert kept.select(F.max("n_chars")).first()[0] > 10_000
