import random

import corpus_pipeline as cp
import numpy as np
import pytest
from pyspark.sql import functions as F

from callweave.llm import nearcopies, simhash
from callweave.llm.common import table
from tests.conftest import DATA
from tests.llm.test_text_operators import ODD, docs_of, plain_fingerprint, plain_groups


def plain_set(text):
    words = (text or "").lower().split()
    return {tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4))} if words else set()


def jaccard(a, b):
    return len(a & b) / max(1, len(a | b))


def plain_kept(rows):
    """Smallest ids of groups by either link, for (id, text) rows with ids of their own."""
    label, sets = plain_groups([(i, plain_fingerprint(t)) for i, t in rows]), {i: plain_set(t) for i, t in rows}
    links = [(a, b) for a in sets for b in sets if a < b and jaccard(sets[a], sets[b]) >= 0.8]
    changed = True
    while changed:
        changed = False
        for a, b in links:
            low, high = sorted((label[a], label[b]))
            if low != high:
                label = {i: low if c == high else c for i, c in label.items()}
                changed = True
    return {i for i, c in label.items() if i == c}


def edited(r, words, share):
    return [r.choice("pqrstuv") * r.randrange(3, 9) if r.random() < share else w for w in words]


def test_edited_copies_go_and_less_similar_texts_stay(spark):
    """Copies at many similarities around the threshold, short and long, a large group among them, against all pairs."""
    r = random.Random(3)
    word = lambda: "".join(r.choice("abcdefgh") for _ in range(r.randrange(2, 8)))
    texts = []
    for n in (12, 40, 90, 200, 400):
        for share in (0.0, 0.005, 0.01, 0.02, 0.03, 0.05, 0.1):
            base = [word() for _ in range(n)]
            texts += [" ".join(base)] + [" ".join(edited(r, base, share)) for _ in range(3)]
    hot = [word() for _ in range(120)]
    texts += [" ".join(edited(r, hot, 0.01)) for _ in range(120)]
    r.shuffle(texts)
    rows = list(enumerate(texts))
    got = {x["doc_id"] for x in nearcopies.drop_near_copies(docs_of(spark, [(i, t, "a") for i, t in rows])).collect()}
    assert got == plain_kept(rows) and len(got) < len(set(texts))


@pytest.mark.parametrize("sf", ["0.001", "0.01"])
def test_stage_keeps_no_near_copy_of_a_kept_document(spark, sf):
    docs = table(spark, DATA.replace("0.001", sf), "documents")
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    sets = {i: plain_set(t) for i, t in texts.items()}
    alike = {(a, b) for a in sets for b in sets if a < b and sets[a] and 5 * min(len(sets[a]), len(sets[b])) >= 4 * max(len(sets[a]), len(sets[b])) and jaccard(sets[a], sets[b]) >= 0.8}
    kept = {r["doc_id"] for r in cp.drop_near_copies(spark, docs, DATA).collect()}
    assert alike and not [p for p in alike if p[0] in kept and p[1] in kept]


def test_one_bit_hashes_tell_shared_passages_from_copies():
    r = random.Random(5)
    shared, kept, left = [f"s{i}" for i in range(60)], 0, 0
    bits = lambda words: nearcopies.band_keys(nearcopies.shingle_set(" ".join(words)))[1]
    apart = lambda x, y: int(sum(bin(int(v)).count("1") for v in bits(x) ^ bits(y)))
    for i in range(150):
        base = [f"w{i}x{k}" for k in range(200)]
        copy = list(base)
        copy[20] = copy[80] = copy[140] = copy[195] = "new"  # 20 of 196 shingles: similarity 0.82
        assert jaccard(plain_set(" ".join(base)), plain_set(" ".join(copy))) >= 0.8
        kept += apart(base, copy) <= nearcopies.most_apart(0.8)
        other = [f"v{i}x{r.random()}" for _ in range(110)]
        left += apart(base[:110] + shared, other + shared) > nearcopies.most_apart(0.8)
    assert kept == 150 and left >= 149


def test_agreeing_bytes_are_counted(spark):
    rng = np.random.default_rng(3)
    a = rng.integers(0, 256, 240, np.uint8)
    rows, n = [], nearcopies.least_agree(0.8)
    for agree in (0, n - 1, n, 240):
        b = a + rng.integers(1, 256, 240, np.uint8)
        at = rng.permutation(240)[:agree]
        b[at] = a[at]
        rows.append((agree, a.view(np.int64).tolist(), b.view(np.int64).tolist()))
    df = spark.createDataFrame(rows, "n int, x array<long>, y array<long>").where(nearcopies._probably("x", "y", 0.8))
    assert sorted(r["n"] for r in df.collect()) == [n, 240] and n == 168


def test_copies_of_one_id_with_other_texts(spark):
    """Of rows that share an id, a known copy goes and the only copy of another text stays, on any partitioning."""
    a, b = (" ".join(f"{x}{i}" for i in range(60)) for x in "ab")
    docs = docs_of(spark, [(3, a, "s"), (7, a, "s"), (7, b, "s"), (7, b, "s")])
    for parts in (1, 3, 7):
        out = nearcopies.drop_near_copies(docs.repartition(parts)).collect()
        assert sorted((r["doc_id"], r["text"]) for r in out) == [(3, a), (7, b)]


def test_rows_of_one_id_by_fingerprints(spark):
    a, b, c = (" ".join(f"{x}{i}" for i in range(60)) for x in "abc")
    docs = docs_of(spark, [(3, a, "s"), (7, a, "s"), (7, b, "s"), (7, b, "s"), (9, b, "s"), (9, c, "s")])
    for parts in (1, 3, 7):
        out = simhash.drop_near_duplicates(docs.repartition(parts)).collect()
        assert sorted((r["doc_id"], r["text"]) for r in out) == [(3, a), (7, b), (9, c)]


def test_near_copies_odd_rows(spark):
    docs = docs_of(spark, ODD)
    kept = nearcopies.drop_near_copies(docs)
    assert sorted(str(r["doc_id"]) for r in kept.collect()) == ["1", "5", "6", "8", "None"] and kept.columns == docs.columns
    assert nearcopies.drop_near_copies(docs_of(spark, [])).count() == 0


def test_texts_that_stay_are_not_moved(spark):
    """Only documents that go, or repeat, meet in an exchange; the map of marks is bounded, and full it costs moves, not rows."""
    r = random.Random(9)
    plain = [(i, " ".join(f"{r.random()}" for _ in range(40)), "s") for i in range(300)]
    docs = docs_of(spark, plain + [(1000 + i, plain[i][1], "s") for i in range(20)] + [plain[50], plain[50]])
    rows = nearcopies.cut(docs.select("doc_id", F.xxhash64("text").alias("mark"), "text"))
    bitmap = nearcopies._bitmap(rows.where("doc_id >= 1000"))
    there, away = (nearcopies._maybe(rows, bitmap, F.col("mark"), t) for t in (True, False))
    assert there.count() == 40 and away.count() == 282 and "Exchange hash" not in away._jdf.queryExecution().executedPlan().toString()
    kept = nearcopies.drop_near_copies(docs)
    assert sorted(x["doc_id"] for x in kept.collect()) == list(range(300))
    full, nearcopies.MAP_BITS = nearcopies.MAP_BITS, 64
    try:
        assert sorted(x["doc_id"] for x in nearcopies.drop_near_copies(docs).collect()) == list(range(300))
    finally:
        nearcopies.MAP_BITS = full
