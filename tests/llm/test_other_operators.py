"""Toxicity, URL filters and language-model scores."""

import math
import random
import re
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from redgraph.llm import lm_scoring, toxicity, url_filters

WORD = re.compile("[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+")


def words(text):
    return WORD.findall("".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))


# toxicity --------------------------------------------------------------------------------------


def all_maximal(scores):
    """Maximal scoring segments by their definition: split at the best segment, again and again."""

    def split(a, b):
        best = None
        for i in range(a, b):
            total = 0.0
            for j in range(i, b):
                total += scores[j]
                if total > 1e-12 and (best is None or total > best[0] + 1e-12):
                    best = (total, i, j)
        if best is None:
            return []
        return split(a, best[1]) + [(best[1], best[2], best[0])] + split(best[2] + 1, b)

    return split(0, len(scores))


def test_segments_equal_the_definition():
    rng = random.Random(3)
    for _ in range(300):
        scores = np.array([rng.choice([-3, -2, -1, 1, 2, 5]) + rng.random() / 100 for _ in range(rng.randrange(1, 18))])
        got = toxicity.maximal_segments(scores)
        assert [(a, b) for a, b, _ in got] == [(a, b) for a, b, _ in all_maximal(scores)]
        assert all(abs(s - scores[a : b + 1].sum()) < 1e-9 for a, b, s in got)


def test_held_out_accuracy(spark):
    path = "/root/testdata/sf0.1"
    found = toxicity.op5_toxicity(spark, path).join(spark.read.parquet(f"{path}/labels.parquet"), "doc_id")
    rows = found.where("held_out").select("toxic", "predicted", "score").collect()
    hit = sum(r.toxic == r.predicted for r in rows) / len(rows)
    recall = sum(r.predicted for r in rows if r.toxic) / sum(r.toxic for r in rows)
    false = sum(r.predicted for r in rows if not r.toxic) / sum(1 - r.toxic for r in rows)
    assert hit > 0.97 and recall > 0.85 and false < 0.01
    assert all(0 <= r.score <= 1 for r in rows)


def test_toxicity_of_odd_rows(spark, sf):
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    model = toxicity.fit(docs, labels)
    rows = [(1, None, 0.5), (None, "", 0.5), (3, "idiot " * 30000, 0.5), (4, "the of and", 0.1), (4, "the of and", 0.1)]
    odd = spark.createDataFrame(rows, "doc_id long, text string, score double")
    got = toxicity.score_documents(odd, model).collect()
    assert len(got) == 5 and all(0 <= r.score <= 1 for r in got) and got[0].words == 0
    assert toxicity.reject_toxic(odd, model).columns == odd.columns
    assert toxicity.score_documents(odd.where(F.lit(False)), model).count() == 0
    blind = toxicity.fit(docs, labels.where("toxic = 0"))
    assert {r.score < 0.5 for r in toxicity.score_documents(odd, blind).collect()} == {True}
    assert len(toxicity.fit(docs, labels.where(F.lit(False))).tokens) == 0


def test_segments_point_at_the_words(spark):
    path = "/root/testdata/sf0.01"
    docs = spark.read.parquet(f"{path}/documents.parquet")
    model = toxicity.fit(docs, spark.read.parquet(f"{path}/labels.parquet"))
    text = "the of and in " * 40 + "idiot moron scum loser " + "the of and in " * 40
    r = toxicity.score_documents(spark.createDataFrame([(1, text)], "doc_id long, text string"), model).first()
    assert r.score > 0.5 and any(s.word <= 160 and s.word + s.words >= 164 for s in r.segments)


# language-model scores -------------------------------------------------------------------------


def brute_scores(docs, order, backoff, leave_one_out):
    per = [[Counter(tuple(w[i : i + n]) for i in range(len(w) - n + 1)) for n in range(1, order + 1)] for w in map(words, docs)]
    total = [sum((p[n] for p in per), Counter()) for n in range(order)]
    all_words = sum(total[0].values())
    out = []
    for text, own in zip(docs, per, strict=True):
        w, score = words(text), 0.0
        left = lambda g: total[len(g) - 1][g] - (own[len(g) - 1][g] if leave_one_out else 0)  # noqa: E731,B023
        n_all = all_words - (len(w) if leave_one_out else 0)
        for i in range(len(w)):
            for n in range(min(order, i + 1), 0, -1):
                g = tuple(w[i - n + 1 : i + 1])
                if n == 1:
                    score += math.log(left(g)) - math.log(n_all) if left(g) else -math.log(n_all + 1)
                elif left(g):
                    score += math.log(left(g)) - math.log(left(g[:-1]))
                    break
                else:
                    score += math.log(backoff)
        out.append(score)
    return out


@pytest.mark.parametrize("order,leave_one_out,batch_bytes,part_bytes", [(3, True, 6 << 20, 32 << 20), (3, True, 5000, 9000), (2, False, 25000, 3000), (1, True, 6 << 20, 2000), (4, False, 12000, 12000)])
def test_scores_equal_brute_force(spark, sf, order, leave_one_out, batch_bytes, part_bytes):
    rows = [(r.doc_id, (r.text or "")[:900]) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").limit(60).collect()]
    rows += [(1000, None), (1001, ""), (1002, "Uniqueword"), (1003, "x"), (1003, "x")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumn("n_words", F.lit("clash"))
    want = brute_scores([t for _, t in rows], order, 0.4, leave_one_out)
    got = lm_scoring.score_documents(docs, order=order, leave_one_out=leave_one_out, batch_bytes=batch_bytes, part_bytes=part_bytes).collect()
    pairs = zip(sorted((r.doc_id, r.log_score) for r in got), sorted(zip([i for i, _ in rows], want, strict=True)), strict=True)
    assert all(a[0] == b[0] and abs(a[1] - b[1]) < 1e-5 for a, b in pairs)


def test_repeated_rows_are_dealt_apart(spark, tmp_path):
    path = str(tmp_path / "copies.parquet")
    spark.createDataFrame([(None, "one text of all rows")] * 500, "doc_id long, text string").coalesce(1).write.parquet(path)
    for docs in (spark.read.parquet(path), spark.read.parquet(path).repartition(2)):
        rows = lm_scoring.placed_rows(docs, "doc_id", "text")
        sizes = [r["count"] for r in rows.groupBy(F.pmod("__at", F.lit(5))).count().collect()]
        assert len(sizes) == 5 and max(sizes) < 160
    batches, bits = lm_scoring.batch_plan(30 << 30, lm_scoring.BATCH_BYTES, lm_scoring.PART_BYTES)
    # at 30 GB a piece still holds hundreds of n-grams (about six bytes of text each)
    assert lm_scoring.BATCH_BYTES / 6 / (1 << bits) > 500 and batches == 5120


def test_scores_of_an_empty_table(spark):
    assert lm_scoring.score_documents(spark.createDataFrame([], "doc_id long, text string")).count() == 0


# URL filters -----------------------------------------------------------------------------------


def test_intervals_and_judgement(spark):
    entries = spark.createDataFrame(
        [("m", "Bad.com", "add", 10), ("m", "bad.com", "remove", 20), ("m", "bad.com", "add", 20), ("m", "bad.com", "remove", 30), ("s", "x.bad.com", "add", 15), ("s", "x.bad.com", "add", 18), (None, "odd.org", "add", 0), ("m", None, "add", 1), ("m", "y", "other", 1)],
        "list string, rule string, action string, since int",
    )
    spans = {(r.list, r.rule, r.valid_from, r.valid_to) for r in url_filters.validity(entries).collect()}
    assert spans == {("m", "bad.com", 10, 20), ("m", "bad.com", 20, 30), ("s", "x.bad.com", 15, 18), ("s", "x.bad.com", 18, None), (None, "odd.org", 0, None)}
    rows = [
        (1, "http://bad.com/a", 9), (2, "http://BAD.com.:80/a", 10), (3, "https://u@x.bad.com?q", 19), (4, "http://x.bad.com", 30), (5, "http://notbad.com", 12), (6, None, 12), (7, "http://bad.com", None), (8, "bad.com", 12), (9, "http://bad.com", 20), (9, "http://bad.com", 20), (10, "http://odd.org/" + "p" * 70000, 5),
    ]
    caps = spark.createDataFrame([(*r, "clash") for r in rows], "page_id int, url string, fetched int, rule string")
    got = url_filters.judge(caps, entries)
    assert got.columns == ["page_id", "url", "fetched", "host", "blocked", "n_active", "lists", "rule"]
    found = {(r.page_id, r.blocked, r.n_active, r.lists, r.rule) for r in got.collect()}
    assert found == {(1, False, 0, "", None), (2, True, 1, "m", "bad.com"), (3, True, 2, "m,s", "x.bad.com"), (4, True, 1, "s", "x.bad.com"), (5, False, 0, "", None), (6, False, 0, "", None), (7, False, 0, "", None), (8, False, 0, "", None), (9, True, 1, "m", "bad.com"), (10, True, 1, "", "odd.org")}
    assert got.count() == len(rows)
    assert url_filters.judge(caps.where(F.lit(False)), entries).count() == 0
    assert url_filters.judge(caps, entries.where(F.lit(False))).where("blocked").count() == 0
