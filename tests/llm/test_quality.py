import math
import re
from collections import Counter

from pyspark.sql import functions as F

from deltaring.llm import quality as ql
from deltaring.llm.ngrams import NgramModel, log_ratios, slots_of, words

WORDS = re.compile(r"[^\x20\x09-\x0D]+")


def base(text):
    text = text or ""
    w = WORDS.findall(text)
    seen = Counter(zip(w, w[1:], w[2:]))
    covered = {j for i in range(len(w) - 2) if seen[w[i], w[i + 1], w[i + 2]] > 1 for j in (i, i + 1, i + 2)}
    lines = [x for x in text.split("\n") if WORDS.search(x)]
    return len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in text), len(lines) - len(set(lines)), len(covered)


def check(rows, texts):
    for r, t in zip(rows, texts):
        want = base(t)
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == want
        assert r.base_failed == (want[0] < 50 or 100 * want[4] > 50 * want[0])
        assert r.kept == (not r.base_failed and r.mean_log_ratio >= ql.THRESHOLD)


def test_whole_table(small, labels):
    texts = {r.doc_id: r.text for r in small.collect()}
    rows = ql.judged_documents(small, labels).collect()
    assert len(rows) == len(texts)
    check(rows, [texts[r.doc_id] for r in rows])


def test_ratios_against_brute_force(small, labels):
    model = NgramModel(slots=512)
    grams = {r.doc_id: r.g for r in small.select("doc_id", slots_of(words(F.col("text")), 512).alias("g")).collect()}
    good = {r.doc_id for r in labels.where("quality = 1").collect()}
    raw, target = Counter(), Counter()
    for d, g in grams.items():
        raw.update(g)
        if d in good:
            target.update(g)
    got = {r.slot: r.ratio for r in log_ratios(small, labels, model).collect()}
    n, m = sum(raw.values()), sum(target.values())
    for s in range(512):
        assert math.isclose(got[s], math.log(target[s] + 16) - math.log(raw[s] * m / n + 16), abs_tol=1e-9)
    rows = ql.judged_documents(small, labels, model=model).collect()
    for r in rows:
        g = grams[r.doc_id]
        assert math.isclose(r.mean_log_ratio, sum(got[s] for s in g) / max(len(g), 1), abs_tol=1e-5)


def test_held_out_accuracy(spark):
    """Fitted on two thirds of the labels, the verdict agrees with the rest."""
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.01/{t}.parquet") for t in ("documents", "labels"))
    rows = ql.judged_documents(docs, labels.where("doc_id % 3 <> 0")).join(labels.where("doc_id % 3 = 0"), "doc_id").where("not base_failed").collect()
    good = [r.kept for r in rows if r.quality == 1]
    bad = [r.kept for r in rows if r.quality == 0]
    assert sum(good) >= 0.98 * len(good) and sum(bad) <= 0.2 * len(bad)


def test_odd_rows(odd, empty, odd_labels):
    rows = ql.judged_documents(odd, odd_labels).collect()
    assert len(rows) == odd.count()
    none = [r for r in rows if r.doc_id in (3, 4, 5)]
    assert all(r.n_words == 0 and r.base_failed and not r.kept for r in none)
    assert ql.judged_documents(empty, odd_labels).count() == 0
    assert ql.judged_documents(odd, odd_labels.limit(0)).count() == odd.count()


def test_plan_has_no_python(small, labels):
    plan = ql.judged_documents(small, labels)._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Pandas|Arrow|Cartesian|NestedLoop", plan)
