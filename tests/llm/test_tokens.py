from collections import Counter

from deltaring.llm import tokens as tk


def counts(spark, docs):
    from deltaring.llm.common import written

    return written(tk.token_counts(docs, tk.tokenizer_path(), "v1"), "counts")


def totals(t):
    return {(r.source, r.lang, r.tokenizer): (r.n_docs, r.n_tokens) for r in t.totals().collect()}


def brute(rows, sign=1):
    out = Counter(), Counter()
    for r in rows:
        out[0][r.source, r.lang, r.tokenizer] += sign
        out[1][r.source, r.lang, r.tokenizer] += sign * r.n_tokens
    return {k: (out[0][k], out[1][k]) for k in out[0]}


def test_batches_apply_once_and_take_back(spark, small):
    c = counts(spark, small)
    rows = c.collect()
    want = [len(tk.word_ids(tk.tokenizer_path()).tokenizer.encode(r.text, add_special_tokens=False).ids) for r in small.orderBy("doc_id").collect()]
    assert [r.n_tokens for r in sorted(rows, key=lambda r: r.doc_id)] == want
    t = tk.TokenTotals(spark)
    assert t.commit("a", tk.inserts(c)) and not t.commit("a", tk.inserts(c))
    assert totals(t) == brute(rows)
    gone = c.where("doc_id % 3 = 0")
    t.commit("b", tk.deletes(gone))
    assert totals(t) == brute([r for r in rows if r.doc_id % 3])
    new = c.where("doc_id % 3 = 1").selectExpr("doc_id", "source", "lang", "'v2' as tokenizer", "n_tokens + 1 as n_tokens")
    t.commit("c", tk.revisions(c.where("doc_id % 3 = 1"), new))
    before = totals(t)
    assert before == {**brute([r for r in rows if r.doc_id % 3 == 2]), **brute(new.collect())}
    t.fold()
    assert totals(t) == before and not t.commit("a", tk.inserts(c)) and totals(t) == before
    t.commit("d", tk.deletes(c.where("doc_id % 3 = 2")))
    t.commit("e", tk.deletes(new))
    assert totals(t) == {}


def test_a_broken_batch_is_written_over(spark, small):
    c = counts(spark, small)
    t = tk.TokenTotals(spark)
    tk.inserts(c).groupBy("source", "lang", "tokenizer").agg({"sign": "sum"}).limit(1).write.parquet(f"{t.path}/batches/a")  # no marker
    assert totals(t) == {} and t.commit("a", tk.inserts(c)) and totals(t) == brute(c.collect())


def test_odd_rows(spark, odd, empty):
    c = counts(spark, odd)
    assert c.count() == odd.count() and c.where("doc_id = 3").first().n_tokens == 0
    t = tk.TokenTotals(spark)
    t.commit("a", tk.inserts(c))
    assert totals(t) == brute(c.collect())
    assert counts(spark, empty).count() == 0
    t = tk.TokenTotals(spark)
    t.commit("a", tk.inserts(counts(spark, empty)))
    assert totals(t) == {}
