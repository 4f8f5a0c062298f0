import hashlib

from hypothesis import given, settings
from hypothesis import strategies as st

from deltaring.llm import fingerprints as fp


def brute(texts):
    out = []
    for i, t in enumerate(texts):
        k, after = len(t) // 4, texts[(i + 1) % len(texts)]
        out.append((t, t[: len(t) - k] + after[:k], after))
    return out


def test_whole_table_against_brute_force(small):
    rows = sorted(small.select("doc_id", "text").collect())
    got = {r.doc_id: r for r in fp.fingerprinted_documents(small).collect()}
    for (doc, _), (text, edited, after) in zip(rows, brute([r.text for r in rows])):
        r = got[doc]
        assert r.n_chars == len(text)
        assert r.edited_sha256 == hashlib.sha256(edited.encode()).hexdigest()
        assert r.fingerprint == fp.digest(fp.canonical(text)) and r.edited_fingerprint == fp.digest(fp.canonical(edited))
        assert r.near_edited == float(fp.canonical(text) == fp.canonical(edited)) and r.near_next == float(fp.canonical(text) == fp.canonical(after))


def test_odd_rows(odd, empty):
    got = fp.fingerprinted_documents(odd).collect()
    assert len(got) == odd.count() and all(len(r.fingerprint) == 32 for r in got)
    by = {r.doc_id: r.fingerprint for r in got}
    assert by[1] == by[2] and by[3] == by[4] == by[5] and by[6] == by[7] != by[1]
    assert fp.fingerprinted_documents(empty).count() == 0
    one = fp.fingerprinted_documents(odd.where("doc_id = 2")).first()
    assert one.near_next == 1.0


def test_bytes_are_compared_inside_equal_buckets(spark, odd):
    """A digest that stands for two forms is reported, one that stands for copies is not."""
    texts = odd.where("text is not null").select("text")
    weak = lambda form: ("a" if form.startswith((b"one", b"lost")) else hashlib.md5(form).hexdigest()).ljust(32, "0")
    for make, want in ((fp.digest, []), (weak, ["a".ljust(32, "0")])):
        prints = spark.createDataFrame([(make(fp.canonical(r.text)),) for r in texts.collect()], "text_digest string")
        assert [r.digest for r in fp.collided(texts, prints, make).collect()] == want


@settings(max_examples=200, deadline=None)
@given(st.text(max_size=40))
def test_canonical_form_is_stable(t):
    form = fp.canonical(t)
    assert fp.canonical(form.decode("utf-8", "surrogatepass")) == form
    assert fp.canonical(f"  {t}\n") == form


def test_one_canonical_form():
    """Characters that part words do so in ASCII texts as in others; a form is its own form."""
    parted = [chr(c) for c in range(0x1C, 0x20)] + ["\t", "\n", "\x0b", "\x0c", "\r", " ", "\x85", "\xa0", "\u2003", "\u3000"]
    for c in parted:
        assert fp.canonical(f"a{c}b") == fp.canonical(f"\uff41{c}b") == b"a b" and fp.canonical(f"{c}a b{c}\xe9").startswith(b"a b")
    for c in range(0x110000):
        if not 0xD800 <= c < 0xE000:
            once = fp.canonical("x" + chr(c))
            assert fp.canonical(once.decode()) == once


def test_collisions_by_map_and_by_join(spark):
    """Equal digests of different bytes are found, however many digests repeat."""
    texts = [f"t{i % 40}" for i in range(100)] + ["aa1", "aa2", "bb1", "bb1"]
    df = spark.createDataFrame([(t,) for t in texts], "text string")
    make = lambda form: fp.digest(form[:2] if form[:2] in (b"aa", b"bb") else form)
    prints = spark.createDataFrame([(make(t.encode()),) for t in texts], "text_digest string")
    want = {make(b"aa1")}
    assert {r.digest for r in fp.collided(df, prints, make).collect()} == want
    assert {r.digest for r in fp.collided(df, prints, make, most_bits=8).collect()} == want
    assert fp.collided(df.limit(0), prints.limit(0), make).count() == 0


def test_rows_without_ids_follow_each_other(spark):
    rows = [(None, f"lost {i}") for i in range(50)] + [(i, f"t{i}") for i in range(20)]
    got = fp.with_next(spark.createDataFrame(rows, "doc_id long, text string").repartition(5)).collect()
    assert len(got) == 70 and sorted(r.next_text for r in got) == sorted(t for _, t in rows)
    after = {r.text: r.next_text for r in got}
    seen, at = [], "t0"
    for _ in range(70):
        seen.append(at)
        at = after[at]
    assert len(set(seen)) == 70 and seen[:20] == [f"t{i}" for i in range(20)] and at == "t0"
