import hashlib
import hmac
import re
from datetime import date, timedelta

from pyspark.sql import functions as F

from deltaring.llm import pseudonyms as ps


def run(spark, texts, key="k"):
    df = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "i int, text string")
    return [(r.text, r.n_pseudonyms) for r in sorted(ps.pseudonymised(df, key).collect())]


def luhn(n):
    d = [int(c) for c in re.sub(r"\D", "", n)][::-1]
    return (sum(d[::2]) + sum(sum(divmod(2 * x, 10)) for x in d[1::2])) % 10 == 0


def test_forms_and_links(spark):
    got = run(spark, ["a 4845168114407329 b", "4845 1681 1440 7329", "4845-1681-1440-7329", "4845168114407328", "+1 (017) 555-7713", "017-555-7713", "the.72@mail3.example.com", "129.38.82.176", "300.1.1.1", "2024-02-29", "2023-02-29", "29/02/2024", "31.02.2000", "078-05-1120", "000-12-3456", 'token = "908038b7daaf91e730d2f64001c52934d43d9336"', "7536784127813050 4845168114407329"])
    t = [x for x, _ in got]
    card = re.sub(r"\D", "", t[0])
    assert luhn(card) and card != "4845168114407329" and t[0].startswith("a ") and t[0].endswith(" b")
    assert re.sub(r"\D", "", t[1]) == re.sub(r"\D", "", t[2]) == card and re.fullmatch(r"\d{4} \d{4} \d{4} \d{4}", t[1]) and t[16].endswith(card)
    assert t[3] == "4845168114407328" and t[8] == "300.1.1.1" and t[10] == "2023-02-29" and t[12] == "31.02.2000" and t[14] == "000-12-3456"
    assert re.fullmatch(r"\+1 \(\d{3}\) \d{3}-\d{4}", t[4]) and re.sub(r"\D", "", t[4])[1:] == re.sub(r"\D", "", t[5])
    assert re.fullmatch(r"[a-z]{3}\.\d\d@mail3\.example\.com", t[6]) and t[6] != "the.72@mail3.example.com"
    assert all(0 <= int(x) < 256 for x in t[7].split("."))
    date.fromisoformat(t[9])
    d, m, y = map(int, t[11].split("/"))
    assert date(y, m, d).isoformat() == t[9]  # one date, one pseudonym, in either form
    assert re.fullmatch(r'token = "[0-9a-f]{40}"', t[15])
    assert [n for _, n in got] == [1, 1, 1, 0, 1, 1, 1, 1, 0, 1, 0, 1, 0, 1, 0, 1, 2]
    assert run(spark, ["4845168114407329"], "other")[0][0] != card
    low, high = ([x for x, _ in run(spark, [f(a) for a in ("the.72@mail3.example.com", "908038b7daaf91e730d2f64001c52934d43d9336")])] for f in (str.lower, str.upper))
    assert [x.upper() for x in low] == high and low[0] == t[6]


def test_permutations_have_no_collisions(spark):
    days = [(date(1950, 1, 1) + timedelta(i)).isoformat() for i in range(3000)]
    assert len({t for t, _ in run(spark, days)}) == 3000
    ips = [f"10.{i // 50}.7.{i % 50}" for i in range(2500)]
    assert len({t for t, _ in run(spark, ips)}) == 2500
    ssn = [f"{a:03d}-45-{i:04d}" for a in (1, 665, 667, 899) for i in range(1, 300)]
    out = [t for t, _ in run(spark, ssn)]
    assert len(set(out)) == len(ssn) and all(x[:3] not in ("000", "666") and x[0] != "9" and x[4:6] != "00" and x[7:] != "0000" for x in out)


def test_rest_of_the_text_stays(small):
    before = {r.doc_id: r.text for r in small.collect()}
    for r in ps.pseudonymised(small, "k").collect():
        hide = lambda s: re.sub(r"[0-9a-zA-Z]", "_", s)
        if r.n_pseudonyms == 0:
            assert r.text == before[r.doc_id]
        else:
            assert abs(len(r.text) - len(before[r.doc_id])) <= 9 * r.n_pseudonyms
            if not re.search(r"\d+\.\d+\.\d+\.\d+", before[r.doc_id]):
                assert hide(r.text) == hide(before[r.doc_id])


def test_odd_rows(odd, empty):
    out = ps.pseudonymised(odd, "k")
    assert out.columns == [*odd.columns, "n_pseudonyms"] and out.count() == odd.count()
    assert out.where("text is null").count() == 2 and ps.pseudonymised(empty, "k").count() == 0


def test_plan_has_no_python(small):
    plan = ps.pseudonymised(small, "k")._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Pandas|Arrow", plan)


def test_feistel_is_a_bijection(spark):
    cells = F.array(ps.cell(F.floor(F.col("id") / 10) % 10, 10), ps.cell(F.col("id") % 10, 10), ps.cell(F.lit(0), 1), ps.cell(F.floor(F.col("id") / 100), 3))
    rows = spark.range(300).select(ps.feistel(cells, F.lit("k"), F.lit("t")).alias("v"))
    got = {tuple(r.v) for r in rows.collect()}
    assert len(got) == 300 and all(a < 10 and b < 10 and c == 0 and d < 3 for a, b, c, d in got)


def test_valid_values_do_not_stay(spark):
    texts = ["12/25/1985", "03/14/1990", "5/3/1990", "0001-01-01", "1066-10-14", "9999-12-31", "1.2.1650", "25-12-1985", "1990-05-03T10:00", "2024/3/5", "+44 20 7946 0958", "+49 30 1234567", "0049 30 1234567", "5550107713", "+4915112345678", "aB" * 20, "0f" * 80, "F0" * 80]
    got = run(spark, texts)
    assert [n for _, n in got] == [1] * len(texts)
    out = dict(zip(texts, [t for t, _ in got]))
    iso = {x: run(spark, [x])[0][0] for x in ("1985-12-25", "1990-03-05")}
    m, d, y = map(int, out["12/25/1985"].split("/"))
    assert date(y, m, d).isoformat() == iso["1985-12-25"]
    d, m, y = map(int, out["5/3/1990"].split("/"))
    assert date(y, m, d).isoformat() == iso["1990-03-05"] != "1990-03-05"
    assert date.fromisoformat(out["0001-01-01"]) < date(200, 1, 1) and date.fromisoformat(out["9999-12-31"]) > date(9900, 1, 1) and out["1990-05-03T10:00"][10:] == "T10:00"
    assert re.fullmatch(r"\+44 \d\d \d{4} \d{4}", out["+44 20 7946 0958"]) and out["0049 30 1234567"] == out["+49 30 1234567"].replace("+", "00")
    assert re.fullmatch("(?:[a-f0-9][A-F0-9]){20}", out["aB" * 20]) and out["aB" * 20].lower() == run(spark, ["ab" * 20])[0][0]
    assert [n for _, n in run(spark, ["0000-01-01", "13/13/1990", "0.1234567890", "f" * 31])] == [0] * 4
    for first in (date(1, 1, 1), date(9975, 1, 1)):
        days = [(first + timedelta(i)).isoformat() for i in range(2000)]
        assert len({date.fromisoformat(t) for t, _ in run(spark, days)}) == 2000


# A version of the permutation in plain Python, to hold the expressions against.


def numbers(key, text, n):
    inner = hashlib.sha256(f"in|{key}|{text}".encode()).hexdigest()
    digits = "".join(hashlib.sha256(f"out|{key}|{inner}|{i}".encode()).hexdigest() for i in range((n + 7) // 8))
    return [int(digits[8 * i : 8 * i + 8], 16) for i in range(n)]


def permuted(cells, key, tweak):
    """cells: (value, range) in order; the values after the rounds."""
    a, b = cells[::2], cells[1::2]
    for i in range(1, ps.ROUNDS + 1):
        text = f"{tweak}|{i}|{len(a)}|{','.join(str(v) for v, _ in b)}"
        a, b = b, [((v + y) % r, r) for (v, r), y in zip(a, numbers(key, text, len(a)))]
    return [(a if i % 2 == 0 else b)[i // 2][0] for i in range(len(cells))]


def moved(text, key, kind, alphabets=(ps.DIGITS, ps.LOWER, ps.UPPER), fixed_from=None):
    sets = [next((x for x in alphabets if c in x), "") if fixed_from is None or i < fixed_from else "" for i, c in enumerate(text)]
    new = permuted([(s.index(c), len(s)) if s else (0, 1) for c, s in zip(text, sets)], key, kind)
    return "".join(s[v] if s else c for c, s, v in zip(text, sets, new))


def by_hand(text, key):
    key = hmac.new(key.encode(), b"deltaring pseudonyms", hashlib.sha256).hexdigest()
    digits = re.sub(r"\D", "", text)
    fill = lambda new: re.sub(r"\d", lambda m, d=iter(new): next(d), text)
    if re.fullmatch("[0-9a-f]{32,}", text):
        return moved(text, key, "secret", (ps.HEX,))
    if "@" in text:
        return moved(text, key, "email", fixed_from=text.index("@"))
    if re.fullmatch(r"\d+\.\d+\.\d+\.\d+", text):
        return ".".join(map(str, permuted([(int(x), 256) for x in text.split(".")], key, "ip")))
    if re.fullmatch(r"\d{4}-\d\d-\d\d", text):
        at = (date.fromisoformat(text) - date(1900, 1, 1)).days
        low = at // 65536 * 65536
        assert -65536 <= low <= 65536 * 43
        v = permuted([((at - low) // 256, 256), ((at - low) % 256, 256)], key, "day")
        return (date(1900, 1, 1) + timedelta(low + v[0] * 256 + v[1])).isoformat()
    if re.fullmatch(r"\d{3}-\d\d-\d{4}", text):
        a, g, n = map(int, text.split("-"))
        v = permuted([(a - 1 - (a > 666), 898), (g - 1, 99), (n - 1, 9999)], key, "ssn")
        return f"{v[0] + 1 + (v[0] >= 665):03d}-{v[1] + 1:02d}-{v[2] + 1:04d}"
    if text.startswith("+1"):
        return fill("1" + moved(digits[1:], key, "phone", (ps.DIGITS,)))
    body = moved(digits[:-1], key, "card", (ps.DIGITS,))
    return fill(body + next(c for c in ps.DIGITS if luhn(body + c)))


def test_against_plain_python(spark):
    texts = ["4845168114407329", "4845 1681 1440 7329", "371449635398431", "6011000990139424", "+1 (017) 555-7713", "the.72@mail3.example.com", "a-very.long_local-part.with.many.cells42@x.org", "129.38.82.176", "0.0.0.0", "2024-02-29", "1999-12-31", "1800-01-01", "078-05-1120", "665-01-0001", "667-99-9999", "908038b7daaf91e730d2f64001c52934d43d9336", "0" * 64, "f" * 129]
    for key in ("k", "another key"):
        assert [t for t, _ in run(spark, texts, key)] == [by_hand(t, key) for t in texts]


def test_key_is_in_no_plan(spark):
    key = "a-key-nobody-may-see"
    derived = hmac.new(key.encode(), b"deltaring pseudonyms", hashlib.sha256).hexdigest()
    out = ps.pseudonymised(spark.createDataFrame([(1, "2024-02-29")], "i int, text string"), key)
    out.collect()
    q = out._jdf.queryExecution()
    for plan in (q.logical(), q.analyzed(), q.optimizedPlan(), q.sparkPlan(), q.executedPlan()):
        assert key not in plan.toString() and derived not in plan.toString() and derived not in plan.treeString()
    assert derived not in q.toString() and derived not in q.explainString(spark._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("extended"))


def test_columns_with_clashing_names(spark):
    df = spark.createDataFrame([("2024-02-29", "mine", "yours")], "text string, pseudonym_key string, Pseudonym_New string")
    row = ps.pseudonymised(df, "k").first()
    assert row[1:] == ("mine", "yours", 1) and row[0] != "2024-02-29"
