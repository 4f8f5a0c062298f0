import random
import zlib

import numpy as np
import pytest

from deltaring.llm import packing as pk
from deltaring.llm.tokens import WordIds, tokenizer_path


def brute_bins(counts, cap, rule, w=(1.0, 1e-3, 1e-3)):
    whole, w, bins = cap.vector(), np.array(w), []
    for length in sorted(counts, reverse=True):
        for _ in range(counts[length]):
            need, best = pk.item(length), None
            for i, b in enumerate(bins):
                if (b >= need).all():
                    s = (((b - need) / whole) ** 2 * w).sum() if rule == "norm" else -(b * (w / whole) * (need / whole)).sum()
                    if best is None or s < best[0] - 1e-15:
                        best = (s, i)
            if best is None:
                bins.append(whole - need)
            else:
                bins[best[1]] = bins[best[1]] - need
    return len(bins)


@pytest.mark.parametrize("rule", ["norm", "dot"])
def test_best_fit_equals_item_by_item(rule):
    r = random.Random(7)
    for _ in range(25):
        cap = pk.Capacity(100, r.choice([2, 3, 100]), r.choice([4000, 10_000]))
        counts = {n: r.randint(1, 6) for n in r.sample(range(1, 101), 12) if cap.fits_alone(n)}
        used = {}
        for length, _, n, s, o in pk.best_fit(counts, cap, rule):
            for i in range(n):
                used.setdefault(s + i, []).append((o, length))
        for parts in used.values():
            at = 0
            for o, length in sorted(parts):
                assert o == at
                at += length
            assert at <= cap.tokens and len(parts) <= cap.documents and sum(x * x for _, x in parts) <= cap.attention
        assert sum(map(len, used.values())) == sum(counts.values())
        assert len(used) == brute_bins(counts, cap, rule)


def check(rows, docs, path):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(path)
    t.encode_special_tokens = True
    want = []
    for d, text in docs:
        ids = [*t.encode(text or "", add_special_tokens=False).ids, 1]
        for k in range(0, len(ids), 4096):
            part = ids[k : k + 4096]
            want.append((d, k // 4096, k, len(part), zlib.crc32(np.array(part, "<u4").tobytes())))
    key = lambda x: tuple((v is None, v) for v in x)
    assert sorted([tuple(r)[:5] for r in rows], key=key) == sorted(want, key=key)
    seq = {}
    for r in rows:
        seq.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for parts in seq.values():
        at = 0
        for o, n in sorted(parts):
            assert o == at
            at += n
        assert at <= 4096
    return len(seq)


def test_whole_table(small):
    path = tokenizer_path()
    rows = pk.pack_documents(small, path).collect()
    n = check(rows, [(r.doc_id, r.text) for r in small.collect()], path)
    assert n <= -(-sum(r.length for r in rows) // 4096) + 2


def test_odd_rows(odd, empty):
    path = tokenizer_path()
    check(pk.pack_documents(odd, path).collect(), [(r.doc_id, r.text) for r in odd.collect()], path)
    assert pk.pack_documents(empty, path).count() == 0


def test_short_way_gives_the_tokenizers_ids():
    w, r = WordIds(tokenizer_path()), random.Random(3)
    letters = "abcdefgéèñßσΣİıǅﬁ̀'’!%&*-_.0123²½Ⅷ中日ー​\U0001f600 "
    texts = ["".join(r.choice(letters) for _ in range(r.randint(1, 12))) for _ in range(4000)]
    want = [np.array(e.ids, "<u4").tobytes() for e in w.tokenizer.encode_batch(texts, add_special_tokens=False)]
    assert w.encode(texts) == want


def test_generations_of_the_cache_change_no_id(monkeypatch):
    from deltaring.llm import tokens

    monkeypatch.setattr(tokens, "CACHE_WORDS", 5)
    w = WordIds(tokenizer_path())
    texts = [f"alpha beta{i % 7} gamma{i}" for i in range(50)]
    assert w.encode(texts) == [np.array(e.ids, "<u4").tobytes() for e in w.tokenizer.encode_batch(texts, add_special_tokens=False)]
