"""Added spans of the personal-data operator against a plain computation of PMI."""

import collections
import math
import random
import re

import pytest

from conflate.llm import pii

WORD = re.compile(r"[^\W\d_]{3,}")


def slow_terms(rows):
    """Entities' disclosing terms by the definition, from whole texts."""
    held, near, df = collections.Counter(), collections.Counter(), collections.Counter()
    for _, t in rows:
        t = t or ""
        df.update({m.group().lower() for m in WORD.finditer(t)})
        seen = set()
        spans = pii.base_spans(t)
        for s, kind, z in spans:
            e = pii.entity(t, kind, s, z)
            seen.add((e, ""))
            words = list(WORD.finditer(t))
            before, after = [m for m in words if m.end() <= s][-pii.REACH :], [m for m in words if m.start() >= z][: pii.REACH]
            seen |= {(e, m.group().lower()) for m in before + after if not any(a < m.end() and m.start() < q for a, _, q in spans)}
        for e, w in seen:
            (near if w else held)[(e, w) if w else e] += 1
    n = len(rows)
    return {(e, w) for (e, w), k in near.items() if n > held[e] and math.log(n * k / (held[e] * df[w])) >= pii.DISCLOSES * math.log(n / held[e])}


@pytest.mark.parametrize("at_once", [300_000, 1])
def test_terms_equal_plain_pmi(docs_of, monkeypatch, at_once):
    monkeypatch.setattr(pii, "TERMS_AT_ONCE", at_once)
    r = random.Random(8)
    vocab = ["".join(r.choice("abcdefgh") for _ in range(r.randint(3, 7))) for _ in range(60)]
    rows = []
    for i in range(120):
        w = [r.choice(vocab) for _ in range(25)]
        if i % 10 == 0:
            w[12] = f"user{i % 30}@mail.example"
            w[11] = f"alias{'abc'[i % 30 // 10]}x"
        rows.append((i, " ".join(w)))
    want = slow_terms(rows)
    got = {x.doc_id: x.spans for x in pii.find(docs_of(rows)).collect()}
    for i, t in rows:
        entities = {pii.entity(t, k, s, z) for s, k, z in pii.base_spans(t)}
        due = {(m.start(), m.end()) for m in WORD.finditer(t) if any((e, m.group().lower()) in want for e in entities) and not any(a < m.end() and m.start() < q for a, _, q in pii.base_spans(t))}
        told = {tuple(map(int, x.split(":")[1:])) for x in got[i].split(",") if x.startswith("term:")}
        assert told == due, i
    assert any("term:" in s for s in got.values())


def test_many_spans_are_quick():
    inside = pii.Inside([(i * 10, i * 10 + 4) for i in range(100_000)])
    assert sum(inside(i * 10 + 5, i * 10 + 8) for i in range(100_000)) == 0 and all(inside(i * 10 + 3, i * 10 + 8) for i in range(1000))
