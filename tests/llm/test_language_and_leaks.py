import itertools
import random

import numpy as np
import pytest

from densegrid.llm import decontaminate, langid
from tests.llm.test_operators import prose


@pytest.mark.parametrize("text,want", [("²½ 12", False), ("①②", False), ("12 !?", False), ("", False), (None, False), ("x", True), ("é", True), ("日本", True), ("1 ª", True)])
def test_letters(text, want):
    assert langid.has_letter(text.encode() if text is not None else None) is want


def test_prediction_equals_brute_force():
    """Sums of trigram weights, every pair asked, wins counted, text by text."""
    rng = random.Random(1)
    parts = {"en": "the th ing", "de": "sch ei ung", "nl": "ij oo cht", "fr": "eau que ment", "es": "ción ñ ado"}
    rows = []
    for lang, s in parts.items():
        for _ in range(20):
            h, _ends = langid.trigrams([prose(30, rng, s.split()).encode()])
            idx, n = np.unique(h, return_counts=True)
            rows.append((lang, idx.astype(np.int32), (n * (langid.SCALE / n.sum())).astype(np.float32)))
    model = langid.LanguageModel(rows)
    texts = [prose(12, rng, s.split()) for s in parts.values() for _ in range(6)] + ["thing eau", "123", "²"]
    names, _ = model.predict([t.encode() for t in texts])
    for t, got in zip(texts, names, strict=True):
        if not any(c.isalpha() for c in t):
            assert got == "und"
            continue
        b = (" " + t.lower() + " ").encode()
        grams = [((b[i] << 16 | b[i + 1] << 8 | b[i + 2]) * 2654435761 % 2**32) >> (32 - langid.BITS) for i in range(len(b) - 2)]
        margin = [sum(float(model.weights[g, k]) for g in grams) / len(grams) + model.bias[k] for k in range(len(model.bias))]

        def best(kind, options, margin=margin):
            p = {}
            for a, c in itertools.combinations(options, 2):
                k = model.pairs[kind + a, c]
                s, o = model.sigmoid[k]
                p[a, c] = 1 / (1 + np.exp(-(s * margin[k] + o)))
                p[c, a] = 1 - p[a, c]
            return max(options, key=lambda a: sum((p[a, c] >= 0.5) + p[a, c] / len(options) for c in options if c != a))

        assert got == best("l:", model.families[best("f:", list(model.families))])


def test_question_and_answer_must_both_be_there():
    rng = random.Random(4)
    q, a = prose(30, rng), prose(12, rng)
    index = decontaminate.ItemIndex([(1, f"{q}.\n{a}.".encode()), (2, prose(40, rng).encode())])
    assert [r[0] for r in decontaminate.leaks(f"{prose(50, rng)} {q} {a} {prose(50, rng)}".encode(), index)] == [1]
    assert decontaminate.leaks(f"{prose(50, rng)} {q} {prose(50, rng)}".encode(), index) == []
    assert decontaminate.leaks(f"{prose(50, rng)} {a} {prose(50, rng)}".encode(), index) == []
