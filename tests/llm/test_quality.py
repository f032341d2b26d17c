"""Facts of many tokens at once against the same facts worked out character by character."""

import re

import numpy as np
import pyarrow as pa

from caserubric.llm import quality as Q

TEXTS = ["Plain words, PLAIN words!", None, "", "   ", "\u0130stanbul a\u01c5b \u0661\u0662 aa-AA A1b2 --- x x x", "\U0001d538\U0001d539c \U0001f600 stupid-ass Moron", "one " * 30]


def shape(w):
    return re.sub(r"(.)\1+", r"\1", "".join("A" if c.isupper() else "a" if c.isalpha() else "0" if c.isdigit() else c for c in w))


def test_facts_of_many_tokens():
    facts = Q.Tokens(frozenset(Q.ABUSE))
    (words, at), *more = Q.tokenised(pa.array(TEXTS), facts)
    assert not more and [len(ws) for ws in words] == [len((t or "").split()) for t in TEXTS]
    found, toxic, size = Q.signals(words, at, facts)
    for ws, x, bad in zip(words, found.tolist(), toxic.tolist(), strict=True):
        text, n = "".join(ws), max(1, len(ws))
        plain = [sum(not c.isalnum() for c in text) / max(1, len(text)), sum(map(str.isupper, text)) / max(1, sum(map(str.isalpha, text))), len(set(ws)) / n]
        assert np.allclose(x[:3], plain, atol=0)
        assert x[4] == sum(a == b for a, b in zip(ws, ws[1:], strict=False)) / n
        assert bad == any(p in Q.ABUSE for w in ws for p in re.findall(r"\w+", w.lower()))
    row = {w: facts.facts[k].tolist() for w, k in facts.items()}
    for a in row:
        for b in row:
            assert (row[a][7] == row[b][7]) == (a.lower() == b.lower())
            assert (row[a][8] == row[b][8]) == (shape(a) == shape(b))


def test_small_chunks_rate_alike(monkeypatch):
    batch = pa.RecordBatch.from_arrays([pa.array(range(len(TEXTS))), pa.array(TEXTS)], ["row", "text"])
    weights, harmful = np.linspace(-1, 1, Q.BINS + len(Q.SIGNALS) + 1), np.linspace(-1, 1, Q.HARM_BINS + 1)
    whole = next(Q.scorer(weights, harmful)(iter([batch]))).to_pydict()
    monkeypatch.setattr(Q, "CHUNK_TOKENS", 3)
    assert next(Q.scorer(weights, harmful)(iter([batch]))).to_pydict() == whole
    assert [whole["quality"][k] for k in (1, 2, 3)] == [0.0] * 3


def test_harm_of_tokens_equals_that_of_features():
    harmful = np.sin(np.arange(Q.HARM_BINS + 1))
    facts = Q.Tokens(harmful=harmful)
    for text in filter(None, TEXTS):
        ws = Q.FIND(text)
        harm, n = facts.harm[facts.numbers(ws)].sum(axis=0) if ws else (0.0, 0)
        idx, val = Q.harm_features(text)
        assert np.isclose(harm * Q.harm_scale(n), (harmful[idx] * val).sum(), rtol=1e-4, atol=1e-4)
