"""Quality scores, feature by feature in plain Python."""

import math
import re

import numpy as np
import pyarrow as pa
import pytest

from bucketcsr.llm import quality

WORD = re.compile(r"[^\x20\x09-\x0D]+")
FULL = (1 << 64) - 1


def mixed(x):
    x = ((x ^ (x >> 30)) * 0xBF58476D1CE4E5B9) & FULL
    x = ((x ^ (x >> 27)) * 0x94D049BB133111EB) & FULL
    return x ^ (x >> 31)


def framed(word):
    return [1, *map(ord, word), 2]


def word_hash(word):
    return mixed(sum(mixed(c + (i << 24)) for i, c in enumerate(framed(word))) & FULL)


def features(text, spec):
    words = WORD.findall(text or "")
    out = []
    for w in words:
        out.append(word_hash(w))
        f = framed(w)
        for n in range(spec.shortest, spec.longest + 1):
            for i in range(len(f) - n + 1):
                h = n
                for c in f[i : i + n]:
                    h = (h * 0x9E3779B97F4A7C15 + c) & FULL
                out.append(mixed(h))
    for a, b in zip(words, words[1:], strict=False):
        out.append(mixed(0xA6A1 if a == b else (word_hash(a) * 3 + word_hash(b)) & FULL))
    return [h % spec.buckets for h in out]


def plain_score(text, model, spec):
    found = features(text, spec)
    z = model.bias + (sum(float(model.logits[f]) for f in found) / len(found) if found else 0.0)
    return 1 / (1 + math.exp(-z))


@pytest.fixture(scope="module")
def model():
    return quality.Model(np.random.default_rng(5).normal(0, 20, 1 << 10).astype(np.float32), -0.3)


SPEC = quality.Subwords(buckets=1 << 10)
TEXTS = [None, "", " \n\t", "a", "a a a b", "één ünï 中文字 word", "end\x1cnot a blank", "x" * 3000, "the same words the same words\nagain", "tab\tand\vfeed\f"]


def test_scores_equal_the_plain_sum(model):
    got = quality.scores(pa.array(TEXTS, pa.string()), model, SPEC)
    assert np.allclose(got, [plain_score(t, model, SPEC) for t in TEXTS], atol=1e-9)
    for text, (at, counts) in zip(TEXTS, quality.sparse(pa.array(TEXTS, pa.string()), SPEC), strict=True):
        plain = features(text, SPEC)
        assert dict(zip(at.tolist(), counts.tolist(), strict=True)) == {f: plain.count(f) for f in set(plain)}


def test_every_row_of_the_table(spark, model):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text")
    got = {r["doc_id"]: r["score"] for r in quality.classify(docs, model, spec=SPEC, keep=["doc_id"]).collect()}
    rows = docs.collect()
    assert len(got) == len(rows)
    assert max(abs(got[r["doc_id"]] - plain_score(r["text"], model, SPEC)) for r in rows) < 1e-8
