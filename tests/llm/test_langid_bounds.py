"""Language profiles beside a plain sum, and their memory on texts with many different n-grams."""

import re
import subprocess
import sys

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import pytest

from bucketcsr.llm import langid

SF = "/root/testdata/sf0.001"


def plain_bundle(text, spec):
    """N-gram by n-gram, word by word."""
    profiles, out = langid.Profiles(spec), np.zeros(spec.width, np.int64)
    letter = lambda p: 1 - 2 * np.unpackbits(profiles.letters(np.array([p])), axis=1)[0].astype(np.int64)
    low = pc.utf8_lower(pa.array([text or ""]))[0].as_py()
    for word in re.findall(r"[^\x20\x09-\x0D]+", low):
        symbols = [0]
        for x in [*(ord(c) if c.isalpha() else 0 for c in word), 0]:
            if x or symbols[-1]:
                symbols.append(x)
        vectors = {x: letter(x) for x in set(symbols)}
        for i in range(len(symbols) - spec.n + 1):
            bound = 1
            for j in range(spec.n):
                bound = bound * np.roll(vectors[symbols[i + j]], spec.n - 1 - j)
            out = out + bound
    return out


@pytest.mark.parametrize("n", [2, 3, 4])
@pytest.mark.parametrize("most", [1 << 19, 40, 100])
def test_bundles_equal_the_plain_sum_however_texts_are_cut(n, most):
    rng = np.random.default_rng(n)
    signs = list("abcdeéß 12-. \n\t中文字ÀΩ𐐀İ")
    texts = ["".join(rng.choice(signs, k)) for k in rng.choice([0, 1, 2, 5, 30, 200], 30)]
    texts += [None, "", "----a----b----", "a" * 50, "x---------------------------y", " " * 60]
    spec = langid.Hyper(width=64, n=n, most_symbols=most)
    got, has = langid.Profiles(spec).bundles(pa.array(texts))
    for row, h, t in zip(got, has, texts, strict=True):
        assert (row == plain_bundle(t, spec)).all() and h == any(c.isalpha() for c in (t or "").lower())


def test_predictions_equal_plain_prototypes_and_cosines(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").where("length(text) < 1500")
    spec = langid.Hyper(width=256)
    got = {r["doc_id"]: r for r in langid.predict_documents(docs, spec=spec).collect()}
    rows = docs.selectExpr("doc_id", "text", "lang", "crc32(cast(doc_id as string)) % 4 <> 2 as learn").collect()
    bundles = {r["doc_id"]: plain_bundle(r["text"], spec) for r in rows}
    total = {}
    for r in rows:
        if r["learn"] and r["lang"] is not None and r["text"] is not None:
            total[r["lang"]] = total.get(r["lang"], 0) + bundles[r["doc_id"]]
    cosine = lambda a, b: a @ b / max(np.linalg.norm(a) * np.linalg.norm(b), 1e-12)
    for r in rows:
        scores = {name: cosine(bundles[r["doc_id"]], v) for name, v in total.items()}
        best = max(scores.values())
        assert abs(got[r["doc_id"]]["score"] - min(1, max(0, best))) < 1e-9
        assert got[r["doc_id"]]["held_out"] != r["learn"]
        if any(c.isalpha() for c in r["text"] or ""):
            assert scores[got[r["doc_id"]]["lang_pred"]] > best - 1e-9


PEAK = """
import resource, numpy as np, pyarrow as pa
from bucketcsr.llm import langid
rng = np.random.default_rng(1)
profiles = langid.Profiles(langid.Hyper())
base = resource.getrusage(resource.RUSAGE_SELF).ru_maxrss
han = lambda n: rng.integers(0x4E00, 0x9F00, n).astype(np.uint32).tobytes().decode("utf-32-le")
{}
print((resource.getrusage(resource.RUSAGE_SELF).ru_maxrss - base) / 1024)
"""


@pytest.mark.parametrize("work", ["profiles.bundles(pa.array([han(100) for _ in range(3500)]))", "profiles.bundles(pa.array([han(7_000_000)]))"])
def test_memory_stays_below_500_mb(work):
    """A step of 1 MB of short varied texts, and one text of 20 MB without a blank."""
    out = subprocess.run([sys.executable, "-c", PEAK.format(work)], capture_output=True, text=True, check=True, timeout=300)
    assert float(out.stdout) < 500
