"""Labels and scores of the licence index beside a search of every place of every template."""

import random
from collections import Counter

import pytest

from bucketcsr.llm import licenses

SF = "/root/testdata/sf0.001"


def fold(text):
    out = "".join(c.lower() if c.isascii() and c.isalpha() else c if not c.isascii() or c.isdigit() else " " for c in text or "")
    return out.encode().split()


def plain(words, index):
    """Label -> best share: each template at each place, word by word."""
    found, slack = {}, index.slack
    joined = b" " + b" ".join(words) + b" "
    have = Counter(words)
    for t, template in enumerate(index.words):
        if not all(p in joined for p in index.phrases[t]):
            continue
        rare = [w for w in sorted(set(template), key=lambda w: (-index.idf[w], w)) if have[w]][: index.rare]
        need = max(1, (len(rare) + 1) // 2)
        total = sum(index.idf[w] for w in template)
        for begin in range(-len(template), len(words)):
            at = lambda k: words[max(0, begin + k - slack) : max(0, begin + k + slack + 1)]  # noqa: B023, E731
            if not any(begin + k < len(words) and begin + k >= 0 and words[begin + k] == w for k, w in enumerate(template) if w in rare):
                continue
            if sum(any(w == x and w in at(k) for k, x in enumerate(template)) for w in rare) < need:
                continue
            lo = max(0, begin - slack)
            span = words[lo : max(0, begin + len(template) + slack)]
            if not all(p in b" " + b" ".join(span) + b" " for p in index.phrases[t]):
                continue
            share = sum(index.idf[w] for k, w in enumerate(template) if w in at(k) and w in span) / total
            if share >= index.share - 1e-12:
                found[index.labels[t]] = max(found.get(index.labels[t], 0.0), share)
    return found


def edited(rng):
    """A text with some templates in it, with words lost, changed and put in."""
    filler = "the a software you may not copy file license version of and general public words other".split()
    words = [rng.choice(filler) for _ in range(rng.randint(0, 30))]
    for _ in range(rng.randint(0, 3)):
        for w in rng.choice(licenses.TEMPLATES)[1].split():
            x = rng.random()
            words += [] if x < 0.03 else [rng.choice(filler)] if x < 0.06 else [w, "indeed"] if x < 0.08 else [w]
        words += [rng.choice(filler) for _ in range(rng.randint(0, 10))]
    return " ".join(words)


def same(a, b):
    return a.keys() == b.keys() and all(abs(a[k] - b[k]) < 1e-9 for k in a)


def test_index_equals_plain_search_on_edited_licences():
    rng, index, hits = random.Random(5), licenses.LicenseIndex(), 0
    for _ in range(250):
        words = fold(edited(rng))
        want = plain(words, index)
        assert same(index.matches(words), want), words
        hits += len(want)
    assert hits > 150


def test_every_template_is_found_whole():
    index = licenses.LicenseIndex()
    for label, text, _ in licenses.TEMPLATES:
        assert index.matches(fold(f"some words before {text} and some behind"))[label] > 0.999


@pytest.mark.parametrize("table", ["documents"])
def test_query_rows_equal_plain_search(spark, table):
    index = licenses.LicenseIndex()
    docs = spark.read.parquet(f"{SF}/{table}.parquet")
    got = {r["doc_id"]: r for r in licenses.scan(docs, keep=["doc_id"]).collect()}
    for i, text in docs.select("doc_id", "text").collect():
        words = fold(text)
        base = set(filter(None, got[i]["base_labels"].split(",")))
        more = plain(words, index)
        assert got[i]["labels"] == ",".join(sorted(base | more.keys()))
        assert abs(got[i]["score"] - (1.0 if base else max(more.values(), default=0.0))) < 1e-9
