"""Rules, licences, SimHash, quality, language and packing against brute force; dirty inputs for all of them."""

import re
import zlib
from collections import Counter, defaultdict

import duckdb
import numpy as np
import pytest
import xxhash

from bucketcsr.llm import host_rules, langid, licenses, packing, quality, simhash

WORD = re.compile(r"[^\x20\x09-\x0D]+")
SF = "/root/testdata/sf0.001"
DIRTY = [
    (1, None, "en", "a"),
    (2, "", None, "a"),
    (3, " \n\t ", "en", None),
    (None, "some words here", "en", "b"),
    (4, "a\n\na\nb a", "en", "b"),
    (4, "a\n\na\nb a", "en", "b"),
    (5, "x " * 3000, "de", "c"),
    (6, "é" * 5000, "fr", "c"),
    (7, "one two three four five six seven eight nine " * 3, "en", "a"),
    (8, "ends with nbsp  and 　wide\x85 marks\x1c\x1d", "en", "a"),
]


@pytest.fixture(scope="module")
def dirty(spark):
    df = spark.createDataFrame(DIRTY, "doc_id bigint, text string, lang string, source string")
    return df.selectExpr("*", "length(text) as n_chars", "'x' as n_words", "1 as kept", "2 as score", "3 as fp", "'y' as size")


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SF}/documents.parquet")


def texts(df):
    return [(r["doc_id"], r["text"]) for r in df.select("doc_id", "text").collect()]


def brute_rules(text):
    text = text or ""
    words = WORD.findall(text)
    seen, dup = set(), 0
    for line in text.split("\n"):
        dup += bool(WORD.search(line)) and line in seen
        seen.add(line)
    count = Counter(tuple(words[i : i + 8]) for i in range(len(words) - 7))
    cover = {j for i in range(len(words) - 7) if count[tuple(words[i : i + 8])] > 1 for j in range(i, i + 8)}
    return len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in text), dup, len(cover)


@pytest.mark.parametrize("which", ["docs", "dirty"])
def test_rule_counts(which, request):
    df = request.getfixturevalue(which)
    got = Counter(tuple(r) for r in host_rules.measure(df, keep=["doc_id"]).drop("n_lines").collect())
    assert got == Counter((i, *brute_rules(t)) for i, t in texts(df))


def test_a_bad_host_is_rejected_whole_and_others_are_not(spark):
    good = " ".join(f"word{i}" for i in range(40))
    rows = [(i, good, "fine") for i in range(60)] + [(100 + i, "short", "bad") for i in range(95)] + [(300 + i, good, "bad") for i in range(5)]
    judged = host_rules.judge(spark.createDataFrame(rows, "doc_id bigint, text string, source string"), keep=["doc_id"])
    kept = {r["doc_id"] for r in judged.where("kept").collect()}
    assert kept == set(range(60))


def brute_fingerprint(text):
    low = re.sub("[A-Z]", lambda m: m.group().lower(), text or "")
    words = WORD.findall(low)
    shingles = [" ".join(words[i : i + 3]) for i in range(len(words) - 2)] or ([" ".join(words)] if words else [])
    counts = np.zeros(64, int)
    for s in shingles:
        h = xxhash.xxh64_intdigest(s.encode(), 42)
        counts += np.array([(h >> b) & 1 for b in range(64)])
    return sum(1 << b for b in range(64) if shingles and 2 * counts[b] > len(shingles))


def components(prints):
    """Smallest id reachable, by rows of (id, fingerprint)."""
    parent = list(range(len(prints)))

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i, (_, a) in enumerate(prints):
        for j in range(i):
            if (a ^ prints[j][1]).bit_count() <= 2:
                x, y = root(i), root(j)
                parent[max(x, y)] = min(x, y)
    least = defaultdict(list)
    for i, (k, _) in enumerate(prints):
        if k is not None:
            least[root(i)].append(k)
    return [min(least[root(i)], default=None) for i in range(len(prints))]


@pytest.mark.parametrize("which", ["docs", "dirty"])
def test_simhash_groups(which, request):
    df = request.getfixturevalue(which)
    rows = [(i, brute_fingerprint(t)) for i, t in texts(df)]
    want = Counter((i, f"{f:016x}", c) for (i, f), c in zip(rows, components(rows), strict=True))
    got = simhash.near_duplicates(df, keep=["doc_id"]).select("doc_id", simhash.as_hex("fp").alias("h"), "component_id")
    assert Counter(tuple(r) for r in got.collect()) == want
    kept = simhash.one_per_group(df)
    assert kept.columns == df.columns and kept.count() == len({c for _, _, c in want})


def test_links_equal_brute_force_on_close_fingerprints(spark):
    rng = np.random.default_rng(4)
    base = [int(x) for x in rng.integers(-(2**63), 2**63 - 1, 30)]
    values = set(base)
    for b in base:
        for _ in range(6):
            x = b & (2**64 - 1)
            for bit in rng.choice(64, rng.integers(1, 4), replace=False):
                x ^= 1 << int(bit)
            values.add(x - 2**64 if x >> 63 else x)
    from bucketcsr.llm.components import connected

    found = simhash.links(spark.createDataFrame([(v,) for v in sorted(values)], "fp bigint"))
    got = {r["node"]: r["root"] for r in connected(found).collect()}
    rows = [(v, v & (2**64 - 1)) for v in sorted(values)]
    want = {v: c for (v, _), c in zip(rows, components(rows), strict=True)}
    assert {v: got.get(v, v) for v in values} == want


def test_bk_tree_finds_what_a_scan_finds():
    rng = np.random.default_rng(0)
    tree, seen = simhash.BKTree(), []
    for v in (int(x) for x in rng.integers(0, 1 << 12, 300)):
        assert set(tree.near_then_add(v, 2)) == {s for s in seen if (s ^ v).bit_count() <= 2}
        seen.append(v)


def test_components_of_a_long_chain_and_a_star(spark):
    from bucketcsr.llm.components import connected

    chain = [(i, i + 1) for i in range(100, 170)] + [(7, k) for k in range(8, 60)] + [(5, 5)]
    got = {r["node"]: r["root"] for r in connected(spark.createDataFrame(chain, "u bigint, v bigint").repartition(5)).collect()}
    assert got == {i: 100 for i in range(100, 171)} | {k: 7 for k in range(7, 60)}


def brute_places(text):
    low = re.sub("[A-Z]", lambda m: m.group().lower(), text or "")
    words = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", low)
    at, labels = [], set()
    for phrase, label in licenses.BASE_PHRASES.items():
        p = phrase.split()
        hits = [i for i in range(len(words)) if words[i : i + len(p)] == p]
        at += hits
        labels |= {label} if hits else set()
    return len(words), len(at), min(at, default=None), max(at, default=None), ",".join(sorted(labels))


@pytest.mark.parametrize("which", ["docs", "dirty"])
def test_license_base(which, request):
    df = request.getfixturevalue(which)
    got = licenses.scan(df, keep=["doc_id"])
    assert Counter(tuple(r) for r in got.select("doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels").collect()) == Counter((i, *brute_places(t)) for i, t in texts(df))
    for r in got.collect():
        assert set(filter(None, r["base_labels"].split(","))) <= set(r["labels"].split(",")) and 0 <= r["score"] <= 1


def test_license_index_needs_order_and_key_phrases():
    find = lambda s: licenses.LicenseIndex().matches(s.encode().translate(licenses.FOLD).split())
    assert "gpl-3" in find("x y This work is licensed under the GNU General Public License, version 3. z")
    assert "bsd" in find("Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:")
    assert find("license public general gnu the under licensed version") == {}
    assert find("general words about a license and its public version") == {}
    assert licenses.places(b" a b a b a b ", b" a b ") == [0, 2, 4]


def test_quality_and_language_on_held_out_rows(spark):
    d = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    scored = quality.score_documents(docs, labels).join(labels, "doc_id").where("held_out").toPandas()
    order = scored.score.rank()
    good = scored.quality == 1
    auc = (order[good].sum() - good.sum() * (good.sum() + 1) / 2) / (good.sum() * (~good).sum())
    assert auc > 0.95 and scored.score.between(0, 1).all()
    named = langid.predict_documents(docs).join(docs.select("doc_id", "lang"), "doc_id").where("held_out").toPandas()
    assert (named.lang == named.lang_pred).mean() > 0.98 and named.score.between(0, 1).all()


def test_quality_and_language_on_dirty_and_empty_tables(spark, dirty):
    labels = spark.createDataFrame([(4, 1), (5, 0), (None, 1), (7, None), (99, 1)], "doc_id bigint, quality int")
    assert quality.score_documents(dirty, labels).count() == len(DIRTY)
    assert quality.score_documents(dirty.limit(0), labels).count() == 0
    assert quality.score_documents(dirty, labels.limit(0)).where("score between 0 and 1").count() == len(DIRTY)
    got = {(r["doc_id"], r["lang_pred"] == "und") for r in langid.predict_documents(dirty).collect()}
    assert {(1, True), (2, True), (3, True), (6, False)} <= got
    assert langid.predict_documents(dirty.limit(0)).count() == 0


def test_hyperdimensional_bundle_is_the_sum_of_bound_vectors():
    import pyarrow as pa

    p = langid.Profiles(langid.Hyper(width=64))
    got, has = p.bundles(pa.array(["Ab c1d", None, "12 !"]))
    letter = lambda c: 1 - 2 * np.unpackbits(p.letters(np.array([ord(c)])), axis=1)[0].astype(int)
    want = sum(np.roll(letter(a), 2) * np.roll(letter(b), 1) * letter(c) for a, b, c in (" ab", "ab ", " c ", "c d", " d "))
    assert (got[0] == want).all() and not got[1].any() and has.tolist() == [True, False, False]


@pytest.mark.parametrize("which", ["docs", "dirty"])
def test_packing_holds_every_token_once(which, request):
    from tokenizers import Tokenizer

    df = request.getfixturevalue(which)
    t = Tokenizer.from_file(packing.default_vocabulary())
    t.encode_special_tokens = True
    rows = packing.pack(df).toPandas()
    streams = [t.encode(x or "", add_special_tokens=False).ids + [1] for _, x in texts(df)]
    pieces = Counter((len(s), a, min(2048, len(s) - a), zlib.crc32(np.array(s[a : a + 2048], "<u4").tobytes())) for s in streams for a in range(0, len(s), 2048))
    assert Counter((r.doc_tokens, r.start, r.length, r.ids_crc32) for r in rows.itertuples()) == pieces
    used = 0
    for _, g in rows.sort_values("offset").groupby("sequence_id"):
        assert (g.offset.values == np.concatenate(([0], g.length.cumsum()[:-1]))).all() and g.length.sum() <= 2048
        used += 1
    assert used == rows.sequence_id.max() + 1
    assert used <= -(-sum(map(len, streams)) // 2048) * 1.05 + 1


def one_by_one(lengths, window):
    """The rule piece by piece: longest first, each into the pack with the fewest tokens that has room; sorted packs."""
    packs = []
    for n in sorted(lengths, reverse=True):
        fits = [p for p in packs if sum(p) + n <= window]
        if fits:
            min(fits, key=sum).append(n)
        else:
            packs.append([n])
    return sorted(sorted(p) for p in packs)


def packs_of(histogram, window):
    """Packs as lists of lengths, read back from the patterns; every slot must be used once and packs must have no gaps."""
    p = packing.shortest_pack_first(histogram, window)
    packs = defaultdict(list)
    for length, n in histogram.items():
        sequence, offset = p.place(np.full(n, length, np.int64), np.arange(n))
        for s, o in zip(sequence.tolist(), offset.tolist(), strict=True):
            packs[s].append((o, length))
    for slots in packs.values():
        slots.sort()
        ends = np.cumsum([n for _, n in slots])
        assert ends[-1] <= window and [o for o, _ in slots] == [0, *ends[:-1].tolist()]
    assert sorted(packs) == list(range(p.sequences))
    filled = [sum(n for _, n in slots) for slots in packs.values()]
    assert p.padding == sum(0 if f & (f - 1) == 0 else window - f for f in filled)
    return sorted(sorted(n for _, n in slots) for slots in packs.values())


def test_shortest_pack_first_equals_the_rule_piece_by_piece():
    assert packs_of({8: 1, 5: 2, 3: 3, 1: 2}, 8) == [[1, 1, 3], [3, 5], [3, 5], [8]]
    assert packing.shortest_pack_first({}, 8).sequences == 0
    assert packing.shortest_pack_first({2: 1001}, 8).sequences == 251
    rng = np.random.default_rng(6)
    for window in (8, 16, 32):
        for _ in range(40):
            lengths = rng.integers(1, window + 1, rng.integers(1, 60)).tolist()
            histogram = dict(Counter(lengths))
            got, want = packs_of(histogram, window), one_by_one(lengths, window)
            assert len(got) == len(want) and sorted(map(sum, got)) == sorted(map(sum, want))


def test_ids_equal_those_of_the_tokenizer_on_generated_strings():
    from tokenizers import Tokenizer

    vocabulary = packing.default_vocabulary()
    t, encode = Tokenizer.from_file(vocabulary), packing.Encoder(vocabulary)
    t.encode_special_tokens = True
    special = [x.content for x in t.get_added_tokens_decoder().values()]
    parts = [" ", "  ", "\t", "\n", "\r\n", "\u00a0", "\u3000", "a", "the", "don't", "I'LL", "12", "3.5", "é", "ß", "中文", "😀", "\u0301", "\x00", "…", "--", "'s", "naïve", "x" * 70, *special]
    rng = np.random.default_rng(2)
    for _ in range(4000):
        text = "".join(rng.choice(parts, rng.integers(0, 12)))
        assert np.frombuffer(encode(text), "<u4").tolist() == t.encode(text, add_special_tokens=False).ids, repr(text)


def test_memory_of_runs_is_bounded_in_bytes(monkeypatch):
    encode = packing.Encoder(packing.default_vocabulary())
    monkeypatch.setattr(packing, "CACHE_BYTES", 50_000)
    fresh = packing.Encoder(packing.default_vocabulary())
    for k in range(300):
        text = f"run{k} of{k} words{k} " + "y" * 20_000 + f"{k} end"
        assert fresh(text) == encode.whole(text)
        assert fresh.held <= 50_000 and all(len(r) <= packing.CACHE_RUN for r in fresh.known)
        assert fresh.held == sum(packing.ENTRY_BYTES + 4 * len(r) + len(v) for r, v in fresh.known.items())


def test_empty_tables(dirty):
    none = dirty.limit(0)
    assert host_rules.judge(none).count() == 0
    assert simhash.near_duplicates(none).count() == 0 and simhash.one_per_group(none).count() == 0
    assert licenses.scan(none).count() == 0 and packing.pack(none).count() == 0


def test_sql_of_host_rules_agrees(spark, docs):
    from bucketcsr.llm import entries

    db = duckdb.connect()
    db.execute(f"create view documents as select * from '{SF}/documents.parquet'")
    out = db.execute(entries.OP4_SQL)
    heads = [c[0] for c in out.description]
    want = sorted(tuple(r) for r in out.fetchall())
    assert sorted(tuple(r) for r in entries.op4_host_rules(spark, SF).select(*heads).collect()) == want


def test_similar_texts_are_linked_and_others_are_not(spark, dirty):
    rng = np.random.default_rng(8)
    word = lambda: "".join(rng.choice(list("abcdefghij"), 6))
    texts_, i = [], 0
    for n in (40, 90, 300, 1500):
        base = [word() for _ in range(n)]
        for share in (0.0, 0.005, 0.01, 0.02, 0.03):
            copy = list(base)
            for k in rng.choice(n, int(share * n), replace=False):
                copy[k] = word()
            texts_.append((i, " ".join(copy)))
            i += 1
    texts_ += [(i, texts_[3][1].upper()), (i + 1, " ".join(word() for _ in range(200)))]
    sets = [{tuple(w[k : k + 5]) for k in range(len(w) - 4)} for w in (t.lower().split() for _, t in texts_)]
    parent = list(range(len(sets)))

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a in range(len(sets)):
        for b in range(a):
            if len(sets[a] & sets[b]) / len(sets[a] | sets[b]) >= 0.8:
                x, y = root(a), root(b)
                parent[max(x, y)] = min(x, y)
    df = spark.createDataFrame(texts_, "doc_id bigint, text string")
    for spec in (simhash.Similarity(), simhash.Similarity(tile=2)):
        got = {r["doc_id"]: r["component_id"] for r in simhash.near_duplicates(df, similarity=spec).collect()}
        assert got == {k: root(k) for k in range(len(sets))}
    kept = simhash.one_per_group(dirty, similarity=simhash.Similarity())
    assert kept.columns == dirty.columns
    assert sorted(r["doc_id"] for r in kept.where("doc_id is not null").collect()) == [1, 4, 5, 6, 7, 8]
    assert simhash.one_per_group(dirty.limit(0), similarity=simhash.Similarity()).count() == 0


def parted(name, n, shared):
    """Two texts of n five-word shingles each that share the first ones."""
    head = [f"{name}x{k}" for k in range(shared + 4)]
    return [" ".join(head + [f"{name}{side}{k}" for k in range(n - shared)]) for side in "ab"]


def test_long_texts_are_compared_whole(spark):
    # 1,500 shared shingles of 1,680 each: 0.806; 1,485: 0.792
    rows, i = [], 0
    for shared in (1500, 1485):
        for k in range(12):
            rows += [(i + j, t) for j, t in enumerate(parted(f"p{shared}n{k}", 1680, shared))]
            i += 2
    df = spark.createDataFrame(rows, "doc_id bigint, text string").repartition(4)
    for spec in (simhash.Similarity(), simhash.Similarity(tile_shingles=1000)):
        got = {r["doc_id"]: r["component_id"] for r in simhash.near_duplicates(df, keep=["doc_id"], similarity=spec).collect()}
        assert got == {k: k - k % 2 if k < 24 else k for k in range(48)}


def test_short_similar_texts_are_linked_however_far_their_fingerprints_are(spark):
    # sets of 4 and 5 shingles, similarity 0.8
    rows = []
    for k in range(150):
        words = [f"s{k}w{j}" for j in range(9)]
        rows += [(2 * k, " ".join(words)), (2 * k + 1, " ".join(words[:8]))]
    got = {r["doc_id"]: r["component_id"] for r in simhash.near_duplicates(spark.createDataFrame(rows, "doc_id bigint, text string"), keep=["doc_id"], similarity=simhash.Similarity()).collect()}
    apart = [k for k in range(150) if got[2 * k + 1] != 2 * k]
    assert apart == []
