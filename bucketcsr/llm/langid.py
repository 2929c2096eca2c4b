"""Language identification by hyperdimensional profiles.

Every letter has a random vector of +1 and -1. An n-gram is bound from its letters' vectors, each permuted (rotated) by
its place, multiplied component by component; a text is the bundle (sum) of its n-grams' vectors, and so is a
language over its training texts. A text gets the language whose prototype has the largest cosine.

N-grams run inside words framed by one blank; what is no letter becomes one blank. A text's symbols form one stream in which
white space is a break that no n-gram crosses. Sums are of whole numbers, so results don't depend on how rows are batched.
Memory is bounded whatever the texts: a step takes at most `most_symbols` symbols and 512 texts, a longer text is worked through
in pieces whose last n - 1 symbols go along to the next one, and n-gram vectors exist for one tile at a time. N-grams that many texts of a step
share are summed by a product of counts and vectors, the others one by one. Prototypes come from about `sample` rows of every
language, and one at least, however often a text is repeated; they go along with the scoring function (8 KB for each language).

Null text or no letter: `und`, score 0. No training rows: `und` for all. Null language: never learned from.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, functions as F, types as T

from . import words as W
from .quality import remainder
from .shared import map_text, slices, store

#: Stands between words in the symbol stream; no n-gram holds it. Letters stand for themselves, 0 for anything else.
BREAK = -1
TEXTS = 512
TILE = 2048


@dataclass(frozen=True)
class Hyper:
    width: int = 1024
    n: int = 3
    sample: int = 1500  # training texts per language, about
    seed: int = 3
    most_symbols: int = 1 << 19  # of one step


POINTS = 0x110000


@lru_cache(maxsize=1)
def _symbol_of() -> np.ndarray:
    """By code point: letters as they are, ASCII white space as BREAK, anything else 0."""
    table = np.fromiter((p if chr(p).isalpha() else 0 for p in range(POINTS)), np.int32, POINTS)
    table[[0x20, *range(0x09, 0x0E)]] = BREAK
    return table


def _symbols(points: np.ndarray) -> np.ndarray:
    return _symbol_of()[points]


def _framed(symbols: np.ndarray, doc: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Every break with a blank on both sides, and runs of blanks as one."""
    copies = np.where(symbols == BREAK, 3, 1)
    at = np.cumsum(copies) - copies
    out, owner = np.repeat(symbols, copies), np.repeat(doc, copies)
    gaps = at[symbols == BREAK]
    out[gaps] = 0
    out[gaps + 2] = 0
    again = np.zeros(len(out), bool)
    again[1:] = (out[1:] == 0) & (out[:-1] == 0) & (owner[1:] == owner[:-1])
    return out[~again], owner[~again]


@dataclass(frozen=True)
class Profiles:
    """Makes bundles of texts. A vector is kept as bits: bit 1 stands for -1, so that binding is exclusive or."""

    spec: Hyper

    def letters(self, points: np.ndarray) -> np.ndarray:
        """Random bits of letters (rows x width / 8), from a hash of seed and code point. The blank's are those of the space."""
        start = W.mixed(np.where(points > 0, points, 0x20).astype(np.uint64) + np.uint64(self.spec.seed << 32))
        words = W.mixed(start[:, None] + W.mixed(np.arange(self.spec.width // 64) + 1)[None, :])
        return words.view(np.uint8).reshape(len(points), -1)

    def _turned(self, points: np.ndarray) -> list[np.ndarray]:
        """Bits of letters at each place of an n-gram, packed in 64-bit words."""
        out = [np.empty((len(points), self.spec.width // 64), np.uint64) for _ in range(self.spec.n)]
        for lo in range(0, len(points), TILE):
            plain = np.unpackbits(self.letters(points[lo : lo + TILE]), axis=1)
            for j, table in enumerate(out):
                table[lo : lo + TILE] = np.packbits(np.roll(plain, self.spec.n - 1 - j, axis=1), axis=1).view(np.uint64)
        return out

    def bound(self, grams: np.ndarray, turned: list[np.ndarray]) -> np.ndarray:
        """Bits (rows x width, 0 or 1) of n-grams given as rows of places in `turned`."""
        bits = turned[0][grams[:, 0]]
        for j in range(1, self.spec.n):
            bits = bits ^ turned[j][grams[:, j]]
        return np.unpackbits(bits.view(np.uint8), axis=1)

    def _add(self, symbols: np.ndarray, doc: np.ndarray, out: np.ndarray) -> None:
        """Adds the vectors of all n-grams of a framed stream to their texts' rows of out."""
        n, docs, m = self.spec.n, len(out), max(0, len(symbols) - self.spec.n + 1)
        fine = doc[:m] == doc[n - 1 : n - 1 + m]
        for j in range(n):
            fine &= symbols[j : m + j] != BREAK
        if not fine.any():
            return
        present = np.zeros(POINTS, bool)
        present[symbols[symbols != BREAK]] = True
        seen = np.flatnonzero(present)
        local = (np.cumsum(present) - 1)[symbols]
        code = np.zeros(m, np.int64)
        for j in range(n):
            code = code * len(seen) + local[j : m + j]
        kinds, kind = np.unique(code[fine], return_inverse=True)
        owners = doc[:m][fine]
        grams = np.empty((len(kinds), n), np.int64)
        for j in range(n - 1, -1, -1):
            kinds, grams[:, j] = np.divmod(kinds, len(seen))
        turned = self._turned(seen)
        out += np.bincount(owners, minlength=docs)[:, None]  # less 2 for every bit that is set
        shared = np.bincount(kind, minlength=len(kinds)) * 48 >= docs
        dense, place = shared[kind], np.cumsum(shared) - 1
        common = np.flatnonzero(shared)
        at, who = place[kind[dense]], owners[dense]
        order = np.argsort(at, kind="stable") if len(common) > TILE else slice(None)
        at, who = at[order], who[order]
        for lo in range(0, len(common), TILE):
            a, b = np.searchsorted(at, (lo, lo + TILE)) if len(common) > TILE else (0, len(at))
            width = min(TILE, len(common) - lo)
            counts = np.bincount(who[a:b] * width + at[a:b] - lo, minlength=docs * width).reshape(docs, width)
            # float32 products are exact: a step has far fewer than 2^24 n-grams
            out -= 2 * (counts.astype(np.float32) @ self.bound(grams[common[lo : lo + width]], turned).astype(np.float32))
        rare, who = kind[~dense], owners[~dense]
        for lo in range(0, len(rare), TILE):
            bits = self.bound(grams[rare[lo : lo + TILE]], turned).astype(np.float32)
            heads = np.flatnonzero(np.diff(who[lo : lo + TILE], prepend=-1))
            out[who[lo : lo + TILE][heads]] -= 2 * np.add.reduceat(bits, heads, axis=0)

    def _long(self, text: str, out: np.ndarray) -> bool:
        """One text piece by piece; whether it has a letter. A BREAK in front and behind frames its first and last word."""
        carry, has = np.array([BREAK], np.int32), False
        step = self.spec.most_symbols // 4
        for lo in range(0, len(text) + 1, step):
            piece = _symbols(np.frombuffer(text[lo : lo + step].encode("utf-32-le", "replace"), np.uint32))
            has |= bool((piece > 0).any())
            last = lo + step > len(text)
            stream, owner = _framed(np.concatenate((carry, piece, [BREAK] * last)).astype(np.int32), np.zeros(len(carry) + len(piece) + last, np.int32))
            self._add(stream, owner, out)
            # the next piece starts with the last n - 1 symbols, so that n-grams across the cut are seen once
            carry = stream[len(stream) - min(len(stream), self.spec.n - 1) :]
        return has

    def _step(self, texts: pa.Array, out: np.ndarray) -> np.ndarray:
        whole = " ".join(texts.to_pylist())
        points = np.frombuffer(whole.encode("utf-32-le", "replace"), np.uint32)
        sizes = pc.utf8_length(texts).to_numpy(zero_copy_only=False)
        # each text owns the blank behind it, and one more stands in front of it
        owner = np.repeat(np.arange(len(texts), dtype=np.int32), sizes + 1)[: len(points)]
        symbols = _symbols(points)
        has = np.bincount(owner, weights=symbols > 0, minlength=len(texts)) > 0
        front = np.concatenate(([0], np.cumsum(sizes + 1)[:-1]))
        symbols, owner = np.insert(symbols, front, BREAK), np.insert(owner, front, np.arange(len(texts)))
        symbols, owner = np.append(symbols, BREAK), np.append(owner, len(texts) - 1)
        self._add(*_framed(symbols, owner), out)
        return has

    def bundles(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(texts x width) bundles as float64 whole numbers, and whether each text has a letter."""
        lower = pc.utf8_lower(pc.fill_null(texts, "").cast(pa.large_string()))
        out, has = np.zeros((len(texts), self.spec.width)), np.zeros(len(texts), bool)
        sizes = pc.utf8_length(lower).to_numpy(zero_copy_only=False)
        lo = 0
        while lo < len(texts):
            if sizes[lo] > self.spec.most_symbols // 4:
                has[lo] = self._long(lower[lo].as_py(), out[lo : lo + 1])
                lo += 1
                continue
            hi, total = lo, 0
            while hi < len(texts) and hi - lo < TEXTS and sizes[hi] <= self.spec.most_symbols // 4 and total + sizes[hi] + 1 <= self.spec.most_symbols:
                total += sizes[hi] + 1
                hi += 1
            has[lo:hi] = self._step(lower.slice(lo, hi - lo), out[lo:hi])
            lo = hi
        return out, has


def draw(docs: DataFrame, text: str = "text", lang: str = "lang", doc_id: str | None = None, spec: Hyper = Hyper()) -> DataFrame:
    """Training rows (l, t): about spec.sample of each language, by a hash of id and text, and its smallest hash in any case.

    Rows with equal id, text and language count once.
    """
    ident = F.col(f"`{doc_id}`").cast("string") if doc_id else F.lit(None).cast("string")
    rows = docs.select(F.col(f"`{text}`").alias("t"), F.col(f"`{lang}`").cast("string").alias("l"), ident.alias("i")).where("l is not null and t is not null")
    rows = rows.select("l", "t", F.xxhash64(F.lit(spec.seed), F.coalesce("i", F.lit("")), "t").alias("h"))
    shares = store(rows.groupBy("l").agg((F.lit(float(spec.sample)) / F.count("*")).alias("share"), F.min("h").alias("first")))
    drawn = rows.join(shares, "l").where((F.pmod("h", F.lit(1 << 30)) < F.col("share") * (1 << 30)) | (F.col("h") == F.col("first")))
    return drawn.dropDuplicates(["l", "h"]).select("l", "t")


def learn(docs: DataFrame, text: str = "text", lang: str = "lang", spec: Hyper = Hyper(), doc_id: str | None = None) -> tuple[list[str], np.ndarray]:
    """Languages and their prototypes (languages x width) from the rows given."""
    drawn = draw(docs, text, lang, doc_id, spec)

    def bundle(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        profiles, sums = Profiles(spec), {}
        for batch in batches:
            for part in slices(batch, 1):
                made, _ = profiles.bundles(part.column(1))
                for name, row in zip(part.column(0).to_pylist(), made.astype(np.int64), strict=True):
                    sums[name] = sums.get(name, 0) + row
        yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.string()), pa.array([v.tolist() for v in sums.values()], pa.list_(pa.int64()))], names=["l", "v"])

    # tasks send one row per language; they are added up before anything reaches the driver
    parts = drawn.repartition("l", F.pmod(F.xxhash64("t"), F.lit(16))).mapInArrow(bundle, "l string, v array<bigint>")
    summed = parts.select("l", F.posexplode("v").alias("at", "x")).groupBy("l", "at").agg(F.sum("x").alias("x"))
    rows = summed.groupBy("l").agg(F.transform(F.array_sort(F.collect_list(F.struct("at", "x"))), lambda e: e["x"]).alias("v")).collect()
    total = {r["l"]: r["v"] for r in rows}
    names = sorted(total)
    return names, np.array([total[x] for x in names], np.float64).reshape(-1, spec.width)


def identify(docs: DataFrame, names: list[str], prototypes: np.ndarray, text: str = "text", keep: list[str] | None = None, spec: Hyper = Hyper()) -> DataFrame:
    """keep columns (default: all of docs) + lang_pred (string), score (double: the cosine, 0 at least)."""
    keep = [c for c in (docs.columns if keep is None else keep) if c.lower() not in ("lang_pred", "score")]
    unit = prototypes / np.maximum(np.linalg.norm(prototypes, axis=1, keepdims=True), 1e-12) if len(names) else prototypes
    profiles = Profiles(spec)

    def make(texts: pa.Array) -> list[pa.Array]:
        if not names:
            return [pa.array(["und"] * len(texts), pa.string()), pa.array(np.zeros(len(texts)))]
        pred, score = [], np.zeros(len(texts))
        for lo in range(0, len(texts), TEXTS):
            bundle, has = profiles.bundles(texts.slice(lo, TEXTS))
            cosine = (bundle @ unit.T) / np.maximum(np.linalg.norm(bundle, axis=1), 1e-12)[:, None]
            best = cosine.argmax(axis=1)
            score[lo : lo + len(best)] = np.where(has, np.clip(cosine[np.arange(len(best)), best], 0, 1), 0.0)
            pred += [names[b] if h else "und" for b, h in zip(best.tolist(), has.tolist(), strict=True)]
        return [pa.array(pred, pa.string()), pa.array(score)]

    return map_text(docs, text, [T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType())], make, keep)


def predict_documents(docs: DataFrame, doc_id: str = "doc_id", spec: Hyper = Hyper()) -> DataFrame:
    """doc_id, held_out, lang_pred, score: learns from rows whose id's crc32 mod 4 is not 2."""
    fold: Column = remainder(F.col(f"`{doc_id}`"), 4)
    names, prototypes = learn(docs.where(fold != 2), spec=spec, doc_id=doc_id)
    made = identify(docs, names, prototypes, keep=[doc_id], spec=spec)
    return made.select(F.col(f"`{doc_id}`"), F.coalesce(fold == 2, F.lit(False)).alias("held_out"), "lang_pred", "score")
