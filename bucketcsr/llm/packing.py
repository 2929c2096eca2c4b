"""Packing token sequences: shortest pack first over the length histogram.

One pass tokenizes whole texts and cuts each document into pieces: full windows and a rest.
Only piece lengths (at most `window` different ones)
are counted. On that histogram lengths are placed longest first, always into the pack with the fewest tokens that
still has room; equal packs are one pattern with a count, so the work depends on the window, not on the corpus.
Patterns go back to the pieces by rank: a piece's rank among those of its length is its running number inside the
stored partition that wrote it plus that partition's base, a small prefix sum; a binary search in the pattern table
(bounded by the window) gives its sequence and offset.

Null or empty text: only the end id, one piece. Null doc_id: carried along. Empty table: empty result. Repeated rows
are packed each by itself.
"""

from __future__ import annotations

import json
import os
import zlib
from array import array
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window, functions as F, types as T

from .shared import fresh, slices, store

END_ID = 1
#: What a worker's memory of runs may hold, about; longer runs are never remembered.
CACHE_BYTES = 64 << 20
CACHE_RUN = 48
ENTRY_BYTES = 200


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


#: Fixed value: the public split rule of byte-level BPE vocabularies of this kind.
SPLIT_RULE = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


def _byte_of() -> dict[str, int]:
    """The printable stand-ins of byte-level vocabularies: printable Latin-1 stands for itself, the rest for 256 and up."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


def _ranked(vocabulary: str):
    """The same vocabulary in the faster encoder, or None where its rules are not those of plain byte-level BPE."""
    with open(vocabulary, encoding="utf-8") as f:
        spec = json.load(f)
    model, pre = spec.get("model", {}), spec.get("pre_tokenizer") or {}
    if model.get("type", "BPE") != "BPE" or spec.get("normalizer") or pre.get("type") != "ByteLevel" or pre.get("add_prefix_space") or model.get("ignore_merges") or not pre.get("use_regex", True):
        return None
    merged = [model["vocab"]["".join(m) if isinstance(m, list) else m.replace(" ", "", 1)] for m in model["merges"]]
    if merged != sorted(merged):
        return None
    import tiktoken

    byte_of = _byte_of()
    special = {t["content"] for t in spec.get("added_tokens", [])}
    ranks = {bytes(byte_of[c] for c in word): i for word, i in model["vocab"].items() if word not in special}
    return tiktoken.Encoding("ranked", pat_str=SPLIT_RULE, mergeable_ranks=ranks, special_tokens={})


class Encoder:
    """Ids of whole texts as little-endian 32-bit bytes; remembers runs between single spaces.

    The vocabulary's rule never joins across a space that stands before a run, unless two blanks meet; such texts are
    encoded whole. Strings of special tokens count as ordinary text.
    """

    def __init__(self, vocabulary: str) -> None:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(vocabulary)
        self.tokenizer.encode_special_tokens = True
        self.ranked = _ranked(vocabulary)
        self.known: dict[str, bytes] = {}
        self.held = 0

    def whole(self, text: str) -> bytes:
        if self.ranked is not None:
            return array("I", self.ranked.encode_ordinary(text)).tobytes()
        return array("I", self.tokenizer.encode(text, add_special_tokens=False).ids).tobytes()

    def __call__(self, text: str) -> bytes:
        if "  " in text:
            return self.whole(text)
        first, *runs = text.split(" ")
        head = self.whole(first) if first else b""
        try:
            return head + b"".join(map(self.known.__getitem__, runs))
        except KeyError:
            return head + b"".join([self.known.get(w) or self._run(w) for w in runs])

    def _run(self, run: str) -> bytes:
        """Ids of a run behind its blank; short runs are remembered within CACHE_BYTES."""
        ids = self.whole(" " + run)
        if len(run) <= CACHE_RUN:
            size = ENTRY_BYTES + 4 * len(run) + len(ids)
            if self.held + size > CACHE_BYTES:
                self.known.clear()
                self.held = 0
            self.known[run] = ids
            self.held += size
        return ids


def cuts(tokens: int, window: int) -> list[tuple[int, int]]:
    """(start, length) of a document's pieces: full windows, then the rest."""
    return [(at, min(window, tokens - at)) for at in range(0, tokens, window)]


_encoders: dict[str, Encoder] = {}


def _tokenize(vocabulary: str, window: int, keep: int, names: list[str]):
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if vocabulary not in _encoders:
            _encoders[vocabulary] = Encoder(vocabulary)
        encode = _encoders[vocabulary]
        part = TaskContext.get().partitionId()
        seen = np.zeros(window + 1, np.int64)  # pieces of each length so far in this partition
        for batch in batches:
            for piece in slices(batch, keep):
                row, made = [], []
                for i, text in enumerate(piece.column(keep).to_pylist()):
                    ids = encode(text or "") + END_ID.to_bytes(4, "little")
                    view, n = memoryview(ids), len(ids) // 4
                    for start, length in cuts(n, window):
                        row.append(i)
                        made.append((start, length, zlib.crc32(view[4 * start : 4 * (start + length)]), n, part, int(seen[length])))
                        seen[length] += 1
                kept = [piece.column(k).take(pa.array(row, pa.int64())) for k in range(keep)]
                cols = [pa.array([m[k] for m in made], t) for k, t in enumerate((pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int64()))]
                yield pa.RecordBatch.from_arrays(kept + cols, names=names)

    return run


@dataclass
class Patterns:
    """Slots of all packing patterns, ordered by (length, first rank): where the pieces of a rank range go."""

    length: np.ndarray
    rank: np.ndarray  # of the first piece in the range
    sequence: np.ndarray  # that piece's sequence; the next piece's is one more
    offset: np.ndarray
    sequences: int
    padding: int

    def place(self, length: np.ndarray, rank: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        key = (self.length.astype(np.int64) << 44) + self.rank
        at = np.searchsorted(key, (length << 44) + rank, "right") - 1
        return self.sequence[at] + rank - self.rank[at], self.offset[at]


def shortest_pack_first(histogram: dict[int, int], window: int) -> Patterns:
    """Places lengths longest first into the pack with the most room; equal packs stay one (slots, count)."""
    room: list[list[tuple[tuple, int]]] = [[] for _ in range(window + 1)]
    widest = 0  # no pack has more room
    rank = dict.fromkeys(histogram, 0)
    for length in sorted(histogram, reverse=True):
        left = histogram[length]
        while left:
            while widest and not room[widest]:
                widest -= 1
            if widest >= length:
                slots, count = room[widest].pop()
                n = min(count, left)
                if n < count:
                    room[widest].append((slots, count - n))
                groups, at = [((slots, length, rank[length]), n)], widest - length
                left -= n
                rank[length] += n
                # ranks inside a split pattern start later, so a pattern's slots are (parent, length, first rank), and a split parent shifts
                if n < count:
                    room[widest][-1] = (_shift(slots, n), count - n)
                room[at].extend(groups)
                continue
            fit = window // length
            for per_pack, n in ((fit, left // fit), (left % fit, 1)):
                if per_pack and n:
                    slots: tuple | None = None
                    for _ in range(per_pack):
                        slots = (slots, length, rank[length])
                        rank[length] += n
                    at = window - per_pack * length
                    room[at].append((slots, n))
                    widest = max(widest, at)
                    left -= per_pack * n
    rows, sequence, padding = [], 0, 0
    for space, groups in enumerate(room):
        for slots, count in groups:
            chain = []
            while slots is not None:
                slots, length, first = slots
                chain.append((length, first))
            at = 0
            for length, first in reversed(chain):
                rows.append((length, first, sequence, at))
                at += length
            sequence += count
            used = window - space
            padding += count * (0 if used & (used - 1) == 0 else space)
    rows.sort()
    cols = np.array(rows, np.int64).reshape(-1, 4)
    return Patterns(cols[:, 0], cols[:, 1], cols[:, 2], cols[:, 3], sequence, padding)


def _shift(slots: tuple | None, by: int) -> tuple | None:
    """The same pattern for the packs after the first `by` ones."""
    chain = []
    while slots is not None:
        slots, length, first = slots
        chain.append((length, first + by))
    out = None
    for length, first in reversed(chain):
        out = (out, length, first)
    return out


def pack(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", vocabulary: str | None = None, window: int = 2048, keep: list[str] | None = None) -> DataFrame:
    """keep columns (default: doc_id) + start, length, ids_crc32, doc_tokens, sequence_id, offset; one row per piece."""
    vocabulary = vocabulary or default_vocabulary()
    added = ["start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]
    keep = [c for c in ([doc_id] if keep is None else keep) if c.lower() not in added]
    part, local = (fresh([*keep, *added], n) for n in ("_part", "_local"))
    schema = T.StructType([docs.schema[c] for c in keep] + [T.StructField(c, T.LongType()) for c in added[:4]] + [T.StructField(part, T.IntegerType()), T.StructField(local, T.LongType())])
    source = docs.select(*[F.col(f"`{c}`") for c in keep], F.col(f"`{text}`").cast("string").alias(fresh(keep, "_text")))
    pieces = store(source.mapInArrow(_tokenize(vocabulary, window, len(keep), schema.names), schema))
    counts = store(pieces.groupBy(F.col(part).alias("_p"), F.col("length").alias("_l")).agg(F.count("*").alias("_n")))
    histogram = {r["_l"]: r["n"] for r in counts.groupBy("_l").agg(F.sum("_n").alias("n")).collect()}  # at most `window` rows
    patterns = shortest_pack_first(histogram, window)
    bases = counts.select("_p", "_l", (F.sum("_n").over(Window.partitionBy("_l").orderBy("_p")) - F.col("_n")).alias("_base"))
    ranked = pieces.join(bases, (pieces[part] == bases["_p"]) & (pieces["length"] == bases["_l"]))
    ranked = ranked.select(*[pieces[c] for c in keep], *added[:4], (F.col("_base") + F.col(local)).alias(local))
    out = T.StructType(ranked.schema.fields[:-1] + [T.StructField("sequence_id", T.LongType()), T.StructField("offset", T.LongType())])
    names, k = out.names, len(keep)

    def place(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ranks = batch.column(k + 4).to_numpy(zero_copy_only=False).astype(np.int64)
            lengths = batch.column(k + 1).to_numpy(zero_copy_only=False).astype(np.int64)
            sequence, offset = patterns.place(lengths, ranks) if len(ranks) else (ranks, ranks)
            yield pa.RecordBatch.from_arrays([batch.column(i) for i in range(k + 4)] + [pa.array(sequence), pa.array(offset)], names=names)

    return ranked.mapInArrow(place, out)
