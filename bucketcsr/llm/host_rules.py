"""Host-level quality rules.

Each text is held against the plain RULES; every rule's failures are counted by host. For each rule a beta prior is fitted to the
hosts' failure rates (method of moments), and each host's rate is shrunk towards it: the posterior mean lies between the host's own
share and the mean of all hosts, nearer to the latter the fewer texts the host has. The prior never weighs more than a host of
mean size, so hosts that are all alike do not freeze it. A host falls as a whole when for some rule it is credibly both an outlier
and bad: the posterior rate less `certain` posterior deviations lies above the rule's bar, which is the prior mean plus
`outlying` prior deviations, `worst_rate` at least and, for the two rules that reject texts by themselves, `surely_bad` at most.
Verdicts are joined back to the documents.

Plan: one Arrow pass per text; a partial aggregate by host, one row per host; one small aggregate for
the priors; a join of the *rejected* hosts (broadcast only below `broadcast_hosts`, else a shuffled
join, whose hot hosts AQE splits).

Null or empty text: no words, so the base rule rejects it. Null host: a host of its own. An empty table
gives an empty result. Repeated rows are judged row by row; extra columns are ignored or passed along.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce
from operator import or_

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F, types as T

from . import words as W
from .shared import fresh, map_text, store

SYMBOLS = np.zeros(256, bool)
SYMBOLS[list(b"#*$%&|<>")] = True
WINDOW = 8


@dataclass(frozen=True)
class HostRules:
    """least_words, most_repeat: the base rule; the rest: when a host is rejected."""

    least_words: int = 20
    most_repeat: int = 30  # percent of words inside repeated windows
    worst_rate: float = 0.5  # a host's credible failure rate must be above this at least
    surely_bad: float = 0.8  # rate of texts failing a base rule that no host may have, outlier or not
    outlying: float = 2.0  # prior deviations above the mean of hosts
    certain: float = 3.0  # posterior deviations below the host's shrunk rate
    least_docs: int = 20  # hosts with fewer texts are never rejected as hosts
    broadcast_hosts: int = 100_000


FEATURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
N_LINES = "n_lines"  # lines with a word; for the rules alone


BASE = ("short", "repeats")


def failures(rules: HostRules, col=F.col) -> dict[str, Column]:
    """Whether a text fails each rule. Those in BASE make up the base rule; the others count for hosts only."""
    n = col("n_words")
    return {
        "short": n < rules.least_words,
        "repeats": 100 * col("n_repeat_words") > rules.most_repeat * n,
        "symbols": 10 * col("n_symbols") > n,
        "dup_lines": 10 * col("n_dup_lines") > 3 * col(N_LINES),
        "word_size": (col("word_chars") < 2 * n) | (col("word_chars") > 15 * n),
    }


def repeated_words(ids: np.ndarray, first: np.ndarray, window: int = WINDOW) -> np.ndarray:
    """By text: words inside windows whose word sequence occurs twice or more in that text.

    A 64-bit rolling sum finds candidates; equal candidates are then compared word by word.
    """
    n, docs = len(ids), len(first) - 1
    doc = np.repeat(np.arange(docs), np.diff(first))
    at = np.arange(max(0, n - window + 1))
    at = at[doc[at] == doc[at + window - 1]] if len(at) else at
    if not len(at):
        return np.zeros(docs, np.int64)
    value = W.mixed(ids + 1)
    key = W.mixed(doc[at] + 0x9E37)
    for k in range(window):
        key = key * np.uint64(0x9E3779B97F4A7C15) + value[at + k]
    order = np.argsort(key, kind="stable")
    ranked = key[order]
    same = np.zeros(len(ranked) + 1, bool)
    same[1:-1] = ranked[1:] == ranked[:-1]
    maybe = np.sort(at[order[same[1:] | same[:-1]]])
    if not len(maybe):
        return np.zeros(docs, np.int64)
    rows = np.empty((len(maybe), window + 1), np.int64)
    rows[:, 0] = doc[maybe]
    for k in range(window):
        rows[:, k + 1] = ids[maybe + k]
    group = np.lexsort(rows.T[::-1])
    equal = np.zeros(len(group) + 1, bool)
    equal[1:-1] = (rows[group[1:]] == rows[group[:-1]]).all(axis=1)
    found = maybe[group[equal[1:] | equal[:-1]]]
    cover = np.zeros(n + 1, np.int64)
    np.add.at(cover, found, 1)
    np.add.at(cover, found + window, -1)
    return W.sums((np.cumsum(cover[:-1]) > 0).astype(np.int64), first)


def repeated_lines(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """By text: lines with a word that equal an earlier line of the text, and lines with a word."""
    newline = raw == 0x0A
    cuts = np.flatnonzero(newline)
    starts = np.union1d(offsets[:-1], cuts + 1)
    starts = starts[starts < len(raw)]
    if not len(starts):
        return np.zeros(len(offsets) - 1, np.int64), np.zeros(len(offsets) - 1, np.int64)
    before = np.zeros(len(raw) + 1, np.int64)
    np.cumsum(~newline, out=before[1:])
    filled = np.zeros(len(raw) + 1, np.int64)
    np.cumsum(~W.SPACE[raw], out=filled[1:])
    ends = np.append(starts[1:], len(raw))
    full = filled[ends] > filled[starts]
    body = raw[~newline]
    lines = W.Words(body, np.append(before[starts], len(body)), np.searchsorted(starts, offsets))
    ids, _ = lines.encoded()
    doc = lines.doc
    keys = (doc * (len(ids) + 1) + ids)[full]
    _, at = np.unique(keys, return_index=True)
    again = np.ones(len(keys), bool)
    again[at] = False
    return np.bincount(doc[full][again], minlength=len(offsets) - 1), np.bincount(doc[full], minlength=len(offsets) - 1)


def features(texts: pa.Array) -> list[pa.Array]:
    raw, offsets = W.flat(texts)
    words = W.split(raw, offsets)
    ids, _ = words.encoded()
    points = ((raw & 0xC0) != 0x80) & ~W.SPACE[raw]
    again, lines = repeated_lines(raw, offsets)
    made = (np.diff(words.first), W.sums(points, offsets), W.sums(SYMBOLS[raw], offsets), again, repeated_words(ids, words.first), lines)
    return [pa.array(x.astype(np.int64)) for x in made]


def measure(docs: DataFrame, text: str = "text", keep: list[str] | None = None) -> DataFrame:
    """The kept columns and the counts of each text, under the names in FEATURES and N_LINES."""
    return map_text(docs, text, [T.StructField(c, T.LongType()) for c in (*FEATURES, N_LINES)], features, keep)


def base_failed(rules: HostRules, col=F.col) -> Column:
    made = failures(rules, col)
    return reduce(or_, (made[r] for r in BASE))


def beta_priors(hosts: DataFrame, names: list[str]) -> dict[str, tuple[float, float]]:
    """By rule (mean, strength) of the beta prior of failure rates, from hosts(n, bad_<rule>...) by moments; two small aggregates.

    strength counts like so many texts: between 2 and the mean number of a host.
    """
    n, k, squares, *bad = (float(x or 0) for x in hosts.agg(F.sum("n"), F.count("*"), F.sum(F.col("n") * F.col("n")), *[F.sum(f"bad_{r}") for r in names]).first())
    if not n:
        return dict.fromkeys(names, (0.5, 2.0))
    means = {r: min(max(x / n, 1e-6), 1 - 1e-6) for r, x in zip(names, bad, strict=True)}
    spreads = hosts.agg(*[F.sum(F.col("n") * F.pow(F.col(f"bad_{r}") / F.col("n") - F.lit(m), 2)) for r, m in means.items()]).first()
    scale, made = n - squares / n, {}
    for (r, m), spread in zip(means.items(), spreads, strict=True):
        # between-host variance: weighted spread less what binomial sampling alone would give
        between = max(0.0, (float(spread) - (k - 1) * m * (1 - m)) / scale) if scale > 0 else 0.0
        strength = m * (1 - m) / between - 1 if between > 0 else n / k
        made[r] = (m, max(2.0, min(strength, n / k)))
    return made


def host_verdicts(judged: DataFrame, host: str, rules: HostRules) -> DataFrame:
    """One row per host: host, n, failures and shrunk rate by rule, and the rules for which it falls (comma-joined; empty: it stays)."""
    made = failures(rules)
    counted = judged.groupBy(F.col(host).alias("host")).agg(F.count("*").alias("n"), *[F.sum(c.cast("long")).alias(f"bad_{r}") for r, c in made.items()])
    hosts = store(counted)
    fell = []
    for r, (mean, strength) in beta_priors(hosts, list(made)).items():
        rate = (F.col(f"bad_{r}") + F.lit(mean * strength)) / (F.col("n") + F.lit(strength))
        sure = rate - rules.certain * F.sqrt(rate * (1 - rate) / (F.col("n") + F.lit(strength + 1)))
        bar = max(rules.worst_rate, mean + rules.outlying * (mean * (1 - mean) / (strength + 1)) ** 0.5)
        if r in BASE:
            bar = min(bar, rules.surely_bad)
        hosts = hosts.withColumn(f"rate_{r}", rate)
        fell.append(F.when((sure > F.lit(bar)) & (F.col("n") >= rules.least_docs), F.lit(r)))
    return hosts.withColumn("fell", F.concat_ws(",", *fell))


def judge(docs: DataFrame, text: str = "text", host: str = "source", rules: HostRules = HostRules(), keep: list[str] | None = None) -> DataFrame:
    """keep columns (default: all of docs) + FEATURES + base_failed, host_fell (rules, comma-joined), kept; one row per input row.

    Columns of docs that bear one of the added names are replaced.
    """
    added = {*FEATURES, N_LINES, "base_failed", "host_fell", "kept"}
    keep = [c for c in (docs.columns if keep is None else keep) if c.lower() not in added]
    tag = fresh([*docs.columns, *added], "_host")
    tagged = docs.withColumn(tag, F.col(f"`{host}`").cast("string"))
    judged = store(measure(tagged, text, [*keep, tag]).withColumn("base_failed", base_failed(rules)))
    fallen = store(host_verdicts(judged, tag, rules).where("fell <> ''").select(F.col("host").alias("_v_host"), F.col("fell").alias("_v_fell")))
    if fallen.count() <= rules.broadcast_hosts:
        fallen = F.broadcast(fallen)
    joined = judged.join(fallen, judged[tag].eqNullSafe(fallen["_v_host"]), "left")
    return joined.select(*[judged[c] for c in keep], *FEATURES, "base_failed", F.coalesce("_v_fell", F.lit("")).alias("host_fell"), (~F.col("base_failed") & F.col("_v_fell").isNull()).alias("kept"))
