"""Secret scans: patterns propose candidates, a random forest removes false positives.

Everything on the executors is built-in SQL functions: one regular expression finds candidates with the text between
them, features are counted inside array lambdas, and the trained forest is a sum of CASE expressions. No shuffle.
Features: length, share of digits, upper case and marks, transitions between character classes one kind at a time, repeated and
distinct characters, dictionary coverage, a known prefix, the assigned name, neighbouring words, and the path.

The forest is grown with NumPy on the driver from labelled findings (path, before, value, label), whose features come from
the same SQL. `labelled_findings` generates a default set; pass your own reviewed findings instead where you have them.

Null or empty text: no candidates. Null path: as empty. Repeated rows are scanned each by itself.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, functions as F

from .shared import fresh

#: Names that secrets are assigned to, public key prefixes, words that hint at harmless values.
NAMES = r"pass(?:word|wd|phrase)?|pwd|secret|token|api[_-]?key|access[_-]?key|auth[_-]?key|client[_-]?secret|credential"
PREFIXES = r"^(?:AKIA|ASIA|ghp_|gho_|ghs_|github_pat_|glpat-|xox[abp]-|sk_live_|rk_live_|AIza|eyJ|SG\.)"
HARMLESS_NEAR = r"(?i)\b(?:commit|sha1|sha256|md5|checksum|digest|hash|uuid|guid|etag|revision|integrity|build|version|example|sample|placeholder|image|icon|font)\b\W*(?:\w+\W+)?$"
HARMLESS_PATH = r"(?i)(?:^|[/_.-])(?:test|tests|spec|example|examples|sample|samples|fixture|fixtures|mock|docs?|vendor|node_modules|lock)(?:[/_.-]|$)"
#: Words of which names, placeholders and code are made.
WORDS = (
    "about abc access account action active address admin after all alpha and another any api app application array asset auth back bar base batch beta block board body book "
    "build button byte cache call change check child class click client close cloud code color column command common config connect content context copy core count create "
    "current custom data date debug default delete demo deploy detail device dev directory document domain download dummy edit email enable end enter entry env environ error event "
    "example export failed field file filter first folder foo format frame from full function get global group guest handle header hello here home host http icon image import "
    "index info input insert instance item job key label last layout length level line link list load local location log login main manager master member message method mode "
    "model module name network new none not null number object offset open option order output package page param parent password path photo place port post prefix print private process "
    "product project public query read record release remote remove replace request reset resource response result return root row sample save schema screen script search secret section "
    "select send server service session set show simple size source stage start state static status storage store stream string style submit system table target task temp test text the theme "
    "this time title token tool total type under update upload user util value version view web widget window word work world write your"
).split()
DICTIONARY = r"(?i)" + "|".join(sorted((w for w in WORDS), key=lambda w: (-len(w), w)))

BARE = r"(?<![A-Za-z0-9+/_\-])(?=[A-Za-z+/_\-]*[0-9])(?=[0-9+/_\-]*[A-Za-z])[A-Za-z0-9+/_\-]{16,}={0,2}"
ASSIGNED = r"(?i:\b(?:" + NAMES + r")[\"']?\s{0,3}[=:]\s{0,3}[\"']?)[^\s\"'<>]{6,}"
PREFIXED = r"(?<![A-Za-z0-9])(?:(?:AKIA|ASIA)[A-Z0-9]{16}|gh[pousr]_[A-Za-z0-9]{20,}|github_pat_[A-Za-z0-9_]{20,}|glpat-[A-Za-z0-9_\-]{16,}|xox[abp]-[A-Za-z0-9\-]{10,}|[sr]k_live_[A-Za-z0-9]{16,}|AIza[A-Za-z0-9_\-]{30,})"
CANDIDATE = f"{ASSIGNED}|{PREFIXED}|{BARE}"
NAME_PART = r"^(?i:(?:" + NAMES + r")[\"']?\s{0,3}[=:]\s{0,3}[\"']?)"

FEATURES = ("size", "digits", "uppers", "marks", "letter_digit", "digit_letter", "lower_upper", "upper_lower", "repeats", "variety", "words", "prefix", "named", "harmless_near", "named_near", "harmless_path")


@dataclass(frozen=True)
class Forest:
    trees: int = 15
    depth: int = 6
    least: int = 8
    seed: int = 5


def _features(value: Column, named: Column, before: Column, path: Column) -> list[Column]:
    """The features of one candidate, doubles in the order of FEATURES."""
    size = F.greatest(F.length(value), F.lit(1))
    share = lambda pattern: F.regexp_count(value, F.lit(pattern)) / size
    return [
        size.cast("double"),
        share("[0-9]"),
        share("[A-Z]"),
        share("[^A-Za-z0-9]"),
        # transitions between classes of neighbouring characters
        share("[A-Za-z](?=[0-9])"),
        share("[0-9](?=[A-Za-z])"),
        share("[a-z](?=[A-Z])"),
        share("[A-Z](?=[a-z])"),
        share(r"(.)(?=\1)"),
        F.size(F.array_distinct(F.split(value, ""))) / F.least(size, F.lit(64)),
        1 - F.length(F.regexp_replace(value, DICTIONARY, "")) / size,
        F.when(value.rlike(PREFIXES), 1.0).otherwise(0.0),
        F.when(named, 1.0).otherwise(0.0),
        F.when(before.rlike(HARMLESS_NEAR), 1.0).otherwise(0.0),
        F.when(before.rlike(r"(?i)\b(?:" + NAMES + r"|key|bearer|authorization|login)\b\W*(?:\w+\W+)?$"), 1.0).otherwise(0.0),
        F.when(path.rlike(HARMLESS_PATH), 1.0).otherwise(0.0),
    ]


def labelled_findings(spark: SparkSession, rows: int = 6000) -> DataFrame:
    """(path, before, named, value, label): findings of known kinds, generated from row numbers by SQL alone.

    Lengths, alphabets, contexts and paths vary by hash; nothing in them is taken from any table that is scanned.
    """
    pick = lambda salt, n: f"cast(pmod(xxhash64('{salt}', id), {n}) as int)"
    size = lambda salt, lo, hi: f"({lo} + {pick('n' + salt, hi - lo + 1)})"
    bits = lambda salt: f"concat(md5(concat('{salt}', id)), md5(concat('{salt}x', id)), md5(concat('{salt}y', id)))"
    hexa = lambda salt, lo, hi: f"substring({bits(salt)}, 1, {size(salt, lo, hi)})"
    mixed = lambda salt, lo, hi: f"substring(translate(base64(unhex({bits(salt)})), '+/=', 'aZ9'), 1, {size(salt, lo, hi)})"
    marked = lambda salt, lo, hi: f"translate({mixed(salt, lo, hi)}, 'AEIOUaeiou', '!@#$%^*-_?')"
    word = lambda salt, options: f"element_at(array({', '.join(repr(o) for o in options)}), 1 + {pick(salt, len(options))})"
    plain = ("and the", "of this", "une de la", "in der", "value", "set", "on", "we use", "then", "")
    near = ("api key", "secret", "bearer", "token", "login", "access key", "authorization", "my password is", "secret key")
    some = WORDS[:: max(1, len(WORDS) // 60)]
    joined = lambda salt: f"concat({word(salt + 'a', some)}, {word(salt + 's', ('_', '-', '', '.'))}, {word(salt + 'b', some)}, {word(salt + 't', ('_', '-', ''))}, {word(salt + 'c', some)}, {word(salt + 'e', ('', '1', '2', '42', '_01', '2024'))})"
    kinds = [
        (hexa("p", 16, 64), "true", word("c", plain), 1),
        (mixed("b", 10, 48), "true", word("c", plain), 1),
        (marked("w", 8, 24), "true", word("c", plain), 1),
        (hexa("q", 16, 40), "true", word("c", plain), 1),
        (f"concat({word('pre', ('AKIA', 'ASIA'))}, substring(upper({mixed('k', 40, 40)}), 1, 16))", "false", word("c", plain), 1),
        (f"concat('AKIA', substring(translate(upper({mixed('l', 40, 40)}), '0123456789', 'QWRTYPSDFG'), 1, 16))", "false", word("c", plain), 1),
        (f"concat({word('pr2', ('ghp_', 'gho_', 'sk_live_', 'glpat-', 'xoxb-', 'AIza'))}, {mixed('g', 24, 40)})", "false", word("c", plain), 1),
        (mixed("r", 24, 44), "false", word("n", near), 1),
        (hexa("h", 32, 64), "false", word("n", near), 1),
        (hexa("s", 32, 64), "false", word("n", ("commit", "sha1", "revision", "at commit", "digest", "sha256")), 0),
        (hexa("d", 32, 40), "false", word("n", ("md5", "checksum", "etag", "hash", "integrity")), 0),
        (f"regexp_replace({hexa('u', 32, 32)}, '^(.{{8}})(.{{4}})(.{{4}})(.{{4}})', '$1-$2-$3-$4-')", "false", word("n", ("uuid", "guid", "id", "request", "and the")), 0),
        (joined("i"), "false", word("c", plain), 0),
        (joined("j"), "true", word("c", plain), 0),
        (f"concat({word('ph', ('changeme', 'your_password', 'example', 'placeholder', 'password', 'test_token', 'dummy_value', 'secret_here', 'enter-your-key', 'replace_me', 'hunter2', 'admin123', 'letmein'))}, {pick('pn', 7)})", "true", word("c", plain), 0),
        (f"{word('ref', ('os.environ[TOKEN]', 'process.env.API_KEY', 'getenv(SECRET)', 'config.password', 'request.headers.get', '${DB_PASSWORD}', 'settings.SECRET_KEY', 'self.access_key', 'None,', 'null;', 'user.password)'))}", "true", word("c", plain), 0),
        (f"{word('mask', ('xxxxxxxxxxxxxxxx', '****************', '12345678', '1234567890', 'abcdefgh', 'aaaaaaaaaaaa', '0000000000000000', 'XXXXXXXX', '........', 'qwertyuiop'))}", "true", word("c", plain), 0),
        (f"concat({word('px', ('AKIA', 'ASIA'))}, {word('py', ('EXAMPLEEXAMPLE', 'XXXXXXXXXXXXXX', 'IOSFODNNEXAMPL'))}, {pick('pz', 10)}, 'A')", "false", word("c", plain), 0),
        (f"concat({word('dir', ('assets', 'static', 'src', 'public', 'build'))}, '/', {word('di2', some)}, '/', {word('di3', some)}, '_', {pick('pf', 9999)}, 'x', {pick('pg', 77)})", "false", word("c", plain), 0),
        (f"concat('build-', 2000 + {pick('yr', 30)}, '-release-candidate-', {pick('rc', 12)})", "false", word("c", ("version", "build", "and")), 0),
        (mixed("e", 24, 40), "true", word("n", ("example", "sample value", "a placeholder")), 0),
        (f"concat({pick('d1', 9999999)}, '-', {pick('d2', 999999)}, 'th-item')", "false", word("c", plain), 0),
    ]
    n = len(kinds)
    case = lambda k: "case cast(pmod(id, {}) as int) {} end".format(n, " ".join(f"when {i} then {row[k]}" for i, row in enumerate(kinds)))
    shared = ("src/app", "lib/client", "", "web", "core/main")
    path = F.when(F.expr(case(3)) == 0, F.expr(word("path", ("tests/data", "docs/example", "vendor/lib", *shared)))).otherwise(F.expr(word("path", ("config/prod", "deploy/env", *shared))))
    return spark.range(rows).select(path.alias("path"), F.expr(case(2)).alias("before"), F.expr(case(1)).alias("named"), F.expr(case(0)).alias("value"), F.expr(case(3)).alias("label"))


def grow(x: np.ndarray, y: np.ndarray, spec: Forest) -> list:
    """Trees as nested (feature, threshold, left, right) or a leaf's share of label 1."""
    rng = np.random.default_rng(spec.seed)
    tries = max(1, round(np.sqrt(x.shape[1]))) + 1

    def split(rows: np.ndarray, depth: int):
        share = float(y[rows].mean())
        if depth == 0 or len(rows) < 2 * spec.least or share in (0.0, 1.0):
            return round(share, 4)
        best = None
        for f in rng.permutation(x.shape[1])[:tries]:
            values = np.unique(x[rows, f])
            if len(values) < 2:
                continue
            middle = (values[1:] + values[:-1]) / 2
            for t in np.unique(np.quantile(middle, np.linspace(0, 1, 12), method="nearest")):
                left = x[rows, f] < t
                a, b = y[rows[left]], y[rows[~left]]
                if min(len(a), len(b)) < spec.least:
                    continue
                impurity = len(a) * a.mean() * (1 - a.mean()) + len(b) * b.mean() * (1 - b.mean())
                if best is None or impurity < best[0]:
                    best = (impurity, int(f), float(t), left)
        if best is None:
            return round(share, 4)
        _, f, t, left = best
        return (f, round(t, 6), split(rows[left], depth - 1), split(rows[~left], depth - 1))

    return [split(rng.integers(0, len(y), len(y)), spec.depth) for _ in range(spec.trees)]


def fit(findings: DataFrame, spec: Forest = Forest(), sample: int = 20_000) -> list:
    """A forest from labelled findings; at most `sample` rows (smallest hashes) reach the driver."""
    made = _features(F.col("value"), F.col("named"), F.coalesce("before", F.lit("")), F.coalesce("path", F.lit("")))
    rows = findings.where("label in (0, 1) and value is not null").select(*[c.cast("double").alias(f) for c, f in zip(made, FEATURES, strict=True)], F.col("label").cast("int").alias("label"))
    got = rows.orderBy(F.xxhash64(*FEATURES), "label").limit(sample).collect()
    table = np.array([[r[f] for f in FEATURES] for r in got], float).reshape(-1, len(FEATURES))
    labels = np.array([r["label"] for r in got], float)
    return grow(table, labels, spec) if len(labels) else [0.5]


def _score(forest: list, feature) -> Column:
    def tree(node) -> Column:
        if not isinstance(node, tuple):
            return F.lit(float(node))
        f, t, left, right = node
        return F.when(feature(FEATURES[f]) < t, tree(left)).otherwise(tree(right))

    total = tree(forest[0])
    for node in forest[1:]:
        total = total + tree(node)
    return total / len(forest)


def with_findings(docs: DataFrame, forest: list, name: str, pieces: str, text: str = "text", path: str = "source", context: int = 60) -> DataFrame:
    """Adds `pieces` (texts between candidates) and `name`: an array of (lead, value, features..., score), in text order."""
    body = F.coalesce(F.col(f"`{text}`").cast("string"), F.lit(""))
    whole = fresh([*docs.columns, name, pieces], "_whole")
    found = docs.withColumn(whole, F.when(body.rlike(CANDIDATE), F.regexp_extract_all(body, F.lit(CANDIDATE), F.lit(0))).otherwise(F.array().cast("array<string>")))
    found = found.withColumn(pieces, F.when(F.size(whole) > 0, F.split(body, CANDIDATE, -1)).otherwise(F.array(body)))
    where = F.coalesce(F.col(f"`{path}`").cast("string"), F.lit(""))

    def parts(match: Column, i: Column) -> Column:
        lead = F.regexp_extract(match, NAME_PART, 0)
        value = F.substring(match, F.length(lead) + 1, F.length(match))
        before = F.right(F.coalesce(F.get(F.col(pieces), i), F.lit("")), F.lit(context))
        return F.struct(lead.alias("lead"), value.alias("value"), before.alias("before"))

    def judged(c: Column) -> Column:
        made = _features(c["value"], F.length(c["lead"]) > 0, c["before"], where)
        return F.struct(c["lead"].alias("lead"), c["value"].alias("value"), *[m.cast("double").alias(f) for m, f in zip(made, FEATURES, strict=True)])

    found = found.withColumn(name, F.transform(F.transform(F.col(whole), parts), judged))
    return found.withColumn(name, F.transform(F.col(name), lambda c: F.struct(*[c[k].alias(k) for k in ("lead", "value", *FEATURES)], F.round(_score(forest, lambda f: c[f]), 6).alias("score")))).drop(whole)


def scan(docs: DataFrame, forest: list | None = None, doc_id: str = "doc_id", text: str = "text", path: str = "source", least: float = 0.5) -> DataFrame:
    """One row per candidate: doc_id, ordinal (from 0, in text order), kind, size, sha256 of the value, score, secret."""
    forest = forest or fit(labelled_findings(docs.sparkSession))
    slim = docs.select(F.col(f"`{doc_id}`").alias("doc_id"), F.col(f"`{text}`").alias("text"), F.col(f"`{path}`").alias("path"))
    rows = with_findings(slim, forest, "found", "pieces", "text", "path").where(F.size("found") > 0).select("doc_id", F.posexplode("found").alias("ordinal", "f"))
    kind = F.when(F.col("f.prefix") > 0, "prefixed").when(F.col("f.named") > 0, "assigned").otherwise("bare")
    return rows.select("doc_id", "ordinal", kind.alias("kind"), F.length("f.value").alias("size"), F.sha2("f.value", 256).alias("value_sha256"), F.col("f.score").alias("score"), (F.col("f.score") >= least).alias("secret"))


def redact(docs: DataFrame, forest: list | None = None, text: str = "text", path: str = "source", least: float = 0.5, mark: str = "[secret]") -> DataFrame:
    """docs with every secret's value replaced by the mark; other texts and all other columns stay as they are."""
    forest = forest or fit(labelled_findings(docs.sparkSession))
    columns = docs.columns
    clean = docs.select(*[F.col(f"`{c}`").alias(f"c{i}") for i, c in enumerate(columns)])
    at = {c: f"c{i}" for i, c in enumerate(columns)}
    rows = with_findings(clean, forest, "found", "pieces", at[text], at[path])
    shown = F.transform("found", lambda c, i: F.concat(F.get(F.col("pieces"), i), c["lead"], F.when(c["score"] >= least, mark).otherwise(c["value"])))
    rebuilt = F.concat(F.array_join(shown, ""), F.element_at("pieces", -1))
    new = F.when(F.exists("found", lambda c: c["score"] >= least), rebuilt).otherwise(F.col(at[text]))
    return rows.select(*[(new if c == text else F.col(at[c])).alias(c) for c in columns])
