"""Secret scans on findings drawn by another generator than the training rows, and the native plan."""

import random
import string

import pytest

from bucketcsr.llm import secrets
from bucketcsr.measures import plan_facts

CONTEXT = "lorem ipsum dolor sit amet consectetur le petit chat mange une pomme der Hund schläft heute nicht".split()
NAMES = ["token", "password", "api_key", "SECRET", "client_secret", "access-key", "passwd"]
IDENTIFIERS = "order invoice customer queue worker thread parser lexer button canvas socket router handler matrix vector".split()


def draw(rng):
    """(text with one value, value, whether it is a secret)."""
    chars = lambda alphabet, lo, hi: "".join(rng.choice(alphabet) for _ in range(rng.randint(lo, hi)))
    words = lambda n: " ".join(rng.choice(CONTEXT) for _ in range(n))
    name, quote = rng.choice(NAMES), rng.choice(["", '"', "'"])
    strong = string.ascii_letters + string.digits
    kind = rng.randrange(10)
    if kind == 0:
        value, lead = chars("0123456789abcdef", 20, 48), f"{name} = {quote}"
    elif kind == 1:
        value, lead = chars(strong, 16, 40), f"{name}: {quote}"
    elif kind == 2:
        value, lead = chars(strong + "!#$%&*+-@^_", 14, 28), f"{name}={quote}"
    elif kind == 3:
        value, lead, quote = "ghp_" + chars(strong, 36, 36), "pushed with ", ""
    elif kind == 4:
        value, lead, quote = "AKIA" + chars(string.ascii_uppercase + string.digits, 16, 16), "id ", ""
    elif kind == 5:
        value, lead, quote = chars("0123456789abcdef", 40, 40), rng.choice(["commit ", "revision ", "sha1 "]), ""
    elif kind == 6:
        value, lead, quote = "_".join(rng.choice(IDENTIFIERS) for _ in range(3)) + str(rng.randint(1, 99)), "", ""
    elif kind == 7:
        value, lead = rng.choice(["changeme", "your_token_here", "placeholder", "example_value", "test_password", "insert-key-here"]), f"{name} = {quote}"
    elif kind == 8:
        value, lead, quote = rng.choice(["os.environ[KEY]", "settings.password", "config.get(token)", "${API_TOKEN}", "process.env.SECRET"]), f"{name} = ", ""
    else:
        value, lead = rng.choice("x*0") * rng.randint(8, 20), f"{name} = {quote}"
    return f"{words(6)} {lead}{value}{quote} {words(4)}", value, kind < 5


@pytest.fixture(scope="module")
def forest(spark):
    return secrets.fit(secrets.labelled_findings(spark))


def test_precision_and_recall_on_another_generator(spark, forest):
    rng = random.Random(17)
    cases = [draw(rng) for _ in range(1500)]
    df = spark.createDataFrame([(i, t, rng.choice(["web", "crawl/17", "books", None])) for i, (t, _, _) in enumerate(cases)], "doc_id bigint, text string, source string")
    rows = secrets.scan(df, forest).collect()
    found = {r["doc_id"] for r in rows if r["secret"]}
    candidates = {r["doc_id"] for r in rows}
    real = {i for i, c in enumerate(cases) if c[2]}
    assert real <= candidates
    assert len(found & real) / len(real) > 0.95
    assert len(found & real) / len(found) > 0.95
    # without the forest every candidate would be reported
    assert len(candidates - real) > 300
    clean = {r["doc_id"]: r["text"] for r in secrets.redact(df, forest).collect()}
    for i, (text, value, _) in enumerate(cases):
        assert (value not in clean[i]) if i in found else clean[i] == text


def test_the_scan_runs_without_python(spark, forest):
    df = spark.createDataFrame([(1, "token = abcdef0123456789abcdef", "a")], "doc_id bigint, text string, source string")
    assert plan_facts(secrets.scan(df, forest))["python"] == 0
    assert plan_facts(secrets.redact(df, forest))["python"] == 0
