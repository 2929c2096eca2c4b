"""Hosts that fall, and the same verdicts from the SQL beside the query."""

import duckdb

from bucketcsr.llm import entries, host_rules

GOOD = " ".join(f"word{i}" for i in range(40))
NOISY = " ".join(f"w{i} | # <" for i in range(40))
TWICE = "\n".join(["the same line of five words", *[f"line {i} of this very text" for i in range(3)]] * 2)


def table():
    """24 hosts of 50 texts: some texts of each are short; one host's are noisy, one's lines repeat, one host is tiny and bad."""
    rows = []
    for h in range(24):
        for i in range(50):
            text = "short" if i % 10 == h % 10 else NOISY if h == 7 and i % 9 else TWICE if h == 11 and i % 8 else GOOD
            rows.append((len(rows), text, f"host{h}"))
    rows += [(len(rows) + i, NOISY, "tiny") for i in range(5)]
    rows += [(len(rows) + i, GOOD if i % 3 else None, None) for i in range(30)]
    return rows


def test_outlying_hosts_fall_with_their_good_texts_and_sql_agrees(spark, tmp_path):
    df = spark.createDataFrame(table(), "doc_id bigint, text string, source string")
    df.write.parquet(f"{tmp_path}/documents.parquet")
    db = duckdb.connect()
    db.execute(f"create view documents as select * from '{tmp_path}/documents.parquet/*.parquet'")
    out = db.execute(entries.OP4_SQL)
    heads = [c[0] for c in out.description]
    want = sorted(tuple(r) for r in out.fetchall())
    got = entries.op4_host_rules(spark, str(tmp_path))
    assert sorted(tuple(r) for r in got.select(*heads).collect()) == want
    fell = {r["source"]: r["host_fell"] for r in host_rules.judge(df).where("host_fell <> ''").select("source", "host_fell").distinct().collect()}
    assert set(fell) == {"host7", "host11"} and "symbols" in fell["host7"] and "dup_lines" in fell["host11"]
    assert host_rules.judge(df).where("kept = base_failed").count() > 0


def test_hosts_that_are_alike_all_stay(spark):
    rows = [(i, "short" if i % 4 == 0 else GOOD, f"h{i % 13}") for i in range(1300)]
    judged = host_rules.judge(spark.createDataFrame(rows, "doc_id bigint, text string, source string"))
    assert judged.where("kept = base_failed").count() == 0


def test_one_host_and_no_rows(spark):
    rows = [(i, GOOD, "only") for i in range(30)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, source string")
    assert host_rules.judge(df).where("kept").count() == 30 and host_rules.judge(df.limit(0)).count() == 0
