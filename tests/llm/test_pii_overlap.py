"""Overlapping values in texts with many of them."""

from bucketcsr.llm import pii


def test_a_value_inside_another_is_not_counted_however_many_there_are():
    p = pii.Pseudonyms(b"k" * 32)
    many = " ".join(f"user{k}@host.org" for k in range(100))
    for value, kinds in (("mail_2020-01-02@x.org", ["email"]), ("+1 2024-01-01", ["date"])):
        alone, found = p(value)
        assert [k for k, _, _ in found] == kinds
        tail = " ".join(["2021-03-04"] * 100)
        new, spans = p(f"{value} {many} {tail}")
        assert new.startswith(alone + " ") and [k for k, _, _ in spans] == kinds + ["email"] * 100 + ["date"] * 100
        assert all(a[2] <= b[1] for a, b in zip(spans, spans[1:], strict=False))
        assert p(new, back=True)[0] == f"{value} {many} {tail}"
