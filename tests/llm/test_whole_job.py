"""Operators do the whole job: long lines, rare domains, long secrets."""

from quorumlab.llm import quality, secrets


def test_long_lines_are_judged_like_short_ones():
    at = quality.STATISTICS.index("worst_line_same")
    for n in (4_000, 6_000, 20_000):
        assert quality.statistics(b"again " * n)[at] == 1 - 1 / n


def linked(text):
    c = secrets.compiled_patterns()
    return [f[2] for f in secrets.linked_findings(text, secrets.base_findings(text, text.encode(), c), c)]


def test_long_secrets_reach_from_their_end():
    found = linked("user=alice " + "aB3" * 100 + " https://example.org/x")
    assert "linked_secret" in found and "linked_endpoint" not in found  # the identifier is out of the endpoint's reach
    assert "linked_endpoint" in linked("token=" + "aB3" * 100 + " https://example.org/x user=alice")


def test_many_base_spans_inside_a_value():
    value = "/".join(["0123456789abcdef01234567"] * 5) + "/Zz9" + "Q7" * 10
    assert "linked_secret" not in linked("user=alice token=" + value)
    assert "linked_secret" not in linked("user=alice token=" + "/".join(["0123456789abcdef01234567"] * 5) + ".Zz9" + "Q7" * 10)
