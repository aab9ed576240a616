"""Features of words without bounds on their length."""

from hybridrange.llm import toxicity


def test_inner_runs_of_the_whole_word():
    found = toxicity.features(b"x" * 70 + b"insult")
    assert {b"insul", b"nsult", b"sult>"} <= found and b"<xxxx" in found
