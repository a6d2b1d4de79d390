"""Trigram queries of optional groups and branches, against a full scan."""

import re

from tricount.llm import secrets


def test_optional_groups_and_branches_lose_nothing():
    texts = ["myfoo_token", "mytoken", "my_token", "xaby_key", "xcd_key", "x9q_key", "nothing"]
    for pattern in (r"my(?:[a-z]+_)?token", r"x(?:[a-z]+y|cd)_key", r"x(?:[0-9]q|ab[a-z])_key", r"[a-z]+_key"):
        found = secrets.Scanner((secrets.Rule("r", pattern),)).spans(texts)
        assert [[(s, e) for s, _, e in x] for x in found] == [[m.span() for m in re.finditer(pattern, t)] for t in texts]
