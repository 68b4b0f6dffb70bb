"""The lexer has no limit on blanks, literals, names and scored characters."""

import random
import string

import pyarrow as pa
import pytest

from quorumgrad.llm import secrets

MIXED = "".join(random.Random(1).choices(string.ascii_letters + string.digits, k=600))


@pytest.mark.parametrize(
    ("text", "found"),
    [
        ("private_key" + " " * 12 + '= "Xy7#kLm29Qpz"', ["Xy7#kLm29Qpz"]),
        ("private_key" + "\t " * 5000 + '= "Xy7#kLm29Qpz"', ["Xy7#kLm29Qpz"]),
        (f'private_key = "{"Gh3x+" * 1500}"', ["Gh3x+" * 1500]),
        (f"private_key = '{'Gh3x+' * 300_000}'", ["Gh3x+" * 300_000]),
        ("".join(f"v{i} = 1\n" for i in range(10_001)) + 'zz = "Zq81mmPL77xK"\nclient_pass = zz', ["Zq81mmPL77xK"]),
        (f'user_pass = "{"z" * 256}{MIXED}"', ["z" * 256 + MIXED]),
    ],
)
def test_nothing_is_cut(text, found):
    ((_, spans),) = secrets.find_all(pa.array([text]))
    assert [text[a:b] for k, a, b in spans if k == "literal"] == found
