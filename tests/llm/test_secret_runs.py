"""Keys of every DER length byte, and runs in either base64 alphabet."""

import base64
import random

from edgefold.llm import secrets

from .test_text_operators import der, rsa_key

EC, P256, K256, ED448 = bytes.fromhex("06072a8648ce3d0201"), bytes.fromhex("06082a8648ce3d030107"), bytes.fromhex("06052b8104000a"), bytes.fromhex("06032b6571")


def short_keys(rng):
    plain = lambda n: der(0x30, der(2, b"\x01"), der(4, rng.randbytes(n)))
    wrapped = lambda inner, *kind: der(0x30, der(2, b"\x00"), der(0x30, *kind), der(4, inner))
    bare = der(0x30, der(2, b"\x01"), der(4, rng.randbytes(32)), der(0xA0, P256))
    return [wrapped(plain(32), EC, P256), wrapped(plain(32), EC, K256), wrapped(der(4, rng.randbytes(57)), ED448), bare]


def found(text):
    return [(a, b) for a, b, k in secrets.confirmed_spans(text) if k == "der"]


def test_short_keys_in_base64_and_hex():
    for key in short_keys(random.Random(1)):
        run = base64.b64encode(key).decode()
        assert run[:2] in ("MD", "ME", "MF", "MG") and found(f"k {run} z") == [(2, 2 + len(run))] and found(key.hex()) == [(0, 2 * len(key))]


def test_runs_of_the_url_safe_alphabet_are_whole():
    rng, late = random.Random(2), 0
    for _ in range(60):
        for key in (*short_keys(rng), rsa_key(rng)):
            run = base64.urlsafe_b64encode(key).decode()
            late += any(run.find(c) > 40 for c in "-_")
            assert found(f"k {run} z") == [(2, 2 + len(run))]
    assert late


def test_a_key_before_a_mark_of_the_other_alphabet():
    key = short_keys(random.Random(4))[3]
    run = base64.b64encode(key).decode()
    assert found(f"k {run}-old") == [(2, 2 + len(run))]


def test_clean_runs_starting_with_m():
    rng = random.Random(3)
    for _ in range(300):
        assert found("M" + "".join(rng.choices("ABCDabcd0123+/-_", k=rng.randint(40, 120)))) == []
