"""Key blocks and signed tokens against plain patterns, and texts that repeat what a scan starts at."""

import base64
import json
import random
import re
import time

import pytest

from assetmill.llm import secrets

JWT = re.compile(rb"(eyJ[A-Za-z0-9_-]+)\.eyJ[A-Za-z0-9_-]+\.[A-Za-z0-9_-]+")
PEM = re.compile(rb"-----BEGIN ((?:[A-Z0-9]+ )*PRIVATE KEY)-----[A-Za-z0-9+/=\s:,-]*?-----END \1-----")
HEAD = base64.urlsafe_b64encode(json.dumps({"alg": "HS256"}).encode()).rstrip(b"=")
PARTS = [b"-----BEGIN PRIVATE KEY-----", b"-----BEGIN RSA PRIVATE KEY-----", b"-----END PRIVATE KEY-----", b"-----END RSA PRIVATE KEY-----", b"\nAbc+/=\n", b" ", b"!", b"-----", b"eyJ", b"eyJx", b".", HEAD, b".eyJhIjoxfQ.", b"sig", b"\n"]


def plain(buf):
    out = []
    for m in JWT.finditer(buf):
        if secrets._is_jwt(m[1]):
            out.append((m.start(), m.end(), "jwt"))
    return out + [(m.start(), m.end(), "pem") for m in PEM.finditer(buf)]


def test_runs_as_plain_patterns():
    rng, seen = random.Random(4), set()
    for _ in range(6000):
        buf = b"".join(rng.choice(PARTS) for _ in range(rng.randint(1, 14)))
        got = [x for x in secrets.byte_spans(buf) if x[2] in ("jwt", "pem")]
        assert sorted(got) == sorted(plain(buf))
        seen |= {x[2] for x in got}
    assert seen == {"jwt", "pem"}


@pytest.mark.parametrize("unit", [b"-----BEGIN PRIVATE KEY-----\n", b"eyJ", b"eyJ.", b"token:", b"token ", b"AKIA", b"0123456789abcdef", b"-----BEGIN A A A ", b"-----END PRIVATE KEY-----", b"password = \"", b"ghp_"])
def test_ten_megabytes_of_starts(unit):
    began = time.time()
    secrets.byte_spans(unit * (10_000_000 // len(unit)))
    assert time.time() - began < 60
