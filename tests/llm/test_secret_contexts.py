"""Secrets that are written more than once, and names that the base patterns miss."""

import random
import re
import string

import pytest

from semrank.llm import secret_scan


def secret(n, seed):
    return "".join(random.Random(seed).choices(string.ascii_letters, k=n - 4)) + "7x3Q"


def novel(text):
    return [tuple(map(int, x.split(":")[1:])) for x in secret_scan.scan(text)["spans"].split(",") if x.startswith("novel")]


@pytest.mark.parametrize("n", [16, 20, 24, 32, 64])
@pytest.mark.parametrize("apart", [0, 300, 1990, 2500])
def test_a_secret_written_twice(n, apart):
    v = secret(n, n)
    filler = ("the job reads its settings and starts again " * 60)[:apart]
    t = f"dev: auth_value = '{v}'\n{filler}\nprod: auth_value = '{v}'\nlog: sent {v} to the server\n"
    first, second = t.index(v), t.index(v, t.index(v) + 1)
    assert novel(t) == [(first, first + n), (second, second + n)]


NAMES = ["secret_key", "SECRET-KEY", "token2", "password_prod", "aws-secret-access-key", "API_KEY_2", "api-key", "private-key-1", "my_passwd_v2", "auth2", "session-id", "x-token-old", "signing_key"]


@pytest.mark.parametrize("name", NAMES)
@pytest.mark.parametrize("form", ["{} = '{}'", '"{}": "{}"', "{}={}", "{}: {}", "{} {}"])
def test_names(name, form):
    v = secret(24, 1)
    t = "some words before\n" + form.format(name, v) + "\nsome words after"
    assert novel(t) == [(t.index(v), t.index(v) + 24)]


def test_values_that_are_names_too():
    v = secret(24, 2)
    t = f"use authorization_token_1 = {v} now"
    assert (t.index(v), t.index(v) + 24) in novel(t)
    assert novel(f"colour_value = {v}") == [] and novel("the key " + "a" * 30) == []


def test_the_prefilter_lets_names_through(spark):
    v = secret(24, 3)
    rows = [(i, f"{name} = {v}") for i, name in enumerate(NAMES)]
    got = secret_scan.secret_scan(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()
    assert [r.n_novel for r in got] == [1] * len(rows)


def plain_novel(text):
    """The novel spans by a plain scan: every name and value, each judged by a compressor of its own."""
    import zstandard

    base = [(m.start(), m.end()) for m in secret_scan.ASSIGN.finditer(text) if len(m[2]) >= 6]
    base += [m.span() for m in re.finditer("AKIA[A-Z0-9]{16,}|[0-9a-f]{24,}", text)]
    out = []
    for m in re.finditer(r"""(?<![A-Za-z0-9_-])([A-Za-z0-9_-]+)(?=["']? *(?:[:=] *| )["']?([A-Za-z0-9+/_=-]{16,}))""", text, re.A):
        (s, e), v = m.span(2), m[2]
        if not any(w in m[1].lower() for w in secret_scan.NAMES) or any(a < e and s < b for a, b in base):
            continue
        if not any(c in "0123456789" for c in v) or not any(c.isalpha() for c in v):
            continue
        cut = lambda x: x.replace(v, " " * len(v))
        ids = re.findall("[A-Za-z_][A-Za-z0-9_]{2,}", cut(text))
        best = sorted(set(ids), key=lambda w: (-ids.count(w), w))[:2000]
        before, after = cut(text[max(0, s - 2000 - len(v)) : s])[-2000:], cut(text[e : e + 2000 + len(v)])[:2000]
        primer = (" ".join(sorted(best)) + "\n" + after + before).encode().ljust(8)
        z = zstandard.ZstdCompressor(level=19, dict_data=zstandard.ZstdCompressionDict(primer, dict_type=zstandard.DICT_TYPE_RAWCONTENT), write_content_size=False, write_dict_id=False)
        if (len(z.compress(v.encode())) - len(z.compress(b""))) / len(v) >= 0.55:
            out.append(f"novel:{s}:{e}")
    return out


def test_novel_spans_against_a_plain_scan():
    rng = random.Random(8)
    letters = string.ascii_letters + string.digits
    word = lambda: rng.choice(["config", "handler", "user_session", "auth_client", "request_token_cache", "license_key", "x"])
    found = 0
    for _ in range(60):
        lines = []
        for _ in range(rng.randrange(1, 25)):
            secret = "".join(rng.choices(letters, k=rng.choice([8, 16, 24, 40])))
            value = rng.choice([secret, "user_session_handler_of_request_1", word() * 3 + "7", "deadbeef" * 4])
            lines += [f"{word()}{rng.choice([' = ', ': ', '='])}{rng.choice(['', chr(34)])}{value}"] * rng.choice([1, 1, 2])
        text = "\n".join(lines)
        got = [x for x in secret_scan.scan(text)["spans"].split(",") if x.startswith("novel")]
        assert got == plain_novel(text)
        found += len(got)
    assert found > 100


def test_identifiers_far_away_are_known():
    name = "ConnectionPoolRegistry7ForSessions"
    for far, known in ((name.replace("7", "8"), True), ("Q" * len(name), False)):
        text = f"class {far}:\n    pass\n" * 3 + "filler words of prose that go on\n" * 300 + f"session = {name}\n"
        assert novel(text) == ([] if known else [(text.rindex(name), text.rindex(name) + len(name))])
