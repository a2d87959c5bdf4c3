"""Secrets that reach past a base span, stand behind many blanks or are long."""

import time

import pytest

from localfreq.llm import secrets

LONG = "aB3$xY9!" * 600


def rest(text):
    """The text without its spans."""
    done, out = 0, []
    for s, _, e in sorted(sum(secrets.find_spans(text), [])):
        out.append(text[done:max(s, done)])
        done = max(done, e)
    return "".join([*out, text[done:]])


@pytest.mark.parametrize("text, left", [
    ('password = "S3cr3tpass12#moreSecret!"', '"'),
    ('signing_key = "0123456789abcdef#Zz9!more"', 'signing_key = ""'),
    ("client_secret_value" + " " * 20 + '= "aB3$xY9!kL5#"', "client_secret_value" + " " * 20 + '= ""'),
    ("client_secret_value =" + "\t" * 20 + "'aB3$xY9!kL5#'", "client_secret_value =" + "\t" * 20 + "''"),
    (f'db_password = "{LONG}"', 'db_password = ""'),
    ("x" * 200 + '_secret_value = "aB3$xY9!kL5#"', "x" * 200 + '_secret_value = ""'),
    ('secret_value\n= "aB3$xY9!kL5#"', 'secret_value\n= ""'),
])
def test_whole_secrets_go(text, left):
    assert rest(text) == left


def test_long_constants_are_followed():
    text = f'K{" " * 20}= "{LONG}"\nauth_token = K'
    s = text.index(LONG)
    assert secrets.find_spans(text)[1] == [(s, 3, s + len(LONG))]


def test_covered_literals_are_not_listed_twice():
    assert secrets.find_spans('password = "abcdefgh1234"')[1] == []


@pytest.mark.parametrize("text, parts", [
    ('auth_token = "aB3$xY" + "9!kL5#"', ["aB3$xY", "9!kL5#"]),
    ('auth_token = "aB3$xY" \'9!kL5#\'', ["aB3$xY", "9!kL5#"]),
    ('auth_token = "aB3$xY" \\\n    "9!kL5#"', ["aB3$xY", "9!kL5#"]),
    ('auth_token = "aB3$xY"\n    . "9!kL5#"', ["aB3$xY", "9!kL5#"]),
    ('auth_token = (\n  "aB3$xY"\n  "9!kL5#"\n)', ["aB3$xY", "9!kL5#"]),
    ('K = "aB3$xY" + "9!kL5#"\nauth_token = K', ["aB3$xY", "9!kL5#"]),
    ('auth_token = "aB3$xY9!kL5#"\n"other": "plain text"', ["aB3$xY9!kL5#"]),
    ('auth_token = "aB3$xY9!kL5#" "other": "plain"', ["aB3$xY9!kL5#"]),
    ('auth_token = /* why */ "aB3$xY9!kL5#"', ["aB3$xY9!kL5#"]),
    ('# auth_token = "aB3$xY9!kL5#"', ["aB3$xY9!kL5#"]),
    ('K = "aB3$xY9!kL5#"\n# K = "zZ8&wW7?qQ6%"\nauth_token = K', ["aB3$xY9!kL5#"]),
    ('K = "aB3$xY9!kL5#"\n/* was\nK = "zZ8&wW7?qQ6%" */\nauth_token = K', ["aB3$xY9!kL5#"]),
    ('K = "aB3$xY9!kL5#"\nK = "zZ8&wW7?qQ6%"\nauth_token = K', ["zZ8&wW7?qQ6%"]),
    ('label = "aB3$xY" + "9!kL5#"', []),
])
def test_joined_literals_and_comments(text, parts):
    assert [text[s:e] for s, _, e in secrets.find_spans(text)[1]] == parts


@pytest.mark.parametrize("text", [" " * 200_000 + "=", "a" * 200_000 + " =", '="' + "a" * 200_000, "x='\"" * 50_000, "=" + " " * 200_000, "a:'" + 'b="' * 50_000, "." * 200_000 + "=", "/*" * 100_000 + "a=b", "a=" + '"x=" + ' * 50_000, "a=" + '"=" ' * 50_000, 'a="x" ' * 50_000, "a=(" + "\n" * 200_000, "#" * 200_000 + "\na=b", "a=/*" * 50_000])
def test_scan_is_linear(text):
    start = time.process_time()
    secrets.find_spans(text)
    assert time.process_time() - start < 5
