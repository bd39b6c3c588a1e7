"""Values of each syntax that the secret scan lexes."""

import time

import pytest

pytest.importorskip("selweave.llm")

from selweave.llm import secrets  # noqa: E402

LONG = "Zk9" * 3000


@pytest.mark.parametrize(
    "text, value",
    [
        ("db_pwd: hunter22x\n", "hunter22x"),  # YAML
        ("  - db_pwd: hunter22x  # local\n", "hunter22x"),
        ("[db]\r\npassphrase=correcthorse9\r\n", "correcthorse9"),  # INI
        ("export AWS_CREDENTIAL=9fA8kkQ2mPz7\n", "9fA8kkQ2mPz7"),  # .env
        ("private_key: MIIEvQ+IBADAN/Bgkq==\n", "MIIEvQ+IBADAN/Bgkq=="),
        ("app.db.pwd = s3cr3t!value\n", "s3cr3t!value"),  # properties
        ('{\n  "session_credential": 9182736455,\n}', "9182736455"),  # JSON
        (f'{{"private_key": "{LONG}"}}', LONG),
        ("$pwd = 'hunT3r' . '22xyz';", "22xyz"),
        ('$end = "hunter22x";\n$db_pwd = $end."-5";', "hunter22x"),
    ],
)
def test_value_is_masked(text, value):
    assert value in text
    assert value not in secrets.redact_text(text)


def test_references_and_calls_are_no_literals():
    text = 'base = "s3cr3tvalue99"\ndb_pwd = base\nnew_pwd = getpass.getpass("Again")\n'
    spans = {text[s:e] for s, _, e in secrets.all_spans(text)[1]}
    assert "s3cr3tvalue99" in spans and "base" not in spans and not any("getpass" in x for x in spans)


@pytest.mark.parametrize("text", ['a="' * 100_000, "a='\\\"" * 100_000, 'pwd="' + "x" * 1_000_000, "a: " * 100_000, " " * 300_000])
def test_scan_is_linear(text):
    began = time.monotonic()
    secrets.all_spans(text)
    assert time.monotonic() - began < 20


@pytest.mark.parametrize(
    "text, secret",
    [
        ('os.environ["DB_PWD"] = "xK3nQ9vT2m"', "xK3nQ9vT2m"),
        ("config['credential'] = 'zz81KwPq04'", "zz81KwPq04"),
        ("const passphrase = `m4Tq8ZpL0x`;", "m4Tq8ZpL0x"),
        ('private_key = """MIIEow0\nq9Xv7Kd2"""', "MIIEow0\nq9Xv7Kd2"),
        ("<credential type='a'> p0Wq7Zr5Lm </credential>", "p0Wq7Zr5Lm"),
        ("passphrase: s3cr3tValue99", "s3cr3tValue99"),
        ('base = "q7Zr5Lmx81"\nother = base\nmy_credential = other', "q7Zr5Lmx81"),
    ],
)
def test_more_syntax(text, secret):
    at = text.index(secret)
    assert (at, 3, at + len(secret)) in secrets.all_spans(text)[1]


@pytest.mark.parametrize("text", ['credential = "plain text"', "passphrase: ask the owner", "<title>hunter2hunter2</title>", 'greeting["name"] = "xK3nQ9vT2m"'])
def test_prose_and_harmless_names_stay(text):
    assert secrets.all_spans(text)[1] == []
