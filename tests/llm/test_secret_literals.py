"""Added literals of the secret scan on planted source and configuration lines, and the SimHash index's guarantee."""

from __future__ import annotations

import random
from itertools import combinations

import pytest

from depscope.llm import secrets, simhash

LETTERS = "abcdefghijkmnpqrstuvwxyzABCDEFGHJKLMNPQRSTUVWXYZ23456789"


def found(text: str) -> list[str]:
    return [text[s:e] for _, s, e in secrets.added_spans(text, secrets.base_spans(text))]


@pytest.mark.parametrize(
    "line, literal",
    [
        ('my_pwd = "a\\\\b9XkQ27zLm"', "a\\\\b9XkQ27zLm"),
        ('db.pwd = "say \\"Qx71\\" Lm29z"', None),  # white space: not a secret's form
        ("pwd=Abc123!xyz789", "Abc123!xyz789"),
        ("pwd: $2y$10$Qx71Lm29zTT", "$2y$10$Qx71Lm29zTT"),
        ('CLIENT_CREDENTIALS = """Qx71Lm29zTTp"""', "Qx71Lm29zTTp"),
        ("signingKey := `Qx71Lm29zTTp`", "Qx71Lm29zTTp"),
        ('pwd = "sk_live_0123456789abcdef0123"', "sk_live_0123456789abcdef0123"),
        ('author = "Qx71Lm29zTTp"', None),
        ('monkey = "Qx71Lm29zTTp"', None),
        ('keyboard: "Qx71Lm29zTTp"', None),
        ("if pwd == Qx71Lm29zTTp9:", None),
    ],
)
def test_lexed_literals(line, literal):
    assert found(line) == ([literal] if literal else [])


def made(rnd: random.Random) -> str:
    return "".join(rnd.choice(LETTERS) for _ in range(rnd.randint(14, 28))) + rnd.choice(["7", "42", "x9"])


def test_planted_literals(spark):
    """Precision and recall of added spans on lines in several syntaxes; the README gives the figures."""
    rnd = random.Random(8)
    names = ["db_pwd", "smtpPassphrase", "client-credential", "signingKey", "ADMIN_PASSCODE", "bearer", "userAuth", "PRIVATE_KEY"]
    plain = ["title", "author", "region", "build_id", "color", "file.path", "hostname", "keyboard", "monkey", "checksum_name", "author_id", "compass"]
    forms = ['{n} = "{v}"', "{n}: {v}", "export {n}='{v}'", '{{"{n}": "{v}", "x": 1}}', "{n} := `{v}`", 'set("{n}") ; {n} => "{v}"', 'v = "{v}"\n{n} = v', "<!-- --> {n}={v}"]
    rows, want = [], {}
    for i in range(400):
        v = made(rnd)
        rows.append((i, rnd.choice(["", "some words before\n", "# note\n"]) + rnd.choice(forms).format(n=rnd.choice(names), v=v) + "\nend"))
        want[i] = v
    rows += [(1000 + i, rnd.choice(forms).format(n=rnd.choice(plain), v=made(rnd))) for i in range(300)]
    rows += [(2000 + i, rnd.choice(forms).format(n=rnd.choice(names), v=rnd.choice(["changeme", "your-password-here", "${SECRET_VALUE}", "example12345", "nonesuch"]))) for i in range(100)]
    right = wrong = 0
    for i, text in rows:
        for x in found(text):
            if want.get(i) == x:
                right += 1
            else:
                wrong += 1
    got = {r.doc_id: r.spans for r in secrets.scanned(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert sum("literal" in s for s in got.values()) == sum(bool(found(t)) for _, t in rows)
    print(f"added secrets: precision {right / (right + wrong):.3f}, recall {right / 400:.3f}")
    assert right / (right + wrong) > 0.95 and right / 400 > 0.9


def test_every_close_pair_meets_in_the_least_number_of_lists():
    lists = [set(t) for t in simhash.TRIPLES]
    assert len(set(simhash.TRIPLES)) == 16
    assert min(sum(t <= set(shared) for t in lists) for shared in combinations(range(8), 5)) == simhash.LEAST_LISTS
    # a pair that shares three bytes alone never reaches it: this is what the tally removes
    assert max(sum(t <= set(shared) for t in lists) for shared in combinations(range(8), 3)) == 1


def test_tally_drops_pairs_and_loses_no_link(spark):
    rnd = random.Random(6)
    some = [[rnd.choice([0, 1, 2]) for _ in range(8)] for _ in range(400)]
    fps = sorted({int.from_bytes(bytes(x), "big") for x in some})
    df = spark.createDataFrame([(f - (1 << 64) if f >> 63 else f,) for f in fps], "fp long")
    met = simhash._meetings(simhash._postings(df, simhash.TRIPLES)).collect()
    kept = {(r.a, r.b) for r in simhash._verified(simhash._meetings(simhash._postings(df, simhash.TRIPLES)), simhash.LEAST_LISTS).collect()}
    close = {(a, b) for a, b in combinations(fps, 2) if (a ^ b).bit_count() <= 3}
    assert kept == close
    assert sum(r.lists >= simhash.LEAST_LISTS for r in met) < len(met)
