import hashlib
import re

from winnow.llm import secrets

HEX = "0123456789abcdef" * 2
TEXTS = [
    "password = token: abcdefghijk",
    "secret=token=abcdefgh API_KEY : 'Zz09+/_.=-x'",
    "apikey=short and passwd:longenough1",
    f"AKIAABCDEFGHIJKL AKIASHORT {HEX} x{HEX}f g{HEX[:-1]}",
    "ſecret=abcdefghij secret=abcdefghij Kelvin toKen=abcdefghij",
    'token""=abcdefgh "secret":"abc.def-ghi"',
    "é" * 5 + " token=12345678é" + " -----BEGIN RSA PRIVATE KEY-----",
    "",
    None,
]


def plain(text):
    """The base kinds by the contract's own words: match all, then drop what is too short."""
    text = text or ""
    out = []
    for m in re.finditer(r"""(?a:(?i:(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)))""", text):
        if len(m.group(2)) >= 8:
            out.append((m.start(), 0, f"assign:{m.start()}:{m.end()}"))
    for k, (kind, pattern, least) in enumerate((("access", "AKIA[A-Z0-9]+", 16), ("hex", "[0-9a-f]+", 32)), 1):
        for m in re.finditer(pattern, text):
            if m.end() - m.start() >= least:
                out.append((m.start(), k, f"{kind}:{m.start()}:{m.end()}"))
    out.sort()
    return [x[2] for x in out]


def rows_of(df):
    return {r.doc_id: (r.n_assign, r.n_access, r.n_hex, r.base_sha256, r.spans) for r in df.collect()}


def check(got, texts):
    for i, t in enumerate(texts):
        base = plain(t)
        a, b, c, sha, spans = got[i]
        assert (a, b, c) == tuple(sum(x.startswith(k) for x in base) for k in ("assign:", "access:", "hex:"))
        assert sha == hashlib.sha256(",".join(base).encode()).hexdigest()
        assert set(base) <= set(spans.split(",")) | {""}


def test_base_kinds_match_the_definition(spark):
    versions = secrets.paths(spark.createDataFrame(list(enumerate(TEXTS)), "doc_id long, text string"))
    got = rows_of(secrets.digest(secrets.findings(versions, secrets.scan(secrets.unseen(versions, None)))))
    check(got, TEXTS)
    assert "pem:" in got[6][4]


def test_whole_table(spark, sf):
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    got = rows_of(secrets.op2_secret_scan(spark, sf))
    assert got.keys() == texts.keys()
    check(got, [texts[i] for i in sorted(texts)])


def test_ledger_scans_only_what_is_new(spark, tmp_path):
    path = str(tmp_path / "ledger")
    first = spark.createDataFrame([(1, TEXTS[2]), (2, TEXTS[2]), (3, TEXTS[3])], "doc_id long, text string")
    ledger = secrets.update(spark, first, path)
    assert ledger.count() == 2 * len(secrets.RULES)  # the copy is scanned once
    second = first.unionByName(spark.createDataFrame([(4, TEXTS[1]), (5, TEXTS[2])], "doc_id long, text string"))
    due = secrets.unseen(secrets.paths(second), secrets.update(spark, first, path)).collect()
    assert [d.text for d in due] == [TEXTS[1]] and len(due[0].due) == len(secrets.RULES)
    ledger = secrets.update(spark, second, path)
    assert ledger.count() == 3 * len(secrets.RULES)
    newer = (secrets.RULES[0], secrets.Rule("access", 2, "AKIA[A-Z0-9]{12}"), *secrets.RULES[2:])
    assert {tuple(d.due) for d in secrets.unseen(secrets.paths(second), ledger, newer).collect()} == {("access",)}
    whole = rows_of(secrets.digest(secrets.findings(secrets.paths(second), ledger)))
    assert whole[5] == whole[1] and whole[5][0] == 1


def test_versions_of_a_path_in_one_table(spark, tmp_path):
    """Three versions of one path, one of them held by another path as well: each version has its findings, each blob one scan."""
    rows = [(1, "token=abcdefgh"), (1, "token=abcdefgh and AKIAABCDEFGHIJKLMN"), (1, "clean now"), (2, "clean now"), (2, "token=abcdefgh")]
    versions = spark.createDataFrame(rows, "doc_id long, text string")
    ledger = secrets.update(spark, versions, str(tmp_path / "ledger"))
    assert ledger.count() == 3 * len(secrets.RULES) and ledger.dropDuplicates(["blob", "rule"]).count() == ledger.count()
    got = sorted((r.doc_id, r.n_assign, r.n_access) for r in secrets.digest(secrets.findings(secrets.paths(versions), ledger)).collect())
    assert got == [(1, 0, 0), (1, 1, 0), (1, 1, 1), (2, 0, 0), (2, 1, 0)]


def test_the_query_writes_and_reads_its_ledger(spark, sf, tmp_path):
    path = str(tmp_path / "ledger")
    first = rows_of(secrets.op2_secret_scan(spark, sf, path))
    ledger = spark.read.parquet(path)
    blobs = len({hashlib.sha256((r.text or "").encode()).hexdigest() for r in spark.read.parquet(f"{sf}/documents.parquet").collect()})
    assert ledger.count() == blobs * len(secrets.RULES)
    assert rows_of(secrets.op2_secret_scan(spark, sf, path)) == first and spark.read.parquet(path).count() == ledger.count()


def test_empty_and_odd_tables(spark):
    none = spark.createDataFrame([], "doc_id long, text string, blob string")
    v = secrets.paths(none)
    assert secrets.digest(secrets.findings(v, secrets.scan(secrets.unseen(v, None)))).count() == 0
    odd = secrets.paths(spark.createDataFrame([(None, "token=abcdefgh", "x"), (None, "token=abcdefgh", "y")], "doc_id long, text string, blob string"))
    assert [r.n_assign for r in secrets.digest(secrets.findings(odd, secrets.scan(secrets.unseen(odd, None)))).collect()] == [1, 1]
