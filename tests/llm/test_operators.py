"""The corpus operators on small tables: exact answers by brute force, and rows of every awkward kind."""

import hashlib
import re
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from ripplegraph.llm import kernel as K
from ripplegraph.llm import op1_license_scan as op1
from ripplegraph.llm import op2_warc as op2
from ripplegraph.llm import op3_substring_dedup as op3
from ripplegraph.llm import op4_url_filter as op4
from ripplegraph.llm import op5_ngram_join as op5
from ripplegraph.llm import op6_decontamination as op6
from ripplegraph.llm import op7_toxicity as op7
from ripplegraph.llm import op8_pii as op8
from ripplegraph.llm import op9_quality as op9
from ripplegraph.llm import op10_mixing as op10
from ripplegraph.llm.store import Scratch

WORD = re.compile(r"[^\x20\x09-\x0D]+")
DOCS = "doc_id long, text string, lang string, source string, n_chars long, th string, words int"


def docs(spark, texts, sources=None):
    """Rows with extra columns whose names clash with the operators' own."""
    rows = [(i, t, "en", (sources or {}).get(i, "s1"), len(t or ""), "x", 1) for i, t in texts]
    return spark.createDataFrame(rows, DOCS)


def prose(seed, n):
    rng = np.random.default_rng(seed)
    return " ".join("".join(rng.choice(list("abcdefghij"), 5)) for _ in range(n))


BASE = prose(1, 120)
AWKWARD = [
    (1, BASE), (2, BASE), (2, BASE), (None, BASE + " tail"), (3, None), (4, ""), (5, " \n\t "), (6, "one"), (7, "one"), (8, prose(2, 60)), (9, prose(3, 9_000)),
    (10, " ".join(BASE.split()[:60] + prose(4, 40).split())), (11, "a " * 80), (12, prose(5, 30) + "\n" + prose(5, 30)), (13, "É ü\u00a0x \u2028 y"),
]


@given(st.lists(st.one_of(st.none(), st.text(alphabet="ab é\n\t\r\x0b\x0c\u00a0x", max_size=30)), max_size=8))
@settings(max_examples=60, deadline=None)
def test_kernel_cuts_the_same_words(texts):
    got = [[] for _ in texts]
    for w in K.slices(pa.array(texts, pa.string())):
        for b, e, d in zip(w.begin, w.end, w.doc, strict=True):
            got[w.first + d].append(w.data[b:e].tobytes().decode())
    assert got == [WORD.findall(t or "") for t in texts]


def test_kernel_hashes_follow_content():
    (w,) = K.slices(pa.array(["a b c a b", "b c"]))
    h = w.hashes()
    g = K.grams(h, 2)
    assert h[0] == h[3] and h[1] == h[5] and g[0] == g[3] and g[1] == g[5] and len(set(h.tolist())) == 3
    assert K.window_min(np.array([5, 3, 4, 1, 2, 9]), 3).tolist() == [3, 1, 1, 1]


def brute_removed(texts, width):
    words = [WORD.findall(t or "") for t in texts]
    seen = Counter(tuple(w[i : i + width]) for w in words for i in range(len(w) - width + 1))
    out = []
    for w in words:
        gone = set()
        for i in range(len(w) - width + 1):
            if seen[tuple(w[i : i + width])] > 1:
                gone |= set(range(i, i + width))
        kept = " ".join(x for i, x in enumerate(w) if i not in gone)
        out.append((len(w), len(gone), hashlib.sha256(kept.encode()).hexdigest()))
    return out


def test_substring_dedup_equals_brute_force(spark):
    got = op3.substring_dedup(spark, docs(spark, AWKWARD)).collect()
    expected = [(i, *x) for (i, _), x in zip(AWKWARD, brute_removed([t for _, t in AWKWARD], 35), strict=True)]
    assert Counter((r.doc_id, r.n_words, r.n_removed, r.kept_sha256) for r in got) == Counter(expected)


def test_substring_dedup_short_windows_and_nothing(spark):
    texts = [(i, " ".join(np.random.default_rng(i).choice(list("abc"), 30))) for i in range(12)]
    got = op3.substring_dedup(spark, docs(spark, texts), width=9).collect()
    assert Counter((r.doc_id, r.n_words, r.n_removed, r.kept_sha256) for r in got) == Counter((i, *x) for (i, _), x in zip(texts, brute_removed([t for _, t in texts], 9), strict=True))
    assert op3.substring_dedup(spark, docs(spark, [])).count() == 0


def brute_groups(texts):
    sets = []
    for t in texts:
        w = WORD.findall((t or "").translate({c: c + 32 for c in range(65, 91)}))
        sets.append({tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set())
    group = list(range(len(texts)))

    def root(x):
        while group[x] != x:
            x = group[x]
        return x

    for a in range(len(sets)):
        for b in range(a):
            if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b]):
                group[root(a)] = root(b)
    return sets, [root(x) for x in range(len(texts))]


def edited(text, n, seed):
    words = text.split()
    for i in np.random.default_rng(seed).choice(len(words), n, replace=False):
        words[i] = f"new{seed}x{i}"
    return " ".join(words)


def test_ngram_join_equals_brute_force(spark):
    texts = AWKWARD + [(100 + i, edited(BASE, i % 6, i)) for i in range(30)] + [(200 + i, edited(prose(8, 200), 2 + i % 9, i)) for i in range(30)]
    got = op5.ngram_components(spark, docs(spark, texts)).collect()
    sets, group = brute_groups([t for _, t in texts])
    least = {g: min((i for (i, _), h in zip(texts, group, strict=True) if h == g and i is not None), default=None) for g in group}
    expected = Counter((i, len(s), least[g] if s else i) for (i, _), s, g in zip(texts, sets, group, strict=True))
    assert Counter((r.doc_id, r.n_shingles, r.component_id) for r in got) == expected


def test_one_of_each_keeps_one_row_of_a_group(spark):
    kept = op5.one_of_each(spark, docs(spark, AWKWARD)).collect()
    _, group = brute_groups([t for _, t in AWKWARD])
    empty = sum(1 for _, t in AWKWARD if not WORD.findall(t or ""))
    assert len(kept) == len({g for g, (_, t) in zip(group, AWKWARD, strict=True) if WORD.findall(t or "")}) + empty
    assert op5.one_of_each(spark, docs(spark, [])).count() == 0


def test_leaks_equal_brute_force(spark):
    items = [(1, " ".join(BASE.split()[10:40])), (2, "one"), (3, None), (4, ""), (5, prose(9, 25)), (6, "x y x y x y x y x y")]
    texts = AWKWARD + [(20, "pre " + edited(prose(9, 25), 1, 3) + " post"), (21, "z " + " x y" * 6)]
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = {(r.doc_id, r.item_id): r.similarity for r in op6.leaks(spark, docs(spark, texts), bench).collect()}

    def words(t):
        return re.findall(r"[^\W_]+", (t or "").lower())

    def shingles(w, k):
        return Counter(tuple(w[i : i + k]) for i in range(len(w) - k + 1))

    expected = {}
    for i, t in texts:
        w = words(t)
        for j, x in items:
            v = words(x)
            k = min(5, len(v))
            for b in range(len(w) - len(v) + 1) if v else ():
                p, q = shingles(w[b : b + len(v)], k), shingles(v, k)
                s = sum((p & q).values()) / sum((p | q).values())
                if s >= 0.75:
                    expected[i, j] = max(expected.get((i, j), 0), s)
    assert got.keys() == expected.keys()
    assert all(got[k] == pytest.approx(expected[k]) for k in got)
    assert op6.leaks(spark, docs(spark, []), bench).count() == 0


def test_blocks_guarantee_the_radius(spark):
    """A fingerprint with any RADIUS bits turned shares an entry with the index."""
    rng = np.random.default_rng(5)
    rows = []
    for _ in range(200):
        a = int(rng.integers(-(2**62), 2**62))
        b = a
        for bit in rng.choice(63, op6.RADIUS, replace=False):
            b ^= 1 << int(bit)
        rows.append((a, b))
    frame = spark.createDataFrame(rows, "a long, b long")
    shared = F.arrays_overlap(op6.blocks_of(F.col("a"), False), op6.blocks_of(F.col("b"), True))
    assert frame.where(~shared).count() == 0


def test_archives_round_trip(spark, tmp_path):
    pages = [(1, "http://a.example/", "<p>é</p>"), (2, "http://b.example/\r\nX: y", "<p>é</p>"), (3, None, None), (4, "u", ""), (None, "v", "WARC/1.1\r\n\r\n"), (6, "w", "WARC/1.1\r\n\r\n"), (6, "w", "WARC/1.1\r\n\r\n")]
    frame = spark.createDataFrame([(*p, 7) for p in pages], "page_id long, url string, html string, digest int")
    scratch = Scratch(spark, "t")
    op2.archive_pages(frame, scratch.path("a"))
    whole = op2.read_archive(spark, scratch.path("a"), payloads=True).collect()
    assert Counter((r.page_id, bytes(r.payload).decode()) for r in whole) == Counter((i, h or "") for i, _, h in pages)
    op2.dedup_archive(spark, scratch.path("a"), scratch.path("b"), scratch)
    got = Counter((r.page_id, r.payload_bytes, r.record_type, r.refers_to) for r in op2.resolve(spark, scratch.path("b"), scratch).collect())
    assert got == Counter([(1, 9, "revisit", 2), (2, 9, "response", None), (3, 0, "revisit", 4), (4, 0, "response", None), (None, 12, "revisit", 6), (6, 12, "revisit", 6), (6, 12, "response", None)])
    assert op2.resolve(spark, scratch.path("b"), scratch).where("record_type = 'response'").select("payload_digest").distinct().count() == 3
    op2.dedup_archive(spark, scratch.path("a"), scratch.path("c"), scratch, least=10)
    assert op2.resolve(spark, scratch.path("c"), scratch).where("record_type = 'revisit'").count() == 2


def test_url_rules(spark):
    urls = ["https://A.Example.ORG/es/1", "http://example.org/en/12?x", "http://example.org/en/2#f", "x://com", "http://b.com/de/9", "http://notcom/de/", "nothing", None, "http://example.org?/es/", "://org/", "http://u:1@c.com:80/fr/"]
    got = [(r.host, r.path, r.rule, r.verdict) for r in op4.filter_urls(spark, spark.createDataFrame([(i, u, "z") for i, u in enumerate(urls)], "page_id long, url string, rule string"), op4.RULES).orderBy("page_id").collect()]
    assert got == [
        ("a.example.org", "/es/1", "example.org/es/", "block"), ("example.org", "/en/12", "example.org/en/1", "block"), ("example.org", "/en/2", "org/", "allow"), ("com", "", None, "allow"),
        ("b.com", "/de/9", "com/de/", "block"), ("notcom", "/de/", None, "allow"), ("", "", None, "allow"), ("", "", None, "allow"), ("example.org", "", None, "allow"), ("org", "/", "org/", "allow"), ("u:1@c.com:80", "/fr/", None, "allow"),
    ]


def test_licenses(spark):
    grant = op1.TEMPLATES["MIT-grant"]
    texts = [(1, "x\nReleased under the MIT License.\ny"), (2, "é " + edited(grant, 8, 1)), (3, None), (4, ""), (5, prose(1, 50)), (6, "Released under the MIT License. z " + op1.TEMPLATES["GPL-3.0"]), (6, "Released under the MIT License. z " + op1.TEMPLATES["GPL-3.0"])]
    rows = op1.license_scan(docs(spark, texts)).collect()
    assert Counter((r.doc_id, r.license) for r in rows) == Counter([(1, "MIT"), (2, "MIT-grant"), (6, "MIT"), (6, "GPL-3.0"), (6, "MIT"), (6, "GPL-3.0")])
    by = {i: t for i, t in texts}
    for r in rows:
        assert by[r.doc_id][r.begin_char : r.end_char].lower().split()[0] in ("released", "permission", "this") or r.doc_id == 2
        assert r.coverage >= op1.COVERAGE


def test_alignment_equals_full_longest_common_subsequence():
    rng = np.random.default_rng(2)
    for _ in range(30):
        a = rng.integers(0, 50, 30).astype(np.uint64)
        b = np.concatenate((rng.integers(100, 150, 10), np.where(rng.random(30) < 0.15, 99, a), rng.integers(100, 150, 10))).astype(np.uint64)
        full = np.zeros((31, len(b) + 1), dtype=int)
        for i in range(30):
            for j in range(len(b)):
                full[i + 1, j + 1] = full[i, j] + 1 if a[i] == b[j] else max(full[i, j + 1], full[i + 1, j])
        assert op1.align(a, b, 10, 10)[0] == full[30, len(b)]


def test_grammar_weakens_and_strengthens():
    plain = op7.clause_score([op7.INSULT], [2.0])
    assert op7.clause_score([op7.NEGATION, op7.OTHER, op7.INSULT], [0, 0, 2.0]) < plain
    assert op7.clause_score([op7.REPORT, op7.INSULT], [0, 2.0]) < plain
    assert op7.clause_score([op7.INSULT, op7.TARGET], [2.0, 0]) > plain
    assert op7.clause_score([op7.NEGATION, op7.OTHER, op7.OTHER, op7.OTHER, op7.INSULT], [0, 0, 0, 0, 2.0]) == plain


def test_toxicity_held_out(spark):
    sf = "/root/testdata/sf0.1"
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    got = op7.op7_toxicity(spark, sf).where("held_out").join(labels, "doc_id").toPandas()
    hit = (got.predicted == got.toxic).mean()
    assert hit > 0.97 and got[got.toxic == 0].predicted.mean() < 0.01 and got[got.toxic == 1].predicted.mean() > 0.85


def test_toxicity_of_awkward_rows(spark):
    frame = docs(spark, AWKWARD)
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    rows = op7.toxicity(spark, frame, none).collect()
    assert len(rows) == len(AWKWARD) and all(0 <= r.score <= 1 and r.predicted == 0 for r in rows)
    assert op7.without_toxic(frame, none).columns == frame.columns
    assert op7.toxicity(spark, docs(spark, []), none).count() == 0


def test_pseudonyms(spark):
    texts = [
        (1, "card 4111 1111 1111 1111, 4111111111111111; no card 4111111111111112"), (2, "a.b9@x.example.com +1 (017) 555-7713 10.0.200.3 123-45-6789 000-12-3456"), (3, None), (4, ""),
        (5, "2024-02-29 29.02.2023 28/02/2023 2024-02-30 1850-01-01"), (6, "DE89 3704 0044 0532 0130 00 GB82WEST12345698765432 DE00370400440532013000"), (7, 't = "b44e15e09fd311c3cf3163b66d5a9875b883d8ce"'),
        (8, "10.0.200.3 999.1.1.1 4111-1111-1111-1111"), (8, "10.0.200.3 999.1.1.1 4111-1111-1111-1111"), (9, "b" * 50_000 + "1" * 400),
    ]
    frame = docs(spark, texts)
    out = op8.pseudonymise(frame).drop("n_pseudonyms").cache()
    by = {r.doc_id: r.text for r in out.collect()}
    assert by[3] is None and by[4] == "" and by[9] == texts[-1][1]
    assert "4111111111111112" in by[1] and "000-12-3456" in by[2] and "2024-02-30 1850-01-01" in by[5] and "29.02.2023" in by[5] and by[6].endswith("DE00370400440532013000")
    spaced, plain = re.search(r"card (\d{4} \d{4} \d{4} \d{4}), (\d{16});", by[1]).groups()
    dashed = re.search(r"\d{4}-\d{4}-\d{4}-\d{4}", by[8])[0]
    assert spaced.replace(" ", "") == plain == dashed.replace("-", "") != "4111111111111111"
    assert re.search(r"[\d.]{7,}", by[2].split(")")[1].split(" ", 2)[2])[0] == by[8].split()[0]
    back = op8.pseudonymise(out, inverse=True).collect()
    assert Counter((r.doc_id, r.text) for r in back) == Counter(texts)
    assert op8.pseudonymise(out, key="another").where("doc_id = 1").first().text != by[1]


def test_card_pseudonyms_are_a_permutation(spark):
    cards = spark.range(100).select(F.format_string("%012d", F.col("id") * 7919).alias("p")).select(F.concat("p", F.lit("0")).alias("v"))
    valid = cards.select(F.concat(F.substr("v", F.lit(1), F.lit(12)), F.pmod(-op8.luhn_sum(F.col("v")), F.lit(10)).cast("string")).alias("v"))
    out = [r.x for r in valid.select(op8.pseudonym(F.col("v")).alias("x")).collect()]
    assert len(set(out)) == 100 and spark.createDataFrame([(x,) for x in out], "x string").where(op8.luhn_sum(F.col("x")) % 10 != 0).count() == 0


def brute_quality(t):
    t = t or ""
    w = WORD.findall(t)
    tri = list(zip(w, w[1:], w[2:], strict=False))
    n = Counter(tri)
    cov = {j for i, g in enumerate(tri) if n[g] > 1 for j in (i, i + 1, i + 2)}
    lines = [x for x in t.split("\n") if WORD.search(x)]
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), len(cov)


def test_quality_counts_equal_brute_force(spark):
    texts = AWKWARD + [(30, "# a\n# a\n\n*b* <c>"), (31, "a a a a"), (32, "  x  ")]
    labels = spark.createDataFrame([(1, 1, 0), (8, 1, None), (11, 0, 0), (None, 1, 1), (9, None, 1)], "doc_id long, quality int, toxic int")
    got = op9.quality(spark, docs(spark, texts), labels).collect()
    fields = lambda r: (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words)
    assert Counter((r.doc_id, *fields(r)) for r in got) == Counter((i, *brute_quality(t)) for i, t in texts)
    for r in got:
        assert r.base_failed == (r.n_words < 50 or 100 * r.n_repeat_words > 50 * r.n_words) and not (r.base_failed and r.kept)
    assert op9.quality(spark, docs(spark, []), labels).count() == 0


def test_repeated_words_survive_collisions(spark):
    texts = [(i, " ".join(np.random.default_rng(i).choice(list("abcdefgh"), 3 + 9 * i))) for i in range(8)] + [(8, "x y"), (9, "x y z"), (10, "x x x x")]
    for bits in (64, 4, 1):
        measure = op9._bound(op9._words(F.col("text")), lambda ws: op9.repeated_words(ws, op9._n_words(ws), bits))  # noqa: B023
        got = {r.doc_id: r.n for r in docs(spark, texts).select("doc_id", measure.alias("n")).collect()}
        assert got == {i: brute_quality(t)[-1] for i, t in texts}


def test_counts_of_a_very_long_text(spark):
    text = " ".join(f"w{i}" for i in range(400_000))
    got = op9.base_counts(docs(spark, [(1, text), (2, text + " " + text)])).where("not base_failed or n_words > 0").collect()
    assert {r.doc_id: (r.n_words, r.n_repeat_words) for r in got} == {1: (400_000, 0), 2: (800_000, 800_000)}


def test_quality_tells_good_from_bad(spark):
    """Figures on all labels; the fitted fold and the trusted rows are among them."""
    sf = "/root/testdata/sf0.1"
    got = op9.op9_quality(spark, sf).join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id").where("not base_failed").toPandas()
    assert got[got.quality == 1].kept.mean() > 0.97 and got[got.quality == 0].kept.mean() < 0.03


def test_base_counts_equal_sql(spark):
    import duckdb

    con = duckdb.connect()
    con.sql("create view documents as select * from '/root/testdata/sf0.01/documents.parquet'")
    columns = ["doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed"]
    got = op9.quality_base_counts(spark, "/root/testdata/sf0.01").select(*columns).collect()
    assert Counter(map(tuple, got)) == Counter(con.sql(f"select {', '.join(columns)} from ({op9.BASE_ORACLE})").fetchall())


def test_mixing_targets(spark):
    sizes = spark.createDataFrame([("a", 10), ("b", 1000), ("c", 500), ("d", 2000), (None, 0)], "source string, source_size long")
    got = {r.source: r.target for r in op10.source_targets(sizes).collect()}
    weight = dict(zip(["a", "b", "c", "d", None], [5, 2, 1, 5, 2], strict=True))
    cap = {"a": 20.0, "b": 2000.0, "c": 1000.0, "d": 4000.0, None: 0.0}
    left, free, target = 1.5 * 3510, set(cap), {}
    while free:
        share = {s: left * weight[s] / sum(weight[x] for x in free) for s in free}
        over = {s for s in free if share[s] > cap[s]}
        for s in over or free:
            target[s] = cap[s] if over else share[s]
        left -= sum(cap[s] for s in over)
        free = free - over if over else set()
    assert {s: pytest.approx(v) for s, v in target.items()} == got


def test_mixing_of_awkward_rows(spark):
    frame = docs(spark, AWKWARD, {1: None, 8: "b", 9: "c"})
    mixed = op10.mix(spark, frame)
    a = Counter((r.doc_id, r.mix_copies) for r in mixed.collect())
    assert a == Counter((r.doc_id, r.mix_copies) for r in op10.mix(spark, frame).collect()) and sum(a.values()) == len(AWKWARD)
    assert op10.emit(mixed).count() == sum(c * n for (_, c), n in a.items())
    assert op10.mix(spark, docs(spark, [])).count() == 0
