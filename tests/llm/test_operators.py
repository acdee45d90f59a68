"""Text operators against brute force, and their edge cases: nulls in any column, empty
and repeated rows, empty tables, extra columns with clashing names."""

import random
import re

import duckdb
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from peakgroups.functions.storage import shared_path
from peakgroups.llm import decontaminate, language, licenses, linededup, mixing, quality, simhash, tokens, urls, warc

SF = "/root/testdata/sf0.001"
DOCS = "doc_id long, text string, lang string, source string, n_chars long, words string, key long"


def lower(t):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t)


@pytest.fixture(scope="module")
def odd(spark):
    long = " ".join(f"w{i}" for i in range(3000))
    texts = [None, "", " \n\t", "one", long, long, "Licensed under the MIT License.\nmit license", "A b c d e f g\nA b c d e f g", "ünïcödé Straße ẞ"]
    rows = [(i, t, "en" if i % 2 else None, None if i == 3 else "s", None, "clash", 7) for i, t in enumerate(texts)]
    return spark.createDataFrame([*rows, rows[7], (None, "no id at all", None, None, None, None, None)], DOCS)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], DOCS)


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SF}/documents.parquet")


@pytest.fixture(scope="module")
def texts():
    return dict(duckdb.sql(f"select doc_id, text from '{SF}/documents.parquet'").fetchall())


def test_every_row_comes_back(spark, odd, none):
    items = spark.createDataFrame([(1, "one"), (2, None), (None, "b c")], "item_id long, text string")
    for make in (
        lambda d: decontaminate.contamination(decontaminate.find_hits(d, items)),
        lambda d: decontaminate.decontaminate(d, items),
        quality.judge,
        licenses.scan,
        linededup.dedup_lines,
        simhash.near_duplicates,
        lambda d: language.predict(d, language.learn(d), ["doc_id"]),
    ):
        assert len(make(odd).collect()) == odd.count()
        assert make(none).collect() == []
    assert mixing.mix(none, max_repeats=2.0).count() == 0
    assert decontaminate.decontaminate(odd, items).columns == odd.columns == quality.keep_good(odd).columns


def test_decontamination_cuts_hits(spark):
    items = spark.createDataFrame([(1, "a b c d e f g h i j k"), (2, "short one")], "item_id long, text string")
    d = spark.createDataFrame([(1, "X: a b, c d e f g h i J tail."), (3, "a short, one! a Short one"), (4, "a b c")], "doc_id long, text string")
    hits = {r.doc_id: (r.n_words, r.n_hit, r.n_items) for r in decontaminate.contamination(decontaminate.find_hits(d, items)).collect()}
    assert hits == {1: (12, 10, 1), 3: (6, 4, 1), 4: (3, 0, 0)}
    assert {r.doc_id: r.text for r in decontaminate.decontaminate(d, items).collect()} == {1: "X tail.", 3: "a! a", 4: "a b c"}
    assert [r.doc_id for r in decontaminate.decontaminate(d, items, action="documents").collect()] == [4]


def test_simhash_against_brute_force(spark, texts):
    xxhash = pytest.importorskip("xxhash")
    fps = {}
    for i, t in texts.items():
        w = re.findall(r"[^\x20\x09-\x0D]+", lower(t or ""))
        sh = [" ".join(w[k : k + 3]) for k in range(len(w) - 2)] if len(w) >= 3 else [" ".join(w)] * bool(w)
        h = [xxhash.xxh64_intdigest(s.encode(), seed=42) for s in sh]
        fps[i] = sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))
    top = {i: i for i in fps}

    def find(a):
        while top[a] != a:
            a = top[a]
        return a

    ids = sorted(fps)
    for a in ids:
        for b in ids:
            if b < a and (fps[a] ^ fps[b]).bit_count() <= 2:
                x, y = find(a), find(b)
                top[max(x, y)] = min(x, y)
    got = simhash.op2_simhash(spark, SF).collect()
    assert {r.doc_id: (r.fingerprint, r.component_id) for r in got} == {i: (f"{fps[i]:016x}", find(i)) for i in ids}


def test_masks_cover_every_pair_of_bits():
    masks = [m % 2**64 for m in simhash.covering_masks()]
    assert len(masks) == 7
    assert all(any(not m >> i & 1 and not m >> j & 1 for m in masks) for i in range(64) for j in range(i + 1))


def test_links_of_near_fingerprints(spark):
    rng = random.Random(5)
    base = [rng.getrandbits(64) for _ in range(20)]
    near = {b ^ (1 << rng.randrange(64)) ^ (1 << rng.randrange(64)) for b in base for _ in range(5)} | set(base)
    signed = lambda x: x - (1 << 64) if x >> 63 else x
    found = simhash.links(spark.createDataFrame([(signed(x),) for x in near], "fp long")).collect()
    assert all(((r.a ^ r.b) % 2**64).bit_count() <= 2 for r in found)
    groups = {x: x for x in map(signed, near)}

    def find(a):
        while groups[a] != a:
            a = groups[a]
        return a

    for r in found:
        groups[find(r.a)] = find(r.b)
    for a in near:
        for b in near:
            if (a ^ b).bit_count() <= 2:
                assert find(signed(a)) == find(signed(b))


def test_license_places(spark, docs, texts):
    for r in licenses.scan(docs).collect():
        w = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", lower(texts[r.doc_id] or ""))
        hits = [(i, label) for p, label in licenses.PHRASES.items() for i in range(len(w)) if w[i : i + len(p.split())] == p.split()]
        at = [i for i, _ in hits]
        assert (r.n_words, r.n_base, r.first_word, r.last_word) == (len(w), len(hits), min(at, default=None), max(at, default=None))
        assert r.base_labels == ",".join(sorted({x for _, x in hits})) and set(r.base_labels.split(",")) - {""} <= set(r.labels.split(","))


def test_license_suppression(spark):
    d = spark.createDataFrame([(1, "Licensed under the GNU Lesser General Public License v3. SPDX-License-Identifier: MIT")], "doc_id long, text string")
    r = licenses.scan(d).first()
    assert (r.labels, r.score) == ("lgpl,mit", 1.0) and [x["label"] for x in r.detections] == ["lgpl", "mit"]
    assert len(licenses.signatures()) >= 200


def test_cascade_asks_lazily_and_keeps_the_same(spark, docs, odd, none):
    """Both cascades agree; a rule behind one that rejects a text is not asked about it."""
    for d in (docs, odd, none):
        want = sorted(str(r.doc_id) for r in quality.judge(d).where("kept").collect())
        assert sorted(str(r.doc_id) for r in quality.keep_good(d).collect()) == want
    few = quality.QualityRule("few", "n_words < 5")
    trap = quality.QualityRule("trap", "if(n_words < 5, cast(raise_error('asked') as boolean), n_words < 0)")
    short = spark.createDataFrame([(1, "a b")], "doc_id long, text string")
    verdict = quality.F.when(quality.F.expr(quality.on_demand(few.bad)), False).when(quality.F.expr(quality.on_demand(trap.bad)), False)
    assert quality._worded(short, "doc_id", "text").select(verdict.alias("kept")).first().kept is False
    with pytest.raises(Exception, match="asked"):
        quality._worded(short, "doc_id", "text").select(quality.F.expr(quality.on_demand(trap.bad)).alias("x")).collect()


def test_rules_are_ordered_by_rejections_per_second(docs):
    rules = [quality.QualityRule("never", "n_words < 0"), quality.QualityRule("always", "n_words >= 0"), quality.QualityRule("dear", "n_repeat_words >= 0")]
    found = quality.ordered_rules(docs, lambda d: quality._worded(d, "doc_id", "text"), quality.on_demand, rules)
    assert [x[0].name for x in found] == ["always", "dear", "never"] and [x[2] for x in found] == [1.0, 1.0, 0.0]


@pytest.fixture(scope="module")
def machine():
    paths = pytest.importorskip("public_tokenizers")
    lib = pytest.importorskip("tokenizers").Tokenizer.from_file(paths.path("byte_bpe_50k.json"))
    with open(paths.path("byte_bpe_50k.json"), "rb") as f:
        return tokens.Transducer(f.read()), lambda xs: [len(e.ids) for e in lib.encode_batch(xs, add_special_tokens=False)]


def test_token_counts_equal_the_library(machine, texts):
    mine, library = machine
    xs = [t or "" for t in texts.values()] + ["<|endoftext|>", "a<|endoftext|> b", "don't  \n\n we'll  ", "", "a" * 4000, "'s's ''s 's"]
    assert mine.count(xs) == library(xs)


@settings(max_examples=150, deadline=None)
@given(st.text("abst'relvmd \n\t é漢1２.,!\u3000\x85", max_size=60), st.integers(1, 9))
def test_chunks_compose(machine, text, size):
    mine, library = machine
    assert mine.count([text], size) == mine.count([text]) == library([text])


@settings(max_examples=60, deadline=None)
@given(st.text("abst'rel \n é漢1", min_size=1, max_size=40), st.integers(1, 4), st.randoms())
def test_maps_compose_in_any_order(machine, text, size, random):
    mine, library = machine
    ends = tokens.np.array([len(text)])
    (maps,) = mine.chunks(text + "\n", tokens.all_starts(text + "\n", ends), ends, size)
    while len(maps) > 1:
        i = random.randrange(len(maps) - 1)
        maps[i : i + 2] = [mine.compose(text, *maps[i : i + 2])]
    assert [maps[0].count] == library([text])


def test_runs_without_a_pre_token_start(machine):
    mine, library = machine
    xs = ["a" * 100_000, "-" * 5000 + "ab" * 9000, "=" * 70_000 + " x", "漢字" * 5000, " " * 9000]
    assert mine.count(xs) == library(xs)


def test_counts_come_from_the_transitions(machine):
    """A wrong annotation and a composition that counts nothing must both show."""
    with open(__import__("public_tokenizers").path("byte_bpe_50k.json"), "rb") as f:
        mine = tokens.Transducer(f.read())
    text = "to be or not to be " * 2000
    right = mine.count([text])[0]
    state, made = mine.root.steps[ord("t")]
    mine.root.steps[ord("t")] = state, made + 1
    mine.emitted.clear()
    assert mine.count([text])[0] > right
    mine._anew()
    mine.compose = lambda text, a, b: a
    assert mine.count([text])[0] < right


def test_token_counts_of_odd_rows(spark, odd, none, machine):
    path = __import__("public_tokenizers").path("byte_bpe_50k.json")
    got = sorted((r.doc_id is None, r.doc_id or 0, r.n_bytes, r.n_tokens, r.over_limit) for r in tokens.count_tokens(odd, path).collect())
    rows = [(r.doc_id, r.text or "") for r in odd.collect()]
    want = machine[1]([t for _, t in rows])
    assert got == sorted((i is None, i or 0, len(t.encode()), n, n > 1024) for (i, t), n in zip(rows, want))
    assert tokens.count_tokens(none, path).collect() == []


def test_language_held_out(spark):
    got = language.op8_language_id(spark, "/root/testdata/sf0.01").where("held_out").select("doc_id", "lang_pred").collect()
    truth = dict(duckdb.sql("select doc_id, lang from '/root/testdata/sf0.01/documents.parquet'").fetchall())
    assert sum(truth[r.doc_id] == r.lang_pred for r in got) >= 0.97 * len(got)


def test_language_without_letters(spark):
    d = spark.createDataFrame([(1, None), (2, "123 !"), (3, "")], "doc_id long, text string")
    train = spark.createDataFrame([("the cat", "en"), ("der hund", "de")], "text string, lang string")
    assert {(r.lang_pred, r.score) for r in language.predict(d, language.learn(train), ["doc_id"]).collect()} == {("und", 0.0)}


def test_archives_reject_quoted_records(spark):
    fake = "WARC/1.1\r\nWARC-Type: response\r\nWARC-Record-ID: <urn:page:777>\r\nContent-Length: 5\r\n\r\nhello\r\n\r\n"
    rows = [(1, "http://a/b", fake * 3 + "t"), (2, None, None), (3, "u\r\nX: y", ""), (5, "y", fake * 2), (6, "z", fake * 3 + "t"), (None, "n", "alone")]
    path = shared_path(spark, "t")
    warc.write_archives(warc.deduplicated(spark.createDataFrame(rows, "page_id long, url string, html string").coalesce(1)), path)
    got = {r.page_id: (r.record_type, r.refers_to, r.payload and bytes(r.payload).decode()) for r in warc.read_archives(spark, path, block=256, payloads=True).collect()}
    assert got == {1: ("revisit", 6, None), 2: ("revisit", 3, None), 3: ("response", None, b"".decode() or b""), 5: ("response", None, fake * 2), 6: ("response", None, fake * 3 + "t"), None: ("response", None, "alone")}


def test_cascade_is_exact(spark):
    every = spark.range(3000).selectExpr("concat('k', id) as key")
    listed = every.where("xxhash64(key) % 7 = 0")
    c = urls.build_cascade(listed, every)
    assert every.where(c.contains(every.key)).exceptAll(listed).count() == 0 and every.where(c.contains(every.key)).count() == listed.count()
    assert urls.build_cascade(listed.where("false"), every).levels == ()


def test_url_edges(spark):
    rows = [(1, None), (2, "no scheme"), (3, "http://Sub.EXAMPLE.org/es/x?q"), (4, "x://example.org"), (5, "x://notorg/a"), (6, "x://a.com/de/#f")]
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in urls.judge_urls(spark.createDataFrame(rows, "page_id long, url string"), urls.RULES).collect()}
    assert got[1] == got[2] == ("", "", None, "allow")
    assert got[3] == ("sub.example.org", "/es/x", "example.org/es/", "block") and got[4] == ("example.org", "", None, "allow")
    assert got[5][2] is None and got[6] == ("a.com", "/de/", "com/de/", "block")


def test_mixing_limits(spark):
    rows = [(i, "w " * 10, "big" if i < 80 else "small") for i in range(100)]
    d = spark.createDataFrame(rows, "doc_id long, text string, source string")
    counts = {(r.source): r["count"] for r in mixing.mix(d, max_repeats=2.0).groupBy("source").count().collect()}
    assert abs(counts["small"] - 40) <= 1 and abs(counts["big"] - 60) <= 1
    kept = {(r.source): r["count"] for r in mixing.mix(d, target_entropy=0.0).groupBy("source").count().collect()}
    assert kept == {"big": 80, "small": 20}
    assert mixing.mix(d, budget=3000, max_repeats=3.0).groupBy("doc_id", "mix_epoch").count().where("count > 1").count() == 0


def test_short_lines_are_compared(spark):
    rows = [(1, "Menu\n\na b c d\nx y z\na a b b"), (2, "menu\n\nd c b a e\nx y w\nb a"), (3, "e f g h i\nMENU menu\nx y z q"), (4, "h g f e\nx  z y")]
    d = spark.createDataFrame(rows, "doc_id long, text string")
    # Four of five words are as similar as asked, three of four are not; blank lines stay.
    assert {r.doc_id: r.text for r in linededup.dedup_lines(d).collect()} == {1: rows[0][1], 2: "\nx y w", 3: "e f g h i\nx y z q", 4: ""}


def test_leaders_change_nothing(spark, monkeypatch):
    """With every word taken for frequent, leaders settle what they can, and both ways to
    use what they found give the rows of the SQL."""
    con = duckdb.connect()
    con.execute(f"create view documents as select * from '{SF}/documents.parquet'")
    names = ["doc_id", "n_lines", "n_eligible", "n_removed", "kept_lines"]
    want = con.execute(f"select {', '.join(names)} from ({linededup.OP3_SQL})").fetchall()
    for limit in (0, 10**6):
        monkeypatch.setattr(linededup, "HOT", 0)
        monkeypatch.setattr(linededup, "LIGHT", -1)
        monkeypatch.setattr(linededup, "BROADCAST_SETS", limit)
        got = [tuple(r) for r in linededup.op3_line_dedup(spark, SF).select(*names).collect()]
        assert sorted(got) == sorted(want)


def test_second_look_moves_the_lines_that_it_needs(spark, monkeypatch):
    """Of a text with one line to compare only that line moves, once, and none of an equal text."""
    fill = [" ".join(f"f{i}x{j}x{k}" for k in range(9)) for i in range(2) for j in range(30)]
    rows = [(1, "\n".join(["a b c d e", *fill[:30]])), (2, "\n".join([*fill[30:], "e d c b a f"])), (3, "\n".join(["a b c d e", *fill[:30]]))]
    moved, write = [], linededup.materialize

    def counted(df, name):
        if name == "codes":
            plan = df._jdf.queryExecution().optimizedPlan().toString()
            moved.append((plan.count("Join "), plan.count("collect_list"), df.count()))
        return write(df, name)

    monkeypatch.setattr(linededup, "materialize", counted)
    got = {r.doc_id: r.text for r in linededup.dedup_lines(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {1: rows[0][1], 2: "\n".join(fill[30:]), 3: ""}
    assert moved == [(1, 0, 2)]


def test_pairs_of_sets_that_are_both_gone_are_not_looked_at(spark):
    """Whatever the numbers and sizes of the sets, the first one's and equal ones included."""
    rows = [(i, n, 0, None, [1, 2], i in (0, 3)) for i, n in enumerate([6, 5, 5, 5, 9])]
    sets = spark.createDataFrame(rows, "set long, n int, bits long, more long, prefix array<long>, gone boolean")
    assert sorted(tuple(r) for r in linededup._pairs(sets).collect()) == [(0, 1), (0, 2), (1, 2), (1, 3), (2, 3)]


def test_lines_that_differ_in_a_few_words(spark):
    """Sets around the limit of similarity, of all sizes, against brute force."""
    rng = random.Random(9)
    rows = []
    for i in range(120):
        base = rng.sample([f"w{k}" for k in range(400)], rng.choice([3, 4, 5, 6, 9, 20, 45, 90, 130]))
        for _ in range(3):
            line = [w for w in base if rng.random() > 0.1] + rng.sample(["x%d" % k for k in range(50)], rng.randrange(0, 1 + len(base) // 8))
            rng.shuffle(line)
            rows.append(" ".join(line))
    rng.shuffle(rows)
    d = spark.createDataFrame([(i, t) for i, t in enumerate(rows)], "doc_id long, text string")
    sets = [frozenset(t.split()) for t in rows]
    want = {i for i, s in enumerate(sets) if s and any(9 * len(s & o) >= 4 * (len(s) + len(o)) for o in sets[:i] if o)}
    got = {r.doc_id for r in linededup.kept_lines(d).where("size(kept) < n_eligible").collect()}
    assert got == want and len(want) > 50


def test_repeated_rows_and_other_white_space(spark):
    d = spark.createDataFrame([(1, "a\tb  c d"), (1, "a\tb  c d"), (1, "other text"), (2, "D C\x0bB\x0cA\r"), (None, "a b c d e"), (3, None)], "doc_id long, text string")
    got = sorted((r.doc_id or 0, r.text or "") for r in linededup.dedup_lines(d).collect())
    # The null id comes first, and its five words are as similar as asked to the four.
    assert got == [(0, "a b c d e"), (1, ""), (1, ""), (1, "other text"), (2, ""), (3, "")]


def test_long_texts_lose_no_run(monkeypatch):
    text = "".join(random.Random(4).choice("abc XÉß.  ") for _ in range(9000))
    whole = language.np.unique(language.run_codes(text), return_counts=True)
    monkeypatch.setattr(language, "CHUNK", 37)
    assert all((a == b).all() for a, b in zip(language.run_counts(text), whole))


SQL = {
    "op1": (decontaminate.op1_decontaminate, decontaminate.OP1_SQL),
    "op3": (linededup.op3_line_dedup, linededup.OP3_SQL),
    "op5": (warc.op5_warc, warc.OP5_SQL),
    "op6": (quality.op6_quality_rules, quality.OP6_SQL),
    "op9": (urls.op9_url_filter, urls.OP9_SQL),
    "op10": (mixing.op10_mix_sources, mixing.OP10_SQL),
}


@pytest.mark.parametrize("name", SQL)
def test_same_as_sql(spark, name):
    run, sql = SQL[name]
    con = duckdb.connect()
    for t in ("documents", "benchmark", "pages"):
        con.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    found = con.execute(sql)
    names = sorted(x[0] for x in found.description)
    order = [x[0] for x in found.description]
    want = sorted(tuple(row[order.index(n)] for n in names) for row in found.fetchall())
    got = sorted(tuple(r[n] for n in names) for r in run(spark, SF).select(*names).collect())
    assert sorted(map(repr, got)) == sorted(map(repr, want))
