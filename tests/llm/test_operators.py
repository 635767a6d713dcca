"""The dealt operators against brute force, exact round trips and held-out accuracy, with the awkward rows of every kind."""

import collections
import hashlib
import re
import zlib

import numpy as np
import pytest
from labelsketch.llm import common, decontaminate, html_text, lang_id, near_dedup, packing, pii, quality, queries, sharding, token_count, toxicity
from pyspark.sql import functions as F

PROSE = "The old house stood by the river and nobody knew who had lived in it before the war came to the valley. "
LONG = " ".join(f"word{i % 977} and{i % 31}" for i in range(20000))
ROWS = [
    (1, None, "en"), (2, "", "en"), (3, " \t\n\x0b", None), (4, PROSE * 3, "en"), (5, PROSE * 3, "en"), (5, PROSE * 3, "en"), (6, LONG, "en"), (None, PROSE, None), (7, "one", "fr"), (8, "ONE", "fr"),
    (9, "x@y.example and +1 (222) 333-4444 and 10.0.0.1 and 4111 1111 1111 1111", "en"), (10, "a b c a b c a b c\na b c\na b c", "de"), (11, "é ß 中文 \U0001f600 <|endoftext|> </s>", None), (12, "é ß 中文 \U0001f600 <|endoftext|> </s>", None),
]
#: Extra columns whose names clash with those the operators use.
CLASHING = ["kept", "score", "n_words", "set", "bucket", "component", "m", "v", "host", "shard"]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(*r, "s", 1, *range(len(CLASHING))) for r in ROWS]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, " + ", ".join(f"{c} int" for c in CLASHING))


@pytest.fixture(scope="module")
def nothing(docs):
    return docs.limit(0)


def rows_of(df):
    return df.collect()


def words_of(text):
    return re.findall(r"[^\x20\x09-\x0D]+", text or "")


# quality


def measured(text):
    w, lines = words_of(text), [x for x in (text or "").split("\n") if words_of(x)]
    at = collections.defaultdict(list)
    for i in range(len(w) - 2):
        at[tuple(w[i : i + 3])].append(i)
    covered = {j for v in at.values() if len(v) > 1 for i in v for j in (i, i + 1, i + 2)}
    return len(w), sum(map(len, w)), sum((text or "").count(c) for c in "#*$%&|<>"), len(lines) - len(set(lines)), len(covered)


def test_quality_measures(docs, nothing):
    found = rows_of(quality.quality(docs))
    want = collections.Counter((i, *measured(t)) for i, t, _ in ROWS)
    assert collections.Counter((r.doc_id, r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) for r in found) == want
    for r in found:
        assert r.base_failed == (r.n_words < 50 or 100 * r.n_repeat_words > 50 * r.n_words)
        assert not (r.base_failed and r.kept)
    assert rows_of(quality.quality(nothing)) == []
    assert quality.kept_rows(docs).columns == docs.columns


def test_quality_plan_is_native(docs):
    plan = quality.votes(quality.measures(docs, ["doc_id"]))._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Pandas|Arrow", plan)


def test_quality_against_labels(spark, sf):
    found = {r.doc_id: r for r in rows_of(queries.op3_quality(spark, "/root/testdata/sf0.01"))}
    labels = [r for r in rows_of(spark.read.parquet("/root/testdata/sf0.01/labels.parquet")) if not found[r.doc_id].base_failed]
    assert sum(found[r.doc_id].kept for r in labels if r.quality) > 0.97 * sum(r.quality for r in labels)
    bad = [r for r in labels if not r.quality]
    assert sum(not found[r.doc_id].kept for r in bad) > 0.9 * len(bad)


def test_label_model_weighs_rules():
    n = len(quality.RULES)
    code = lambda votes: sum(v * 3 ** (n - 1 - i) for i, v in enumerate(votes))
    assert quality.unpack(code([0, 1, *[2] * (n - 2)])) == [0, 1, *[2] * (n - 2)]
    share, table = quality.fit({code([2] * n): 900, code([0, *[2] * (n - 1)]): 100})
    assert quality.posterior([2] * n, share, table) > 0.9 and quality.posterior([0, *[2] * (n - 1)], share, table) < 0.5


def votes_of(rng, n, kinds, noise):
    """Counts and truth of vote patterns: kinds of bad texts (rules, share), and rules that err at random (rule: rate)."""
    counts, truth = collections.Counter(), collections.defaultdict(collections.Counter)
    for _ in range(n):
        p, x, bad = [2] * len(quality.RULES), rng.random(), False
        for rules, share in kinds:
            if 0 <= x < share:
                bad = True
                for r in rules:
                    p[r] = 0
            x -= share
        for r, rate in noise.items():
            if rng.random() < rate:
                p[r] = 0
        code = sum(v * 3 ** (len(p) - 1 - i) for i, v in enumerate(p))
        counts[code] += 1
        truth[code][bad] += 1
    return counts, truth


@pytest.mark.parametrize(
    ("kinds", "noise"),
    [([((0,), 0.02), ((1, 3), 0.02), ((2,), 0.01)], {6: rate}) for rate in (0.02, 0.05, 0.15, 0.3)]  # a rule that is often wrong
    + [([((0, 1), 0.3), ((2,), 0.02), ((4, 5), 0.01)], {}), ([((0,), 0.3), ((2,), 0.02), ((4,), 0.01)], {}), ([((0,), 0.02), ((1,), 0.02), ((2,), 0.01)], {})],  # a frequent kind of bad text
)
def test_label_model_finds_noise_and_frequent_junk(kinds, noise):
    counts, truth = votes_of(np.random.default_rng(1), 20000, kinds, noise)
    for scale in (1, 1000):  # the verdicts don't depend on the size of the corpus
        share, table = quality.fit({c: n * scale for c, n in counts.items()})
        kept = {c for c in counts if quality.posterior(quality.unpack(c), share, table) >= 0.5}
        assert sum(truth[c][False] for c in counts if c not in kept) == 0 and sum(truth[c][True] for c in kept) == 0


MEASURES = r"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS t, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
grams AS (SELECT r, i, array_to_string(w[i : i + 2], ' ') AS g FROM (SELECT r, w, unnest(range(1, len(w) - 1)) AS i FROM d WHERE len(w) > 2)),
twice AS (SELECT r, i FROM (SELECT r, i, count(*) OVER (PARTITION BY r, g) AS n FROM grams) WHERE n > 1),
covered AS (SELECT r, count(DISTINCT p) AS n FROM (SELECT r, unnest(range(i, i + 3)) AS p FROM twice) GROUP BY 1),
lines AS (SELECT r, x FROM (SELECT r, unnest(string_split(t, chr(10))) AS x FROM d) WHERE regexp_matches(x, '[^\x20\x09-\x0D]')),
dup AS (SELECT r, count(*) - count(DISTINCT x) AS n FROM lines GROUP BY 1)
SELECT doc_id, len(w) AS n_words, length(array_to_string(w, '')) AS word_chars, length(regexp_replace(t, '[^#*$%&|<>]', '', 'g')) AS n_symbols, coalesce(dup.n, 0) AS n_dup_lines, coalesce(covered.n, 0) AS n_repeat_words,
len(w) < 50 OR 100 * coalesce(covered.n, 0) > 50 * len(w) AS base_failed FROM d LEFT JOIN dup USING (r) LEFT JOIN covered USING (r)
"""


def test_quality_measures_equal_sql(spark, duck, sf):
    want = duck.execute(MEASURES)
    columns = [c[0] for c in want.description]
    assert sorted(tuple(r) for r in rows_of(queries.op3_quality(spark, sf).select(*columns))) == sorted(want.fetchall())


# near duplicates


def components(texts, size, percent):
    """Brute force over rows [(doc_id, text)]: row -> (set size, component)."""
    sets = []
    for _, t in texts:
        w = words_of((t or "").translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")))
        sets.append(frozenset(zip(*(w[i:] for i in range(size)), strict=False)) if len(w) >= size else frozenset([tuple(w)] if w else []))
    group = list(range(len(texts)))
    for a in range(len(texts)):
        for b in range(a):
            both = len(sets[a] & sets[b])
            if None in (texts[a][0], texts[b][0]) and sets[a] != sets[b]:
                continue  # a row without an id joins its exact copies alone
            if both and 100 * both >= percent * (len(sets[a]) + len(sets[b]) - both):
                old, new = group[a], group[b]
                group = [new if g == old else g for g in group]
    least = {g: min((texts[i][0] for i in range(len(texts)) if group[i] == g and texts[i][0] is not None), default=None) for g in group}
    return [(texts[i][0], len(sets[i]), least[group[i]]) for i in range(len(texts))]


def test_near_duplicates_edges(docs, nothing):
    found = collections.Counter((r.doc_id, r.n_shingles, r.component_id) for r in rows_of(near_dedup.duplicates(docs, 2, 80)))
    assert found == collections.Counter(components([(i, t) for i, t, _ in ROWS], 2, 80))
    assert rows_of(near_dedup.duplicates(nothing)) == []


def test_near_duplicates_on_table(spark, sf):
    texts = [(r.doc_id, r.text) for r in rows_of(spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text"))]
    found = collections.Counter((r.doc_id, r.n_shingles, r.component_id) for r in rows_of(queries.op7_near_duplicates(spark, sf)))
    assert found == collections.Counter(components(texts, 2, 80))


def test_near_duplicates_take_any_ids(spark):
    rows = [("b", PROSE), ("a", PROSE.upper()), ("c", "quite another text of some length"), ("c", PROSE)]
    found = sorted((r.doc_id, r.component_id, r.kept) for r in rows_of(near_dedup.duplicates(spark.createDataFrame(rows, "doc_id string, text string"), 2, 80)))
    assert found == [("a", "a", True), ("b", "a", False), ("c", "a", False), ("c", "c", True)]


def test_label_sample_bounds_any_count(spark):
    counts = spark.createDataFrame([(10,), (10**10,), (10**15,)], "n long")
    for n, bound in rows_of(counts.select("n", common.hash_bound(F.col("n"), 250))):
        assert bound == 2**63 - 1 if n <= 250 else abs((bound + 2**63) / 2**64 * n - 250) < 1
    rows = spark.range(20000).select(F.col("id").alias("doc_id"), (F.col("id") % 400).cast("string").alias("lang"))
    sample = common.label_sample(rows, "lang", 10, "x")
    assert sample.select("lang").distinct().count() == 400 and 3000 < sample.count() < 5000


@pytest.mark.parametrize("stars", [2, 0])
def test_near_duplicates_borderline_groups(spark, stars, monkeypatch):
    monkeypatch.setattr(near_dedup, "BLOCK_ROWS", 8)
    rng = np.random.default_rng(5)
    rows = []
    for _ in range(3):
        base = rng.integers(0, 4000, 120)
        for _ in range(25):
            text = base.copy()
            text[rng.integers(0, 120, rng.integers(2, 11))] = rng.integers(0, 4000)
            rows.append((len(rows), " ".join(f"w{x}" for x in text)))
    found = {r.doc_id: r.component_id for r in rows_of(near_dedup.duplicates(spark.createDataFrame(rows, "doc_id long, text string"), 2, 80, stars=stars))}
    assert found == {i: c for i, _, c in components(rows, 2, 80)}


def test_near_duplicates_keep_one(docs):
    left = near_dedup.kept_rows(docs, 2, 80)
    assert left.columns == docs.columns
    ids = collections.Counter(r.doc_id for r in rows_of(left))
    assert ids[4] == 1 and ids[5] == 0 and ids[7] == 1 and ids[8] == 0


def test_densified_bins_agree_on_equal_sets_and_estimate_similarity():
    order = near_dedup.borrow_order(300)
    rng = np.random.default_rng(1)
    a = rng.integers(0, 1 << 63, 1000, dtype=np.uint64)
    b = np.r_[a[:900], rng.integers(0, 1 << 63, 100, dtype=np.uint64)]
    s = near_dedup.signatures(np.r_[a, a[::-1], b, a[:3]], np.array([1000, 1000, 1000, 3]), order)
    assert (s[0] == s[1]).all() and abs((s[0] == s[2]).mean() - 900 / 1100) < 0.08 and (s[3] != near_dedup.NONE).all()


# decontamination


def leaked(text, items, size=10):
    split = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (t or "").translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")))
    w, hit, found = split(text), set(), set()
    for item_id, item in items:
        x = split(item)
        for win in [x] if len(x) < size else [x[i : i + size] for i in range(len(x) - size + 1)]:
            for i in range(len(w) - len(win) + 1):
                if win and w[i : i + len(win)] == win:
                    hit |= set(range(i, i + len(win)))
                    found.add(str(item_id))
    return len(w), len(hit), len(found), hashlib.sha256(",".join(sorted(found)).encode()).hexdigest()


def test_decontamination(spark, docs, nothing, monkeypatch):
    items = [(1, PROSE), (2, "ONE"), (3, None), (4, ""), (10, "b c a"), (5, PROSE), (6, "nobody knew who had lived in it before the war came to"), (7, "é ß 中文")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    small = docs.filter("doc_id is null or doc_id <> 6")
    for most in (decontaminate.BROADCAST_ROWS, 1):  # sides that are broadcast, and sides that are shuffled
        monkeypatch.setattr(decontaminate, "BROADCAST_ROWS", most)
        found = collections.Counter((r.doc_id, r.n_words, r.n_hit, r.n_items, r.items_sha256) for r in rows_of(decontaminate.contamination(small, bench, ["doc_id"])))
        assert found == collections.Counter((i, *leaked(t, items)) for i, t, _ in ROWS if i != 6)
    assert rows_of(decontaminate.contamination(nothing, bench, ["doc_id"])) == []
    for none in (bench.limit(0), bench.filter("item_id in (3, 4)")):
        found = rows_of(decontaminate.contamination(docs, none, ["doc_id"]))
        assert not any(r.contaminated for r in found)
        assert collections.Counter((r.doc_id, r.n_words) for r in found) == collections.Counter((i, len(leaked_words(t))) for i, t, _ in ROWS)


def leaked_words(text):
    return [w for w in re.split("[^a-z0-9\\x80-\U0010ffff]+", (text or "").translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"))) if w]


def test_decontamination_equals_sql(spark, duck, sf):
    found = queries.op4_decontamination(spark, sf)
    want = duck.execute(queries.oracle_sql()["op4_decontamination"])
    assert found.columns == [c[0] for c in want.description]
    assert sorted(map(tuple, rows_of(found))) == sorted(want.fetchall())


def test_kept_rows_judges_rows_not_ids(spark):
    one, other, third = PROSE, "Quite another text about ships and harbours and the men who sail them over the seas.", "A third one that tells of bread and salt and of the long way to the mill in winter."
    rows = [(5, other), (5, one.upper()), (3, one), (None, third), (None, third.upper() + " "), (None, other + "  "), (7, None), (None, None), (9, "short"), (9, "short")]
    kept = rows_of(near_dedup.kept_rows(spark.createDataFrame(rows, "doc_id long, text string")))
    assert [r for r in kept if r.text in (one, one.upper())] == [(3, one)]
    assert [r for r in kept if r.text in (other, other + "  ")] == [(5, other)]
    assert sum(r.text in (third, third.upper() + " ") for r in kept) == 1
    assert sorted(map(str, (tuple(r) for r in kept if r.text in (None, "short")))) == ["(7, None)", "(9, 'short')", "(None, None)"] and len(kept) == 6


# personal data

EMAIL, IP, CARD, PHONE = (re.compile(p) for p in (r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", r"[0-9]([\x20-]?[0-9])+", r"\+[0-9][\x20().0-9-]+[0-9]"))


def plain_spans(text):
    digits = lambda s: re.sub("[^0-9]", "", s)
    return {
        "email": [m.span() for m in EMAIL.finditer(text)],
        "ip": [m.span() for m in IP.finditer(text) if all(int(p) <= 255 for p in m[0].split("."))],
        "card": [m.span() for m in CARD.finditer(text) if 16 <= len(digits(m[0])) <= 19 and pii.luhn(digits(m[0]))],
        "phone": [m.span() for m in PHONE.finditer(text) if 8 <= len(digits(m[0])) <= 15],
    }


def test_base_spans_equal_plain_patterns():
    rng = np.random.default_rng(3)
    parts = ["a", "b.", "@", "@c.d", "1", "23", ".", "+", "+1 ", "-", " ", "(", "_", "%", "x@y.z", "4111111111111111", "256", "٣", "é"]
    for _ in range(4000):
        text = "".join(rng.choice(parts, rng.integers(1, 25)))
        assert pii.detect(text) == plain_spans(text), text


@pytest.mark.parametrize(
    ("text", "kind", "hidden"),
    [
        ("mail john.doe [at] example [dot] com now", "email", "john.doe [at] example [dot] com"),
        ("mail john at example dot com now", "email", "john at example dot com"),
        ("ｊohn＠exаmple.com x", "email", "ｊohn＠exаmple.com"),
        ("call plus one two one two five five five one two three four", "phone", "plus one two one two five five five one two three four"),
        ("ip 192 dot 168 dot 1 dot 20.", "ip", "192 dot 168 dot 1 dot 20"),
        ("four one one one one one one one one one one one one one one one", "card", "four one one one one one one one one one one one one one one one"),
    ],
)
def test_disguises_map_back(text, kind, hidden):
    base, spans = pii.find(text)
    assert not any(base.values())
    assert [text[a:b] for a, b in spans[kind]] == [hidden]
    assert hidden not in pii.redact(text) and f"<{kind.upper()}>" in pii.redact(text)


@pytest.mark.parametrize(
    ("text", "kind", "base", "whole"),
    [
        ("to j\u043ehn@example.com now", "email", "hn@example.com", "j\u043ehn@example.com"),
        ("to jane@mail.example [dot] com now", "email", "jane@mail.example", "jane@mail.example [dot] com"),
        ("call +1 222 333 44 five six seven eight now", "phone", "+1 222 333 44", "+1 222 333 44 five six seven eight"),
        ("to j\u043ehn@example.com, hn@example.com", "email", "hn@example.com", "j\u043ehn@example.com"),
    ],
)
def test_partial_disguises_are_whole(text, kind, base, whole):
    plain, spans = pii.find(text)
    assert plain == pii.detect(text) and text[slice(*plain[kind][0])] == base
    assert whole in [text[a:b] for a, b in spans[kind]] and set(plain[kind]) < set(spans[kind])
    assert pii.redact(text) == text.replace(whole, f"<{kind.upper()}>").replace(base, f"<{kind.upper()}>")


@pytest.mark.parametrize(
    ("text", "kind", "whole"),
    [
        ("card 4111\xa01111\xa01111\xa01111 x", "card", "4111\xa01111\xa01111\xa01111"),
        ("call +1\xa0222\xa0333\xa04444 x", "phone", "+1\xa0222\xa0333\xa04444"),
        ("to jo\xadhn@exam\xadple.com x", "email", "jo\xadhn@exam\xadple.com"),
        ("call +1 two 3 four 5 six 7 eight 1 now", "phone", "+1 two 3 four 5 six 7 eight 1"),
        ("four 111 one 111 one 111 one 111 x", "card", "four 111 one 111 one 111 one 111"),
    ],
)
def test_listed_disguises_are_reached(text, kind, whole):
    assert [text[a:b] for a, b in pii.find(text)[1][kind]] == [whole]
    assert pii.redact(text) == text.replace(whole, f"<{kind.upper()}>")


def test_trigger_covers_rewrite():
    rng = np.random.default_rng(5)
    parts = ["one", "2", "three", "44", "oh", "plus", " ", "-", ", ", ".", "at", "dot", "[", "]", "(", ")", "@", "a", "\xa0", "\xad", "\u043e", "é", "\u212a", "\u0131"]
    found = 0
    for _ in range(20000):
        text = "".join(rng.choice(parts, rng.integers(1, 14)))
        if pii.REWRITE.search(text):
            found += 1
            assert pii.TRIGGER.search(text), text
    assert found > 1000


@pytest.mark.parametrize("text", ["we met at noon, dot your i", "one or two, three at most", "", "1.2.3 at 4", "Привет, мир", "at home"])
def test_clean_texts_stay(text):
    assert not any(pii.find(text)[1].values()) and pii.redact(text) == text


def test_personal_data_rows(docs, nothing):
    for r in rows_of(pii.personal_data(docs)):
        text = next(t for i, t, _ in ROWS if i == r.doc_id)
        spans = plain_spans(text or "")
        assert (r.n_email, r.n_ip, r.n_card, r.n_phone) == tuple(len(spans[k]) for k in pii.KINDS)
        assert r.base_sha256 == hashlib.sha256(",".join(f"{k}:{a}:{b}" for k in pii.KINDS for a, b in spans[k]).encode()).hexdigest()
    assert rows_of(pii.personal_data(nothing)) == []


# sharding


def test_sharding(docs, nothing, spark, sf):
    found = rows_of(sharding.sharded(docs, [1.0] * 8))
    assert collections.Counter((r.doc_id, r.size, r.text_crc32) for r in found) == collections.Counter((i, len((t or "").encode()) + 1, zlib.crc32((t or "").encode())) for i, t, _ in ROWS)
    whole = rows_of(queries.op6_sharding(spark, sf))
    for rows in (found, whole):
        assert all(r.grown_shard in (r.shard, 8) for r in rows)
        for s in range(8):
            slots = sorted(r.slot for r in rows if r.shard == s)
            assert slots == list(range(len(slots)))
    assert rows_of(sharding.sharded(nothing, [1.0] * 8)) == []
    heavy = collections.Counter(r.shard for r in rows_of(sharding.sharded(spark.range(4000).selectExpr("id AS doc_id", "'x' AS text"), [3.0, 1.0])))
    assert 0.72 < heavy[0] / 4000 < 0.78


# packing and token counts


@pytest.fixture(scope="module")
def coder():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(queries.tokenizer("byte_bpe_50k.json"))


def check_packing(rows, texts, coder):
    ids = {}
    for r in rows:
        ids.setdefault(r.doc_id, []).append(r)
    for doc, pieces in ids.items():
        want = [*coder.encode(texts[doc] or "", add_special_tokens=False).ids, 0]
        copies = sum(p.start == 0 for p in pieces)
        covered = sorted((p.start, p.length) for p in pieces)[::copies]
        assert [a for a, _ in covered] == list(np.cumsum([0, *[n for _, n in covered]])[:-1]) and sum(n for _, n in covered) == len(want)
        for p in pieces:
            assert p.doc_tokens == len(want)
            assert p.ids_crc32 == zlib.crc32(np.array(want[p.start : p.start + p.length], "<u4").tobytes())
    windows = collections.defaultdict(list)
    for r in rows:
        windows[r.sequence_id].append((r.offset, r.length))
    for w in windows.values():
        w.sort()
        assert [a for a, _ in w] == list(np.cumsum([0, *[n for _, n in w]])[:-1]) and sum(n for _, n in w) <= packing.CAPACITY
    return sum(r.length for r in rows) / (packing.CAPACITY * len(windows))


def test_packing(docs, nothing, spark, sf, coder):
    path = queries.tokenizer("byte_bpe_50k.json")
    check_packing(rows_of(packing.packed(docs, path)), {i: t for i, t, _ in ROWS}, coder)
    texts = {r.doc_id: r.text for r in rows_of(spark.read.parquet(f"{sf}/documents.parquet"))}
    assert check_packing(rows_of(queries.op9_packing(spark, sf)), texts, coder) > 0.97
    assert rows_of(packing.packed(nothing, path)) == []


def test_differencing_fills_windows():
    rng = np.random.default_rng(2)
    sizes = rng.integers(1, 129, 3000)
    window = packing.pack(sizes, 1024)
    sums = np.bincount(window, sizes)
    assert sums.max() <= 1024 and sizes.sum() / (1024 * len(sums)) > 0.99
    assert packing.pack(np.array([1000, 1000, 1000]), 1024).tolist() == [0, 1, 2]
    assert packing.difference(np.array([8, 7, 6, 5, 4]), 2).tolist().count(0) in (2, 3)


def test_token_counts(docs, nothing):
    import sentencepiece

    path = queries.tokenizer("piece_bpe_32k.model")
    model = sentencepiece.SentencePieceProcessor(model_file=path)
    for r in rows_of(token_count.token_counts(docs, path)):
        text = next(t for i, t, _ in ROWS if i == r.doc_id) or ""
        assert (r.n_bytes, r.n_tokens, r.over_limit) == (len(text.encode()), len(model.encode(text)), len(model.encode(text)) > 4096)
    assert rows_of(token_count.token_counts(nothing, path)) == []
    memo, rng = token_count.counter(path), np.random.default_rng(1)
    alphabet = list("ab é\n\t▁ ①\U0001f600the  ing 　\r\x00!!--ñß") + ["<s>", "</s>", "<unk>"]
    for _ in range(1500):
        text = "".join(rng.choice(alphabet, rng.integers(0, 60)))
        assert memo.count(text) == len(model.encode(text)), repr(text)


# language, toxicity


def test_language_id(docs, nothing, spark):
    sf = "/root/testdata/sf0.01"
    found = {r.doc_id: r for r in rows_of(queries.op1_language_id(spark, sf))}
    truth = [r for r in rows_of(spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "lang")) if zlib.crc32(str(r.doc_id).encode()) % 5 == 0]
    assert all(found[r.doc_id].held_out for r in truth) and sum(r.held_out for r in found.values()) == len(truth)
    assert np.mean([found[r.doc_id].lang_pred == r.lang for r in truth]) > 0.97
    model = lang_id.train([(PROSE, "en"), ("Der alte Mann ging durch den Wald und sah das Haus. ", "de")], steps=20)
    odd = rows_of(lang_id.predict(docs, model))
    assert {r.doc_id for r in odd if r.lang_pred == "und"} == {1, 2, 3} and all(0 <= r.score <= 1 for r in odd)
    assert rows_of(lang_id.predict(nothing, model)) == []
    assert lang_id.learn(nothing) is None and all(r.lang_pred == "und" for r in rows_of(lang_id.predict(docs, None)))


def test_gradients_follow_the_loss():
    rng = np.random.default_rng(0)
    windows, target = rng.integers(0, 256, (12, 6)).astype(np.uint8), np.array([0, 1, 0, 1, 0, 1])
    model = lang_id.ByteGru.fresh(["a", "b"], 4)
    for name in ("table", "recur", "head", "bias"):
        setattr(model, name, getattr(model, name).astype(np.float64))
    adam: dict = {}
    loss = lambda m: float(-np.log(m.position_probabilities(m.states(windows))[:, np.arange(6), target] + 1e-9).mean())
    start = loss(model)
    for _ in range(60):
        model.train_step(windows, target, adam, 0.02)
    assert loss(model) < 0.5 * start


def test_toxicity(docs, nothing, spark):
    sf = "/root/testdata/sf0.01"
    model = toxicity.train([(PROSE * 2 + f"You idiot number{i}. " + PROSE, 1) for i in range(12)] + [(PROSE * 3 + f"Fine number{i}.", 0) for i in range(30)])
    score, worst = model.document("Hello there. You IDIOT! Bye.")
    assert score >= 0.5 and ["Hello there. You IDIOT! Bye."[a:b].strip() for a, b, _ in worst] == ["You IDIOT"]
    assert all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.5) for r in rows_of(toxicity.scores(docs, model)))
    assert rows_of(toxicity.scores(nothing, model)) == []
    assert toxicity.learn(nothing, spark.createDataFrame([], "doc_id long, toxic long")).weights == {}
    found = {r.doc_id: r for r in rows_of(queries.op8_toxicity(spark, sf))}
    labels = [r for r in rows_of(spark.read.parquet(f"{sf}/labels.parquet")) if found[r.doc_id].held_out]
    pos, neg = ([found[r.doc_id].score for r in labels if r.toxic == y] for y in (1, 0))
    assert np.mean([a > b for a in pos for b in neg]) > 0.85


# pages


def test_main_text(spark, sf):
    page = '<body><nav><a href=x>menu</a></nav><div class="ad">buy</div><article><h1>T &amp; x</h1><p>Hello <b>wor</b>ld<br>again<p>two &lt;3<ul><li>a<li>b</ul><div id="comments"><p>bad</div></article><footer>f</footer><script>var a="<p>"</script>'
    rows = [(1, "http://h.example/1", page), (2, "http://h.example/2", None), (3, None, ""), (4, "http://h.example/1", page), (5, "not a url", "plain < text"), (6, "http://g.example/", "<div" * 3000)]
    found = {r.page_id: r for r in rows_of(html_text.main_text(spark.createDataFrame(rows, "page_id long, url string, html string")))}
    assert found[1].text == "T & x\n\nHello world again\n\ntwo <3\n\na\n\nb" == found[4].text
    assert found[2].text == found[3].text == "" and found[5].text == "plain < text"
    assert all(r.n_chars == len(r.text) for r in found.values())
    assert rows_of(html_text.main_text(spark.createDataFrame([], "page_id long, url string, html string"))) == []
    for r in rows_of(html_text.main_text(spark.read.parquet(f"{sf}/pages.parquet"))):
        html = next(p.html for p in rows_of(spark.read.parquet(f"{sf}/pages.parquet").filter(f"page_id = {r.page_id}")))
        inside = re.search("<article>(.*)</article>", html, re.S)[1]
        want = [re.sub(r"\s+", " ", __import__("html").unescape(re.sub("<br>", " ", re.sub("</?b>", "", x)))).strip() for x in re.split("</?(?:p|h1)>", inside)]
        assert r.text == "\n\n".join(x for x in want if x)


BODY = "".join(f"<p>{PROSE}</p>" for _ in range(4))
TEXTS = [PROSE.strip()] * 4
LINKS = "<ul>" + "".join(f"<li><a href=/{i}>Another story of the day {i}</a>" for i in range(9)) + "</ul>"


@pytest.mark.parametrize(
    ("page", "want"),
    [
        (f"<body><nav>n</nav><article><h1>T</h1><p>lead</p><div class=body>{BODY}</div></article>", ["T", "lead", *TEXTS]),
        (f"<body><div class=post><h1>T</h1><p>lead</p><div class=body>{BODY}</div>{LINKS}</div><div>{LINKS}</div>", ["T", "lead", *TEXTS]),
        (f"<body>{LINKS}<h1>T</h1><p>lead</p><div class=body>{BODY}</div><div>© x</div>", ["T", "lead", *TEXTS]),
        (f"<body><div class=post><div class=intro><p>lead</p><p>more</p></div><div class=body>{BODY}</div></div>", ["lead", "more", *TEXTS]),
        (f"<body><main><div class=hero><h1>T</h1></div><article><p>lead</p><section class=a>{BODY}</section><section class=b><p>end</p></section></article></main><div>x</div>", ["T", "lead", *TEXTS, "end"]),
        (f"<body><article><p>before</p><blockquote>{BODY}</blockquote><p>after</p></article><div>x</div>", ["before", *TEXTS, "after"]),
        (f"<body><div class=post><p>before</p><table><tr><td>{BODY}<td>cell</table></div>", ["before", *TEXTS, "cell"]),
        (f"<body><div>{LINKS}</div><div class=body>{BODY}</div>", TEXTS),
    ],
)
def test_article_is_whole(page, want):
    scores = html_text.best_paths(page)
    for winner in (max(scores, key=scores.get), None):
        assert html_text.extract(page, winner).split("\n\n") == want


@pytest.mark.parametrize(
    ("page", "want"),
    [
        (f'<body><div class="layout with-sidebar"><nav>n</nav>{BODY}<div class="sidebar">s</div></div>', TEXTS),
        (f'<body><main id="content" class="no-sidebar">{BODY}</main>', TEXTS),
        (f'<body><article class="post has-comments">{BODY}</article>', TEXTS),
        (f'<body><article class="post comments-open">{BODY}<div class="comments">c</div></article>', TEXTS),
        (f'<body><div class="social-layout"><div class="nav">n</div>{BODY}</div>', TEXTS),
        (f'<body><h1>Site</h1><div class="social-layout">{BODY}</div>', ["Site", *TEXTS]),
        (f'<body><form id="aspnetForm" action=x><input name=q><div class="menu">{LINKS}</div><div class="content">{BODY}</div><div class="comments">{BODY[: len(BODY) // 2]}</div></form>', TEXTS),
        (f'<body><form><div class="social-layout"><section class="side-story">{BODY}</section></div></form>', TEXTS),
        (f'<body><article>{BODY}</article><div class="comments">{BODY * 2}</div>', TEXTS),
        (f'<body><article><h1>T</h1><div class="share-body">{BODY}</div></article>', ["T", *TEXTS]),
        (f'<body><div class="ad">{BODY}</div><article><h1>T</h1><p>short</article>', ["T", "short"]),
        (f'<body><div class="content">{BODY}</div><div class="sidebar">{LINKS * 9}</div><form>Search</form>', TEXTS),
        (f'<body><p>x<div class="ad" hidden>{BODY}</div>', ["x"]),
        ('<div class="ad">' * 2000 + "x", ["x"]),
    ],
)
def test_marks_do_not_take_the_page(page, want):
    assert html_text.extract(page, None).split("\n\n") == want


# the pipeline


def test_pipeline(spark, sf, docs, coder):
    import corpus_pipeline

    for _, stage in corpus_pipeline.STAGES[:-1]:
        for df in (docs, docs.limit(0)):
            assert stage(spark, df, sf).columns == docs.columns
    kept = spark.read.parquet(f"{sf}/documents.parquet")
    before = {r.doc_id: r.text for r in rows_of(kept)}
    good = {r.doc_id for r in rows_of(quality.quality(kept)) if r.kept}
    items = [(r.item_id, r.text) for r in rows_of(spark.read.parquet(f"{sf}/benchmark.parquet"))]
    one = {i for i, _, c in components([(i, before[i]) for i in sorted(good)], 5, 80) if i == c}
    clean = {i for i in one if leaked(before[i], items)[1] == 0}
    texts = {i: pii.redact(before[i]) for i in clean}
    final = rows_of(corpus_pipeline.run(spark, sf))
    assert {r.doc_id for r in final} == clean
    check_packing(final, texts, coder)
