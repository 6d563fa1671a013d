"""Every corpus operator against a brute-force version, with nulls, empty and repeated rows, and clashing columns."""

import collections
import hashlib
import os
import random
import re
import zlib

import duckdb
import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
import xxhash

from cohesion.llm import classify, decontaminate, fingerprint, language, neardup, packing, pii, quality, secrets, sentencededup, suffixdedup
from cohesion.session import load_table

TOKENIZER = public_tokenizers.path("word_bpe_49k.json")
WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
LOW = {c: c + 32 for c in range(65, 91)}


def words(text):
    return WORD.findall((text or "").translate(LOW))


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls in any column, empty and long texts, repeated rows and ids, and columns whose names clash with ours."""
    rng = random.Random(3)
    vocabulary = ["".join(rng.choice("abcdeéß") for _ in range(rng.randint(2, 7))) for _ in range(400)]
    prose = lambda n: " ".join(rng.choice(vocabulary) for _ in range(n)) + "."
    a, b = prose(120), prose(90)
    texts = [None, "", "!!!", "one two", a, a, a + " " + prose(3), b + "\n" + a[:300], "x" * 700, "ab" * 300, prose(8000), b, "AKIA" + "A1" * 9 + " token = 'abcdef12'", "mail jo.e@ex-am.ple.org or +1 (555) 123-4567"]
    rows = [(i if i != 6 else None, t, "en" if i % 3 else None, i, "s") for i, t in enumerate(texts)] + [(4, a, None, 0, "s"), (None, None, None, None, None)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, n_words long, piece string")


@pytest.fixture(scope="module")
def empty(spark, odd):
    return spark.createDataFrame([], odd.schema)


@pytest.fixture(scope="module")
def docs(spark, sf):
    return load_table(spark, sf, "documents")


def texts_of(df):
    return [(r["doc_id"], r["text"] or "") for r in df.select("doc_id", "text").collect()]


def shingles_of(t):
    w = words(t)
    return collections.Counter(tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))) if w else collections.Counter()


def item_windows(items):
    held = collections.defaultdict(set)
    for r in items.collect():
        w = words(r["text"])
        size = min(13, len(w))
        for k in range(len(w) - size + 1 if size else 0):
            held[tuple(w[k : k + size])].add(str(r["item_id"]))
    return held


def hit_words(w, held):
    hit, named = set(), set()
    for size in {len(k) for k in held}:
        for k in range(len(w) - size + 1):
            if found := held.get(tuple(w[k : k + size])):
                named |= found
                hit |= set(range(k, k + size))
    return hit, named


def contaminated(w, held):
    hit, _ = hit_words(w, held)
    return bool(hit) and 20 * len(hit) >= len(w)


def masked_by_hand(t):
    """All secrets of the text as it came, as one run where they touch, replaced."""
    spans = []
    for rule in secrets.RULES:
        spans += [(m.start(), m.end()) for m in re.finditer(rule.pattern, t) if len(m[rule.group]) >= rule.least]
    out, last = "", 0
    for a, b in sorted(spans):
        if a >= last:
            out += t[last:a] + secrets.MASK
        last = max(last, b)
    return out + t[last:]


def brute_repeats(texts, size=200):
    seen = collections.Counter(hashlib.md5(t[i : i + size]).digest() for t in texts for i in range(len(t) - size + 1))
    out = []
    for t in texts:
        depth = np.zeros(len(t) + 1, int)
        for i in range(len(t) - size + 1):
            if seen[hashlib.md5(t[i : i + size]).digest()] > 1:
                depth[i] += 1
                depth[i + size] -= 1
        hit = np.cumsum(depth)[:-1] > 0
        rest = np.frombuffer(t, np.uint8)[~hit].tobytes()
        out.append((len(t), int(hit.sum()), int((np.diff(np.r_[0, hit.astype(int)]) == 1).sum()), hashlib.sha256(rest).hexdigest()))
    return out


@pytest.mark.parametrize("kw", [{}, {"shard_bytes": 2000}, {"shard_bytes": 600, "together": 0}])
def test_suffix_dedup(odd, kw):
    rows = texts_of(odd)
    want = collections.Counter((i, *x) for (i, _), x in zip(rows, brute_repeats([t.encode() for _, t in rows])))
    assert collections.Counter(tuple(r) for r in suffixdedup.remove_repeats(odd, **kw).collect()) == want


def test_suffix_array_and_merge():
    rng = random.Random(1)
    text = bytes(rng.choice(b"ab") for _ in range(300))
    order, _ = suffixdedup.suffix_array(np.frombuffer(text, np.uint8), 512)
    assert order.tolist() == sorted(range(300), key=lambda i: text[i:])
    for data in (text, b"a" * 300, text[:90] * 3, b"\0" * 100 + b"a"):
        raw = np.frombuffer(data, np.uint8)
        order, _ = suffixdedup.suffix_array(raw, len(data))
        shared = [0] + [next((k for k in range(40) if data[a + k : a + k + 1] != data[b + k : b + k + 1] or a + k == len(data)), 40) for a, b in zip(order.tolist(), order[1:].tolist())]
        assert suffixdedup.common_prefixes(raw, order, 40, 16).tolist() == shared
    pieces = [text[:120], text[60:200], b"b" + text[80:120] + b"a" * 50, text[200:]]
    held = collections.Counter(p[i : i + 40] for p in pieces for i in range(len(p) - 39))
    shard = suffixdedup.Shard(pieces, 40)
    want = [held[p[i : i + 40]] > 1 if i + 40 <= len(p) else False for p in pieces for i in range(len(p))]
    assert shard.repeated.tolist() == want
    one, two = suffixdedup.Shard([text[:250]], 40), suffixdedup.Shard([text[100:]], 40)
    one.merge(two)
    assert one.repeated[100:211].all() and two.repeated[:111].all()


def test_secret_scan(spark, odd, sf):
    assign = re.compile(r"""((?:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
    for table in (odd, load_table(spark, sf, "documents")):
        found = secrets.scan(table).collect()
        want = []
        for i, t in texts_of(table):
            spans = [(m.start(), 0, "assign", m.end()) for m in assign.finditer(t) if len(m[2]) >= 6]
            spans += [(m.start(), 1, "access", m.end()) for m in re.finditer("AKIA[A-Z0-9]+", t) if len(m[0]) >= 20]
            spans += [(m.start(), 2, "hex", m.end()) for m in re.finditer("[0-9a-f]+", t) if len(m[0]) >= 24]
            shown = ",".join(f"{k}:{a}:{b}" for a, _, k, b in sorted(spans))
            want.append((i, hashlib.sha256(shown.encode()).hexdigest()))
        assert collections.Counter((r["doc_id"], r["base_sha256"]) for r in found) == collections.Counter(want)
    con = duckdb.connect()
    con.sql(f"CREATE VIEW documents AS SELECT * FROM '{sf}/documents.parquet'")
    assert sorted(con.sql(secrets.oracle()).fetchall()) == sorted(tuple(r) for r in found)
    masked = secrets.redact(odd)
    assert masked.columns == odd.columns and masked.count() == odd.count()
    want = collections.Counter((i, masked_by_hand(t)) for i, t in texts_of(odd))
    assert collections.Counter((r["doc_id"], r["text"] or "") for r in masked.collect()) == want and any(secrets.MASK in t for _, t in want)
    rng = random.Random(4)
    parts = ["password=abcdef12", "AKIA" + "Q1" * 9, "0123456789abcdef" * 2, "ghp_" + "a1" * 20, " é ", "token: ", "xyz", "eyJhbGciOiJIU.eyJhbGciOiJIU.abcdefgh12", "://me:pass@host", "secret='AKIA" + "Z" * 20 + "'"]
    mixed = [(i, "".join(rng.choice(parts) for _ in range(rng.randint(0, 12)))) for i in range(150)] + [(1000, " token=abcdef1 " * 3000), (1001, ("f" * 30 + " ") * 1000)]
    table = spark.createDataFrame(mixed, "doc_id long, text string")
    got = {r["doc_id"]: r["text"] for r in secrets.redact(table).collect()}
    assert got == {i: masked_by_hand(t) for i, t in mixed}
    assert {r["doc_id"]: (r["n_assign"], r["n_hex"]) for r in secrets.scan(table).collect()}[1000] == (3000, 0)


def test_trigram_queries():
    assert secrets.trigram_clauses("[0-9a-f]{24,}") == []
    assert secrets.trigram_clauses("AKIA[A-Z0-9]+") == [frozenset({"aki", "kia"})]
    assert frozenset({"api", "pi_", "i_k", "_ke", "key"}) in secrets.trigram_clauses(secrets.BASE[0].pattern)


def test_fingerprints(spark, odd, docs):
    for table in (docs,):
        rows = sorted(texts_of(table))
        found = {r["doc_id"]: r for r in fingerprint.compare_with_next(table).collect()}
        for (i, t), (_, n) in zip(rows, rows[1:] + rows[:1]):
            cut = len(t) // 4
            edited = t[: len(t) - cut] + n[:cut]
            r = found[i]
            assert (r["n_chars"], r["edited_sha256"]) == (len(t), hashlib.sha256(edited.encode()).hexdigest())
            a, b = set(shingles_of(t)) or {t}, set(shingles_of(edited)) or {edited}
            assert abs(len(a & b) / len(a | b) - r["near_edited"]) < 0.2
            a, b = set(shingles_of(n)) or {n}, set(shingles_of(t)) or {t}
            assert abs(len(a & b) / len(a | b) - r["near_next"]) < 0.2
    # Nulls first, ties by the hash of the text; string ids; an id that half of the rows share.
    named = odd.selectExpr("concat('d', cast(doc_id as string)) AS doc_id", "text")
    hot = spark.createDataFrame([(7 if i % 2 else i, f"text number {i} " + "of some words " * (i % 9)) for i in range(400)], "doc_id long, text string")
    for table in (odd, named, hot):
        rows = sorted(texts_of(table), key=lambda x: (x[0] is not None, x[0] or 0, xxhash.xxh64_intdigest(x[1].encode(), 42) - (1 << 64) * (xxhash.xxh64_intdigest(x[1].encode(), 42) >> 63)))
        want = collections.Counter()
        for (i, t), (_, n) in zip(rows, rows[1:] + rows[:1]):
            cut = len(t) // 4
            want[(i, len(t), hashlib.sha256((t[: len(t) - cut] + n[:cut]).encode()).hexdigest())] += 1
        assert collections.Counter(tuple(r)[:3] for r in fingerprint.compare_with_next(table).collect()) == want
    both = fingerprint.fingerprint(docs.select("doc_id", "text"))
    from pyspark.sql import functions as F

    whole = fingerprint.merge_parts(both.withColumn("g", F.lit(1)), "g").first()
    distinct = {x for _, t in texts_of(docs) for x in shingles_of(t)}
    assert abs(whole["n_shingles"] / len(distinct) - 1) < 0.35
    x = fingerprint.sketches(pa.array(["a b c d e f g h", "a b c d e f g h", "", None]))
    assert fingerprint.resemblance(x[0], x[1]) == 1.0 and fingerprint.resemblance(x[2], x[3]) == 1.0
    assert (fingerprint.from_bytes(fingerprint.to_bytes(x[0])) == x[0]).all()


def test_packing(odd, docs):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(TOKENIZER)
    for table in (docs, odd.where("doc_id is not null").dropDuplicates(["doc_id"])):
        ids = {i: t.encode(x, add_special_tokens=False).ids + [1] for i, x in texts_of(table)}
        rows = packing.pack(table, TOKENIZER).collect()
        assert sum(r["length"] for r in rows) == sum(map(len, ids.values()))
        for r in rows:
            part = ids[r["doc_id"]][r["start"] : r["start"] + r["length"]]
            assert zlib.crc32(np.array(part, "<u4").tobytes()) == r["ids_crc32"] and len(ids[r["doc_id"]]) == r["doc_tokens"]
        by = collections.defaultdict(list)
        for r in rows:
            by[r["sequence_id"]].append((r["offset"], r["length"]))
        ends = {s: sum(n for _, n in v) for s, v in by.items() if [o for o, _ in sorted(v)] == np.cumsum([0] + [n for _, n in sorted(v)])[:-1].tolist()}
        assert len(ends) == len(by) and sum(e != 2048 for e in ends.values()) <= 1
    assert packing.pack(odd, TOKENIZER).where("start = 0").count() == odd.count()
    hard = ["don't can't IT'S", "Ünï ÀÉ ß ſ İ", "a b c\x1cd", "<|endoftext|> 12 345", "é ﬁ 你好 한국", "!!x?? ,,a.."]
    for x, got in zip(hard, packing.WordTokenizer(TOKENIZER).ids(hard)):
        assert np.frombuffer(got, "<u2").tolist() == t.encode(x, add_special_tokens=False).ids, x


def test_sentence_spans(spark, odd):
    passage = " ".join(f"Alpha{i} beta gamma delta epsilon zeta eta theta." for i in range(8))
    rows = [(1, f"Start here now. {passage} End one."), (2, f"Other words first. {passage} Quite another end."), (3, "A clean text with nothing in common. It has two sentences only.")]
    found = {r["doc_id"]: r for r in sentencededup.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert found[1]["n_removed"] == 0 and found[3]["n_removed"] == 0 and found[3]["text"] == rows[2][1]
    assert found[2]["n_removed"] == 8 and found[2]["text"] == "Other words first. Quite another end."
    assert sentencededup.remove_repeats(odd).count() == odd.count()


def test_runs_of_short_sentences_grow(spark):
    menu = "".join(f"Dish{i} price{i % 7}.\n" for i in range(60))
    rows = [(1, f"First of all we greet the guests here.\n{menu}Thanks to all."), (2, f"Another card.\n{menu}Come again."), (3, "Dish1 price1.\nOnly this."), (4, menu), (5, menu)]
    found = {r["doc_id"]: r for r in sentencededup.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert found[1]["n_removed"] == 0 and found[3]["n_removed"] == 0
    assert found[2]["text"] == "Another card.\nCome again."
    assert found[4]["text"] == "" and found[5]["text"] == ""


def test_passages_inside_long_sentences(spark):
    rng = random.Random(8)
    word = lambda: "".join(rng.choice("abcdefghij") for _ in range(6))
    some = lambda n: [word() for _ in range(n)]
    rows, n = [], 51
    for i in range(60):
        passage = some(n)
        for _ in range(rng.randrange(3)):
            passage[rng.randrange(n - 1)] += rng.choice(".\n?")
        rows += [(2 * i, " ".join(some(rng.randrange(40)) + passage + some(rng.randrange(40)))), (2 * i + 1, " ".join(some(rng.randrange(40)) + passage + some(rng.randrange(40))))]
    found = {r["doc_id"]: r["n_removed"] for r in sentencededup.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert all((found[i] > 0) == (i % 2 == 1) for i in found)


def test_decontamination(spark, odd, sf, monkeypatch):
    table, items = load_table(spark, sf, "documents"), load_table(spark, sf, "benchmark")
    held = item_windows(items)
    want = {}
    for i, t in texts_of(table):
        w = words(t)
        hit, named = hit_words(w, held)
        want[i] = (len(w), len(hit), len(named), hashlib.sha256(",".join(sorted(named)).encode()).hexdigest(), bool(hit) and 20 * len(hit) >= len(w))
    # The second bitmap is nearly full, so that nearly all words are in segments.
    for least, most in ((1 << 20, 1 << 27), (1 << 15, 1 << 15)):
        monkeypatch.setattr(decontaminate, "BITS_LEAST", least)
        monkeypatch.setattr(decontaminate, "BITS_MOST", most)
        got = decontaminate.contamination(table, items).collect()
        assert {r["doc_id"]: (r["n_words"], r["n_hit"], r["n_items"], r["items_sha256"], r["contaminated"]) for r in got} == want
        assert sorted(r["doc_id"] for r in decontaminate.clean(table, items).collect()) == sorted(i for i, x in want.items() if not x[4])
    few = spark.createDataFrame([(1, None), (2, ""), (3, "one two"), (None, "one")], "item_id long, text string")
    got = collections.Counter(tuple(r)[:4] + (r["contaminated"], tuple(r["items"])) for r in decontaminate.contamination(odd, few).collect())
    short = {(w,): [i] for w, i in (("one", "null"),)} | {("one", "two"): ["3"]}
    want = collections.Counter()
    for i, t in texts_of(odd):
        w, hit, named = words(t), set(), []
        for key, ids in short.items():
            for k in range(len(w) - len(key) + 1):
                if tuple(w[k : k + len(key)]) == key:
                    hit |= set(range(k, k + len(key)))
                    named += ids
        want[(i, len(w), len(hit), len(set(named)), bool(hit) and 20 * len(hit) >= len(w), tuple(sorted(set(named))))] += 1
    assert got == want and sum(x[4] for x in got) == 1
    twice = spark.createDataFrame([(7, "one two"), (7, "one  TWO!")], "item_id long, text string")
    assert decontaminate.contamination(odd, twice).where("contaminated").first()["items"] == ["7", "7"]
    assert decontaminate.clean(odd, few.where("false")).count() == odd.count()


def test_classifiers(spark, odd, docs, sf):
    labels = load_table(spark, sf, "labels")
    found = quality.score(docs, quality.fit(docs, labels)).join(labels, "doc_id").where("held_out").collect()
    assert np.mean([r["predicted"] == r["quality"] for r in found]) > 0.9
    model, threshold = language.fit(docs)
    got = language.predict(docs, model, threshold).join(docs.select("doc_id", "lang"), "doc_id").where("held_out").collect()
    assert np.mean([r["lang_pred"] == r["lang"] for r in got]) > 0.95
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2) for r in got)
    rows = language.predict(odd, model).collect()
    assert len(rows) == odd.count() and sum(r["lang_pred"] == "und" for r in rows) == 4
    assert language.accepted(odd, model, threshold).columns == odd.columns
    # What no language of the table is like is rejected, what was learnt stays.
    rng = random.Random(1)
    scripts = ["абвгдежзиклмнопрстуфхцчшщыэюя", "αβγδεζηθικλμνξοπρστυφχψω", "אבגדהוזחטיכלמנסעפצקרשת"]
    noise = [(i, " ".join("".join(rng.choice(scripts[i % 3]) for _ in range(rng.randint(2, 9))) for _ in range(rng.choice([6, 50, 300])))) for i in range(90)]
    foreign = spark.createDataFrame(noise, "doc_id long, text string")
    assert language.accepted(foreign, model, threshold).count() <= 4
    kept = language.accepted(docs, model, threshold)
    lettered = [t for _, t in texts_of(docs) if classify.has_letter(t)]
    assert kept.count() >= 0.99 * len(lettered)
    long = docs.limit(20).select("doc_id", "lang", "text").union(spark.createDataFrame([(10**6, "en", "the " * 10**6)], "doc_id long, lang string, text string"))
    texts, _ = classify.sample(long, "lang")
    assert max(map(len, texts)) == classify.SAMPLE_CHARS and len(texts) == 21
    assert quality.score(odd, classify.train([], [])).where("score = 0.5").count() == odd.count()


def test_near_duplicates(spark, odd, docs, monkeypatch):
    rng = random.Random(2)
    base = [f"w{rng.randrange(500)}" for _ in range(200)]
    near = []
    for i in range(40):
        copy = list(base)
        for _ in range(rng.randint(0, 6)):
            copy[rng.randrange(200)] = f"z{rng.randrange(900)}"
        near.append((1000 + i, " ".join(copy)))
    group = spark.createDataFrame(near, "doc_id long, text string")
    for table, kw, sparse in ((odd.where("doc_id is not null").dropDuplicates(["doc_id"]), {}, 2), (group, {}, 2), (group, {"bucket": 8}, 0)):
        monkeypatch.setattr(neardup, "SPARSE", sparse)
        rows = sorted(texts_of(table))
        own = {i: shingles_of(t) for i, t in rows}
        parent = {i: i for i, _ in rows}

        def find(i):
            while parent[i] != i:
                i = parent[i]
            return i

        for n, (i, t) in enumerate(rows):
            for j, u in rows[:n]:
                a, b = own[i], own[j]
                if t == u or (a and b and (a & b).total() >= 0.8 * (a | b).total()):
                    x, y = sorted((find(i), find(j)))
                    parent[y] = x
        got = {r["doc_id"]: r["class_id"] for r in neardup.near_duplicates(table, **kw).collect()}
        assert got == {i: find(i) for i, _ in rows}
    assert neardup.near_duplicates(odd).count() == odd.count()
    kept = neardup.one_of_each(odd)
    assert kept.columns == odd.columns and kept.count() == neardup.near_duplicates(odd).select("class_id").distinct().count()


def test_recall_against_all_pairs(docs):
    """Of all pairs of documents that are alike by brute force, at least nine in ten are in one class."""
    rows = sorted(texts_of(docs))
    own = {i: shingles_of(t) for i, t in rows}
    got = {r["doc_id"]: r["class_id"] for r in neardup.near_duplicates(docs).collect()}
    pairs = found = 0
    for n, (i, _) in enumerate(rows):
        for j, _ in rows[:n]:
            a, b = own[i], own[j]
            if a and b and min(a.total(), b.total()) >= 0.8 * max(a.total(), b.total()) and (a & b).total() >= 0.8 * (a | b).total():
                pairs, found = pairs + 1, found + (got[i] == got[j])
    assert pairs > 5 and found >= 0.9 * pairs


def test_signatures_are_unbiased():
    rng = np.random.default_rng(0)
    codes = rng.integers(0, 2**63, 300).astype(np.uint64)
    wa, wb = rng.integers(1, 9, 300), rng.integers(1, 9, 300)
    s = neardup.signatures(np.repeat([0, 1], 300), np.concatenate([codes, codes]), np.concatenate([wa, wb]), 2, 4096)
    assert abs((s[0] == s[1]).mean() - np.minimum(wa, wb).sum() / np.maximum(wa, wb).sum()) < 0.03


def test_personal_data(spark, odd, docs):
    patterns = [r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", r"[0-9]([\x20-]?[0-9])+", r"\+[0-9][\x20().0-9-]+[0-9]"]

    def ok(k, m):
        digits = re.sub("[^0-9]", "", m)
        return k == 0 or (k == 1 and all(int(p) <= 255 for p in m.split("."))) or (k == 2 and 12 <= len(digits) <= 19 and pii.luhn(digits)) or (k == 3 and 9 <= len(digits) <= 15)

    def brute(t):
        return sorted((m.start(), k, m.end()) for k, p in enumerate(patterns) for m in re.finditer(p, t) if ok(k, m[0]))

    rng = random.Random(5)
    for t in [t for _, t in texts_of(docs)] + ["".join(rng.choice("12 .-@+a(") for _ in range(60)) for _ in range(3000)]:
        assert pii.base_spans(t) == brute(t)
    tagger = pii.fit(docs)
    found = {(r["doc_id"], r["base_sha256"]) for r in pii.scan(odd, tagger).collect()}
    shown = lambda t: hashlib.sha256(",".join(f"{pii.KINDS[k]}:{a}:{b}" for a, k, b in brute(t)).encode()).hexdigest()
    assert found == {(i, shown(t)) for i, t in texts_of(odd)} and pii.scan(odd, tagger).count() == odd.count()
    for r in pii.scan(docs, tagger).collect():
        assert r["spans"].count(":") // 2 == r["n_email"] + r["n_ip"] + r["n_card"] + r["n_phone"] + r["n_added"]
    # Windows of texts that are not sampled, values and words that training has not seen.
    held = [t[k : k + 300] for _, t in texts_of(docs) for k in range(0, max(1, len(t) - 300), 700) if t][::7]
    precision, recall = pii.measured(tagger, pii.invented(np.random.default_rng(99), held, 500))
    assert precision > 0.9 and recall > 0.75
    precision, recall = pii.measured(tagger, pii.invented(np.random.default_rng(98), held, 300, pii.UNSEEN))
    assert precision > 0.8 and recall > 0.4


def test_every_character_is_read():
    for lengths in ([0, 1, 5], [pii.SIZE, pii.SIZE + 1, 0, pii.STEP, 5000], [3 * pii.STEP + pii.SIZE]):
        offsets = np.concatenate([[0], np.cumsum(lengths)])
        text, start = pii.windows_of(offsets)
        for i, n in enumerate(lengths):
            own = np.sort(start[text == i]) - offsets[i]
            assert sorted({c for s in own.tolist() for c in range(s, min(n, s + pii.SIZE))}) == list(range(n))
            # A span of up to the overlap is whole in some window.
            assert (np.diff(own) <= pii.STEP).all()


def test_open_places_keep_the_best_path(docs):
    rng = np.random.default_rng(3)
    texts = [t[:200] for _, t in texts_of(docs) if t]
    tagger = pii.Tagger(seed=9)
    cases = pii.invented(rng, texts, 800)
    tagger.fit(pii.codes([t for t, _ in cases], pii.LEARNT), np.stack([pii.labelled(s) for _, s in cases]), epochs=8)
    x = pii.codes([t for t, _ in pii.invented(rng, texts, 200, size=200)], 200)
    e = tagger.emissions(np.ascontiguousarray(x.T))
    np.copyto(e[:, 1:], -1e4, where=(x.T == 0)[:, None])
    whole, found = tagger.viterbi(e), np.zeros(x.shape, np.int8)
    for row, at, tags in tagger.decode(x):
        n = min(len(tags), 200 - at)
        found[row, at : at + n] = np.where(tags[:n] > 0, tags[:n], found[row, at : at + n])
    assert whole.any() and (whole == found).all()


def test_gradients_of_the_tagger():
    rng = np.random.default_rng(1)
    tagger = pii.Tagger(seed=2)
    tagger.p["A"] += rng.normal(0, 0.3, tagger.p["A"].shape).astype(np.float32)
    x, y = rng.integers(40, 60, (3, 7)).astype(np.uint8), rng.integers(0, pii.TAGS, (3, 7))

    def loss():
        e = tagger.emissions(np.ascontiguousarray(x.T)).astype(np.float64)
        total = 0.0
        for i in range(len(x)):
            alpha = e[0, :, i]
            for t in range(1, x.shape[1]):
                alpha = np.log(np.exp(alpha[:, None] + tagger.p["A"]).sum(axis=0)) + e[t, :, i]
            right = sum(e[t, y[i, t], i] for t in range(x.shape[1])) + sum(tagger.p["A"][y[i, t - 1], y[i, t]] for t in range(1, x.shape[1]))
            total += np.log(np.exp(alpha).sum()) - right
        return total / len(x)

    found = tagger.gradients(x, y)
    for name in ("A", "ob", "O", "Uf", "Wb", "cb", "E"):
        flat, grad = tagger.p[name].reshape(-1), found[name].reshape(-1)
        for i in np.argsort(-np.abs(grad))[:3].tolist():
            was = flat[i]
            flat[i] = was + 1e-2
            up = loss()
            flat[i] = was - 1e-2
            down = loss()
            flat[i] = was
            assert abs((up - down) / 2e-2 - grad[i]) < 0.02 + 0.1 * abs(grad[i]), name


def test_empty_tables(spark, empty, docs):
    model, threshold = language.fit(empty)
    few = spark.createDataFrame([], "item_id long, text string")
    for found in (
        suffixdedup.remove_repeats(empty), secrets.scan(empty), secrets.redact(empty), fingerprint.compare_with_next(empty), packing.pack(empty, TOKENIZER), sentencededup.remove_repeats(empty),
        decontaminate.contamination(empty, few), neardup.near_duplicates(empty), neardup.one_of_each(empty), language.predict(empty, model, threshold), language.accepted(empty, model, threshold), pii.scan(empty, pii.Tagger()),
    ):
        assert found.count() == 0


def test_pipeline(spark, sf, tmp_path):
    import corpus_pipeline

    # The given rows, and some that each stage must act upon.
    rng = random.Random(12)
    given = load_table(spark, sf, "documents")
    item = load_table(spark, sf, "benchmark").orderBy("item_id").first()["text"]
    plain = [t for _, t in texts_of(given.where("lang = 'en' and n_chars > 400").orderBy("doc_id").limit(6))]
    turned = [" ".join(reversed(t.split())) for t in plain]  # like no other text
    more = [turned[0] + " password = 'abcd1234efgh' and more", plain[1], plain[1] + " again", turned[2] + " " + item, "AKIA" + "Z7" * 9 + " " + turned[3]]
    more += [" ".join("".join(rng.choice("абвгдежзиклмнопрст") for _ in range(7)) for _ in range(60)) for _ in range(3)]
    extra = spark.createDataFrame([(10**6 + i, t) for i, t in enumerate(more)], "doc_id long, text string").selectExpr("doc_id", "text", "cast(null as string) AS lang", "'x' AS source", "cast(char_length(text) as bigint) AS n_chars")
    given.unionByName(extra).write.parquet(f"{tmp_path}/documents.parquet")
    load_table(spark, sf, "benchmark").write.parquet(f"{tmp_path}/benchmark.parquet")
    sf = str(tmp_path)
    docs = load_table(spark, sf, "documents")
    assert [n for n, _ in corpus_pipeline.STAGES] == ["language", "near_duplicates", "decontamination", "secrets", "packing"]
    kept, columns = docs, docs.columns
    for _, stage in corpus_pipeline.STAGES[:-1]:
        kept = stage(spark, kept, sf)
        assert kept.columns == columns
    # The same by plain loops over texts; only the trained language model is taken from the library.
    model, threshold = language.fit(docs)
    named = {r["doc_id"] for r in language.predict(docs, model, threshold).where("not rejected").collect()}
    rows = sorted((i, t) for i, t in texts_of(docs) if i in named)
    own = {i: shingles_of(t) for i, t in rows}
    lead: dict[int, int] = {}
    parent = {i: i for i, _ in rows}

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for n, (i, t) in enumerate(rows):
        for j, u in rows[:n]:
            a, b = own[i], own[j]
            if t == u or (a and b and min(a.total(), b.total()) >= 0.8 * max(a.total(), b.total()) and (a & b).total() >= 0.8 * (a | b).total()):
                x, y = sorted((find(i), find(j)))
                parent[y] = x
    lead = {i: t for i, t in rows if find(i) == i}
    held = item_windows(load_table(spark, sf, "benchmark"))
    clean = {i: t for i, t in lead.items() if not contaminated(words(t), held)}
    masked = {i: masked_by_hand(t) for i, t in clean.items()}
    assert len(named) <= docs.count() - 3 and len(lead) < len(named) and len(clean) < len(lead) and any(masked[i] != clean[i] for i in clean)
    from tokenizers import Tokenizer

    tokenizer = Tokenizer.from_file(TOKENIZER)
    want = {i: np.array(tokenizer.encode(t, add_special_tokens=False).ids + [1], "<u4") for i, t in masked.items()}
    pieces = corpus_pipeline.run(spark, sf).collect()
    assert {r["doc_id"] for r in pieces} == set(want)
    assert sum(r["length"] for r in pieces) == sum(map(len, want.values()))
    for r in pieces:
        ids = want[r["doc_id"]]
        assert r["doc_tokens"] == len(ids) and r["ids_crc32"] == zlib.crc32(ids[r["start"] : r["start"] + r["length"]].tobytes())


def test_models_are_fitted_in_a_task(spark, sf, monkeypatch):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    texts, labels = classify.sample(docs.where(~classify.held_out("doc_id", language.FOLDS, language.FOLD)), "lang")
    want, threshold = language._calibrated(texts, labels)

    driver, train = os.getpid(), classify.train

    def elsewhere(*texts_and_labels):
        assert os.getpid() != driver
        return train(*texts_and_labels)

    monkeypatch.setattr(classify, "train", elsewhere)
    got, same = language.fit(docs)
    assert got.classes == want.classes and same == threshold and (got.table == want.table).all()
    monkeypatch.undo()
    assert language.fit(docs.where("false"))[0].classes == []


def test_overlaps_of_a_bucket_are_held_in_strips():
    import tracemalloc

    rng = np.random.default_rng(2)

    def linked(x, y, least=0.8):
        (xc, xt), (yc, yt) = x, y
        _, i, j = np.intersect1d(xc, yc, return_indices=True)
        both = np.minimum(xt[i], yt[j]).sum()
        return both >= least * (xt.sum() + yt.sum() - both)

    def classes_of(n, pairs):
        label = list(range(n))
        for a, b in pairs:
            label = [label[a] if x == label[b] else x for x in label]
        return [label.index(x) for x in label]

    base = [rng.integers(1, 1 << 60, 30).astype(np.uint64) for _ in range(25)]
    parts = []
    for i in range(300):
        codes = np.unique(np.where(rng.random(30) < 0.08, rng.integers(1, 1 << 60, 30).astype(np.uint64), base[i % 25]))
        parts.append((codes, rng.integers(1, 4, len(codes)) if i % 3 else np.ones(len(codes), np.int64)))
    links = list(zip(*neardup._forest(parts, 0.8)))
    want = [(a, b) for a in range(300) for b in range(a) if linked(parts[a], parts[b])]
    assert len(links) < 300 and all(linked(parts[a], parts[b]) for a, b in links) and classes_of(300, links) == classes_of(300, want)

    far = [(np.unique(np.concatenate([rng.integers(1, 1 << 60, 20), rng.integers(1, 50, 20)]).astype(np.uint64)),) for _ in range(3000)]
    tracemalloc.start()
    assert neardup._forest([(c, np.ones(len(c), np.int64)) for (c,) in far], 0.8) == ([], [])
    assert tracemalloc.get_traced_memory()[1] < 30_000_000  # all pairs would be 36 MB and their bounds as much again
    tracemalloc.stop()
