"""The operators against brute force, exact round trips and hand-made cases."""

import hashlib
import itertools
import math
import random
import unicodedata
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from conftest import SF
from pyspark.sql import functions as F

from privfreq.llm import common, decontaminate, fingerprints, lines, near, packing, pii, quality, secrets, suffix_tree, toxicity

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint"


def documents(spark, texts, first=0):
    return spark.createDataFrame([(i, t, "en", "s", None if t is None else len(t)) for i, t in enumerate(texts, first)], SCHEMA)


@pytest.fixture(scope="module")
def docs(spark):
    return common.read(spark, SF, "documents")


@pytest.fixture(scope="module")
def labels(spark):
    return common.read(spark, SF, "labels")


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls everywhere, empty and long texts, ties, repeated rows, and extra columns with clashing names."""
    long = " ".join(f"word{i % 997} of" for i in range(60_000))
    rows = [(1, None), (2, ""), (3, "  \n\t "), (4, "a"), (5, long), (6, "same text here now and then"), (6, "same text here now and then"), (7, "same text here now and then"), (None, "no id"), (None, None), (8, "x\ny\nz\nx\ny\nz")]
    df = spark.createDataFrame([(i, t, None, None, None) for i, t in rows], SCHEMA)
    clash = ("score", "terms", "node", "comp", "key", "label", "piece", "length", "d", "k", "first", "solid", "bucket", "held_out", "words", "a", "b")
    return df.withColumns({c: F.lit(c) for c in clash})


# packing


def brute_best_fit(lengths, capacity):
    gaps = []
    for n in sorted(lengths, reverse=True):
        fit = [g for g in gaps if g >= n]
        if fit:
            gaps.remove(min(fit))
            gaps.append(min(fit) - n)
        else:
            gaps.append(capacity - n)
    return len(gaps)


@pytest.mark.parametrize("seed", range(8))
def test_plan_is_best_fit(seed):
    rng = random.Random(seed)
    lengths = [rng.choice((rng.randint(1, 60), 17, 64)) for _ in range(rng.randint(1, 300))]
    runs, opened = packing.plan_best_fit(Counter(lengths), 64)
    assert opened == brute_best_fit(lengths, 64)
    used = defaultdict(list)
    for n, rank, count, first, each, offset in runs.tolist():
        for i in range(count):
            used[first + i // each].append((offset + i % each * n, n))
    assert sum(len(v) for v in used.values()) == len(lengths)
    for places in used.values():
        at = 0
        for start, n in sorted(places):
            assert start == at
            at += n
        assert at <= 64


def test_packing_round_trip(spark, docs):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(packing.vocabulary_path())
    out = packing.pack_documents(docs).toPandas()
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    for doc, rows in out.groupby("doc_id"):
        ids = np.array([*t.encode(texts[doc], add_special_tokens=False).ids, 1], "<u4").tobytes()
        rows = rows.sort_values("piece")
        assert rows["start"].tolist() == [4096 * i for i in range(len(rows))]
        for r in rows.itertuples():
            assert zlib.crc32(ids[4 * r.start : 4 * (r.start + r.length)]) == r.ids_crc32
        assert rows["length"].sum() * 4 == len(ids)
    for _, rows in out.groupby("sequence_id"):
        rows = rows.sort_values("offset")
        assert rows["offset"].tolist() == [0, *rows["length"].cumsum().tolist()[:-1]] and rows["length"].sum() <= 4096
    assert out["sequence_id"].nunique() <= math.ceil(out["length"].sum() / 4096) * 1.02 + 1


def test_encoder_equals_tokenizer():
    e = packing.Encoder(packing.vocabulary_path())
    rng, alphabet = random.Random(3), "ab'sTtre vem'll 12_-.É ßİſŉ²½ª\x1c\x85\xa0\n<|endoftext|>"
    for _ in range(2000):
        s = "".join(rng.choice(alphabet) for _ in range(rng.randint(0, 14)))
        assert e.ids(s) == e.whole(s).tobytes()


def test_packing_refuses_bad_lengths(spark):
    with pytest.raises(ValueError):
        packing.pack(spark.createDataFrame([(1, 0, 0, 5000, 0)], packing.PIECES))


# personal data


def test_pii_disguises():
    cases = {
        "write to john (at) example (dot) com now": ("email", "john (at) example (dot) com"),
        "john at example dot com": ("email", "john at example dot com"),
        "x four zero one two eight eight eight eight eight eight eight eight one eight eight one": ("card", "four zero one two eight eight eight eight eight eight eight eight one eight eight one"),
        "mail іvаn@exаmple.com": ("email", "іvаn@exаmple.com"),
        "card ４０１２８８８８８８８８１８８１": ("card", "４０１２８８８８８８８８１８８１"),
    }
    for text, (kind, want) in cases.items():
        base, found = pii.all_spans(text)
        assert want in [text[a:b] for a, b in found[kind]], text
        assert set(base[kind]) <= set(found[kind])


def test_pii_each_disguise_alone():
    cases = {
        "john AT example.com": ("email", "john AT example.com"),
        "at one nine two dot one six eight dot one dot one now": ("ip", "one nine two dot one six eight dot one dot one"),
        "one zero dot zero dot zero dot one": ("ip", "one zero dot zero dot zero dot one"),
        "“one zero (dot) zero [.] zero dot one”": ("ip", "one zero (dot) zero [.] zero dot one"),
        "call plus one three zero one five five five zero three four six": ("phone", "plus one three zero one five five five zero three four six"),
    }
    for text, (kind, want) in cases.items():
        _, found = pii.all_spans(text)
        assert want in [text[a:b] for a, b in found[kind]], text
    assert pii.all_spans("one plus one is two, one point five")[1] == {k: [] for k in pii.KINDS}


def test_pii_leaves_plain_text_alone():
    for text in ("One of two or three dots at home.", "un deux trois", "meet at noon (at the dot)", "1.2.3.4.5 +1 23"):
        base, found = pii.all_spans(text)
        assert base == found, text
    assert pii.plain_spans("999.1.1.1 1.2.3.4")["ip"] == [(10, 17)]


def brute_spans(text, kind):
    """Leftmost, longest, non-overlapping matches by trying every start and end."""
    import regex

    full, at, out = regex.compile(pii.PATTERNS[kind].pattern), 0, []
    while at < len(text):
        end = next((j for j in range(len(text), at, -1) if full.fullmatch(text, at, j)), None)
        if end is None:
            at += 1
            continue
        digits = [int(c) for c in text[at:end] if c in "0123456789"]
        doubled = [d if i % 2 == 0 else sum(divmod(2 * d, 10)) for i, d in enumerate(reversed(digits))]
        good = {"email": True, "ip": all(int(p or 0) <= 255 for p in text[at:end].split(".")) if kind == "ip" else True, "card": 13 <= len(digits) <= 19 and sum(doubled) % 10 == 0, "phone": 9 <= len(digits) <= 15}[kind]
        if good:
            out.append((at, end))
        at = end
    return out


def test_plain_spans_against_brute_force():
    rng = random.Random(11)
    pools = {"email": "ab1.-@ _", "ip": "0125..x ", "card": "4028 -x", "phone": "+12 ().-x"}
    hits = Counter()
    for _ in range(1500):
        kind = rng.choice(pii.KINDS)
        text = "".join(rng.choice(pools[kind]) for _ in range(rng.randint(5, 45)))
        if kind == "card" and rng.random() < 0.5:
            text += " 4012 8888 8888 1881 " + text[:4]
        if kind == "phone" and rng.random() < 0.5:
            text += "+" + "".join(str(rng.randint(0, 9)) + rng.choice(("", " ", "-", "(", ".")) for _ in range(rng.randint(7, 17))) + "x"
        if kind == "ip" and rng.random() < 0.5:
            text += ".".join(str(rng.randint(0, 300)) for _ in range(rng.randint(3, 6)))
        for k in pii.KINDS:
            want = brute_spans(text, k)
            assert pii.plain_spans(text)[k] == want, text
            hits[k] += len(want)
    assert min(hits.values()) > 30


NAMES = "zero one two three four five six seven eight nine".split()
GERMAN = "null eins zwei drei vier fünf sechs sieben acht neun".split()


def disguise(kind, rng):
    """A disguised identifier, and the text that is to be found."""
    twins = {v: k for k, v in pii.LOOKALIKES.items()}
    user, host, top = (rng.choice(x) for x in (("john.doe", "info", "anna-b"), ("example", "mail-box", "acme"), ("com", "org", "net")))
    digits = {"card": "4012888888881881", "phone": f"{rng.randint(1, 9)}{rng.randint(10**9, 10**10 - 1)}"}.get(kind, "")
    if kind == "email":
        at, dot = rng.choice((" (at) ", "[at]", " {AT} ", " <at> ", " AT ")), rng.choice((" (dot) ", "[dot]", ".", " [.] "))
        return rng.choice((f"{user}{at}{host}{dot}{top}", f"{user} at {host} dot {top}", f"{user}@{host}".replace("o", twins["o"]).replace("a", twins["a"]) + f".{top}"))
    if kind == "ip":
        parts = [str(rng.randint(0, 255)) for _ in range(4)]
        names = rng.choice((NAMES, GERMAN))
        return rng.choice((" dot ", " (dot) ", " [.] ")).join(" ".join(names[int(c)] for c in p) for p in parts)
    wide = "".join(chr(0xFF10 + int(c)) for c in digits)
    spelled = " ".join(rng.choice((NAMES, GERMAN))[int(c)] for c in digits)
    return {"card": rng.choice((wide, spelled)), "phone": rng.choice(("+" + wide, "plus " + spelled))}[kind]


@pytest.mark.parametrize("kind", pii.KINDS)
def test_disguises_are_found_and_plain_text_is_not(kind):
    rng = random.Random(kind)
    filler = "the report was read at home. In 1990 we met at the station, one or two of us; look at google.com now. Drei von vier, seven days a week".split()
    found = clean = 0
    for _ in range(200):
        before, after = (" ".join(rng.choice(filler) for _ in range(rng.randint(0, 12))) for _ in range(2))
        hidden = disguise(kind, rng)
        text = f"{before} | {hidden} | {after}"
        _, spans = pii.all_spans(text)
        found += hidden in [text[a:b] for a, b in spans[kind]]
        plain = f"{before} | {after} х (dot) х"
        clean += pii.all_spans(plain)[0] == pii.all_spans(plain)[1]
    assert found >= 190 and clean == 200


def test_a_sign_far_away_changes_nothing():
    for text in ("look at google.com now", "he sat at home.In 1990", "meet me at the dot matrix", "One. Two. Three. Four.", "we look at the dot com"):
        for more in ("", " х", " (dot)", " plus one two three", "​"):
            base, found = pii.all_spans(text + more)
            assert base == found, text + more


def test_pii_masks(spark):
    got = pii.masked(documents(spark, ["me@x.org or +1 (301) 555-0346"])).first()["text"]
    assert got == "[email] or [phone]"


# near-duplicates


def brute_components(texts, width, percent):
    def shingles(t):
        w = t.encode().lower().split()
        return {tuple(w[i : i + width]) for i in range(max(1, len(w) - width + 1))} if w else set()

    sets = {i: shingles(t or "") for i, t in texts.items()}
    comp = {i: i for i in sets}
    for a, b in itertools.combinations(sorted(sets), 2):
        both = len(sets[a] & sets[b])
        if sets[a] and sets[b] and 100 * both >= percent * (len(sets[a]) + len(sets[b]) - both):
            old, new = max(comp[a], comp[b]), min(comp[a], comp[b])
            comp = {i: new if c == old else c for i, c in comp.items()}
    return comp, {i: len(s) for i, s in sets.items()}


@pytest.mark.parametrize("width", [2, 5])
def test_near_duplicates_against_brute_force(spark, docs, width):
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    comp, n = brute_components(texts, width, 80)
    got = {r["doc_id"]: r for r in near.near_duplicates(docs, width).collect()}
    assert {i: r["component_id"] for i, r in got.items()} == comp
    assert {i: r["n_shingles"] for i, r in got.items()} == n
    assert all(r["kept"] == (i == comp[i]) for i, r in got.items())


def test_near_chain_of_edits(spark):
    """A chain whose ends are unlike is one component; a hot group of copies too."""
    words = [f"w{i}" for i in range(100)]
    chain = []
    for i in range(12):
        words = words[3:] + [f"n{i}a", f"n{i}b", f"n{i}c"]
        chain.append(" ".join(words))
    out = near.near_duplicates(documents(spark, chain + ["same " * 30] * 50), 2).collect()
    assert {r["component_id"] for r in out} == {0, 12}


def test_star_components_equal_one_task(spark):
    rng = random.Random(5)
    pairs = [(rng.randint(0, 60), rng.randint(0, 60)) for _ in range(45)]
    edges = spark.createDataFrame(pairs, "a bigint, b bigint")
    want = {r["node"]: r["comp"] for r in near.components(edges).collect() if r["node"] != r["comp"]}
    got = {r["node"]: r["comp"] for r in near.star_components(edges).collect() if r["node"] != r["comp"]}
    assert got == want


def test_min_max_estimates_similarity():
    rng = np.random.default_rng(1)
    x = rng.integers(0, 2**63, 1000).astype(np.uint64)
    a, b = np.unique(x[:900]), np.unique(x[100:])
    table = near.permutation_table(400)
    same = (near.min_max_signature(a, table) == near.min_max_signature(b, table)).mean()
    assert abs(same - 0.8) < 0.05


# fingerprints


def test_fingerprints_estimate(spark, docs):
    out = {r["doc_id"]: r for r in fingerprints.edited_likeness(docs).collect()}
    rows = [(r["doc_id"], r["text"]) for r in docs.orderBy("doc_id").collect()]

    def sh(t):
        w = t.encode().lower().split()
        return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()

    for n, (i, t) in enumerate(rows):
        following = rows[(n + 1) % len(rows)][1]
        e = fingerprints.edit(t, following)
        a, b = sh(t), sh(e)
        assert out[i]["edited_sha256"] == hashlib.sha256(e.encode()).hexdigest() and out[i]["n_chars"] == len(t)
        c = sh(following)
        assert abs(out[i]["near_edited"] - len(a & b) / max(1, len(a | b))) < 0.2
        assert abs(out[i]["near_next"] - (len(a & c) / len(a | c) if a | c else 1)) < 0.2
        assert abs(out[i]["held_by_edited"] - (len(a & b) / len(a) if a else 1)) < 0.25
        assert abs(out[i]["n_distinct"] - len(a)) <= 0.4 * len(a)


def test_fingerprints_merge(spark):
    keyed = common.Keyed()
    a = b"one two three four five six seven eight"
    b = b"four five six seven eight nine ten"
    x, y = (fingerprints.sketch(t, keyed, 8) for t in (a, b))
    assert (fingerprints.merge(x, y, 8) == fingerprints.merge(y, x, 8)).all()
    assert fingerprints.resemblance(x, y, 99) == pytest.approx(1 / 6)
    assert fingerprints.containment(y, x, 99) == pytest.approx(1 / 3)
    big = np.unique(np.random.default_rng(2).integers(0, 2**64, 50_000, dtype=np.uint64))
    assert abs(fingerprints.distinct(big[:128], 128) / 50_000 - 1) < 0.3
    prints = fingerprints.fingerprints(documents(spark, [a.decode(), b.decode()])).withColumn("g", F.lit(1))
    merged = fingerprints.merged(prints, "g").collect()
    assert len(merged) == 1 and len(fingerprints.from_text(merged[0]["fingerprint"])) == 6


# lines


def brute_lines(texts):
    seen, out = set(), {}
    for i in sorted(texts):
        all_lines = texts[i].split("\n")
        solid = [(n, x.strip(" ")) for n, x in enumerate(all_lines) if x.strip(" ")]
        gone = set()
        for at in range(len(solid) - 2):
            key = tuple(x for _, x in solid[at : at + 3])
            if key in seen:
                gone |= {n for n, _ in solid[at : at + 3]}
            seen.add(key)
        out[i] = "\n".join(x for n, x in enumerate(all_lines) if n not in gone)
    return out


def test_lines_against_brute_force(spark, docs):
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    got = {r["doc_id"]: r["text"] for r in lines.without_repeats(docs).collect()}
    assert got == brute_lines(texts)


def test_lines_by_hand(spark):
    texts = ["a\nb\nc\nd", "x\na\nb\n\nc\ny", "a\na\na\na\na", "a\nb", "b\nc\nd\ne"]
    got = {r["doc_id"]: r["text"] for r in lines.without_repeats(documents(spark, texts)).collect()}
    assert got == brute_lines(dict(enumerate(texts)))
    assert got[1] == "x\n\ny" and got[2] == "a" and got[3] == "a\nb" and got[4] == "e"


def test_lines_sql(spark):
    import duckdb

    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{SF}/documents.parquet'")
    want = sorted(con.execute(lines.OP8_SQL).fetchall())
    assert sorted(map(tuple, lines.op8_three_line_windows(spark, SF).collect())) == want


# decontamination


def test_alignment_by_brute_force():
    rng = np.random.default_rng(4)
    for _ in range(30):
        a, b = rng.integers(0, 4, rng.integers(1, 9)), rng.integers(0, 4, rng.integers(1, 12))
        t = np.zeros((len(a) + 1, len(b) + 1), int)
        for i in range(1, len(a) + 1):
            for j in range(1, len(b) + 1):
                t[i, j] = max(0, t[i - 1, j - 1] + (2 if a[i - 1] == b[j - 1] else -1), t[i - 1, j] - 1, t[i, j - 1] - 1)
        assert decontaminate.align(a, b)[0] == t.max()


def edited(item, rng, vocabulary, how, rate):
    out = []
    for i, w in enumerate(item):
        kind = how if how != "mixed" else rng.choice(("replaced", "added", "left_out"))
        if rng.random() >= rate if rate < 1 else i % 3 != 2:
            out.append(w)
        elif kind == "replaced":
            out.append(rng.choice(vocabulary))
        elif kind == "added":
            out += [w, rng.choice(vocabulary)]
    return out


@pytest.mark.parametrize("how,rate", [("replaced", 1), ("replaced", 0.25), ("added", 0.5), ("left_out", 0.2), ("mixed", 0.3)])
def test_leak_recall_against_aligning_everything(how, rate):
    """Copies with edits: of all passages whose full alignment is a leak, nearly all are found by their seeds (rate 1: every third word)."""
    rng = random.Random(f"{how}{rate}")
    vocabulary = [f"w{int(rng.paretovariate(0.6)) % 20000}".encode() for _ in range(20_000)]
    items = [(n, [rng.choice(vocabulary) for _ in range(rng.randint(12, 60))]) for n in range(60)]
    counts = Counter(vocabulary)
    index = decontaminate.SeedIndex(items, {w: c / len(vocabulary) for w, c in counts.items()})
    want = found = 0
    for n, (_, item) in enumerate(items):
        text = [rng.choice(vocabulary) for _ in range(80)] + edited(item, rng, vocabulary, how, rate) + [rng.choice(vocabulary) for _ in range(80)]
        a, own = np.array([index.ids.get(w, 0) for w in text], np.int64), index.items[n][1]
        if decontaminate.align(own, a)[0] >= decontaminate.LEAK * 2 * len(own):
            want += 1
            found += any(decontaminate.align(own, a[lo:hi])[0] >= decontaminate.LEAK * 2 * len(own) for m, lo, hi in index.passages(a) if m == n)
    assert want >= 40 and found >= 0.95 * want


def test_a_very_long_item_is_aligned_in_little_memory():
    import tracemalloc

    rng = np.random.default_rng(3)
    item = rng.integers(1, 5000, 20_000)
    passage = np.concatenate([rng.integers(1, 5000, 3000), np.delete(item, np.arange(0, 20_000, 10)), rng.integers(1, 5000, 3000)])
    tracemalloc.start()
    score, first, last, matched = decontaminate.align(item, passage)
    assert tracemalloc.get_traced_memory()[1] < 50_000_000
    tracemalloc.stop()
    assert matched >= 18_000 and 0 <= first - 3000 < 20 and abs(last - 21_000) < 20 and score >= 2 * 18_000 - 2100


def test_leaks_exact_and_edited(spark):
    rng = random.Random(9)
    vocabulary = [f"w{i}" for i in range(3000)]
    item = [rng.choice(vocabulary) for _ in range(40)]
    edited = [w if i % 6 else "changed" for i, w in enumerate(item)]
    noise = lambda n: [rng.choice(vocabulary) for _ in range(n)]
    texts = [" ".join(noise(80) + item + noise(50)), " ".join(noise(30) + edited + noise(90)), " ".join(noise(200)), " ".join(item[:8] + noise(100))]
    benchmark = spark.createDataFrame([(5, " ".join(item)), (6, None), (None, "x y z"), (7, "too short")], "item_id bigint, text string")
    got = {r["doc_id"]: r for r in decontaminate.leaks(documents(spark, texts), benchmark).collect()}
    assert set(got) == {0, 1} and got[0]["score"] == 1.0 and got[0]["first_word"] == 80 and got[0]["last_word"] == 119
    assert 0.5 < got[1]["score"] < 0.9


def test_leaks_on_the_given_tables(spark, docs):
    benchmark = common.read(spark, SF, "benchmark")
    got = {(r["doc_id"], r["item_id"]) for r in decontaminate.leaks(docs, benchmark).collect()}
    items = benchmark.collect()
    exact = {(d["doc_id"], i["item_id"]) for d in docs.collect() for i in items if i["text"] in d["text"]}
    assert exact <= got and len(got - exact) <= len(exact)


# classifiers


def test_block_max_index_is_exact():
    rng = np.random.default_rng(6)
    n, width = 700, 300
    rows = [np.sort(rng.choice(width, rng.integers(1, 12), replace=False)) for _ in range(n)]
    row, term = np.repeat(np.arange(n), [len(r) for r in rows]), np.concatenate(rows)
    w = rng.random(len(term))
    w = (w / np.sqrt(np.bincount(row, w * w))[row]).astype(np.float32)
    index = toxicity.BlockMaxIndex(n, row, term, w, width, rng.permutation(n), 16, 40)
    dense = np.zeros((n, width))
    dense[row, term] = w
    own = np.arange(60)
    for skip in (None, own):
        scores = dense[:60] @ dense.T
        if skip is not None:
            scores[own, own] = -1
        ids, cosines = index.nearest(row[row < 60], term[row < 60], w[row < 60], 60, 9, skip)
        for q in range(60):
            want = -np.sort(-scores[q])[:9]
            want = want[want > 0]
            found = ids[q] >= 0
            assert found.sum() == len(want) and np.allclose(cosines[q][found], want, atol=2e-6)
            assert np.allclose(scores[q][ids[q][found]], cosines[q][found], atol=2e-6)


def test_toxicity_weights_are_tf_idf(spark, docs, labels):
    """Every word of a text counts, in its vector's norm too; document frequencies are the corpus's."""
    judge = toxicity.learned(docs, labels, "toxic", F.lit(False), 50, 5)
    texts = [r["text"].encode() for r in docs.collect()]
    words = [Counter(x for w in t.lower().split() if (x := w.strip(toxicity.STRIP))) for t in texts]
    df = Counter(w for c in words for w in c)
    hashed = dict(zip(df, (common.word_hashes(list(df))[1] >> np.uint64(12)).view(np.int64).tolist()))
    assert len(hashed) == len(df)
    relevance = dict(zip(judge.weighting.terms.tolist(), judge.weighting.relevance.tolist()))
    row, term, count, weight = judge.weighting.unit(*toxicity.flat(texts[:40]), 40)
    for i in range(40):
        full = {hashed[w]: (1 + math.log(n)) * (math.log((1 + len(texts)) / (1 + df[w])) + 1) * relevance.get(hashed[w], toxicity.FLOOR) for w, n in words[i].items()}
        norm = math.sqrt(sum(x * x for x in full.values()))
        got = dict(zip(judge.weighting.terms[term[row == i]].tolist(), weight[row == i].tolist()))
        assert set(got) == set(full) & set(relevance) and all(got[t] == pytest.approx(full[t] / norm, rel=1e-4) for t in got)


def test_word_hashes():
    rng = random.Random(1)
    texts = [bytes(rng.choice(b"ab. ,\n\tXY\xc3\xa9") for _ in range(rng.randint(0, 30))) for _ in range(300)]
    for edges in (b"", b".,"):
        row, h = common.word_hashes(texts, edges)
        want = [(i, x) for i, t in enumerate(texts) for w in t.lower().split() if (x := w.strip(edges) if edges else w)]
        assert row.tolist() == [i for i, _ in want]
        named = {}
        assert all(named.setdefault(w, x) == x for (_, w), x in zip(want, h.tolist())) and len(set(named.values())) == len(named)


MIDDLE, LARGE = "/root/testdata/sf0.01", "/root/testdata/sf0.1"


def ranking(scored, labels, column, out):
    """Area under the ROC curve, share of label 1 and of label 0 that is predicted so, over held-out rows."""
    rows = scored.join(labels, "doc_id").where(out).select("score", column).collect()
    s, y = np.array([r["score"] for r in rows]), np.array([r[column] for r in rows])
    good, bad = s[y == 1], s[y == 0]
    area = (good[:, None] > bad).mean() + (good[:, None] == bad).mean() / 2
    return area, (good >= 0.3).mean(), (bad < 0.3).mean()


def test_quality_held_out(spark):
    out, labels = common.remainder(5) == 0, common.read(spark, MIDDLE, "labels")
    area, kept, dropped = ranking(quality.score(common.read(spark, MIDDLE, "documents"), labels, "quality", out), labels, "quality", out)
    assert area > 0.9 and kept > 0.9 and dropped > 0.6


def test_toxicity_held_out(spark):
    out, labels = common.remainder(4) == 2, common.read(spark, LARGE, "labels")
    area, found, alone = ranking(toxicity.score(common.read(spark, LARGE, "documents"), labels, "toxic", out), labels, "toxic", out)
    assert area > 0.977 and found > 0.9 and alone > 0.97


@pytest.mark.parametrize("level", [0.0, 0.1, 0.37, 0.5, 1.0])
def test_quantiles_are_exact(spark, level):
    rng = np.random.default_rng(9)
    x = np.concatenate([rng.normal(size=700), np.full(200, 0.25), rng.normal(size=300) * 1e-9 + 3])
    df = spark.createDataFrame([(float(v),) for v in x], "x double")
    rank = max(1, math.ceil(level * len(x)))
    low, high = quality.order_statistics(df, "x", rank, 16)
    s = np.sort(x)
    assert low == s[rank - 1] and high == s[min(rank, len(x) - 1)]


def test_quality_cuts_at_the_quantile_asked_for(spark, docs, labels):
    got = quality.score(docs, labels, level=0.3)
    assert got.where("score < 0.3").count() == pytest.approx(0.3 * got.count(), abs=1.01)


def test_pairs_fit():
    rng = np.random.default_rng(8)
    x = rng.normal(size=(400, 3))
    d = x * np.sign(x @ [2.0, -1.0, 0.0])[:, None]
    w = quality.fit_pairs(d)
    assert w[0] > 0 > w[1] and abs(w[2]) < abs(w[0]) / 3


def test_classifiers_without_labels(spark, docs, labels):
    none = labels.where("false")
    assert toxicity.score(docs, none, "toxic").agg(F.max("score")).first()[0] == 0.0
    assert quality.score(docs, none).agg(F.min("score")).first()[0] == 1.0


def test_leak_of_an_accented_item_in_capitals(spark):
    item = "Élodie prüft über Größe und Maß señor año déjà vécu naïve façade crème brûlée œuvre"
    decomposed = unicodedata.normalize("NFD", item)
    texts = [f"vorher {item.upper()} nachher", f"avant “{decomposed}” après", "Élodie und nichts weiter"]
    bench = spark.createDataFrame([(1, item)], "item_id long, text string")
    got = {r["doc_id"]: (r["score"], r["first_word"], r["last_word"]) for r in decontaminate.leaks(documents(spark, texts), bench).collect()}
    n = len(item.split())
    assert got == {0: (1.0, 1, n), 1: (1.0, 1, n)}


# suffix tree


def brute_tree(texts, learns, depth):
    """log10 probabilities by dictionaries of word tuples, and every state's next-word distribution."""
    end, start = "END", "START"
    tokens = [[*t.encode().lower().split(), end] for t in texts]
    training = [[start, *x] for x, y in zip(tokens, learns) if y]
    counts = [Counter() for _ in range(depth + 1)]  # counts[d]: (context of d words, word)
    for x in training:
        for i in range(1, len(x)):
            for d in range(min(depth, i) + 1):
                counts[d][tuple(x[i - d : i + 1])] += 1
    total, kinds = sum(counts[0].values()), len(counts[0])
    seen = [Counter() for _ in range(depth + 1)]
    for d in range(1, depth + 1):
        for run, c in counts[d].items():
            seen[d][run[:-1]] += c
    states = [{} for _ in range(depth + 1)]

    def p(context, word):
        if not context:
            return (counts[0][(word,)] + 1) / (total + kinds + 1)
        shorter = p(context[1:], word)
        if context not in states[len(context)]:
            return shorter
        c, n = counts[len(context)][(*context, word)], seen[len(context)][context]
        return (c - suffix_tree.DISCOUNT) / n * (c >= 2) + states[len(context)][context] * shorter

    for d in range(1, depth + 1):
        by = defaultdict(dict)
        for run, c in counts[d].items():
            by[run[:-1]][run[-1]] = c
        for context, following in by.items():
            n = seen[d][context]
            twice = {w: c for w, c in following.items() if c >= 2}
            if n < 2 or not twice:
                continue
            rest = max(1e-9, 1 - sum(c - suffix_tree.DISCOUNT for c in twice.values()) / n)
            gain = sum(c * math.log((c - 1 - suffix_tree.DISCOUNT) / (n - 1) / p(context[1:], w)) for w, c in twice.items())
            if gain + (n - sum(twice.values())) * math.log(rest) > math.log(n) / 2:
                states[d][context] = rest
    out = []
    for x in tokens:
        full = [start, *x]
        out.append(sum(math.log10(p(tuple(full[max(0, i - depth) : i]), full[i])) for i in range(1, len(full))))
    return out, p, states, [w for (w,) in counts[0]]


@pytest.mark.parametrize("depth", [1, 2, 3])
def test_suffix_tree_against_brute_force(spark, docs, depth):
    out = common.remainder(7) == 2
    rows = sorted((r["doc_id"], r["text"]) for r in docs.collect())
    learns = [zlib.crc32(str(i).encode()) % 7 != 2 for i, _ in rows]
    want, _, states, _ = brute_tree([t for _, t in rows], learns, depth)
    assert all(states[d] for d in range(1, depth + 1))
    got = {r["doc_id"]: r["score"] for r in suffix_tree.text_scores(docs, out, depth, 60_000).collect()}
    assert max(abs(got[i] - w) / abs(w) for (i, _), w in zip(rows, want)) < 1e-5


def test_suffix_tree_counts_and_base(spark, docs):
    out = common.remainder(7) == 2
    got = {r["doc_id"]: r for r in suffix_tree.text_scores(docs, out).collect()}
    tokens = {r["doc_id"]: r["text"].encode().lower().split() for r in docs.collect()}
    train = [i for i in tokens if zlib.crc32(str(i).encode()) % 7 != 2]
    counts = Counter(w for i in train for w in tokens[i])
    n, v = sum(counts.values()) + len(train), len(counts) + 1
    for i, ws in tokens.items():
        base = sum(math.log10((counts[w] + 1) / (n + v + 1)) for w in ws) + math.log10((len(train) + 1) / (n + v + 1))
        r = got[i]
        assert r["base_score"] == pytest.approx(base, rel=1e-9) and r["n_known"] == sum(counts[w] > 0 for w in ws) + 1
        assert r["n_tokens"] == len(ws) + 1 and r["train_tokens"] == n and r["held_out"] == (i not in train)


def test_suffix_tree_is_a_distribution():
    texts = ["a b a b a b c", "b a b a c", "a b c a b c x y"] * 20
    _, p, states, words = brute_tree(texts, [True] * len(texts), 2)
    assert states[1] and states[2]
    for context in [*states[1], *states[2], ("never",)]:
        assert sum(p(context, w) for w in words) + p(context, "unknown") == pytest.approx(1.0)


@pytest.mark.parametrize("sf", ["sf0.01", "sf0.1"])
def test_held_out_texts_are_likelier_than_by_their_words_alone(spark, sf):
    scored = suffix_tree.op7_suffix_tree(spark, f"/root/testdata/{sf}").where("held_out")
    r = scored.agg((F.sum("score") / F.sum("n_tokens")).alias("tree"), (F.sum("base_score") / F.sum("n_tokens")).alias("base")).first()
    assert r["tree"] > r["base"] + 0.05


def test_suffix_tree_keeps_rare_contexts_however_large_the_corpus(spark):
    rare, common_ = "zqxj vvkw zqxj vvkw", " ".join(["plain words of a long text"] * 300)
    docs = documents(spark, [rare, rare] + [common_] * 100)
    got = {r["doc_id"]: r for r in suffix_tree.text_scores(docs, F.lit(False), 2, 100_000).collect()}
    assert got[0]["score"] == pytest.approx(got[1]["score"]) and got[0]["score"] > got[0]["base_score"] / 2


def test_packed_arrays_are_small_and_whole():
    rng = np.random.default_rng(3)
    keys = np.unique(rng.integers(0, 1 << 46, 20_000, dtype=np.uint64))
    assert len(suffix_tree.packed(keys, 1)) < 4.6 * len(keys)  # 5 bytes a key before
    for values, kind, columns in ((rng.poisson(1.0, 5000).astype("<u4"), "<u4", 1), (rng.random((70, 3)).astype("<f4"), "<f4", 3), (np.zeros(0, "<u4"), "<u4", 1)):
        assert (suffix_tree.expanded(suffix_tree.squeezed(values), kind, columns) == values).all()
    assert len(suffix_tree.squeezed(np.ones(5000, "<u4"))) < 100


def test_packed_hashes():
    for level in (0, 1, -1, -2):
        keys = np.unique(common.mix(np.arange(5000, dtype=np.uint64)) >> np.uint64(64 - suffix_tree.bits(level)))
        for buckets in (64, 1024):
            cuts = (keys >> np.uint64(suffix_tree.bits(level) - buckets.bit_length() + 1)).astype(int)
            for b in np.unique(cuts)[:20]:
                part = keys[cuts == b]
                assert (suffix_tree.unpacked(suffix_tree.packed(part, level), level, int(b), buckets) == part).all()


# secrets


def test_secrets_found_and_false_positives_removed(spark):
    key = hashlib.sha1(b"1").hexdigest()
    texts = [f'then token = "{key}" and on', f"commit {key} fixed it", "uuid 123e4567-e89b-42d3-a456-426614174000 of", "see /usr/lib/python3/dist-packages/thing2.py now", 'api_key = "xxxxxxxxxxxxxxxxxxxxxxxx"', "plain 9807915762804490 number"]
    got = {(r["doc_id"], r["value"]): r["predicted"] for r in secrets.secrets(documents(spark, texts)).collect()}
    assert got[(0, key)] == 1 and got[(1, key)] == 0
    assert all(v == 0 for (i, _), v in got.items() if i > 0)


def brute_candidates(text):
    """place, piece, value by walking over the words and their runs."""
    import re

    words, out = re.split(r"[ \t\n\r\f]+", text), []
    for place, word in enumerate(words):
        before = " ".join(words[max(0, place - 2) : place])
        for piece, m in enumerate(re.finditer(secrets.RUN, word)):
            value = re.sub(r"[.!]+$", "", m[0])
            lead = word[: word.index(value)][-60:]
            inside = re.search("[=:][\"'`]*$", lead) and not lead.endswith("://")
            begins = re.match("^[\"'`(\\[{<]*$", lead) and re.search("[=:]\\s*[\"'`]?$", before)
            if (len(value) >= 16 and re.search("[0-9]", value)) or (len(value) >= 8 and (inside or begins)):
                out.append((place, piece, value))
    return out


def test_candidates_against_brute_force(spark, docs):
    extra = ['{"api_key":"9f8e7d6c5b4a39281706","n":1}', "https://h/v1?token=9f8e7d6c5b4a3928&a=1", "postgres://user:pw12345678@host/db", "KEY2=abcdef0123456789abcd", "password: s3cr$t!Pass.", ""]
    both = docs.select("doc_id", "text").unionByName(documents(spark, extra, 10**6).select("doc_id", "text"))
    got = defaultdict(list)
    for r in secrets.candidates(both).collect():
        got[r["doc_id"]].append((r["place"], r["piece"], r["value"]))
    for r in both.collect():
        assert sorted(got[r["doc_id"]]) == brute_candidates(r["text"]), r["text"][:200]
    assert [x[2] for x in got[10**6]] == ["9f8e7d6c5b4a39281706"] and [x[2] for x in got[10**6 + 2]] == ["pw12345678"] and got[10**6 + 4][0][2] == "s3cr$t!Pass"


def test_secrets_in_json_urls_and_connection_strings(spark):
    key = hashlib.sha1(b"2").hexdigest()
    texts = [f'{{"id":7,"api_key":"{key}"}}', f"see https://h.example.com/v1?token={key}&a=1 now", "postgres://svc:Xk29fLq81Zpw@db.example.com/prod", "DB_PASSWORD=Hunter7f3a!Qz9", '{"id":"123e4567-e89b-42d3-a456-426614174000","name":"something"}', "version=1.22.333-45 date=2024-01-31"]
    found = {r["doc_id"] for r in secrets.secrets(documents(spark, texts)).where("predicted = 1").collect()}
    assert found == {0, 1, 2, 3}


def test_secrets_planted_in_the_given_documents(spark, docs):
    """Keys put between the words of real texts are found; what else is reported is little."""
    rows = [(r["doc_id"], r["text"]) for r in docs.orderBy("doc_id").limit(120).collect()]
    planted, texts = {}, []
    for i, t in rows:
        words = t.split(" ")
        key = hashlib.sha256(str(i).encode()).hexdigest()[:40]
        if i % 2 == 0:
            words.insert(len(words) // 2, rng_form(i, key))
            planted[i] = key
        texts.append((i, " ".join(words), None, None, None))
    got = secrets.secrets(spark.createDataFrame(texts, SCHEMA)).where("predicted = 1").collect()
    assert sum(any(r["doc_id"] == i and r["value"] == k for r in got) for i, k in planted.items()) >= 0.9 * len(planted)


def rng_form(i, key):
    return (f'api_key = "{key}"', f"token={key}", f'{{"secret":"{key}"}}', f"https://x.example.com/?access_token={key}&z=1")[i // 2 % 4]


def test_forest_on_labelled_findings(spark):
    found = common.materialize(secrets.labelled_findings(spark, 3000), "f")
    triples = "".join("1" if i % 7 == 0 else "0" for i in range(26**3)), "5" * 676
    model = secrets.train(found.where(F.xxhash64("word") % 4 != 0), triples, trees=15, depth=8)
    from pyspark.ml.feature import VectorAssembler

    rows = secrets.described(secrets.valued(found.where(F.xxhash64("word") % 4 == 0)), triples)
    out = model.transform(VectorAssembler(inputCols=list(secrets.FEATURES), outputCol="features", handleInvalid="keep").transform(rows))
    assert out.agg(F.avg((F.col("prediction") == F.col("label")).cast("double"))).first()[0] > 0.93


# every operator on odd rows and on nothing

OPERATORS = {
    "toxicity": lambda d, l, b: toxicity.score(d, l, "toxic"),
    "quality": lambda d, l, b: quality.score(d, l),
    "packing": lambda d, l, b: packing.pack_documents(d),
    "pii": lambda d, l, b: pii.personal_data(d),
    "near": lambda d, l, b: near.near_duplicates(d),
    "fingerprints": lambda d, l, b: fingerprints.edited_likeness(d),
    "lines": lambda d, l, b: lines.without_repeats(d),
    "leaks": lambda d, l, b: decontaminate.leaks(d, b),
    "suffix_tree": lambda d, l, b: suffix_tree.text_scores(d, common.remainder(7) == 2),
    "secrets": lambda d, l, b: secrets.secrets(d),
}
PER_ROW = {"toxicity", "quality", "pii", "near", "fingerprints", "lines", "suffix_tree"}


def test_a_query_of_rare_words_that_no_example_has():
    index = toxicity.BlockMaxIndex(2, np.array([0, 1, 1]), np.array([0, 0, 1]), np.ones(3, np.float32), 4, frequent=1)
    ids, cosines = index.nearest(np.array([0, 0]), np.array([2, 3]), np.full(2, 0.5, np.float32), 1, 2)
    assert (ids == -1).all() and (cosines == 0).all()


@pytest.mark.parametrize("name", OPERATORS)
def test_odd_rows_and_empty_tables(spark, odd, labels, name):
    benchmark = common.read(spark, SF, "benchmark")
    got = OPERATORS[name](odd, labels, benchmark).collect()
    if name in PER_ROW:
        assert len(got) == odd.count()
        assert sorted(str(r["doc_id"]) for r in got) == sorted(str(r["doc_id"]) for r in odd.select("doc_id").collect())
    assert OPERATORS[name](odd.where("false"), labels, benchmark).count() == 0


def test_odd_rows_results(spark, odd):
    got = near.near_duplicates(odd).collect()
    assert all(r["component_id"] == 6 for r in got if r["doc_id"] in (6, 7)) and all(r["kept"] for r in got if r["doc_id"] in (1, 2, 3, None))
    prints = [r["fingerprint"] for r in fingerprints.edited_likeness(odd).collect() if r["doc_id"] in (6, 7)]
    assert len(set(prints)) == 1
    pieces = packing.pack_documents(odd).where("doc_id in (1, 2)").collect()
    assert [r["length"] for r in pieces] == [1, 1]
