import hashlib
import random
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from fimspark.llm import (
    decontamination,
    induced_sort,
    near_copies,
    packing,
    pii,
    quality_classifier,
    quality_rules,
    registry,
    simhash,
    substring_dedup,
    token_counts,
    toxicity,
    url_filter,
)
from fimspark.llm.components import components

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
SF = "/root/testdata/sf0.001"
WORDS = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon".split()


def prose(rng, n):
    return " ".join(rng.choice(WORDS) for _ in range(n))


def odd_rows():
    """Nulls in any column, empty, blank and very long texts, repeated rows, ties."""
    rng = random.Random(1)
    long = prose(rng, 30_000)
    a = prose(rng, 60)
    return [
        (1, None, None, None, None),
        (2, "", "en", None, 0),
        (3, " \t\n ", None, "s", 4),
        (4, long, "en", "s", len(long)),
        (5, a, "en", "s", len(a)),
        (5, a, "en", "s", len(a)),
        (6, a, "en", "s", len(a)),
        (None, a, "en", "s", len(a)),
        (None, None, "en", "s", None),
        (7, "é " * 40 + "\x00\x1c end", "fr", "t", None),
        (8, "x" * 70_000, "en", "t", 70_000),
    ]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(odd_rows(), DOCS).cache()


def crowded(df):
    """Extra columns with names that operators use inside or return."""
    for c in ("fp", "score", "n_found", "found", "part", "shard", "weight", "selected", "kept", "length", "start", "words", "component_id", "node", "k"):
        df = df.withColumn(c, F.lit("extra"))
    return df


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], DOCS)


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame([(5, 1, 0), (2, 0, None), (None, 1, 1), (6, None, 1), (5, 1, 0)], "doc_id long, quality int, toxic int")


# --- packing and token counts ---


def covered(pieces, length_of):
    by_doc, by_seq = {}, {}
    for d, s, n, q, o in pieces:
        by_doc.setdefault(d, []).append((s, n))
        by_seq.setdefault(q, []).append((o, n))
    for d, x in by_doc.items():
        x.sort()
        assert x[0][0] == 0 and all(a + n == b for (a, n), (b, _) in zip(x, x[1:])) and sum(x[-1]) == length_of[d]
    for x in by_seq.values():
        x.sort()
        used = sum(x[-1])
        assert x[0][0] == 0 and all(a + n == b for (a, n), (b, _) in zip(x, x[1:]))
        assert used == 4096 or used & (used - 1) == 0
    return by_seq


def test_plan_covers_every_token_without_padding():
    rng = random.Random(0)
    for _ in range(100):
        lengths = [rng.choice([1, 2, 4095, 4096, 4097, 9000]) if rng.random() < 0.3 else rng.randint(1, 3000) for _ in range(rng.randint(1, 50))]
        covered(packing.plan(np.asarray(lengths)), dict(enumerate(lengths)))


def test_plan_balances_cost():
    seqs = covered(packing.plan(np.asarray([3000] * 10 + [100] * 200)), dict(enumerate([3000] * 10 + [100] * 200)))
    cost = [sum(n + n * n / 2048 for _, n in x) for x in seqs.values() if sum(max(x)) == 4096]
    assert max(cost) < 2.1 * min(cost)


def test_packing_of_odd_rows(spark, odd, empty):
    import public_tokenizers
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    rows = packing.pack(crowded(odd)).collect()
    assert sum(r.length for r in rows) == sum(len(t.encode(x[1] or "", add_special_tokens=False).ids) + 1 for x in odd_rows())
    want = {x[0]: np.asarray([*t.encode(x[1] or "", add_special_tokens=False).ids, 2], "<u4") for x in odd_rows() if x[0] not in (None, 5)}
    for r in rows:
        if r.doc_id in want:
            assert r.doc_tokens == len(want[r.doc_id])
            assert r.ids_crc32 == zlib.crc32(want[r.doc_id][r.start : r.start + r.length].tobytes())
    assert packing.pack(empty).count() == 0


def test_tokenizer_equals_library():
    import public_tokenizers

    t = packing.tokenizer(public_tokenizers.path("word_bpe_49k.json"))
    for x in ["it's DON'T 's's \x1cfoo\x85bar\u2003q <|startoftext|>a 12 3.14!!", "ΑΣ ΣΑΣ İstanbul é́ ½ Ⅳ", "x" * 3000, "日本語 テキスト", "a\tb\nc", "", "éa ́b"]:
        assert t.ids(x) == t.whole(x)


def test_histogram_answers(spark, odd, empty):
    import public_tokenizers

    t = packing.tokenizer(public_tokenizers.path("word_bpe_49k.json"))
    n = sorted(len(t.ids(x[1] or "")) // 4 for x in odd_rows())
    sums = token_counts.with_suffix_sums(token_counts.length_histogram(crowded(odd))).cache()
    for r in sums.collect():
        assert r.docs_at_least == sum(x >= r.n_tokens for x in n)
        assert r.tokens_at_least == sum(x for x in n if x >= r.n_tokens)
        assert r.truncated_total == sum(min(x, r.n_tokens) for x in n)
    for limit in (1, 50, 10**6):
        assert token_counts.truncated_total(sums, limit).first()[0] == sum(min(x, limit) for x in n)
    for p in (0.1, 0.5, 0.9, 1.0):
        assert token_counts.quantile(sums, p).first()[0] == n[int(np.ceil(p * len(n) - 1e-9)) - 1]
    assert token_counts.with_suffix_sums(token_counts.length_histogram(empty)).count() == 0


# --- PII ---


def luhn(s):
    return sum(d if k % 2 == 0 else d * 2 - 9 * (d > 4) for k, d in enumerate(map(int, reversed([c for c in s if c.isdigit()])))) % 10 == 0


def test_pseudonyms_keep_format_and_links(spark):
    texts = {
        1: "card 4845168114407329 and 4845168114407329, not 4845168114407328.",
        2: "again 4845168114407329",
        3: "+1 (017) 555-7713 at 97.51.17.173 or ab.34@mail7.example.com",
        4: "born 2024-02-29 or 29/02/2024, never 30/02/2024; 123-45-6789, not 666-45-6789",
        5: "plain text, 1.2.3.4.5 and f699e44f19092102589454a stay",
        6: None,
        7: "",
    }
    got = {r.doc_id: r for r in pii.pseudonymise(crowded(spark.createDataFrame([(k, t, None, None, None) for k, t in texts.items()], DOCS))).collect()}
    w = got[1].text.split()
    assert w[1] + "," == w[3] and w[1] != "4845168114407329" and len(w[1]) == 16 and luhn(w[1]) and w[5] == "4845168114407328."
    assert got[2].text == f"again {w[1]}"
    import re

    assert re.fullmatch(r"\+1 \(\d{3}\) \d{3}-\d{4} at \d+\.\d+\.\d+\.\d+ or [a-z]{2}\.\d\d@mail7\.example\.com", got[3].text) and got[3].n_found == 3
    for gone in ("555-7713", "97.51.17.173", "ab.34@"):
        assert gone not in got[3].text
    m = re.fullmatch(r"born (\d{4})-(\d\d)-(\d\d) or (\d\d)/(\d\d)/(\d{4}), never 30/02/2024; (\d{3}-\d\d-\d{4}), not 666-45-6789", got[4].text)
    assert m[1] == m[6] and m[2] == m[5] and m[3] == m[4] and m[7] != "123-45-6789"
    assert got[5].text == texts[5] and got[5].n_found == 0 and got[6].text is None and got[7].text == ""
    assert got[1].score == "extra" and got[1].found == "extra"


def test_feistel_is_a_permutation(spark):
    n = 30 * 14
    f = pii.feistel("k", "t", "id div 14", "id % 14", "30", "14")
    assert spark.range(n).select(F.expr(f"named_struct('z', {f})").alias("s")).select(F.col("s.z.x") * 14 + F.col("s.z.y")).distinct().count() == n
    days = spark.range(0, 73_000, 97).select(F.expr("date_format(date_add(DATE'1900-01-01', cast(id AS int)), 'yyyy-MM-dd')").alias("text"), F.col("id").alias("doc_id"))
    out = pii.pseudonymise(days)
    assert out.select("text").distinct().count() == days.count() and out.where("try_cast(text AS date) IS NULL").count() == 0


def test_pii_of_odd_rows(spark, odd, empty):
    assert sorted((r.doc_id or -1, r.text or "") for r in pii.pseudonymise(odd).collect()) == sorted((x[0] or -1, x[1] or "") for x in odd_rows())
    assert pii.pseudonymise(empty).count() == 0


# --- decontamination ---


def edits(p, r):
    row = [0] * (len(r) + 1)
    for i, c in enumerate(p, 1):
        new = [i]
        for j, e in enumerate(r, 1):
            new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (c != e)))
        row = new
    return min(row)


def test_alignment_equals_full_matrix():
    rng = random.Random(0)
    for _ in range(400):
        p, r = bytes(rng.choice(b"abc") for _ in range(rng.randint(1, 20))), bytes(rng.choice(b"abc") for _ in range(rng.randint(0, 30)))
        e = edits(p, r)
        for k in range(len(p)):
            assert decontamination.edit_distance_within(p, r, k) == (e <= k)


def test_leaks_equal_brute_force(spark):
    rng = random.Random(2)
    letters = "abcdefghijklmnopqrstuvwxyz"
    text = lambda n: " ".join("".join(rng.choice(letters) for _ in range(rng.randint(2, 8))) for _ in range(n))
    items = [(k, text(14)) for k in range(6)] + [(90, "short one"), (91, None), (92, "")]
    docs = []
    for k in range(60):
        t = text(80)
        if k % 3 == 0:
            x = list(items[k % 6][1])
            for _ in range(rng.randint(0, 5)):
                x[rng.randrange(len(x))] = rng.choice(letters)
            t = f"{t[:200]} {''.join(x).upper() if k % 2 else ''.join(x)}\n{t[200:]}"
        docs.append((k, t, None, None, None))
    docs += [(70, None, None, None, None), (71, "", None, None, None), (0, docs[0][1], None, None, None)]
    got = {(r.doc_id, r.item_id) for r in decontamination.leaks(crowded(spark.createDataFrame(docs, DOCS)), spark.createDataFrame(items, "item_id long, text string")).collect()}
    want = set()
    for i, t, *_ in docs:
        folded = decontamination.fold((t or "").encode())
        for j, b in items:
            whole = decontamination.fold((b or "").encode())
            if len(whole) >= decontamination.MIN_ITEM and folded:
                m = min(64, len(whole))
                if any(edits(whole[s : s + m], folded) <= decontamination.budget(m) for s in range(len(whole) - m + 1)):
                    want.add((i, j))
    assert got == want and len(want) >= 10


def test_leaks_in_parts_and_of_empty_tables(spark, empty, monkeypatch):
    b = spark.createDataFrame([(k, f"item number {k} " + prose(random.Random(k), 20)) for k in range(8)], "item_id long, text string")
    docs = spark.createDataFrame([(k, "so " + r.text, None, None, None) for k, r in enumerate(b.collect())], DOCS)
    want = {(k, k) for k in range(8)}
    assert {(r.doc_id, r.item_id) for r in decontamination.leaks(docs, b).collect()} >= want
    monkeypatch.setattr(decontamination, "MAX_INDEX_BYTES", 300)
    assert {(r.doc_id, r.item_id) for r in decontamination.leaks(docs, b).collect()} >= want
    assert decontamination.leaks(empty, b).count() == 0 and decontamination.leaks(docs, b.limit(0)).count() == 0


# --- SimHash ---


def plain_fingerprint(text):
    import re

    from xxhash import xxh64_intdigest

    low = "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "")
    w = re.findall(r"[^\x20\x09-\x0D]+", low)
    if not w:
        return 0
    h = [xxh64_intdigest(" ".join(x).encode(), 42) for x in ([w] if len(w) < 3 else [w[i : i + 3] for i in range(len(w) - 2)])]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def groups_of(points):
    parent = list(range(len(points)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    d = np.bitwise_count(points[:, None] ^ points[None, :]) <= 2
    for a, b in zip(*np.nonzero(d)):
        a, b = find(a), find(b)
        parent[max(a, b)] = min(a, b)
    return [find(k) for k in range(len(points))]


def cloud(seed, bases=30):
    rng = np.random.default_rng(seed)
    out = []
    for b in rng.integers(0, 2**63, bases, dtype=np.uint64):
        for _ in range(rng.integers(1, 30)):
            x = b
            for _ in range(rng.integers(0, 6)):
                x ^= np.uint64(1) << np.uint64(rng.integers(0, 64))
            out.append(x)
    return np.unique(np.asarray(out, np.uint64))


@pytest.mark.parametrize("seed", range(5))
def test_shards_link_all_that_is_near(seed):
    p = cloud(seed)

    def joined(pairs):
        parent = list(range(len(p)))

        def find(x):
            while parent[x] != x:
                x = parent[x]
            return x

        for a, b in pairs:
            a, b = find(a), find(b)
            parent[max(a, b)] = min(a, b)
        return [find(k) for k in range(len(p))]

    every = np.ones(len(p), bool)
    assert joined(simhash.shard_links(p, every, leaf=4)) == groups_of(p)
    assert joined(simhash.shard_links(p, every, leaf=4, dense=2)) == groups_of(p)


def test_near_duplicates_equal_brute_force(spark, monkeypatch):
    monkeypatch.setattr(simhash, "SHARD", 40)
    rng = random.Random(3)
    base = [prose(rng, 90) for _ in range(12)]
    texts = []
    for k in range(150):
        w = base[k % 12].split()
        for _ in range(rng.randint(0, 2)):
            w[rng.randrange(len(w))] = rng.choice(WORDS)
        texts.append(" ".join(w))
    texts += [None, "", " ", "one", "One", "two words", *texts[:3]]
    rows = [(k, t, None, None, None) for k, t in enumerate(texts)]
    got = {r.doc_id: r for r in simhash.near_duplicates(crowded(spark.createDataFrame(rows, DOCS))).collect()}
    fp = np.asarray([plain_fingerprint(t) for t in texts], np.uint64)
    assert [got[k].fp for k in range(len(texts))] == fp.view(np.int64).tolist()
    assert [got[k].component_id for k in range(len(texts))] == groups_of(fp)


def test_components_of_a_long_chain(spark):
    rows = [(k, k + 1) for k in range(100, 160)] + [(7, 9), (9, 8), (5, 5), (7, 9)]
    got = {r.node: r.component for r in components(spark.createDataFrame(rows, "a long, b long")).collect()}
    assert got == {**{k: 100 for k in range(100, 161)}, 7: 7, 8: 7, 9: 7}


def test_simhash_of_odd_rows(odd, empty):
    got = simhash.near_duplicates(odd).collect()
    assert len(got) == len(odd_rows())
    by = {(r.doc_id, r.fp): r.component_id for r in got}
    assert by[(1, 0)] == by[(2, 0)] == by[(3, 0)] == 1 and all(r.component_id is None for r in got if r.doc_id is None)
    assert len({r.component_id for r in got if r.doc_id in (5, 6)}) == 1
    assert simhash.near_duplicates(empty).count() == 0


# --- toxicity ---


def plain_kernel(a, b, p=toxicity.P, decay=toxicity.DECAY):
    from itertools import combinations

    total = 0.0
    for i in combinations(range(len(a)), p):
        for j in combinations(range(len(b)), p):
            if all(a[x] == b[y] for x, y in zip(i, j)):
                total += decay ** (i[-1] - i[0] + 1 + j[-1] - j[0] + 1)
    return total


def test_kernel_equals_enumeration():
    words = ["idiot", "idxiot", "i.d.iot", "aaaa", "patio", "abc"]
    k = toxicity.Kernel(words)
    c, n = toxicity.codes(words)
    for x in range(len(words)):
        got = toxicity.raw_kernel(c, k.codes[x])
        want = [plain_kernel(w, words[x]) for w in words]
        assert np.allclose(got, want, rtol=1e-4) and np.isclose(k.own[x], want[x], rtol=1e-4)
    assert np.allclose(np.diag(k.gram()), 1)


def test_gaps_are_tolerated():
    k = toxicity.Kernel(["idiot"])
    v = k(["idiot", "idxiot", "id-iot", "garden", "xidiotx"])[:, 0]
    assert v[0] > 0.99 and v[1] > 0.5 and v[2] > 0.5 and v[3] == 0 and v[4] > 0.99
    assert "idiot" in toxicity.words_of("you i d i o t there") and "idiot" in toxicity.words_of("you i.d.i.o.t!")


def test_a_character_between_all_letters_is_tolerated():
    words = ["idio", "moron", "idiot", "stupid", "worthless", "worthlessy", "abcdefghijk", "abcdefghijkl"]
    k = toxicity.Kernel(words)
    for x in "x7+":
        assert (np.diag(k([x.join(w) for w in words])) > 0.3).all()
    for sep in ("+", "/", " , ", ":", "|", "~", "...", "----"):
        assert "idiot" in toxicity.words_of(f"you {sep.join('idiot')} there")


def test_toxicity_of_held_out_rows(spark):
    docs, labels = spark.read.parquet("/root/testdata/sf0.1/documents.parquet"), spark.read.parquet("/root/testdata/sf0.1/labels.parquet")
    got = toxicity.score(docs, toxicity.train(docs, labels)).join(labels, "doc_id").where("held_out").toPandas()
    hit = got.predicted == 1
    # a few of these labels are wrong, and outside English the telling word parts occur in other texts too, only less often
    english = got.doc_id.isin([r.doc_id for r in docs.where("lang = 'en'").select("doc_id").collect()])
    assert hit[english & (got.toxic == 1)].mean() > 0.8 and hit[got.toxic == 1].mean() > 0.6 and hit[got.toxic == 0].mean() < 0.02
    assert all((zlib.crc32(str(i).encode()) % 3 == 1) for i in got.doc_id)


def test_toxicity_of_odd_rows(spark, odd, empty, labels):
    m = toxicity.train(crowded(odd), labels)
    got = toxicity.score(crowded(odd), m).collect()
    assert len(got) == len(odd_rows()) and all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.7) for r in got)
    assert toxicity.score(empty, toxicity.train(empty, labels)).count() == 0
    assert toxicity.score(odd, toxicity.train(odd, labels.limit(0))).agg(F.max("score")).first()[0] == 0


# --- quality rules ---


def plain_measures(text):
    import re

    text = text or ""
    w = re.findall(r"[^\x20\x09-\x0D]+", text)
    lines = [x for x in text.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    seen = {}
    for i in range(len(w) - 7):
        seen.setdefault(tuple(w[i : i + 8]), []).append(i)
    rep = {i + j for v in seen.values() if len(v) > 1 for i in v for j in range(8)}
    return len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in text), len(lines) - len(set(lines)), len(rep)


def test_measures_equal_plain_ones(spark, odd, empty):
    rng = random.Random(5)
    texts = [x[1] for x in odd_rows()] + ["a b c d e f g h " * 3, "x\nx\n \n\nx", "# $ %% <a> | &", "a b\x0bc\x0cd\re", "\u00a0a\u2003b"]
    for _ in range(40):
        texts.append(" ".join(rng.choice("ab") for _ in range(rng.randint(0, 40))) + "\n" * rng.randint(0, 2))
    got = {r.doc_id: r for r in quality_rules.measures(crowded(spark.createDataFrame([(k, t, None, None, None) for k, t in enumerate(texts)], DOCS))).collect()}
    for k, t in enumerate(texts):
        r = got[k]
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == plain_measures(t), repr(t)[:60]
        assert r.base_failed == (r.n_words < 20 or 100 * r.n_repeat_words > 30 * r.n_words)
    assert quality_rules.apply_rules(odd).count() == len(odd_rows()) and quality_rules.apply_rules(empty).count() == 0


def test_sketches_merge_and_adapt(spark):
    docs = [(k, prose(random.Random(k), 50).replace(" ", " " if k % 20 else "# "), "en", "plain", None) for k in range(200)]
    docs += [(1000 + k, prose(random.Random(k), 50).replace(" ", "# "), "en", "code", None) for k in range(50)]
    df = spark.createDataFrame(docs, DOCS)
    kept = {r.doc_id: r.kept for r in quality_rules.apply_rules(df).collect()}
    assert not any(kept[k] for k in range(0, 200, 20)) and all(kept[k] for k in range(200) if k % 20) and all(kept[1000 + k] for k in range(50))
    m = quality_rules.measures(df)
    whole = {tuple(r) for r in quality_rules.sketch(m).collect()}
    parts = quality_rules.sketch(m.where("doc_id % 2 = 0")).unionByName(quality_rules.sketch(m.where("doc_id % 2 = 1")))
    assert {tuple(r) for r in parts.groupBy("lang", "source", "measure", "bucket").agg(F.sum("n")).collect()} == whole


# --- suffix arrays ---


def test_suffix_array_equals_sorting():
    rng = random.Random(1)
    for _ in range(300):
        x = bytes(rng.choice(rng.choice([b"ab", b"a", b"abcdefgh"])) for _ in range(rng.randint(0, 60)))
        t = np.append(np.frombuffer(x, np.uint8).astype(np.uint16) + np.uint16(1), np.uint16(0)).astype(np.uint16)
        assert induced_sort.suffix_array(t).tolist() == sorted(range(len(t)), key=lambda i: t[i:].tolist())
        some = induced_sort.suffix_array(t, depth=5)
        cut = [tuple(t[i : i + 5]) for i in some]
        assert cut == sorted(cut) and sorted(some.tolist()) == list(range(len(t)))


def plain_removal(rows):
    first = {}
    for i, b in sorted((x for x in rows if x[0] is not None), key=lambda x: x[0]):
        for k in range(len(b) - 49):
            first.setdefault(b[k : k + 50], i)
    out = []
    for i, b in rows:
        gone = bytearray(len(b))
        for k in range(len(b) - 49):
            if i is not None and first[b[k : k + 50]] < i:
                gone[k : k + 50] = b"\1" * 50
        kept = bytes(c for c, g in zip(b, gone) if not g)
        out.append((i, len(b), sum(gone), sum(g and (k == 0 or not gone[k - 1]) for k, g in enumerate(gone)), hashlib.sha256(kept).hexdigest()))
    return out


def sorted_rows(rows):
    return sorted(rows, key=lambda r: tuple((x is None, x) for x in r))


@pytest.mark.parametrize("hot", [100_000, 3])
def test_removal_equals_brute_force(spark, monkeypatch, hot):
    monkeypatch.setattr(substring_dedup, "HOT", hot)
    rng = random.Random(7)
    shared = [prose(rng, 14) for _ in range(5)]
    rows = [(None, "n " + shared[0]), (None, shared[0] * 2)]
    for k in range(80):
        t = prose(rng, rng.randint(1, 40))
        if k % 2:
            t = t[:33] + rng.choice(shared) + t[33:] + (rng.choice(shared)[:60] if k % 3 else "é" * 60)
        rows.append((k, t))
    rows += [(200, rows[10][1]), (201, rows[10][1]), (150, rows[10][1]), (11, rows[11][1]), (300, None), (301, ""), (302, "ab" * 200), (303, "ab" * 100)]
    docs = spark.createDataFrame([(i, t, None, None, None) for i, t in rows], DOCS)
    got = [tuple(r) for r in substring_dedup.remove_repeats(crowded(docs)).drop("kept").collect()]
    assert sorted_rows(got) == sorted_rows(plain_removal([(i, (t or "").encode()) for i, t in rows]))


def test_removal_of_odd_rows(odd, empty):
    got = [tuple(r) for r in substring_dedup.remove_repeats(odd).drop("kept").collect()]
    assert sorted_rows(got) == sorted_rows(plain_removal([(x[0], (x[1] or "").encode()) for x in odd_rows()]))
    assert substring_dedup.remove_repeats(empty).count() == 0


# --- quality classifier ---


def test_ordinal_regression_orders_grades():
    rng = np.random.default_rng(0)
    x = rng.normal(size=(3000, 6)).astype(np.float32)
    z = x @ np.asarray([2, -1, 0.5, 0, 0, 0]) + rng.logistic(size=3000)
    grade = np.digitize(z, [-1.5, 0.5, 2.0])
    m = quality_classifier.fit(x, grade, steps=400)
    assert (np.diff(m.thresholds) > 0).all() and np.argsort(-np.abs(m.w))[:2].tolist() == [0, 1]
    tails = m.tails(x @ m.w)
    assert (np.diff(tails, axis=1) <= 1e-9).all()
    assert np.corrcoef(tails.sum(axis=1), grade)[0, 1] > 0.65


def test_classifier_on_held_out_rows(spark):
    docs, labels = spark.read.parquet("/root/testdata/sf0.1/documents.parquet"), spark.read.parquet("/root/testdata/sf0.1/labels.parquet")
    out = F.pmod(F.xxhash64("doc_id"), F.lit(3)) == 0
    m = quality_classifier.train(docs, quality_classifier.graded(labels.where(~out)), 2000)
    got = quality_classifier.score(docs.join(labels.where(out), "doc_id"), m).toPandas()
    assert got.selected[got.quality == 1].mean() > 0.98 and got.selected[got.quality == 0].mean() < 0.1
    assert got.expected_grade[(got.quality == 1) & (got.toxic == 0)].mean() > got.expected_grade[(got.quality == 1) & (got.toxic == 1)].mean()


def test_classifier_of_odd_rows(spark, odd, empty, labels):
    m = quality_classifier.train(odd, quality_classifier.graded(labels))
    got = quality_classifier.score(crowded(odd), m)
    assert got.count() == len(odd_rows()) and got.columns[:5] == odd.columns
    assert quality_classifier.score(empty, m).count() == 0
    none = quality_classifier.train(odd, quality_classifier.graded(labels.limit(0)))
    assert none is None and quality_classifier.score(odd, none).where("not selected").count() == 0


# --- URLs ---


def plain_judgement(url):
    rest = url.split("://", 1)[1] if url and "://" in url else ""
    end = min([rest.index(c) for c in "/?#" if c in rest], default=len(rest))
    host = "".join(c.lower() if "A" <= c <= "Z" else c for c in rest[:end])
    path = rest[end:]
    path = path[: min([path.index(c) for c in "?#" if c in path], default=len(path))]
    best = None
    for verdict, rule in url_filter.RULES:
        h, p = rule[: rule.index("/")], rule[rule.index("/") :]
        if (host == h or host.endswith("." + h)) and path.startswith(p) and (best is None or len(rule) > len(best[1])):
            best = (verdict, rule)
    return host, path, best and best[1], best and best[0]


def test_url_rules_and_model(spark):
    rng = random.Random(0)
    urls = [None, "", "no scheme", "http://", "HTTP://ExAmple.ORG/en/17?x", "https://a.org", "http://org/x", "http://example.org/es/#a", "x://y://z.org/q", "http://notexample.org/es/", "http://org.net/a\nb/c"]
    for k in range(400):
        urls.append(f"http://{rng.choice(['good', 'fine'])}{k}.example.com/fr/{k}" if k % 2 else f"http://{rng.choice(['casino', 'pills'])}{k}.example.com/de/{k}")
    tests = [f"http://{w}{k}.example.net/x/{k}" for k in range(30) for w in ("good", "casino")]
    pages = spark.createDataFrame([(k, u) for k, u in enumerate(urls + tests)], "page_id long, url string")
    got = {r.page_id: r for r in url_filter.judge(pages.withColumn("host", F.lit("x")).withColumn("score", F.lit("x"))).collect()}
    for k, u in enumerate(urls + tests):
        host, path, rule, verdict = plain_judgement(u)
        assert (got[k].host, got[k].path, got[k].rule) == (host, path, rule)
        assert got[k].verdict == verdict if rule else got[k].verdict in ("allow", "block")
    right = sum(got[len(urls) + k].verdict == ("allow" if "good" in u else "block") for k, u in enumerate(tests))
    assert right >= 0.9 * len(tests)
    assert url_filter.judge(pages.limit(0)).count() == 0 and url_filter.judge(pages.limit(3)).count() == 3


def plain_ratio(url, trained, order=url_filter.ORDER):
    """Per byte: the log ratio of two smoothed models, from counts of a dictionary for each order."""
    import math

    total = 0.0
    data = b"\0" * order + url.encode()
    for i in range(order, len(data)):
        logs = []
        for counts in trained:
            p = 1 / 256
            for o in range(order + 1):
                seen = counts.get((o, data[i - o : i]))
                if seen:
                    n, kinds = sum(seen.values()), len(seen)
                    p = (seen.get(data[i], 0) + kinds * p) / (n + kinds)
            logs.append(math.log(p))
        total += logs[0] - logs[1]
    return total / max(1, len(data) - order)


@pytest.mark.parametrize("common", [10_000, 3])
def test_url_scores_equal_plain_models(spark, monkeypatch, common):
    rng = random.Random(4)
    monkeypatch.setattr(url_filter, "COMMON", common)
    urls = [f"http://{rng.choice(['good', 'fine', 'caf\u00e9'])}{rng.randrange(50)}.example.com/{rng.choice(['fr', 'de', 'it'])}/{rng.randrange(99)}" for _ in range(300)] + [None, "", "http://x.org/" + "long" * 5000]
    pages = spark.createDataFrame([(k, u) for k, u in enumerate(urls)], "page_id long, url string")
    got = {r.page_id: r for r in url_filter.judge(pages).collect()}
    held = {r.page_id for r in pages.where(F.pmod(F.xxhash64("url"), F.lit(5)) == 0).collect()}
    trained = ({}, {})
    for k, u in enumerate(urls):
        verdict = plain_judgement(u)[3]
        if verdict and k not in held:
            data = b"\0" * url_filter.ORDER + u.encode()
            for i in range(url_filter.ORDER, len(data)):
                for o in range(url_filter.ORDER + 1):
                    seen = trained[verdict == "block"].setdefault((o, data[i - o : i]), {})
                    seen[data[i]] = seen.get(data[i], 0) + 1
    for k, u in enumerate(urls):
        assert abs(got[k].score - (plain_ratio(u, trained) if u else 0.0)) < 1e-6
    free = [got[k] for k, u in enumerate(urls) if plain_judgement(u)[3] is None]
    limit = max([r.score for r in free if r.verdict == "block"], default=-9.0)
    assert all((r.verdict == "allow") == (r.score > limit) for r in free) and {got[300].verdict, got[301].verdict} == {"allow" if 0 > limit else "block"}


def test_classifier_reads_whole_words_and_skips_null_grades(spark):
    long = "x" * 70
    f = quality_classifier.features
    assert (f(long + "!!") != f(long + "??")).any() and (f("a" * 80) != f("a" * 79 + "1")).any()
    rows = [(1, 0, 0), (2, 1, 1), (3, 1, 0), (4, None, 0), (5, 1, None), (6, 0, None), (None, 1, 0)]
    got = {r.doc_id: r.grade for r in quality_classifier.graded(spark.createDataFrame(rows, "doc_id long, quality int, toxic int")).collect()}
    assert got == {1: 0, 2: 1, 3: 2, 4: None, 5: None, 6: 0, None: 2}


def test_ordinal_likelihood_is_at_its_maximum():
    """The fitted weights against a plain likelihood: no small step in any direction raises it."""
    rng = np.random.default_rng(3)
    x = rng.normal(size=(400, 4)).astype(np.float32)
    grade = np.digitize(x @ np.asarray([1.0, -1, 0, 0.5]) + rng.logistic(size=400), [-1, 1])
    m = quality_classifier.fit(x, grade, steps=3000)
    weight = np.sqrt(400 / 3 / np.bincount(grade))[grade]

    def loss(w, t):
        s = 1 / (1 + np.exp(-((x @ w)[:, None] - t[None, :])))
        edges = np.hstack([np.ones((400, 1)), s, np.zeros((400, 1))])
        rows = np.arange(400)
        return -(weight * np.log(edges[rows, grade] - edges[rows, grade + 1])).mean() + quality_classifier.L2 / 2 * (w @ w)

    best = loss(m.w, m.thresholds)
    for k in range(6):
        for step in (0.02, -0.02):
            w, t = m.w.copy(), m.thresholds.copy()
            (w if k < 4 else t)[k if k < 4 else k - 4] += step
            assert loss(w, t) > best - 1e-6


def test_repeated_labelled_rows_stay_within_the_bound(spark):
    docs = spark.createDataFrame([(k % 3, f"text number {k}", "en", "s", None) for k in range(300)], DOCS)
    labels = spark.createDataFrame([(k, k % 2, k % 2) for k in range(3)], "doc_id long, quality int, toxic int")
    seen = []
    fit, quality_classifier.fit = quality_classifier.fit, lambda x, grade: seen.append(len(grade))
    try:
        quality_classifier.train(docs, quality_classifier.graded(labels), 10)
    finally:
        quality_classifier.fit = fit
    assert seen == [10]
    fit, toxicity.fit = toxicity.fit, lambda bags, toxic: seen.append(len(bags))
    try:
        toxicity.train(docs, labels, 10)
    finally:
        toxicity.fit = fit
    assert seen[1] <= 10


# --- round 2: formats, starts, limits, guards ---


def test_word_parallel_alignment_equals_full_matrix():
    rng = random.Random(8)
    n = 300
    passages, regions = np.zeros((n, 64), np.uint8), np.zeros((n, 90), np.uint8)
    sizes, reach, k, want = np.zeros(n, np.int64), np.zeros(n, np.int64), np.zeros(n, np.int64), []
    for i in range(n):
        p, r = bytes(rng.choice(b"ab") for _ in range(rng.randint(1, 64))), bytes(rng.choice(b"ab") for _ in range(rng.randint(0, 90)))
        passages[i, : len(p)], regions[i, : len(r)] = np.frombuffer(p, np.uint8), np.frombuffer(r, np.uint8)
        sizes[i], reach[i], k[i] = len(p), len(r), rng.randrange(len(p))
        want.append(edits(p, r) <= k[i])
    assert decontamination.within(passages, sizes, regions, reach, k).tolist() == want


@pytest.mark.parametrize("n_edits", [0, 3, 5])
def test_no_start_of_a_passage_is_lost(n_edits):
    """Passages from any place of longer items, with as many substitutions, insertions and deletions as the budget has."""
    rng = random.Random(n_edits)
    letters = b"abcdefghijklmnopqrstuvwxyz    "
    noise = lambda n: decontamination.fold(bytes(rng.choice(letters) for _ in range(n)))
    items = [(k, noise(400)) for k in range(15)]
    index, docs, source = decontamination.Index(items), [], []
    for _ in range(120):
        i, t = items[rng.randrange(15)]
        at = rng.randrange(len(t) - 64)
        x = list(t[at : at + 64])
        for _ in range(n_edits):
            j, how = rng.randrange(len(x)), rng.random()
            if how < 0.5:
                x[j] = rng.choice(letters)
            elif how < 0.75:
                del x[j]
            else:
                x.insert(j, rng.choice(letters))
        docs.append(noise(200) + b" " + bytes(x) + b" " + noise(200))
        source.append(i)
    assert set(index.search(docs)) == set(enumerate(source))


def test_more_formats_are_replaced(spark):
    texts = ["at 2024-05-01T10:00:00Z", "01.05.2024", "1/5/2024", "12/25/2024", "02/29/2000", "555-123-4567", "(555) 123-4567", "555.123.4567", "+33 6 12 34 56 78", "+49 30 1234567", "+44 (20) 7946 0958", "3782 822463 10005"]
    same = ["13/13/2024", "version 1.2.2024.5", "1,234,567", "12-34-5678", "+12", "02/30/2024"]
    docs = spark.createDataFrame([(k, t, None, None, None) for k, t in enumerate(texts + same)], DOCS)
    got = {r.doc_id: r.text for r in pii.pseudonymise(docs).collect()}
    shape = lambda t: "".join("0" if c.isdigit() else c for c in t)
    for k, t in enumerate(texts):
        assert got[k] != t and (shape(got[k]) == shape(t) or t == "1/5/2024"), t
    assert [got[len(texts) + k] for k in range(len(same))] == same
    assert got[8].startswith("+33 ") and got[9].startswith("+49 ") and got[10].startswith("+44 (") and luhn("".join(c for c in got[11] if c.isdigit()))
    assert got[0][3:13] == "-".join(got[1].split(".")[::-1]), "a day is linked across formats"


def test_dates_with_the_month_first_stay_apart(spark):
    import datetime as dt

    days = [dt.date(1999, 1, 1) + dt.timedelta(days=k) for k in range(1000)]
    texts = sorted({d.strftime("%m/%d/%Y") for d in days} | {d.strftime("%d/%m/%Y") for d in days})
    docs = spark.createDataFrame([(k, t, None, None, None) for k, t in enumerate(texts)], DOCS)
    got = [r.text for r in pii.pseudonymise(docs).collect()]
    assert len(set(got)) == len(texts)
    for t in got:
        a, b, y = map(int, t.split("/"))
        assert any(1 <= m <= 12 and 1 <= d <= (dt.date(y + m // 12, m % 12 + 1, 1) - dt.timedelta(days=1)).day for d, m in ((a, b), (b, a)))


def test_junk_cannot_lift_the_limits(spark):
    clean = lambda k: prose(random.Random(k), 60)
    junk = lambda k: clean(k).replace(" ", " ## ")
    docs = [(k, junk(k) if k % 5 == 0 else clean(k), "en", "heavy", None) for k in range(300)]
    docs += [(1000 + k, junk(k) if k == 0 else clean(k), "en", "small", None) for k in range(10)] + [(2000, junk(1), None, None, None), (2001, clean(1), None, None, None)]
    kept = {r.doc_id: r.kept for r in quality_rules.apply_rules(spark.createDataFrame(docs, DOCS)).collect()}
    assert not any(kept[k] for k in range(0, 300, 5)) and all(kept[k] for k in range(300) if k % 5)
    assert not kept[1000] and all(kept[1000 + k] for k in range(1, 10)), "a small group has its language's limits"
    assert kept[2001]


def test_landmarks_share_one_kernel():
    k = toxicity.Kernel(["idiot", "idiotic", "garden"])
    g, share = k.gram(), k(["idiot", "idiotic", "garden"])
    assert np.allclose(g, (share + share.T) / 2) and np.allclose(np.diag(g), 1) and g[0, 1] > 0.5 > g[0, 2]


def test_an_unknown_engine_is_not_trusted(monkeypatch):
    import public_tokenizers

    path = public_tokenizers.path("word_bpe_49k.json")
    good = packing.WordTokenizer(path)
    assert good.trusted
    monkeypatch.setattr(packing.WordTokenizer, "chunk", lambda self, word: b"")
    other = packing.WordTokenizer(path)
    assert not other.trusted and other.ids("a few words") == good.whole("a few words")


def test_quantiles_are_whole_counts(spark):
    hist = spark.createDataFrame([(5, 1), (7, 1), (9, 1), (11, 7)], "n_tokens long, n_docs long")
    sums = token_counts.with_suffix_sums(hist).cache()
    assert [token_counts.quantile(sums, q).first()[0] for q in (0.1, 0.2, 0.3, 0.31, 1.0)] == [5, 7, 9, 11, 11]


def test_stages_need_a_shared_folder_off_one_machine():
    from types import SimpleNamespace

    from fimspark.llm import common

    none = SimpleNamespace(isDefined=lambda: False)
    context = SimpleNamespace(master="spark://host:7077", _jsc=SimpleNamespace(sc=lambda: SimpleNamespace(getCheckpointDir=lambda: none)))
    with pytest.raises(RuntimeError):
        common.ensure_checkpoint_dir(SimpleNamespace(sparkContext=context, conf=SimpleNamespace(get=lambda *_: None)))


def test_blocks_are_searched_alike_in_one_piece_and_in_chunks():
    rng = random.Random(6)
    sets = []
    for _ in range(12):
        base = rng.sample(range(10_000), 60)
        for gone in (0, 2, 4, 6, 14):
            sets.append(np.unique(np.asarray(base[gone:] + rng.sample(range(10_000), gone), np.uint64)))
    n = len(sets)
    similar = [(a, b) for a in range(n) for b in range(a) if 5 * (s := len(np.intersect1d(sets[a], sets[b]))) >= 4 * (len(sets[a]) + len(sets[b]) - s)]

    def groups(pairs):
        root = list(range(n))
        for a, b in pairs:
            x, y = sorted((root[a], root[b]))
            root = [x if r == y else r for r in root]
        return root

    comp, one = np.arange(n), np.zeros(n, np.int64)
    whole = near_copies.linked(sets, comp, one)
    assert groups(whole) == groups(similar) and len(whole) < len(similar)
    half = np.arange(n) % 2
    pairs = near_copies.linked(sets, comp, half)
    for h in (0, 1):
        own = np.flatnonzero(half == h)
        pairs += [(own[a], own[b]) for a, b in near_copies.linked([sets[k] for k in own], comp[own], one[own])]
    assert groups(pairs) == groups(similar)


# --- registry and pipeline ---


def test_registered_queries():
    import __spark_entry__ as e

    names = e.queries()
    assert [sum(n.startswith(f"op{k}_") for n in names) for k in range(1, 11)] == [1] * 10 and "pipeline" in names
    assert set(registry.oracle_sql()) <= set(registry.queries())


def test_pipeline_stages(spark):
    import corpus_pipeline as p

    assert [n for n, _ in p.STAGES] == ["quality", "near_dedup", "decontaminate", "pii", "packing"]
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    kept = p.quality(spark, docs, SF).cache()
    assert kept.columns == docs.columns
    one = p.near_dedup(spark, kept, SF).cache()
    texts = {r.doc_id: r.text for r in kept.collect()}
    assert sorted(r.doc_id for r in one.collect()) == similar_leaders(sorted(texts), [texts[i] for i in sorted(texts)])
    clean = p.decontaminate(spark, one, SF).cache()
    bad = {r.doc_id for r in decontamination.leaks(one, spark.read.parquet(f"{SF}/benchmark.parquet")).collect()}
    assert {r.doc_id for r in clean.collect()} == {r.doc_id for r in one.collect()} - bad
    safe = p.pseudonyms(spark, clean, SF).cache()
    assert safe.columns == docs.columns and safe.count() == clean.count()
    assert p.pack(spark, safe, SF).groupBy().sum("length").first()[0] == p.run(spark, SF).groupBy().sum("length").first()[0]


def similar_leaders(ids, texts):
    """The least id of each group of texts that links of five-word similarity 0.8 or more connect, by comparing all pairs."""
    sets = [frozenset(tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))) if w else frozenset() for w in ((t or "").lower().split() for t in texts)]
    parent = list(range(len(texts)))
    for a in range(len(texts)):
        for b in range(a):
            if 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b]) and parent[a] != parent[b]:
                lo, hi = sorted((parent[a], parent[b]))
                parent = [lo if x == hi else x for x in parent]
    return [i for k, i in enumerate(ids) if parent[k] == k]


def test_chain_through_other_members(spark):
    """Two groups whose leaders are not similar, linked by members that are."""
    import corpus_pipeline as p

    words = [f"w{k}" for k in range(400)]
    texts = [" ".join(words[18 * k : 18 * k + 200]) for k in (0, 4, 1, 3, 2)]
    docs = spark.createDataFrame([(k, t, "en", "s", None) for k, t in enumerate(texts)], DOCS)
    assert similar_leaders(range(5), texts) == [0] and [r.doc_id for r in p.near_dedup(spark, docs, SF).collect()] == [0]


def test_near_dedup_removes_similar_texts(spark, monkeypatch):
    """Against the similarity of all pairs: some lie on either side of 0.8, most of them far over two bits apart."""
    import corpus_pipeline as p

    rng = random.Random(11)
    texts = [None, "", "one two", "One  two"]
    for _ in range(12):
        base = [f"w{rng.randrange(3000)}" for _ in range(200)]
        for edits in (0, 2, 4, 4, 5, 8, 30):
            w = list(base)
            for at in rng.sample(range(0, 200, 6), edits):
                w[at] = f"new{rng.randrange(10**6)}"
            texts.append(" ".join(w))
    docs = spark.createDataFrame([(k, t, "en", "s", None) for k, t in enumerate(texts)], DOCS)
    want = similar_leaders(range(len(texts)), texts)
    assert len(want) < len(texts) - 30
    assert sorted(r.doc_id for r in p.near_dedup(spark, docs, SF).collect()) == want
    # the same when leaders' points and buckets are dealt to many small groups
    monkeypatch.setattr(near_copies, "GROUP", 2)
    monkeypatch.setattr(near_copies, "CHUNK", 2)
    monkeypatch.setattr(near_copies, "VOLUME", 500)
    assert sorted(r.doc_id for r in p.near_dedup(spark, docs, SF).collect()) == want


@pytest.mark.parametrize("shard", [100_000, 60])
def test_candidates_meet_in_trees_of_fingerprints(spark, monkeypatch, shard):
    """Points of noisy copies, ten of 64 bits apart and more: the trees connect what all pairs of blocks connect, whether or not they are dealt to shards."""
    monkeypatch.setattr(near_copies, "SHARD", shard)
    rng = np.random.default_rng(shard)
    words = []
    for base in rng.integers(0, 2, (60, 64 * near_copies.WIDE), np.uint8):
        words += [np.packbits(base ^ (rng.random(len(base)) < share), bitorder="little").view(np.uint64) for share in (0, 0.08, 0.15, 0.2)]
    words = np.stack(words)
    size = rng.choice([100, 110, 130, 150, 180], len(words))
    key, check = near_copies.blocks(words), words[:, : near_copies.CHECK]
    parent = list(range(len(words)))
    for a in range(len(words)):
        for b in range(a):
            met = (np.bitwise_count(key[a] ^ key[b]) <= simhash.REACH).any() and np.bitwise_count(check[a] ^ check[b]).sum() <= near_copies.FAR
            if met and 5 * min(size[a], size[b]) >= 4 * max(size[a], size[b]):
                lo, hi = sorted((parent[a], parent[b]))
                parent = [lo if x == hi else x for x in parent]
    assert 20 < sum(p != k for k, p in enumerate(parent)) < 200
    assert len(near_copies.size_bounds(size, -(-len(words) // shard))) == 2 * (shard < 100)
    points = spark.createDataFrame([(k, int(n), w.view(np.int64).tolist()) for k, (n, w) in enumerate(zip(size, words))], "node long, n long, fp array<long>")
    near = near_copies.near_pairs(points)
    got = {r.node: r.component for r in near_copies.components(near).collect()}
    assert [got.get(k, k) for k in range(len(words))] == parent
    assert any(np.bitwise_count(words[r.a, 0] ^ words[r.b, 0]) >= 10 for r in near.collect())


def test_similar_sizes_meet_in_one_level():
    sizes = np.arange(1, 400)
    bounds = near_copies.size_bounds(sizes, 40)
    assert len(bounds) > 10 and near_copies.size_bounds(np.full(50, 7), 9).tolist() == [] == near_copies.size_bounds(sizes[:0], 1).tolist()
    held = {}
    for c, rows, stored in near_copies.by_size(sizes, bounds):
        for r in rows.tolist():
            held.setdefault(r, {})[c] = stored
    assert all(sum(x.values()) == 1 and len(x) < 3 for x in held.values())
    for a in range(len(sizes)):
        for b in range(a, len(sizes)):
            if 5 * sizes[a] < 4 * sizes[b]:
                break
        for near in range(a, b):
            assert any(held[a][c] or held[near][c] for c in held[a].keys() & held[near].keys())


def test_crowded_leaves_keep_all_candidates():
    rng = np.random.default_rng(5)
    base = rng.integers(0, 1 << 63, (4, near_copies.CHECK), np.uint64)
    check = base[rng.integers(0, 4, 300)] ^ (np.uint64(1) << rng.integers(0, 64, (300, near_copies.CHECK), np.uint64))
    key, size = rng.integers(0, 2, 300, np.uint64), np.full(300, 50)
    whole, crowd = (near_copies.candidates(key, check, size, np.arange(300) % 3 > 0, leaf=16, dense=d) for d in (4096, 10))
    for c in (whole, crowd):
        near = np.bitwise_count(check[:, None] ^ check[None]).sum(axis=2) <= near_copies.FAR
        assert c.roots(np.arange(300)).tolist() == [int(np.flatnonzero(x).min()) for x in near]
        pairs = np.concatenate(c.pairs())
        assert near[pairs[:, 0], pairs[:, 1]].all()
        again = near_copies.Candidates(check, size)
        again.add(*pairs.T)
        assert again.roots(np.arange(300)).tolist() == c.roots(np.arange(300)).tolist()


def test_fingerprint_is_a_majority_of_bits():
    s = near_copies.shingles(" ".join(f"w{k % 700}" for k in range(900)))
    counts = [sum(int(x) >> b & 1 for x in s) for b in range(64)]
    assert len(s) > 255 and int(near_copies.fingerprint(s)[0]) == sum(1 << b for b in range(64) if 2 * counts[b] > len(s))


def test_pipeline_of_odd_rows(spark, odd, empty):
    import corpus_pipeline as p

    for df in (crowded(odd), empty):
        for _, stage in p.STAGES:
            df = stage(spark, df, SF).cache()
        df.count()
