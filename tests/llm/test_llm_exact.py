"""Operators against brute force, on the smallest documents and on odd texts."""

import hashlib
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from bipercolate.llm import media, mixing, near_dups, packing, pii, quality_model, quality_rules, secrets, token_counts, token_files, tokens
from bipercolate.llm.common import documents

SF = "/root/testdata/sf0.001"
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
SCHEMA_NAMES = [x.split()[0] for x in SCHEMA.split(", ")]
ODD = [None, "", " ", "\n\n", "a", "é" * 300, "x" * 70_000, "a  b \n c", "word " * 3000, "4111 1111 1111 1111", "1.2.3.4.5.6.7.8", "a@b.c_d@e.f", "+1 (555) 123-4567 ", "token = secret : abcdefghijklmnop", "key q9Zk2LmX81vbTr0PwYs3 end", "GB82 WEST 1234 5698 7654 32 bank", "tail\x1c　\x85 mixed 漢字"]


@pytest.fixture(scope="module")
def odd(spark):
    rows = [(k, x, "en", f"s{k % 3}" if k % 4 else None, 0) for k, x in enumerate(ODD)]
    rows += [rows[8], rows[8], (None, "no id at all", None, None, None), (100, "one two three four five six", "en", "s1", 0), (101, "one two three four five six", "en", "s1", 0)]
    return spark.createDataFrame(rows, SCHEMA)


@pytest.fixture(scope="module")
def docs(spark):
    return documents(spark, SF)


@pytest.fixture(params=["docs", "odd"])
def either(request):
    return request.getfixturevalue(request.param)


def rows_of(df):
    return [(r.doc_id, r.text or "") for r in df.collect()]


def test_encoders_equal_the_library():
    rnd = random.Random(3)
    texts = [x or "" for x in ODD] + ["".join(rnd.choice(" \n\tab'sé1漢 .,<-\r\x0b\x1c　\x85") for _ in range(rnd.randint(1, 14))) for _ in range(800)] + ["don't 's <|endoftext|>", "́abc d́"]
    for encoder in (tokens.byte_encoder(tokens.vocabulary("byte_bpe_50k.json")), tokens.word_encoder(tokens.vocabulary("word_bpe_49k.json"))):
        library = encoder.library if hasattr(encoder, "library") else encoder.chunks.tokenizer
        want = [np.array(x.ids, "<u4").tobytes() for x in library.encode_batch(texts, add_special_tokens=False)]
        assert encoder.encode([x.encode() for x in texts]) == want


def test_token_counts_follow_edits():
    rnd = random.Random(2)
    encoder = tokens.byte_encoder(tokens.vocabulary("byte_bpe_50k.json"))
    count = lambda x: len(encoder.library.encode(x, add_special_tokens=False).ids)
    for text in ["", "a b", "the quick brown fox " * 200, "é è  x\n\ny z " * 60]:
        tree = token_counts.CountTree(text.encode(), encoder.encode)
        assert tree.total == count(text)
        for _ in range(25):
            a = rnd.randint(0, len(text))
            b = min(len(text), a + rnd.choice([0, 1, 3, 50, 900]))
            new = rnd.choice(["", "x", " ", "\n", "foo bar", "é", "'s", "the lazy dog " * 40])
            tree.edit(len(text[:a].encode()), len(text[:b].encode()), new.encode())
            text = text[:a] + new + text[b:]
            assert tree.text == text.encode() and tree.total == count(text)


def test_many_edits_encode_each_segment_once(spark):
    encoder = tokens.byte_encoder(tokens.vocabulary("byte_bpe_50k.json"))
    text = "some words here " * 3500
    edits = [(k, k + 4, "x y") for k in range(0, len(text) - 16, 7)]
    new, done = [], 0
    for a, b, x in edits:
        new += [text[done:a], x]
        done = b
    new = "".join([*new, text[done:]])
    tree = token_counts.CountTree(text.encode(), encoder.encode)
    tree.encoded_bytes = 0
    tree.edit_all([(a, b, x.encode()) for a, b, x in edits])
    assert tree.text == new.encode() and tree.total == len(encoder.library.encode(new, add_special_tokens=False).ids)
    assert tree.encoded_bytes <= 1.1 * len(new)
    for _ in range(300):  # insertions at one place
        tree.edit(500, 500, b" and more words to go")
    assert max(tree.sizes[len(tree.sizes) // 2 :]) < 3 * token_counts.SEGMENT
    assert tree.total == len(encoder.library.encode(tree.text.decode(), add_special_tokens=False).ids)
    state = token_counts.build(spark.createDataFrame([(1, text), (None, None)], "doc_id long, text string"))
    edited = token_counts.apply(state.withColumn("edits", F.expr("if(doc_id = 1, array(named_struct('start', 5, 'end', 10, 'text', 'WORDS')), null)"))).collect()
    assert {(r.doc_id, bytes(r.text[:16]), r.n_edits) for r in edited} == {(1, b"some WORDS here ", 1), (None, b"", 0)}
    assert all(r.encoded_bytes < 600 for r in edited)


def test_token_counts_query(either):
    library = tokens.byte_encoder(tokens.vocabulary("byte_bpe_50k.json")).library
    count = lambda x: len(library.encode(x, add_special_tokens=False).ids)
    want = Counter((i, count(x), count(re.sub(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "[EMAIL]", x))) for i, x in rows_of(either))
    assert Counter((r.doc_id, r.n_tokens, r.n_tokens_after) for r in token_counts.count_and_mask(either, pii.EMAIL, "[EMAIL]").collect()) == want


def brute_classes(rows, percent=75):
    shingles, where = {}, defaultdict(list)
    for i, x in rows:
        w = re.sub("[A-Z]", lambda m: m[0].lower(), x).encode().split()
        shingles[i] = {tuple(w[k : k + 5]) for k in range(max(len(w) - 4, 1))} if w else set()
    parent = {i: i for i in shingles}

    def find(a):
        while parent[a] != a:
            a = parent[a]
        return a

    for i, s in shingles.items():
        for g in s:
            where[g].append(i)
    for i, s in shingles.items():
        for j, n in Counter(j for g in s for j in where[g] if i is not None and j is not None and j < i).items():
            if 100 * n >= percent * (len(s) + len(shingles[j]) - n):
                a, b = find(i), find(j)
                parent[max(a, b)] = min(a, b)
    return {i: (len(shingles[i]), find(i)) for i in shingles}


@pytest.mark.parametrize("pairwise", [48, 1])
def test_near_duplicates(either, pairwise, monkeypatch):
    monkeypatch.setattr(near_dups, "PAIRWISE", pairwise)
    monkeypatch.setattr(near_dups, "BLOCK", 2 if pairwise == 1 else 1024)
    monkeypatch.setattr(near_dups, "GROUP_BYTES", 2000 if pairwise == 1 else 4 << 20)
    got = near_dups.classes(either).collect()
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in got} == brute_classes(rows_of(either))
    assert len(got) == either.count() and all(r.kept == (r.doc_id == r.component_id) for r in got)


def test_near_copies_just_above_the_threshold_are_found(spark):
    """Pairs of similarity 0.75 to 0.8: the bands miss one of 200,000, so that none of these may lack its link."""
    rnd, rows, want = random.Random(12), [], {}
    for k in range(150):
        words = [f"w{rnd.randrange(10**6)}" for _ in range(rnd.randint(120, 400))]
        changed = list(words)
        for at in rnd.sample(range(len(words)), max(1, len(words) * (24 + k % 12) // 1000)):
            changed[at] = f"x{rnd.randrange(10**6)}"
        a, b = ({tuple(x[j : j + 5]) for j in range(len(x) - 4)} for x in (words, changed))
        rows += [(2 * k, " ".join(words)), (2 * k + 1, " ".join(changed))]
        want[2 * k + 1] = 2 * k if 100 * len(a & b) >= 75 * len(a | b) else 2 * k + 1
    assert 40 < sum(a != b for a, b in want.items()) < 150
    got = {r.doc_id: r.component_id for r in near_dups.classes(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert {k: got[k] for k in want} == want


def test_files_follow_the_numbers_in_their_names(spark):
    sizes = spark.createDataFrame([(f"part-{k}-x.parquet", 1, 5, k) for k in (99999, 100000, 100001)], "file string, row long, n_tokens long, doc_id long")
    got = {r.doc_id: r.start for r in token_files._starts(sizes, sizes).collect()}
    assert got == {99999: 0, 100000: 5, 100001: 10}


def test_token_files(either, spark, tmp_path):
    library = tokens.byte_encoder(tokens.vocabulary("byte_bpe_50k.json")).library
    rows = sorted(rows_of(either), key=lambda r: (r[0] is not None, r[0]))
    want, start = [], 0
    for i, x in rows:
        ids = np.array([*library.encode(x, add_special_tokens=False).ids, 0], "<u4")
        want.append((i, start, len(ids), zlib.crc32(ids.tobytes())))
        start += len(ids)
    token_files.write(either, str(tmp_path / "t"), delta=True)
    got = token_files.verified(spark, str(tmp_path / "t")).collect()
    assert Counter((r.doc_id, r.start, r.n_tokens, r.ids_crc32) for r in got) == Counter(want)
    assert token_files.metadata(spark, str(tmp_path / "t")).count() == len(rows)
    assert {r.doc_id for r in token_files.slices(spark, str(tmp_path / "t"), 3, 5).collect()} == {3, 4, 5}


def luhn(digits):
    return sum(sum(divmod(int(c) * (1 + k % 2), 10)) for k, c in enumerate(reversed(digits))) % 10 == 0


def personal(x):
    out = [(m.start(), 0, "email", m.end()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", x)]
    out += [(m.start(), 1, "ip", m.end()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", x) if all(int(p) <= 255 for p in m[0].split("."))]
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", x):
        digits = re.sub("[^0-9]", "", m[0])
        if 12 <= len(digits) <= 19 and luhn(digits):
            out.append((m.start(), 2, "card", m.end()))
    return sorted(out + [(m.start(), 3, "phone", m.end()) for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", x) if 9 <= len(re.sub("[^0-9]", "", m[0])) <= 15])


def secret(x):
    out = [(m.start(), 0, "assign", m.end()) for m in re.finditer(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", x, re.I | re.A) if len(m[2]) >= 12]
    out += [(m.start(), 1, "access", m.end()) for m in re.finditer("AKIA[A-Z0-9]+", x) if len(m[0]) >= 18]
    return sorted(out + [(m.start(), 2, "hex", m.end()) for m in re.finditer("[0-9a-f]+", x) if len(m[0]) >= 16])


@pytest.mark.parametrize(("operator", "brute", "base"), [(pii, personal, pii.BASE), (secrets, secret, secrets.BASE)])
def test_spans(either, spark, operator, brute, base):
    rnd = random.Random(5)
    extra = ["".join(rnd.choice("ab@.+-1234567890 ()_é") for _ in range(rnd.randint(1, 60))) for _ in range(300)]
    parts = ["token", "SECRET", "api_key", " ", "=", ":", '"', "abcdef0123456789", "AKIA", "Q9Zk2LmX81", "é", "\n"]
    extra += ["".join(rnd.choice(parts) for _ in range(rnd.randint(1, 30))) for _ in range(300)] + ["7 " * 3000]
    df = either.select("doc_id", "text").union(spark.createDataFrame([(1000 + k, x) for k, x in enumerate(extra)], "doc_id long, text string"))
    want = {}
    for i, x in rows_of(df):
        found = brute(x)
        text = ",".join(f"{k}:{a}:{b}" for a, _, k, b in found)
        want[i] = (hashlib.sha256(text.encode()).hexdigest(), *(sum(s[2] == k for s in found) for k in base))
    got = operator.report(df).collect()
    assert {r.doc_id: (r.base_sha256, *(r[f"n_{k}"] for k in base)) for r in got} == want


def test_added_spans_and_masks(odd):
    by_id = {r.doc_id: r for r in pii.report(odd).collect()}
    assert "iban:0:27" in by_id[15].spans
    masked = {r.doc_id: r.text for r in pii.redacted(odd).collect()}
    assert masked[0] is None and masked[9] == "[CARD]" and masked[15] == "[IBAN] bank" and masked[11] == "[EMAIL][EMAIL]"
    assert "entropy:4:24" in {r.doc_id: r.spans for r in secrets.report(odd).collect()}[14]


def test_ibans_end_where_their_country_says(spark):
    ibans = ["BE68 5390 0754 7034", "ES91 2100 0418 4502 0005 1332", "ES9121000418450200051332", "AT61 1904 3002 3457 3201", "GB82 WEST 1234 5698 7654 32", "NO93 8601 1117 947"]
    rows = [(k, x + after) for k, x in enumerate(ibans) for after in ("", " BIC CAIXESBB", " 2024", " AB")]
    found = pii.report(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert all(f"iban:0:{len(ibans[r.doc_id])}" in r.spans for r in found)


def test_masks_are_the_detectors_spans(spark):
    texts = {
        "part 219-09-9999 stays": "part 219-09-9999 stays", "ssn 219-09-9999": "ssn [SSN]", "sample GB82 WEST 1234 5698 7654 32": "sample GB82 WEST 1234 5698 7654 32",
        "call +1 555 123 4567 10.0.0.1 now": "call [PHONE] [IP] now", "+1 555 123 4567 (4111 1111 1111 1111 10.0.0.1": "[PHONE] ([CARD] [IP]",
        "10.0.0.1 10.0.0.2 a@b.c_d@e.f": "[IP] [IP] [EMAIL][EMAIL]", "é漢 +1 555 123 4567 é": "é漢 [PHONE] é",
        "bank ES91 2100 0418 4502 0005 1332 BIC CAIXESBB": "bank [IBAN] BIC CAIXESBB",
    }
    masked = pii.redacted(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"))
    assert [r.text for r in masked.orderBy("doc_id").collect()] == list(texts.values())
    assert pii.report(masked).agg({f"n_{k}": "sum" for k in pii.BASE}).first() == (0, 0, 0, 0)


def test_mixed_takes_each_row_by_its_own_share(spark):
    text = lambda k: " ".join(f"w{k}x{j}" for j in range(100))
    rows = [(None, text(k), "en", "a" if k < 10 else "b", 0) for k in range(30)] + [(7, text(99), "en", "a", 0)] * 3 + [(7, text(98), "en", "b", 0)]
    df = spark.createDataFrame(rows, SCHEMA)
    weights = spark.createDataFrame([("a", 540.0), ("b", 730.0)], "source string, weight double")
    for budget, want in ((1270, {"a": 540, "b": 730}), (5080, {"a": 2160, "b": 2920})):
        got, cut = Counter(), Counter()
        for r in mixing.mixed(df, weights, budget).collect():
            n = len(r.text.split())
            got[r.source] += n
            cut[r.source] += n < 100
        assert got == want and all(n <= 1 for n in cut.values())


def test_random_tokens_behind_prefixes_are_secrets(spark):
    rnd = random.Random(9)
    low, mixed = "abcdefghijklmnopqrstuvwxyz0123456789", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789"
    forms = [("ghp_", 36, mixed), ("sk_live_", 24, mixed), ("xoxb-", 24, mixed), ("glpat-", 20, mixed + "-_"), ("pypi-", 60, mixed + "-_"), ("hf_", 34, mixed), ("xoxb-", 24, low), *[("", n, mixed + "+/") for n in (40, 64, 88)]]
    bodies = [(before + "".join(rnd.choice(letters) for _ in range(n - 2)) + "7q", before) for before, n, letters in forms for _ in range(100)]
    clean = ["release-notes-of-2024-05-12", "usr/share/lib/python/3/dist-packages", "/blog/2024/05/12/how-to-write-tests/", "123e4567-e89b-12d3-a456-426614174000"]
    rows = [(k, f"key {x} end") for k, x in enumerate([x for x, _ in bodies] + clean)]
    found = {r.doc_id: f"entropy:4:{4 + len(rows[r.doc_id][1]) - 8}" in r.spans for r in secrets.report(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert [x for k, (x, _) in enumerate(bodies) if not found[k]] == []
    assert not any(found[len(bodies) + k] for k in range(len(clean)))


def test_window_entropy_equals_counting(spark):
    rnd = random.Random(4)
    texts = ["".join(rnd.choice("abc123XYZ/+"[: rnd.randint(1, 11)]) for _ in range(rnd.choice([20, 21, 219, 220, 221, 700]))) for _ in range(60)]

    def brute(text, width=secrets.WINDOW):
        windows = [Counter(text[k : k + width]).values() for k in range(len(text) - width + 1)]
        return max(-sum(c / width * np.log2(c / width) for c in w) for w in windows)

    rows = spark.createDataFrame([(x,) for x in texts], "t string")
    for r in rows.select("t", secrets.window_entropy(F.col("t")).alias("e")).collect():
        assert abs(r.e - brute(r.t)) < 1e-9


def test_long_runs_neither_crash_nor_crawl(spark):
    n, rnd = 1_000_000, random.Random(6)
    blob = "".join(rnd.choices("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/", k=n))
    texts = {blob: "entropy", "1a" + "/a" * (n // 2): "", "1a" + "-a" * (n // 2): "", "a" * n + "1": "hex", "zz/1-" * (n // 5): "", "a@" * 10_000: "", "+1 " * 10_000: ""}
    rows = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(len(texts))
    found = {r.doc_id: r.spans.split(":")[0] for r in secrets.report(rows).collect()}
    assert [found[k] for k in range(len(texts))] == list(texts.values())
    assert pii.report(rows).count() == len(texts)


def test_quality_rules(either):
    def brute(x):
        w = re.findall(r"[^\x20\x09-\x0D]+", x)
        seen, marked = Counter(tuple(w[i : i + 8]) for i in range(len(w) - 7)), set()
        for i in range(len(w) - 7):
            if seen[tuple(w[i : i + 8])] > 1:
                marked.update(range(i, i + 8))
        lines = [y for y in x.split("\n") if re.search(r"[^\x20\x09-\x0D]", y)]
        return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", x)), len(lines) - len(set(lines)), len(marked)

    got = quality_rules.measure(either).collect()
    assert Counter((r.doc_id, r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) for r in got) == Counter((i, *brute(x)) for i, x in rows_of(either))
    assert all(r.base_failed == (r.n_words < 20 or 100 * r.n_repeat_words > 30 * r.n_words) and not (r.base_failed and r.kept) for r in got)
    kept = quality_rules.accepted(either)
    assert kept.columns == either.columns and kept.count() == sum(r.kept for r in got)


def test_bands_reject_what_no_language_looks_like(spark):
    rnd = random.Random(4)
    docs = documents(spark, "/root/testdata/sf0.01")
    words = lambda n, letters: " ".join("".join(rnd.choice(letters) for _ in range(rnd.randint(2, 9))) for _ in range(n))
    blob = lambda n: " ".join("".join(rnd.choice("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/") for _ in range(60)) for _ in range(n))
    garbled = [words(150, "абвгдежзийклмнопрстуфхцчшщыьэюя").encode().decode("cp1252", "replace") for _ in range(5)]
    junk = [words(200, "abcdefghijklmnopqrstuvwxyz") for _ in range(10)] + [blob(40) for _ in range(10)] + garbled
    rows = [(10**9 + k, x, "en" if k < 20 else "de", "s1", len(x)) for k, x in enumerate(junk)]
    got = {r.doc_id: r for r in quality_rules.measure(docs.select(*SCHEMA_NAMES).unionByName(spark.createDataFrame(rows, SCHEMA))).collect()}
    assert [k for k, r in enumerate(rows) if got[r[0]].kept or got[r[0]].base_failed] == []
    labels = {r.doc_id: r.quality for r in spark.read.parquet("/root/testdata/sf0.01/labels.parquet").collect()}
    passed = {q: [got[i].kept for i, x in labels.items() if x == q and i in got and not got[i].base_failed] for q in (0, 1)}
    assert all(passed[1]) and sum(passed[0]) < 0.7 * len(passed[0])


def test_quality_model(spark, docs):
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    scores = quality_model.scored(docs, quality_model.train(docs, labels)).collect()
    assert all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.3) and r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in scores)
    big = documents(spark, "/root/testdata/sf0.01")
    known = spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    report = quality_model.evaluate(quality_model.scored(big, quality_model.train(big, known)), known).first()
    assert report.accuracy > 0.95
    none = quality_model.train(docs, labels.filter("false"))
    assert none.score(quality_model.features(b"")) == 0.5


def brute_targets(sizes, most=3):
    names = sorted((s for s in sizes if s is not None), key=lambda s: s.encode()) + [None] * (None in sizes)
    weight = {s: 1 + k % 3 for k, s in enumerate(names)}
    stopped, total = set(), sum(sizes.values())
    while True:
        rest = total - most * sum(sizes[s] for s in stopped)
        weights = sum(weight[s] for s in names if s not in stopped)
        share = {s: most * sizes[s] if s in stopped else rest * weight[s] / weights for s in names}
        more = {s for s in names if share[s] > most * sizes[s] + 1e-9} - stopped
        if not more:
            return share
        stopped |= more


def test_mixing(either):
    rows = mixing.mix(either).collect()
    sizes, took, source, target = Counter(), Counter(), {}, {}
    words = [(r.doc_id, r.source, len((r.text or "").encode().split())) for r in either.collect()]
    for i, s, n in words:
        sizes[s] += n
        source[i] = s
    want = brute_targets(dict(sizes))
    for r in rows:
        took[source[r.doc_id]] += r.taken
        target[source[r.doc_id]] = r.target
        assert 0 <= r.taken <= 3 * r.size and r.source_size == sizes[source[r.doc_id]]
    assert Counter((r.doc_id, r.size) for r in rows) == Counter((i, n) for i, _, n in words)
    for s, t in want.items():
        assert abs(target[s] - t) < 1e-6 * max(t, 1) and abs(took[s] - t) <= 1
    assert sorted(map(tuple, mixing.mix(either.repartition(3)).collect()), key=repr) == sorted(map(tuple, rows), key=repr)
    mixed = Counter()
    for r in mixing.mixed(either).collect():
        mixed[r.doc_id] += len(r.text.encode().split())
    by_id = Counter()
    for r in rows:
        by_id[r.doc_id] += r.taken
    assert all(abs(mixed[i] - n) <= 2 for i, n in by_id.items())


def test_the_mix_ends_at_the_budget(spark):
    """The global order by finish time, cut by a prefix sum, against a plain loop."""
    rnd = random.Random(5)
    rows = [(k if k % 7 else None, " ".join(["w"] * rnd.randint(0, 30)) + f" t{k}", "en", rnd.choice("abc"), 0) for k in range(150)]
    df = spark.createDataFrame(rows, SCHEMA)
    queue = mixing.queues(df)
    every = mixing.copies(queue.light, queue)
    copies = sorted((c["finish"], r["__source"], c["pass"], r["__before"], c["words"]) for r in every.collect() for c in r["__copies"])
    for budget in (0, 1, 700, sum(c[-1] for c in copies) - 1, 10**9):
        left, want = budget, Counter()
        for finish, source, turn, before, n in copies:
            want[source, before] += min(n, max(left, 0))
            left -= n
        end = mixing._end(every, budget)
        cut = mixing.copies(queue.light, mixing.Queues(queue.light, queue.aimed, end))
        got = Counter({(r["__source"], r["__before"]): sum(c["words"] for c in r["__copies"]) for r in cut.filter("__size > 0").collect()})
        assert +got == +want and (end is None) == (budget == 10**9)


def test_packing(either):
    library = tokens.word_encoder(tokens.vocabulary("word_bpe_49k.json")).chunks.tokenizer
    ids = {i: np.array([*library.encode(x, add_special_tokens=False).ids, 1], "<u4") for i, x in rows_of(either)}
    found = packing.pack(either).collect()
    filled = defaultdict(list)
    for r in found:
        piece = ids[r.doc_id][r.start : r.start + r.length]
        assert len(piece) == r.length and r.ids_crc32 == zlib.crc32(piece.tobytes()) and r.doc_tokens == len(ids[r.doc_id])
        filled[r.sequence_id].append((r.offset, r.length))
    for parts in filled.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 2048
    assert sum(r.length for r in found) == sum(len(ids[i]) for i, _ in rows_of(either))


def test_cutting_stock_is_near_its_bound():
    rng = np.random.default_rng(1)
    sizes = np.arange(1, 129)
    demand = rng.poisson(40, 128)
    plan = packing.rounded(sizes, demand, 128)
    held = np.zeros(128, int)
    for times, counts in plan:
        assert sum(sizes[i] * n for i, n in counts.items()) <= 128
        for i, n in counts.items():
            held[i] += times * n
    assert (held == demand).all() and sum(t for t, _ in plan) <= 1.01 * -(-(sizes @ demand) // 128) + 2


def test_media(either):
    texts = dict(rows_of(either))
    got = media.round_trip(either).collect()
    assert Counter(r.doc_id for r in got) == Counter(i for i, _ in rows_of(either))
    for r in got:
        p = media.payload(texts[r.doc_id].encode())
        assert len(p) % 576 == 0 and len(p) > 0
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(texts[r.doc_id].encode()), len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-32:]))
        assert (r.media_bytes, r.media_sha256) == (len(p) + 44, hashlib.sha256(media.media(p)).hexdigest()) and r.feature == media.feature(p)


def test_media_by_shuffle(odd, spark, tmp_path):
    """The path for more lenders and borrowers than may be broadcast gives the same rows."""
    media.write(odd, str(tmp_path / "m"), broadcast=0)
    assert media.read(spark, str(tmp_path / "m"), broadcast=0).count() == odd.count()


def test_empty_tables(spark):
    none = spark.createDataFrame([], SCHEMA)
    for f in (near_dups.classes, token_files.round_trip, pii.report, secrets.report, quality_rules.measure, mixing.mix, mixing.mixed, packing.pack, media.round_trip, token_counts.build, pii.redacted, quality_rules.accepted, near_dups.deduplicated):
        assert f(none).count() == 0, f


def test_clashing_columns(odd):
    from pyspark.sql import functions as F

    wide = odd.withColumns({c: F.lit(1) for c in ("size", "before", "node", "label", "band", "key", "match", "pii", "n", "target")})
    assert near_dups.deduplicated(wide).columns == wide.columns and mixing.mixed(wide).columns == wide.columns
    assert quality_rules.accepted(wide).columns == wide.columns and pii.redacted(wide).columns == wide.columns
    assert packing.pack(wide).count() == packing.pack(odd).count() and media.round_trip(wide).count() == odd.count()
