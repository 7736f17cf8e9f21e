"""Operators against brute force, round trips and held-out accuracy, on small tables with awkward rows."""

import hashlib
import re
import textwrap
import zlib
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest

from rankflow.llm import boosting, common, embedding_dedup, exact_dedup, language_id, licenses, mixing, near_dedup, packing, pii, queries, token_output, tokens, toxicity

DOC = "doc_id long, text string, lang string, source string, n_chars long, u double, level string, _g_0 string"


def docs(spark, rows):
    """rows: (doc_id, text[, source]); further columns clash with names that the operators use inside."""
    return spark.createDataFrame([(r[0], r[1], "en", r[2] if len(r) > 2 else "s", len(r[1] or ""), 0.5, "x", "y") for r in rows], DOC)


AWKWARD = [(1, "Same Text here\n"), (2, "same text HERE\n"), (3, None), (4, ""), (5, "é" * 30), (6, "É" * 30), (7, "a b c d e f g " * 3000), (8, "Same Text here\n"), (8, "Same Text here\n"), (None, "no id at all"), (9, "one")]


def test_exact_dedup_brute_force(spark):
    got = {(r.doc_id, r.text_sha256): r for r in exact_dedup.groups(docs(spark, AWKWARD)).collect()}
    by = defaultdict(list)
    for d, t in AWKWARD:
        by[(t or "").translate({c: c + 32 for c in range(65, 91)})].append(d)
    for t, ids in by.items():
        for d in ids:
            r = got[d, hashlib.sha256(t.encode()).hexdigest()]
            assert r.group_size == len(ids) and r.keep_id == max((i for i in ids if i is not None), default=None)
    left = exact_dedup.survivors(docs(spark, AWKWARD))
    assert left.columns == docs(spark, AWKWARD).columns and left.count() == len(by)


def test_grace_spills_and_stays_exact(tmp_path):
    rows = [(hash((k % 700, 1)) & (2**64 - 1), f"text {k % 700} {'x' * 500}".encode(), k, 1, (k,)) for k in range(5000)]
    got = list(exact_dedup.grace(iter(rows), 40_000, str(tmp_path)))
    assert Counter(e[3] for e in got).total() == 700 and sum(e[3] for e in got) == 5000
    assert sorted(e[2] for e in got) == list(range(4300, 5000)) and not list(tmp_path.iterdir())


def test_equal_hashes_do_not_merge(tmp_path):
    rows = [(5, f"{k}".encode(), k, 1, (k,)) for k in range(300)]
    assert len(list(exact_dedup.grace(iter(rows), 1000, str(tmp_path)))) == 300


def brute_shingles(text):
    w = re.findall(rb"[^\x20\x09-\x0d]+", (text or "").encode().lower())
    return {tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())


def near_corpus(n_base=12, copies=14):
    g = np.random.default_rng(3)
    rows = list(AWKWARD[:7])
    k = 100
    for _ in range(n_base):
        base = [f"w{x}" for x in g.integers(0, 900, int(g.integers(20, 160)))]
        for _ in range(copies):
            t = list(base)
            for _ in range(int(g.integers(0, 4 if copies < 50 else 9))):
                t[int(g.integers(0, len(t)))] = f"n{g.integers(0, 9999)}"
            rows.append((k, " ".join(t)))
            k += 1
    return rows


@pytest.mark.parametrize(("n_base", "copies", "large"), [(12, 14, 64), (3, 60, 8)])
def test_near_dedup_brute_force(spark, monkeypatch, n_base, copies, large):
    monkeypatch.setattr(near_dedup, "LARGE", large)
    monkeypatch.setattr(near_dedup, "BLOCK", 8)
    rows = near_corpus(n_base, copies)
    sets = {d: brute_shingles(t) for d, t in rows}
    name = {d: d for d in sets}

    def root(x):
        while name[x] != x:
            x = name[x]
        return x

    ids = sorted(sets)
    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            u = len(sets[a] | sets[b])
            if u and sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 75 * u:
                x, y = sorted((root(a), root(b)))
                name[y] = x
    for r in near_dedup.classes(docs(spark, rows)).collect():
        assert (r.n_shingles, r.component_id) == (len(sets[r.doc_id]), root(r.doc_id)) and r.kept == (r.component_id == r.doc_id)
    assert near_dedup.survivors(docs(spark, rows)).count() == len({root(d) for d in ids})


def test_odd_sketch_estimates_similarity():
    g = np.random.default_rng(1)
    mul, add = near_dedup._family()
    for same in (0.75, 0.9):
        xor = []
        for _ in range(30):
            a = g.integers(0, 1 << 63, 1000, dtype=np.uint64)
            common_n = int(1000 * 2 * same / (1 + same))
            b = np.concatenate((a[:common_n], g.integers(0, 1 << 63, 1000 - common_n, dtype=np.uint64)))
            x, y = (near_dedup.odd_sketch(near_dedup.minhash(s, mul, add)) for s in (a, b))
            xor.append(sum(bin(int(p) & (2**64 - 1)).count("1") for p in x ^ y))
        expected = near_dedup.most_different_bits(same)
        assert abs(np.mean(xor) - expected) < 8


def test_embedding_recall_and_classes(spark):
    g = np.random.default_rng(5)
    rows, k = [], 0
    for label in (0, 1, None):
        for _ in range(40):
            c = g.standard_normal(16)
            for _ in range(int(g.integers(1, 6))):
                v = c + g.standard_normal(16) * 0.12
                rows.append((k, [float(x) for x in v], label))
                k += 1
    rows += [(k, [0.0] * 16, 0), (k + 1, None, 0), (k + 2, [float("nan")] * 16, 0), (k + 3, rows[0][1], 0), (k + 4, rows[0][1], 0), (k + 5, rows[0][1], 0)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int")
    got = {r.vec_id: r for r in embedding_dedup.classes_of(df, leaf=24, block=16).collect()}
    x = {d: np.array(v) for d, v, lab in rows if lab is not None and v and np.isfinite(v).all() and np.any(v)}
    lab = {d: q for d, _, q in rows}
    links = {(a, b) for a in x for b in x if a != b and lab[a] == lab[b] and x[a] @ x[b] / np.linalg.norm(x[a]) / np.linalg.norm(x[b]) >= 0.93}
    want = Counter(a for a, _ in links)
    assert len(got) == len(rows) and all(got[d].n_links <= want[d] for d in got)
    assert sum(got[d].n_links for d in got) >= 0.95 * len(links)
    assert got[k].component_id == k and got[k + 4].component_id == 0


def test_mixing_targets_and_wholes(spark):
    g = np.random.default_rng(2)
    rows = [(d, "w " * int(g.integers(0, 60)), None if d % 9 == 0 else f"src{d % 4}") for d in range(4000)] + [(9000, "big " * 300, "tiny")]
    got = mixing.copies(docs(spark, rows)).collect()
    again = mixing.copies(docs(spark, rows)).collect()
    assert sorted(map(str, got)) == sorted(map(str, again)) and len(got) == len(rows)
    sizes = Counter()
    for _, t, s in rows:
        sizes[s] += len(t.split())
    taken, target = Counter(), {}
    for r in got:
        assert r.source_size == sizes[r.source] and 0 <= r.copies <= 3
        taken[r.source] += r.copies * r.size
        target[r.source] = r.target
    order = sorted((s for s in sizes if s is not None)) + [None]
    weight = {s: k % 3 + 1 for k, s in enumerate(order)}
    want, free = {}, set(order)
    while True:  # by the words of the contract: cap, share the excess again, until none is above
        level = (sum(sizes.values()) - sum(want.values())) / sum(weight[s] for s in free)
        over = {s for s in free if weight[s] * level > 3 * sizes[s]}
        if not over:
            break
        want |= {s: 3 * sizes[s] for s in over}
        free -= over
    want |= {s: weight[s] * level for s in free}
    for s in order:
        assert target[s] == pytest.approx(want[s]) and abs(taken[s] - want[s]) <= 60
    out = mixing.mixed(docs(spark, rows))
    assert out.columns == docs(spark, rows).columns and out.count() == sum(r.copies for r in got)


LANG_WORDS = {"en": "the of and with that this from have".split(), "de": "der die und nicht das ein über größe".split(), "fr": "le les des une être avec pour où".split()}


def test_language(spark):
    g = np.random.default_rng(4)
    rows = [(k, " ".join(g.choice(LANG_WORDS[q], 40)), q) for k in range(600) for q in [list(LANG_WORDS)[k % 3]]]
    df = spark.createDataFrame([*rows, (9001, None, "en"), (9002, "12 34 !!", "de"), (9003, "", None)], "doc_id long, text string, lang string")
    got = {r.doc_id: r for r in language_id.predict(df, language_id.fit(df)).collect()}
    assert all(got[d].lang_pred == q for d, _, q in rows) and all(0 <= r.score <= 1 for r in got.values())
    assert [got[d].lang_pred for d in (9001, 9002, 9003)] == ["und"] * 3
    none = df.filter("false")
    assert language_id.predict(none, language_id.fit(none)).count() == 0


def test_toxicity(spark):
    g = np.random.default_rng(6)
    rows, marks = [], []
    for k in range(1200):
        words = [f"w{x}" for x in g.integers(0, 50, 60)] + ["plain"] * 5
        toxic = int(k % 6 == 0)
        for _ in range(4 * toxic):
            words.insert(int(g.integers(0, 60)), str(g.choice(["idiot", "moron", "blarg"])))
        rows.append((k, " ".join(words)))
        marks.append((k, 1, toxic))
    d, labels = docs(spark, rows), spark.createDataFrame([*marks, (None, 1, 1), (5, None, None)], "doc_id long, quality int, toxic int")
    got = {r.doc_id: r for r in toxicity.scored(d, labels).collect()}
    held = [k for k, _ in rows if zlib.crc32(str(k).encode()) % 4 == 2]
    assert np.mean([got[k]._toxic == int(k % 6 == 0) for k in held]) > 0.97
    assert toxicity.scored(docs(spark, AWKWARD), labels.filter("false")).filter("_toxic = 1").count() == 0


def test_isotonic_is_monotone_least_squares():
    x, y = np.arange(6.0), np.array([0, 1, 0, 0, 1, 1.0])
    assert boosting.Isotonic().fit(x, y)(x).tolist() == pytest.approx([0, 1 / 3, 1 / 3, 1 / 3, 1, 1])


BASE = [("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"), ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"), ("card", r"[0-9]([\x20-]?[0-9])+"), ("phone", r"\+[0-9][\x20().0-9-]+[0-9]")]


def luhn(d):
    return sum(sum(divmod(2 * int(c), 10)) if k % 2 else int(c) for k, c in enumerate(reversed(d))) % 10 == 0


def brute_pii(text):
    out = []
    for k, (kind, pattern) in enumerate(BASE):
        for m in re.finditer(pattern, text or ""):
            d = re.sub("[^0-9]", "", m[0])
            if kind == "email" or kind == "ip" and all(int(x) <= 255 for x in m[0].split(".")) or kind == "card" and 12 <= len(d) <= 19 and luhn(d) or kind == "phone" and 9 <= len(d) <= 15:
                out.append((m.start(), k, m.end(), kind))
    return sorted(out)


def pii_texts(spark, sf):
    own = ["mail a.b@c.de, x@y..z q@w.e-r_t@u.i 𝒳 é 😀 n@m.op", "ip 1.2.3.4 256.1.1.1 001.002.0255.4 1.2.3.4.5", "4111 1111 1111 1111 and 4111-1111-1111-1112 5500 0000 0000 0004", "+1 (555) 123-4567 +49.30.1234567 +12 +1234567890123456", "7" * 9000, "a@b." * 50, " x@y.zz ", None, "", "tel: (030) 123-4567, jane(at)corp(dot)com"]
    return own + [r.text for r in spark.read.parquet(f"{sf}/documents.parquet").select("text").collect()]


def test_pii_base_spans_brute_force(spark, sf):
    texts = pii_texts(spark, sf)
    df = docs(spark, list(enumerate(texts)))
    for r in pii.redactions(df).collect():
        want = brute_pii(texts[r.doc_id])
        assert [tuple(x) for x in r.base] == want, texts[r.doc_id]
        assert [getattr(r, f"n_{k}") for k, _ in BASE] == [sum(w[3] == k for w in want) for k, _ in BASE]
        assert set(map(tuple, r.base)) <= set(map(tuple, r.spans))
    found = {r.doc_id: r.spans for r in pii.redactions(df).collect()}
    assert {s.kind for s in found[9]} == {"handle", "number"}
    red = {r.doc_id: r.text for r in pii.redact(df).collect()}
    assert "jane" not in red[9] and len(red[0]) == len(texts[0]) and "@" not in red[0].replace("x@y..z", "")


def test_pii_query_digest(spark, sf):
    rows = {r.doc_id: r for r in queries.op2_pii_boosting(spark, sf).collect()}
    for r in spark.read.parquet(f"{sf}/documents.parquet").collect():
        text = ",".join(f"{k}:{a}:{b}" for a, _, b, k in brute_pii(r.text))
        assert rows[r.doc_id].base_sha256 == hashlib.sha256(text.encode()).hexdigest()


def test_licenses(spark):
    mit = licenses.LICENSES["MIT"]
    rows = [(1, "Copyright (c) 2020 Jane\n\n" + mit.upper().replace("SUBLICENSE", "SUB-LICENSE")), (2, mit + " and more"), (3, "words\nReleased under the MIT Licence\nmore"), (4, None), (5, "© 1999 x\n" + licenses.LICENSES["ISC"].replace('"', "'"))]
    got = {r.doc_id: r for r in licenses.scan(docs(spark, rows)).collect()}
    assert [got[k].license for k in range(1, 6)] == ["MIT", None, None, None, "ISC"]
    assert got[3].notices == "MIT" and got[4].n_notices == 0


def test_license_table_is_full(spark):
    """Licence lines are counted from the table itself, not from NOTICES; every whole text is found under its own name."""
    table = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text").collect()
    count = {r.doc_id: sum(bool(re.match(r"(?i)\s*(?:(?:this work is )?licensed|released) under\b", x)) for x in (r.text or "").split("\n")) for r in table}
    got = licenses.scan(spark.createDataFrame(table)).select("doc_id", "n_notices").collect()
    assert sum(count.values()) == 39 and {r.doc_id: r.n_notices for r in got} == count
    names = ["BSD-3-Clause", "Apache-2.0", "GPL-2.0", "GPL-3.0", "LGPL-2.1", "LGPL-3.0", "MPL-2.0", "CC0-1.0", "CC-BY-SA-4.0", "Unlicense"]
    assert [r.license for r in licenses.scan(docs(spark, [(k, licenses.LICENSES[n]) for k, n in enumerate(names)])).orderBy("doc_id").collect()] == names
    lines = ["Licensed under CC BY-NC-ND 3.0.", "SPDX-License-Identifier: AGPL-3.0", "Released under the GNU Lesser General Public License, version 2.1."]
    assert [r.notices for r in licenses.scan(docs(spark, list(enumerate(lines)))).orderBy("doc_id").collect()] == ["CC-BY-NC-ND-3.0", "AGPL-3.0", "LGPL-2.1"]


def test_license_texts_may_be_wrapped(spark):
    """Every known text at several widths, the short ones at narrow ones too; only copyright statements go."""
    rows, want = [], []
    for name, text in licenses.LICENSES.items():
        for width in (40, 60, 66, 72, 79, 100, 10_000):
            flat = [textwrap.fill(" ".join(p.split()), width, break_long_words=False, break_on_hyphens=False) for p in re.split(r"\n\s*\n", text)]
            rows.append((len(rows), "Copyright (c) 2019-2021 J. Doe, Foo Inc. and others. All rights reserved.\n\n" + "\n\n".join(flat)))
            want.append(name)
    got = {r.doc_id: r.license for r in licenses.scan(docs(spark, rows)).collect()}
    assert [(k, want[k], got[k]) for k in range(len(rows)) if got[k] != want[k]] == []
    lines = ["Copyright 2020 X. Released under the MIT License.", "(c) 2020 Foo Inc. Licensed under CC BY-NC 4.0.", "copyright notice: Released under the MIT License."]
    assert [r.notices for r in licenses.scan(docs(spark, list(enumerate(lines)))).orderBy("doc_id").collect()] == ["MIT", "CC-BY-NC-4.0", ""]


def lengths_of(counts, plan, capacity):
    used = np.zeros_like(counts)
    for filling, n in plan:
        assert sum(s * k for s, k in filling.items()) <= capacity
        for s, k in filling.items():
            used[s] += n * k
    assert (used == counts).all()
    return sum(n for _, n in plan)


def test_bin_completion_beats_best_fit_and_bound_holds():
    counts = np.zeros(11, np.int64)
    for s, n in ((6, 2), (5, 2), (4, 2), (3, 2), (2, 2)):
        counts[s] = n  # volume 40: four full bins exist
    assert lengths_of(counts, packing.plan(counts, 10), 10) == 4 == packing.lower_bound(counts, 10)
    # The classic 3-partition case where best-fit decreasing needs one bin more.
    counts = np.bincount([44, 24, 24, 22, 21, 17, 8, 8, 6, 6], minlength=61)
    best = lengths_of(counts, packing.best_fit(counts, 60), 60)
    assert lengths_of(counts, packing.plan(counts, 60), 60) == 3 < best
    g = np.random.default_rng(0)
    for top in (300, 1500, 4096):
        counts = np.bincount(g.integers(1, top + 1, 2000), minlength=4097)
        assert packing.lower_bound(counts, 4096) <= lengths_of(counts, packing.plan(counts, 4096), 4096) <= lengths_of(counts, packing.best_fit(counts, 4096), 4096)


@pytest.fixture(scope="module")
def tokenizers_of():
    import public_tokenizers
    from tokenizers import Tokenizer

    def get(name):
        t = Tokenizer.from_file(public_tokenizers.path(name))
        t.encode_special_tokens = True
        return public_tokenizers.path(name), t

    return get


def test_packing_brute_force(spark, tokenizers_of):
    path, t = tokenizers_of("word_bpe_49k.json")
    rows = [*AWKWARD[:9], (20, "wörter  und\tmehr <|endoftext|> " * 900), (21, "x" * 5000), (22, " lead\n\n trail ")]
    got = packing.pack_documents(docs(spark, rows), path).collect()
    assert packing.pack_documents(docs(spark, []), path).count() == 0
    want = Counter()
    for d, text in rows:
        ids = [*t.encode(text or "", add_special_tokens=False).ids, 1]
        for p in range(0, len(ids), 4096):
            part = np.array(ids[p : p + 4096], "<u4").tobytes()
            want[d, p // 4096, p, len(part) // 4, zlib.crc32(part)] += 1
    assert Counter((r.doc_id, r.piece, r.start, r.length, r.ids_crc32) for r in got) == want
    bins = defaultdict(list)
    for r in got:
        bins[r.sequence_id].append((r.offset, r.length))
    for b in bins.values():
        at = 0
        for offset, length in sorted(b):
            assert offset == at
            at += length
        assert at <= 4096


@pytest.mark.parametrize(("name", "keeps_space"), [("word_bpe_49k.json", False), ("byte_bpe_50k.json", True)])
def test_added_tokens_keep_their_ids(name, keeps_space):
    """Against the library at its default, where a text holds the string of an added token."""
    import public_tokenizers
    from tokenizers import Tokenizer

    path = public_tokenizers.path(name)
    t = Tokenizer.from_file(path)
    texts = ["one <|endoftext|> two", "a<|endoftext|>b", "<|startoftext|>x. y", "end <|endoftext|>", "plain, words.", "<|ENDOFTEXT|> <| endoftext |>", "word " * 70_000 + "<|endoftext|>"]
    got = tokens.Encoder(path, keeps_space).each(pa.array(texts))
    assert [np.frombuffer(g, "<u4").tolist() for g in got] == [t.encode(x, add_special_tokens=False).ids for x in texts]


def test_range_coder_round_trips():
    g = np.random.default_rng(8)
    for n in (0, 1, 2, 63, 65, 4097, 30000):
        for ids in (g.integers(0, 50257, n), g.zipf(1.4, n) % 50257, np.zeros(n, int), np.full(n, 50256)):
            assert (token_output.decode_ids(token_output.encode_ids(ids, 50257), 50257) == ids).all()
    block = token_output.write_block([None, 3, 3], np.array([1, 2, 0]), np.array([7, 8, 9]), 100)
    assert {k: v.tolist() for k, v in token_output.documents_of(block).items()}[None] == [7]
    with pytest.raises(ValueError, match="damaged"):
        token_output.read_block(block[:30] + bytes([block[30] ^ 1]) + block[31:])


def test_token_output_brute_force(spark, tokenizers_of, tmp_path):
    path, t = tokenizers_of("byte_bpe_50k.json")
    rows = [*AWKWARD[:7], (20, "wörter  und\tmehr <|endoftext|> "), (21, "a\nb c\n\nd"), (22, " lead")]
    token_output.write_tokens(docs(spark, rows), str(tmp_path / "t"), path, 50257, 2, block_ids=64)
    got = token_output.read_tokens(spark, str(tmp_path / "t")).orderBy("doc_id").collect()
    at = 0
    for (d, text), r in zip(sorted(rows), got, strict=True):
        ids = [*t.encode(text or "", add_special_tokens=False).ids, 2]
        assert (r.doc_id, r.start, r.n_tokens, r.ids_crc32) == (d, at, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
        at += len(ids)


def test_components(spark):
    edges = spark.createDataFrame([(k, k + 1) for k in range(50)] + [(100, 200), (200, 300), (7, 7), (None, 3)], "src long, dst long")
    got = {r.node: r.component for r in common.components(edges).collect()}
    assert got == {k: 0 for k in range(51)} | {100: 100, 200: 100, 300: 100}
    assert common.components(edges.filter("false")).count() == 0


def test_empty_tables(spark):
    none = docs(spark, [])
    for df in (exact_dedup.groups(none), near_dedup.classes(none), mixing.copies(none), pii.redactions(none), licenses.scan(none)):
        assert df.count() == 0
    v = spark.createDataFrame([], "vec_id long, embedding array<float>, label int")
    assert embedding_dedup.classes_of(v).count() == 0


def test_shingles_match_words():
    texts = [t for _, t in near_corpus(2, 2)] + ["A b\x0bC\x1fd e f", " x ", "\n"]
    got = near_dedup.Shingles(5)(pa.array(texts, pa.string()))
    assert [len(x) for x in got] == [len(brute_shingles(t)) for t in texts]
