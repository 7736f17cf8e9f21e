"""The methods behind the operators against plain versions of them, and cases that the contracts leave to the docstrings."""

import re
import zlib
from collections import Counter
from itertools import combinations

import numpy as np
import pyarrow as pa
import pytest

from rankflow.llm import boosting, embedding_dedup, exact_dedup, language_id, licenses, mixing, near_dedup, packing, pii, token_output, tokens, toxicity


@pytest.mark.parametrize(("name", "keeps_space"), [("word_bpe_49k.json", False), ("byte_bpe_50k.json", True)])
def test_merging_many_words_at_once_matches_the_library(name, keeps_space):
    import public_tokenizers
    from tokenizers import Tokenizer

    path = public_tokenizers.path(name)
    g = np.random.default_rng(3)
    letters = list("abcdefghijklmnopqrstuvwxyzABCXYZéèßñÉÜø")
    texts = [" ".join("".join(g.choice(letters, int(g.integers(1, 30)))) for _ in range(200)) for _ in range(20)]
    texts += ["Words, with marks. And% more$$$ of&&& them!! (so) it's don't 12.5 a-b x_y", "aaaaaaaaaaaaaaaa " * 50, "", None, "İstanbul K Å ﬁ ŉ ǅ", "a\nb c\n\nd", "é É"]
    for added in (True, False):
        t = Tokenizer.from_file(path)
        t.encode_special_tokens = not added
        rows = [*texts, "one <|endoftext|> two"]
        got = [np.frombuffer(x, "<u4").tolist() for x in tokens.Encoder(path, keeps_space, added, most=500).each(pa.array(rows, pa.string()), 2000)]
        assert got == [t.encode(x or "", add_special_tokens=False).ids for x in rows]


def fewest(sizes, capacity):
    best = [len(sizes)]

    def go(k, rooms):
        if len(rooms) >= best[0]:
            return
        if k == len(sizes):
            best[0] = len(rooms)
            return
        for j, room in enumerate(rooms):
            if room >= sizes[k] and room not in rooms[:j]:
                go(k + 1, (*rooms[:j], room - sizes[k], *rooms[j + 1 :]))
        go(k + 1, (*rooms, capacity - sizes[k]))

    go(0, ())
    return best[0]


def test_branch_and_bound_proves_the_fewest_bins():
    g, better = np.random.default_rng(1), 0
    for turn in range(150):
        capacity = int(g.integers(20, 60))
        sizes = g.integers(1, capacity + 1, 9) if turn % 2 else g.integers(capacity // 5, capacity // 2 + 2, 11)
        counts = np.bincount(sizes, minlength=capacity + 1)
        plan, proved = packing.search(counts, capacity)
        held = Counter()
        for filling, n in plan:
            assert sum(s * k for s, k in filling.items()) <= capacity
            held.update({s: n * k for s, k in filling.items()})
        assert held == Counter(sizes.tolist()) and proved
        used = sum(n for _, n in plan)
        assert used == fewest(sorted(sizes.tolist(), reverse=True), capacity)
        better += used < sum(n for _, n in packing.best_fit(counts, capacity))
    assert better > 3


def test_dominated_fillings():
    left = np.bincount([9, 7, 6, 5, 3, 2, 2], minlength=13)
    sizes = np.flatnonzero(left)
    assert packing.dominated((9, 2), 1, left, sizes)  # 3 fits in place of 2
    assert packing.dominated((5, 3, 2), 2, left, sizes)  # 5 or more in place of 3 and 2
    assert not packing.dominated((9, 3), 0, left, sizes)


def test_forest_recall_at_depth(spark):
    """Trees of depth eight find the links, each counted once; and vectors of two lengths link among their own."""
    g = np.random.default_rng(2)
    base = g.standard_normal((1200, 32))
    x = np.concatenate([base, base[:600] + 0.2 * g.standard_normal((600, 32)), base[:200] + 0.01 * g.standard_normal((200, 32))])
    rows = [(k, [float(c) for c in v], 1) for k, v in enumerate(x)]
    short = g.standard_normal(16)
    rows += [(9000, [float(c) for c in short], 1), (9001, [float(c) for c in short * 1.5], 1), (9002, [float(c) for c in short + 0.01], 1), (9002, [float(c) for c in short + 0.01], 1)]
    got = {r.vec_id: r for r in embedding_dedup.classes_of(spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int"), leaf=8, block=24).collect()}
    u = x / np.linalg.norm(x, axis=1, keepdims=True)
    near = u @ u.T >= 0.93
    np.fill_diagonal(near, False)
    found = np.array([got[k].n_links for k in range(len(x))])
    assert (found <= near.sum(1)).all() and found.sum() >= 0.95 * near.sum()
    assert [got[k].component_id for k in (9000, 9001, 9002)] == [9000] * 3 and got[9000].n_links == 3


def test_near_dedup_of_awkward_rows(spark):
    long = " ".join(f"t{k}" for k in range(60_000))
    a, b = " ".join(f"a{k}" for k in range(40)), " ".join(f"b{k}" for k in range(40))
    rows = [(1, a), (1, b), (2, a + " more"), (3, b + " more"), (None, a), (None, "alone with no id"), (4, long), (5, long + " end"), (6, None), (6, None), (7, ""), (8, "one two"), (8, "one two")]
    df = spark.createDataFrame([(d, t, "x", 1, "y") for d, t in rows], "doc_id long, text string, mark string, gone long, id string")
    got = Counter((r.doc_id, r.n_shingles, r.component_id) for r in near_dedup.classes(df).collect())
    assert got[1, 36, 1] == 2 and got[2, 37, 1] == 1 and got[3, 37, 1] == 1 and got[None, 36, 1] == 1
    assert got[None, 1, None] + got[None, 0, None] == 1 and got[5, 59_997, 4] == 1 and got[6, 0, 6] == 2 and got[8, 1, 8] == 2
    left = near_dedup.survivors(df)
    assert left.columns == df.columns and sorted(r.doc_id for r in left.collect() if r.doc_id) == [1, 1, 4, 6, 6, 7, 8, 8]


def test_odd_sketch_join_splits_hot_buckets(spark, monkeypatch):
    """The last round with parts of four documents finds what brute force finds."""
    monkeypatch.setattr(near_dedup, "BLOCK", 4)
    monkeypatch.setattr(near_dedup, "LARGE", 1 << 30)
    g = np.random.default_rng(5)
    base = [f"w{k}" for k in range(60)]
    rows = []
    for k in range(70):
        t = list(base)
        for _ in range(int(g.integers(1, 4))):
            t[int(g.integers(0, 60))] = f"n{g.integers(0, 9999)}"
        rows.append((k, " ".join(t)))
    sets = [{tuple(t.split()[j : j + 5]) for j in range(56)} for _, t in rows]
    parent = list(range(70))

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i, j in combinations(range(70), 2):
        if 100 * len(sets[i] & sets[j]) >= 75 * len(sets[i] | sets[j]):
            parent[max(root(i), root(j))] = min(root(i), root(j))
    got = near_dedup._classes(spark.createDataFrame(rows, "doc_id long, text string"), 75, 5, leader_rounds=1, most_rounds=1).collect()
    assert {r.doc_id: r.component_id for r in got} == {k: root(k) for k in range(70)}


def test_inclusion_probabilities_are_unequal_and_hold_the_missing_words(spark):
    g = np.random.default_rng(8)
    sizes = np.maximum(1, (g.pareto(1.5, 3000) * 20).astype(int))
    rows = [(k, "w " * int(n), "big" if k % 3 else "small") for k, n in enumerate(sizes)]
    got = mixing.copies(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()
    for source in ("big", "small"):
        own = [r for r in got if r.source == source]
        missing = own[0].target % own[0].source_size
        p = np.array([r.p for r in own])
        assert len(np.unique(p.round(9))) > 3 and abs(sum(r.p * r.size for r in own) - missing) < 1e-6 * missing
        longer = sorted(own, key=lambda r: r.size)
        assert all(a.p <= b.p for a, b in zip(longer, longer[1:], strict=False))
        taken = sum(r.copies * r.size for r in own)
        assert abs(taken - own[0].target) <= sizes.max()
        drawn = sum(r.copies - int(own[0].target // own[0].source_size) for r in own)
        assert abs(drawn - p.sum()) <= 6 * np.sqrt((p * (1 - p)).sum()) + 3


def test_mixing_of_awkward_rows(spark):
    rows = [(None, "a b c", "x"), (None, "a b c", "x"), (None, None, "y"), (7, "", "y"), (8, "one two three four", None), (8, "one two three four", None), (9, "w " * 5000, "x")]
    df = spark.createDataFrame([(*r, 1, "k", 2.0) for r in rows], "doc_id long, text string, source string, copies int, slice string, p double")
    figures = mixing.copies(df).collect()
    out = mixing.mixed(df)
    assert out.columns == df.columns
    assert Counter((r.doc_id, r.source) for r in out.collect()) == +Counter({k: n for k, n in Counter([(r.doc_id, r.source) for r in figures for _ in range(r.copies)]).items()})
    assert all(r.copies == 0 for r in figures if r.source == "y" and r.target == 0) and mixing.mixed(df.filter("false")).count() == 0


def test_generators_propose_overlapping_spans_and_context_decides(spark):
    token = "9f8a7b6c5d4e3f2a1b0c9d8e7f6a5b4c3d2e1f0a"
    texts = [f'config token = "{token}" end', f"commit {token} fixed it", "IBAN DE89 3704 0044 0532 0130 00 please", "no DE88 3704 0044 0532 0130 00 please", "host fe80:0000:0000:0000:0202:b3ff:fe1e:8329 up",
             "device 00:1a:2b:3c:4d:5e seen", "she lives at 12 Baker Street now", "dear Mrs Jane Miller, hello", "write to jane (AT) corp (DOT) com", "jane @ corp.com please", "room 12 (555) 123-4567 and (555) 987-6543",
             "order 2669109448945251 was sent", "call +1 (974) 555-3436 now", "version 10.20.300 and 2024-10-11", "token " * 400 + f'token = "{token}" ' * 700]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r.doc_id: [(s.kind, texts[r.doc_id][s.start : s.end]) for s in r.spans] for r in pii.redactions(df).collect()}
    assert got[0] == [("secret", token)] and got[1] == [] and got[11] == [] and got[13] == []
    assert [k for k, _ in got[2]] == ["iban"] and got[3] == []
    assert [got[k][0][0] for k in (4, 5, 6, 7, 8, 9)] == ["ipv6", "mac", "address", "name", "handle", "handle"]
    assert [s for _, s in got[10]] == ["(555) 123-4567", "(555) 987-6543"]
    assert [k for k, _ in got[12]] == ["phone"] and len(got[14]) == 700  # many matches, over several runs of parts
    spans = pii.redactions(df).select("spans").collect()
    assert all(a.end <= b.start for r in spans for a, b in zip(r.spans, r.spans[1:], strict=False))


def test_secrets_of_the_tables_are_found_and_checksums_left(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text")
    text = {r.doc_id: r.text or "" for r in docs.collect()}
    found = {r.doc_id: {text[r.doc_id][s.start : s.end] for s in r.spans if s.kind == "secret"} for r in pii.redactions(docs).collect()}
    planted = {d: set(re.findall(r'(?i)token = "([0-9a-f]{40})"', t)) for d, t in text.items()}
    assert sum(map(len, planted.values())) > 3 and all(planted[d] <= found[d] for d in planted)
    assert sum(len(found[d] - planted[d]) for d in found) <= 2


def test_trees_as_sql_score_alike(spark):
    g = np.random.default_rng(0)
    x = g.standard_normal((400, 3))
    trees = boosting.Boosted(rounds=12).fit(x, (x[:, 0] * x[:, 1] > 0).astype(float))
    df = spark.createDataFrame([(k, *map(float, r)) for k, r in enumerate(x)], "k int, a double, b double, c double")
    got = df.selectExpr("k", f"{trees.sql_text(['a', 'b', 'c'])} AS s").orderBy("k").collect()
    assert np.allclose([r.s for r in got], trees.score(x))


def test_boosting_against_plain_stumps():
    """One round of depth one is the best single split, found by trying all."""
    g = np.random.default_rng(4)
    x = g.integers(0, 12, (200, 2)).astype(float)
    y = (x[:, 1] > 6).astype(float)
    y[:20] = 1 - y[:20]
    p = y.mean()
    gain = {}
    for k in (0, 1):
        for c in np.unique(x[:, k])[:-1]:
            left = x[:, k] <= c
            gain[k, c] = sum((y[s] - p).sum() ** 2 / (s.sum() * p * (1 - p) + 1) for s in (left, ~left))
    k, c = max(gain, key=gain.get)
    tree = boosting.Boosted(rounds=1, depth=1).fit(x, y).trees[0]
    assert tree[0] == k and tree[1] == c


def test_language_against_exact_kernel_ridge(spark):
    """With every training text a landmark, the Nyström solution is close to ridge regression on the kernel itself."""
    g = np.random.default_rng(9)
    vocabulary = {"en": "the of and with that this".split(), "de": "der die und nicht das ein".split(), "es": "los una con para está niño".split()}
    rows = [(k, " ".join(g.choice(vocabulary[q], 12)), q) for k in range(240) for q in [list(vocabulary)[k % 3]]]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = language_id.fit(df)
    train = [r for r in rows if zlib.crc32(str(r[0]).encode()) % 3 != 1]
    held = [r for r in rows if zlib.crc32(str(r[0]).encode()) % 3 == 1]
    spectrum = language_id.Spectrum(model.letters)
    sets = [set(spectrum(t).tolist()) for _, t, _ in train]
    kernel = lambda a, b: len(a & b) / np.sqrt(len(a) * len(b))
    gram = np.array([[kernel(a, b) for b in sets] for a in sets])
    y = np.array([[float(q == r[2]) for q in model.languages] for r in train])
    alpha = np.linalg.solve(gram + 1e-3 * len(train) * np.eye(len(train)), y)
    names, scores = model([t for _, t, _ in held])
    exact = [model.languages[int(np.argmax([kernel(set(spectrum(t).tolist()), s) for s in sets] @ alpha))] for _, t, _ in held]
    assert names == exact == [q for _, _, q in held] and all(0 <= s <= 1 for s in scores)


def test_language_draws_do_not_overflow_and_long_only_languages_are_learnt(spark):
    rows = [(k, "the of and " * 5, "en") for k in range(60)] + [(1000 + k, "der und die " * 4000, "de") for k in range(9)] + [(2000, "the of", None), (2001, "the of", None), (2001, "the of", None)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    got = {r.doc_id: r.lang_pred for r in language_id.predict(df, language_id.fit(df, text_chars=500)).collect()}
    assert got[1000] == "de" and got[2000] == got[2001] == "en"


def test_clashing_columns_pass(spark):
    rows = [(1, "You idiot", 5, 0.1, 9), (2, "fine words here", 6, 0.2, 8), (2, "fine words here", 6, 0.2, 8)]
    df = spark.createDataFrame(rows, "doc_id long, text string, _g_size long, _score double, _toxic int")
    labels = spark.createDataFrame([(1, 1), (2, 0)], "doc_id long, toxic int")
    assert exact_dedup.survivors(df).columns == df.columns and exact_dedup.survivors(df).count() == 2
    assert toxicity.clean(df, labels).columns == df.columns and toxicity.scored(df, labels).columns == df.columns
    more = spark.createDataFrame([(1, "Released under the MIT License", "a", "b")], "doc_id long, text string, spans string, n_email string")
    assert "spans" in pii.redactions(more).columns and licenses.scan(more).count() == 1


def test_token_output_of_empty_table_and_ties(spark, tmp_path):
    import public_tokenizers

    path = public_tokenizers.path("byte_bpe_50k.json")
    for name, rows in (("none", []), ("ties", [(1, "b"), (1, "a"), (1, "a"), (None, None), (2, "")])):
        df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
        token_output.write_tokens(df, str(tmp_path / name), path, 50257, 2)
        got = token_output.read_tokens(spark, str(tmp_path / name)).orderBy("start").collect()
        assert [r.doc_id for r in got] == [d for d in sorted((r[0] for r in rows), key=lambda d: (d is not None, d or 0))]
        assert [r.start for r in got] == [0, *np.cumsum([r.n_tokens for r in got])[:-1]][: len(got)]


def test_dense_groups_are_counted_as_matrices(monkeypatch):
    """A leaf's links against brute force, and no pair of a dense group is listed (a group of 6,000 has 18 million)."""
    g = np.random.default_rng(3)
    x = np.concatenate((g.standard_normal(64) + 0.1 * g.standard_normal((300, 64)), np.repeat(g.standard_normal((40, 64)), 2, axis=0), g.standard_normal((60, 64))))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    n = len(x)
    ids, copies = g.permutation(n) * 7, g.integers(1, 5, n)
    lists = [sorted(g.choice(60, 9, replace=False).tolist()) if k % 3 else [] for k in range(n)]
    listed, old = [], embedding_dedup._met_before
    monkeypatch.setattr(embedding_dedup, "_met_before", lambda e, u, w: listed.append(len(u)) or old(e, u, w))
    near = embedding_dedup._near(x, 0.93)
    others, least = embedding_dedup._counted(near, pa.array(lists, pa.list_(pa.int64())), copies, ids)
    want = x @ x.T >= 0.93
    np.fill_diagonal(want, False)
    assert (near == want).all() and want[:300, :300].sum() == 300 * 299
    assert others.tolist() == [sum(int(copies[w]) for w in np.flatnonzero(want[u]) if not set(lists[u]) & set(lists[w])) for u in range(n)]
    assert least.tolist() == [int(min(ids[:300])) if u < 300 else int(ids[want[u] | (np.arange(n) == u)].min()) for u in range(n)]
    assert sum(listed) == 40
