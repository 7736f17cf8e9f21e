"""The pipeline and its stages against a plain Python version, on rows that are awkward in every column."""

import hashlib
import math
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest

import corpus_pipeline
from rankflow.llm import toxicity

CLASHING = "_g_size long, _score double, copies long, mark long, slice string, c0 string, id long, gone string, p double, source_size long, spans string"
SCHEMA = f"doc_id long, text string, lang string, source string, n_chars long, {CLASHING}"
EXTRA = (1, 2.0, 3, 4, "a", "b", 5, "c", 6.0, 7, "d")


def corpus():
    g = np.random.default_rng(11)
    rows, toxic = [], []
    for k in range(480):
        words = [f"w{x}" for x in g.integers(0, 400, int(g.integers(8, 90)))]
        bad = k % 6 == 0
        for _ in range(5 * bad):
            words.insert(int(g.integers(0, len(words))), str(g.choice(["idiot", "moron", "blarg"])))
        rows.append((k, " ".join(words), "en", ["a", "b", "c", None][k % 4]))
        toxic.append((k, 1, int(bad)))
    for k in range(30):  # near copies, and exact ones but for case
        d, text, lang, source = rows[1 + 3 * k]
        words = text.split()
        if k % 2:
            words[-1] = "changed"
        rows.append((1000 + k, " ".join(words).upper() if k % 4 == 0 else " ".join(words), lang, "b"))
    rows += [(2000, None, None, "a"), (2001, "", "en", "a"), (2002, "   \n", "de", "b"), (2003, "x y z " * 9000, "en", "c"), (None, "no id here at all but words", None, None), (None, None, None, None)]
    rows += [(2004, "one", "en", "a"), (2004, "one", "en", "a"), (2005, "ONE", "en", "b"), (2006, "only in this source", "en", "own"), (2007, "é" * 40, "fr", "c")]
    return [(*r, len(r[1] or "")) for r in rows], toxic


def low(text):
    return (text or "").translate({c: c + 32 for c in range(65, 91)})


def words(text):
    return re.findall(r"[^\x20\x09-\x0d]+", text or "")


def plain_exact(rows):
    best = {}
    for r in rows:
        t = low(r[1])
        if t not in best or (r[0] is not None and (best[t][0] is None or r[0] > best[t][0])):
            best[t] = r
    return list(best.values())


def plain_near(rows):
    sets = []
    for r in rows:
        w = words(low(r[1]))
        sets.append({tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set()))
    parent = list(range(len(rows)))

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in range(len(rows)):
        for j in range(i):
            union = len(sets[i] | sets[j])
            if sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= 75 * union:
                parent[root(i)] = root(j)
    least = {}
    for i, r in enumerate(rows):
        if r[0] is not None:
            least[root(i)] = min(r[0], least.get(root(i), r[0]))
    return [r for i, r in enumerate(rows) if not sets[i] or r[0] == least.get(root(i))]


def plain_mix(rows):
    """Counter of (doc_id, source, size) -> words' worth of copies, and each source's target and missing words."""
    size = [len(words(r[1])) for r in rows]
    total = Counter()
    for r, s in zip(rows, size, strict=True):
        total[r[3]] += s
    order = [*sorted(s for s in total if s is not None), *([None] if None in total else [])]
    weight = {s: k % 3 + 1 for k, s in enumerate(order)}
    target, free = {}, set(order)
    while free:
        level = (sum(total.values()) - sum(target.values())) / sum(weight[s] for s in free)
        over = {s for s in free if weight[s] * level > 3 * total[s]}
        if not over:
            break
        target |= {s: 3 * total[s] for s in over}
        free -= over
    target |= {s: weight[s] * level for s in free}
    out = Counter()
    for source in order:
        own = [(r[0], s) for r, s in zip(rows, size, strict=True) if r[3] == source]
        rate = target[source] / total[source] if total[source] else 0.0
        whole, missing = math.floor(rate), (rate - math.floor(rate)) * total[source]
        draw = lambda s: math.ceil(math.sqrt(s))
        scale, most = 0.0, 0
        for limit in sorted({s for _, s in own if s}, reverse=True):  # the largest size whose probability is under one
            certain = sum(s for _, s in own if s > limit)
            scale, most = (missing - certain) / sum(draw(s) * s for _, s in own if 0 < s <= limit), limit
            if scale * draw(limit) <= 1:
                break
        ranked = []
        for d, s in own:
            p = 0.0 if not s or not missing else 1.0 if s > most or scale * draw(s) >= 1 else scale * draw(s)
            u = (int(hashlib.md5(("" if d is None else str(d)).encode()).hexdigest()[:13], 16) + 0.5) / 2.0**52
            ranked.append((0 if p == 1 else 1 if p else 2, (u / (1 - u)) / (p / (1 - p)) if 0 < p < 1 else 0.0, -1 if d is None else d, s, p, d))
        ahead = 0
        for _, _, _, s, p, d in sorted(ranked, key=lambda x: x[:4]):
            take = whole + int(p == 1 or (p > 0 and ahead + s / 2 <= missing))
            ahead += s if p else 0
            out[d, source, s] += take
    return out, target


@pytest.fixture(scope="module")
def data(spark, tmp_path_factory):
    folder = tmp_path_factory.mktemp("tables")
    rows, toxic = corpus()
    spark.createDataFrame([(*r, *EXTRA) for r in rows], SCHEMA).repartition(5).write.parquet(f"{folder}/documents.parquet")
    spark.createDataFrame([*toxic, (None, 0, 1), (5, None, None), (3, 0, 0), (3, 0, 0)], "doc_id long, quality int, toxic int").write.parquet(f"{folder}/labels.parquet")
    return str(folder), rows


def same(df):
    return Counter((r.doc_id, r.text, r.lang, r.source, r.n_chars) for r in df.collect())


def test_stages_and_run_match_plain_python(spark, data):
    folder, rows = data
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    scorer = toxicity.fit(docs, spark.read.parquet(f"{folder}/labels.parquet"))
    scores = scorer([r[1] for r in rows])
    stages = dict(corpus_pipeline.STAGES)
    left = [r for r, s in zip(rows, scores, strict=True) if s < 0.3]
    got = stages["toxicity"](spark, docs, folder)
    assert got.columns == docs.columns and same(got) == Counter(left) and len(left) < len(rows)

    frame = lambda rows: spark.createDataFrame([(*r, *EXTRA) for r in rows], SCHEMA)
    unique = plain_exact(left)
    got = stages["exact_dedup"](spark, frame(left), folder)
    assert got.columns == docs.columns
    assert {(low(r.text), r.doc_id) for r in got.collect()} == {(low(r[1]), r[0]) for r in unique} and got.count() == len(unique)

    near = plain_near(unique)
    got = stages["near_dedup"](spark, frame(unique), folder)
    assert got.columns == docs.columns
    # A null id is kept where its component has no other; the plain version drops it there.
    assert {k: v for k, v in same(got).items() if k[0] is not None} == {k: v for k, v in Counter(near).items() if k[0] is not None}

    copies, target = plain_mix(near)
    got = stages["mixing"](spark, frame(near), folder)
    assert got.columns == docs.columns
    assert Counter((r.doc_id, r.source, len(words(r.text))) for r in got.collect()) == +copies
    for s, want in target.items():
        longest = max(len(words(r[1])) for r in near if r[3] == s)
        assert abs(sum(n * k[2] for k, n in copies.items() if k[1] == s) - want) <= max(1, longest)


def test_run_packs_what_the_stages_keep(spark, data):
    import public_tokenizers
    from tokenizers import Tokenizer

    folder, _ = data
    got = corpus_pipeline.run(spark, folder).collect()
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    for _, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, folder)
    t = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    want = Counter()
    for r in docs.collect():
        ids = [*t.encode(r.text or "", add_special_tokens=False).ids, 1]
        for p in range(0, len(ids), 4096):
            part = np.array(ids[p : p + 4096], "<u4").tobytes()
            want[r.doc_id, p // 4096, p, len(part) // 4, zlib.crc32(part)] += 1
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


def test_stages_take_an_empty_table(spark, data):
    folder, _ = data
    none = spark.createDataFrame([], SCHEMA)
    for name, stage in corpus_pipeline.STAGES:
        got = stage(spark, none, folder)
        assert got.count() == 0 and (name == "packing" or got.columns == none.columns)
