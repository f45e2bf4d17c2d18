import hashlib
from collections import Counter, defaultdict

import numpy as np
import pytest

import corpus_pipeline
from arcfield.llm import curriculum, packing, quality_rules, queries
from oracle import same
from test_operators import brute_fingerprint, brute_repeat, words

STAGES = dict(corpus_pipeline.STAGES)


@pytest.mark.parametrize("name", sorted(queries.ORACLES))
def test_oracle(spark, sf, name):
    same(spark, sf, queries.QUERIES[name], queries.ORACLES[name])


@pytest.fixture(scope="module")
def docs(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")


def texts_of(df):
    return {r.doc_id: r.text for r in df.collect()}


def test_quality_stage(spark, sf, docs):
    """The base rules and the learned list, over plain statistics."""
    rules = quality_rules.learn_rules(docs, queries.table(spark, sf, "labels"))

    def kept(t):
        s = dict(zip(quality_rules.STATS, quality_rules.text_stats(t)))
        w = words(t)
        if len(w) < 50 or 100 * brute_repeat(w) > 50 * len(w):
            return False
        ratio = {k: eval(v, {"greatest": max}, s) for k, v in quality_rules.RATIOS.items()}  # noqa: S307
        return not any(all(ratio[c] >= v if op == ">=" else ratio[c] <= v for c, op, v in r.tests) for r in rules)

    out = STAGES["quality rules"](spark, docs, sf)
    assert out.columns == docs.columns
    assert texts_of(out) == {i: t for i, t in texts_of(docs).items() if kept(t)}


def test_line_stage(spark, sf, docs):
    key = lambda line: "".join(c.lower() if "A" <= c <= "Z" else c for c in line.strip(" \t\n\x0b\x0c\r"))
    split, first = {i: (t or "").split("\n") for i, t in texts_of(docs).items()}, {}
    for i in sorted(split):
        for line in split[i]:
            first.setdefault(key(line), i)
    want = {i: "\n".join(x for x in ls if len(key(x)) < 10 or first[key(x)] == i) for i, ls in split.items()}
    out = STAGES["line dedup"](spark, docs, sf)
    assert out.columns == docs.columns
    assert texts_of(out) == want and all(r.n_chars == len(r.text) for r in out.collect())


def test_near_copy_stage(spark, sf, docs):
    texts = texts_of(docs)
    fp = {i: brute_fingerprint(t) for i, t in texts.items()}
    root = {i: i for i in fp}

    def find(a):
        while root[a] != a:
            a = root[a]
        return a

    for a in sorted(fp):
        for b in fp:
            if a < b and (fp[a] ^ fp[b]).bit_count() <= 3:
                x, y = sorted((find(a), find(b)))
                root[y] = x
    out = STAGES["simhash near-dedup"](spark, docs, sf)
    assert out.columns == docs.columns
    assert texts_of(out) == {i: t for i, t in texts.items() if find(i) == i} and out.count() < len(texts)


def test_mix_stage(spark, sf, docs):
    """Copies by source, from targets and streams worked out one source at a time."""
    rows = docs.collect()
    size = {r.doc_id: len(words(r.text)) for r in rows}
    by = defaultdict(list)
    for r in sorted(rows, key=lambda r: (hashlib.md5(str(r.doc_id).encode()).hexdigest(), r.doc_id)):
        by[r.source].append(r.doc_id)
    sources = sorted(by, key=lambda s: (s is None, s))
    held, weight, full = {s: sum(size[i] for i in by[s]) for s in by}, {s: (3, 1, 2)[k % 3] for k, s in enumerate(sources)}, set()
    while True:
        rest = 1.5 * sum(held.values()) - sum(2 * held[s] for s in full)
        target = {s: 2.0 * held[s] if s in full else rest * weight[s] / sum(weight[x] for x in by if x not in full) for s in by}
        over = {s for s in by if s not in full and target[s] > 2 * held[s]}
        if not over:
            break
        full |= over
    want = Counter()
    for s, ids in by.items():
        goal, before = int(target[s]), 0
        for i in ids:
            part = max(0, min(size[i], goal - goal // held[s] * held[s] - before))
            want[i] = goal // held[s] + (2 * part >= max(1, size[i]))
            before += size[i]
    out = STAGES["curriculum mix"](spark, docs, sf)
    assert out.columns == docs.columns
    assert Counter(r.doc_id for r in out.collect()) == +want
    at = {(r.doc_id, r.copy): r.position for r in curriculum.order(curriculum.assign(docs)).collect()}
    seen, places = Counter(), []
    for r in out.collect():
        if (r.doc_id, seen[r.doc_id]) in at:
            places.append(at[r.doc_id, seen[r.doc_id]])
        seen[r.doc_id] += 1
    assert places == sorted(places)


def test_packing_stage(spark, sf, docs):
    """Every document's ids, whole and once, in windows without gaps."""
    from tokenizers import Tokenizer

    coder = Tokenizer.from_file(queries.tokenizer_path())
    out = STAGES["mixture packing"](spark, docs, sf).collect()
    by, seq = defaultdict(list), defaultdict(list)
    for r in out:
        by[r.doc_id].append(r)
        seq[r.sequence_id].append(r)
    import zlib

    for i, t in texts_of(docs).items():
        ids, at = np.array([*coder.encode(t or "", add_special_tokens=False).ids, 1], "<u4"), 0
        for r in sorted(by[i], key=lambda r: r.start):
            assert (r.start, r.doc_tokens) == (at, len(ids)) and r.ids_crc32 == zlib.crc32(ids[at : at + r.length].tobytes())
            at += r.length
        assert at == len(ids)
    for rows in seq.values():
        rows.sort(key=lambda r: r.offset)
        assert [r.offset for r in rows] == list(np.cumsum([0] + [r.length for r in rows])[:-1]) and sum(r.length for r in rows) <= packing.WINDOW


def test_run_is_its_stages(spark, sf, docs):
    before, now = {r.doc_id for r in docs.collect()}, docs
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES):
        now = stage(spark, now, sf)
        if k < 4:
            ids = {r.doc_id for r in now.collect()}
            assert ids <= before and ids
            before = ids
    assert {r.doc_id for r in now.collect()} == before
    assert corpus_pipeline.run(spark, sf).count() == now.count()
