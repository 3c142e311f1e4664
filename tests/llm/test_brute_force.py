"""Operators that SQL can't express, against plain versions of them."""

from __future__ import annotations

import math
from collections import Counter, defaultdict

import numpy as np
import pytest
from test_operators import docs_of

from passage_engine.llm import html_text, language, mixing, neighbours, secrets, toxicity


def bucket(gram: str, size: int) -> int:
    h = len(gram) * 0x165667B1 % 2**32
    for c, step in zip(gram, (0x9E3779B1, 0x85EBCA77, 0xC2B2AE3D), strict=False):
        h = (h ^ ord(c)) * step % 2**32
        h ^= h >> 15
    return h % size


def grams(text: str) -> list[str]:
    t = text.lower() + "\n"
    return [(t + "\n\n")[i : i + n] for n in (1, 2, 3) for i in range(len(t))]


def test_language_equals_plain_naive_bayes(spark):
    rows = [(i, " ".join(f"{p}{(i * 7 + j) % 13}" for j in range(1 + i % 9)), lang) for i, (p, lang) in enumerate([("the", "en"), ("der", "de"), ("él", "es")] * 20)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = language.fit(df, buckets=512)
    counts = {x: Counter() for x in ("de", "en", "es")}
    for _, t, lang in rows:
        counts[lang].update(bucket(g, 512) for g in grams(t))
    queries = [(100, "the dér 5"), (101, "él"), (102, ""), (103, "42"), (104, None), (105, "The The\nthe")]
    got = {r.doc_id: r for r in language.identify(spark.createDataFrame(queries, "doc_id long, text string").coalesce(1), model).collect()}
    for i, t in queries:
        if not t or not any(map(str.isalpha, t)):
            assert (got[i].lang_pred, got[i].score) == ("und", 0)
            continue
        total = {x: math.log(1 / 3) + sum(math.log((c[bucket(g, 512)] + 1) / (sum(c.values()) + 512)) for g in grams(t)) for x, c in counts.items()}
        best = max(sorted(total), key=total.get)
        assert got[i].lang_pred == best and abs(got[i].score - 1 / sum(math.exp(v - total[best]) for v in total.values())) < 1e-3
    alone = language.identify(spark.createDataFrame(queries[:1], "doc_id long, text string"), model).first()
    assert alone.score == got[100].score
    with pytest.raises(ValueError):
        language.fit(df, most_langs=2)


def test_secret_spans_equal_a_plain_scan(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    model = secrets.fit(docs)
    texts = {r.doc_id: r.text or "" for r in docs.collect()}
    for r in secrets.scan(docs, model).collect():
        t, spans = texts[r.doc_id], []
        for kind, rx, ok in (("assign", secrets.ASSIGN, lambda m: len(m[2]) >= 6), ("access", secrets.ACCESS, lambda m: len(m[0]) >= 20)):
            spans += [(m.start(), secrets.KINDS.index(kind), kind, m.end()) for m in rx.finditer(t) if ok(m)]
        at = 0
        while at < len(t):
            end = at
            while end < len(t) and t[end] in "0123456789abcdef":
                end += 1
            if end - at >= 24:
                spans.append((at, 2, "hex", end))
            at = max(end, at + 1)
        spans.sort()
        found = [s.split(":") for s in r.spans.split(",")] if r.spans else []
        assert [(k, int(s), int(e)) for k, s, e in found if k != "markov"] == [(k, s, e) for s, _, k, e in spans]
        assert (r.n_assign, r.n_access, r.n_hex) == tuple(sum(x[2] == k for x in spans) for k in secrets.KINDS[:3])


def test_mixing_equals_plain_balancing(spark):
    rows = [(i, "w " * (1 + i % 37), [None, "a", "b", "c", "é"][i % 5] if i % 3 else "a") for i in range(900)]
    got = mixing.mix(docs_of(spark, rows)).collect()
    size = {i: len(t.split()) for i, t, _ in rows}
    total = defaultdict(int)
    for i, _, s in rows:
        total[s] += size[i]
    names = [*sorted(x for x in total if x is not None), None]
    weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(names)}
    target, left, open_ = {}, sum(total.values()), set(names)
    while open_:
        unit = left / sum(weight[s] for s in open_)
        over = {s for s in open_ if weight[s] * unit > 3 * total[s]}
        target |= {s: 3 * total[s] for s in over} if over else {s: weight[s] * unit for s in open_}
        left -= sum(target[s] for s in over)
        open_ = open_ - over if over else set()
    taken = defaultdict(int)
    for r in got:
        assert (r.size, r.source_size) == (size[r.doc_id], total[r.source]) and abs(r.target - target[r.source]) < 1e-6
        assert r.taken % r.size == 0 and r.taken <= 3 * r.size
        taken[r.source] += r.taken
    assert len(got) == 900 and all(abs(taken[s] - target[s]) <= 37 for s in names)
    again = mixing.mix(docs_of(spark, rows[::-1]).repartition(5)).collect()
    assert sorted((r.doc_id, r.taken) for r in again) == sorted((r.doc_id, r.taken) for r in got)


def test_mixed_keeps_own_columns_and_repeated_ids(spark):
    from pyspark.sql import functions as F

    df = docs_of(spark, [(i // 2, f"w {i} " * (1 + i % 5), "ab"[i % 3 > 0]) for i in range(300)]).withColumns({"mix_copy": F.lit("own"), "__copies": F.lit("own")})
    out = mixing.mixed(df)
    assert out.columns == [*df.columns, "mix_copy_"] and out.where("mix_copy <> 'own' or `__copies` <> 'own'").count() == 0
    want = mixing.mix(df).agg(F.sum("copies")).first()[0]
    assert abs(out.count() - want) <= 0.15 * want


def test_toxicity_equals_a_scan_of_all_entries(spark, small):
    docs, labels = (spark.read.parquet(f"{small}/{t}.parquet") for t in ("documents", "labels"))
    model = toxicity.fit(docs, labels)
    ix = model.index
    dense = np.zeros((len(model.sizes), len(model.idf)))
    for t in range(len(model.idf)):
        for c in range(ix.first[t], ix.first[t + 1]):
            own = slice(ix.start[c], ix.start[c + 1])
            dense[ix.entry[own], t] = ix.weight[own]
            assert ix.largest[c] == ix.weight[own].max() and set(ix.entry[own] // model.block) == {ix.block[c]}
    assert len(dense) and np.allclose(np.linalg.norm(dense, axis=1), 1)
    for r in docs.limit(300).collect():
        v = toxicity.vector(r.text or "", model.terms, model.idf)
        if v is None:
            p = (model.empty[1] + model.prior) / (sum(model.empty) + 1)
        else:
            cos = dense[:, v[0]] @ v[1]
            by = [i for i in np.argsort(-cos, kind="stable") if cos[i] > 0]
            have = np.cumsum([model.sizes[i].sum() for i in by])
            worst = cos[by[min(len(by) - 1, int(np.searchsorted(have, model.k)))]] if by else 0
            near = [i for i in by if cos[i] >= worst - 1e-12]
            p = (sum(cos[i] * model.sizes[i, 1] for i in near) + model.prior) / (sum(cos[i] * model.sizes[i].sum() for i in near) + 1)
        x = math.log((p + 1e-3) / (1 - p + 1e-3))
        assert abs(toxicity.score_text(r.text or "", model)[0] - 1 / (1 + math.exp(-(model.line[0] * x + model.line[1])))) < 1e-9


@pytest.mark.parametrize("clustered", [False, True])
def test_recall_beyond_small_tables(spark, clustered):
    rng = np.random.default_rng(8)
    x = rng.standard_normal((6000, 64)) * (0.4 if clustered else 1.0)
    if clustered:
        x += 3 * rng.standard_normal((20, 64))[rng.integers(0, 20, 6000)]
    df = spark.createDataFrame([(i, v.tolist(), "x", 1) for i, v in enumerate(x.astype(np.float32))], "vec_id long, embedding array<float>, list string, rank int")
    x = x.astype(np.float32).astype(float)
    got = defaultdict(set)
    for r in neighbours.search(df, df.where("vec_id % 100 = 0").select("vec_id")).collect():
        got[r.query_id].add(r.vec_id)
    hit = 0
    for q in range(0, 6000, 100):
        d = ((x - x[q]) ** 2).sum(axis=1)
        d[q] = np.inf
        hit += len(got[q] & set(np.argpartition(d, 10)[:10].tolist()))
    assert hit / 600 >= 0.95


def test_plain_page_equals_its_blocks():
    blocks = ["A headline", "First  para &amp; more\n text", "Third <b>bold</b> one"]
    page = "<html><head><title>x</title><style>p{}</style></head><body><nav><a href=x>menu</a></nav><article><h1>%s</h1><p>%s</p><p>%s</p><div class='comments'><p>me too</p></div></article><footer>f</footer></body></html>" % tuple(blocks)
    assert html_text.main_text(page) == "A headline\n\nFirst para & more text\n\nThird bold one"
