"""Each operator against a plain rendering of its contract, on whole small tables."""

import hashlib
import html
import re
from collections import Counter, defaultdict

import numpy as np
import pandas as pd
import public_tokenizers
import pytest

from temporal_patterns.llm import queries as Q

BLANK = "[ \t-\r]"
WORD = re.compile(r"[^\x20\x09-\x0D]+")


@pytest.fixture(scope="module")
def docs(spark, sf):
    return spark.read.parquet(f"{sf('0.001')}/documents.parquet").toPandas()


def by_id(df, key="doc_id"):
    return df.set_index(key).sort_index()


def brute_targets(sizes):
    """Targets by resharing until none is above its ceiling."""
    order = sorted((s for s in sizes if s is not None), key=lambda s: s.encode("utf-8")) + ([None] if None in sizes else [])
    weight = {s: (3, 1, 2)[i % 3] for i, s in enumerate(order)}
    target, left, free = dict.fromkeys(order, 0.0), 1.5 * sum(sizes.values()), set(order)
    while left > 1e-9 and free:
        total = sum(weight[s] for s in free)
        for s in free:
            target[s] += left * weight[s] / total
        left = 0.0
        for s in list(free):
            if target[s] >= 2 * sizes[s]:
                left += target[s] - 2 * sizes[s]
                target[s] = 2.0 * sizes[s]
                free.discard(s)
    return target


@pytest.mark.parametrize("scale", ["0.001", "0.01"])
def test_mix(spark, sf, scale):
    docs = spark.read.parquet(f"{sf(scale)}/documents.parquet").toPandas()
    docs["size"] = [len(WORD.findall(t or "")) for t in docs.text]
    got = Q.op1_mix(spark, sf(scale)).toPandas()
    want = by_id(docs)
    got = by_id(got)
    assert (got["size"] == want["size"]).all()
    sizes = docs.groupby("source")["size"].sum().to_dict()
    target = brute_targets(sizes)
    source = want.source
    assert (got.source_size == source.map(sizes)).all()
    assert np.allclose(got.target, source.map(target))
    assert (got.taken <= 2 * got["size"]).all()
    taken = got.taken.groupby(source).sum()
    for s, t in target.items():
        assert abs(taken[s] - t) <= max(0.02 * t, 300), (s, taken[s], t)
    again = by_id(Q.op1_mix(spark, sf(scale)).toPandas())
    assert (again.taken == got.taken).all()


def brute_base(text):
    text = text or ""
    words = WORD.findall(text)
    lines = [x for x in text.split("\n") if WORD.search(x)]
    windows = [tuple(words[i : i + 8]) for i in range(len(words) - 7)]
    n = Counter(windows)
    hit = set()
    for i, w in enumerate(windows):
        if n[w] > 1:
            hit.update(range(i, i + 8))
    return [len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in text), len(lines) - len(set(lines)), len(hit)]


def test_quality(spark, sf, docs):
    got = by_id(Q.op2_quality(spark, sf("0.001")).toPandas())
    for i, text in zip(docs.doc_id, docs.text):
        r = got.loc[i]
        base = brute_base(text)
        assert [r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words] == base
        assert r.base_failed == (base[0] < 20 or 100 * base[4] > 30 * base[0])
        assert not (r.base_failed and r.kept)


def test_quality_tells_labels_apart(spark, sf):
    got = Q.op2_quality(spark, sf("0.01")).toPandas()
    labels = spark.read.parquet(f"{sf('0.01')}/labels.parquet").toPandas()
    both = got.merge(labels, on="doc_id")
    both = both[both.n_words >= 20]
    good = both[(both.quality == 1) & ~both.base_failed]
    assert good.kept.mean() > 0.99
    assert (~both[both.quality == 0].kept).mean() > 0.85


def test_extract(spark, sf):
    pages = spark.read.parquet(f"{sf('0.01')}/pages.parquet").toPandas()
    got = by_id(Q.op3_extract(spark, sf("0.01")).toPandas(), "page_id")
    for i, page in zip(pages.page_id, pages.html):
        body = re.search(r"<article>(.*?)(</article>|$)", page, re.S)[1]
        parts = [" ".join(html.unescape(re.sub("<[^>]*>", "", p.replace("<br>", " "))).split()) for p in re.split(r"</?(?:p|h1)>", body)]
        want = "\n".join(p for p in parts if p)
        assert got.text[i] == want and got.n_chars[i] == len(want)


def test_token_counts(spark, sf, docs):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    got = by_id(Q.op4_token_counts(spark, sf("0.001")).toPandas())
    want = [len(e) for e in tok.encode_batch([t or "" for t in docs.text], add_special_tokens=False)]
    assert (got.n_tokens.loc[docs.doc_id].to_numpy() == want).all()
    assert (got.over_limit == (got.n_tokens > 512)).all()


def brute_lines(rows, least=25):
    """doc_id -> what is left, by the earliest occurrence of each normalised unit and the runs of all others."""
    import pyarrow as pa

    from temporal_patterns.llm.line_dedup import line_units

    first, units = {}, defaultdict(list)
    for i, text in sorted(rows):
        raw = text.encode()
        _, _, _, start, length, _ = line_units(pa.array([text]))
        for a, n in zip(start.tolist(), length.tolist()):
            words = re.findall(rb"[^\x20\x09-\x0D]+", re.sub(rb"[A-Z]", lambda m: m[0].lower(), raw[a : a + n]))
            key = b" ".join(words)
            first.setdefault(key, (i, a))
            units[i].append((a, a + n, len(words), first[key] != (i, a)))
        assert sum(n for _, _, n, _ in units[i]) == len(WORD.findall(text))
    out = {}
    for i, text in rows:
        raw, rest, at, run = text.encode(), b"", 0, []
        for a, b, n, repeat in [*units[i], (len(text.encode()), None, 0, False)]:
            if repeat and (not run or run[-1][1] == a):
                run.append((a, b, n))
                continue
            if sum(x[2] for x in run) >= least:
                rest += raw[at : run[0][0]]
                at = run[-1][1]
            run = [(a, b, n)] if repeat else []
        out[i] = rest + raw[at:]
    return out


def test_passages_inside_lines(spark):
    import random

    from temporal_patterns.llm.line_dedup import drop_repeated_lines

    rng = random.Random(3)
    word = lambda: "".join(rng.choice("abcdefghij") for _ in range(rng.randrange(2, 7)))
    some = lambda n: " ".join(word() for _ in range(n))
    passages, stock = [some(55) for _ in range(30)], [some(9) for _ in range(4)]
    rows = []
    for i in range(300):
        parts = [some(rng.randrange(20, 60)), passages[i % 30] if i < 120 else some(40), some(rng.randrange(20, 60)), "\n" + rng.choice(stock)]
        rows.append((i, " ".join(parts)))
    got = {r.doc_id: r for r in drop_repeated_lines(spark.createDataFrame(rows, "doc_id long, text string").repartition(7)).collect()}
    assert all(got[i].n_removed > 100 for i in range(30, 120))  # the first holder keeps its passage
    assert all(got[i].n_repeated > 100 for i in range(120)) and not any(got[i].n_removed for i in range(30))
    assert not any(got[i].n_removed or got[i].n_repeated for i in range(120, 300))
    for i, rest in brute_lines(rows).items():
        assert got[i].text.encode() == rest


def test_line_dedup(spark, sf, docs):
    got = by_id(Q.op5_line_dedup(spark, sf("0.001")).toPandas())
    for i, rest in brute_lines([(i, t or "") for i, t in zip(docs.doc_id, docs.text)]).items():
        assert got.kept_sha256[i] == hashlib.sha256(rest).hexdigest()
        assert got.text[i].encode() == rest
        raw = docs.text[docs.doc_id == i].iloc[0].encode()
        assert sum(s["length"] for s in got.spans[i]) == got.n_removed[i] == len(raw) - len(rest)


def test_byte_bpe(spark, sf, docs):
    import base64

    import tiktoken

    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(public_tokenizers.path("byte_bpe_50k.tiktoken"), "rb"))}
    lib = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    got = by_id(Q.op6_byte_bpe(spark, sf("0.001")).toPandas())
    for i, text in zip(docs.doc_id, docs.text):
        ids = lib.encode_ordinary(text or "")
        assert got.n_tokens[i] == len(ids)
        assert got.ids_sha256[i] == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest()
        assert got.decoded_sha256[i] == hashlib.sha256((text or "").encode()).hexdigest()


def brute_classes(rows, size, num, den):
    """doc_id -> (shingles, least id reachable)."""
    sets = {}
    for i, text in rows:
        words = WORD.findall(re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
        sets[i] = {tuple(words[j : j + size]) for j in range(len(words) - size + 1)} or ({tuple(words)} if words else set())
    parent = {i: i for i in sets}

    def root(i):
        while parent[i] != i:
            parent[i] = parent[parent[i]]
            i = parent[i]
        return i

    holders = defaultdict(list)
    for i, s in sets.items():
        shared = Counter(j for x in s for j in holders[x])
        for j, n in shared.items():
            if den * n >= num * (len(s) + len(sets[j]) - n):
                a, b = root(i), root(j)
                parent[max(a, b)] = min(a, b)
        for x in s:
            holders[x].append(i)
    return {i: (len(s), root(i)) for i, s in sets.items()}


@pytest.mark.parametrize("scale", ["0.001", "0.01"])
def test_jaccard_join(spark, sf, scale):
    docs = spark.read.parquet(f"{sf(scale)}/documents.parquet").toPandas()
    got = by_id(Q.op7_jaccard_join(spark, sf(scale)).toPandas())
    want = brute_classes(list(zip(docs.doc_id, docs.text)), 3, 90, 100)
    assert {i: (r.n_shingles, r.component_id) for i, r in got.iterrows()} == want


def brute_bytes(rows, length=200):
    n = Counter()
    for _, text in rows:
        raw = (text or "").encode()
        n.update(raw[i : i + length] for i in range(len(raw) - length + 1))
    out = {}
    for i, text in rows:
        raw = (text or "").encode()
        gone = np.zeros(len(raw) + 1, bool)
        for a in range(len(raw) - length + 1):
            if n[raw[a : a + length]] > 1:
                gone[a : a + length] = True
        gone = gone[: len(raw)]
        spans = int(np.count_nonzero(np.diff(np.concatenate([[0], gone.astype(int)])) == 1))
        out[i] = (len(raw), int(gone.sum()), spans, hashlib.sha256(np.frombuffer(raw, np.uint8)[~gone].tobytes()).hexdigest())
    return out


def test_repeated_bytes(spark, sf, docs):
    got = by_id(Q.op9_repeated_bytes(spark, sf("0.001")).toPandas())
    want = brute_bytes(list(zip(docs.doc_id, docs.text)))
    assert {i: tuple(r[["n_bytes", "n_removed", "n_spans", "kept_sha256"]]) for i, r in got.iterrows()} == want


def test_nearest(spark, sf):
    rows = spark.read.parquet(f"{sf('0.1')}/embeddings.parquet").toPandas()
    got = Q.op10_nearest(spark, sf("0.1")).toPandas()
    x = np.stack(rows.embedding.to_numpy()).astype(float)
    ids = rows.vec_id.to_numpy()
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    hits = total = 0
    for q in np.flatnonzero(ids % 50 == 0):
        score = unit @ unit[q]
        score[q] = -9
        best = set(ids[np.lexsort((ids, -score))[:5]])
        mine = got[got.query_id == ids[q]].sort_values("rank")
        assert list(mine["rank"]) == [1, 2, 3, 4, 5]
        at = {v: i for i, v in enumerate(ids)}
        assert np.allclose(mine.score, [score[at[v]] for v in mine.vec_id], atol=1e-12)
        hits += len(best & set(mine.vec_id))
        total += 5
    assert hits / total >= 0.9


def test_lm_scores_follow_their_definition(spark):
    from temporal_patterns.llm import lm_scoring as L

    texts = ["a b a b c", "a b c", "b b b a c d", "", None, "c a B"]
    docs = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    labels = spark.createDataFrame([(0, 1, 0), (1, 1, 0), (2, 0, 0), (5, 1, 1)], "doc_id long, quality int, toxic int")
    got = by_id(L.score(L.fit(docs, labels)).toPandas())
    tokens = [WORD.findall((t or "").lower()) for t in texts]
    vocab = sorted({w for t in tokens for w in t})
    v = len(vocab) + 1

    def model(ids):
        one = Counter(w for i in ids for w in tokens[i])
        two = Counter(p for i in ids for p in zip(tokens[i], tokens[i][1:]))
        n = sum(one.values())

        def loss(t):
            out = 0.0
            for k, w in enumerate(t):
                p = (one[w] + 1) / (n + v)
                if k:
                    p = 0.4 * p + 0.6 * two[t[k - 1], w] / max(one[t[k - 1]], 1)
                out -= np.log(p)
            return out / max(len(t), 1)

        return loss

    background, target = model(range(len(texts))), model([0, 1])
    for i, t in enumerate(tokens):
        assert got.n_tokens[i] == len(t)
        assert got.background_entropy[i] == pytest.approx(background(t))
        assert got.target_entropy[i] == pytest.approx(target(t))
        assert got.score[i] == pytest.approx(target(t) - background(t))


def test_lm_scores_rank_trusted_text_first(spark, sf):
    got = Q.op8_lm_scores(spark, sf("0.01")).toPandas()
    labels = spark.read.parquet(f"{sf('0.01')}/labels.parquet").toPandas()
    both = got.merge(labels, on="doc_id")
    both = both[both.n_tokens >= 20]
    assert both[both.quality == 1].score.mean() < both[both.quality == 0].score.mean()


def test_pipeline(spark, sf):
    """Stage by stage against brute force."""
    import corpus_pipeline as P

    sf_dir = sf("0.001")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    kept = P.quality_rules(spark, docs, sf_dir)
    judged = Q.op2_quality(spark, sf_dir).where("kept").toPandas()
    k = kept.toPandas()
    assert kept.columns == docs.columns and set(k.doc_id) == set(judged.doc_id)
    unique = P.near_duplicates(spark, kept, sf_dir)
    u = unique.toPandas()
    classes = brute_classes(list(zip(k.doc_id, k.text)), 5, 80, 100)
    assert unique.columns == docs.columns and set(u.doc_id) == {c for _, c in classes.values()}
    cut = P.repeated_lines(spark, unique, sf_dir)
    c = cut.toPandas()
    rest = brute_lines(list(zip(u.doc_id, u.text)))
    assert cut.columns == docs.columns
    assert dict(zip(c.doc_id, c.text)) == {i: r.decode() for i, r in rest.items() if WORD.search(r.decode())}
    mixed = P.source_mix(spark, cut, sf_dir)
    m = mixed.toPandas()
    assert mixed.columns == docs.columns and (m.n_chars == m.text.str.len()).all()
    whole = dict(zip(c.doc_id, c.text))
    sizes = {s: 0 for s in c.source}
    for s, t in zip(c.source, c.text):
        sizes[s] += len(WORD.findall(t))
    taken = Counter()
    for i, s, t in zip(m.doc_id, m.source, m.text):
        words = WORD.findall(t)
        taken[s] += len(words)
        assert t == whole[i] or not Counter(words) - Counter(WORD.findall(whole[i]))
    for s, t in brute_targets(sizes).items():
        assert abs(taken[s] - t) <= max(0.02 * t, 300)
    out = P.encode(spark, mixed, sf_dir).toPandas()
    assert sorted(out.n_tokens) == sorted(Q.token_counts.counter(public_tokenizers.path("byte_bpe_50k.json")).count(t) for t in m.text)
    assert isinstance(P.run(spark, sf_dir).toPandas(), pd.DataFrame)
