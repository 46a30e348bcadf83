"""The training-data operators on small fixtures: brute force, round trips, and odd rows."""

import itertools
import math
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from arcloom.llm import ann, chat_format, decontamination, line_dedup, lm_scoring, mixing, ngram_join, quality, sharding, token_output
from arcloom.llm.common import words

DOC = "doc_id long, text string, shard string, size double, _key int, rate string"
BASE = " ".join(f"w{i}" for i in range(60))
NEAR = BASE.replace("w30", "other")
LONG = "long line number one\n" * 300


@pytest.fixture(scope="module")
def docs(spark):
    """Nulls, empty and long texts, copies, a repeated row, and columns whose names clash."""
    texts = [(1, BASE), (2, NEAR), (3, BASE), (4, None), (5, ""), (6, "short"), (7, LONG), (8, "Alpha beta\n  ALPHA BETA gamma \nalpha beta gamma"), (9, "alpha beta gamma\nown words here"), (None, "no id here"), (3, BASE), (11, "été ÉTÉ ♫ x'y\tz")]
    return spark.createDataFrame([(i, t, "s", 1.0, 0, "r") for i, t in texts], DOC)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], DOC)


def plain(text):
    return re.findall(r"[^\x20\x09-\x0d]+", "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")) + [None]


def test_elias_fano(monkeypatch):
    dice = np.random.default_rng(0)
    monkeypatch.setattr(lm_scoring, "STRETCH", 65536)
    for values in (np.zeros(0, int), np.array([0, 0, 0]), np.sort(dice.integers(0, 1 << 40, 3000)), np.arange(1000), np.sort(dice.integers(0, 1 << 30, 200_000)), np.repeat(np.arange(3) << 50, 70_000), np.arange(65536 * 2)):
        e, _ = lm_scoring.EliasFano.view(lm_scoring.EliasFano.of(values).to_bytes(), 0)
        assert (e.decode() == values).all() and all(e[i] == values[i] for i in range(0, len(values), 3001))
        for i in range(0, len(values), 65536):
            assert (e.decode(i, i + 65536) == values[i : i + 65536]).all()
        asked = dice.permutation(np.concatenate([values[::17], values[::13] + 1, [-1, 1 << 60]]))
        at, there = e.locate(asked), np.isin(asked, values)
        assert ((at >= 0) == there).all() and (values[at[there]] == asked[there]).all()
        some = np.sort(dice.integers(0, max(1, len(values)), 500)) if len(values) else np.zeros(0, int)
        assert (e.gather(some) == values[some]).all()


def test_trie_searches_agree():
    dice = np.random.default_rng(0)
    windows, count = np.unique(dice.integers(0, 30, (3000, 3)), axis=0, return_counts=True)  # (w2, w1, w3) in order
    words, near = np.arange(0, 60, 2), np.arange(5, 35)
    seen = dice.random(len(windows)) < 0.7
    m, a, b = windows[seen].T
    t = lm_scoring.Trie.build(words, near, m, a, b, count[seen]).mapped()
    wide = np.unique(np.concatenate([windows, dice.integers(0, 32, (500, 3))]), axis=0)
    m, a, b = wide.T
    words, near = np.arange(0, 64, 2), np.arange(5, 37)
    got = t.answer(words, near, m, a, b)
    new = np.cumsum((np.diff(m, prepend=-1) != 0) | (np.diff(a, prepend=-1) != 0)) - 1
    for i in range(0, len(wide), 7):
        assert t.lookup(int(near[a[i]]), int(words[m[i]]), int(near[b[i]])) == (got["a3"][i], got["b3"][new[i]], got["a2"][i], got["b2"][m[i]])
    value = lm_scoring.value_of
    for x, y in ((3, 4), (31, 4), (3, 31)):  # what is seen and what is left for the unigrams
        codes = [t.lookup(int(near[x]), int(words[y]), int(w)) for w in near]
        mass = sum(value(p) + value(q) * (value(r) + value(s) / 31) for p, q, r, s in codes) + value(codes[0][1]) * value(codes[0][3]) * (1 - len(near) / 31)
        assert 0.98 < mass <= 1 + 1e-9


def brute_scores(rows):
    """(base, score, n_tokens, n_known, all training tokens) of (text, held) by a plain trigram model."""
    step = lambda p: 10.0 ** (-math.ceil(-math.log10(p) * lm_scoring.STEPS) / lm_scoring.STEPS) if p > 0 else 0.0
    one, two, three = {}, {}, {}
    windows = lambda t: (lambda x: zip([0, 0, *x][: len(x)], [0, *x][: len(x)], x, strict=True))(plain(t))
    for text, held in rows:
        for x, y, z in () if held else windows(text):
            one[z] = one.get(z, 0) + 1
            for k, of in ((y, two), ((x, y), three)):
                of.setdefault(k, {})[z] = of.setdefault(k, {}).get(z, 0) + 1
    n, v = sum(one.values()), len(one)

    def part(of, k, z, rest):
        seen = of.get(k)
        if not seen:
            return rest
        total = sum(seen.values()) + len(seen)
        return step(seen.get(z, 0) / total) + step(len(seen) / total) * rest

    out = []
    for text, _ in rows:
        low = [(one.get(z, 0) + 1) / (n + v + 1) for z in plain(text)]
        full = [part(three, (x, y), z, part(two, y, z, p)) for (x, y, z), p in zip(windows(text), low, strict=True)]
        out.append((sum(map(math.log10, low)), sum(map(math.log10, full)), len(low), sum(z in one for z in plain(text)), n))
    return out


@pytest.mark.parametrize("hot,shard,block", [(10**6, 10**6, 1 << 23), (5, 40, 200), (2, 7, 3000), (60, 10**6, 1 << 23)])
def test_lm_scores(spark, docs, empty, hot, shard, block):
    """However windows are dealt, scores are those of a plain model."""
    prose = spark.createDataFrame([(100 + i, f"the cat sat on the mat and the dog of the house sat on the {i % 5} of the {i % 7} the end", "s", 1.0, 0, "r") for i in range(60)], DOC)
    held = docs.unionByName(prose).withColumn("held", F.crc32(F.col("doc_id").cast("string")) % 7 == 2)
    got = lm_scoring.train_and_score(held, block_chars=block, shard_windows=shard, hot=hot)[0].collect()
    rows = [(r.text, bool(r.held)) for r in held.select("text", "held").collect()]
    want = sorted(brute_scores(rows))
    have = sorted((r.base_score, r.score, r.n_tokens, r.n_known, r.train_tokens) for r in got)
    assert np.allclose(np.array(have), np.array(want), rtol=0, atol=1e-7)


def test_lm_scores_of_no_documents(spark, docs, empty):
    assert lm_scoring.train_and_score(empty.withColumn("held", F.lit(False)))[0].count() == 0
    untrained = lm_scoring.train_and_score(docs.withColumn("held", F.lit(True)))[0].collect()
    assert all(r.score == r.base_score == 0.0 and r.n_known == 0 and r.train_tokens == 0 for r in untrained)


def test_lm_scores_of_the_given_table(spark):
    """The same scores for any shards and hot words, and stored tries that answer as the model does."""
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text", (F.col("doc_id") % 7 == 2).alias("held"))
    made = {}
    for shard, hot in ((2_000_000, 500_000), (20_000, 500_000), (20_000, 300)):
        scored, answers = lm_scoring.train_and_score(docs, shard_windows=shard, hot=hot, keep_tries=True)
        made[shard, hot] = {r.doc_id: (r.score, r.base_score) for r in scored.collect()}
        tries = [lm_scoring.Trie.view(r.trie) for r in answers.where("trie is not null").collect()]
        assert len(tries) > 1 or shard > 20_000
    first = made[2_000_000, 500_000]
    for other in made.values():
        assert set(other) == set(first) and all(np.allclose(other[i], first[i], rtol=0, atol=1e-6) for i in first)
    rows = [(r.text, bool(r.held)) for r in docs.orderBy("doc_id").limit(40).collect()]
    assert len(brute_scores(rows)) == 40


def test_preferences(spark):
    turns = spark.createDataFrame([(1, 0, "user", "hi"), (1, 1, "assistant", "yes"), (1, 2, "user", None), (1, 3, "assistant", "no"), (2, 0, "user", "alone"), (3, None, None, None), (3, None, None, None)], "conv_id long, turn long, role string, text string")
    got = {r.id: r for r in chat_format.format_preferences(chat_format.stale_pairs(turns)).collect()}
    assert got[1].n_prompt_turns == 3 and got[1].prompt.count("<|end|>") == 3
    a, b = map(int, got[1].chosen_mask.split("-"))
    assert got[1].chosen_completion[a:b] == "no<|end|>\n" and "yes" in got[1].rejected_completion
    assert got[2].status == "identical" and got[3].status == "identical" and got[3].n_prompt_turns == 2
    assert chat_format.format_preferences(chat_format.stale_pairs(turns.limit(0))).count() == 0


def test_preferences_with_nulls(spark):
    turn = "struct<role:string,text:string>"
    rows = [(1, [("user", "a"), ("assistant", None)], [("user", "a"), ("assistant", "b")]), (2, [("user", None)], [("user", "")]), (3, None, [(None, "x")])]
    got = {r.id: r for r in chat_format.format_preferences(spark.createDataFrame(rows, f"id int, chosen array<{turn}>, rejected array<{turn}>")).collect()}
    assert got[1].chosen_completion == "<|assistant|>\n<|end|>\n" and got[1].chosen_mask == "14-22" and got[1].rejected_mask == "14-23" and got[1].n_prompt_turns == 1
    assert got[2].status == "identical" and got[2].prompt == "<|user|>\n<|end|>\n"
    assert got[3].chosen_completion == "" and got[3].rejected_completion == "<||>\nx<|end|>\n" and got[3].status == "pair"


def test_jaccard_classes(spark, docs, empty):
    got = {}
    for r in ngram_join.jaccard_classes(docs).collect():
        got.setdefault(r.doc_id, r)
    assert {got[i].class_id for i in (1, 2, 3)} == {1} and got[2].n_links == 1 and got[3].n_links == 1
    assert got[1].n_copies == 3 and got[3].copy_of == 1
    assert got[4].class_id == 4 and got[5].class_id == 5 and got[6].n_links == 0
    assert ngram_join.jaccard_classes(empty).count() == 0
    kept = ngram_join.drop_near_duplicates(docs.withColumnsRenamed({"shard": "text_hash", "rate": "lost_id", "size": "class_key"}))
    assert kept.columns == ["doc_id", "text", "text_hash", "class_key", "_key", "lost_id"]
    assert sorted(r.doc_id for r in kept.where("doc_id is not null").collect()) == [1, 4, 5, 6, 7, 8, 9, 11]
    assert kept.where("doc_id is null").count() == 1


def jaccard_links(rows, n=5, threshold=0.8):
    """Shingle sets of rows (id, text), and the pairs of different sets that are similar, by brute force."""
    sets = [frozenset(tuple(w[k : k + n]) for k in range(max(1, len(w) - n + 1))) if (w := words(t)) else frozenset() for _, t in rows]
    kinds = sorted(set(sets) - {frozenset()}, key=lambda s: sorted(s))
    links = [(a, b) for i, a in enumerate(kinds) for b in kinds[:i] if min(len(a), len(b)) >= threshold * max(len(a), len(b)) and len(a & b) >= threshold * len(a | b)]
    return sets, links


def test_jaccard_rows_of_one_id(spark):
    """Two texts of one id are two sets; what is like one of them is not in the class of the other."""
    other = " ".join(f"z{i}" for i in range(60))
    rows = [(1, BASE), (1, other), (2, NEAR), (3, other.replace("z30", "new"))]
    got = ngram_join.jaccard_classes(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert all(r.n_links == 1 and r.n_copies == 1 for r in got)
    keys = {(r.doc_id, r.copy_of): r.class_key for r in got if r.doc_id > 1}
    by_key: dict = {}
    for r in got:
        by_key.setdefault((r.class_key, r.class_id), []).append(r.doc_id)
    assert sorted(map(sorted, by_key.values())) == [[1, 2], [1, 3]] and len({c for _, c in by_key}) == 2 and len(keys) == 2
    kept = ngram_join.drop_near_duplicates(spark.createDataFrame([*rows, (1, other), (None, BASE)], "doc_id long, text string"))
    assert sorted(map(tuple, kept.collect()), key=repr) == sorted([(1, BASE), (1, other), (None, BASE)], key=repr)


def test_jaccard_against_brute_force_on_the_given_table(spark):
    """Links, copies and classes of all documents; recall of links, and no link that is none."""
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text")
    rows = [tuple(r) for r in docs.collect()]
    sets, links = jaccard_links(rows)
    got = {r.doc_id: r for r in ngram_join.jaccard_classes(docs).collect()}
    many: dict = {}
    for a, b in links:
        many[a], many[b] = many.get(a, 0) + 1, many.get(b, 0) + 1
    found = sum(got[i].n_links for (i, _), s in zip(rows, sets, strict=True))
    want = sum(many.get(s, 0) for s in sets)
    assert 0.99 * want <= found <= want and want > 0
    assert all(got[i].n_links <= many.get(s, 0) for (i, _), s in zip(rows, sets, strict=True))
    least: dict = {}
    for (i, _), s in zip(rows, sets, strict=True):
        least[s] = min(i, least.get(s, i))
    assert all(got[i].copy_of == (least[s] if s else i) for (i, _), s in zip(rows, sets, strict=True))
    root = {s: s for s in least}

    def find(s):
        while root[s] != s:
            s = root[s]
        return s

    for a, b in links:
        root[find(a)] = find(b)
    first: dict = {}
    for (i, _), s in zip(rows, sets, strict=True):
        if s:
            first[find(s)] = min(i, first.get(find(s), i))
    assert sum(got[i].class_id == (first[find(s)] if s else i) for (i, _), s in zip(rows, sets, strict=True)) >= 0.995 * len(rows)


@pytest.mark.parametrize("most", [0, 32 << 20])
def test_components_with_a_hub(spark, monkeypatch, most):
    from arcloom.llm import components
    from arcloom.llm.components import connected_components, keyed_join

    monkeypatch.setattr(components, "BROADCAST_BYTES", most)
    edges = [(0, i) for i in range(1, 700)] + [(1000 + i, 1001 + i) for i in range(40)] + [(5000, 5000)]
    got = {r.node: r.root for r in connected_components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {i: 0 for i in range(700)} | {i: 1000 for i in range(1000, 1041)}
    assert connected_components(spark.createDataFrame([], "a long, b long")).count() == 0
    rows = spark.range(1000).select(F.when(F.col("id") < 600, 1).otherwise(F.col("id")).alias("k"), "id")
    keyed = keyed_join(rows, rows.groupBy("k").agg(F.count("*").alias("n"), F.min("id").alias("m")), ["k"], 1000)
    assert keyed.count() == 1000 and keyed.where("m <> case when id < 600 then 0 else id end").count() == 0


def test_jaccard_tiles_of_a_large_group(spark):
    """A group of more units than a tile: every pair once, by brute force."""
    dice = np.random.default_rng(5)
    base = [f"t{i}" for i in range(80)]
    rows = []
    for i in range(60):
        w = list(base)
        for j in dice.integers(0, 80, 2):
            w[j] = f"x{i}y{j}"
        rows.append((i, " ".join(w)))
    sets = {i: {tuple(t.split()[k : k + 5]) for k in range(76)} for i, t in rows}
    want = {i: sum(i != j and sets[i] != sets[j] and len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]) for j in sets) for i in sets}
    got = {r.doc_id: r.n_links for r in ngram_join.jaccard_classes(spark.createDataFrame(rows, "doc_id long, text string"), tile=16).collect()}
    assert got == want
    assert ngram_join.forest_depth(0.8, 32, 10, 0.999) == 7 and ngram_join.forest_depth(0.8, 4, 10, 0.999) == 1


def test_mixing(spark, empty):
    rows = [(i, f"good words number {i % 7} here") for i in range(60)] + [(100 + i, f"bad idiot words {i % 5}") for i in range(30)] + [(None, None), (200, "")]
    docs = spark.createDataFrame([(i, t, "s", 1.0, 0, "r") for i, t in rows], DOC)
    labels = spark.createDataFrame([(i, 1, 0) for i in range(40)] + [(100 + i, 1, 1) for i in range(20)] + [(500, None, None)], "doc_id long, quality int, toxic int")
    keyed = docs.withColumn("text_hash", F.xxhash64("text"))
    rates, said = mixing.document_rates(keyed, mixing.domain_labels(labels), [0.9, 0.0, 0.1], ["doc_id", "text_hash"])
    got = rates.collect()
    assert len(got) == 92 and all(r.rate >= 0 and abs(r.p0 + r.p1 + r.p2 - 1) < 1e-9 for r in got)
    tokens = [sum(r.n_tokens * r[f"p{k}"] * r.rate for r in got) for k in range(3)]
    assert abs(tokens[0] - said["targets"][0]) < 1e-3 * tokens[0] and abs(tokens[2] - said["targets"][2]) < 1e-2 * tokens[0]
    clashing = docs.withColumnsRenamed({"shard": "key", "size": "times", "_key": "copy"})
    drawn = mixing.draw(clashing, rates)
    assert drawn.columns == clashing.columns and drawn.where("doc_id < 60").count() >= 60
    assert {tuple(r) for r in drawn.drop("text").collect()} <= {tuple(r) for r in clashing.drop("text").collect()}
    with pytest.raises(ValueError):
        mixing.with_features(docs, ["rate"])
    assert mixing.document_rates(empty, mixing.domain_labels(labels), [1.0, 0.1, 0.1], ["doc_id"])[0].count() == 0


def test_mixing_against_plain_numbers(spark):
    """Posteriors of all documents by a plain naive Bayes, and the rates by a plain projected solution."""
    import xxhash

    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text")
    labels = mixing.domain_labels(spark.read.parquet("/root/testdata/sf0.001/labels.parquet"))
    rows = {r.doc_id: r.text for r in docs.collect()}
    domain = {}
    for r in labels.collect():
        if r.domain is not None and r.doc_id in rows:
            domain[r.doc_id] = max(r.domain, domain.get(r.doc_id, 0))
    blank = str.maketrans({**dict.fromkeys(mixing.BLANKS, " "), **dict.fromkeys(mixing.MARKS), **{u: u.lower() for u in mixing.UPPER}})

    def features(text):
        text = text or ""
        tokens = [w for w in text.translate(blank).split(" ") if w]
        n, symbols = len(tokens), sum(c in mixing.SYMBOLS for c in text)
        share = symbols / max(n, 1)
        style = [f" symbols {0 if not symbols else 1 if share < 0.02 else 2 if share < 0.1 else 3 if share < 0.4 else 4}", f" distinct {10 * len(set(tokens)) // max(n, 1)}"]
        style += [f" capitals {10 * sum(c in mixing.UPPER for c in text) // max(len(text), 1)}", f" letters {min(len(text) // max(n, 1), 20)}"]

        def bucket(f):
            h = xxhash.xxh64_intdigest(f, 42)
            h -= (h >> 63) << 64
            return -(abs(h) % 1_000_003) - 1 if f[0] == " " else h % (1 << mixing.BITS)

        return n, [bucket(f) for f in [*set(tokens), *style]]

    every = {i: features(t) for i, t in rows.items()}
    size = [sum(d == k for d in domain.values()) for k in range(3)]
    seen: dict = {}
    for i, d in domain.items():
        for f in every[i][1]:
            seen.setdefault(f, [0, 0, 0])[d] += 1
    weight = {}
    for f, c in seen.items():
        log_p = [math.log((c[k] + sum(c) / sum(size)) / (size[k] + 1)) for k in range(3)]
        w = [log_p[1] - log_p[0], log_p[2] - log_p[0]]
        if sum(c) >= 5 and max(map(abs, w)) >= 1:
            weight[f] = w
    prior = [math.log((x + 1) / (sum(size) + 3)) for x in size]
    model, priors = mixing.fit(docs, labels)
    got = {r.doc_id: r for r in mixing.posteriors(docs, model, priors, ["doc_id"]).collect()}
    for i, (n, fs) in every.items():
        logit = [prior[0], *[prior[k] + max(-60, min(60, sum(weight[f][k - 1] for f in fs if f in weight))) for k in (1, 2)]]
        p = np.exp(np.array(logit) - max(logit))
        assert got[i].n_tokens == n and np.allclose([got[i].p0, got[i].p1, got[i].p2], p / p.sum(), atol=1e-9)
    rates, said = mixing.document_rates(docs, labels, [0.9, 0.06, 0.04], ["doc_id"])
    found = rates.collect()
    a = np.array([[r.n_tokens * r[f"p{k}"] for k in range(3)] for r in found])
    rate = np.array([r.rate for r in found])
    assert (rate >= 0).all() and np.allclose(a.T @ rate, said["targets"], rtol=1e-3) and np.allclose(said["targets"][0], a[:, 0].sum())


def test_pipeline_stages_against_brute_force(spark):
    """Every stage on what the stage before kept."""
    import corpus_pipeline
    from tokenizers import Tokenizer

    sf = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    run = dict(corpus_pipeline.STAGES)
    keep = lambda df: {r.doc_id: r.text for r in df.collect()}
    good = run["quality"](spark, docs, sf)
    assert good.columns == docs.columns
    graded = {r.doc_id: r for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    kept, before = keep(good), keep(docs)
    clean = [i for i, r in graded.items() if i in before and r.quality == 1 and not r.toxic]
    assert sum(i in kept for i in clean) >= 0.95 * len(clean)
    single = run["near_duplicates"](spark, good, sf)
    rows = sorted(kept.items())
    sets, links = jaccard_links(rows)
    root = {s: s for s in sets}

    def find(s):
        while root[s] != s:
            s = root[s]
        return s

    for a, b in links:
        root[find(a)] = find(b)
    first: dict = {}
    for (i, _), s in zip(rows, sets, strict=True):
        first.setdefault(find(s) if s else i, i)
    assert single.columns == docs.columns and set(keep(single)) == set(first.values())
    apart = run["decontamination"](spark, single, sf)
    items = [words(r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    want = {i for i, t in keep(single).items() if not brute_overlap(words(t), items)}
    assert apart.columns == docs.columns and set(keep(apart)) == want
    mixed = run["mixing"](spark, apart, sf)
    assert mixed.columns == docs.columns and set(keep(mixed)) <= want and len(keep(mixed)) >= 0.5 * len(want)
    tok, at, digest = Tokenizer.from_file(token_output.tokenizer_file()), 0, []
    for i, t in sorted((r.doc_id, r.text) for r in mixed.collect()):
        ids = np.array([*tok.encode(t or "", add_special_tokens=False).ids, 2], "<u4")
        digest.append((i, at, len(ids), zlib.crc32(ids)))
        at += len(ids)
    assert sorted(map(tuple, run["tokens"](spark, mixed, sf).collect()), key=lambda r: r[1]) == digest
    empty = docs.limit(0)
    assert all(run[s](spark, empty, sf).count() == 0 for s in ("quality", "near_duplicates", "decontamination", "mixing", "tokens"))


def brute_overlap(doc, items, need=12, identity=0.75):
    """Whether an item overlaps on some diagonal: matching ends, long and similar enough."""
    for item in items:
        if len(item) < 5:
            continue
        diagonals: dict = {}
        where: dict = {}
        for j, w in enumerate(item):
            where.setdefault(w, []).append(j)
        for i, w in enumerate(doc):
            for j in where.get(w, ()):
                diagonals.setdefault(i - j, []).append(i)
        for d, at in diagonals.items():
            if len(item) < need:
                if 0 <= d <= len(doc) - len(item) and len(at) >= identity * len(item):
                    return True
                continue
            for x in range(len(at)):
                for y in range(x, len(at)):
                    n = at[y] - at[x] + 1
                    if n >= need and y - x + 1 >= identity * n:
                        return True
    return False


def test_decontamination_against_brute_force_on_the_given_table(spark):
    docs, bench = (spark.read.parquet(f"/root/testdata/sf0.001/{t}.parquet") for t in ("documents", "benchmark"))
    items = [words(r.text) for r in bench.collect()]
    want = {r.doc_id for r in docs.collect() if brute_overlap(words(r.text), items)}
    assert {r.id for r in decontamination.find_overlaps(docs, bench).collect()} == want


def test_pipeline_mixing_meets_its_shares(spark, tmp_path, caplog):
    """Domains that have less than is asked for are raised, and what is attained is said."""
    import corpus_pipeline

    rows = [(i, f"good words number {i % 7} here and some more of them {i}") for i in range(2000)] + [(5000 + i, f"bad awful words {i}") for i in range(40)] + [(6000 + i, f"you idiot {i}") for i in range(40)]
    every = spark.createDataFrame(rows, "doc_id long, text string")
    every.write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(i, int(i < 5000), int(i >= 6000)) for i, _ in rows], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    short = every.where("doc_id < 5001 or doc_id = 6000")
    with caplog.at_level("INFO", "corpus_pipeline"):
        drawn = {r.doc_id: r["count"] for r in corpus_pipeline.mix(spark, short, str(tmp_path)).groupBy("doc_id").count().collect()}
    assert "converged True" in caplog.text
    assert drawn[5000] > 1 and drawn[6000] > 1


def test_best_fit_decreasing_against_one_by_one():
    dice = np.random.default_rng(2)
    sizes = dice.integers(1, 40, 300).tolist()
    histogram = [(s, sizes.count(s)) for s in set(sizes)]
    runs, fill = sharding.best_fit_decreasing(histogram, 100)
    left: list[int] = []
    for s in sorted(sizes, reverse=True):
        fits = [(x, i) for i, x in enumerate(left) if x >= s]
        i = min(fits)[1] if fits else len(left)
        if not fits:
            left.append(100)
        left[i] -= s
    assert sorted(fill) == sorted(100 - x for x in left)
    assert sum(b - a for _, a, b, _ in runs) == 300
    with pytest.raises(ValueError):
        sharding.best_fit_decreasing([(101, 1)], 100)
    even = sharding.even_bins(histogram, 7)
    by = np.bincount([r[3] for r in even], [(r[2] - r[1]) * r[0] for r in even], 7)
    assert by.max() - by.min() <= 40


def test_sharding(docs, empty):
    got = sharding.pack_groups(docs, 3).collect()
    assert len(got) == docs.count()
    for s in range(3):
        assert sorted(r.slot for r in got if r.shard == s) == list(range(sum(r.shard == s for r in got)))
    assert len({r.shard for r in got if r.text_crc32 == zlib.crc32(BASE.encode())}) == 1
    assert {r.size for r in got if r.doc_id in (4, 5)} == {8}
    assert sharding.pack_groups(empty, 3).count() == 0


def brute_lines(rows):
    key = lambda x: "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in x.strip(" \t\n\x0b\x0c\r"))
    last = 2**63 - 1
    where: dict = {}
    for i, t in rows:
        for x in (t or "").split("\n"):
            where.setdefault(key(x), set()).add(last if i is None else i)
    out = []
    for i, t in rows:
        lines = (t or "").split("\n")
        kept = [x for x in lines if len(key(x)) < 10 or len(where[key(x)]) < 2 or min(where[key(x)]) == (last if i is None else i)]
        out.append((i, len(lines), len(lines) - len(kept), "\n".join(kept)))
    return sorted(out, key=repr)


def test_line_dedup(docs, empty):
    bitmaps = line_dedup.line_bitmaps(docs)
    got = line_dedup.apply_bitmaps(docs, bitmaps).collect()
    assert sorted(map(tuple, got), key=repr) == brute_lines([(r.doc_id, r.text) for r in docs.collect()])
    assert line_dedup.apply_bitmaps(empty, line_dedup.line_bitmaps(empty)).count() == 0


def test_line_dedup_hot_and_cold_keys(spark):
    """A line that most documents share, lines that few share, and one range exchange without a join of lines."""
    rows = [(i, "\n".join([f"shared by all documents {i % 2}" * (i != 7), f"pair line number {i // 2}", "own line of " + "x" * i, "short"])) for i in range(3000)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    bitmaps = line_dedup.line_bitmaps(docs)
    assert sorted(map(tuple, line_dedup.apply_bitmaps(docs, bitmaps).collect()), key=repr) == brute_lines(rows)
    plain = line_dedup.line_bitmaps(docs.where("doc_id < 900"))
    text = plain._jdf.queryExecution().executedPlan().toString()
    assert text.count("rangepartitioning") == 1 and "Join" not in text
    lines = docs.select(F.xxhash64("text").alias("h1"), F.xxhash64(F.lit(1), "text").alias("h2"), F.col("doc_id").alias("doc"))
    assert line_dedup.hot_firsts(lines) is None
    many = lines.unionByName(spark.range(2000).select(F.lit(5).cast("long").alias("h1"), F.lit(6).cast("long").alias("h2"), (F.col("id") + 40).alias("doc")))
    assert list(map(tuple, line_dedup.hot_firsts(many).collect())) == [(5, 6, 40)]


def test_line_dedup_over_many_words(spark):
    rows = [(1, "the very first line"), (2, "\n".join(["the very first line"] * 130 + [f"own line number {i}" for i in range(70)]))]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = line_dedup.apply_bitmaps(docs, line_dedup.line_bitmaps(docs)).collect()
    assert sorted(map(tuple, got), key=repr) == brute_lines(rows)


def test_decontamination(spark, docs, empty):
    item = "the quick brown fox jumps over the lazy dog while nobody looks at the old grey barn door"
    swapped = item.replace("lazy", "sleepy").replace("old", "new")
    rows = [(50, f"before it {item} after it", "s", 1.0, 0, "r"), (51, f"{swapped} tail", "s", 1.0, 0, "r"), (52, " ".join(item.split()[:8]), "s", 1.0, 0, "r")]
    every = docs.unionByName(spark.createDataFrame(rows, DOC))
    items = spark.createDataFrame([(9, item), (10, None), (11, ""), (12, "too short")], "item_id long, text string")
    found = {r.id: r.spans for r in decontamination.find_overlaps(every, items).collect()}
    assert set(found) == {50, 51}
    assert (found[50][0].doc_start, found[50][0].doc_end, found[50][0].matched) == (2, 20, 18)
    assert found[51][0].matched == 16
    blocks = decontamination.find_overlaps(every, items, block_items=1)
    assert {r.id for r in blocks.collect()} == {50, 51}
    clean = decontamination.decontaminate(every, items)
    assert clean.columns == every.columns and clean.count() == every.count() - 2
    assert decontamination.decontaminate(empty, items).count() == 0 and decontamination.find_overlaps(every, items.limit(0)).count() == 0


def _substituted(n, off):
    """Patterns of n words of which ``off`` are substituted, as bits of the matches."""
    return [sum(1 << i for i in range(n) if i not in out) for out in itertools.combinations(range(n), off)]


def test_every_overlap_has_a_seed():
    """Longer ones hold one of 12 to 23 words that is as similar; fewer substitutions are no harder."""
    for need, top in [(12, 24), *((n, n + 1) for n in range(5, 12))]:
        bits = [(sum(1 << i for i, c in enumerate(m) if c == "1"), len(m)) for m in decontamination.masks_for(need, 0.75)]
        for n in range(need, top):
            every = np.array(_substituted(n, n // 4))
            hit = np.zeros(len(every), bool)
            for m, span in bits:
                for at in range(n - span + 1):
                    hit |= every >> at & m == m
            assert hit.all()
    assert decontamination.masks_for(12, 0.5) == ("1",) and decontamination.masks_for(3, 0.75) == ("11",)


def test_every_overlap_is_found():
    item = [f"i{k}" for k in range(30)]
    whole = decontamination.SeedIndex([(1, " ".join(item)), (2, "s0 s1 s2 s3 s4 s5 s6 s7")], 5, 12, 0.75)
    texts = []
    for n, off in [(12, 2), (12, 3), (16, 4)]:
        inner = [m for m in _substituted(n, off) if m & 1 and m >> (n - 1)]
        texts += [["x"] + [item[7 + k] if m >> k & 1 else "y" for k in range(n)] + ["z"] for m in inner]
    texts += [[f"s{k}" if m >> k & 1 else "y" for k in range(8)] for m in _substituted(8, 2)]
    batch = pa.RecordBatch.from_pydict({"text": [" ".join(t) for t in texts]})
    found = {a + k: s for _, a, f in decontamination._search(iter([batch]), whole, "text") for k, s in f.items()}
    assert set(found) == set(range(len(texts)))
    assert all(s[0]["matched"] >= 0.75 * (s[0]["doc_end"] - s[0]["doc_start"]) for s in found.values())
    near = [" ".join(item[:8] + ["y"] * 4), " ".join(item[:11]), "s0 s1 y s3 y s5 y s7"]
    assert not any(f for *_, f in decontamination._search(iter([pa.RecordBatch.from_pydict({"text": near})]), whole, "text"))


def test_windows_against_brute_force():
    dice = np.random.default_rng(6)
    for _ in range(300):
        same = dice.random(int(dice.integers(1, 40))) < 0.75
        ok = {(a, b) for a in range(len(same)) for b in range(a + 6, len(same) + 1) if same[a] and same[b - 1] and same[a:b].sum() >= 0.75 * (b - a)}
        got = decontamination.windows(same, 6, 0.75)
        assert set(got) <= ok and bool(got) == bool(ok)
        assert all(any(a < d and c < b for c, d in got) for a, b in ok)


def exact_neighbours(ids, x, q, k):
    """The k nearest of query ``q`` by plain scoring, ties to the smaller id."""
    s = (x * x[np.flatnonzero(ids == q)[0]]).sum(1)
    other = ids != q
    best = np.lexsort((ids[other], -s[other]))[:k]
    return list(zip(ids[other][best].tolist(), s[other][best].tolist(), strict=True))


def found_neighbours(index, queries, **how):
    got: dict = {}
    for r in ann.search(index, queries, **how).orderBy("query_id", "rank").collect():
        assert r.rank == len(got.setdefault(r.query_id, [])) + 1
        got[r.query_id].append((r.vec_id, r.score))
    return got


def test_ann(spark):
    """Clustered vectors: high recall from few parts; ranks, scores and ties are exact among what is found."""
    dice = np.random.default_rng(3)
    x = (dice.standard_normal((30, 16))[dice.integers(0, 30, 3000)] + 0.3 * dice.standard_normal((3000, 16))).astype(np.float32)
    x[2980:] = x[0]
    rows = [(i, v.tolist()) for i, v in enumerate(x)] + [(5000, x[0].tolist()), (5001, None), (5002, [0.0] * 16), (5003, [float("nan")] + [1.0] * 15), (5004, [None] + [1.0] * 15), (5005, [1.0])]
    table = spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumn("part", F.lit("clash"))
    index = ann.build_index(table, chunk=500)
    assert index.vectors.count() == 3001 and index.router.parts == 55 and index.router.probes < 20
    got = found_neighbours(index, index.vectors.where("id % 20 = 0"), chunk=64)
    ids, full = np.append(np.arange(3000), 5000), np.concatenate([x, x[:1]]).astype(float)
    hit = 0
    for q in (i for i in ids if i % 20 == 0):
        want = exact_neighbours(ids, full, q, 20)
        hit += len({v for v, _ in want} & {v for v, _ in got[q]})
        assert len(got[q]) == 20 and got[q] == sorted(got[q], key=lambda r: (-r[1], r[0]))
        assert all(s == (full[np.flatnonzero(ids == v)[0]] * full[np.flatnonzero(ids == q)[0]]).sum() for v, s in got[q])
    assert hit / (20 * len(got)) >= 0.9
    assert got[0] == exact_neighbours(ids, full, 0, 20)  # equal vectors: by id
    few = ann.build_index(table.where("vec_id < 5"))
    assert ann.search(few, few.vectors.where("id = 0")).count() == 4
    none = ann.build_index(table.limit(0))
    assert ann.search(none, none.vectors).count() == 0


def test_ann_on_the_given_table(spark):
    """Vectors without any structure: parts are fitted and recall holds."""
    index = ann.build_index(spark.read.parquet("/root/testdata/sf0.1/embeddings.parquet"))
    assert 40 <= index.router.parts <= 50 and 1 < index.router.probes < index.router.parts
    rows = index.vectors.collect()
    ids, x = np.array([r.id for r in rows]), np.array([r.v for r in rows])
    got = found_neighbours(index, index.vectors.where("id % 20 = 0"))
    assert set(got) == {i for i in ids.tolist() if i % 20 == 0}
    assert np.mean([len({v for v, _ in got[q]} & {v for v, _ in exact_neighbours(ids, x, q, 20)}) / 20 for q in got]) >= 0.9


def test_bundles_hold_every_part():
    assert ann.bundles(np.array([5, 4, 1, 30, 2, 2]), 10).tolist() == [0, 0, 0, 1, 2, 2]
    assert len(ann.bundles(np.zeros(0, np.int64), 10)) == 0


def test_repair_round_trip():
    dice = np.random.default_rng(4)
    ids = dice.choice(50, 20_000, p=np.r_[[0.3, 0.2], np.full(48, 0.5 / 48)]).astype(np.uint32)
    data = token_output.pack(ids)
    shard = token_output.Shard(data)
    assert (shard.ids() == ids).all() and len(data) < 2 * len(ids)
    for a, b in ((0, 5), (1023, 1026), (7777, 15000), (19_990, 30_000), (5, 5)):
        assert (shard.range(a, b) == ids[a:b]).all()
    assert len(token_output.Shard(token_output.pack(ids[:0])).ids()) == 0


def _most_often(seq):
    """The most occurrences of a pair without overlap, one by one."""
    seen: dict = {}
    for i, pair in enumerate(zip(seq.tolist(), seq[1:].tolist(), strict=False)):
        n, last = seen.get(pair, (0, -2))
        if i > last + 1 or pair[0] != pair[1]:
            seen[pair] = (n + 1, i)
    return max((n for n, _ in seen.values()), default=0)


def test_repair_leaves_no_frequent_pair():
    dice = np.random.default_rng(7)
    passage = dice.integers(0, 60_000, 3000)
    skewed = np.concatenate([x for _ in range(40) for x in (passage, dice.zipf(1.5, 200) % 500)])
    cases = [skewed, np.full(100_003, 5), np.tile([1, 1, 2], 5000), dice.integers(0, 3, 20_000), np.arange(100_000), np.array([70_000] * 20)]
    for ids in (x.astype(np.uint32) for x in cases):
        seq, rules, base = token_output.repair(ids)
        assert _most_often(seq) < 4
        data = token_output.pack(ids)
        shard = token_output.Shard(data)
        assert (shard.ids() == ids).all() and (shard.range(777, 9999) == ids[777:9999]).all()
    assert len(token_output.repair(np.full(1 << 20, 5))[0]) < 16 and len(token_output.repair(skewed.astype(np.uint32))[0]) < 4 * 40 * 200
    with pytest.raises(RuntimeError):
        token_output.repair(skewed, rounds=2)


def test_token_files(docs, empty):
    from tokenizers import Tokenizer

    path = token_output.tokenizer_file()
    tok, at, want = Tokenizer.from_file(path), 0, []
    rows = sorted(((r.doc_id, r.text or "") for r in docs.collect()), key=lambda r: (r[0] is not None, r[0] or 0))
    for i, t in rows:
        ids = np.array([*tok.encode(t, add_special_tokens=False).ids, 2], "<u4")
        want.append((i, at, len(ids), zlib.crc32(ids)))
        at += len(ids)
    shards = token_output.write_tokens(docs, path, shard_tokens=500)
    got = sorted(map(tuple, token_output.read_digest(shards).collect()), key=lambda r: r[1])
    assert got == want
    assert token_output.read_digest(token_output.write_tokens(empty, path)).count() == 0


def test_encoder_on_odd_texts():
    from tokenizers import Tokenizer

    path = token_output.tokenizer_file()
    odd = ["it's don't x's, <|endoftext|>, a<|startoftext|>b", "Σας ΣΑΣ İst, é É, Å 12ab", "♫ x ♫♫ y", "\t x y\x1cz", "", None, "ª, º. ß! a-b_c", "x" * 5000]
    ids, n = token_output.ChunkEncoder(path).encode(pa.array(odd))
    tok = Tokenizer.from_file(path)
    assert ids.tolist() == [i for t in odd for i in [*tok.encode(t or "", add_special_tokens=False).ids, 2]] and len(n) == len(odd)


def test_quality(spark, docs, empty):
    good = [(i, f"fine prose of document {i} goes on with sense") for i in range(80)]
    poor = [(100 + i, "BUY!! NOW!! " * 8 + str(i)) for i in range(40)]
    toxic = [(200 + i, f"you idiot number {i} are worthless") for i in range(40)]
    every = spark.createDataFrame([(i, t, "s", 1.0, 0, "r") for i, t in good + poor + toxic], DOC).unionByName(docs.where("doc_id is null or text is null"))
    labels = spark.createDataFrame([(i, 1, 0) for i in range(60)] + [(100 + i, 0, 0) for i in range(30)] + [(200 + i, 1, 1) for i in range(30)] + [(300, None, 1), (301, 1, None)], "doc_id long, quality int, toxic int")
    model = quality.train(every, quality.graded(labels))
    kept = quality.select_documents(every, model)
    assert kept.columns == every.columns
    ids = {r.doc_id for r in kept.collect()}
    assert set(range(80)) <= ids and not ids & set(range(100, 300))
    scores = quality.score_documents(every, model).select("quality.*").collect()
    assert all(0 <= s.expected_grade <= 2 and 0 <= s.tail_prob <= 1 for s in scores)
    untrained = quality.train(every, quality.graded(labels).limit(0))
    assert quality.select_documents(every, untrained).count() == every.count()
    assert quality.select_documents(empty, model).count() == 0


def test_quality_does_not_depend_on_the_layout(spark):
    """One model, one cut and one kept set however the tables are laid out; all rows agree with plain scoring."""
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.001/{t}.parquet") for t in ("documents", "labels"))
    docs = docs.select("doc_id", "text", F.lit(7).alias("quality"))
    made = [quality.train(docs.repartition(n), quality.graded(labels).repartition(n)) for n in (1, 7, 16)]
    assert all(m.cut == made[0].cut and (m.weights == made[0].weights).all() and (m.thresholds == made[0].thresholds).all() for m in made)
    m, make = made[0], quality.Features()
    rows, scored = docs.collect(), {r.doc_id: r.q for r in quality.score_documents(docs, m, out="q").collect()}
    for r in rows:
        _, features, style = make(pa.array([r.text]))
        margin = sum(m.weights[f] for f in features.tolist()) + float((style[0] * m.style).sum())
        below = [1 / (1 + math.exp(margin - t)) for t in m.thresholds]
        assert abs(scored[r.doc_id].expected_grade - (2 - sum(below))) < 1e-9 and abs(scored[r.doc_id].tail_prob - (1 - below[1])) < 1e-9
        assert scored[r.doc_id].keep == (scored[r.doc_id].tail_prob >= m.cut)
    kept = quality.select_documents(docs, m)
    assert kept.columns == docs.columns and {r.quality for r in kept.collect()} == {7}
    assert {r.doc_id for r in kept.collect()} == {i for i, s in scored.items() if s.keep}
    with pytest.raises(ValueError):
        quality.score_documents(docs, m)


def test_ordinal_fit_lowers_the_likelihood_and_orders_grades():
    """Against plain numbers: the fitted loss is a minimum along every weight and threshold."""
    dice = np.random.default_rng(1)
    true = np.array([2.0, -2.0, 0.0, 1.0])
    x = (dice.random((600, 4)) < 0.5).astype(float)
    grade = np.searchsorted([-1.0, 1.0], x @ true + dice.logistic(size=600))
    rows, features = np.nonzero(x)
    m = quality.fit_ordinal(rows, features, np.zeros((600, 1)), grade, steps=3000, l1=0.0, width=4)

    def loss(w, t):
        edge = 1 / (1 + np.exp(-(np.concatenate([[-60.0], t, [60.0]])[None, :] - (x @ w)[:, None])))
        return -np.log(edge[np.arange(600), grade + 1] - edge[np.arange(600), grade]).mean()

    least = loss(m.weights, m.thresholds)
    assert least < loss(np.zeros(4), m.thresholds) and m.thresholds[0] < m.thresholds[1]
    for i in range(4):
        for step in (-0.2, 0.2):
            assert loss(m.weights + step * np.eye(4)[i], m.thresholds) > least
    assert (np.sign(m.weights[[0, 1, 3]]) == [1, -1, 1]).all()


def test_words():
    assert words("It's A-b  Été_x\n9") == ["it", "s", "a", "b", "été", "x", "9"] and words(None) == []


def test_op8_neighbours_of_the_sample_take_little_of_the_driver():
    """At most 64 MB beside 4 MB of vectors, and the nearest of a plain sort."""
    import tracemalloc

    import numpy as np

    from arcloom.llm.ann import neighbour_graph

    x = np.random.default_rng(2).standard_normal((8192, 64))
    tracemalloc.start()
    near = neighbour_graph(x, 20)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 64 << 20
    for i in (0, 63, 64, 8191):
        score = x @ x[i]
        score[i] = -np.inf
        assert set(near[i].tolist()) == set(np.argsort(-score)[:20].tolist())


def test_op9_only_nested_symbols_are_split_again():
    """Of a long sequence with one deep symbol, only what that one leaves is looked at again; a shard reads back."""
    import numpy as np

    from arcloom.llm.token_output import Shard, _lengths, _split, pack

    class Seen:
        def __init__(self, values):
            self.values, self.n = values, 0

        def __getitem__(self, at):
            self.n += len(at)
            return self.values[at]

    rules = np.array([(0, 1)] + [(9 + k, 2) for k in range(1, 40)])
    base, seq = 10, np.zeros(10_000, np.int64)
    seq[5000] = base + 39
    lens = _lengths(rules, base)
    assert lens[:base].tolist() == [1] * base and lens[base:].tolist() == list(range(2, 42))
    long = Seen(np.arange(base + 40) >= base)
    out = _split(seq, rules, base, long)
    assert out.tolist() == [0] * 5000 + [0, 1] + [2] * 39 + [0] * 4999
    assert long.n < 2 * len(seq)
    ids = np.concatenate([np.tile(np.arange(300), 50), np.zeros(3000, np.int64), np.arange(500)]).astype(np.uint32)
    shard = Shard(pack(ids))
    assert (shard.ids() == ids).all() and (shard.range(14_000, 17_000) == ids[14_000:17_000]).all()
