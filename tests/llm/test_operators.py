"""The ten operators against brute force, on odd rows and under hot groups."""

import collections
import hashlib
import math
import pickle
import random
import re
import zlib

import numpy as np
import pandas as pd
import pyarrow as pa
import public_tokenizers
import pytest
import xxhash
from pyspark.sql import functions as F

from tests.llm.conftest import ODD
from trailgraph.llm import decontamination, idcoder, line_dedup, mixing, near_text, quality, sharding, simhash, substring, token_counts, token_output, url_filter

PIECES, WORDS = public_tokenizers.path("piece_bpe_32k.model"), public_tokenizers.path("word_bpe_49k.json")
SPLIT = re.compile("[^\x20\x09-\x0d]+")


def split(t):
    return SPLIT.findall(t or "")


def by_id(df, *names):
    return sorted((tuple(None if v is None else v for v in (r[n] for n in names)) for r in df.collect()), key=str)


def low(t):
    return re.sub("[A-Z]", lambda m: m[0].lower(), t or "")


@pytest.fixture(scope="module")
def corpus(sf):
    return pd.read_parquet(f"{sf}/documents.parquet")


# ---- 1 ----

def _tree(rows, limit):
    """Buckets of (bits, size) rows, split one bit at a time while over the limit."""
    out, todo = {}, [("", rows)]
    while todo:
        p, rs = todo.pop()
        if sum(n for _, n in rs) <= limit or len(p) == 60:
            out[p] = rs
            continue
        for b in "01":
            if part := [r for r in rs if r[0][len(p)] == b]:
                todo.append((p + b, part))
    return out


@pytest.mark.parametrize("limit", [1_500, 6_000, 40_000, 10**9])
def test_sharding_splits_only_what_is_too_large(spark, sf, corpus, limit):
    d = spark.read.parquet(f"{sf}/documents.parquet").where("octet_length(text) <= 1500" if limit == 1500 else "true")
    got = sharding.assign(d, limit).select("doc_id", F.octet_length("text").alias("n"), "shard.*").collect()
    bits = {r.doc_id: f"{int(hashlib.md5(str(r.doc_id).encode()).hexdigest()[:15], 16):060b}" for r in got}
    tree = _tree([(bits[r.doc_id], r.n) for r in got], limit)
    where = {b: p for p, rs in tree.items() for b, _ in rs}
    for r in got:
        p = where[bits[r.doc_id]]
        if r.page == 0:
            assert (r.bits, r.local_depth, r.bytes) == (p, len(p), sum(n for _, n in tree[p]))
            assert r.bytes <= limit
        else:
            assert p.startswith(r.bits) and r.n > limit
    assert len(got) == d.count()


def test_sharding_pages_of_one_key(docs):
    d = docs([(7, "x" * 10)] * 300 + [(i, "y" * 10) for i in range(40)])
    got = sharding.assign(d, 95).select("doc_id", "shard.*").collect()
    sizes = collections.Counter(r.name for r in got)
    assert len(got) == 340 and all(n * 10 <= 95 for n in sizes.values())
    assert all(r.bytes == 10 * sizes[r.name] for r in got)


def test_sharding_is_the_same_again(docs):
    """Pages follow from the rows, whatever task holds them."""
    rows = [(7, f"{'x' * (i % 13)}{i % 50}") for i in range(300)] + [(i, "y" * 10) for i in range(40)]
    a, b = docs(rows), docs(rows[::-1]).repartition(7)
    pages = lambda d: by_id(sharding.assign(d, 95).select("doc_id", "text", "shard.*"), "doc_id", "text", "name", "bytes")
    assert pages(a) == pages(b)


def test_sharding_goes_deeper_only_where_it_must(spark, docs, monkeypatch):
    """Rows under the prefixes that are too large, and only they, are counted again."""
    counted = []
    real = sharding.directory
    monkeypatch.setattr(sharding, "directory", lambda hist, limit, depth, above=-1: (counted.append(hist.count()), real(hist, limit, depth, above))[1])
    d = docs([(7, "x" * 10)] * 500 + [(i, "y" * 10) for i in range(100, 400)])
    got = sharding.assign(d, 200).select("doc_id", "shard.*").collect()
    assert len(got) == 800 and all(n <= 4 for n in counted[2:])
    per = collections.Counter(r.name for r in got)
    assert all(r.bytes == 10 * per[r.name] <= 200 for r in got)


def test_sharding_odd_rows(docs, spark, tmp_path):
    d = docs(ODD, extra=True)
    got = sharding.assign(d, 1 << 20)
    assert got.count() == len(ODD) and len(got.columns) == len(d.columns) + 1
    assert got.columns[-1] == "shard_" and got.select("shard", "shard_.name").count() == len(ODD)
    sharding.write_shards(docs(ODD, extra=True).withColumnRenamed("a b", "a_b"), str(tmp_path / "out"), 1 << 20)
    assert spark.read.parquet(str(tmp_path / "out")).count() == len(ODD)
    over = sharding.assign(docs([(7, "x" * 10)] * 30).selectExpr("*", "1 AS __size", "2 AS __page", "3 AS __row"), 95)
    assert over.count() == 30 and over.select("shard.name").distinct().count() >= 4
    assert sharding.assign(docs(ODD).limit(0), 100).count() == 0
    with pytest.raises(ValueError):
        sharding.assign(d, 0)


# ---- 2 ----

def _substrings(rows, size):
    first = {}
    for d, t in rows:
        w = split(t)
        for i in range(len(w) - size + 1) if d is not None else ():
            g = tuple(w[i : i + size])
            first[g] = min(first.get(g, d), d)
    out = []
    for d, t in rows:
        w, gone = split(t), set()
        for i in range(len(w) - size + 1) if d is not None else ():
            if first[tuple(w[i : i + size])] < d:
                gone.update(range(i, i + size))
        kept = " ".join(x for i, x in enumerate(w) if i not in gone)
        out.append((d, len(w), len(gone), hashlib.sha256(kept.encode()).hexdigest()))
    return sorted(out, key=str)


@pytest.mark.parametrize("size", [50, 6, 7])
def test_substrings_of_planted_repeats(docs, size):
    r = random.Random(size)
    words = lambda n: " ".join(f"w{r.randrange(10**6)}" for _ in range(n))
    shared = [words(n) for n in (size - 1, size, size + 1, 3 * size)]
    rows = [(i, " ".join([words(r.randrange(30)), *r.sample(shared, r.randrange(3)), words(r.randrange(30))])) for i in r.sample(range(1000), 60)]
    rows += [(2000 + i, words(5) + " " + shared[3]) for i in range(80)] + [(5, "a " * 300), (6, "a " * 120)]
    got = by_id(substring.deduplicate(docs(rows), window=size), "doc_id", "n_words", "n_removed", "kept_sha256")
    assert got == _substrings(rows, size)


def test_substrings_odd_rows(docs):
    d = docs(ODD, extra=True)
    assert by_id(substring.deduplicate(d, window=10), "doc_id", "n_words", "n_removed", "kept_sha256") == _substrings([r[:2] for r in ODD], 10)
    assert substring.deduplicate(d.limit(0)).count() == 0
    kept = {r.doc_id: r.kept_text for r in substring.deduplicate(docs(["x y z", "x y z q"]), window=3, with_text=True).collect()}
    assert kept == {0: "x y z", 1: "q"}


def test_a_window_needs_both_hashes():
    taken, state = substring._Taken(1), {"bucket": 0}
    one, h = np.array([1], np.uint32), np.array([77], np.uint64).tobytes()
    entry = lambda check, at: np.array([check << 32 | at], np.uint64)
    for kind, i, spots in ((substring.FIRST, 1, np.array([5], np.uint32)), (substring.ALL, 2, entry(6, 30)), (substring.ALL, 3, entry(5, 40)), (substring.ALL, 1, entry(5, 0))):
        assert not list(taken.step(state, kind, np.array([i]), np.array([0]), one, h, spots))
    (batch,) = taken.finish()
    (row,) = batch.to_pylist()
    assert np.frombuffer(row["ids"], np.int64).tolist() == [3]


# ---- 3 ----

def test_piece_counts(docs, corpus):
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=PIECES)
    r = random.Random(1)
    odd = ["".join(r.choice([" ", "  ", "a", "the", "\n", "▁", "é", "中", "<s>", "</s>", "<unk>", "\t", "zz", "1"]) for _ in range(r.randrange(12))) for _ in range(300)]
    texts = corpus.text.tolist()[:60] + odd + [t for _, t in [x[:2] for x in ODD]]
    got = {x.doc_id: (x.n_bytes, x.n_tokens, x.over_limit) for x in token_counts.counts(docs(list(enumerate(texts)), extra=True), PIECES).collect()}
    for i, t in enumerate(texts):
        n = len(sp.encode(t or ""))
        assert got[i] == (len((t or "").encode()), n, n > 4096), t
    assert token_counts.counts(docs(ODD).limit(0), PIECES).count() == 0


def test_memo_that_begins_anew(monkeypatch):
    c = token_counts.PieceCounter(PIECES)
    assert c.separable and len(c.single) > 10_000
    monkeypatch.setattr(token_counts, "MEMO", 3)
    for t in ("qzx wvq qqz jjx kkz", "the qzx and wvq xx1 xx2 xx3 xx4", "qzx qzx"):
        assert c.count(t) == len(c.model.encode(t))


def test_library_counts(docs):
    texts = ["Hello <|endoftext|> there", "it's", None]
    got = {x.doc_id: x.n_tokens for x in token_counts.counts(docs(list(enumerate(texts))), WORDS).collect()}
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(WORDS)
    assert got == {i: len(t.encode(x or "", add_special_tokens=False).ids) for i, x in enumerate(texts)}


# ---- 4 ----

@pytest.mark.parametrize("n, kinds", [(0, 4), (1, 1), (5, 5), (4096, 9), (4097, 2), (20_000, 3000), (9_000, 1)])
def test_coder_round_trip(n, kinds):
    r = np.random.default_rng(n)
    ids = (r.zipf(1.3, n) % kinds * 77_777).astype(np.uint32)
    known, blocks, crcs = idcoder.encode(ids)
    assert (idcoder.decode(known, blocks, n, crcs) == ids).all()


def test_coder_packs_and_checks():
    r = np.random.default_rng(0)
    ids = np.tile(r.integers(0, 500, 1000), 20).astype(np.uint32)
    known, blocks, crcs = idcoder.encode(ids)
    assert sum(map(len, blocks)) < len(ids) * 2 * 0.5  # of 16-bit ids
    spoiled = [blocks[0][:40] + bytes([blocks[0][40] ^ 1]) + blocks[0][41:], *blocks[1:]]
    with pytest.raises(ValueError):
        idcoder.decode(known, spoiled, len(ids), crcs)
    with pytest.raises(ValueError):
        idcoder.encode(np.arange(70_000, dtype=np.uint32))


def _order0_bits(ids, block):
    """What an adaptive order-0 coder needs that is begun anew in each block and escapes to the dictionary for new ids."""
    kinds, bits = len(set(ids)), 0.0
    for i in range(0, len(ids), block):
        seen = collections.Counter()
        for n, x in enumerate(ids[i : i + block]):
            d = len(seen)
            bits -= math.log2(seen[x] / (n + d)) if seen[x] else (math.log2(d / (n + d)) if n else 0) - math.log2(kinds)
            seen[x] += 1
    return bits


def test_coder_beats_order_0_on_texts(corpus):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(WORDS)
    ids = np.array([i for x in corpus.text[:600] for i in [*t.encode(x or "", add_special_tokens=False).ids, 2]], np.uint32)
    _, blocks, _ = idcoder.encode(ids)
    assert 8 * sum(map(len, blocks)) < _order0_bits(ids.tolist(), idcoder.BLOCK)


def test_mixing_weights_follow_what_events_cost():
    r = np.random.default_rng(3)
    model, first = idcoder.Model(2), None
    for t in range(600):  # lane 0 repeats ten ids in turn, which contexts foresee; lane 1 has no order
        code = np.array([t % 10, r.integers(0, 900)])
        seen = model.look(2)
        event = np.where(seen[2] == code, 0, np.where(seen[3] == code, 1, 2))
        start, width, widths = model.share(seen, event)
        assert (width > 0).all() and (model.mixed(seen)[np.arange(2), event] == start).all()
        model.learn(seen, event, widths, code)
        first = model.w.copy() if t == 0 else first
    assert (model.w != first).any() and (model.w > 0).all() and (model.w.sum(0) <= 1 << 16).all()


@pytest.mark.parametrize("lanes", [1, 2, 3])
def test_lanes_of_a_long_group(monkeypatch, lanes):
    ids = (np.random.default_rng(lanes).zipf(1.4, 5 * 4096 + 7) % 900).astype(np.uint32)
    whole = idcoder.encode(ids)
    monkeypatch.setattr(idcoder, "LANES", lanes)
    known, blocks, crcs = idcoder.encode(ids)
    assert blocks == whole[1]
    assert (idcoder.decode(known, blocks, len(ids), crcs) == ids).all()


def test_files_hold_the_library_ids(spark, docs, corpus, tmp_path):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(WORDS)
    texts = corpus.text.tolist()[:40] + ["DON'T <|startoftext|>x<|endoftext|> Ünïcödé ſtraße Σας 12345 a\u00a0b\u2003c\x1cd '''s", "", None, "e\u0301 \u0301x"]
    rows = [(3 * i - 20, x) for i, x in enumerate(texts)]
    path = str(tmp_path / "ids")
    token_output.write(docs(rows, extra=True).repartition(5), path, WORDS, group=3000)
    got = sorted(tuple(r) for r in token_output.read(spark, path, with_ids=True).collect())
    start, want = 0, []
    for d, x in rows:
        ids = np.array([*t.encode(x or "", add_special_tokens=False).ids, 2], "<u4")
        want.append((d, start, len(ids), zlib.crc32(ids.tobytes()), bytearray(ids.tobytes())))
        start += len(ids)
    assert got == want


def test_plain_parts_go_to_the_model_alone(monkeypatch):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(WORDS)
    r = random.Random(4)
    pieces = ["".join(chr(r.choice([*range(33, 127)] * 9 + [1, 31, 127, 233, 0x3C2])) for _ in range(r.randrange(1, 12))) for _ in range(3000)]
    e, sent = token_output.Encoder(WORDS), []
    batch = e._batch
    monkeypatch.setattr(e, "_batch", lambda x: sent.extend(x) or batch(x))
    for p in pieces:
        assert np.frombuffer(e.encode(p.encode()), "<u4").tolist() == t.encode(p, add_special_tokens=False).ids
    assert e.direct and not any(x.isascii() and x.decode().isprintable() and b"<|" not in x for x in sent)


def test_files_of_odd_rows(docs):
    got = token_output.roundtrip(docs(ODD), WORDS).collect()
    assert len(got) == len(ODD) and sorted(r.start for r in got)[0] == 0
    assert sum(r.n_tokens for r in got) == max(r.start + r.n_tokens for r in got)
    assert token_output.roundtrip(docs(ODD).limit(0), WORDS).count() == 0


# ---- 5 ----

def _fingerprint(t):
    w = split(low(t))
    if not w:
        return 0
    s = [" ".join(w[i : i + 3]) for i in range(max(1, len(w) - 2))]
    h = [xxhash.xxh64(x.encode(), seed=42).intdigest() for x in s]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def _groups(fps):
    par = list(range(len(fps)))

    def find(x):
        while par[x] != x:
            par[x] = par[par[x]]
            x = par[x]
        return x

    for i in range(len(fps)):
        for j in range(i):
            if (fps[i] ^ fps[j]).bit_count() <= 2:
                par[max(find(i), find(j))] = min(find(i), find(j))
    return [find(i) for i in range(len(fps))]


def test_fingerprints(corpus):
    for t in [*corpus.text[:40], "", "a", "A b", "É A b c"]:
        assert simhash.fingerprint(t.encode()) == _fingerprint(t)


@pytest.mark.parametrize("hot", [2, 8, 64])
def test_components_of_near_fingerprints(spark, hot):
    r = random.Random(hot)
    base = [r.getrandbits(64) for _ in range(30)]
    fps = {b for b in base} | {0, (1 << 64) - 1, 1 << 63, 3 << 62}
    for b in base[:6]:  # dense balls, and chains that leave them
        for _ in range(60):
            x = b
            for _ in range(r.randrange(1, 5)):
                x ^= 1 << r.randrange(64)
            fps.add(x)
    fps = sorted(fps)
    df = spark.createDataFrame([(x - (1 << 64) if x >> 63 else x,) for x in fps], "fp long")
    from trailgraph.operators.components import wcc

    lab = {r_.node % (1 << 64): r_.component % (1 << 64) for r_ in wcc(simhash.links(df, hot=hot)).collect()}
    want = _groups(fps)
    parts = collections.defaultdict(set)
    for x, c in zip(fps, want):
        parts[c].add(x)
    got = collections.defaultdict(set)
    for x in fps:
        got[lab.get(x, x)].add(x)
    assert sorted(map(sorted, got.values())) == sorted(map(sorted, parts.values()))


def test_threshold_plans_keep_the_pigeonhole():
    for m in range(1, 4):
        for groups in [simhash.partitions(100, np.eye(64) * 50 + 25, m)]:
            assert sorted(b for g in groups for b in g) == list(range(64))
    cost = [{-1: 0.0, 0: 5.0, 1: 50.0}, {-1: 0.0, 0: 1.0, 1: 2.0}]
    assert simhash.allocate(cost, 1) == (7.0, [0, 1])
    assert simhash.allocate(cost, 0) == (2.0, [-1, 1])


def test_plan_goes_by_counted_pairs(spark):
    r = random.Random(1)
    fps = sorted({r.getrandbits(60) << 4 | r.getrandbits(2) for _ in range(400)} | {(5 << 43) | r.getrandbits(20) for _ in range(100)})
    df = spark.createDataFrame([(x - (1 << 64) if x >> 63 else x,) for x in fps], "fp long")
    groups = [[0, 1, 2, 3], list(range(40, 64)), list(range(64))]
    want = [sum((a ^ b) & sum(1 << x for x in g) == 0 for i, a in enumerate(fps) for b in fps[:i]) for g in groups]
    assert simhash.agreeing_pairs(df, groups) == want and want[1] >= 4950
    n, both = simhash.bit_statistics(df)
    asked = []

    def hot_first(groups):
        asked.extend(groups)
        return [1e12 if 0 in g else 0.0 for g in groups]

    plan = simhash.plan(n, both, hot_first)
    assert len(asked) == 5  # divisions in two and in three
    assert not any(0 in bits for bits, _ in plan)  # the partition that all agree on is left out
    m = 2 if max(len(b) for b, _ in plan) > 22 else 3
    assert sum(t + 1 for _, t in plan) == 3 and m in (2, 3)


def test_simhash_odd_rows(docs):
    d = docs(ODD, extra=True)
    got = {(r.doc_id, r.fp % (1 << 64)): r.component_id for r in simhash.components(d).collect()}
    assert got[1, 0] == got[2, 0] == got[3, 0] == 1
    assert simhash.components(d.limit(0)).count() == 0
    kept = simhash.deduplicated(docs(ODD, extra=True))
    assert kept.columns == d.columns
    assert sorted((r.doc_id for r in kept.collect()), key=str) == [1, 4, 6, 8, 9, None]


def test_survivors_by_row(docs):
    texts = ["one text about the sea and its many ships", "another of mountains snow and early winter mornings", "a third on bread salt and ovens of clay"]
    rows = [(None, t) for t in texts] + [(None, texts[0]), (5, texts[1]), (7, "quite other words stand under number seven here"), (7, "and again some different ones with the same number")]
    kept = simhash.deduplicated(docs(rows, extra=True))
    assert sorted(((r.doc_id, r.text) for r in kept.collect()), key=str) == sorted([(None, texts[0]), (5, texts[1]), (None, texts[2]), *rows[-2:]], key=str)


def _five(t):
    w = split(low(t))
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def _alike(texts):
    """The least place reachable over pairs at Jaccard 0.8 of five-word shingles."""
    sets = [_five(t) for t in texts]
    par = list(range(len(texts)))
    for i in range(len(texts)):
        for j in range(i):
            if 5 * len(sets[i] & sets[j]) >= 4 * len(sets[i] | sets[j]):
                a, b = par[i], par[j]
                par = [min(a, b) if x in (a, b) else x for x in par]
    return par


@pytest.mark.parametrize("block", [2, 64])
def test_near_texts_at_four_fifths(docs, block):
    r = random.Random(block)
    words = lambda n: [f"w{r.randrange(10**6)}" for _ in range(n)]
    passage, template, rows = words(60), words(150), []
    for _ in range(8):  # a text and its edits, in chains, and texts of other words around one passage
        base = words(r.choice([40, 100, 200]))
        for _ in range(6):
            rows.append(" ".join(base))
            base = list(base)
            for _ in range(r.choice([1, 1, 2, 4])):
                base[r.randrange(len(base))] = "EDIT"
        rows.append(" ".join(words(r.choice([8, 20, 90])) + passage))
    for _ in range(40):  # copies of one text, each with edits of its own, some near no other
        base = list(template)
        for _ in range(r.choice([1, 3, 5, 7, 9])):
            base[r.randrange(len(base))] = words(1)[0]
        rows.append(" ".join(base))
    rows += ["a b", "A  b", "a c", "", None]
    par = _alike(rows)
    d = docs(rows).selectExpr("doc_id", "xxhash64(text) AS k1", "xxhash64(1, text) AS k2", "text")
    got = collections.defaultdict(set)
    for x in near_text.labelled(d, block=block).collect():
        got[x.c].add(x.doc_id)
    want = collections.defaultdict(set)
    for i, x in enumerate(par):
        want[x].add(i)
    assert sorted(map(sorted, got.values())) == sorted(map(sorted, want.values()))
    if block == 64:
        assert {x.doc_id for x in simhash.deduplicated(docs(rows)).collect()} == set(want)


def test_near_text_rules_out_before_it_moves_texts(spark, docs):
    r = random.Random(9)
    words = lambda n: [f"w{r.randrange(10**6)}" for _ in range(n)]
    near = words(2600)
    texts = [near, near[:-40] + words(40), *(words(2600) for _ in range(4)), words(1900)]  # all but the last fit in size, two are near
    sets = [np.array(sorted(hash(s) & ((1 << 63) - 1) for s in _five(" ".join(t))), np.uint64) for t in texts]
    rows = [(i, len(h), near_text._sketches(h, np.zeros(len(h), np.int64), 1)[0], near_text._wide(h)) for i, h in enumerate(sets)]
    nodes = spark.createDataFrame(rows, "node long, n int, sketch binary, wide binary")
    pairs = spark.createDataFrame([(a, b) for b in range(len(texts)) for a in range(b)], "a long, b long")
    assert {tuple(x) for x in near_text._possible(pairs, nodes, near_text.LEAST).collect()} == {(0, 1)}
    for a in range(len(sets)):
        for b in range(a):
            x, y = sets[a], sets[b]
            assert near_text._apart(near_text._wide(x), near_text._wide(y)) <= len(x) + len(y) - 2 * len(np.intersect1d(x, y))
    fill = lambda i: [*range(1000 * i, 1000 * i + 40)]
    made = [(0, 100, [5, 6]), (1, 110, [5, 7]), (2, 300, [6, *fill(2), 8]), (3, 310, [7, *fill(3), 8])]  # 5: sizes fit; 6 and 7: they don't; 8: in no smaller set's prefix
    spread = lambda k: (k * 0x9E3779B97F4A7C15 + (1 << 63)) % (1 << 64) - (1 << 63)
    few = spark.createDataFrame([(i, n, [spread(k) for k in ks]) for i, n, ks in made] * 2, "node long, n int, prefix array<bigint>")
    got = sorted((x.key, x.node) for x in near_text._shared(few, near_text.LEAST).collect())
    assert got == sorted((spread(5), i) for i in (0, 1))


def test_dedup_links_by_fingerprints_first(docs, monkeypatch):
    r = random.Random(5)
    base = [f"w{r.randrange(10**6)}" for _ in range(400)]
    rows = [" ".join(base), " ".join([*base[:-1], "end"]), " ".join(f"v{i}" for i in range(300)), "A b  c", "a b c", None, ""]
    seen, plain = [], simhash.near_pairs

    def recorded(rows, nodes):
        pairs = plain(rows, nodes)
        seen.extend(map(tuple, pairs.collect()))
        return pairs

    monkeypatch.setattr(simhash, "near_pairs", recorded)
    assert {x.doc_id for x in simhash.deduplicated(docs(rows)).collect()} == {0, 2, 3, 5}
    assert len(seen) == (bin(simhash.fingerprint(rows[0].encode()) ^ simhash.fingerprint(rows[1].encode())).count("1") <= 2) == 1


# ---- 6 ----

def test_rules_and_aliases(spark):
    link = lambda u: f'<html><head><link data-x="1" REL=canonical href="{u}"></head>'
    rows = [
        (1, "http://Shop.Example.COM/de/1?x#y", None), (2, "https://b.example.net/p", link("http://shop.example.com/de/1?x")), (3, "https://c.example.net/q", '<meta http-equiv="refresh" content="0; URL=https://b.example.net/p">'),
        (4, "http://a.org/ok", link("/x")), (5, "http://free.net/1", link("http://a.org/ok")), (6, "http://free.net/2", link("http://free.net/1")), (7, "http://free.net/3", link("http://x.com/de/")), (8, "http://free.net/2", link("http://x.com/de/")),
        (9, None, None), (10, "no scheme/com/de/", ""), (11, "http://example.org", ""), (12, "http://example.org/en/12", ""), (12, "http://example.org/en/12", ""), (13, "http://notexample.org.evil/es/", ""), (14, "http://lone.net/?a=://b", link("")), (None, "x://com/fr/", ""),
    ]
    d = spark.createDataFrame(rows, "page_id long, url string, html string").selectExpr("*", "'x' AS host", "'y' AS node", "1 AS m")
    got = {r.page_id: tuple(r)[1:5] for r in url_filter.judge(d).collect()}
    assert got[1] == ("shop.example.com", "/de/1", "com/de/", "block")
    assert got[2][2:] == (None, "block") and got[3][2:] == (None, "block")
    assert got[4][2:] == ("org/", "allow") and got[5][3] == "allow"
    assert got[6][3] == "allow" and got[7][3] == "allow" and got[8][3] == "allow"  # an allow in the component goes before its block
    assert got[9] == ("", "", None, "allow") and got[10] == ("", "", None, "allow")
    assert got[11] == ("example.org", "", None, "allow") and got[12][2:] == ("example.org/en/1", "block")
    assert got[13][2:] == (None, "allow") and got[None] == ("com", "/fr/", "com/fr/", "allow")
    assert url_filter.judge(d).count() == len(rows) and url_filter.judge(d.limit(0)).count() == 0
    assert url_filter.allowed(d).columns == d.columns
    twice = spark.createDataFrame([(1, "http://a.com/de/1", None), (1, "http://a.net/", None), (1, "http://a.net/", None)], "page_id long, url string, html string")
    assert [r.url for r in url_filter.allowed(twice).collect()] == ["http://a.net/"] * 2


def test_many_rules_are_a_table(spark):
    """Rules that an expression can't hold give the same verdicts by a join."""
    rules = [("block" if i % 2 else "allow", f"h{i}.com", f"/{'x' * (i % 3)}") for i in range(5000)] + list(url_filter.RULES)
    r = random.Random(3)
    urls = [f"http://{r.choice(['', 'a.', 'b.c.'])}h{r.randrange(5200)}.com/{'x' * r.randrange(4)}" for _ in range(200)] + [None, "x", "http://", "http://com/fr/"]
    d = spark.createDataFrame([(i, u, None) for i, u in enumerate(urls)], "page_id long, url string, html string")
    got = {r.page_id: r.rule for r in url_filter.judge(d, rules).collect()}
    for i, u in enumerate(urls):
        host, _, path = (u or "").partition("://")[2].partition("/")
        fits = [h + p for _, h, p in rules if (host == h or host.endswith("." + h)) and f"/{path}".startswith(p)] if host else []
        assert got[i] == max(fits, key=len, default=None), u


def test_hot_canonical_target(spark):
    rows = [(i, f"http://h.net/{i}", '<link rel="canonical" href="http://x.com/de/">') for i in range(400)]
    d = spark.createDataFrame(rows, "page_id long, url string, html string")
    assert url_filter.judge(d).where("verdict = 'block'").count() == 400


# ---- 7 ----

def _contaminated(rows, items, size=13):
    tok = re.compile("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+")
    pats = collections.defaultdict(set)
    for i, t in items:
        w = tok.findall(low(t))
        for k in range(max(1, len(w) - size + 1)) if w else ():
            pats[tuple(w[k : k + size])].add(i)
    out = []
    for d, t in rows:
        w, hit, names = tok.findall(low(t)), set(), set()
        for m in {len(p) for p in pats}:
            for k in range(len(w) - m + 1):
                if (g := tuple(w[k : k + m])) in pats:
                    hit.update(range(k, k + m))
                    names |= pats[g]
        names = sorted(str(x) for x in names if x is not None)
        out.append((d, len(w), len(hit), len(names), hashlib.sha256(",".join(names).encode()).hexdigest(), len(hit) > 0 and 20 * len(hit) >= len(w)))
    return sorted(out, key=str)


@pytest.mark.parametrize("block", [32 << 20, 40])
def test_decontamination(spark, docs, block):
    r = random.Random(5)
    vocab = ["a", "b", "c", "Dé", "e1", "中"]
    text = lambda n: "".join(r.choice(vocab) + r.choice([" ", ", ", "\n", "-"]) for _ in range(n))
    items = [(i, text(r.choice([1, 2, 3, 13, 14, 20]))) for i in (1, 2, 10, 11, 12, 30)] + [(99, None), (98, " ., "), (12, "b b b b")]
    rows = [(i, text(r.randrange(60))) for i in range(60)] + [(100 + i, text(20) + (items[i % 9][1] or "") + text(5)) for i in range(20)] + [r_[:2] for r_ in ODD]
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = by_id(decontamination.judge(docs(rows, extra=True), bench, block_bytes=block), "doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated")
    assert got == _contaminated(rows, items)
    none = decontamination.judge(docs(rows), bench.limit(0), block_bytes=block)
    assert none.where("contaminated or n_hit > 0").count() == 0 and none.count() == len(rows)


def test_searcher_is_small():
    r = random.Random(1)
    vocab = ["".join(r.choices("abcdefghijklmnopqrstuvwxyz", k=r.randrange(3, 9))) for _ in range(5000)]
    items = [(str(i), " ".join(r.choices(vocab, k=300)).encode()) for i in range(300)]
    assert len(pickle.dumps(decontamination.Searcher(items))) < 10 * sum(len(t) for _, t in items)


def test_clean_keeps_columns(spark, docs):
    d = docs(ODD, extra=True)
    bench = spark.createDataFrame([(1, "a b c d e f g h i j")], "item_id long, text string")
    kept = decontamination.clean(d, bench)
    assert kept.columns == d.columns and sorted((r.doc_id for r in kept.collect()), key=str) == [1, 2, 3, 4, 4, 8, 9, None]


# ---- 8 ----

def _base(t):
    w, lines, seen, dup = split(t), (t or "").split("\n"), set(), 0
    for x in lines:
        if split(x):
            dup += x in seen
            seen.add(x)
    grams = collections.defaultdict(list)
    for i in range(len(w) - 4):
        grams[tuple(w[i : i + 5])].append(i)
    rep = {j for v in grams.values() if len(v) > 1 for i in v for j in range(i, i + 5)}
    return (len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t or ""), dup, len(rep), len(w) < 10 or 100 * len(rep) > 20 * len(w))


def test_base_counts(docs, corpus):
    r = random.Random(2)
    odd = [" ".join(r.choice("abc") for _ in range(r.randrange(40))) + r.choice(["", "\n", "\n x\n x"]) for _ in range(150)]
    texts = [*corpus.text, *odd, *(x[1] for x in ODD)]
    got = {x.doc_id: x for x in quality.with_verdict(docs(list(enumerate(texts)), extra=True), name="q").select("doc_id", "q.*").collect()}
    for i, t in enumerate(texts):
        x = got[i]
        assert (x.n_words, x.word_chars, x.n_symbols, x.n_dup_lines, x.n_repeat_words, x.base_failed) == _base(t), t
        assert not (x.base_failed and x.kept)


def _js(p, q):
    p, q = np.array(p, float) / sum(p), np.array(q, float) / sum(q)
    m = (p + q) / 2
    kl = lambda a: sum(x * np.log2(x / y) for x, y in zip(a, m) if x > 0)
    return float(np.sqrt(max(0, (kl(p) + kl(q)) / 2)))


def test_class_distances(docs, corpus):
    d = corpus[corpus.lang == "en"]
    classes = ["[A-Z]", "[0-9]", "[\x20\x09-\x0d]", r"[.,;:!?'\"()\-]", r"[#*$%&|<>]", "[^\x00-\x7f]"]
    count = lambda t: (lambda c: [*c, len(t) - sum(c)])([len(re.findall(p, t)) for p in classes])
    ref = np.sum([count(t) for t in d.text], axis=0)
    tops = collections.Counter(w for t in d.text for w in split(t))
    got = {x.doc_id: x for x in quality.with_verdict(docs([(int(i), t, "en", "s") for i, t in zip(d.doc_id, d.text)]), name="q").select("doc_id", "q.*").collect()}
    cut = tops.most_common(17)
    tie = cut[15][1] == cut[16][1]
    common = [w for w, _ in cut[:16]]
    all_other = sum(tops.values()) - sum(tops[w] for w in common)
    for i, t in zip(d.doc_id, d.text):
        want = _js(count(t), ref) if len(t) >= 200 else 0.0
        assert abs(got[i].class_distance - want) < 1e-9
        w = split(t)
        if not tie:
            seen = collections.Counter(w)
            mine = [seen[x] for x in common]
            want = _js([*mine, len(w) - sum(mine)], [*(tops[x] for x in common), all_other]) if len(w) >= 50 else 0.0
            assert abs(got[i].word_distance - want) < 1e-9


def test_divergence_catches_junk_and_keeps_text(docs):
    r = random.Random(4)
    vocab = ["the", "of", "and", "to", *(f"word{chr(97 + i % 26)}{chr(97 + i // 26)}" for i in range(60))]
    good = [" ".join(r.choices(vocab, weights=[60, 40, 30, 20] + [3] * 60, k=200)) + "." for _ in range(80)]
    junk = "".join(r.choice("0123456789#%&|<>$*") + r.choice(["", " "]) for _ in range(900))
    got = {x.doc_id: x.kept for x in quality.with_verdict(docs([*good, junk, "short but clean text is left alone because it says too little"]), name="q").select("doc_id", "q.kept").collect()}
    assert all(got[i] for i in range(80)) and not got[80] and got[81]


def test_every_language_has_a_reference(docs):
    """More languages than any fixed number are each held against themselves, by broadcast or by merge."""
    d = docs([(i, f"word{i} " * 60 + "tail", f"l{i % 1100}", "s") for i in range(2200)])
    refs = {r.lang: r for r in quality.references(d).collect()}
    assert len(refs) == 1101 and all(r.common for lang, r in refs.items() if lang)
    few = by_id(quality.with_verdict(d, name="q").select("doc_id", "q.*"), "doc_id", "class_distance", "word_distance", "kept")
    before, quality.BROADCAST_LANGUAGES = quality.BROADCAST_LANGUAGES, 10
    try:
        assert by_id(quality.with_verdict(d, name="q").select("doc_id", "q.*"), "doc_id", "class_distance", "word_distance", "kept") == few
    finally:
        quality.BROADCAST_LANGUAGES = before


def test_quality_odd_rows(docs):
    d = docs([*ODD, (20, "null language here " * 30, None, None)], extra=True)
    assert quality.kept_documents(d).columns == d.columns
    assert quality.with_verdict(d, name="q").count() == len(ODD) + 1
    assert quality.kept_documents(d.limit(0)).count() == 0


# ---- 9 ----

def _targets(sizes, share=1.5, most=2.0, weights=(5, 2, 1)):
    names = sorted((s for s in sizes if s is not None), key=lambda s: [ord(c) for c in s]) + [s for s in sizes if s is None]
    w = {s: weights[i % 3] for i, s in enumerate(names)}
    total, full = share * sum(sizes.values()), {}
    while True:
        free = [s for s in names if s not in full]
        left = total - sum(full.values())
        t = {s: left * w[s] / sum(w[x] for x in free) for s in free}
        over = [s for s in free if t[s] > most * sizes[s] + 1e-9]
        if not over:
            return {**full, **t}
        full |= {s: most * sizes[s] for s in over}


@pytest.mark.parametrize("seed", range(4))
def test_mixing_meets_its_targets(spark, docs, seed):
    r = random.Random(seed)
    rows = [(i, "w " * r.choice([0, 1, 2, 5, 30]), "en", r.choice(["a", "b", "Z", "ä", None, "c"][: 3 + seed])) for i in range(400)] + [(1000 + i, "w " * 9, "en", "hot") for i in range(300)]
    rows += [(5000, None, "en", "empty"), (5001, "", "en", "empty")]
    out = mixing.mix(docs(rows, extra=True).drop("taken", "size")).collect()
    sizes = collections.Counter()
    for r_ in rows:
        sizes[r_[3]] += len(split(r_[1]))
    want, got = _targets(dict(sizes)), collections.Counter()
    source = {r_[0]: r_[3] for r_ in rows}
    for x in out:
        s = source[x.doc_id]
        got[s] += x.taken
        assert x.taken <= 2 * x.size and x.source_size == sizes[s] and abs(x.target - want[s]) < 1e-6
    for s, t in want.items():
        assert t - 1 <= got[s] <= t + 1e-6
    assert sorted(map(tuple, out)) == sorted(map(tuple, mixing.mix(docs(rows).repartition(7)).collect()))


def test_mixed_rows(docs):
    d = docs([(i, "w " * 10, "en", "ab"[i % 2]) for i in range(200)], extra=True)
    m = mixing.mixed_rows(d)
    assert m.columns == d.columns
    n = {r.source: r["count"] for r in m.groupBy("source").count().collect()}
    assert n == {"a": 200, "b": 100} or abs(n["a"] - 200) + abs(n["b"] - 100) <= 2
    one = docs([(1, "w " * 10), (1, "")])  # one id, two texts: nothing is taken of the empty one
    assert {r.text for r in mixing.mixed_rows(one).collect()} == {"w " * 10}
    same = mixing.mixed_rows(docs([(1, "w " * 10, "en", "a")] * 6 + [(2, "v " * 10, "en", "b")] * 6))
    assert sorted(r["count"] for r in same.groupBy("doc_id").count().collect()) in ([6, 12], [5, 12], [6, 11])
    assert mixing.mixed_rows(docs(ODD)).count() > 0 and mixing.mix(docs(ODD).limit(0)).count() == 0
    assert mixing.mix(docs(ODD, extra=True)).count() == len(ODD)


# ---- 10 ----

def _one_apart(a, b):
    """By words from five words on, by characters below, from five characters on; plain dynamic programming."""
    if max(len(a), len(b)) < 5:
        a, b = (b" ".join(x).decode() for x in (a, b))
    if min(len(a), len(b)) < 5 or abs(len(a) - len(b)) > 1:
        return False
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        last, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
    return row[-1] <= 1


def _lines(rows):
    first, occ = {}, []
    order = lambda d: -(1 << 63) if d is None else d
    for d, t in rows:
        for j, x in enumerate((t or "").split("\n")):
            if w := tuple(x.encode().split()):
                occ.append((d, t, j, w))
                first[w] = min(first.get(w, (order(d), j)), (order(d), j))
    best = dict(first)
    for a in first:
        for b in first:
            if a != b and _one_apart(a, b):
                best[a] = min(best[a], first[b])
    gone = collections.defaultdict(set)
    for d, t, j, w in occ:
        if best[w] < (order(d), j):
            gone[d, t].add(j)
    out = []
    for d, t in rows:
        ls = (t or "").split("\n")
        kept = "\n".join(x for j, x in enumerate(ls) if j not in gone[d, t])
        out.append((d, sum(1 for x in ls if x.encode().split()), len(gone[d, t]), hashlib.sha256(kept.encode()).hexdigest()))
    return sorted(out, key=str)


@pytest.mark.parametrize("seed", range(3))
def test_near_lines(docs, seed):
    r = random.Random(seed)
    base = [[r.choice("abcdefgh") for _ in range(r.choice([1, 4, 5, 6, 9, 15]))] for _ in range(25)]

    def line():
        w = list(r.choice(base))
        for _ in range(r.choice([0, 0, 1, 1, 2])):
            i = r.randrange(len(w) + 1)
            w = r.choice([w[:i] + w[i + 1 :], [*w[:i], "x", *w[i:]], [*w[:i], "y", *w[i + 1 :]]])
        return "  ".join(w)

    rows = [(d, "\n".join(line() for _ in range(r.randrange(8)))) for d in r.sample(range(500), 60)]
    rows += [(1000 + i, f"Page {i} of the same old report\nbody {i}") for i in range(60)]
    got = by_id(line_dedup.deduplicate(docs(rows)), "doc_id", "n_lines", "n_removed", "kept_sha256")
    assert got == _lines(rows)


def test_typos_in_short_lines(docs):
    r = random.Random(8)
    base = ["Read more", "Über uns", "naïve", "abcde", "abcd", "Contact  us now", "See also this one", "a b c", "x" * 70]

    def typo(x):
        for _ in range(r.choice([0, 1, 1, 2])):
            i = r.randrange(len(x) + 1)
            x = r.choice([x[:i] + x[i + 1 :], x[:i] + "é" + x[i:], x[:i] + "q" + x[i + 1 :], x[:i] + " " + x[i:]])
        return x

    rows = [(d, "\n".join(typo(r.choice(base)) for _ in range(r.randrange(6)))) for d in r.sample(range(500), 50)]
    rows += [(900, "Home page"), (901, "Home pages\nhomepage"), (902, "Home  pagE\nabcd"), (903, "abce\none two three four five"), (904, "one two three four")]
    got = by_id(line_dedup.deduplicate(docs(rows)), "doc_id", "n_lines", "n_removed", "kept_sha256")
    assert got == _lines(rows)


def test_all_partners_are_tried_where_the_first_fails(docs):
    """As if the earliest partner's hash had collided: it fails the check, and a later one counts."""
    right = line_dedup._near
    rows = line_dedup._rows(docs([(1, "BAD a b c d e"), (2, "NEAR a b c d e"), (3, "then a b c d e"), (4, "quite another line than these")]), "doc_id", "text")
    assert sorted(r.doc_id for r in line_dedup.removed_lines(rows).collect()) == [2, 3]
    refuse = lambda a, b: b"BAD" not in (*a, *b) and right(a, b)
    assert [r.doc_id for r in line_dedup.removed_lines(rows, refuse).collect()] == [3]


def test_near_lines_odd_rows(docs):
    d = docs(ODD, extra=True)
    assert by_id(line_dedup.deduplicate(d), "doc_id", "n_lines", "n_removed", "kept_sha256") == _lines([r[:2] for r in ODD])
    assert line_dedup.deduplicate(d.limit(0)).count() == 0
    kept = {r.doc_id: r.kept_text for r in line_dedup.deduplicate(docs(["a b c d e\nq", "a b X d e\nr"]), with_text=True).collect()}
    assert kept == {0: "a b c d e\nq", 1: "r"}


def test_line_dedup_takes_text_in_small_pieces():
    class Rows:
        def mapInArrow(self, run, _):
            return run

    texts = ["".join(f"ab{k}-{i}\n" for i in range(400)) for k in range(1500)]
    batch = pa.RecordBatch.from_arrays([pa.array(range(1500), pa.int64()), pa.array(range(1500), pa.int64()), pa.array(texts)], names=["doc_id", "rk", "text"])
    seen = []
    list(line_dedup._scan(Rows(), lambda x, ids, rk, c: seen.append((len(c.data), len(x.at))), "")([batch]))
    assert sum(n for n, _ in seen) == sum(map(len, texts)) and sum(n for _, n in seen) == 400 * 1500
    assert max(n for n, _ in seen) <= 1 << 19
