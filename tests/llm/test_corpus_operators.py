"""Corpus operators against brute force on small fixtures with awkward rows."""

import collections
import hashlib
import math
import random
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest
import xxhash

from consensus_spark.llm import (
    blocks,
    lines,
    mixture,
    neighbours,
    ngram_trie,
    packing,
    rules,
    sharding,
    simhash,
    substrings,
    textbytes,
    token_counts,
)

WORD = re.compile(r"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, _n long, _id string, block string"


def fixture_rows():
    rng = random.Random(4)
    vocab = ["the", "of", "and", "Über", "été", "x9", "don't", "a", "tion", "ing's", "12", "…"]
    word = lambda: rng.choice(vocab) + rng.choice(["", "", "s", "q" * rng.randint(0, 3)])
    base = " ".join(word() for _ in range(90)) + "\nLicensed under the plain terms of use.\n" + " ".join(word() for _ in range(40))
    rows = [(0, None), (1, ""), (2, " \n\t "), (3, base), (4, base), (5, base + " extra"), (6, "one"), (7, "two words"), (8, base.replace("the", "THE", 1))]
    for i in range(9, 60):
        text = " ".join(word() for _ in range(rng.randint(3, 220)))
        if i % 3 == 0:
            text += "\nLicensed under the plain terms of use."
        if i % 7 == 0:
            text = base[: 300 + i] + " " + text
        rows.append((i, text))
    rows += [(60, "\n".join(" ".join(word() for _ in range(60)) for _ in range(100))), (9, rows[9][1])]
    return [(i, t, "en", None if i % 11 == 0 else f"s{i % 4}", None if t is None else len(t), 1, "x", "y") for i, t in rows]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(fixture_rows(), SCHEMA).repartition(3).cache()


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def words(t):
    return WORD.findall(t or "")


def by_id(df):
    out = collections.defaultdict(list)
    for r in df.collect():
        out[r["doc_id"]].append(r)
    return out


def test_quality_rules(docs, empty):
    got = by_id(rules.judge(docs))
    for i, t, *_ in fixture_rows():
        w = words(t)
        g = got[i][0]
        wins = collections.Counter(tuple(w[j : j + 3]) for j in range(len(w) - 2))
        hit = {j + k for j in range(len(w) - 2) if wins[tuple(w[j : j + 3])] > 1 for k in range(3)}
        ls = [x for x in (t or "").split("\n") if words(x)]
        assert (g["n_words"], g["word_chars"]) == (len(w), sum(map(len, w)))
        assert g["n_symbols"] == sum(c in "#*$%&|<>" for c in t or "")
        assert g["n_dup_lines"] == len(ls) - len(set(ls))
        assert g["n_repeat_words"] == len(hit)
        assert g["base_failed"] == (len(w) < 50 or 100 * len(hit) > 50 * len(w))
        assert not (g["base_failed"] and g["kept"])
    assert rules.judge(empty).count() == 0
    kept = rules.apply_rules(docs)
    assert kept.columns == docs.columns


def test_shards(docs, empty):
    def jump(key, n):
        key &= (1 << 64) - 1
        b, j = -1, 0
        while j < n:
            b = j
            key = (key * 2862933555777941757 + 1) % (1 << 64)
            j = int((b + 1) * (float(1 << 31) / float((key >> 33) + 1)))
        return b

    slots = collections.defaultdict(list)
    for r in sharding.shard_documents(docs).collect():
        assert r["shard"] == jump(r["doc_id"], 16) and r["grown_shard"] == jump(r["doc_id"], 17)
        assert r["grown_shard"] in (r["shard"], 16)
        slots[r["shard"]].append(r["slot"])
    assert all(sorted(s) == list(range(len(s))) for s in slots.values())
    text = {i: t for i, t, *_ in fixture_rows()}
    for r in sharding.shard_documents(docs).collect():
        b = (text[r["doc_id"]] or "").encode()
        assert (r["size"], r["text_crc32"]) == (len(b) + 1, zlib.crc32(b))
    assert sharding.shard_documents(empty).count() == 0


def test_neighbours_recall_and_exact_scores(spark):
    rng = np.random.default_rng(3)
    x = rng.normal(size=(1500, 16))
    x[1000:1400] = x[5]
    rows = [(i, v.tolist()) for i, v in enumerate(x)] + [(9000, None), (9100, [0.0] * 16), (9200, [float("nan")] * 16), (9300, [1.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = collections.defaultdict(list)
    for r in neighbours.search(df, df["vec_id"] % 100 == 0, parts=8, sample=800).collect():
        got[r["query_id"]].append((r["rank"], r["vec_id"], r["score"]))
    hits = 0
    for q in range(0, 1500, 100):
        d = np.sqrt(((x - x[q]) ** 2).sum(axis=1))
        d[q] = np.inf
        true = np.lexsort((np.arange(1500), d))[:10]
        mine = sorted(got[q])
        assert [m[0] for m in mine] == list(range(1, 11))
        assert all(abs(s - d[v]) < 1e-12 for _, v, s in mine)
        hits += len(set(true) & {m[1] for m in mine})
    assert hits / 150 >= 0.9 and set(got) == set(range(0, 1500, 100))
    assert neighbours.search(df.filter("vec_id < 0"), df["vec_id"] % 100 == 0).count() == 0
    few = neighbours.search(df.filter("vec_id < 4"), df["vec_id"] % 2 == 0)
    assert few.count() == 6


def test_neighbours_in_many_cells(spark, monkeypatch):
    """All parts probed: equal to brute force, with ties, repeated ids and rows, in any blocks."""
    monkeypatch.setattr(neighbours, "CELL_ROWS", 20)
    monkeypatch.setattr(neighbours, "QUERY_ROWS", 5)
    monkeypatch.setattr(neighbours, "TILE", 60)
    rng = np.random.default_rng(8)
    x = rng.integers(0, 3, (400, 6)).astype(float) + 1
    rows = [(i % 390, v.tolist()) for i, v in enumerate(x)] + [(None, [1.0] * 6)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    monkeypatch.setattr(neighbours, "AIM", 2.0)
    monkeypatch.setattr(neighbours.learn, "__defaults__", (16, 10, 2.0))
    got = collections.defaultdict(list)
    for r in neighbours.search(df, df["vec_id"] % 10 == 0, sample=300).collect():
        got[r["query_id"]].append((r["rank"], r["vec_id"], r["score"]))
    assert set(got) == set(range(0, 390, 10))
    for q, found in got.items():
        own = min(v for i, v in rows[:-1] if i == q)
        want = sorted((math.dist(own, v), i) for i, v in rows[:-1] if i != q)[:10]
        assert [(v, pytest.approx(s)) for _, v, s in sorted(found)] == [(i, s) for s, i in want]


def test_ngram_scores(docs, empty):
    got = by_id(ngram_trie.score_documents(docs))
    rows = fixture_rows()
    tok = [(i, words((t or "").translate({c: c + 32 for c in range(65, 91)})) + ["\n"]) for i, t, *_ in rows]
    trains = lambda i: zlib.crc32(str(i).encode()) % 10 != 0
    uni, bi, cv, kinds = (collections.Counter() for _ in range(4))
    for i, w in tok:
        if trains(i):
            uni.update(w)
            bi.update(zip([" ", *w[:-1]], w, strict=True))
    for (a, _), c in bi.items():
        cv[a] += c
        kinds[a] += 1
    n, v = sum(uni.values()), len(uni)
    d1 = ngram_trie.discount(sum(c == 1 for c in uni.values()), sum(c == 2 for c in uni.values()))
    for i, w in tok:
        g = got[i][0]
        assert (g["held_out"], g["n_tokens"], g["train_tokens"]) == (not trains(i), len(w), n)
        assert g["n_known"] == sum(x in uni for x in w)
        assert g["base_score"] == pytest.approx(sum(math.log10((uni[x] + 0.1) / (n + 0.1 * (v + 1))) for x in w))
        # one shard at this size, so one discount for all contexts
        d2 = ngram_trie.discount(sum(c == 1 for c in bi.values()), sum(c == 2 for c in bi.values()))
        s = 0.0
        for a, x in zip([" ", *w[:-1]], w, strict=True):
            p = (uni[x] - d1) / n if x in uni else d1 * v / n
            own = max(bi[a, x] - d2, 0) / cv[a] if cv[a] else 0.0
            s += math.log10(own + (d2 * kinds[a] / cv[a] if cv[a] else 1.0) * p)
        assert g["score"] == pytest.approx(s, abs=0.001 * len(w))
    assert ngram_trie.score_documents(empty).count() == 0


def test_ngram_scores_of_order_three_over_many_shards(docs):
    assert ngram_trie.QUERY_ORDER >= 3
    got = by_id(ngram_trie.score_documents(docs, 3, shard_keys=200))
    tok = [(i, words((t or "").translate({c: c + 32 for c in range(65, 91)})) + ["\n"]) for i, t, *_ in fixture_rows()]
    trains = lambda i: zlib.crc32(str(i).encode()) % 10 != 0
    count, cv, kinds = ([collections.Counter() for _ in range(4)] for _ in range(3))
    back = lambda w, j, k: tuple(w[j - b] if j >= b else " " for b in range(1, k))
    for i, w in tok:
        for j, x in enumerate(w if trains(i) else []):
            for k in (1, 2, 3):
                count[k][back(w, j, k), x] += 1
    for k in (2, 3):
        for (a, _), c in count[k].items():
            cv[k][a] += c
            kinds[k][a] += 1
    n, v = sum(count[1].values()), len(count[1])
    d = [0.5] + [ngram_trie.discount(*(sum(c == m for c in count[k].values()) for m in (1, 2))) for k in (1, 2, 3)]
    for i, w in tok:
        s = 0.0
        for j, x in enumerate(w):
            c = count[1][(), x]
            p = (c - d[1]) / n if c else d[1] * v / n
            for k in (2, 3):
                a = back(w, j, k)
                if cv[k][a]:
                    p = max(count[k][a, x] - d[k], 0) / cv[k][a] + d[k] * kinds[k][a] / cv[k][a] * p
            s += math.log10(p)
        assert got[i][0]["score"] == pytest.approx(s, abs=0.001 * len(w))


def test_scores_do_not_depend_on_the_layout(docs):
    ways = [{}, {"shard_keys": 1_000_000}, {"shard_keys": 150}, {"shard_keys": 150, "block_bytes": 3000}]
    got = [sorted((str(r["doc_id"]), r["n_tokens"], r["n_known"], round(r["score"], 9)) for r in ngram_trie.score_documents(docs, 3, **w).collect()) for w in ways]
    assert got[0] == got[1] == got[2] == got[3]


def test_trie_search_stays_between_pointers():
    context, of = np.array([1, 9], np.uint64), np.array([0, 0, 1, 1, 1])
    word = np.array([3, 8, 2, 3, 7], np.uint64)
    level = ngram_trie.TrieLevel.build(context[of], word, np.array([4, 1, 1, 2, 1]), 0.5)
    assert (level.look_up(context, of, word)[0] > 0).all()
    level.pointers = ngram_trie.EliasFano.encode(np.array([0, 1, 5]))
    prob, _ = level.look_up(context, of, word)
    assert (prob > 0).tolist() == [True, False, True, True, True]
    prob, back = level.look_up(np.array([0, 5, 12], np.uint64), np.array([0, 1, 2]), word[:3])
    assert not prob.any() and (back == ngram_trie.LEVELS).all()


def test_elias_fano_successor():
    rng = np.random.default_rng(0)
    for n in (0, 1, 7, 3000):
        for shift in (0, 22, 39):
            v = np.unique(rng.integers(0, 1 << 40, n).astype(np.uint64) >> np.uint64(shift)) + np.uint64(5)
            e = ngram_trie.EliasFano.encode(v)
            q = np.concatenate([v, v + np.uint64(1), rng.integers(0, 1 << 40, 500).astype(np.uint64)])
            at, hit = e.successor(q)
            assert (at == np.searchsorted(v, q)).all() and (hit == np.isin(q, v)).all()
            assert (e.at(np.arange(len(v))) == v).all()


@pytest.mark.parametrize("other", [0, 3, 30, 99])
def test_packed_values_come_back(other):
    rng = np.random.default_rng(other)
    for n in (0, 1, 64, 65, 511, 512, 5000):
        v = np.where(rng.integers(0, 100, n) < other, rng.integers(0, 1 << 63, n), 7).astype(np.uint64)
        assert (textbytes.unpack(textbytes.pack(v, False), False) == v).all()
        assert (textbytes.unpack(textbytes.pack(np.sort(v))) == np.sort(v)).all()


def test_ranks_of_keys_alike_in_their_leading_bits():
    rng = np.random.default_rng(3)
    for keys, width in ((rng.integers(0, 50, 999), 6), (rng.integers(0, 50, 999) + (1 << 62), 64), (rng.integers(0, 1 << 62, 99), 64)):
        want, rank = np.unique(keys.astype(np.uint64), return_inverse=True)
        for known in (width, None):
            got = blocks.ranked(keys.astype(np.uint64), known)
            assert (got[0] == want).all() and (got[1] == rank).all()


def test_mixture(docs, empty):
    rows = mixture.mix(docs, block_tokens=16).collect()
    assert len(rows) == len(fixture_rows())
    per = collections.defaultdict(int)
    for r in rows:
        assert 0 <= r["taken"] <= 2 * r["size"]
        per[r["source"]] += r["taken"]
    target = {r["source"]: r["target"] for r in rows}
    size = {r["source"]: r["source_size"] for r in rows}
    assert sum(target.values()) == pytest.approx(1.5 * sum(size.values()))
    assert all(abs(per[s] - target[s]) <= 1 and target[s] <= 2 * size[s] + 1e-9 for s in per)
    assert sorted(map(str, rows)) == sorted(map(str, mixture.mix(docs, block_tokens=16).collect()))
    used = mixture.apply_mix(docs, block_tokens=16)
    assert used.columns == docs.columns
    assert sum(len(words(r["text"])) for r in used.collect()) == sum(per.values())
    assert mixture.mix(empty).count() == 0


def _targets(sizes, weights=(3, 1, 2), share=1.5):
    """Shares dealt by weight again and again until no source stands above twice its size."""
    order = sorted(sizes, key=lambda s: (s is None, s or ""))
    weight = {s: weights[i % len(weights)] for i, s in enumerate(order)}
    total, fixed = share * sum(sizes.values()), {}
    while True:
        free = [s for s in order if s not in fixed]
        left = total - sum(fixed.values())
        got = {s: left * weight[s] / sum(weight[f] for f in free) for s in free}
        over = [s for s in free if got[s] > 2 * sizes[s]]
        if not over:
            return got | fixed
        fixed |= {s: 2 * sizes[s] for s in over}


@pytest.mark.parametrize("block", [4, 16, 128])
def test_mixture_against_brute_force(docs, block):
    from pyspark.sql import functions as F

    rows = [
        (r["doc_id"], r["source"], len(words(r["text"])), r["h"])
        for r in docs.select("*", F.size(rules.words_of(F.col("text"))).cast("long").alias("size"))
        .select("*", F.xxhash64(F.lit(mixture.SEED), "doc_id", "size").alias("h")).collect()
    ]
    sizes = collections.Counter()
    for _, s, n, _ in rows:
        sizes[s] += n
    target = _targets(sizes)
    order = sorted((s for s in sizes if sizes[s]), key=lambda s: (s is None, s or ""))
    blocks = {s: -(-sizes[s] // block) for s in order}
    goal = {s: int(target[s] + 1e-9) for s in order}
    slots = {s: goal[s] // sizes[s] * blocks[s] + -(-(goal[s] % sizes[s]) // block) for s in order}
    n = sum(slots.values())
    # slot k takes point k * step mod n; its source is the one whose stretch of points holds it
    owner = [s for s in order for _ in range(slots[s])]
    step, rank, used = mixture._golden_step(n), collections.Counter(), collections.defaultdict(collections.Counter)
    for k in range(n):
        s = owner[k * step % n]
        epoch, b = divmod(rank[s], blocks[s])
        room = goal[s] - epoch * sizes[s] - b * block
        used[s, b][min(block, sizes[s] - b * block, room)] += 1
        rank[s] += 1
    want = collections.Counter()
    for s in order:
        at = 0
        for i, _, size, _ in sorted((r for r in rows if r[1] == s and r[2]), key=lambda r: (r[3], r[0])):
            taken = 0
            for w in range(at, at + size):
                b, place = divmod(w, block)
                taken += sum(c for length, c in used[s, b].items() if place < length)
            want[i, s, size, taken] += 1
            at += size
    got = mixture.mix(docs, block_tokens=block).collect()
    assert all(r["target"] == pytest.approx(target[r["source"]]) and r["source_size"] == sizes[r["source"]] for r in got)
    assert collections.Counter((r["doc_id"], r["source"], r["size"], r["taken"]) for r in got if r["size"]) == want


def test_mixture_schedule_is_near_weights_in_every_prefix(docs):
    rows = mixture.sized(docs)
    slots = mixture.schedule(mixture.source_targets(rows), 4).collect()
    total = collections.Counter(r["src"]["name"] for r in slots)
    seen, n = collections.Counter(), len(slots)
    for k, r in enumerate(sorted(slots, key=lambda r: r["slot"]), 1):
        seen[r["src"]["name"]] += 1
        assert all(abs(seen[s] - k * total[s] / n) < 6 for s in total)


@pytest.mark.parametrize("whole, layout", [(True, {}), (False, {}), (False, {"shard_keys": 90, "block_bytes": 3000})])
def test_substrings(docs, empty, whole, layout):
    k, rows = 13, fixture_rows()
    first = {}
    for i, t, *_ in sorted(rows, key=lambda r: r[0]):
        w = words(t)
        for j in range(len(w) - k + 1):
            first.setdefault(tuple(w[j : j + k]), i)
    got = by_id(substrings.dedup_substrings(docs, whole=whole, **layout))
    for i, t, *_ in rows:
        w = words(t)
        keep = [True] * len(w)
        for j in range(len(w) - k + 1):
            if first[tuple(w[j : j + k])] < i:
                keep[j : j + k] = [False] * k
        kept = " ".join(x for x, y in zip(w, keep, strict=True) if y)
        g = got[i][0]
        assert (g["n_words"], g["n_removed"]) == (len(w), keep.count(False))
        assert g["kept_sha256"] == hashlib.sha256(kept.encode()).hexdigest()
        if whole:
            assert g["text"] == kept
            assert sum(s["to"] - s["from"] for s in g["removed"]) == g["n_removed"]
    assert substrings.dedup_substrings(empty).count() == 0


def test_packing(docs, empty):
    rows = packing.pack(docs, capacity=64).collect()
    bins = collections.defaultdict(list)
    path = token_counts.vocabulary_path()
    ids = token_counts.library_ids(path, [t or "" for _, t, *_ in fixture_rows()])
    want = collections.Counter()
    for (i, *_), v in zip(fixture_rows(), ids, strict=True):
        a = np.array([*v, 1], "<u4")
        for p, s in enumerate(range(0, len(a), 64)):
            want[i, p, s, len(a[s : s + 64]), zlib.crc32(a[s : s + 64].tobytes())] += 1
    assert want == collections.Counter((r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in rows)
    for r in rows:
        bins[r["sequence_id"]].append((r["offset"], r["length"]))
    for b in bins.values():
        at = 0
        for o, n in sorted(b):
            assert o == at
            at += n
        assert at <= 64
    assert len(bins) <= math.ceil(sum(r["length"] for r in rows) / 64) + 2
    assert packing.pack(empty).count() == 0


def test_fullest_is_optimal():
    rng = random.Random(1)
    for _ in range(200):
        have = {rng.randint(1, 30): rng.randint(1, 3) for _ in range(5)}
        room = rng.randint(0, 60)
        sums = {0}
        for k, n in have.items():
            sums = {s + k * c for s in sums for c in range(n + 1) if s + k * c <= room}
        got = packing.fullest(sorted(have.items(), reverse=True), room)
        assert sum(k * n for k, n in got) == max(sums)
        assert all(n <= have[k] for k, n in got)


def test_token_counts(docs, empty):
    got = by_id(token_counts.count_tokens(docs))
    path = token_counts.vocabulary_path()
    for i, t, *_ in fixture_rows():
        g = got[i][0]
        assert g["n_tokens"] == len(token_counts.library_ids(path, [t or ""])[0])
        assert g["n_bytes"] == len((t or "").encode())
    assert token_counts.count_tokens(empty).count() == 0


def _chunked_texts():
    rng = random.Random(3)
    alpha = "ab'strevmld SDT\n0123.,!-_éÉßÿÄ\t<|*x"
    texts = ["".join(rng.choice(alpha) for _ in range(rng.randint(0, 120))) for _ in range(300)] + ["", "a" * 5000, "it's"]
    return texts + [" ".join("".join(rng.choice("etaoinshr") for _ in range(rng.randint(1, 60))) for _ in range(40)) for _ in range(30)]


def test_token_counts_of_any_chunking():
    texts, path = _chunked_texts(), token_counts.vocabulary_path()
    tr = token_counts.transducer(path)
    want = [len(x) for x in token_counts.library_ids(path, texts)]
    data, off = textbytes.flat_bytes(pa.array(texts))
    for chunk in (1, 3, 64, 1 << 14):
        counts, unsafe = token_counts.count_bytes(tr, data, off, chunk)
        assert all(a == b for a, b, u in zip(counts, want, unsafe, strict=True) if not u)
        assert unsafe.sum() < 200
    cut, _ = token_counts.chunks(data, off, 3)
    assert len(cut) > 1000  # chunks end inside pre-tokens


def test_token_counts_need_the_scan(monkeypatch):
    """Without composition each chunk starts from nothing, and counts differ."""
    texts, path = _chunked_texts(), token_counts.vocabulary_path()
    want = [len(x) for x in token_counts.library_ids(path, texts)]
    data, off = textbytes.flat_bytes(pa.array(texts))
    monkeypatch.setattr(token_counts.Maps, "scan", lambda self: self)
    counts, unsafe = token_counts.count_bytes(token_counts.transducer(path), data, off, 64)
    assert any(a != b for a, b, u in zip(counts, want, unsafe, strict=True) if not u)


def test_chunk_maps_compose_in_any_order():
    path = token_counts.vocabulary_path()
    tr = token_counts.transducer(path)
    data, off = textbytes.flat_bytes(pa.array(["international misunderstandings notwithstanding " * 3 + "x" * 40]))
    maps, _ = token_counts.state_maps(tr, data, off, 5)
    left = maps
    while len(left.count) > 1:  # ((a b) c) d ...
        left = token_counts.Maps.joined(left.take([0]).compose(left.take([1])), left.take(range(2, len(left.count))))
    right = maps
    while len(right.count) > 1:  # a (b (c d)) ...
        n = len(right.count)
        right = token_counts.Maps.joined(right.take(range(n - 2)), right.take([n - 2]).compose(right.take([n - 1])))
    want = len(token_counts.library_ids(path, [data.tobytes().decode()])[0])
    assert left.count[0] == right.count[0] == maps.scan().count[-1] == want


def test_line_templates(docs, empty):
    got = lines.drop_lines(docs)
    assert got.columns == [*docs.columns, "_n_lines", "_n_dropped"] and got.count() == len(fixture_rows())
    kept = [r["text"] for r in got.collect() if r["text"] and "Licensed under" in r["text"]]
    had = [t for _, t, *_ in fixture_rows() if t and "Licensed under" in t]
    assert len(had) > 10 and len(set(kept)) < 4
    for i, rs in by_id(got).items():
        if i in (0, 1, 2, 6, 7):
            assert all(r["_n_dropped"] == 0 for r in rs)
    assert lines.drop_lines(empty).count() == 0


def _dropped(spark, texts):
    rows = [(i, t, "en", "s", len(t), 1, "x", "y") for i, t in enumerate(texts)]
    return {r["doc_id"]: (r["_n_dropped"], r["text"]) for r in lines.drop_lines(spark.createDataFrame(rows, SCHEMA)).collect()}


@pytest.mark.parametrize("n", [900, 2300])
def test_line_templates_of_large_leaves(spark, n):
    name = lambda i: "".join(chr(97 + int(c)) for c in str(i))
    texts = [
        f"Posted by user {name(i)} in forum general\nThe thread was closed by the moderator named {name(i)} for good today"
        for i in range(n)
    ]
    got = _dropped(spark, texts)
    assert [got[i][0] for i in range(n)] == [0, *[2] * (n - 1)]


@pytest.mark.parametrize("odd", [0, 1])
def test_line_templates_compare_all_places(spark, odd):
    rng = random.Random(7)
    word = lambda: "".join(rng.choice("abcdefghij") for _ in range(8))
    # half of the places agree: every other one, after a common start
    texts = [" ".join("label" + "abcdefghijklmnopqrstuvwxyzABCDEF"[k] if k < 3 or k % 2 == odd else word() for k in range(32)) for _ in range(5)]
    near = [" ".join(["one common long line"] + ["w" + chr(97 + k % 26) for k in range(27)] + [word()]) for _ in range(5)]
    assert all(n == 0 for n, _ in _dropped(spark, texts).values())
    assert [n for _, (n, _) in sorted(_dropped(spark, near).items())] == [0, 1, 1, 1, 1]


def test_line_templates_of_two_texts_and_short_lines(spark):
    passage = " ".join("word" + c for c in "abcdefghijklmnopqrstuvwxyz" * 2)
    texts = [f"{passage}\nfirst own", f"Read more\n\n{passage}", "Read more\nPage 12", "Page 13\n日本語の長い文。", "日本語の長い文。\nPage 12", "", "\n"]
    got = _dropped(spark, texts)
    assert [got[i][0] for i in range(7)] == [0, 1, 1, 0, 2, 0, 0]
    assert got[1][1] == "Read more\n" and got[2][1] == "Page 12"


def test_line_templates_against_brute_force(spark):
    """Families far apart, so that linked lines are a template in whatever order they come."""
    rng = random.Random(11)
    word = lambda n=7: "".join(rng.choice("abcdefghij") for _ in range(n))
    shapes = [[word() for _ in range(rng.choice((5, 8, 8, 13, 64)))] for _ in range(25)]

    def line():
        kind = rng.random()
        if kind < 0.2:
            return word(3)  # short
        if kind < 0.4:
            return " ".join(word() for _ in range(rng.choice((3, 8, 13))))
        w = list(rng.choice(shapes))
        if rng.random() < 0.6:
            w[-1] = word()  # one field, at the end
        if rng.random() < 0.2:
            w[0] = str(rng.randint(0, 10**6))
        return " ".join(w)

    texts = ["\n".join(line() for _ in range(rng.randint(0, 12))) for _ in range(150)]
    texts += [f"{' '.join(shapes[0])} {word()} {word()}" for _ in range(1300)]  # a leaf of more than one block
    texts += texts[:5]
    field = lambda t: "*" if re.search("[0-9]", t) else t
    shown = lambda ln: tuple(map(field, words(ln))) if len(words(ln)) >= 3 else tuple(words(ln))
    every = sorted({shown(ln) for t in texts for ln in t.split("\n") if words(ln)})
    by_leaf = collections.defaultdict(list)
    for ln in every:
        by_leaf[len(ln), ln[:3]].append(ln)
    name = {}
    for (size, _), own in by_leaf.items():
        groups = []
        for ln in own:
            near = [g for g in groups if any(sum(a == b for a, b in zip(ln, o, strict=True)) >= 0.75 * size for o in g)]
            if size <= 3:
                near = []
            merged = [ln, *(o for g in near for o in g)]
            groups = [g for g in groups if g not in near] + [merged]
        for g in groups:
            name |= dict.fromkeys(g, g[0])
    holders = collections.defaultdict(dict)
    for i, t in enumerate(texts):
        for ln in t.split("\n"):
            if words(ln):
                holders[name[shown(ln)]].setdefault(t, i)
    first = {k: min(v, key=v.get) for k, v in holders.items() if len(v) >= 2}
    want = [[ln for ln in t.split("\n") if not words(ln) or first.get(name[shown(ln)], t) == t] for t in texts]
    got = _dropped(spark, texts)
    assert [got[i] for i in range(len(texts))] == [(len(t.split("\n")) - len(w), "\n".join(w)) for t, w in zip(texts, want, strict=True)]


def test_template_index_finds_all_matches():
    rng = np.random.default_rng(1)
    kinds = rng.integers(1, 60000, (40, 13)).astype(np.uint16)
    rows = np.repeat(kinds, 20, axis=0)
    rows[np.arange(len(rows)), rng.integers(0, 2, len(rows)) * 7 + 2] = rng.integers(60000, 65000, len(rows))
    rows = rows[rng.permutation(len(rows))]
    many = lines.match_templates(rows)
    had, lines.INDEXED = lines.INDEXED, 10_000
    try:
        assert (lines.match_templates(rows) == many).all() and many.max() == 39
    finally:
        lines.INDEXED = had


def test_templates_generalise_fields():
    a = np.array([[1, 2, 3, 4, 5, 6, 7, 8]], np.uint16)
    rows = np.vstack([a, a, a])
    rows[1, 7], rows[2, :6] = 99, [11, 12, 13, 14, 15, 16]
    assert lines.match_templates(rows).tolist() == [0, 0, 1]


def test_simhash_groups(docs, empty):
    def fp(t):
        w = words((t or "").translate({c: c + 32 for c in range(65, 91)}))
        sh = [" ".join(w[j : j + 3]) for j in range(len(w) - 2)] or ([" ".join(w)] if w else [])
        c = [0] * 64
        for s in sh:
            h = xxhash.xxh64_intdigest(s.encode(), 42)
            for b in range(64):
                c[b] += h >> b & 1
        return sum(1 << b for b in range(64) if 2 * c[b] > len(sh))

    rows = fixture_rows()
    prints = [(i, fp(t)) for i, t, *_ in rows]
    label = {p: p for _, p in prints}
    changed = True
    while changed:
        changed = False
        for a in label:
            for b in label:
                if (a ^ b).bit_count() <= 3 and label[a] != label[b]:
                    label[a] = label[b] = min(label[a], label[b])
                    changed = True
    least = {}
    for i, p in prints:
        least[label[p]] = min(i, least.get(label[p], i))
    for i, rs in by_id(simhash.groups(docs)).items():
        p = dict(prints)[i]
        assert all(r["print"] % (1 << 64) == p and r["component_id"] == least[label[p]] for r in rs)
    kept = simhash.keep_one(docs)
    assert kept.columns == docs.columns
    assert sorted(r["doc_id"] for r in kept.collect()) == sorted(least.values())
    assert simhash.groups(empty).count() == 0


def test_keep_one_of_null_and_repeated_ids(spark):
    rng = random.Random(11)
    text = lambda: " ".join(rng.choice("abcdefghij") * rng.randint(1, 4) for _ in range(60))
    a, b, c, d, e, f = (text() for _ in range(6))
    rows = [(None, a), (None, b), (None, c), (None, c), (1, c), (7, d), (7, e), (7, e), (8, d), (None, f), (None, None), (None, "")]
    rows = [(i, t, "en", "s", None, 1, "x", "y") for i, t in rows]
    kept = [(r["doc_id"], r["text"]) for r in simhash.keep_one(spark.createDataFrame(rows, SCHEMA).repartition(3)).collect()]
    full = collections.Counter(x for x in kept if x[1])
    assert full == collections.Counter([(None, a), (None, b), (1, c), (7, d), (7, e), (None, f)])
    assert len(kept) == 7


def test_components_of_a_long_chain(spark):
    e = spark.createDataFrame([(i, i + 1) for i in range(40)] + [(100, 101)], "a long, b long")
    got = {r["node"]: r["root"] for r in simhash.components(e).collect()}
    assert got == {i: 0 for i in range(41)} | {100: 100, 101: 100}


def test_pipeline_stages(spark, tmp_path):
    import corpus_pipeline

    folder = str(tmp_path)
    spark.createDataFrame(fixture_rows(), SCHEMA).write.parquet(f"{folder}/documents.parquet")
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, folder)
        assert out.columns == docs.columns, name
    assert corpus_pipeline.run(spark, folder).count() > 0
