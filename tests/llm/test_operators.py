"""The ten operators against brute force, and on nulls, empty and very long texts, ties, repeated rows, empty tables and clashing columns."""

from __future__ import annotations

import collections
import functools
import hashlib
import json
import random
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from tracefl.llm import byte_bpe, chaining, common, compression, exact_dedup, jaccard_join, line_dedup, mixing, quality_rules, queries, suffix_array, tool_calls
from tracefl.llm.words import blocks, grams, minimisers

WORD = re.compile(r"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def sentence(rng, n):
    return " ".join(rng.choice(["the", "of", "and", "in", "to"]) if rng.random() < 0.3 else "".join(rng.choice(["ba", "ko", "re", "tion", "mu"]) for _ in range(rng.randint(1, 4))) for _ in range(n))


@pytest.fixture(scope="module")
def odd(spark):
    """Edge cases, with columns named like those that operators add."""
    rng = random.Random(3)
    long = sentence(rng, 60_000)
    near = sentence(rng, 200)
    rows = [(1, None, "en", None), (2, "", None, "a"), (3, " \n\t ", "en", "a"), (4, long, "en", "a"), (5, long + " x", "en", None), (6, near, "en", "b"), (6, near, "en", "b"), (7, near.replace("the", "tha", 1), "xx", "b"), (None, near + "  ", "en", "b"), (None, None, None, None), (8, "one", "en", "c"), (9, "one", "en", "c"), (10, "É\x00 ü" * 30, "fr", "c"), (11, "und " * 300, "de", "c"), (12, "a" * 3000, "en", "c")]
    schema = f"{SCHEMA}, kept boolean, score double, size string, component int, _id int, taken string"
    return spark.createDataFrame([(i, t, g, s, len(t or ""), True, 0.5, "x", 1, 7, "y") for i, t, g, s in rows], schema)


@pytest.fixture(scope="module")
def none(odd):
    return odd.where("1 = 0")


@pytest.fixture(scope="module")
def docs(spark, tiny):
    return common.documents(spark, tiny)


def texts(df):
    return [(r["doc_id"], r["text"]) for r in df.collect()]


def test_words_and_grams():
    import pyarrow as pa

    rng = random.Random(1)
    rows = ["".join(rng.choice("ab \n\té") for _ in range(rng.randint(0, 60))) for _ in range(300)] + [None, "", "x" * 5000]
    seen = {}
    for b in blocks(pa.array(rows), 256):
        for i in range(b.n):
            words = WORD.findall(rows[b.row0 + i] or "")
            part = slice(b.first[i], b.first[i + 1])
            assert [b.data[s:e].tobytes().decode() for s, e in zip(b.start[part], b.end[part], strict=True)] == words
            for w, h in zip(words, b.hash[part].tolist(), strict=True):
                assert seen.setdefault(w, h) == h
        at, _ = grams(b, 3)
        assert len(at) == sum(max(0, b.first[i + 1] - b.first[i] - 2) for i in range(b.n))
    assert len(set(seen.values())) == len(seen)


def test_minimisers_cover_every_window():
    rng = np.random.default_rng(0)
    h, owner = rng.integers(0, 50, 400).astype(np.uint64), np.sort(rng.integers(0, 7, 400))
    chosen = set(minimisers(h, owner, 6).tolist())
    for i in range(395):
        if owner[i] == owner[i + 5]:
            assert i + int(np.argmin(h[i : i + 6])) in chosen


# 1 mixing


def fair_targets(sizes):
    names = sorted(sizes, key=lambda s: (s is None, (s or "").encode()))
    weight = {s: (3, 1, 2)[i % 3] for i, s in enumerate(names)}
    left, out, open_ = 1.5 * sum(sizes.values()), {}, set(names)
    while open_:
        share = {s: left * weight[s] / sum(weight[x] for x in open_) for s in open_}
        over = {s for s in open_ if share[s] > 2 * sizes[s]}
        if not over:
            return out | share
        for s in over:
            out[s] = 2.0 * sizes[s]
            left -= out[s]
        open_ -= over
    return out


@pytest.mark.parametrize("which", ["docs", "odd"])
def test_mixing(which, request):
    df = request.getfixturevalue(which)
    rows = mixing.taken(df, block_words=512).collect()
    assert len(rows) == df.count()
    size = collections.Counter()
    for r in df.collect():
        size[r["source"]] += len(WORD.findall(r["text"] or ""))
    goal, got, most = fair_targets(size), collections.Counter(), collections.Counter()
    for r in rows:
        assert r["source_size"] == size[r["source"]] and r["target"] == pytest.approx(goal[r["source"]])
        assert r["taken"] <= 2 * r["size"] and (not r["size"] or r["taken"] % r["size"] == 0)
        got[r["source"]] += r["taken"]
        most[r["source"]] = max(most[r["source"]], r["size"])
    assert all(abs(got[s] - goal[s]) <= most[s] + 1 for s in size)
    again = mixing.taken(df.repartition(5), block_words=512).collect()
    assert sorted(map(str, rows)) == sorted(map(str, again))


def test_mixing_shards_and_splits(docs, none):
    mixed = mixing.mix(docs, levels=2, block_words=128)
    words = mixed.agg(F.sum("size")).first()[0]
    assert words == mixing.taken(docs, block_words=128).agg(F.sum("taken")).first()[0]
    n = [r["n"] for r in mixed.groupBy("shard").agg(F.count_distinct("source", "pass_no", "block").alias("n")).collect()]
    assert len(n) == 4 and max(n) - min(n) <= 2
    assert mixing.mix(none).count() == 0 and mixing.taken(none).count() == 0


def test_mixing_takes_what_the_shards_draw(docs):
    """A row is taken once for each shard's draw; shards' draws are disjoint and as equal as can be; the order is by shard, then shuffled."""
    rows = mixing.in_order(mixing.mix(docs, levels=3, block_words=64)).select("doc_id", "source", "size", "pass_no", "block", "shard", "shard_order").collect()
    assert [(r["shard"], r["shard_order"]) for r in rows] == sorted((r["shard"], r["shard_order"]) for r in rows)
    owner, words, shards = collections.defaultdict(set), collections.Counter(), collections.defaultdict(list)
    for r in rows:
        owner[r["source"], r["pass_no"], r["block"]].add(r["shard"])
        words[r["doc_id"], r["source"], r["size"]] += r["size"]
        shards[r["doc_id"], r["source"], r["size"]].append(r["shard"])
    assert all(len(s) == 1 for s in owner.values())
    for r in mixing.taken(docs, levels=3, block_words=64).collect():
        key = r["doc_id"], r["source"], r["size"]
        assert r["taken"] == words[key] and r["shards"] == sorted(shards[key])


def test_mixing_tree_is_hypergeometric(spark):
    """Quotas split exactly, with the mean and variance of draws without replacement."""
    quota = spark.createDataFrame([("a", 30), ("b", 50), ("c", 20), ("d", 0)], "colour string, n long")
    seeds, got = range(80), collections.defaultdict(list)
    everything = functools.reduce(lambda x, y: x.unionAll(y), [mixing._splits(quota, 1, seed).withColumn("seed", F.lit(seed)) for seed in seeds])
    by = collections.defaultdict(list)
    for r in everything.collect():
        by[r["seed"], r["colour"]].append((r["shard"], r["lo"], r["hi"]))
    for (seed, colour), parts in by.items():
        (_, lo, mid), (_, mid2, hi) = sorted(parts)
        assert lo == 0 and mid == mid2 and hi == {"a": 30, "b": 50, "c": 20, "d": 0}[colour]
        got[colour].append(mid)
    assert all(sum(got[c][i] for c in got) == 50 for i in range(len(seeds)))
    for c, n in (("a", 30), ("b", 50), ("c", 20)):
        var = n * 0.25 * (100 - n) / 99
        assert abs(np.mean(got[c]) - n / 2) < 4 * (var / len(seeds)) ** 0.5
        assert 0.5 * var < np.var(got[c]) < 1.7 * var


def test_mixing_blocks_are_bounded(docs, monkeypatch):
    """With few blocks allowed the targets are met all the same."""
    monkeypatch.setattr(mixing, "MOST_BLOCKS", 8)
    rows = mixing.taken(docs, block_words=16).collect()
    got, goal, most = collections.Counter(), {}, collections.Counter()
    for r in rows:
        got[r["source"]] += r["taken"]
        goal[r["source"]] = r["target"]
        most[r["source"]] = max(most[r["source"]], r["size"])
    assert all(abs(got[s] - goal[s]) <= most[s] + 1 for s in goal)


# 2 exact dedup


def exact_groups(rows):
    groups = collections.defaultdict(list)
    for i, t in rows:
        groups[re.sub(r"[\x20\x09-\x0D]", "", t or "")].append((i, t or ""))
    out = {}
    for key, members in groups.items():
        keep = min(members, key=lambda m: (-len(m[1]), m[0] is None, m[0] or 0))[0]
        for i, t in members:
            out[i, t] = (keep, len(members), hashlib.sha256(key.encode()).hexdigest())
    return out


@pytest.mark.parametrize("which", ["docs", "odd"])
@pytest.mark.parametrize("batch", ["all new", "all old", "mixed"])
def test_exact_dedup(which, batch, request):
    df = request.getfixturevalue(which)
    batch = queries.incoming() if batch == "mixed" else F.lit(batch == "all new")
    expected = exact_groups(texts(df))
    got = exact_dedup.resolve(df, batch).collect()
    assert sorted(map(str, ((r["doc_id"], r["keep_id"], r["group_size"], r["text_sha256"]) for r in got))) == sorted(map(str, ((i, *expected[i, t or ""]) for i, t in texts(df))))
    kept = exact_dedup.dedup(df, batch)
    assert kept.columns == df.columns and kept.count() == len({v[2] for v in expected.values()})


def test_fuse_filter():
    for n in (0, 1, 2, 3, 10, 1000, 20_000):
        keys = np.random.default_rng(n).integers(0, 1 << 63, n).astype(np.uint64)
        f = exact_dedup.BinaryFuse.from_bytes(exact_dedup.BinaryFuse.build(keys).to_bytes())
        assert f.contains(keys).all()
    assert f.contains(np.arange(100_000, dtype=np.uint64)).mean() < 0.01 and len(f.cells) < 1.6 * n


def test_exact_dedup_empty(none):
    assert exact_dedup.resolve(none, F.lit(True)).count() == 0 and exact_dedup.dedup(none, F.lit(True)).count() == 0


# 3 tool calls


def test_tool_calls(spark):
    calls = spark.createDataFrame([(1, 3, "c", "f", '{"b": 1, "a": "x"}', ["a", "b"]), (1, 1, "a", "f", '{"a": 5}', ["b"]), (1, 2, "b", "g", "{", None), (1, 4, None, "f", None, []), (2, 0, "p", "f", '{"a": "é\\n"}', ["q"]), (2, 1, "q", "f", '{"a": ""}', ["p"])], "conv_id long, turn long, call_id string, name string, arguments string, depends_on array<string>")
    results = spark.createDataFrame([(1, 5, "a", "one"), (1, 6, "a", "two"), (1, 7, "zz", "lost"), (3, 1, None, "none")], "conv_id long, turn long, call_id string, content string")
    schema = {"f": {"type": "object", "required": ["a"], "properties": {"a": {"type": "string", "minLength": 1}}}}
    got = {(r["conv_id"], r["call_id"], r["turn"]): r for r in tool_calls.link(calls, results, schema).collect()}
    assert len(got) == 8
    assert got[1, "c", 3]["status"] == "pending" and got[1, "c", 3]["json"] == '{"arguments":{"a":"x","b":1},"depends_on":["a","b"],"id":"c","name":"f"}'
    assert got[1, "a", 1]["status"] == "linked" and json.loads(got[1, "a", 1]["json"])["result"] == "one" and got[1, "a", 1]["first_error"] == "$.a: not of type string"
    assert got[1, "b", 2]["first_error"] == "unknown tool g" and got[1, None, 4]["n_errors"] == 1
    assert got[1, "zz", 7]["status"] == "orphan" and got[2, "q", 1]["first_error"] == "$.a: below minLength"
    order = sorted((x for x in got.values() if x["conv_id"] == 1 and x["call_id"] in ("a", "b", "c")), key=lambda r: (r["place"], r["step"], r["turn"]))
    assert [r["call_id"] for r in order] == ["b", "a", "c"]
    assert got[2, "p", 0]["cyclic"] and got[2, "q", 1]["cyclic"] and not got[1, "a", 1]["cyclic"]
    assert tool_calls.link(calls.limit(0), results.limit(0), schema).count() == 0


def test_tool_calls_query(spark, tiny):
    rows = {(r["conv_id"], r["turn"]): r for r in queries.op3_tool_calls(spark, tiny).collect()}
    turns = {(r["conv_id"], r["turn"]): r for r in spark.read.parquet(f"{tiny}/conversations.parquet").collect()}
    for k, t in turns.items():
        if t["role"] in ("user", "system"):
            nxt = turns.get((k[0], k[1] + 1))
            linked = nxt is not None and nxt["role"] == "assistant"
            assert rows[k]["status"] == ("linked" if linked else "pending") and rows[k]["n_errors"] == 0
            body = json.loads(rows[k]["json"])
            assert body["arguments"].get("prompt", body["arguments"].get("rule")) == t["text"]
            assert rows[k]["json"] == tool_calls.canonical(body)


# 4 quality rules


def base(t):
    words = WORD.findall(t or "")
    windows = [tuple(words[i : i + 8]) for i in range(len(words) - 7)]
    n = collections.Counter(windows)
    again = {j for i, w in enumerate(windows) if n[w] > 1 for j in range(i, i + 8)}
    seen, dup = set(), 0
    for line in (t or "").split("\n"):
        if WORD.search(line):
            dup += line in seen
            seen.add(line)
    return len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", t or "")), dup, len(again)


@pytest.mark.parametrize("which", ["docs", "odd"])
def test_quality_rules(which, request):
    df = request.getfixturevalue(which)
    got = quality_rules.judge(df).collect()
    names = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
    assert sorted(map(str, ((r["doc_id"], *(r[n] for n in names)) for r in got))) == sorted(map(str, ((i, *base(t)) for i, t in texts(df))))
    for r in got:
        assert r["base_failed"] == (r["n_words"] < 20 or 100 * r["n_repeat_words"] > 30 * r["n_words"])
        assert not (r["base_failed"] and r["kept"]) and ((r["js_chars"] is None) == (r["n_words"] < 50))


def test_quality_rules_against_labels(spark, small):
    rows = queries.op4_quality_rules(spark, small).join(spark.read.parquet(f"{small}/labels.parquet"), "doc_id").where("not base_failed").collect()
    good, bad = [r for r in rows if r["quality"] == 1], [r for r in rows if r["quality"] == 0]
    assert sum(r["kept"] for r in good) == len(good) and sum(not r["kept"] for r in bad) > len(bad) / 3


def test_quality_rules_empty(none):
    assert quality_rules.judge(none).count() == 0


def test_js_distance():
    assert quality_rules.js_distance(np.array([[1.0, 1.0], [1.0, 0.0]]), np.array([1.0, 1.0]))[0] == 0
    assert quality_rules.js_distance(np.array([[1.0, 0.0]]), np.array([0.0, 1.0]))[0] == pytest.approx(1)


# 5 lines


def line_classes(rows, least):
    lines = {(i, k): line_dedup.normalised(x) for i, t in rows for k, x in enumerate((t or "").split("\n"))}
    names = sorted({x for x in lines.values() if x})
    root = {x: x for x in names}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in range(len(names)):
        for b in range(a + 1, len(names)):
            if find(names[a]) != find(names[b]) and distance(names[a], names[b]) <= (1 - least) * max(len(names[a]), len(names[b])) + 1e-9:
                root[find(names[a])] = find(names[b])
    return lines, {x: find(x) for x in names}


def distance(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        new = [i]
        for j, y in enumerate(b, 1):
            new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (x != y)))
        row = new
    return row[-1]


def test_line_dedup(spark):
    rng = random.Random(5)
    base_lines = [sentence(rng, rng.randint(1, 25)) for _ in range(25)]

    def vary(x):
        w = x.split() or ["empty"]
        k = rng.randrange(len(w))
        return " ".join([*w[:k], rng.choice([w[k].upper(), w[k] + "!", "zz", "", w[k] + " 7"]), *w[k + 1 :]])

    rows = [(i, "\n".join(rng.choice([x, vary(x), vary(vary(x))]) for x in rng.sample(base_lines, 6)) + rng.choice(["", "\n", "\n\n..."])) for i in range(30)]
    rows += [(100, "und " * 50), (101, "und " * 55), (102, "und " * 400), (103, None), (104, ""), (105, "b a c d"), (106, "d c b a")]
    df = spark.createDataFrame([(i, t, 1) for i, t in rows], "doc_id long, text string, class_id int")
    lines, cls = line_classes(rows, line_dedup.SIMILARITY)
    got = {(r["doc_id"], r["line_no"]): r for r in line_dedup.resolve(df).collect()}
    assert got.keys() == lines.keys()
    first, pairs = {}, set()
    for k in sorted(lines):
        if lines[k]:
            c = cls[lines[k]]
            pairs.add((c, got[k]["class_id"]))
            assert got[k]["kept"] == (first.setdefault(c, k) == k)
        else:
            assert got[k]["kept"] and got[k]["class_id"] is None
    assert len(pairs) == len({a for a, _ in pairs}) == len({b for _, b in pairs})
    out = {r["doc_id"]: r["text"] for r in line_dedup.dedup(df).collect()}
    for i, t in rows:
        kept = [x for k, x in enumerate((t or "").split("\n")) if got[i, k]["kept"]]
        assert out[i] is None if t is None else out[i] == "\n".join(kept)


def test_line_dedup_edges(odd, none):
    assert line_dedup.resolve(odd).count() == sum((t or "").count("\n") + 1 for _, t in texts(odd))
    assert line_dedup.resolve(none).count() == 0


# 6 byte-level BPE


@pytest.mark.parametrize("which", ["docs", "odd"])
@pytest.mark.parametrize("by_chunk", [True, False])
def test_byte_bpe(which, by_chunk, request):
    import tiktoken

    df = request.getfixturevalue(which)
    path, pattern = queries.tokenizer()
    enc = tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks=byte_bpe.ranks(path), special_tokens={})
    got = byte_bpe.encode(df, path, pattern, by_chunk=by_chunk).collect()
    expected = []
    for i, t in texts(df):
        ids = enc.encode_ordinary(t or "")
        expected.append((i, len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256((t or "").encode()).hexdigest()))
    assert sorted(map(str, expected)) == sorted(str((r["doc_id"], r["n_tokens"], hashlib.sha256(r["ids"]).hexdigest(), hashlib.sha256(r["decoded"]).hexdigest())) for r in got)


def test_byte_bpe_odd_spaces_and_words(spark, none):
    import tiktoken

    path, pattern = queries.tokenizer()
    enc = tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks=byte_bpe.ranks(path), special_tokens={})
    rng = random.Random(2)
    rows = ["".join(rng.choice(["a", "b's", "é", " ", "  ", "\n", "\t", " ", "12", "!", "'", "x\x1cy", "日本", "<|endoftext|>", "　"]) for _ in range(rng.randint(0, 30))) for _ in range(400)]
    df = spark.createDataFrame(list(enumerate(rows)), "doc_id long, text string")
    for r in byte_bpe.encode(df, path, pattern).collect():
        assert np.frombuffer(r["ids"], "<u4").tolist() == enc.encode_ordinary(rows[r["doc_id"]]) and r["decoded"] == rows[r["doc_id"]].encode()
    for n in (399, 401, 3000):
        w = "".join(rng.choice("abcdé") for _ in range(n)).encode()
        assert byte_bpe.encode_word(w, byte_bpe.ranks(path)) == enc.encode_ordinary(w.decode())
    assert byte_bpe.encode(none, path, pattern, digest=True).count() == 0


# 7 and 9 passages


@pytest.fixture(scope="module")
def planted(spark):
    rng = random.Random(11)
    passages = [sentence(rng, 60) for _ in range(4)]
    rows, holds = [], collections.defaultdict(set)
    for i in range(60):
        parts = [sentence(rng, rng.randint(20, 120)) for _ in range(3)]
        if i % 3 == 0:
            p = (i // 3) % 4
            w = passages[p].split()
            if i % 2:
                w[17], w[40] = "changed", "also"
            parts.insert(1, " ".join(w))
            holds[p].add(i)
        rows.append((i, "\n".join(parts)))
    rows += [(200, None), (201, ""), (202, "word " * 500), (None, passages[0])]
    return spark.createDataFrame(rows, "doc_id long, text string"), rows, holds


def test_chaining(planted):
    df, _, holds = planted
    got = chaining.passages(df).collect()
    found = {r["doc_id"] for r in got} | {r["other_id"] for r in got}
    assert found == set().union(*holds.values())
    for r in got:
        assert r["other_id"] < r["doc_id"] and r["identity"] >= 0.8 and min(r["end_word"] - r["start_word"], r["other_end"] - r["other_start"]) >= 50
        assert any({r["doc_id"], r["other_id"]} <= h for h in holds.values())
    for h in holds.values():
        assert {r["doc_id"] for r in got if r["doc_id"] in h} == h - {min(h)}


def test_chain_scores():
    anchors = [(i, i + 100) for i in range(0, 60, 10)] + [(5, 500), (25, 20), (30, 900)]
    best = chaining.chains(anchors)[0]
    assert best == [(i, i + 100) for i in range(0, 60, 10)]
    rng = random.Random(4)
    for _ in range(200):
        points = sorted({(rng.randint(0, 30), rng.randint(0, 30)) for _ in range(rng.randint(1, 9))})
        score = {}
        for x, y in points:
            score[x, y] = chaining.K + max([0.0, *(s - chaining.GAP * (x - a + y - b) for (a, b), s in score.items() if a < x and b < y)])
        chain = chaining.chains(points)[0]
        value = chaining.K * len(chain) - chaining.GAP * (chain[-1][0] - chain[0][0] + chain[-1][1] - chain[0][1])
        assert value == pytest.approx(max(score.values()))


def test_word_edit_distance():
    rng = random.Random(6)
    for _ in range(200):
        a, b = ([rng.randint(0, 3) for _ in range(rng.randint(0, 9))] for _ in range(2))
        assert chaining.edit_distance(np.array(a), np.array(b)) == distance(a, b)


@pytest.mark.parametrize("which", ["docs", "planted"])
def test_suffix_array(which, request):
    df = request.getfixturevalue(which)
    df = df[0] if which == "planted" else df
    words = {i: WORD.findall(t or "") for i, t in texts(df) if i is not None}
    owners = collections.defaultdict(set)
    for i, w in words.items():
        for k in range(len(w) - 49):
            owners[tuple(w[k : k + 50])].add(i)
    expected, got = collections.defaultdict(set), collections.defaultdict(set)
    for i, w in words.items():
        for k in range(len(w) - 49):
            if len(owners[tuple(w[k : k + 50])]) > 1:
                expected[i].update(range(k, k + 50))
    rows = suffix_array.passages(df).collect()
    for r in rows:
        span = words[r["doc_id"]][r["start_word"] : r["start_word"] + 50]
        assert words[r["other_id"]][r["other_start"] : r["other_start"] + 50] == span and r["other_id"] != r["doc_id"]
        got[r["doc_id"]].update(range(r["start_word"], r["end_word"]))
    assert got == expected


def test_suffix_cut(spark):
    df = spark.createDataFrame([(1, "a b  c d"), (2, None), (3, "x")], "doc_id long, text string")
    spans = spark.createDataFrame([(1, 1, 3)], "doc_id long, start_word int, end_word int")
    assert dict(texts(suffix_array.cut(df, spans))) == {1: "a d", 2: None, 3: "x"}


def test_passages_on_edge_cases(odd, none):
    for op in (suffix_array.passages, chaining.passages):
        assert op(none).count() == 0
        pairs = {(min(r["doc_id"], r["other_id"]), max(r["doc_id"], r["other_id"])) for r in op(odd).collect()}
        assert pairs == {(4, 5), (6, 7)}


# 8 classifier


def test_classifier_separates_unseen_rows(spark, small):
    rows = queries.op8_quality_classifier(spark, small).join(spark.read.parquet(f"{small}/labels.parquet"), "doc_id").where("held_out").collect()
    good, bad = [r for r in rows if r["quality"] == 1], [r for r in rows if r["quality"] == 0]
    auc = np.mean([[(g["score"] > b["score"]) + 0.5 * (g["score"] == b["score"]) for b in bad] for g in good])
    assert auc > 0.95 and np.mean([r["predicted"] for r in good]) > 0.95
    assert all(r["predicted"] == int(r["score"] >= 0.3) for r in rows)


def test_classifier_edges(odd, none, spark):
    labels = spark.createDataFrame([(4, 1), (7, 0), (11, 0), (12, 0), (6, 1), (99, 1), (None, 1), (8, None)], "doc_id long, quality int")
    model = compression.fit(compression.sample(odd, labels, F.lit(True)))
    out = compression.score(odd, model)
    assert sorted(out.columns) == sorted(odd.columns)
    assert all(0 <= r["score"] <= 1 for r in out.collect()) and compression.score(none, model).count() == 0
    assert compression.fit([]).offset == 0.0
    prior = compression.score(odd, compression.fit([(b"x", 1)])).select("score").distinct().collect()
    assert len(prior) == 1 and prior[0][0] == pytest.approx(2 / 3)


# 10 Jaccard join


def jaccard_classes(rows):
    sets = []
    for _, t in rows:
        w = WORD.findall(t or "")
        sets.append(frozenset(tuple(w[k : k + 5]) for k in range(len(w) - 4)) if len(w) >= 5 else frozenset([tuple(w)] if w else []))
    distinct = list(dict.fromkeys(sets))
    links, root = collections.Counter(), list(range(len(distinct)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for a in range(len(distinct)):
        for b in range(a + 1, len(distinct)):
            x, y = distinct[a], distinct[b]
            if x and y and len(x & y) >= 0.8 * len(x | y):
                links[a] += 1
                links[b] += 1
                root[find(a)] = find(b)
    place = {s: i for i, s in enumerate(distinct)}
    cls = [find(place[s]) for s in sets]
    name = {}
    for (i, _), c in zip(rows, cls, strict=True):
        name.setdefault(c, []).append(i)
    return [(i, min((x for x in name[c] if x is not None), default=None), links[place[s]]) for (i, _), s, c in zip(rows, sets, cls, strict=True)]


def test_jaccard_join(spark, odd, none):
    rng = random.Random(8)
    seeds = [sentence(rng, rng.randint(30, 200)).split() for _ in range(12)]
    rows = []
    for i in range(150):
        w = list(rng.choice(seeds))
        for _ in range(rng.choice([0, 0, 1, 1, 2, 5])):
            w[rng.randrange(len(w))] = f"new{rng.randint(0, 9)}"
        rows.append((i, " ".join(w)))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    for frame, own in ((df, rows), (odd, texts(odd))):
        got = [(r["doc_id"], r["class_id"], r["n_links"]) for r in jaccard_join.join(frame).collect()]
        assert sorted(map(str, got)) == sorted(map(str, jaccard_classes(own)))
    assert jaccard_join.join(none).count() == 0
    kept = jaccard_join.dedup(df)
    assert kept.columns == df.columns and kept.count() == len({c for _, c, _ in jaccard_classes(rows)})


def test_jaccard_chunks_count_links_once(spark):
    rng = random.Random(9)
    w = sentence(rng, 120).split()
    rows = [(i, " ".join([*w[:60], f"n{i}", *w[61:]])) for i in range(40)]
    members = spark.createDataFrame([(1, i, t) for i, t in rows], "component long, set long, text string")
    for chunk in (7, 64):
        got = jaccard_join.verify(members, chunk=chunk, check=False)
        n = {r["set"]: r["n"] for r in got.where("other is null").groupBy("set").agg(F.sum("n").alias("n")).collect()}
        assert n == dict.fromkeys(range(40), 39)


def test_band_plan():
    for t in (0.5, 0.8, 0.95):
        b, r = jaccard_join.band_plan(t)
        assert 1 - (1 - t**r) ** b >= 0.995 and b * r <= 128


def test_overlaps():
    rng = np.random.default_rng(1)
    sets = [np.unique(rng.integers(0, 60, 30)).astype(np.uint64) for _ in range(9)]
    at = np.concatenate([[0], np.cumsum([len(s) for s in sets])])
    got = jaccard_join.overlaps(at, np.concatenate(sets), at, np.concatenate(sets))
    assert all(got[i, j] == len(np.intersect1d(sets[i], sets[j])) for i in range(9) for j in range(9))


# shared pieces


def test_components(spark):
    rng = random.Random(1)
    edges = [(rng.randint(0, 300), rng.randint(0, 300)) for _ in range(200)] + [(1000 + i, 1001 + i) for i in range(200)] + [(5000, 5001 + i) for i in range(300)]
    root = {}

    def find(x):
        root.setdefault(x, x)
        while root[x] != x:
            x = root[x]
        return x

    for a, b in edges:
        if a != b:
            x, y = sorted((find(a), find(b)))
            root[y] = x
    got = {r["node"]: r["component"] for r in common.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {x: find(x) for x in root}
    assert common.components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_neighbours_over_partitions(spark):
    rng = random.Random(2)
    rows = [(rng.randint(0, 4) if rng.random() < 0.5 else rng.randint(10, 4000), rng.randint(0, 30), i) for i in range(6000)]
    docs = collections.defaultdict(set)
    for k, d, _ in rows:
        docs[k].add(d)
    got = common.neighbours(spark.createDataFrame(rows, "key long, doc_id long, pos int")).collect()
    assert {(r["key"], r["doc_id"], r["pos"]) for r in got} == {r for r in rows if len(docs[r[0]]) > 1} and len(got) == len({(r["key"], r["doc_id"], r["pos"]) for r in got})
    have = set(rows)
    for r in got:
        assert (r["key"], r["other"], r["o_pos"]) in have and r["other"] != r["doc_id"] and r["first"] == (r["doc_id"] == min(docs[r["key"]]))
