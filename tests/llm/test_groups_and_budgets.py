"""Operators over many rows: shards, near-duplicates, repeated passages, mixing, the pipeline."""

import collections
import hashlib
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from coverdistinct.llm import mixing, neardup, sharding, suffixdedup

DOC = "doc_id long, text string, lang string, source string, n_chars long, id long, value string, n long"


def frame(spark, texts, ids=None):
    return spark.createDataFrame([(i if ids is None else ids[k], t, "en", f"src{k % 3}", None, 1, "v", 2) for k, (i, t) in enumerate(enumerate(texts))], DOC)


@pytest.fixture(scope="module")
def odd(spark):
    return frame(spark, [None, "", " \t ", "one", "a b c d", "a b c d", "x " * 3000, "é" * 500, None, "q" * 250], [0, 1, 2, 3, 4, 5, 6, 7, None, 7])


@pytest.fixture(scope="module")
def none(spark):
    return frame(spark, ["x"]).where("false")


# --- shards ---

def test_shards(spark, sf, odd, none):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    out, text = sharding.shard_documents(docs).collect(), {r["doc_id"]: r["text"].encode() for r in docs.collect()}
    assert len(out) == len(text)
    for r in out:
        assert r["size"] == len(text[r["doc_id"]]) + 16 and r["text_crc32"] == zlib.crc32(text[r["doc_id"]]) and 0 <= r["shard"] < 40 and r["grown_shard"] in (r["shard"], 40)
    by = collections.defaultdict(list)
    for r in out:
        by[r["shard"]].append(r["slot"])
    assert all(sorted(v) == list(range(len(v))) for v in by.values())
    assert sharding.shard_documents(odd).count() == odd.count() and sharding.shard_documents(none).count() == 0
    again = sharding.shard_documents(docs.repartition(9)).collect()
    assert sorted(map(tuple, again)) == sorted(map(tuple, out))


def test_draws_are_those_of_the_tree(spark, sf):
    """Region, rack and shard of every document, each the child with the least -ln(u) / weight, from the published hash alone."""
    draw = lambda name: F.udf(lambda h: -np.log(((h & (2**64 - 1)) >> 11) * 2.0**-53 + 2.0**-54).item(), "double")(F.xxhash64("key", F.lit(name)))
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text", F.col("doc_id").cast("string").alias("key"))
    t = sharding.Topology.regular(2, 2, 2).grow(2.0)
    names = [f"region:{r}" for r in t.tree()] + [f"rack:{k}" for r in t.tree().values() for k in r] + [f"shard:{s}" for r in t.tree().values() for k in r.values() for s in k]
    got = sharding.assign(docs, "doc_id", t).select("*", *[draw(n).alias(n) for n in names]).collect()
    for r in got:
        region = min(t.tree(), key=lambda x: r[f"region:{x}"] / sum(w for k in t.tree()[x].values() for w in k.values()))
        rack = min(t.tree()[region], key=lambda x: r[f"rack:{x}"] / sum(t.tree()[region][x].values()))
        assert r["shard"] == min(t.tree()[region][rack], key=lambda x: r[f"shard:{x}"] / t.tree()[region][rack][x])


def test_shards_are_written_one_folder_each(spark, odd, none, tmp_path):
    sharding.shard_table(odd.withColumn("shard", F.lit("mine")), f"file://{tmp_path}/a")
    back = spark.read.parquet(f"file://{tmp_path}/a")
    want = sharding.assign(odd, "doc_id", sharding.BASE).select("doc_id", "text", "shard").collect()
    assert sorted(map(str, back.select("doc_id", "text", "shard").collect())) == sorted(map(str, want))
    sharding.shard_table(none, f"file://{tmp_path}/b")


def test_weights_and_confined_movement(spark):
    keys = spark.range(40_000).withColumnRenamed("id", "doc_id")
    t = sharding.Topology((sharding.Shard("a", "a1", 0, 3.0), sharding.Shard("a", "a2", 1, 1.0), sharding.Shard("b", "b1", 2, 2.0), sharding.Shard("b", "b1", 3, 2.0)))
    n = {r["shard"]: r["count"] for r in sharding.assign(keys, "doc_id", t).groupBy("shard").count().collect()}
    assert all(abs(n[s] / 40_000 - w / 8) < 0.01 for s, w in ((0, 3), (1, 1), (2, 2), (3, 2)))
    heavier = sharding.Topology((t.shards[0], sharding.Shard("a", "a2", 1, 2.0), *t.shards[2:]))
    both = sharding.assign(sharding.assign(keys, "doc_id", t, "x"), "doc_id", heavier, "y").where("x <> y")
    # what leaves region b goes to region a; inside region a rows move to the heavier rack alone
    assert both.where("y IN (2, 3)").count() == 0 and both.where("x IN (0, 1) AND y <> 1").count() == 0 and both.count() > 0
    both = sharding.assign(sharding.assign(keys, "doc_id", t, "x"), "doc_id", t.grow(), "y").where("x <> y")
    assert both.where("y <> 4").count() == 0
    with pytest.raises(ValueError):
        sharding.Topology(()).tree()


# --- near-duplicates ---

LOW = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def groups(rows, n, percent):
    sets, up = {}, {}
    for d, t in rows:
        w = re.findall("[^\x20\x09-\x0D]+", (t or "").translate(LOW))
        sets[d], up[d] = frozenset(tuple(w[i:i + n]) for i in range(len(w) - n + 1)) if len(w) >= n else frozenset([tuple(w)] if w else []), d

    def top(x):
        while up[x] != x:
            x = up[x]
        return x
    ids = sorted(sets)
    for i, a in enumerate(ids):
        for b in ids[:i]:
            both = len(sets[a] & sets[b])
            if both and 100 * both >= percent * len(sets[a] | sets[b]):
                x, y = top(a), top(b)
                up[max(x, y)] = min(x, y)
    return {d: (len(sets[d]), top(d)) for d in ids}


def check(spark, texts, n=3, percent=85):
    got = {r["doc_id"]: r for r in neardup.near_duplicates(frame(spark, texts), n, percent).collect()}
    want = groups(list(enumerate(texts)), n, percent)
    assert {d: (r["n_shingles"], r["component_id"]) for d, r in got.items()} == want
    assert all(r["kept"] == (r["component_id"] == d) for d, r in got.items())


def edited(rng, words, edits):
    w = list(words)
    for i in rng.integers(0, len(w), edits):
        w[i] = f"e{rng.integers(1 << 30)}"
    return " ".join(w)


def test_near_duplicates_in_small_groups(spark):
    rng = np.random.default_rng(0)
    base = [[f"w{rng.integers(5000)}" for _ in range(n)] for n in (5, 12, 30, 70, 120, 200, 400)]
    texts = [edited(rng, b, e) for b in base for e in (0, 0, 1, 2, 3, 5, 8)] + [None, "", "two words", "TWO words", "Two  Words\n"]
    check(spark, texts)
    check(spark, texts, 5, 80)


def test_near_duplicates_in_one_large_group_and_a_common_passage(spark, monkeypatch):
    """Long lists: full sets, pivots and differences, with many documents near the threshold."""
    monkeypatch.setattr(neardup, "SHORT", 6)
    monkeypatch.setattr(neardup, "FARS", 6)
    rng = np.random.default_rng(1)
    base = [f"w{i}" for i in range(150)]
    passage = [f"p{i}" for i in range(60)]
    texts = [edited(rng, base, int(e)) for e in rng.integers(0, 9, 120)]
    texts += [" ".join(passage + [f"u{rng.integers(1 << 30)}" for _ in range(int(k))]) for k in rng.integers(3, 40, 60)]
    check(spark, texts)


def family(rng, words, size, edits):
    return [edited(rng, words, int(e)) for e in rng.integers(0, edits, size)]


def test_pairs_grow_with_the_members_of_families_not_with_their_pairs(spark, monkeypatch):
    """Two families that share most shingles, but too few for a link, and texts of one template with contents of their own."""
    size, pairs = 400, []
    confirm = neardup.NearDuplicates._confirm

    def counted(self, found):
        found = found.cache()
        pairs.append(found.count())
        return confirm(self, found)

    monkeypatch.setattr(neardup.NearDuplicates, "_confirm", counted)
    rng = np.random.default_rng(8)
    base = [f"w{i}" for i in range(300)]
    other = base[:260] + [f"v{i}" for i in range(40)]
    template = [f"t{i}" for i in range(160)]
    texts = family(rng, base, size, 5) + family(rng, other, size, 5)
    texts += [" ".join(template + [f"u{rng.integers(1 << 30)}" for _ in range(30)]) for _ in range(size)]
    check(spark, texts)
    assert sum(pairs) <= 60 * len(texts)


def test_families_within_families(spark, monkeypatch):
    """Every turn of new references, the ones of single lists and the last, in full, included."""
    monkeypatch.setattr(neardup, "SHORT", 3)
    monkeypatch.setattr(neardup, "FARS", 3)
    rng = np.random.default_rng(9)
    base = [f"w{i}" for i in range(200)]
    texts = []
    for a in range(3):
        for b in range(3):
            words = base[:150] + [f"a{a}_{i}" for i in range(25)] + [f"b{b}_{i}" for i in range(25)]
            texts += family(rng, words, 9, 9)
    for turns, merged in ((12, 0), (0, 3)):
        monkeypatch.setattr(neardup, "TURNS", turns)
        monkeypatch.setattr(neardup, "MERGED_TURNS", merged)
        check(spark, texts)


def test_only_documents_that_sketches_leave_get_full_sets_in_rounds(spark, monkeypatch):
    """Texts that share a short passage alone are members of lists, but need no full sets; what is moved at once is a part."""
    monkeypatch.setattr(neardup, "ROUND_ROWS", 1)
    rows, rounds = collections.Counter(), collections.Counter()
    keep = neardup.settle

    def counted(df, name):
        out = keep(df, name)
        rows[name] += out.count()
        rounds[name] += 1
        return out

    monkeypatch.setattr(neardup, "settle", counted)
    rng = np.random.default_rng(3)
    passages = [[f"p{k}_{i}" for i in range(120)] for k in range(60)]
    texts = [" ".join(passages[k % 60] + [f"u{rng.integers(1 << 30)}" for _ in range(80)]) for k in range(120)]
    base = [f"w{i}" for i in range(150)]
    texts += [edited(rng, base, 1) for _ in range(10)] + [edited(rng, base[:60], e) for e in (0, 0, 1, 9)]
    check(spark, texts)
    assert rows["members"] >= 60 and rows["sets"] <= 30
    assert rounds["hits"] == rounds["sets"] == rounds["measured"] == neardup.ROUNDS


def test_near_duplicates_of_odd_rows(spark, odd, none):
    out = neardup.near_duplicates(odd).collect()
    assert len(out) == odd.count() and all(r["component_id"] == r["doc_id"] for r in out if r["doc_id"] != 5 and r["doc_id"] is not None)
    assert [r["component_id"] for r in out if r["doc_id"] == 5] == [4]
    assert neardup.near_duplicates(none).count() == 0
    kept = neardup.keep_one_of_each(odd)
    assert kept.columns == odd.columns and kept.where("doc_id = 5").count() == 0 and kept.where("doc_id = 4").count() == 1


# --- repeated passages ---

def removed(rows):
    seen, out = set(), {}
    for d, t in sorted(rows):
        b = (t or "").encode()
        mark = bytearray(len(b))
        for i in range(len(b) - 99):
            if b[i:i + 100] in seen:
                mark[i:i + 100] = b"\1" * 100
            seen.add(b[i:i + 100])
        spans = sum(1 for i in range(len(b)) if mark[i] and (i == 0 or not mark[i - 1]))
        out[d] = (len(b), sum(mark), spans, hashlib.sha256(bytes(x for x, y in zip(b, mark) if not y)).hexdigest())
    return out


def passages():
    rng = np.random.default_rng(3)
    text = lambda n: "".join(chr(c) for c in rng.integers(97, 123, n))
    a, b = text(400), text(150)
    texts = [a, text(50) + a[100:250] + text(30), a, b + text(10) + b, text(30) + a[:99] + text(30) + a[300:], None, "", "short", "ab" * 300, "ab" * 200, "é" * 300, text(99), text(100)]
    texts += [text(int(n)) + b[: int(n)] + text(20) for n in (99, 100, 101, 149)]
    base = text(900)
    for _ in range(25):
        x = list(base)
        for i in rng.integers(0, 900, 4):
            x[i] = chr(rng.integers(97, 123))
        texts.append("".join(x))
    return texts


@pytest.mark.parametrize("together", [suffixdedup.MAX_TOGETHER, 3])
def test_repeated_passages_against_brute_force(spark, monkeypatch, together):
    texts = passages()
    docs = frame(spark, texts).repartition(3)
    monkeypatch.setattr(suffixdedup, "repeated_intervals", lambda d, f=suffixdedup.repeated_intervals: f(d, together))
    out = {r["doc_id"]: tuple(r)[1:] for r in suffixdedup.remove_repeats(docs).collect()}
    assert out == removed(list(enumerate(texts)))


def test_long_texts_come_in_pieces(spark, monkeypatch):
    monkeypatch.setattr(suffixdedup, "BLOCK", 700)
    texts = passages() + ["".join(passages()[:3]) * 2]
    blocks = list(suffixdedup._blocks([t.encode() if t else None for t in texts]))
    cut = {(int(r), int(p)) for b in blocks if len(b.anchors) for r, p in zip(b.rows[b.piece], b.pos)}
    monkeypatch.setattr(suffixdedup, "BLOCK", 1 << 20)
    whole = {(int(r), int(p)) for b in suffixdedup._blocks([t.encode() if t else None for t in texts]) if len(b.anchors) for r, p in zip(b.rows[b.piece], b.pos)}
    assert cut == whole


def test_an_identifier_of_zero_is_an_identifier(spark, monkeypatch):
    """Anchors are chosen by the leading bits of identifiers; all zero, or zero for every other place."""
    texts = passages()[:12]
    for keep in (lambda p: np.zeros(p.shape, bool), lambda p: (p >> np.uint64(7)) & np.uint64(1) == 1):
        def dull(data, depth, f=suffixdedup.refine, keep=keep):
            ids = f(data, depth)
            if suffixdedup.Q in ids:
                x = ids[suffixdedup.Q]
                ids[suffixdedup.Q] = np.where(keep(x), x, x & np.uint64(0xFFFFFFFF))
            return ids
        with monkeypatch.context() as m:
            m.setattr(suffixdedup, "refine", dull)
            seen = {}
            for b in suffixdedup._blocks([t.encode() if t else None for t in texts]):
                for r, p in zip(b.rows[b.piece], b.pos) if len(b.anchors) else ():
                    seen.setdefault(int(r), set()).add(int(p))
        for i, t in enumerate(texts):
            n = len((t or "").encode())
            assert all(any(w <= p <= w + suffixdedup.REACH for p in seen.get(i, ())) for w in range(n - 99))
            assert all(0 <= p <= n - suffixdedup.Q for p in seen.get(i, ()))


def test_repeated_passages_of_odd_rows(spark, odd, none):
    assert suffixdedup.remove_repeats(odd).count() == odd.count() and suffixdedup.remove_repeats(none).count() == 0


# --- mixing ---

def test_shortages_go_to_siblings_before_ancestors(spark):
    leaves = spark.createDataFrame([("web", "en", "a", 10), ("web", "en", "b", 1000), ("web", "de", "c", 1000), ("books", "en", "d", 1000)], "domain string, language string, source string, tokens long")
    weights = {"domain": {"web": 1.0, "books": 1.0}, "language": {"en": 1.0, "de": 1.0}, "source": {}}
    got = {r["source"]: r["budget"] for r in mixing.budgets(leaves, 800 / 3010, 1, weights).collect()}
    # 400 a domain, 200 a language; a can give 10 of its 100, its sibling b takes the rest
    assert got == {"a": 10, "b": 190, "c": 200, "d": 400} or all(abs(got[k] - v) <= 1 for k, v in {"a": 10, "b": 190, "c": 200, "d": 400}.items())
    scarce = leaves.withColumn("tokens", F.when(F.col("language") == "de", 20).when(F.col("source") == "b", 100).otherwise(F.col("tokens")))
    got = {r["source"]: r["budget"] for r in mixing.budgets(scarce, 800 / 1130, 1, weights).collect()}
    # web as a whole has 130: the rest goes to books
    assert got["a"] == 10 and got["b"] == 100 and got["c"] == 20 and abs(got["d"] - 670) <= 1


def test_prefixes_by_cells_are_prefixes_by_sorting(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    got = {(r["doc_id"], r["epoch"]) for r in mixing.mix(docs, 0.6, 3).collect()}
    sized = mixing._sized(docs)
    plan = mixing.budgets(sized.groupBy(*mixing.LEVELS).agg(F.sum("n_tokens").alias("tokens")), 0.6, 3)
    want = set()
    leaves = collections.defaultdict(list)
    for r in sized.join(plan.drop("tokens"), mixing.LEVELS).withColumn("place", mixing._order(mixing.SEED)).collect():
        leaves[r["domain"], r["language"], r["source"]].append(r)
    for rows in leaves.values():
        upto, stopped = 0, False
        for r in sorted(rows, key=lambda r: r["place"]):
            want |= {(r["doc_id"], e) for e in range(r["epochs"])}
            upto += r["n_tokens"]
            stopped = stopped or upto > r["rest"]
            if not stopped and r["rest"] > 0:
                want.add((r["doc_id"], r["epochs"]))
    assert got == want
    again = {(r["doc_id"], r["epoch"]) for r in mixing.mix(docs.repartition(7), 0.6, 3).collect()}
    assert again == got and {x for x in mixing.mix(docs, 0.6, 3, seed=9).select("doc_id").distinct().toPandas()["doc_id"]} != {d for d, _ in got}


def test_rows_that_share_a_place_are_counted(spark):
    """Rows without an id and of equal length: as many as fit, whatever their number."""
    rows = [(None, "a b c", "en", "src1")] * 1000 + [(5, "a b", "en", "src1")] * 3
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    for share, epochs in ((0.5, 1), (1.0, 1), (1.7, 3), (0.001, 1)):
        out = mixing.mix(docs, share, epochs)
        n = int(3006 * share)
        assert n - 3 < out.agg(F.coalesce(F.sum("n_tokens"), F.lit(0)).alias("n")).first()["n"] <= n
    assert mixing.mix(docs, 1.0, 1).count() == 1003


def test_mixing_of_odd_rows(spark, odd, none):
    assert mixing.mix(none).count() == 0
    everything = mixing.mix(odd, 1.0, 1).groupBy("doc_id").count()
    assert {(r["doc_id"], r["count"]) for r in everything.collect() if r["doc_id"] in (3, 4, 5, 6)} == {(3, 1), (4, 1), (5, 1), (6, 1)}
    assert mixing.mix(odd, 1.0, 1).count() >= odd.where("text IS NOT NULL").count() - 3
    assert mixing.keep_mixed(odd, 0.5).columns == odd.columns


# --- the pipeline ---

def test_a_cluster_without_a_shared_folder_is_refused():
    from coverdistinct.llm import common
    assert common.one_process("local[4]") and common.one_process("local") and not common.one_process("local-cluster[2,1,1024]") and not common.one_process("yarn")


def test_pipeline_stages_of_odd_rows(spark, sf, odd, none):
    """Nulls, empty and long texts, repeated ids and rows, more columns, and no rows at all."""
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, odd, sf)
        assert out.columns == odd.columns, name
        left = [tuple(r) for r in out.collect()]
        assert all(r in [tuple(x) for x in odd.collect()] for r in left), name
        assert stage(spark, none, sf).count() == 0, name
    ids = lambda k: sorted((r["doc_id"] for r in corpus_pipeline.STAGES[k][1](spark, odd, sf).select("doc_id").collect()), key=str)
    assert 0 not in ids(0) and 1 not in ids(0)  # no letter
    assert 5 not in ids(1) and 4 in ids(1)  # a copy
    assert ids(2) == sorted((r["doc_id"] for r in odd.select("doc_id").collect()), key=str)
    assert corpus_pipeline.STAGES[4][1](spark, odd, sf).count() == odd.count()


def test_pipeline_against_its_stages_in_python(spark, sf):
    """What each stage keeps, recomputed from the documents of the stage before."""
    from coverdistinct.llm import decontam, langid
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = {r["doc_id"]: r for r in docs.collect()}
    codes = langid.train(docs)
    name, score, near, told = codes.decode([r["text"] or "" for r in rows.values()])
    langs = {}
    for d, n, s, a, t in zip(rows, name, score, near, told):
        if t and re.search(r"[^\W\d_]", rows[d]["text"] or ""):
            langs[d] = n if not a and s >= langid.CONFIDENT else rows[d]["lang"]
    group = groups([(d, rows[d]["text"]) for d in langs], 5, 80)
    kept = {d for d, (_, top) in group.items() if top == d}
    bench = decontam.Benchmark.build([(r["item_id"], r["text"]) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()])
    kept = {d for d in kept if not bench.hits(rows[d]["text"])}
    leaves = collections.defaultdict(list)
    for d in kept:
        leaves[rows[d]["source"], langs[d]].append((d, len(re.findall("[^\x20\x09-\x0D]+", rows[d]["text"]))))
    out = {r["doc_id"]: r for r in corpus_pipeline.run(spark, sf).collect()}
    assert set(out) <= kept
    # of each leaf a prefix in the seeded order, of tokens within its budget
    sized = spark.createDataFrame([(mixing_domain(s), l, s, sum(n for _, n in x)) for (s, l), x in leaves.items()], "domain string, language string, source string, tokens long")
    for b in mixing.budgets(sized, corpus_pipeline.MIX_SHARE, 1).collect():
        mine = leaves[b["source"], b["language"]]
        if b["epochs"]:
            assert all(d in out for d, _ in mine)
            continue
        place = lambda x: hashlib.md5(f"{x[0]}|{x[1]}|0|{mixing.SEED}".encode()).hexdigest()
        upto, want = 0, set()
        for d, n in sorted(mine, key=place):
            upto += n
            if upto > b["rest"]:
                break
            want.add(d)
        assert {d for d, _ in mine if d in out} == (want if b["rest"] > 0 else set())
    assert all(r["text_crc32"] == zlib.crc32((rows[d]["text"] or "").encode()) for d, r in out.items())


def mixing_domain(source):
    n = int(re.fullmatch(r"src(\d+)", source)[1])
    return "web" if n < 10 else "books" if n < 15 else "forum" if n < 20 else "other"


def test_pipeline_stages(spark, sf):
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["language id", "near-duplicates", "decontamination", "mixing", "sharding"]
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    n = docs.count()
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, sf)
        assert out.columns == docs.columns
        out = out.cache()
        k, ids = out.count(), out.select("doc_id").distinct().count()
        assert 0 < k <= n and ids == k and out.drop("lang").exceptAll(docs.drop("lang")).count() == 0
        docs, n = out, k
    assert corpus_pipeline.run(spark, sf).count() == n
