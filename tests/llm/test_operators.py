"""The training-data operators against brute force, and on odd rows."""

import hashlib
import itertools
import math
import random
import re
import zlib

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from gleanwork.llm import decontaminate, htmlcut, lmscore, media, mixing, pii, shard, simhash, tokencount, toxicity, vptree
from gleanwork.llm.components import connected_components
from gleanwork.llm.fmindex import FMIndex

ODD = [
    (1, None, "a"), (2, "", "a"), (3, "Hello, the World of 12 words é", None), (3, "Hello, the World of 12 words é", None), (4, "  \n\t ", "b"), (None, "no id here", "b"), (5, "x " * 50_000, "c"), (6, "ünï" * 30_000, "c"),
]


def clash():
    """Extra columns named like the operators' own."""
    return {"key": F.lit(1), "hit": F.lit("x"), "fp": F.lit(2), "_h": F.lit(3), "rank": F.lit(0), "slot": F.lit(7), "_row": F.lit(1), "spans": F.lit(1), "rows": F.lit(9)}


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(ODD, "doc_id long, text string, source string").withColumns(clash())


@pytest.fixture(scope="module")
def docs(spark, data):
    return spark.read.parquet(f"{data}/documents.parquet")


def test_fm_index_finds_every_occurrence():
    rng = np.random.default_rng(1)
    for _ in range(60):
        n = int(rng.integers(5, 120))
        text = rng.integers(0, 4, n)
        text[-1] = 0
        index = FMIndex(text, every=4)
        for length in (1, 2, 3, 5):
            patterns = rng.integers(1, 6, (8, length))
            lo, hi = index.search(patterns)
            for p, a, b in zip(patterns.tolist(), lo, hi):
                want = [i for i in range(n - length + 1) if text[i : i + length].tolist() == p]
                assert sorted(index.locate(np.arange(a, b)).tolist()) == want


def brute_contamination(text, items):
    fold = {c: c + 32 for c in range(65, 91)}
    words = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (t or "").translate(fold))
    own, hit, names = words(text), set(), set()
    for item, body in items:
        w = words(body)
        for i in range(max(1, len(w) - 12)) if w else ():
            window = w[i : i + 13]
            for j in range(len(own) - len(window) + 1):
                if own[j : j + len(window)] == window:
                    hit.update(range(j, j + len(window)))
                    names.add(item)
    return len(own), len(hit), sorted(n for n in names if n is not None)


@pytest.mark.parametrize("group_bytes", [1 << 25, 40])
def test_contamination(spark, odd, group_bytes):
    passage = "one Two three four five six seven eight nine ten eleven twelve thirteen fourteen fifteen"
    items = [("10", passage), ("9", "WORLD of"), ("9", "world of"), (None, "12 words"), ("7", None), ("8", "...")]
    rows = [(20, f"Before, {passage.upper()}; after {passage}", "a"), (21, passage[:60], "a")]
    df = odd.unionByName(spark.createDataFrame(rows, "doc_id long, text string, source string").withColumns(clash()))
    bench = spark.createDataFrame(items, "item_id string, text string").withColumn("doc_id", F.lit(1))
    got = sorted(((r["doc_id"] or 0, r["n_words"], r["n_hit"], list(r["items"])) for r in decontaminate.find_contamination(df, bench, group_bytes=group_bytes).collect()), key=str)
    want = sorted(((d or 0, *brute_contamination(t, items)) for d, t, _ in ODD + rows), key=str)
    assert got == want
    one = decontaminate.find_contamination(df, bench).join(df.select("doc_id", "text"), "doc_id").filter("doc_id = 20")
    assert one.select(decontaminate.remove_spans(F.col("text"), F.col("spans")).alias("t")).first()["t"] == "Before, ; after "
    assert decontaminate.find_contamination(df, bench.limit(0)).filter("n_hit > 0").count() == 0
    assert decontaminate.find_contamination(df.limit(0), bench).count() == 0


def test_min_cut_is_minimal():
    rng = random.Random(4)
    for _ in range(60):
        n = rng.randint(1, 8)
        gain = [round(rng.uniform(-3, 3), 2) for _ in range(n)]
        edges = [(i, j, round(rng.uniform(0, 2), 2)) for i, j in itertools.combinations(range(n), 2) if rng.random() < 0.4]
        cost = lambda keep: sum(max(g, 0) for g, k in zip(gain, keep) if not k) + sum(max(-g, 0) for g, k in zip(gain, keep) if k) + sum(c for a, b, c in edges if keep[a] != keep[b])  # noqa: E731, B023
        best = min(cost(k) for k in itertools.product([False, True], repeat=n))
        assert abs(cost(htmlcut.min_cut(gain, edges)) - best) < 1e-9


def test_main_text():
    w = np.array(list(htmlcut.PRIOR.values()))
    page = """<html><head><title>T</title><style>p{}</style></head><body><header class=site-header>Site</header><nav><ul><li><a href=/>Home</a></ul></nav>
    <div class="cookie-notice">We use cookies on this site, do accept.</div><main><article><header><h1>Big &amp; small</h1></header><p>First  <b>bold</b><br>line.<p>Second paragraph, no end tag<script>var x="</p>";</script>
    <aside>Read more here, it is related.</aside><div class="ad">Buy this now, please.</div><p>Short.</article></main><form><label>Name</label><button>Send</button></form>
    <section id="comments"><p>Nice article, I liked it a lot, thanks.</p></section><footer>&copy; me</footer>"""
    assert htmlcut.main_text(page, w) == "Big & small\n\nFirst bold line.\n\nSecond paragraph, no end tag\n\nShort."
    for odd_page in (None, "", "<", "<p", "plain words only, no tags at all.", "<script>x", "<!-- x", "<a b='", "<div " * 2000):
        assert isinstance(htmlcut.main_text(odd_page, w), str)


def test_mix(spark, docs, odd):
    got = mixing.mix(docs).join(docs.select("doc_id", "source"), "doc_id").toPandas()
    by = got.groupby("source").agg(target=("target", "first"), size=("source_size", "first"), taken=("taken", "sum"), largest=("size", "max"))
    assert abs(by["target"].sum() / by["size"].sum() - 1.5) < 1e-9
    assert ((by["taken"] - by["target"]).abs() <= by["largest"] / 2 + 1).all() and (by["target"] <= 2 * by["size"] + 1e-6).all()
    assert (got["taken"] <= 2 * got["size"]).all()
    again = mixing.mix(docs.repartition(7)).toPandas().sort_values("doc_id")["taken"].tolist()
    assert again == got.sort_values("doc_id")["taken"].tolist()
    assert mixing.mix(odd).count() == len(ODD) and mixing.mix(odd.limit(0)).count() == 0
    copies = mixing.mixed_documents(odd)
    assert copies.columns == odd.columns and copies.filter("text IS NULL OR trim(text) = ''").count() == 0


def brute_targets(sizes, budget=1.5):
    names = sorted((s for s in sizes if s is not None)) + ([None] if None in sizes else [])
    weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(names)}
    target, free = {}, set(names)
    while True:
        left = budget * sum(sizes.values()) - sum(target.values())
        share = {s: left * weight[s] / sum(weight[x] for x in free) for s in free}
        over = {s for s in free if share[s] > 2 * sizes[s]}
        if not over:
            return target | share
        target |= {s: 2.0 * sizes[s] for s in over}
        free -= over


def test_targets(spark):
    rng = random.Random(2)
    for _ in range(4):
        sizes = {f"s{i}": rng.choice([0, 3, 50, 1000]) + rng.randint(0, 9) for i in range(7)} | {None: 20}
        df = spark.createDataFrame(list(sizes.items()), "source string, source_size long")
        want = brute_targets(sizes)
        assert all(math.isclose(r["target"], want[r["source"]], abs_tol=1e-6) for r in mixing.targets(df).collect())


def test_language_model_score(spark, odd):
    good, bad = "the quick brown fox jumps over the lazy dog and runs", "zz qq ww kk vv zz qq"
    rows = [(i, good if i % 2 else bad) for i in range(60)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    target = df.filter("doc_id % 2 = 1").select("doc_id")
    for limit in (1 << 22, 0):  # ids broadcast, and joined
        s = lmscore.score(df, *lmscore.train(df, target, target_ids=limit)).toPandas()
        assert s[s.doc_id % 2 == 1]["score"].max() < s[s.doc_id % 2 == 0]["score"].min()
    few = lmscore.score(df, *lmscore.train(df, target, bigrams=3)).toPandas()
    assert few[few.doc_id % 2 == 1]["score"].max() < few[few.doc_id % 2 == 0]["score"].min()
    out = lmscore.score(odd, *lmscore.train(odd, odd.select("doc_id"))).toPandas()
    assert len(out) == len(ODD) and (out[out.n_tokens == 0]["score"] == 0).all()
    assert lmscore.score(odd.limit(0), *lmscore.train(odd.limit(0), odd.select("doc_id"))).count() == 0


def test_token_counts(docs, odd):
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(tokencount.default_vocabulary())
    count = lambda t: len(library.encode(t or "", add_special_tokens=False).ids)
    rows = docs.limit(60).collect()
    texts = {r["doc_id"]: r["text"] for r in rows}
    for chunk, overlap in ((1 << 15, 1 << 10), (300, 40)):
        got = {r["doc_id"]: r["n_tokens"] for r in tokencount.token_counts(docs.filter(F.col("doc_id").isin(list(texts))), chunk=chunk, overlap=overlap).collect()}
        assert got == {i: count(t) for i, t in texts.items()}
    got = sorted((r["doc_id"] or 0, r["n_bytes"], r["n_tokens"]) for r in tokencount.token_counts(odd).collect())
    assert got == sorted((d or 0, len((t or "").encode()), count(t)) for d, t, _ in ODD)
    odd_texts = ["<|ENDOFTEXT|> a.b. It's 'S. 12.5%... <|endoftext|>. á.b \x0b\x85c\xa0d.,\x1fe", "ǅ.Σ. İ. ΑΣ. 'tis can't. Can'T.", "..", ".a."]
    encoder = tokencount.Encoder(tokencount.default_vocabulary())
    assert encoder.count(odd_texts) == [count(t) for t in odd_texts]
    assert tokencount.count_long(encoder.encode, "y" * 2000, 300, 40) == count("y" * 2000)


def test_media(odd):
    sniffer = media.Sniffer()
    import gzip
    import io
    import zipfile

    def chunk(kind, body):
        return len(body).to_bytes(4, "big") + kind + body + zlib.crc32(kind + body).to_bytes(4, "big")

    png = b"\x89PNG\r\n\x1a\n" + chunk(b"IHDR", bytes(13)) + chunk(b"IDAT", zlib.compress(b"\0\0")) + chunk(b"IEND", b"")
    z = io.BytesIO()
    with zipfile.ZipFile(z, "w") as f:
        f.writestr("a", "b")
    gif = b"GIF89a\x01\0\x01\0\x80\0\0" + bytes(6) + b",\0\0\0\0\x01\0\x01\0\0\x02\x02D\x01\0;"
    for kind, data in (("image/png", png), ("application/gzip", gzip.compress(b"x" * 99, mtime=0)), ("application/zip", z.getvalue()), ("image/gif", gif), ("audio/wav", media.write_wav(b"abc"))):
        seen = sniffer.sniff(data, "text/plain")
        assert (seen["type"], seen["corrected"], seen["length"]) == (kind, True, len(data))
        inside = sniffer.sniff(media.write_wav(b"junk" + data + b"more"), "audio/wav")
        assert not inside["corrected"] and (kind, 48, 48 + len(data)) in inside["embedded"]
        assert sniffer.sniff(data[:-3])["type"] != kind or kind == "audio/wav" and False
    assert media.read_wav(media.write_wav(b"x" * 33)) == b"x" * 33
    got = {(r["doc_id"], r["n_bytes"], r["payload_bytes"], r["payload_sha256"], r["tail_crc32"]) for r in media.text_media(odd).collect()}
    want = set()
    for d, t, _ in ODD:
        raw = (t or "").encode()
        full = raw + bytes(max(64, -(-len(raw) // 64) * 64) - len(raw))
        want.add((d, len(raw), len(full), hashlib.sha256(full).hexdigest(), zlib.crc32(full[-64:])))
    assert got == want
    blobs = odd.select("doc_id", F.col("text").cast("binary").alias("b"), F.lit("image/png").alias("said"))
    assert media.sniff_media(blobs, "doc_id", "b", "said").filter("type = 'application/octet-stream' AND corrected").count() == len(ODD)


def brute_fingerprint(text):
    words = [w for w in re.split(r"[\x20\x09-\x0D]+", (text or "").translate({c: c + 32 for c in range(65, 91)})) if w]
    grams = [" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))] if words else []
    h = [xxhash.xxh64_intdigest(g.encode(), 42) for g in grams]
    return sum(1 << k for k in range(64) if 2 * sum(x >> k & 1 for x in h) > len(h))


def brute_components(ids, fps, reach=2):
    up = {i: i for i in ids}

    def root(i):
        while up[i] != i:
            i = up[i]
        return i

    for a, b in itertools.combinations(ids, 2):
        if (fps[a] ^ fps[b]).bit_count() <= reach:
            x, y = root(a), root(b)
            up[max(x, y)] = min(x, y)
    return {i: root(i) for i in ids}


def test_near_duplicates(docs, odd):
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    fps = {i: brute_fingerprint(t) for i, t in texts.items()}
    want = brute_components(sorted(texts), fps)
    got = simhash.near_duplicates(docs).collect()
    assert all(r["fp"] & (1 << 64) - 1 == fps[r["doc_id"]] and r["component"] == want[r["doc_id"]] for r in got) and len(got) == len(texts)
    # Shards asked by several tasks, and few or many shards, give the same.
    for how in ({"task_queries": 3}, {"min_shards": 2, "shard_classes": 50, "task_queries": 20}):
        assert {(r["doc_id"], r["component"]) for r in simhash.near_duplicates(docs, **how).collect()} == set(want.items())
    rows = simhash.near_duplicates(odd).collect()
    assert len(rows) == len(ODD) and {r["component"] for r in rows if r["doc_id"] in (1, 2, 4)} == {1}
    assert simhash.near_duplicates(odd.limit(0)).count() == 0


def test_vantage_trees_lose_no_link():
    rng = np.random.default_rng(5)
    base = rng.integers(0, 1 << 63, 800, dtype=np.uint64)
    flips = (np.uint64(1) << rng.integers(0, 64, 800).astype(np.uint64)) | (np.uint64(1) << rng.integers(0, 64, 800).astype(np.uint64))
    points = np.unique(np.concatenate([base, base ^ flips, base[:300] ^ (flips[:300] << np.uint64(1))]))
    close = np.bitwise_count(points[:, None] ^ points[None, :]) <= 2
    labels = vptree.link(points, points, 2)
    router = vptree.Router(points[:500], 4)
    row, leaf, home = router.route(points, 2)
    at_home = np.empty(len(points), int)
    at_home[row[home]] = leaf[home]
    reach = set(zip(row.tolist(), leaf.tolist()))
    for i, j in zip(*np.nonzero(close)):
        assert labels[i] == labels[j] and (i, at_home[j]) in reach
    assert home.sum() == len(points)


def test_components(spark):
    rng = random.Random(3)
    edges = [(rng.randint(0, 60), rng.randint(0, 60)) for _ in range(35)] + [(100 + i, 101 + i) for i in range(30)] + [(200, 200 + i) for i in range(40)]
    up = {n: n for e in edges for n in e}
    for _ in range(100):
        for a, b in edges:
            up[a] = up[b] = min(up[a], up[b])
    df = spark.createDataFrame(edges, "a long, b long")
    got = {r["node"]: r["root"] for r in connected_components(df).collect()}
    assert got == {n: r for n, r in up.items() if any(n in e and e[0] != e[1] for e in edges)}
    assert connected_components(df.limit(0)).count() == 0


def test_toxicity(spark, data, docs, odd):
    labels = spark.read.parquet(f"{data}/labels.parquet")
    rng = random.Random(1)
    words = ["alpha", "beta", "gamma", "delta", "eps"]
    rows, truth = [], []
    for i in range(600):
        bad = i % 4 == 0
        rows.append((i, " ".join(rng.choices(words, k=30) + (rng.choices(["scum", "idiot", "stupid", "réeuxpa", "réeuxvi"], k=2) if bad else []))))
        truth.append((i, int(bad)))
    df, y = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(truth, "doc_id long, toxic int")
    chain = toxicity.train(df.filter("doc_id < 400"), y)
    out = toxicity.score(df.filter("doc_id >= 400"), chain).toPandas()
    assert (out["is_toxic"] == (out["doc_id"] % 4 == 0)).mean() > 0.98
    kinds = [c for c in out.columns if c.startswith("p_kind")]
    assert len(kinds) == toxicity.KINDS and out[out.doc_id % 4 == 0][kinds].sum(axis=1).mean() > 10 * out[out.doc_id % 4 != 0][kinds].sum(axis=1).mean()
    assert toxicity.score(odd, chain).count() == len(ODD)
    assert toxicity.keep_clean(odd, chain).columns == odd.columns and toxicity.keep_clean(odd, chain).count() == len(ODD)
    none = toxicity.train(docs.limit(0), labels)
    assert toxicity.score(docs, none).filter("is_toxic").count() == 0
    assert toxicity.train(docs, labels.limit(0)).columns == 0


def test_personal_data(odd):
    text = "Mail a.b@c-d.org, x@y; 1.2.3.4 and 999.1.1.1; card 4111 1111 1111 1111 or 4111111111111112; call +1 (705) 555-5569 or +12."
    kinds = [(pii.KINDS[k], text[a:b]) for k, a, b in sorted(pii.base_spans(text))]
    assert kinds == [("email", "a.b@c-d.org"), ("ip", "1.2.3.4"), ("card", "4111 1111 1111 1111"), ("phone", "+1 (705) 555-5569")]
    tagger = pii.default_tagger()
    held = pii.labelled_texts(150, seed=77)
    found = pii.tag_stretches(tagger, [t for t, _ in held])
    tp = sum(len(set(a) & set(b)) for a, (_, b) in zip(found, held))
    assert 2 * tp / (sum(map(len, found)) + sum(len(s) for _, s in held)) > 0.75
    base, added = pii.find_all(tagger, [text, "", "x" * 5000 + " 5 " + "y" * 5000])[0]
    assert not any(a < y and x < b for _, a, b in added for _, x, y in base)
    rows = pii.find_pii(odd, tagger).collect()
    assert len(rows) == len(ODD) and all(set(r["base"]) <= set(r["spans"]) for r in rows)


def test_tagger_gradient():
    from gleanwork.llm.tagger import Tagger

    ids, mask, y = np.array([[5, 9, 0], [3, 4, 7]]), np.array([[1, 1, 0], [1, 1, 1]], np.float32), np.array([[1, 2, 0], [0, 1, 2]])
    losses = []
    model, state = Tagger(3, embed=3, hidden=4), {}
    for _ in range(60):
        losses.append(model.step(ids, mask, y, state, 0.05))
    assert losses[-1] < 0.2 * losses[0]
    e = model.emissions(ids, mask)
    assert model.decode(e[1]).tolist() == [0, 1, 2] and model.decode(e[0, :2]).tolist() == [1, 2]


def test_lookup_table(spark, odd):
    names = [f"n{i}" for i in range(10)]
    full, less = shard.lookup_table(names, 1009), shard.lookup_table(names[:-1], 1009)
    counts = np.bincount(full)
    assert counts.max() - counts.min() <= 1
    kept = full != 9
    assert (full[kept] == less[kept]).mean() > 0.8
    with pytest.raises(ValueError):
        shard.lookup_table(names, 1000)
    out = shard.place(odd)
    assert out.count() == len(ODD) and out.columns == [*[c for c in odd.columns if c != "slot"], "slot", "shard"]
    want = {i: int(hashlib.md5(str(i).encode()).hexdigest()[:15], 16) % shard.SLOTS for i in (1, 2, 3)}
    got = {r["doc_id"]: (r["slot"], r["shard"]) for r in out.filter("doc_id <= 3").collect()}
    table = shard.lookup_table([f"shard-{k:05d}" for k in range(shard.SHARDS)])
    assert got == {i: (s, table[s]) for i, s in want.items()}
    assert shard.place(odd.limit(0)).count() == 0
