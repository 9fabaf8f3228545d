"""Each operator against brute force on small tables with nulls, blanks, long texts, ties, repeats, clashing columns."""

import hashlib
import random
import re
import zlib
from collections import Counter, defaultdict
from math import log

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from hopline.llm import decontam, langid, license, media, mixing, neardup, quality, sharding, tokens, urls

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, cls string, row string, shard int, w int, score double"
WORDS = {"en": "the of and with from this that which have their about would", "de": "der die und nicht auch einen wird sich nach über können", "fr": "le la les dans pour avec être cette nous vous même été"}
LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def prose(lang, n, seed):
    r = random.Random(f"{lang}{n}{seed}")
    return " ".join(r.choice(WORDS[lang].split()) + r.choice("abcdefgh") * r.randint(0, 2) for _ in range(n))


def rows():
    base = prose("en", 120, 1)
    words = base.split()
    near = [" ".join(words[:k] + ["changed"] + words[k + 1 :]) for k in (3, 60, 117)]
    texts = [None, "", "  \n\t ", "Two words", "two WORDS", "123 ... !!", base, base, base.upper(), *near, prose("en", 6000, 9) + " tail", prose("de", 80, 2), prose("fr", 80, 3), prose("de", 80, 4)]
    texts += [prose(lang, 60 + k, k) for k in range(12) for lang in WORDS]
    out = [(k, t, ("en", "de", "fr", None)[k % 4], (None, "a", "b", "a", "a")[k % 5], len(t or ""), "x", "y", 5, 6, 0.5) for k, t in enumerate(texts)]
    lang = {}
    for k, r in enumerate(out):
        for name, vocabulary in WORDS.items():
            if r[1] and sum(w in r[1] for w in vocabulary.split()) > 6:
                lang[k] = name
    out = [r[:2] + (lang.get(k),) + r[3:] for k, r in enumerate(out)]
    return [*out, out[6], (None, base + " x y z", "en", None, 1, None, None, None, None, None), (None, None, None, None, None, None, None, None, None, None)]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(rows(), SCHEMA).repartition(3).persist()


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def words_of(t):
    return re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate(LOWER))


def shingles(t):
    w = words_of(t)
    return {" ".join(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else ({" ".join(w)} if w else set())


def components(pairs_of, num=85):
    sets = {k: shingles(t) for k, t in pairs_of.items()}
    parent = {k: k for k in sets}

    def root(k):
        while parent[k] != k:
            k = parent[k]
        return k

    for a in sets:
        for b in sets:
            if a < b and sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= num * len(sets[a] | sets[b]):
                parent[root(b)] = root(a)
    groups = defaultdict(list)
    for k in sets:
        groups[root(k)].append(k)
    return {k: min(v) for v in groups.values() for k in v}, sets


def test_near_duplicates(docs, empty):
    got = {(r.doc_id, r.n_shingles): r for r in neardup.near_duplicates(docs).collect() if r.doc_id is not None}
    want, sets = components({r[0]: r[1] for r in rows() if r[0] is not None})
    assert {k: r.component_id for (k, _), r in got.items()} == want
    assert all(r.n_shingles == len(sets[k]) and r.kept == (k == want[k]) for (k, _), r in got.items())
    assert neardup.near_duplicates(empty).count() == 0
    kept = neardup.keep_one(docs)
    assert kept.columns == docs.columns
    ids = [r.doc_id for r in kept.collect()]
    assert sorted(i for i in ids if i is not None) == sorted({k for k, v in want.items() if k == v})


def test_large_bucket_of_near_copies(spark, monkeypatch):
    monkeypatch.setattr(neardup, "SMALL", 3)
    r = random.Random(5)
    base = prose("en", 80, 7).split()
    texts = [" ".join("z%d" % r.randint(0, 10**6) if r.random() < p else w for w in base) for p in (0.003, 0.01, 0.02, 0.04) for _ in range(30)]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    want, _ = components(dict(enumerate(texts)))
    assert {r.doc_id: r.component_id for r in neardup.near_duplicates(df).collect()} == want
    assert len(set(want.values())) > 5


def test_pipeline_links_at_four_fifths(spark):
    words = [f"w{k}" for k in range(54)]
    near = " ".join(words[:27] + ["changed"] + words[28:])  # 45 of 55 shingles
    far = " ".join(words[:15] + ["one"] + words[16:40] + ["two"] + words[41:])  # 40 of 60
    df = spark.createDataFrame([(1, " ".join(words)), (2, near), (3, far)], "doc_id long, text string")
    assert {r.doc_id for r in corpus_pipeline.near_duplicates(spark, df, "").collect()} == {1, 3}
    assert {r.doc_id for r in neardup.near_duplicates(df).where("kept").collect()} == {1, 2, 3}


def test_posterior_bounds():
    least = neardup.least_matches(0.85, 1e-4)
    assert least == sorted(least) and least[-1] < 0.85 * neardup.HASHES


def test_media(docs, empty):
    out = media.document_media(docs).collect()
    assert len(out) == docs.count() and media.document_media(empty).count() == 0
    texts = {r[0]: r[1] or "" for r in rows()}
    for r in out:
        if r.doc_id is None:
            continue
        raw = texts[r.doc_id].encode()
        load = raw + bytes(-len(raw) % 64 if raw else 64)
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(raw), len(load), hashlib.sha256(load).hexdigest(), zlib.crc32(load[-64:]))
        stored = b"P5\n64 %d\n255\n" % (len(load) // 64) + load
        assert (r.media_bytes, r.media_sha256) == (len(stored), hashlib.sha256(stored).hexdigest())


def test_sequences(spark):
    html = '<head><title>no</title></head><p>One &amp; two</p><figure><img src="a.png" alt="old"><figcaption>A <b>cap</b></figcaption></figure>text <img data-digest="d1" alt="x&lt;y"><!-- c --><script>var t="<p>";</script><p></p>end'
    seq = media.parse_sequence(html)
    assert [(s["pos"], s["kind"], s["text"], s["digest"]) for s in seq] == [(0, "text", "One & two", None), (1, "media", "A cap", "src:a.png"), (2, "text", "text ", None), (3, "media", "x<y", "d1"), (4, "text", "end", None)]
    assert media.parse_sequence(None) == media.parse_sequence("") == []
    pages = spark.createDataFrame([(1, html), (2, None)], "page_id long, html string")
    store = media.features(spark.createDataFrame([("d1", 3, bytearray(b"P5\n64 1\n255\n" + b"abc" + bytes(61)))], "digest string, n_bytes long, media binary"))
    got = {r.pos: r for r in media.resolve(media.sequences(pages, ["page_id"]), ["page_id"], store).collect()}
    assert got[1].payload_bytes is None and got[1].caption == "A cap" and got[3].payload_bytes == 64


def test_captions_and_unclosed_elements(spark):
    plain = lambda html: [(x["kind"], x["text"], x["digest"]) for x in media.parse_sequence(html)]
    both = [("media", "over both", "src:a"), ("media", "over both", "src:b")]
    assert plain("<figure><figcaption>over both</figcaption><img src=a><img src=b></figure>") == both
    assert plain("<figure><img src=a><img src=b alt=x><figcaption>over both</figure>") == both
    assert plain("<figure><img src=a alt=one></figure><img src=b alt=two>") == [("media", "one", "src:a"), ("media", "two", "src:b")]
    assert plain("<head><title>t</title><body><p>shown</p>") == plain("<head><meta x><p>shown") == [("text", "shown", None)]
    assert plain("<p>a</p><script>never closed") == [("text", "a", None), ("text", "never closed", None)]
    pages = spark.createDataFrame([(1, "a<img src=x alt=y>b", 3), (2, None, 3), (None, "c", 3)], "page_id long, html string, pos int")
    got = sorted((str(r.page_id), r.pos, r.kind, r.text) for r in media.page_sequences(pages).collect())
    assert got == [("1", 0, "text", "a"), ("1", 1, "media", "y"), ("1", 2, "text", "b"), ("None", 0, "text", "c")]


def test_payloads_are_stored_once_and_measured(spark):
    import numpy as np

    docs = spark.createDataFrame([(k, "same payload" if k < 50 else f"é {k}") for k in range(60)], "doc_id long, text string").coalesce(1)
    store = docs.select("text").mapInArrow(media._stored, "digest string, n_bytes long, media binary")
    assert store.count() == 11
    for r in media.document_media(docs).collect():
        raw = ("same payload" if r.doc_id < 50 else f"é {r.doc_id}").encode()
        x = np.frombuffer(raw + bytes(64 - len(raw)), np.uint8)
        p = np.bincount(x, minlength=256) / 64
        want = f"rows=1|mean={x.mean():.3f}|spread={x.std():.3f}|entropy={-(p[p > 0] * np.log2(p[p > 0])).sum():.3f}|bands=" + "/".join(f"{v:.3f}" for v in p.reshape(8, 32).sum(axis=1))
        assert r.feature.endswith(want) and r.feature.startswith("parts=2|media@1|caption=")


def licenses_by_hand(text):
    """(units, windows, best) by licence, window by window."""
    out = defaultdict(lambda: [0, 0, 0.0])
    probe = set(license.probes()[0])

    def compare(w, name, template, kind):
        a, b = ({" ".join(x) for x in zip(v, v[1:])} for v in (w, license.template_words(template)))
        if a and 5 * 2 * len(a & b) >= 4 * (len(a) + len(b)):
            out[name][kind] += 1
            out[name][2] = max(out[name][2], round(2 * len(a & b) / (len(a) + len(b)), 6))

    lines = text.split("\n")
    for unit in lines + ([text] if len(lines) > 1 else []):
        for name, template in license.TEMPLATES:
            compare(license.template_words(unit), name, template, 0)
    w = license.template_words(text)
    for name, template in license.TEMPLATES:
        v = license.template_words(template)
        pairs = [" ".join(x) for x in zip(v, v[1:])]
        starts = {i - j for i, x in enumerate(zip(w, w[1:])) for j, y in enumerate(pairs) if " ".join(x) == y and y in probe}
        for s in starts:
            compare(w[max(s, 0) : max(0, s + len(v))], name, template, 1)
    return {k: tuple(x) for k, x in out.items() if x[0] or x[1]}


def test_licenses(docs, empty, spark):
    assert license.scan(docs).count() == 0 and license.scan(empty).count() == 0
    by_name = dict(license.TEMPLATES)
    gpl = by_name["GPL-3.0-header"].split()
    wrapped = "int main;\n * " + "\n * ".join(" ".join(gpl[k : k + 7]) for k in range(0, len(gpl), 7)) + "\nmore code"
    among = "We wrote this long ago. " + by_name["MIT-grant"] + " Ask us for more, we like " + "words " * 40
    whole = "Copyright 2001 A. Person\n\n" + "\n".join(re.findall(r".{1,60}(?: |$)", " ".join(by_name["MIT-text"].split()))) + "\nprint(1)\n" * 5
    texts = ["x\nReleased under the MIT License.\ny", "RELEASED under; the mit license", "Released under some other kind of license", None, "Licensed under the Apache License, Version 2.0.\n" * 2, "by", wrapped, among, whole, "software " * 3000 + by_name["CC0-1.0"].upper() + " software" * 50]
    found = license.scan(spark.createDataFrame([*enumerate(texts), (0, texts[0])], "doc_id long, text string")).collect()
    got = {(r.doc_id, r.license_id): (r.n_units, r.n_windows, r.best_dice) for r in found}
    want = {(k, name): x for k, t in enumerate(texts) for name, x in licenses_by_hand(t or "").items()}
    want[0, "MIT"] = (2 * want[0, "MIT"][0], 2 * want[0, "MIT"][1], want[0, "MIT"][2])  # the row is there twice
    assert got == want
    assert all(got[k][1] > 0 and got[k][2] == 1.0 for k in ((6, "GPL-3.0-header"), (7, "MIT-grant"), (8, "MIT-text"), (9, "CC0-1.0")))


def test_license_probes():
    grams = {n: set(license.bigrams(t)) for n, t in license.TEMPLATES}
    probe, keys = license.probes()
    for n, g in grams.items():
        need = -(-license.THRESHOLD * len(g) // (2 - license.THRESHOLD))
        assert len(g & set(probe)) >= len(g) - need + 1, n
    assert all(set(b.split()) & set(keys) for b in probe)


def test_sharding(docs, empty):
    out = sharding.document_shards(docs).collect()
    sizes = Counter(r.shard for r in out)
    assert max(sizes.values()) - min(sizes.get(s, 0) for s in range(8)) <= 1 and len(out) == docs.count()
    for s in sizes:
        assert sorted(r.slot for r in out if r.shard == s) == list(range(sizes[s]))
    texts = {r[0]: r[1] for r in rows()}
    assert all(r.size == len((texts[r.doc_id] or "").encode()) + 1 and r.text_crc32 == zlib.crc32((texts[r.doc_id] or "").encode()) for r in out if r.doc_id is not None)
    assert sharding.document_shards(empty).count() == 0
    back = sharding.shard(docs)
    assert back.count() == docs.count() and set(docs.columns) <= set(back.columns)


def test_sharding_keeps_groups_and_splits_giants(spark):
    df = spark.createDataFrame([(k, f"text {k // 4}" if k < 600 else ("giant" if k < 1000 else f"single {k}")) for k in range(1200)], "doc_id long, text string")
    out = sharding.document_shards(df).collect()
    text = {k: f"text {k // 4}" for k in range(600)}
    homes = defaultdict(set)
    for r in out:
        if r.doc_id in text:
            homes[text[r.doc_id]].add(r.shard)
    assert set(Counter(r.shard for r in out).values()) == {150}
    assert sum(len(v) > 1 for v in homes.values()) <= 15


def test_sharding_tears_only_what_no_shard_holds(spark, monkeypatch):
    sizes = {"half": 75, "most": 120, "third": 50, "giant": 340, **{f"pair {k}": 3 for k in range(100)}}
    texts = [t for t, n in sizes.items() for _ in range(n)]
    texts += [f"single {k}" for k in range(1200 - len(texts))]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    for tail in (sharding.TAIL, 10):  # all seated exactly; mostly moved in rounds
        monkeypatch.setattr(sharding, "TAIL", tail)
        homes, count = defaultdict(Counter), Counter()
        for r in sharding.document_shards(df).collect():
            homes[texts[r.doc_id]][r.shard] += 1
            count[r.shard] += 1
        assert set(count.values()) == {150} and len(count) == 8
        assert [t for t, n in sizes.items() if len(homes[t]) > 1] == ["giant"]
        assert sorted(homes["giant"].values()) == [40, 150, 150]


def linked_rows():
    """Forty topics of nine texts each; texts of a topic share a line, some texts occur twice, one line is everywhere."""
    r = random.Random(3)
    texts = [f"topic {t} has a line of its own\nevery text of the table has this line\ntext {t}.{k}" for t in range(40) for k in range(9)]
    texts += [x for x in texts[::7]] + [f"lonely {k}" for k in range(120)]
    r.shuffle(texts)
    return list(enumerate(texts))


def cut_by_hand(rows, shard_of):
    """Weight of linked pairs in different shards, pair by pair."""
    holders = defaultdict(set)
    for _, t in rows:
        for line in {x for x in (t or "").split("\n") if len(x) >= sharding.LEAST_LINE}:
            holders[line].add(t)
    ids = defaultdict(list)
    for i, t in rows:
        ids[t].append(i)
    total = 0.0
    for texts in holders.values():
        if len(texts) > 1:
            members = [shard_of[i] for t in texts for i in ids[t]]
            total += sum(a != b for k, a in enumerate(members) for b in members[k + 1 :]) * (sharding.UNIT // (len(texts) - 1)) / sharding.UNIT
    return total


def test_propagation_lowers_the_cut(spark, monkeypatch):
    rows = linked_rows()
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    for hot in (sharding.HOT_LEAST, 20):  # every line by shuffle; the common one by broadcast
        monkeypatch.setattr(sharding, "HOT_LEAST", hot)
        monkeypatch.setattr(sharding, "HOT", 40)
        thin = sharding.thin_rows(df).persist()
        units = thin.withColumn("u", F.xxhash64("doc_id", "g"))
        state, report = sharding.place_units(units, 8, len(rows))
        assert abs(cut_by_hand(rows, {r.doc_id: r.shard for r in state.collect()}) - report[-1][2]) < 1e-6
        cuts = [c for _, _, c, _ in report]
        assert cuts == sorted(cuts, reverse=True) and cuts[-1] < 0.9 * cuts[0] and sum(m for *_, m in report) > 0
    out = sharding.document_shards(df).collect()
    count = Counter(r.shard for r in out)
    assert max(count.values()) - min(count.values()) <= 1
    homes = defaultdict(set)
    for r in out:
        homes[rows[r.doc_id][1]].add(r.shard)
    assert all(len(h) == 1 for h in homes.values())
    assert cut_by_hand(rows, {r.doc_id: r.shard for r in out}) < cuts[0]


def test_wishes_follow_the_neighbours(spark):
    rows = linked_rows()
    thin = sharding.thin_rows(spark.createDataFrame(rows, "doc_id long, text string"))
    units = thin.groupBy("g").agg(F.count("*").alias("n"), F.any_value("lines").alias("lines")).persist()
    links = sharding.Links(units)
    state = units.select("g", "n", F.pmod(F.xxhash64("g"), F.lit(8)).cast("int").alias("shard"), F.lit(True).alias("movable"))
    at = {r.g: (r.shard, r.n) for r in state.collect()}
    lines = {r.g: r.lines for r in units.collect()}
    by_line = defaultdict(list)
    for g, keys in lines.items():
        for k in keys:
            by_line[k].append(g)
    labelled = links.labelled(state)
    got = {r.g: (r.goal, r.gain) for r in sharding.wishes(labelled, [sharding.counted(x, 8) for x in labelled], 8).collect()}
    for g, (own, _) in at.items():
        pull = [0] * 8
        for k in lines[g]:
            if len(by_line[k]) > 1:
                for other in by_line[k]:
                    if other != g:
                        pull[at[other][0]] += at[other][1] * (sharding.UNIT // (len(by_line[k]) - 1))
        gain = max(pull) - pull[own]
        assert (g in got) == (gain > 0)
        if gain > 0:
            assert got[g][1] == gain and pull[got[g][0]] == max(pull)


def test_quotas():
    flows = {(0, 1, False): [(1, 30), (2, 30)], (1, 0, False): [(1, 30)], (0, 1, True): [(0, 10), (5, 50)]}
    total, grouped, size = [100, 100], [40, 60], [100, 100]
    done = sharding.admit(flows, total, grouped, size)
    assert sum(total) == 200 and max(total) <= 102 and max(grouped) <= 100
    assert done[1, 0, False] == 1 and done[0, 1, False] >= 1


def test_shard_deals_every_copy_once(spark, monkeypatch):
    monkeypatch.setattr(sharding, "COPIES", 7)
    rows = [(1, "same text", "a")] * 50 + [(1, "same text", "b")] * 9 + [(None, None, "c")] * 5 + [(k, f"text {k}", "d") for k in range(2, 30)]
    out = sharding.shard(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()
    assert Counter((r.doc_id, r.text, r.source) for r in out) == Counter(rows)
    count = Counter(r.shard for r in out)
    assert max(count.values()) - min(count.values()) <= 1
    assert all(sorted(r.slot for r in out if r.shard == s) == list(range(count[s])) for s in count)


def test_language(docs, empty):
    out = langid.identify(docs).collect()
    assert len(out) == docs.count()
    texts = {r[0]: r[1] for r in rows()}
    for r in out:
        if r.doc_id is not None:
            assert r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 3 == 1)
            assert (r.lang_pred == "und") == (not any(c.isalpha() for c in texts[r.doc_id] or "")) and 0 <= r.score <= 1
    assert langid.identify(empty).count() == 0
    assert {r.lang_pred for r in langid.identify(docs.withColumn("lang", F.lit(None).cast("string"))).collect()} == {"und"}
    assert langid.keep_identified(docs).columns == docs.columns


def test_network_equals_plain_convolution():
    import numpy as np

    windows = [prose(lang, 40, k).encode()[:200] for k in range(30) for lang in WORDS]
    model = langid.train(windows, [lang for _ in range(30) for lang in WORDS])
    net, p = langid.Network(model), model["params"]
    x = np.zeros((5, langid.WINDOW), np.uint8)
    for k in range(5):
        x[k, : len(windows[k])] = np.frombuffer(windows[k], np.uint8)
    e = p["emb"][langid._fold()[x]]
    h = np.concatenate([np.maximum((np.concatenate([e[:, k : langid.WINDOW - w + 1 + k] for k in range(w)], axis=2) @ p[f"w{w}"] + p[f"b{w}"]).max(axis=1), 0) for w in langid.WIDTHS], axis=1)
    z = h @ p["out"] + p["bias"]
    z = z - z.max(axis=1, keepdims=True)
    assert np.allclose(z - np.log(np.exp(z).sum(axis=1, keepdims=True)), net.log_probabilities(x), atol=1e-3)
    assert net.texts(windows)[0] == [lang for _ in range(30) for lang in WORDS]


@pytest.fixture(scope="module")
def tokenizer_path():
    return pytest.importorskip("public_tokenizers").path("word_bpe_49k.json")


def test_tokens(docs, empty, tokenizer_path):
    tok = tokens.load(tokenizer_path)
    texts = {r[0]: r[1] or "" for r in rows()}
    for r in tokens.token_counts(docs, tokenizer_path, chunk=2000, overlap=64).collect():
        if r.doc_id is not None:
            n = len(tok.encode(texts[r.doc_id], add_special_tokens=False))
            assert (r.n_tokens, r.over_limit, r.n_bytes) == (n, n > 2048, len(texts[r.doc_id].encode()))
    assert tokens.token_counts(empty, tokenizer_path).count() == 0


def test_token_fuzz(tokenizer_path):
    r = random.Random(4)
    alphabet = [chr(c) for c in range(32, 384)] + ["'s", "'ll", "<|endoftext|>", "<|", "日本", "。", "١", "ª", "\x1c", "\x85", "\xa0", "\n", "İ", "Σ", "é", "\u0301", "한", "½"]
    counter = tokens.Counter(tokenizer_path, 40, 8)
    whole = tokens.Counter(tokenizer_path, 10**6, 8)
    for k in range(1500):
        text = "".join(r.choices(alphabet if k % 2 else [c for c in alphabet if not c.isspace()], k=r.randint(0, 200)))
        n = counter.encoded(text)
        assert counter.batch([text]) == whole.batch([text]) == [n]
    for text in ("a" * 700, "x " * 400, "a1" * 500, "日本。" * 200, "--" * 300, "aé" * 300):
        assert counter.batch([text]) == [counter.encoded(text)]


def test_chunks_are_spliced_once(tokenizer_path):
    counter = tokens.Counter(tokenizer_path, 64, 16)
    text = "  ".join(f"word{k}" for k in range(400))
    parts = counter.spliced(text)
    assert len(parts) > 20 and [w for p in parts for w in p if w] == text.split()
    assert tokens.common_word(["aa", "bb", "cc"], ["b", "cc", "dd"], 4, 8) is None  # cc may go on beyond the left chunk
    assert tokens.common_word(["aa", "bb", "cc", "d"], ["b", "cc", "dd"], 4, 10) == (2, 1)


def test_other_tokenizer_files_are_encoded_whole(tokenizer_path):
    path = pytest.importorskip("public_tokenizers").path("byte_bpe_50k.json")
    counter = tokens.Counter(path, 20, 4)
    assert tokens.Rules(tokenizer_path).known and not counter.rules.known
    text = "two  words\n\n  and more 'll see " * 9
    assert counter.batch([text]) == [len(counter.tokenizer.encode(text, add_special_tokens=False))]


def test_mixing(docs, empty):
    out = mixing.plan(docs).collect()
    total, seen = Counter(), Counter(r.source for r in out)
    for r in docs.collect():
        total[r.source] += len((r.text or "").split())
    emitted = Counter()
    for r in out:
        emitted[r.source] += r.n_tokens
    assert set(seen) == {None, "a", "b"} and {r.doc_id for r in out} == {r[0] for r in rows()}
    longest = max(len((r[1] or "").split()) for r in rows())
    for s in total:
        assert total[s] <= emitted[s] <= 2 * total[s] + longest
    assert mixing.plan(empty).count() == 0 and mixing.mix(docs).columns == docs.columns
    assert mixing.mix(docs).count() == len(out)


def test_mixing_exponent(spark):
    shares = {"a": 1000, "b": 100, "c": 10}
    table = spark.createDataFrame(list(shares.items()), "s string, tokens long")
    a, _ = mixing.solve(table, repetition=None, entropy=0.9)
    w = [t**a for t in shares.values()]
    assert abs(-sum(x / sum(w) * log(x / sum(w)) for x in w) - 0.9) < 1e-3
    a, budget = mixing.solve(table, repetition=4.0)
    w = {k: t**a for k, t in shares.items()}
    repeats = {k: budget * w[k] / sum(w.values()) / shares[k] for k in shares}
    assert abs(max(repeats.values()) - 4) < 1e-2 and abs(min(repeats.values()) - 1) < 1e-6
    with pytest.raises(ValueError):
        mixing.solve(table, repetition=None)


def test_quality(docs, empty, spark):
    bad = [(1000 + k, prose("en", 60, k) + " idiot scum " + prose("en", 5, k)) for k in range(40)]
    fine = [(2000 + k, prose("en", 60, 100 + k)) for k in range(80)]
    table = spark.createDataFrame(bad + fine, "doc_id long, text string")
    labels = spark.createDataFrame([(i, 1, 1) for i, _ in bad[:25]] + [(i, 1, 0) for i, _ in fine[:50]] + [(None, 1, 0), (1, None, 0)], "doc_id long, quality int, toxic int")
    model = quality.fit(table, labels)
    got = {r.doc_id: r.keep for r in quality.grades(table, model).collect()}
    assert not any(got[i] for i, _ in bad) and all(got[i] for i, _ in fine)
    assert list(model["theta"]) == sorted(model["theta"])
    assert quality.grades(docs, model).count() == docs.count() and quality.grades(empty, model).count() == 0
    assert {r.keep for r in quality.grades(docs, None).collect()} == {True}


def test_quality_sample_is_bounded_after_its_join(spark):
    labels = spark.createDataFrame([(k % 40, 1, int(k % 40 < 8)) for k in range(80)], "doc_id long, quality int, toxic int")
    docs = spark.createDataFrame([(k % 40, f"text of {k % 40}, version {k}") for k in range(4000)], "doc_id long, text string")
    got = quality.sampled(docs, labels, 10).collect()
    assert len(got) == len({r.doc_id for r in got}) == 10
    every = quality.sampled(docs, labels, 100).collect()
    assert len(every) == 40 and sum(r.grade == 0 for r in every) == 8


def test_quality_tails_by_hand():
    model = quality.train([0] * 20 + [1] * 20 + [2] * 20, [[1, 5]] * 20 + [[2, 5]] * 20 + [[3, 5]] * 20, [[0]] * 60, [[1.0]] * 60)
    weight = dict(zip(model["kept"].tolist(), model["word"], strict=True))
    scores = [weight[k] + weight[5] + model["style"][0] for k in (1, 2, 3)]
    tails = [[1 / (1 + 2.718281828459045 ** -(x - t)) for t in model["theta"]] for x in scores]
    assert model["theta"][0] < model["theta"][1] and scores == sorted(scores)
    assert tails[0][0] < 0.5 < tails[1][0] and tails[1][1] < 0.5 < tails[2][1]


def test_hosts_of_very_many_labels(spark):
    pages = spark.createDataFrame([(1, "http://" + "a." * 5000 + "example.net/en/x"), (2, "http://" + "a." * 5000 + "org/")], "page_id long, url string")
    assert {r.page_id: r.rule for r in urls.judge(pages, urls.rule_table(spark)).collect()} == {1: "example.net/en/", 2: None}


def test_urls(spark):
    cases = ["http://Net/x", "https://a.example.NET/en/1?x", "https://example.net/en", "http://b.example.com/de/2#t", "ftp://x.org/fr/", None, "nothing", "http://", "http://planet/", "http://net", "http://example.net:80/en/"]
    pages = spark.createDataFrame([(k, u, 1) for k, u in enumerate(cases)] + [(1, cases[1], 1)], "page_id long, url string, host int")
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in urls.judge(pages, urls.rule_table(spark)).collect()}
    assert got[0] == ("net", "/x", "net/", "block") and got[1] == ("a.example.net", "/en/1", "example.net/en/", "allow")
    assert got[2] == ("example.net", "/en", "net/", "block") and got[3][2:] == ("example.com/de/", "block") and got[4][2:] == ("org/fr/", "allow")
    assert all(got[k][2:] == (None, "allow") for k in (5, 6, 7, 8, 9, 10)) and got[5][:2] == got[6][:2] == ("", "")
    assert urls.judge(pages, urls.rule_table(spark)).count() == 12
    none = spark.createDataFrame([], "host string, path string, verdict string")
    assert urls.judge(pages, none).where("rule is not null").isEmpty()


def test_decontamination(docs, empty, spark):
    item = prose("en", 20, 77)
    inside = prose("fr", 300, 5) + " " + item.upper() + " " + prose("de", 300, 6)
    part = " ".join(item.split()[:19]) + " other end"
    half = " ".join(item.split()[:10]) + " other end"
    table = spark.createDataFrame([(1, inside), (2, part), (3, half), (4, None), (5, ""), (5, "two words"), (1, inside)], "doc_id long, text string")
    items = spark.createDataFrame([(7, item, 1), (8, "two words", 1), (9, None, 1), (10, prose("de", 30, 1), 1)], "item_id long, text string, h int")
    got = {(r.doc_id, r.item_id): (r.n_common, r.n_item) for r in decontam.contained_items(table, items).collect()}
    want = {(d, i): len(shingles(t) & shingles(x)) for d, t in ((1, inside), (2, part), (3, half), (5, "two words")) for i, x in ((7, item), (8, "two words")) if shingles(x) and 5 * len(shingles(t) & shingles(x)) >= 4 * len(shingles(x))}
    assert {k: v[0] for k, v in got.items()} == want and (3, 7) not in got
    assert decontam.contained_items(docs, items.limit(0)).count() == 0 and decontam.contained_items(empty, items).count() == 0
    assert {r.doc_id for r in decontam.keep_clean(table, items).collect()} == {3, 4}


def test_decontamination_of_null_ids(spark):
    item = prose("en", 20, 78)
    inside = prose("fr", 50, 5) + " " + item
    table = spark.createDataFrame([(None, inside), (None, prose("de", 40, 2)), (2, inside), (3, prose("de", 40, 3))], "doc_id long, text string")
    items = spark.createDataFrame([(7, item), (None, prose("de", 40, 3))], "item_id long, text string")
    got = {(r.doc_id, r.item_id, r.containment) for r in decontam.contained_items(table, items).collect()}
    assert got == {(None, 7, 1.0), (2, 7, 1.0), (3, None, 1.0)}
    assert [tuple(r) for r in decontam.keep_clean(table, items).collect()] == [(None, prose("de", 40, 2))]


def test_sketch_estimates_lose_no_contained_item(spark):
    r = random.Random(8)
    items = [(k, prose("en", 8 + 5 * k, k)) for k in range(12)]
    docs = []
    for k, (_, t) in enumerate(items):
        w = t.split()
        for j in range(6):  # some words changed: containment around the threshold
            v = list(w)
            for at in r.sample(range(len(v)), min(len(v), j * len(v) // 30)):
                v[at] = "changed"
            docs.append((100 * k + j, prose("fr", 40, j) + " " + " ".join(v) + " " + prose("de", 40, j)))
    want = {(d, i) for d, t in docs for i, x in items if 5 * len(shingles(t) & shingles(x)) >= 4 * len(shingles(x))}
    got = {(x.doc_id, x.item_id) for x in decontam.contained_items(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")).collect()}
    assert got == want and 20 < len(want) < len(docs)


def test_rows_of_one_document_are_judged_together(spark):
    words = prose("en", 30, 5).split()
    halves = [(1, " ".join(words[:17])), (1, " ".join(words[13:])), (2, " ".join(words[:17]))]
    items = spark.createDataFrame([(7, " ".join(words)), (7, " ".join(words)), (7, prose("de", 9, 1))], "item_id long, text string")
    got = decontam.contained_items(spark.createDataFrame(halves, "doc_id long, text string"), items).collect()
    assert [(x.doc_id, x.item_id, x.n_item, x.n_common) for x in got] == [(1, 7, 26, 26)]


def test_pipeline_stages(spark, docs, empty, sf, tmp_path):
    spark.read.parquet(f"{sf}/benchmark.parquet").write.parquet(str(tmp_path / "benchmark.parquet"))
    docs.write.parquet(str(tmp_path / "documents.parquet"))
    assert [n for n, _ in corpus_pipeline.STAGES] == ["language", "near_duplicates", "decontamination", "mixture", "shards"]
    out = corpus_pipeline.run(spark, str(tmp_path))
    identified = {r.doc_id: r.text for r in langid.keep_identified(docs).collect() if r.doc_id is not None}
    want, _ = components(identified, 80)
    assert {r.doc_id for r in out.collect()} - {None} == {k for k, v in want.items() if k == v} and len(want) > 30
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, empty, str(tmp_path)).count() == 0


def test_thinned_samples(spark):
    from hopline.llm.sampling import SLACK, thinned

    table = spark.range(20_000).select(F.xxhash64("id").alias("draw"))
    assert thinned(table, "draw", 100, 300).count() == 20_000
    some = thinned(table, "draw", 100, 20_000)
    assert abs(some.count() - SLACK * 100) < 120
    assert [r.draw for r in some.orderBy("draw").limit(100).collect()] == [r.draw for r in table.orderBy("draw").limit(100).collect()]


def test_copies_do_not_thin_the_sample(spark, monkeypatch):
    seen = []
    monkeypatch.setattr(langid, "train", lambda parts, langs: seen.append(len(parts)))
    texts = [prose("en", 8, k) for k in range(300)] + [prose("de", 8, 1)] * 20_000
    langid.fit(spark.createDataFrame([(k, t, "en") for k, t in enumerate(texts)], "doc_id long, text string, lang string"), sample=50)
    langid.fit(spark.createDataFrame([(k, t, "en") for k, t in enumerate(texts[300:])], "doc_id long, text string, lang string"), sample=50)
    assert seen == [50, 1]
