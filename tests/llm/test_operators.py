"""Operators against brute force, on small tables with the odd cases: nulls, empties, ties, copies, clashing names."""

import hashlib
import zlib

import numpy as np
import pyarrow as pa
import pytest

from ugraph.llm import chats, id_store, media, mixing, near_dedup, packing, pii, quality_classifier, quality_rules, repeat_levels, repeats
from ugraph.llm.tokens import default_path, encoder

WORDS = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon".split()


def text(seed, n):
    rng = np.random.default_rng(seed)
    return " ".join(rng.choice(WORDS) + str(rng.integers(99)) for _ in range(n))


BASE = text(1, 300)
TEXTS = [BASE, BASE, BASE.replace("alpha", "omega", 1), None, "", "one", "one", text(2, 90), "x " * 400, "passage " + text(3, 120) + BASE[:900], "don't 5's İstanbul á <|endoftext|>", text(4, 4000)]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i if i != 7 else None, t, ["b", "a", None][i % 3], f"extra{i}", 1) for i, t in enumerate(TEXTS)]
    return spark.createDataFrame(rows, "doc_id long, text string, source string, name string, n long")


@pytest.fixture(scope="module")
def empty(docs):
    return docs.limit(0)


def ids(t):
    return np.array(encoder(default_path()).library.encode(t or "", add_special_tokens=False).ids + [1], "<u4")


def test_encoder_equals_library():
    e = encoder(default_path())
    arr = pa.array(TEXTS + ["a'll'm 12ab !'s", "  lead\n tail\t", "…—“q”€5", "\x0b"])
    got, b = e.encode(arr)
    assert [got[b[i] : b[i + 1]].tolist() for i in range(len(arr))] == [e.library.encode(t or "", add_special_tokens=False).ids for t in arr.to_pylist()]


def test_every_vocabulary_entry_encodes_to_itself():
    e = encoder(default_path())
    plain = [(w[:-4], i) for w, i in e.library.get_vocab().items() if w.endswith("</w>") and w[:-4].isascii() and w[:-4].isalpha() and w == w.lower()]
    got, b = e.encode(pa.array([w for w, _ in plain]))
    assert np.array_equal(got[b[:-1]], [i for _, i in plain]) and (np.diff(b) == 1).all()


def test_id_store(spark, docs, empty, tmp_path):
    got = sorted(id_store.store_digest(docs, str(tmp_path / "s")).collect(), key=lambda r: r.start)
    order = sorted(range(len(TEXTS)), key=lambda i: -1 if i == 7 else i)
    start = 0
    for r, i in zip(got, order, strict=True):
        x = ids(TEXTS[i])
        assert (r.start, r.n_tokens, r.ids_crc32) == (start, len(x), zlib.crc32(x.tobytes()))
        start += len(x)
    assert id_store.store_digest(empty).count() == 0
    packs, manifest = id_store.open_store(spark, str(tmp_path / "s"))
    id_store.check_manifest(spark, str(tmp_path / "s"), packs)
    assert [r.n_docs for r in manifest.filter("level = 2").collect()] == [len(TEXTS)]
    for wrong in (packs.filter("n_tokens < 1000"), packs.withColumn("n_tokens", packs.n_tokens + 1), packs.withColumn("leaf", packs.recipe)):
        with pytest.raises(ValueError):
            id_store.check_manifest(spark, str(tmp_path / "s"), wrong)


def test_packing(docs, empty):
    got = packing.pack_documents(docs).toPandas()
    per = {i: ids(t) for i, t in enumerate(TEXTS)}
    for r in got.itertuples():
        x = per[7 if np.isnan(r.doc_id) else int(r.doc_id)]
        assert zlib.crc32(x[r.start : r.start + r.length].tobytes()) == r.ids_crc32 and r.doc_tokens == len(x)
        assert r.ids == x[r.start : r.start + r.length].tobytes()
    assert got.length.sum() == sum(map(len, per.values()))
    for _, g in got.sort_values("offset").groupby("sequence_id"):
        assert g.offset.tolist() == np.concatenate(([0], np.cumsum(g.length)[:-1])).tolist() and g.length.sum() <= 2048
    assert (got.groupby("sequence_id").length.sum() < 2048).sum() <= 1
    assert packing.pack_documents(empty).count() == 0


def test_packing_takes_the_next_best_tails():
    """70 short tails share a term with the last one; those without it come earlier and must wait."""
    tails = [np.array([1, 2, 3])] + [np.array([10 + i, 9, 8]) for i in range(100)] + [np.array([1, 2, 4])] * 70
    idf = np.ones(200)
    lengths = np.array([len(t) for t in tails])
    first = packing.fill_windows(lengths, packing.ShardIndex(tails, idf, 3.0), 3 * 71)[0]
    assert {i for i, _, _ in first} == {0, *range(101, 171)}


def test_packing_looks_up_all_terms():
    """30 terms of high weight lie in no other tail; the one that a copy shares is the 31st."""
    tails = [np.arange(31), np.array([40, 41]), np.array([30, 42])]
    idf = np.array([2.0] * 30 + [1.0] * 20)
    assert packing.ShardIndex(tails, idf, 10.0).scores(0)[2] > 0


def test_packing_deals_copies_to_one_shard(spark):
    rows = [(100 * c + g, text(1000 + g, 60)) for g in range(40) for c in range(9)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(7)
    got = packing.pack_documents(df, shard_tokens=24000).toPandas()
    assert got.length.sum() == sum(len(ids(t)) for _, t in rows)
    got["shard"], got["group"] = got.sequence_id // 2**32, got.doc_id % 100
    assert got.shard.nunique() > 2 and (got.groupby("group").shard.nunique() == 1).all()
    assert packing.deal([(1, 10), (2, 25), (3, 4), (4, 6)], 10) == [(1, 0, 1), (2, 1, 3), (3, 4, 1), (4, 5, 1)]


def brute_components(rows, percent, width):
    sets = [near_dedup.shingle_set(t or "", width) for _, t in rows]
    root = list(range(len(rows)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            k = len(np.intersect1d(sets[i], sets[j]))
            if len(sets[i]) and len(sets[j]) and 100 * k >= percent * (len(sets[i]) + len(sets[j]) - k):
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    return [find(i) for i in range(len(rows))]


def test_near_duplicates(spark, empty):
    rng = np.random.default_rng(5)
    rows = [(i, t) for i, t in enumerate(TEXTS[:7])]
    words = text(9, 150).split()
    for i in range(60):
        w = list(words)
        for _ in range(int(rng.integers(0, 12))):
            w[rng.integers(len(w))] = f"edit{rng.integers(4)}"
        rows.append((100 + i, " ".join(w)))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    for percent, width in ((85, 3), (80, 5)):
        want = brute_components(rows, percent, width)
        got = {r.doc_id: r.component_id for r in near_dedup.near_duplicates(df, percent, width).collect()}
        assert got == {d: rows[c][0] for (d, _), c in zip(rows, want, strict=True)}
    assert near_dedup.near_duplicates(empty).count() == 0


def test_bands_follow_the_limit():
    assert [(near_dedup.side_of(p), near_dedup.least_equal(p)) for p in (85, 80)] == [(10, 36), (14, 49)] or near_dedup.side_of(80) == 14
    for p in (70, 80, 85, 95):
        assert 2 * (1 - (p / 100) ** 3) ** near_dedup.side_of(p) <= near_dedup.MISS


def test_near_duplicates_go_by_row(spark):
    """Equal and null doc_ids, on copies and on unrelated texts: one row of each group, and no other, stays."""
    a, b = text(70, 80), text(71, 80)
    rows = [(1, a, "x"), (1, b, "x"), (2, a, "y"), (2, a, "y"), (None, a, "z"), (None, text(72, 80), "z"), (None, b, "q"), (3, None, "e"), (3, None, "e"), (4, "", "e"), (None, text(73, 80), "r"), (None, text(73, 80), "r")]
    df = spark.createDataFrame(rows, "doc_id long, text string, rid string").repartition(3)
    got = sorted((r.doc_id or -1, r.text or "", r.rid) for r in near_dedup.drop_near_duplicates(df, 80, 5).collect())
    want = [(1, a, "x"), (1, b, "x"), (-1, text(72, 80), "z"), (3, "", "e"), (3, "", "e"), (4, "", "e"), (-1, text(73, 80), "r")]
    assert got == sorted(want)


def test_mixing(spark, docs, empty):
    got = mixing.mix_digest(docs).toPandas()
    assert len(got) == len(TEXTS) and (got.taken <= 3 * got["size"]).all()
    assert got["size"].sum() == sum(len((t or "").encode().split()) for t in TEXTS)
    per = got.groupby("source_size").target.first()
    assert per.sum() == pytest.approx(got["size"].sum()) and (per <= 3 * per.index + 1e-6).all()
    again = mixing.mix_digest(docs.repartition(3)).toPandas()
    key = lambda d: sorted(map(tuple, d.fillna(-1).values.tolist()))
    assert key(got) == key(again)
    assert mixing.mix_digest(empty).count() == 0
    mixed = mixing.mix_documents(docs)
    assert mixed.columns == docs.columns


@pytest.mark.parametrize("kind", range(5))
def test_png_filters(kind):
    rng = np.random.default_rng(kind)
    rows = rng.integers(0, 256, (7, 24)).astype(np.uint8)
    raw = np.zeros((7, 25), np.uint8)
    raw[:, 0] = kind
    for y in range(7):
        for x in range(24):
            a, b, c = (int(rows[y, x - 1]) if x else 0), (int(rows[y - 1, x]) if y else 0), (int(rows[y - 1, x - 1]) if x and y else 0)
            p = a + b - c
            paeth = min((abs(p - a), 0, a), (abs(p - b), 1, b), (abs(p - c), 2, c))[2]
            raw[y, x + 1] = (int(rows[y, x]) - [0, a, b, (a + b) // 2, paeth][kind]) % 256
    assert np.array_equal(media._unfilter(raw if kind else raw.copy()), rows)
    assert np.array_equal(media.decode_png(media.encode_png(rows)), rows)
    broken = bytearray(media.encode_png(rows))
    broken[50] ^= 1
    with pytest.raises(ValueError):
        media.decode_png(bytes(broken))


def test_cosine_hash_against_the_sums():
    """The hash of a small image by the transform's definition."""
    rng = np.random.default_rng(4)
    samples = rng.integers(0, 256, (32, 32)).astype(np.uint8)
    n = 32
    low = np.array([[sum(float(samples[y, x]) * np.cos(np.pi * (y + 0.5) * v / n) * np.cos(np.pi * (x + 0.5) * u / n) for y in range(n) for x in range(n)) for u in range(8)] for v in range(8)]).round(6).ravel()
    assert media.cosine_hash(samples) == np.packbits(low > np.median(low[1:])).tobytes()


def test_media(docs, empty):
    got = {r.doc_id: r for r in media.media_digest(docs).collect()}
    for i, t in enumerate(TEXTS):
        r, data = got[i if i != 7 else None], (t or "").encode()
        data = data + b"\xff" * (max(576, -(-len(data) // 576) * 576) - len(data))
        assert (r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(data), hashlib.sha256(data).hexdigest(), zlib.crc32(data[-32:]))
    assert got[0].feature == got[1].feature and media.media_digest(empty).count() == 0


def test_rule_statistics():
    got = quality_rules.text_stats("a b c a b c\n# x\n# x\n\n")
    assert got[:5] == (10, 10, 2, 1, 6)
    assert quality_rules.text_stats("") [:5] == (0, 0, 0, 0, 0)


def test_rules_and_forest(spark, empty):
    rows = [(i, text(i, 80)) for i in range(80)] + [(100 + i, " ".join(w + "$$$" for w in text(i, 80).split())) for i in range(20)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(i < 100), 0) for i, _ in rows if i % 2], "doc_id long, quality int, toxic int")
    got = {r.doc_id: r.kept for r in quality_rules.quality_digest(df, labels).collect()}
    assert all(got[i] == (i < 100) for i, _ in rows)
    assert quality_rules.keep_good(df, labels).count() == 80
    assert quality_rules.quality_digest(df, labels.limit(0)).filter("kept").count() == 100
    assert quality_rules.quality_digest(empty, labels).count() == 0


def slow_statistics(t):
    import re

    words = re.findall(r"[^\x20\x09-\x0D]+", t)
    lines = [x for x in t.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    windows = [tuple(words[i : i + 3]) for i in range(len(words) - 2)]
    inside = {i + d for i, w in enumerate(windows) if windows.count(w) > 1 for d in range(3)}
    return (
        len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in t), sum(x in lines[:i] for i, x in enumerate(lines)), len(inside),
        sum("A" <= c <= "Z" for c in t), sum("0" <= c <= "9" for c in t), sum(c in "!?;:()[]{}=+/\\@^~`_\"'" for c in t), len(lines), len(set(words)),
    )


def test_rule_statistics_against_a_slow_form():
    rng = np.random.default_rng(3)
    letters = list("ab A1#|!é\n\t  \u00a0x")
    for n in (0, 1, 5, 40, 200):
        for _ in range(20):
            t = "".join(rng.choice(letters, n))
            assert quality_rules.text_stats(t) == slow_statistics(t)


def test_forest_against_a_slow_form():
    """Scores by following each row down each tree, and every statistic's junk caught by itself."""
    rng = np.random.default_rng(8)
    n = 400
    words = rng.integers(60, 400, n)
    good = np.stack([words, words * 5 + rng.integers(0, 60, n), rng.integers(0, 3, n), rng.integers(0, 2, n), rng.integers(0, 6, n), words // 10, rng.integers(0, 12, n), rng.integers(0, 4, n), words // 20, words * 4 // 5], axis=1)
    forest = quality_rules.IsolationForest(quality_rules.rates(good))

    def slow(row):
        each = []
        for trees in forest.trees:
            total = 0.0
            for feature, cut, left, right, length in trees:
                k = 0
                while left[k] != k:
                    k = left[k] if row[feature[k]] < cut[k] else right[k]
                total += length[k]
            each.append(2 ** (-total / len(trees) / forest.expected))
        return max(each)

    assert np.allclose(forest.score(quality_rules.rates(good[:40])), [slow(r) for r in forest.bounds(quality_rules.rates(good[:40]))])
    limit = np.quantile(forest.score(quality_rules.rates(good)), 0.99)
    for name, change in {
        "n_symbols": lambda c: c[0], "n_upper": lambda c: c[1] * 4 // 5, "n_marks": lambda c: c[0], "n_digits": lambda c: c[1] * 4 // 5, "n_dup_lines": lambda c: c[8] + 20,
        "n_repeat_words": lambda c: c[0] * 9 // 20, "n_distinct": lambda c: 5 + 0 * c[0], "word_chars": lambda c: c[0] * 14, "n_lines": lambda c: c[0],
    }.items():
        junk = good.copy()
        junk[:, (quality_rules.COUNTS + quality_rules.MORE).index(name)] = change(good.T)
        assert (forest.score(quality_rules.rates(junk)) > limit).mean() > 0.7, name


def test_forest_with_an_extreme_text(spark):
    """One word of 100,000 signs stretches no range, whether the base rules reject its text or not."""

    def loud(i):
        return " ".join(w.upper() if k % 10 < i % 4 else w + "!" * (k % 9 < i % 3) for k, w in enumerate(text(i, 300).split()))

    def signs(i):
        return " ".join(w + "$" * (k % 2) for k, w in enumerate(text(i, 300).split()))

    rows = [(i, loud(i)) for i in range(80)] + [(100 + i, signs(i)) for i in range(20)]
    rows += [(200, "|" * 100_000), (201, text(201, 80) + " " + "|" * 100_000)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(i < 100), 0) for i, _ in rows], "doc_id long, quality int, toxic int")
    got = {r.doc_id: r.kept for r in quality_rules.quality_digest(df, labels).collect()}
    assert all(got[i] == (i < 100) for i, _ in rows)


def test_classifier(spark, empty):
    rows = [(i, text(i, 60) if i % 2 else text(i, 60).upper()) for i in range(200)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    labels = spark.createDataFrame([(i, i % 2, 0) for i in range(200)], "doc_id long, quality int, toxic int")
    got = quality_classifier.quality_scores(df, labels).toPandas()
    assert (got.held_out == [zlib.crc32(str(i).encode()) % 4 == 2 for i in got.doc_id]).all()
    h = got[got.held_out]
    assert (h.predicted == h.doc_id % 2).mean() > 0.95 and got.score.between(0, 1).all()
    none = quality_classifier.quality_scores(df, labels.limit(0)).toPandas()
    assert np.allclose(none.score, 0.5)
    assert quality_classifier.quality_scores(empty, labels).count() == 0


def test_classifier_against_a_slow_form():
    """Features, ratios and margins with dictionaries, and the fit against projected gradient steps on the same dual."""
    texts = [text(i, 12) if i % 2 else text(i, 12).upper() + " !" for i in range(24)]
    y = np.array([i % 2 for i in range(24)])

    def code(gram):
        h = (0x811C9DC5 + len(gram)) % 2**32
        for c in gram:
            h = (h ^ c) * 0x01000193 % 2**32
        h = (h ^ (h >> 15)) * 0x2C1B3C6D % 2**32
        return h >> (32 - quality_classifier.BITS)

    rows = [quality_classifier.gram_ids(t.encode()) for t in texts]
    for t, r in zip(texts, rows, strict=True):
        b = t.encode()
        assert {code(b[i : i + n]) for n in quality_classifier.SIZES for i in range(len(b) - n + 1)} == set(r.tolist())
    ratio = quality_classifier.log_ratios(rows, y)
    size = 1 << quality_classifier.BITS
    p, q = ({k: 1 + sum(k in set(r.tolist()) for r, v in zip(rows, y, strict=True) if v == side) for k in set(np.concatenate(rows).tolist())} for side in (1, 0))
    total = [sum(x.values()) + size - len(x) for x in (p, q)]
    assert all(abs(ratio[k] - (np.log(p[k] / total[0]) - np.log(q[k] / total[1]))) < 1e-9 for k in p)
    w, intercept = quality_classifier.descend(rows, y, ratio, epochs=400)
    x = np.zeros((24, size))
    for i, r in enumerate(rows):
        x[i, r] = ratio[r] / np.linalg.norm(ratio[r])
    sign = np.where(y == 1, 1.0, -1.0)
    k = (x @ x.T + 1) * np.outer(sign, sign)
    alpha = np.zeros(24)
    for _ in range(20000):
        alpha = np.clip(alpha - (k @ alpha - 1) / np.linalg.eigvalsh(k)[-1], 0, 1) if _ == 0 else np.clip(alpha - step * (k @ alpha - 1), 0, 1)
        step = 1 / 24
    assert np.allclose(w, (alpha * sign) @ x, atol=2e-2) and abs(intercept - alpha @ sign) < 2e-2
    assert np.allclose(quality_classifier.margins(rows, ratio, w, intercept), x @ w + intercept)


def test_snapshots(spark):
    rows = [(1, 1, "u", "hi"), (1, 2, "a", "yo"), (2, 1, "u", "hi"), (2, 2, "a", "yo"), (2, 3, "u", None), (3, 1, "u", "hi"), (4, 1, "u", "other"), (5, 1, "u", "other"), (None, 1, "u", "x"), (6, 1, None, None)]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    got = {(r.conv_id, r.n_turns, r.n_copies): r.text for r in chats.render(df).collect()}
    assert set(got) == {(2, 3, 1), (4, 1, 2), (6, 1, 1)}
    assert got[2, 3, 1] == "<|u|>\nhi\n<|a|>\nyo\n<|u|>\n\n"
    assert chats.render(df.limit(0)).count() == 0


def luhn(d):
    return sum((lambda v: v - 9 if v > 9 else v)(int(c) * (1 + i % 2)) for i, c in enumerate(reversed(d))) % 10 == 0


def test_pseudonyms(spark, empty):
    import re

    texts = ["card 4929603461135148 and 4929 6034 6113 5148", "again 4929603461135148!", "not valid 4929603461135147", "call +1 (614) 555-8001", "ip 10.20.30.40 v 1.2", "on 2021-03-04 or 31.12.1999, not 2021-13-40", "mail jo.x@mail.example.com", None, "", "nothing"]
    assert luhn("4929603461135148")
    got = [r.text for r in pii.masked(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), "k").orderBy("doc_id").collect()]
    card = re.search(r"\d{16}", got[0])[0]
    assert luhn(card) and card != "4929603461135148" and got[0].replace(" ", "").count(card) == 2 and card in got[1]
    assert got[2] == texts[2] and got[7:] == texts[7:]
    assert re.fullmatch(r"call \+1 \(\d{3}\) \d{3}-\d{4}", got[3]) and got[3] != texts[3]
    assert re.fullmatch(r"ip \d\d\.\d\d\.\d\d\.\d\d v 1\.2", got[4]) and "2021-13-40" in got[5] and "2021-03-04" not in got[5]
    assert "jo.x@" not in got[6] and got[6].endswith("@mail.example.com")
    assert all(t is None or len(t) == len(g) for t, g in zip(texts, got, strict=True))
    assert pii.masked(empty, "k").count() == 0


def test_feistel_is_a_permutation(spark):
    df = spark.range(1000).selectExpr("lpad(cast(id as string), 3, '0') AS d").selectExpr(f"{pii._permuted_digits('d', 'test', 'k')} AS x")
    assert sorted(r.x for r in df.collect()) == [f"{i:03d}" for i in range(1000)]


def feistel_numbers(a, b, size_a, size_b, kind, key):
    for i in range(pii.ROUNDS):
        digest = lambda x: int(hashlib.sha256(f"{key}:{kind}:{i}:{x}".encode()).hexdigest()[:15], 16)
        if i % 2 == 0:
            a = (a + digest(b)) % size_a
        else:
            b = (b + digest(a)) % size_b
    return a, b


def feistel_text(x, alphabets, kind, key):
    a, b = x[: len(x) // 2], x[len(x) // 2 :]
    for i in range(pii.ROUNDS):
        part, other = (a, b) if i % 2 == 0 else (b, a)
        h = bytes.fromhex(hashlib.sha512(f"{key}:{kind}:{i}:{other}".encode()).hexdigest())
        new = ""
        for j, c in enumerate(part):
            own = next((s for s in alphabets if c in s), None)
            new += own[(own.index(c) + h[j]) % len(own)] if own else c
        a, b = (new, b) if i % 2 == 0 else (a, new)
    return a + b


def feistel_digits(d, kind, key):
    h = len(d) // 2
    a, b = feistel_numbers(int(d[:h]), int(d[h:]), 10**h, 10 ** (len(d) - h), kind, key)
    return f"{a:0{h}d}{b:0{len(d) - h}d}"


def test_pseudonyms_against_a_second_form(spark):
    import datetime

    key, day = "k'ey", datetime.date(1900, 1, 1)
    card = feistel_digits("492960346113514", "card", key)
    card += next(c for c in "0123456789" if luhn(card + c))
    a, b = feistel_numbers(*divmod((datetime.date(2021, 3, 4) - day).days, 487), 150, 487, "date", key)
    ip = [10 - 10, 20 - 10, 30 - 10, 4]
    c, d = feistel_numbers(ip[0] * 90 + ip[1], ip[2] * 10 + ip[3], 90 * 90, 90 * 10, "ip", key)
    letters = ("0123456789", "abcdefghijklmnopqrstuvwxyz")
    mail, secret = feistel_text("jo.x7", letters, "mail", key), feistel_text("0123456789abcdef" * 2, ("0123456789abcdef",), "secret", key)
    phone = feistel_digits("6145558001", "phone", key)
    rows = {
        "4929603461135148": card, "2021-03-04": str(day + datetime.timedelta(a * 487 + b)),
        "10.20.30.4": f"{c // 90 + 10}.{c % 90 + 10}.{d // 10 + 10}.{d % 10}", "jo.x7@e.org": f"{mail}@e.org", "Jo.X7@e.org": f"{mail[:1].upper()}{mail[1:3]}{mail[3].upper()}{mail[4:]}@e.org",
        "0123456789abcdef" * 2: secret, "0123456789ABCDEF" * 2: secret.upper(), "+1 (614) 555-8001": f"+1 ({phone[:3]}) {phone[3:6]}-{phone[6:]}",
    }
    df = spark.createDataFrame([(f"see {t}, end",) for t in rows], "text string")
    assert [r.text for r in pii.masked(df, key).collect()] == [f"see {t}, end" for t in rows.values()]
    # different values stay different
    names = [f"{x}{y}@e.org" for x in "abcdefgh" for y in range(60)] + ["a@e.org", "b@e.org"]
    got = [r.text for r in pii.masked(spark.createDataFrame([(n,) for n in names], "text string"), key).collect()]
    assert len(set(got)) == len(names)


def removed(data: list[bytes]) -> list[np.ndarray]:
    """Which bytes of each text a string of 400 covers that starts in two places."""
    seen: dict[bytes, int] = {}
    for d in data:
        for i in range(len(d) - 399):
            seen[d[i : i + 400]] = seen.get(d[i : i + 400], 0) + 1
    out = [np.zeros(len(d), bool) for d in data]
    for d, hit in zip(data, out, strict=True):
        for k in range(len(d) - 399):
            if seen[d[k : k + 400]] > 1:
                hit[k : k + 400] = True
    return out


def check_repeats(got, texts, ids):
    data = [(t or "").encode() for t in texts]
    for i, d, hit in zip(ids, data, removed(data), strict=True):
        kept = hashlib.sha256(np.frombuffer(d, np.uint8)[~hit].tobytes()).hexdigest()
        r = got[i]
        assert (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) == (len(d), int(hit.sum()), int((np.diff(np.concatenate(([0], hit.astype(int)))) == 1).sum()), kept)


SIZES = [(repeats.SHARD_ROWS, repeats.NARROW), (5, 0), (23, 3)]


@pytest.mark.parametrize("sizes", SIZES)
def test_repeats(spark, docs, empty, sizes):
    got = {r.doc_id: r for r in repeats.repeated_spans(docs, *sizes).collect()}
    check_repeats(got, TEXTS, [i if i != 7 else None for i in range(len(TEXTS))])
    assert repeats.repeated_spans(empty, *sizes).count() == 0


@pytest.mark.parametrize("sizes", SIZES)
def test_repeats_of_one_passage(spark, sizes):
    """Cuts of one passage, from below 400 bytes up, each between words of its own; some twice in a text."""
    rng, whole, texts = np.random.default_rng(5), text(50, 120), []
    for i in range(40):
        a = int(rng.integers(0, 200))
        cut = whole[a : a + int(rng.integers(360, 520))]
        texts.append(text(100 + i, int(rng.integers(1, 40))) + cut + text(200 + i, int(rng.integers(1, 40))) + (cut if i % 7 == 0 else ""))
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    check_repeats({r.doc_id: r for r in repeats.repeated_spans(df, *sizes).collect()}, texts, range(40))


@pytest.mark.parametrize("sizes", SIZES)
def test_passages_of_words(spark, sizes):
    """51 words in two places count in whole, though below 400 bytes; 50 do not; white space between words is not compared."""
    rng, long_, items = np.random.default_rng(6), text(60, 120).split(), [text(61 + i, n) for i, n in enumerate((50, 51, 55, 59))]
    rows = [f"{text(500 + i, int(rng.integers(0, 60)))} {items[i % 4]} {text(600 + i, int(rng.integers(0, 60)))}" for i in range(12)]
    rows += ["\t".join(items[2].split()), items[3] + "\n" + items[3].replace(" ", "  "), items[0], *["a b c " * n for n in (16, 17, 18, 60)]]
    for i in range(40):
        a = int(rng.integers(0, 60))
        rows.append(f"{text(700 + i, int(rng.integers(0, 20)))} {' '.join(long_[a : a + int(rng.integers(45, 60))])}\x0b{text(800 + i, int(rng.integers(0, 20)))}")
    texts = [*TEXTS, *rows]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r.doc_id: r for r in repeats.repeated_spans(df, *sizes).collect()}
    words, seen = [(t or "").encode().split() for t in texts], {}
    for w in words:
        for k in range(len(w) - 50):
            seen[tuple(w[k : k + 51])] = seen.get(tuple(w[k : k + 51]), 0) + 1
    for i, w in enumerate(words):
        hit = np.zeros(len(w), bool)
        for k in range(len(w) - 50):
            if seen[tuple(w[k : k + 51])] > 1:
                hit[k : k + 51] = True
        inside = np.zeros(len(w), bool)
        for s in got[i].passages or []:
            inside[s.a : s.b] = True
        assert got[i].n_passage_words == hit.sum() and (inside == hit).all()
    assert len(items[1]) < 400 and all((got[len(TEXTS) + i].n_passage_words > 0) == (i % 4 > 0) for i in range(12))
    check_repeats(got, texts, range(len(texts)))


@pytest.mark.parametrize("sizes", [SIZES[0], SIZES[2]])
def test_kept_levels(spark, empty, tmp_path, sizes):
    """Batches against the levels of earlier ones: passages within a batch, across batches, copies, a batch that failed."""
    rng, whole = np.random.default_rng(9), text(51, 120)
    cuts = [whole[a : a + 430] for a in rng.integers(0, 300, 6).tolist()]
    texts = [*TEXTS, *(text(300 + i, 9) + c + text(400 + i, 9) for i, c in enumerate(cuts)), text(2, 90), TEXTS[9], text(7, 150) + text(7, 150)]
    rows = [(i, t, f"extra{i}") for i, t in enumerate(texts)]
    batches = [rows[:1], [], rows[1:14], rows[14:]]
    family = repeat_levels.RepeatLevels(spark, f"{tmp_path}/family", *sizes)
    assert family.removed().count() == 0
    seen, suffixes = [], []
    for n, batch in enumerate(batches):
        if n == 2:  # what a failed batch leaves behind is overwritten
            spark.createDataFrame([(99, 99, "x", b"x")], repeat_levels.MEMBERS).write.parquet(f"{tmp_path}/family/members/3")
        family.add(spark.createDataFrame(batch, "doc_id long, text string, name string").coalesce(1 if n == 0 else 4))
        seen += batch
        done, _, levels = family.state()
        suffixes.append(sum(r for _, r in levels))
        assert done == n + 1 and all(a.bit_length() > b.bit_length() for (_, a), (_, b) in zip(levels, levels[1:], strict=False))
        if n != 1:
            got = {r.doc_id: r for r in family.removed().collect()}
            assert len(got) == len(seen)
            check_repeats(got, [t for _, t, _ in seen], [i for i, _, _ in seen])
    assert suffixes[0] == suffixes[1] < suffixes[2] < suffixes[3]
    path, rows = family.state()[2][0]
    level = family._level(path).toPandas()
    assert len(level) == rows == len(level.drop_duplicates(["cid", "pos"]))


def test_merged_sizes():
    assert repeat_levels._merged([5]) == 1
    assert repeat_levels._merged([100, 5]) == 1
    assert repeat_levels._merged([100, 5, 7]) == 2
    assert repeat_levels._merged([16, 8, 8]) == 3
