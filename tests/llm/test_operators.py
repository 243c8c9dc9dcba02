"""Operators on small fixtures: brute force, round trips, and edge cases (nulls, empty, ties, repeats, clashing columns)."""

import hashlib
import random
import re
import time
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest

from rasterflow.llm import avi, bpe, chat, hmm, mixing, neardup, neighbours, pii, quality, tokens

VOCABULARY = "/opt/tokenizers/byte_bpe_50k.json"
WS = re.compile(r"[^\x20\x09-\x0D]+")


def texts(n=60, seed=1):
    r = random.Random(seed)
    words = ["alpha", "Beta", "gamma,", "été", "漢字", "12", "a@b.co", "x.\ny", "don't", "🙂", "  ", "\n\n"]
    out = [" ".join(r.choice(words) for _ in range(r.randint(1, 60))) for _ in range(n)]
    return [*out, None, "", " ", "z" * 3000, out[0], out[0]]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i if i != 5 else None, t, "en", None if i % 7 == 0 else f"s{i % 3}", 0, "clash") for i, t in enumerate(texts())]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, score string").repartition(3)


def test_avi(docs, spark):
    got = {r["doc_id"]: r for r in avi.digests(docs).collect()}
    for i, t in enumerate(texts()):
        x = (t or "").encode()
        p = x.ljust(max(576, -(-len(x) // 576) * 576), b"\xff")
        r = got[i if i != 5 else None]
        assert (r["n_bytes"], r["payload_bytes"], r["payload_sha256"], r["tail_crc32"]) == (len(x), len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-32:]))
    assert avi.digests(docs.limit(0)).count() == 0
    stored = avi.media(docs).unionByName(spark.createDataFrame([(990, None), (991, b"RIFFxxxx")], "doc_id long, media binary"))
    clips = avi.clips(stored).collect()
    assert {r["doc_id"] for r in clips if r["error"]} == {991} and 990 not in {r["doc_id"] for r in clips}


def test_avi_frames_by_another_decoder(spark):
    payload = bytes(range(256)) * 2 + bytes(64)
    frame = avi.parse(avi.store([payload])[0]).frames[0]
    jvm = spark.sparkContext._jvm
    image = jvm.javax.imageio.ImageIO.read(jvm.java.io.ByteArrayInputStream(bytearray(frame)))
    raster = image.getRaster()
    assert bytes(raster.getSample(8 * (i % 24) + 3, 8 * (i // 24) + 5, 0) for i in range(576)) == payload


def test_avi_general_frame(spark):
    """A frame with AC coefficients and three components, made by the JVM's encoder, against its decoder."""
    jvm = spark.sparkContext._jvm
    kind = jvm.java.awt.image.BufferedImage
    image = kind(40, 24, kind.TYPE_INT_RGB)
    for x in range(40):
        for y in range(24):
            v = (x * 5 + y * 3) % 256
            image.setRGB(x, y, v << 16 | v << 8 | v)
    out = jvm.java.io.ByteArrayOutputStream()
    jvm.javax.imageio.ImageIO.write(image, "jpg", out)
    frame = bytes(out.toByteArray())
    if b"\xff\xda" not in frame:
        pytest.skip("no JPEG writer")
    (_, d), = avi.decode([frame])
    back = jvm.javax.imageio.ImageIO.read(jvm.java.io.ByteArrayInputStream(bytearray(frame)))
    mine = d.pixels(0)
    theirs = np.array([[back.getRGB(x, y) >> 8 & 255 for x in range(40)] for y in range(24)])
    assert mine.shape == (24, 40) and np.abs(mine.astype(int) - theirs).max() <= 6


def test_shots():
    h = np.zeros((40, 16))
    h[:20, 0], h[20:, 9] = 1, 1
    assert [(a, b) for a, b, _ in avi.shots(h)] == [(0, 20), (20, 40)]
    assert avi.shots(np.zeros((0, 16))) == []


def cuts_of(differences):
    """Starts of shots where frames 1, 2, ... differ so much from the one before."""
    h = np.concatenate([[0.0], np.cumsum([x * (-1) ** i for i, x in enumerate(differences)])])
    return [a for a, _, _ in avi.shots(np.stack([h, 1 - h], 1))]


def test_shots_in_quick_series():
    for every in (3, 4, 5, 6):
        at = list(range(every, 60, every))
        assert cuts_of([0.9 if t in at else 0.0 for t in range(1, 60)]) == [0, *at]
    assert cuts_of([{10: 1.0, 14: 0.5, 20: 0.6}.get(t, 0.0) for t in range(1, 40)]) == [0, 10, 14, 20]


def test_shots_at_the_first_frame():
    assert cuts_of([0.9]) == [0, 1]
    assert cuts_of([0.05]) == [0]
    assert cuts_of([0.9, *[0.0] * 20]) == [0, 1]
    assert cuts_of([0.2] * 40) == [0, 1]  # steady noise


def test_quality_separates_and_handles_edges(spark):
    r = random.Random(2)
    good = [" ".join(r.choice(["the", "of", "and", "rain", "fell"]) for _ in range(30)) for _ in range(150)]
    bad = [" ".join(r.choice(["the###", "of!!", "RAIN$$$", "win%%%"]) for _ in range(30)) for _ in range(60)]
    rows = [(i, t) for i, t in enumerate(good + bad)] + [(900, None), (901, ""), (None, "the of"), (0, good[0])]
    docs = spark.createDataFrame([(*x, "clash") for x in rows], "doc_id long, text string, label string")
    labels = spark.createDataFrame([(i, int(i < 150), 0) for i in range(210)] + [(None, 1, 0), (3, None, 0)], "doc_id long, quality int, toxic int")
    model = quality.train(docs, labels)
    got = quality.score(docs, model).collect()
    assert len(got) == len(rows)
    held = [x for x in got if x["held_out"] and x["doc_id"] < 210]
    assert held and all(x["predicted"] == int(x["doc_id"] < 150) for x in held)
    assert all(0 <= x["score"] <= 1 for x in got) and all(x["held_out"] == (x["doc_id"] is not None and zlib.crc32(str(x["doc_id"]).encode()) % 4 == 2) for x in got)
    prior = quality.train(docs, labels.limit(0))
    assert {round(x["score"], 6) for x in quality.score(docs, prior).collect()} == {0.5}
    assert quality.score(docs.limit(0), model).count() == 0


BASE = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}


def brute_pii(t):
    out = {}
    for k, p in BASE.items():
        digits = lambda m: re.sub("[^0-9]", "", m[0])
        fits = {"email": lambda m: True, "ip": lambda m: all(int(x) <= 255 for x in m[0].split(".")), "card": lambda m: 16 <= len(digits(m)) <= 19 and pii.luhn(digits(m)), "phone": lambda m: 8 <= len(digits(m)) <= 15}[k]
        out[k] = [m.span() for m in re.finditer(p, t) if fits(m)]
    return out


def test_pii_equals_brute_force():
    r, finder = random.Random(3), pii.Finder()
    parts = [*"019.+-@ ()aZ_%", "4539578763621486", "255.1.2.3", "a@b.c", "+1 (555) 555-0199", "account ", "é"]
    for _ in range(20000):
        t = "".join(r.choice(parts) for _ in range(r.randint(0, 25)))
        got = finder.spans(t)
        assert {k: got[k] for k in BASE} == brute_pii(t), t


def test_pii_rows_and_redaction(spark):
    t = "Mail a.b@c.org, IBAN: DE89370400440532013000, account no 12345678, http://joe:pw@host.com/x"
    d = spark.createDataFrame([(1, t, "x"), (2, None, "x"), (3, "", "x"), (4, "9" * 20000 + "@" * 5000, "x")], "doc_id long, text string, spans string")
    got = {r["doc_id"]: r for r in pii.find(d).collect()}
    assert got[1]["n_email"] >= 1 and "iban:" in got[1]["spans"] and "account:" in got[1]["spans"] and "login:" in got[1]["spans"]
    assert got[2]["spans"] == got[3]["spans"] == "" and got[2]["base_sha256"] == hashlib.sha256(b"").hexdigest()
    clean = {r["doc_id"]: r["text"] for r in pii.redact(d).collect()}
    assert "a.b@c.org" not in clean[1] and "DE8937" not in clean[1] and clean[2] is None


def test_pii_is_linear_after_every_cue():
    finder = pii.Finder()
    for cue in ("account", "IBAN", "token", "token =", "Bearer", "://a:b@", "+1", "a@b.c", "1", "account no"):
        for filler in (" ", "1 ", "a", ".", "token=", "A1", " no"):
            began = time.perf_counter()
            finder.spans(cue + filler * (300_000 // len(filler)) + "x")
            assert time.perf_counter() - began < 5, (cue, filler)


def test_pii_secrets():
    found = lambda t: [t[a:b] for a, b in pii.Finder().spans(t)["secret"]]
    secret = "04dbebab91ab85687d33eeaaf9ac699e1188f962"
    assert found(f'x token = "{secret}" y') == found(f"TOKEN={secret}!") == found(f"api_key: '{secret}'") == found(f"Authorization: Bearer {secret},") == [secret]
    assert found("the token of friendship") == found("token = short1") == found("password: internationalization") == found("") == []


def test_chat_round_trip_and_branches(spark):
    odd = ["\\", "<|", "|>", "<|end|>\n", "\\<\\|", "<|>", "|\\>", "a<|assistant|>\nb", None, "", "é🙂<|end|>"]
    rows = [(c, k, "assistant" if k % 2 else "user", odd[(c + k) % len(odd)]) for c in range(12) for k in range(5)] + [(3, 1, "assistant", "again"), (None, 0, None, "x")]
    turns = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    out = chat.conversations(chat.linear(turns))
    got = {r["conv_id"]: r for r in chat.digests(out).collect()}
    for c in {r[0] for r in rows}:
        own = sorted(((k, r or "", t or "") for x, k, r, t in rows if x == c))
        assert got[c]["n_turns"] == len(own)
        assert got[c]["turns_sha256"] == hashlib.sha256("".join(f"{r}\n{t}\n" for _, r, t in own).encode()).hexdigest()
        learnt = "".join(t for _, r, t in own if r == "assistant")
        assert (got[c]["loss_chars"], got[c]["loss_sha256"]) == (len(learnt), hashlib.sha256(learnt.encode()).hexdigest())
    tree = spark.createDataFrame([(1, 1, None, "user", "q", 0.0), (1, 2, 1, "assistant", "bad", 1.0), (1, 3, 1, "assistant", "good", 5.0), (1, 4, 3, "user", "thanks", 2.0)], "tree long, node long, parent long, role string, text string, score double")
    best = chat.conversations(tree, best=1).collect()
    assert [r["leaf"] for r in best] == [4] and best[0]["n_turns"] == 3
    assert {r["leaf"] for r in chat.conversations(tree).collect()} == {2, 4}
    loop = spark.createDataFrame([(1, 1, 2, "u", "", 0.0), (1, 2, 1, "u", "", 0.0), (1, 3, 1, "u", "", 0.0)], tree.schema)
    with pytest.raises(ValueError):
        chat.paths(loop)
    assert chat.conversations(chat.linear(turns.limit(0))).count() == 0


def test_hmm_scores(docs, spark):
    rows = hmm.split(docs.select("doc_id", "text"))
    got = hmm.score(rows, rows.where("NOT held_out"), words=6, states=2, rounds=2)
    local = rows.collect()
    words = lambda t: (t or "").encode().lower().split()
    c = Counter(w for r in local if not r["held_out"] for w in [*words(r["text"]), None])
    n, v = sum(c.values()), len(c)
    want = sorted((len(words(r["text"])) + 1, sum(c[w] > 0 for w in [*words(r["text"]), None]), round(sum(np.log10((c[w] + 0.5) / (n + 0.5 * (v + 1))) for w in [*words(r["text"]), None]), 6)) for r in local)
    have = sorted((r["n_tokens"], r["n_known"], round(r["base_score"], 6)) for r in got.collect())
    assert have == want and {r["train_tokens"] for r in got.collect()} == {n}
    assert all(np.isfinite(r["score"]) for r in got.collect())


def test_hmm_forward_and_training(monkeypatch):
    rng = np.random.default_rng(0)
    m = hmm.Model(rng.dirichlet(np.ones(3)), rng.dirichlet(np.ones(3), 3), rng.dirichlet(np.ones(5), 3).T.copy())
    rows = [rng.integers(0, 5, n).astype(np.int32) for n in (1, 3, 6, 2500, 4096)]

    def paths(r):
        total = 0.0
        for k in np.ndindex(*[3] * len(r)):
            p = m.start[k[0]] * m.emit[r[0], k[0]]
            for t in range(1, len(r)):
                p *= m.move[k[t - 1], k[t]] * m.emit[r[t], k[t]]
            total += p
        return np.log(total)

    got = hmm.forward_log(rows, m)
    assert np.allclose(got[:3], [paths(r) for r in rows[:3]])
    s, v, e, log = hmm.expected(rows, m)
    assert np.isclose(log, got.sum()) and np.isclose(e.sum(), sum(map(len, rows))) and np.isclose(s.sum(), len(rows)) and np.isclose(v.sum(), sum(len(r) - 1 for r in rows))
    monkeypatch.setattr(hmm, "LONG", 2)  # the same by blocks
    monkeypatch.setattr(hmm, "BLOCK", 7)
    assert np.allclose(hmm.forward_log(rows, m), got)
    for x, y in zip(hmm.expected(rows, m), (s, v, e, log), strict=True):
        assert np.allclose(x, y)
    better = hmm.Model(s / s.sum(), v / v.sum(1, keepdims=True), e / e.sum(0))
    assert hmm.forward_log(rows, better).sum() >= log - 1e-9


def test_hmm_beats_the_unigram_on_held_out_rows(spark):
    """On whole small tables, where words of a language keep together."""
    docs = hmm.split(spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text"))
    got = hmm.score(docs, docs.where("NOT held_out")).where("held_out").groupBy().sum("score", "base_score").first()
    assert got[0] > got[1]


def test_hmm_starts_from_all_training_texts(spark, monkeypatch):
    """The start equals a mixture of unigrams over every text, of which there are more than a sample of 1,500 held."""
    r = random.Random(4)
    texts = [" ".join(r.choice("abcde" if i % 3 else "defgh") for _ in range(r.randint(0, 12))) for i in range(4000)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    a = hmm.alphabet(hmm.counted(docs, "text"), 8)
    monkeypatch.setattr(hmm, "MIXTURES", 1)
    got, history = hmm.train(docs, a, states=2, rounds=0)
    first, starts, emit = hmm.initial(a, 2), np.zeros(2), np.zeros((10, 2))
    for t in texts:
        symbols = [*(a.ids[w] for w in t.encode().split()), a.end]
        p = first.start * np.prod(first.emit[symbols], axis=0)
        starts += p / p.sum()
        for x in symbols:
            emit[x] += p / p.sum()
    want = hmm.fitted(starts, first.move, emit, hmm.shares(a), hmm.SHARE).emit
    assert np.allclose(got.emit, want) and history == []


def test_hmm_grids_are_bounded():
    rows = [np.zeros(n, np.int32) for n in [45] * 9999 + [20_000, 3000]]
    assert all(len(p) * max(map(len, p)) <= hmm.GRID or len(p) == 1 for _, p in hmm.grouped(rows))
    assert sorted(i for own, _ in hmm.grouped(rows) for i in own) == list(range(len(rows)))


def test_bpe_memory_is_bounded():
    b = bpe.RankArrayBPE(bpe.vocabulary(VOCABULARY))
    for i in range(12):
        b.encode_batch([" ".join(f"w{i}x{j}" for j in range(15_000)), "y" * 20_000])
        assert b.held <= bpe.REMEMBERED // 2
        assert not any(len(p) > bpe.BRIEF for m in (b.words, b.opening, b.spaced, b.odd) for p in {*m.young, *m.old})
    b.forget()
    assert b.held == 0 and not any(m.young or m.old for m in (b.words, b.opening, b.spaced, b.odd))


def test_bpe_equals_the_library(docs):
    tokenizers = pytest.importorskip("tokenizers")
    t = tokenizers.Tokenizer.from_file(VOCABULARY)
    b = bpe.RankArrayBPE(bpe.vocabulary(VOCABULARY))
    r = random.Random(5)
    parts = ["a", "Bé", " ", "  ", "\n", "\t", "'s", "'ll", "12", "<|endoftext|>", "!?", "\x1c", "\x85", "　", "x" * 70, "漢", "🙂", "naïve"]
    many = ["".join(r.choice(parts) for _ in range(r.randint(0, 30))) for _ in range(4000)] + ["", " ", "q" * 4000]
    want = t.encode_batch(many, add_special_tokens=False)
    assert all(x.tolist() == y.ids for x, y in zip(b.encode_batch(many), want, strict=True))
    assert all(b.decode(y.ids) == t.decode(y.ids, skip_special_tokens=False) for y in want)
    got = {x["doc_id"]: x for x in bpe.round_trip(docs, VOCABULARY).collect()}
    ids = t.encode(texts()[0], add_special_tokens=False).ids
    assert got[0]["ids_sha256"] == hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest() and got[0]["decoded_sha256"] == hashlib.sha256(texts()[0].encode()).hexdigest()
    assert bpe.decode(bpe.encode(docs, VOCABULARY), VOCABULARY).where("doc_id = 0").first()["text"] == texts()[0]


def test_neighbours_recall_and_ties(spark):
    rng = np.random.default_rng(7)
    x = rng.normal(size=(3000, 16))
    x[100:400] = x[100]  # copies
    rows = [(i, [float(v) for v in x[i]]) for i in range(3000)] + [(5000, None), (5001, [0.0] * 16), (5002, [float("nan")] * 16), (5003, [1.0, None] * 8), (5004, [1.0])]
    d = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    got = defaultdict(list)
    for r in neighbours.search(neighbours.build(d), d.where("vec_id % 100 = 0")).orderBy("query_id", "rank").collect():
        got[r["query_id"]].append((r["vec_id"], r["score"]))
    y = np.array(x, np.float32).astype(np.float64)
    hits = total = 0
    for q in range(0, 3000, 100):
        far = np.sqrt(((y - y[q]) ** 2).sum(1))
        want = [i for i in np.lexsort((np.arange(3000), far)) if i != q][:10]
        assert len(got[q]) == 10 and all(abs(far[i] - s) < 1e-9 for i, s in got[q])
        hits += len({i for i, _ in got[q]} & set(want))
        total += 10
    assert hits / total >= 0.9
    again = neighbours.search(neighbours.build(d.repartition(5)), d.where("vec_id % 100 = 0"))
    assert {(r["query_id"], r["rank"]): (r["vec_id"], round(r["score"], 9)) for r in again.collect()} == {(q, i): (v, round(s, 9)) for q, found in got.items() for i, (v, s) in enumerate(found, 1)}
    assert all(0 < r["lists_visited"] and 0 < r["rows_scanned"] < 2 * 3000 for r in again.collect())
    assert [i for i, _ in got[100]] == list(range(101, 111))
    few = d.where("vec_id < 4")
    assert neighbours.search(neighbours.build(few), few.where("vec_id = 0")).count() == 3
    none = d.limit(0)
    assert neighbours.search(neighbours.build(none), none).count() == 0


def test_neighbours_of_isolated_vectors_and_small_groups(spark, monkeypatch):
    rng = np.random.default_rng(5)
    x = [v for v in rng.standard_normal((1200, 8))]
    asked = []
    for g in range(1, 10):  # a vector alone and groups of 2 to 9 copies, far from all others
        far = 50.0 * g * np.eye(8)[g % 8] * (-1) ** g
        asked.append(len(x))
        x += [far] * g
    d = spark.createDataFrame([(i, [float(c) for c in v]) for i, v in enumerate(x)], "vec_id long, embedding array<double>")
    planted, fitted = np.array([x[i] for i in asked]), neighbours.balanced_centroids
    monkeypatch.setattr(neighbours, "LIST", 64)
    monkeypatch.setattr(neighbours, "balanced_centroids", lambda x, k: np.concatenate([fitted(x, k)[: k - len(planted)], planted]))
    got = defaultdict(list)
    index = neighbours.build(d)
    for r in neighbours.search(index, d.where(d.vec_id.isin(asked))).orderBy("query_id", "rank").collect():
        got[r["query_id"]].append(r["vec_id"])
    assert {i: len(got[i]) for i in asked} == {i: 10 for i in asked}
    for g, i in enumerate(asked, 1):
        assert got[i][: g - 1] == list(range(i + 1, i + g))


def water(sizes, weights, budget, cap):
    target, left, open_ = dict.fromkeys(sizes, 0.0), budget * sum(sizes.values()), set(sizes)
    while left > 1e-9 and open_:
        w = sum(weights[s] for s in open_)
        over = {s for s in open_ if target[s] + left * weights[s] / w > cap * sizes[s]}
        if not over:
            for s in open_:
                target[s] += left * weights[s] / w
            return target
        share = {s: left * weights[s] / w for s in open_}
        left = 0.0
        for s in list(open_):
            target[s] += share[s]
            if target[s] > cap * sizes[s]:
                left += target[s] - cap * sizes[s]
                target[s] = cap * sizes[s]
                open_.discard(s)
    return target


def test_mixing_targets(docs):
    got = mixing.mix(docs).collect()
    assert len(got) == docs.count()
    sizes, taken, target = Counter(), Counter(), {}
    for r in got:
        size, source = len(WS.findall(r["row"]["text"] or "")), r["row"]["source"]
        assert r["size"] == size and 0 <= r["taken"] <= 2 * size
        assert len(r["positions"]) == (-(-r["taken"] // size) if size else 0) and all(0 <= p <= 1 for p in r["positions"])
        sizes[source] += size
        taken[source] += r["taken"]
        target[source] = r["target"]
    order = sorted(sizes, key=lambda s: (s is None, s or ""))
    want = water(sizes, {s: (3.0, 1.0, 2.0)[i % 3] for i, s in enumerate(order)}, 1.5, 2.0)
    assert all(abs(target[s] - want[s]) < 1e-6 and abs(taken[s] - want[s]) <= 1 for s in sizes)
    assert mixing.copies(docs).count() == sum(len(r["positions"]) for r in got)
    assert mixing.mix(docs.limit(0)).count() == 0


def test_mixing_positions_by_integration(docs):
    """The integral of a source's schedule up to a position, by small steps, is the share of its demand at which the copy begins."""
    grid = np.linspace(0, 1, 100_001)
    done = []
    for knots in mixing.SCHEDULES:
        w = np.interp(grid, [t for t, _ in knots], [w for _, w in knots])
        area = np.concatenate([[0], np.cumsum((w[1:] + w[:-1]) / 2 * np.diff(grid))])
        done.append(area / area[-1])
    got = mixing.mix(docs).collect()
    order = sorted({r["row"]["source"] for r in got}, key=lambda s: (s is None, s or ""))
    for s in order:
        own = [r for r in got if r["row"]["source"] == s and r["taken"]]
        curve = done[order.index(s) % 3]
        line = sorted((p, r["size"]) for r in own for p in r["positions"])
        at = 0
        for p, size in line:
            assert abs(np.interp(p, grid, curve) - at / own[0]["target"]) < 1e-6
            at += size


def test_clashing_columns_keep_their_values(spark):
    rows = [(i, f"some words of text number {i}", "s", 7.0, i, True, "x", "y") for i in range(6)]
    d = spark.createDataFrame(rows, "doc_id long, text string, source string, target double, size long, held_out boolean, score string, row string")
    want = {tuple(r) for r in rows}
    assert {tuple(r["row"]) for r in mixing.mix(d).collect()} == want
    assert {tuple(r["row"]) for r in mixing.copies(d).collect()} <= want
    prior = quality.train(d, spark.createDataFrame([], "doc_id long, quality int"))
    assert {tuple(r) for r in quality.accepted(d, prior, 0.4).collect()} == want and quality.accepted(d, prior, 0.6).count() == 0


def test_quality_equals_brute_force():
    """Log-count ratios and the hinge-loss optimum, stated plainly."""
    r = random.Random(4)
    texts_ = [(" ".join(r.choice("abcd" if i % 2 else "bcde") * 3 for _ in range(6))).encode() for i in range(40)]
    rows, y = [quality.grams(t) for t in texts_], np.array([1 if i % 2 else -1 for i in range(40)])
    plain = lambda t: {t[i : i + n] for n in quality.SIZES for i in range(len(t) - n + 1)}
    hashed = {}
    for t, x in zip(texts_, rows, strict=True):
        for g in plain(t):
            code = (int.from_bytes(g, "big") + len(g)) * 0x9E3779B97F4A7C15 % 2**64 >> 64 - quality.BITS
            assert code in x
            hashed[g] = code
    ratio = quality.log_ratio(rows, y)
    for g, code in hashed.items():
        if sum(c == code for c in hashed.values()) == 1 and not any(code in quality.repeats(t) for t in texts_):
            up, down = (sum(g in plain(t) for t, v in zip(texts_, y, strict=True) if v == s) for s in (1, -1))
            assert abs(ratio[code] - np.log((up + 1) / (20 + 2)) + np.log((down + 1) / (20 + 2))) < 1e-5
    values = [ratio[x] / np.linalg.norm(ratio[x]) for x in rows]
    w, bias = quality.coordinate_descent(rows, values, y, np.full(40, 1.0), epochs=400)
    loss = lambda w, b: 0.5 * (w @ w + b * b) + sum(max(0.0, 1 - s * (w[x] @ v + b)) for x, v, s in zip(rows, values, y, strict=True))
    least, step = loss(w, bias), np.random.default_rng(0)
    used = np.unique(np.concatenate(rows))
    for _ in range(300):
        moved = w.copy()
        moved[used] += step.normal(size=len(used)) * 10.0 ** -step.integers(1, 5)
        assert loss(moved, bias + step.normal() * 1e-2) >= least - 1e-4


def test_token_attribution_of_fields_against_library_offsets(spark):
    tokenizers = pytest.importorskip("tokenizers")
    t = tokenizers.Tokenizer.from_file(VOCABULARY)
    r = random.Random(9)
    many = ["".join(r.choice(["ab ", "été", "漢", " 12", "\n", "hello world"]) for _ in range(r.randint(1, 25))) for _ in range(40)]
    rows = []
    for i, x in enumerate(many):
        cuts = sorted(r.randint(0, len(x)) for _ in range(4))
        rows.append((i, x, [("a", cuts[0], cuts[1]), ("b", cuts[2], cuts[3])]))
    kind = "doc_id long, text string, fields array<struct<name string, first_char int, end_char int>>"
    d = spark.createDataFrame(rows, kind)
    for rule in tokens.RULES:
        got = {(x["doc_id"], x["first_char"], x["end_char"], x["name"]): x["n_tokens"] for x in tokens.sections(d, VOCABULARY, rule, fields_col="fields").collect()}
        for (i, first, end, _), n in got.items():
            raw = [len(many[i][:k].encode()) for k in range(len(many[i]) + 1)]
            lengths = np.cumsum([0, *[len(bytes(b)) for b in token_bytes(t, many[i])]])
            sections = sorted({(a, e) for j, a, e, _ in got if j == i and e > a})
            total = 0.0
            for a, e in zip(lengths, lengths[1:], strict=False):
                inside = [max(0, min(e, raw[y]) - max(a, raw[x])) for x, y in sections]
                own = [k for k, v in enumerate(inside) if v]
                part = {"first": {own[0]: 1.0}, "last": {own[-1]: 1.0}, "largest": {int(np.argmax(inside)): 1.0}, "share": {k: inside[k] / (e - a) for k in own}}[rule]
                total += part.get(sections.index((first, end)), 0.0) if end > first else 0.0
            assert abs(total - n) < 1e-9, (i, rule, first, end)
    odd = [(0, "hello world", [("far", 50, 60), ("over", 6, 99)]), (1, "hello world", [("x", 0, 8), ("y", 3, 5), ("z", 4, 11)]), (2, None, [("x", 0, 3)]), (3, "ab", None), (4, "ab", [("n", None, None), None]), (5, "ab", [("neg", -5, -1), (None, 1, 0)])]
    out = tokens.sections(spark.createDataFrame(odd, kind), VOCABULARY, fields_col="fields").collect()
    for i, x, _ in odd:
        own = sorted((r["section"], r["first_char"], r["end_char"]) for r in out if r["doc_id"] == i)
        assert own[0][1] == 0 and own[-1][2] == len(x or "") and all(a[2] == b[1] for a, b in zip(own, own[1:], strict=False)) and all(a <= e for _, a, e in own)
        assert sum(r["n_tokens"] for r in out if r["doc_id"] == i) == (out and next(r["doc_tokens"] for r in out if r["doc_id"] == i))
    assert [(r["name"], r["first_char"], r["end_char"]) for r in out if r["doc_id"] == 1] == [("x", 0, 8), ("y", 8, 8), ("z", 8, 11)]


def token_bytes(t, text):
    letters = {c: b for b, c in enumerate(bpe.byte_letters())}
    return [bytes(letters[c] for c in t.id_to_token(i)) for i in t.encode(text, add_special_tokens=False).ids]


def test_components_with_a_hub(spark):
    """No task of the join on a hub's edges gets a row for each of them."""
    edges = spark.range(20_000).selectExpr("id + 1 AS a", "0L AS b").unionByName(spark.range(30_000, 30_050).selectExpr("id AS a", "id + 1 AS b"))
    got = {r["node"]: r["root"] for r in neardup.connected(edges.repartition(7)).collect()}
    assert got == {**dict.fromkeys(range(20_001), 0), **dict.fromkeys(range(30_000, 30_051), 30_000)}


def test_token_attribution(docs):
    for rule in tokens.RULES:
        rows = tokens.sections(docs, VOCABULARY, rule).collect()
        total = defaultdict(float)
        for r in rows:
            total[r["doc_id"]] += r["n_tokens"]
        assert all(abs(total[r["doc_id"]] - r["doc_tokens"]) < 1e-6 for r in rows)
    end, bounds = np.array([2, 5, 6]), np.array([0, 3, 6])
    assert tokens.attributed(end, bounds, "first")[0].tolist() == [2, 1]
    assert tokens.attributed(end, bounds, "last")[0].tolist() == [1, 2]
    assert tokens.attributed(end, bounds, "largest")[0].tolist() == [1, 2]
    assert np.allclose(tokens.attributed(end, bounds, "share")[0], [1 + 1 / 3, 2 / 3 + 1])


def brute_components(rows, k, percent=80):
    sets, root = {}, {i: i for i, _ in rows}
    for i, t in rows:
        w = (t or "").encode().lower().split()
        sets[i] = {tuple(w[j : j + k]) for j in range(max(1, len(w) - k + 1))} if w else set()
    find = lambda x: x if root[x] == x else find(root[x])
    ids = sorted(sets)
    for a in ids:
        for b in ids:
            if a < b and sets[a] and sets[b]:
                c = len(sets[a] & sets[b])
                if 100 * c >= percent * (len(sets[a]) + len(sets[b]) - c):
                    x, y = sorted((find(a), find(b)))
                    root[y] = x
    return {i: (len(sets[i]), find(i)) for i in ids}


@pytest.mark.parametrize(("words", "block", "crowd"), [(2, 4, 64), (5, None, 64), (2, 3, 2)])
def test_near_duplicates_equal_brute_force(spark, words, block, crowd, monkeypatch):
    r = random.Random(words)
    base = [[f"w{r.randint(0, 400)}" for _ in range(r.randint(1, 120))] for _ in range(25)]
    rows = []
    for i in range(220):
        t = list(base[i % 25])
        for _ in range(r.randint(0, max(1, len(t) // 12))):
            t[r.randrange(len(t))] = f"e{r.randint(0, 10**6)}"
        rows.append((i, " ".join(t)))
    rows += [(300, None), (301, ""), (302, "one"), (303, "ONE"), (304, rows[0][1])]
    if block:
        monkeypatch.setattr(neardup, "BLOCK_SETS", block)  # groups meet block by block
    monkeypatch.setattr(neardup, "CROWD", crowd)
    d = spark.createDataFrame([(*x, "clash") for x in rows], "doc_id long, text string, rep string").repartition(3)
    got = {x["doc_id"]: (x["n_shingles"], x["component_id"]) for x in neardup.components(d, words).collect()}
    assert got == brute_components(rows, words)
    assert neardup.components(d.limit(0), words).count() == 0


def test_near_duplicates_in_crowds_at_the_threshold(spark, monkeypatch):
    rows = []
    for i in (0, 1, 550, 899, 1169, 2147, 2516, 3993, 4680, 6107):  # exactly 0.8; from 550 on, missed by orders that shared 64 minhashes
        common = [f"w{i}x{j}" for j in range(8)]
        rows += [(2 * i, " ".join([*common, f"a{i}"])), (2 * i + 1, " ".join([*common, f"b{i}"]))]
    monkeypatch.setattr(neardup, "CROWD", 1)  # every region is a crowd
    got = neardup.components(spark.createDataFrame(rows, "doc_id long, text string"), 1).collect()
    assert [r["doc_id"] for r in got if r["component_id"] != r["doc_id"] // 2 * 2] == []


def test_near_duplicates_compare_every_text_of_a_repeated_id(spark):
    a, b = (" ".join(f"{c}{j}" for j in range(20)) for c in "ab")
    rows = [(5, a), (5, b), (7, a + " x"), (9, b + " y"), (11, "other words here")]
    got = {(r["doc_id"], r["component_id"]) for r in neardup.components(spark.createDataFrame(rows, "doc_id long, text string"), 2).collect()}
    assert got == {(5, 5), (7, 5), (9, 5), (11, 11)}


def test_near_duplicates_with_shared_passages_equal_brute_force(spark, monkeypatch):
    rng = random.Random(11)
    passage = " ".join(f"p{i}" for i in range(40))
    rows = []
    for i in range(60):
        own = [f"o{i}x{j}" for j in range(30)]
        rows.append((len(rows), " ".join([passage, *own])))
        if i % 3 == 0:
            own[rng.randrange(30)] = "changed"
            rows.append((len(rows), " ".join([passage, *own])))
    monkeypatch.setattr(neardup, "CROWD", 8)
    want = brute_components(rows, 2)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in neardup.components(spark.createDataFrame(rows, "doc_id long, text string"), 2).collect()}
    assert got == want


def test_near_duplicates_at_the_edges_of_tasks_are_no_crowd(spark, monkeypatch):
    r = random.Random(3)
    rows = []
    for i in range(40):
        own = [f"w{r.randint(0, 10**9)}" for _ in range(40)]
        rows += [(3 * i + k, " ".join([*own, *["x"] * k])) for k in range(3)]
    want = brute_components(rows, 2)
    d = spark.createDataFrame(rows, "doc_id long, text string")
    orders = []
    deeply = neardup.ordered_deeply
    monkeypatch.setattr(neardup, "ordered_deeply", lambda *a: orders.append(1) or deeply(*a))
    for crowd in (64, 2):  # regions of three are no crowd, then all are
        monkeypatch.setattr(neardup, "CROWD", crowd)
        assert {x["doc_id"]: (x["n_shingles"], x["component_id"]) for x in neardup.components(d, 2).collect()} == want
        assert len(orders) == (crowd == 2)
