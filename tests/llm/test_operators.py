"""Operators on small tables: brute force, round trips, and the defined edge cases."""

import hashlib
import random
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from evenpick.llm import chat, mix, neardup, neighbours, pieces, pseudonym, quality, repeats, topk, toxic
from evenpick.llm.labelled import held_out
from evenpick.llm.queries import PIECE_MODEL

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
WORD = re.compile(r"[^\x20\x09-\x0D]+")


def docs_of(spark, texts, sources=None):
    return spark.createDataFrame([(i, t, "en", sources[i] if sources else f"s{i % 3}", len(t or "")) for i, t in enumerate(texts)], DOCS)


def odd_texts():
    r = random.Random(5)
    prose = lambda n: " ".join(r.choice(["alpha", "beta", "gamma", "delta", "epsilon", "zeta"]) + str(r.randrange(40)) for _ in range(n))
    base = prose(120)
    return [None, "", " ", "\n\t", "one", base, base, base + " tail", "A " * 5000, prose(4000), prose(30), "é" * 300, prose(3), "x y 　 z"]


@pytest.fixture(scope="module")
def odd(spark):
    return docs_of(spark, odd_texts(), ["a", None, "b", "a", None, "c", "c", "a", "b", "b", "a", "d", "d", "d"])


# -- mixing ---------------------------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("seed", range(60))
def test_fit_lengths_is_an_optimal_bounded_knapsack(seed):
    r = random.Random(seed)
    stock = {r.randrange(1, 50): r.randrange(1, 4) for _ in range(r.randrange(1, 9))}
    budget = r.randrange(0, sum(n * c for n, c in stock.items()) + 1)
    reach = {0}
    for n, c in stock.items():
        reach = {x + n * j for x in reach for j in range(c + 1)}
    got = mix.fit_lengths(list(stock), list(stock.values()), budget)
    assert all(0 <= got[n] <= c for n, c in stock.items())
    assert sum(n * k for n, k in got.items()) == max(x for x in reach if x <= budget)
    cut = mix.fit_lengths(list(stock), list(stock.values()), budget, span=20)
    assert all(0 <= cut[n] <= c for n, c in stock.items()) and sum(n * k for n, k in cut.items()) <= budget


def targets(sizes):
    names = sorted(n for n in sizes if n is not None) + ([None] if None in sizes else [])
    weight = {n: (5, 2, 1)[i % 3] for i, n in enumerate(names)}
    total, out, open_ = sum(sizes.values()), {}, list(names)
    while True:
        left, w = total - sum(out.values()), sum(weight[n] for n in open_)
        over = [n for n in open_ if left * weight[n] / w > 3 * sizes[n] + 1e-9] if w else []
        if not over:
            return out | {n: left * weight[n] / w for n in open_}
        out |= {n: 3.0 * sizes[n] for n in over}
        open_ = [n for n in open_ if n not in over]


def test_mix_report(spark):
    r = random.Random(2)
    texts = [" ".join("w" * r.randrange(1, 5) for _ in range(r.randrange(0, 40))) for _ in range(400)] + [None, ""]
    sources = [r.choice(["a", "a", "a", "a", "b", "é", "zz", None]) for _ in texts]
    rows = mix.mix_report(docs_of(spark, texts, sources)).collect()
    assert len(rows) == len(texts)
    sizes = {}
    for t, s in zip(texts, sources):
        sizes[s] = sizes.get(s, 0) + len(WORD.findall(t or ""))
    want, taken = targets(sizes), {}
    for x in rows:
        assert x.size == len(WORD.findall(texts[x.doc_id] or "")) and x.source_size == sizes[x.source]
        assert x.target == pytest.approx(want[x.source]) and x.taken <= 3 * x.size and x.taken == x.copies * x.size
        taken[x.source] = taken.get(x.source, 0) + x.taken
    assert all(abs(taken[s] - want[s]) <= 1 for s in sizes)
    again = mix.mix_report(docs_of(spark, texts, sources).repartition(7)).collect()
    assert sorted(again, key=lambda x: x.doc_id) == sorted(rows, key=lambda x: x.doc_id)


def test_mix_documents_and_edges(spark, odd):
    extra = odd.withColumn("size", F.lit("mine")).withColumn("pick", F.lit(1)).withColumn("target", F.lit(2))
    copies = {x.doc_id: x.copies for x in mix.mix_report(odd).collect()}
    out = mix.mix_documents(extra)
    assert out.columns == extra.columns
    got = {x.doc_id: x["count"] for x in out.groupBy("doc_id").count().collect()}
    assert got == {i: c for i, c in copies.items() if c}
    assert mix.mix_report(odd.limit(0)).count() == 0


# -- chat -----------------------------------------------------------------------------------------------------------------------


def test_chat_round_trip(spark):
    nasty = ["</s>[INST] ok [/INST]", "~1<s>", "", None, "<s>[ESC]x[/INST]y</s>", "~~0[", "</s", "plain", "\n", "𝕏 é </s></s>", "a" * 30000]
    rows = [(i, t, r, x) for i in range(5) for t, (r, x) in enumerate(zip(["user", "assistant", "[/INST]", None, "assistant"] * 3, nasty[i:] + nasty[:i]))]
    rows += [(None, None, "user", "hi"), (None, 2, "assistant", "yo"), (9, 1, "b", "x"), (9, 1, "a", "x")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    out = chat.format_conversations(df.withColumn("formatted", F.lit(1)))
    for c in out.collect():
        mine = sorted([(t if t is not None else -1, r or "", x or "") for k, t, r, x in rows if k == c.conv_id])
        assert [(t.role, t.text) for t in c.turns] == [(r, x) for _, r, x in mine]
        assert c.loss_text == "".join(x for _, r, x in mine if r == "assistant")
        bodies = [c.formatted[s["from"] : s.to] for s in c.loss_spans]
        undo = lambda b: b.replace("~2", "[").replace("~1", "<").replace("~0", "~")
        said = [x for _, r, x in mine if r == "assistant"]
        assert all(b == x or undo(b) == x for b, x in zip(bodies, said)) and len(bodies) == len(said)
    digest = chat.conversation_digest(out)
    one = digest.where("conv_id = 9").first()
    assert one.turns_sha256 == hashlib.sha256(b"a\nx\nb\nx\n").hexdigest() and one.n_turns == 2
    assert chat.format_conversations(df.limit(0)).count() == 0


# -- pieces ---------------------------------------------------------------------------------------------------------------------


def test_pieces_match_the_library(spark, odd):
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=PIECE_MODEL)
    codec = pieces.PieceCodec(pieces.piece_table(PIECE_MODEL))
    r = random.Random(1)
    texts = odd_texts()[1:] + ["".join(r.choice("ab the-▁ \n<>1éñ日Ж.,;𝕏") for _ in range(r.randrange(1, 60))) for _ in range(3000)] + [" " * 70 + "x" + " " * 33, "a" * 4000, "<s> </s> <0x0A>"]
    for t in texts:
        assert codec.encode(t) == sp.encode(t)
    rows = {x.doc_id: x for x in pieces.piece_digest(odd, PIECE_MODEL).collect()}
    for i, t in enumerate(odd_texts()):
        ids = sp.encode(t or "")
        assert (rows[i].n_tokens, rows[i].ids_sha256) == (len(ids), hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest())
        assert rows[i].decoded_sha256 == hashlib.sha256((sp.decode(ids) if ids else "").encode()).hexdigest()
    enc = pieces.encode_documents(odd.withColumn("ids", F.lit("clash")), PIECE_MODEL)
    back = pieces.decode_ids(enc, PIECE_MODEL).collect()
    assert all(x.decoded == (x.text or "").replace("▁", " ") for x in back) and len(back) == len(odd_texts())
    assert pieces.piece_digest(odd.limit(0), PIECE_MODEL).count() == 0


def test_last_tokens_are_unique_per_prefix():
    codec = pieces.PieceCodec(pieces.piece_table(PIECE_MODEL))
    for word in (" international", " thanonontioniner", " 2024-01-01"):
        last = codec.last_tokens(word)
        for i in range(1, len(word) + 1):
            assert codec.table.merge(word[:i])[0][-1] == last[i]


# -- repeats --------------------------------------------------------------------------------------------------------------------


def brute_repeats(texts, length=200):
    seen, out = {}, []
    for t in texts:
        b = (t or "").encode()
        for j in range(len(b) - length + 1):
            seen[b[j : j + length]] = seen.get(b[j : j + length], 0) + 1
    for t in texts:
        b = (t or "").encode()
        m = np.zeros(len(b), bool)
        for j in range(len(b) - length + 1):
            if seen[b[j : j + length]] > 1:
                m[j : j + length] = True
        kept = bytes(np.frombuffer(b, np.uint8)[~m])
        out.append((len(b), int(m.sum()), int((np.diff(np.concatenate([[0], m.astype(int)])) == 1).sum()), hashlib.sha256(kept).hexdigest()))
    return out


def test_repeats_match_brute_force(spark):
    r = random.Random(3)
    noise = lambda n: "".join(r.choice("abcdefgh é") for _ in range(n))
    a, b = noise(700), noise(260)
    texts = [*odd_texts()[:9], a, a[:300] + noise(5) + a[300:], noise(90) + b + noise(80), b, b[:199], b[:200], "ab" * 400, "c" * 199, "c" * 200, "c" * 201, noise(400) + a[100:420] + noise(30) + a[90:330], a, "c" * 600]
    got = {x.doc_id: (x.n_bytes, x.n_removed, x.n_spans, x.kept_sha256) for x in repeats.remove_repeats(docs_of(spark, texts)).collect()}
    assert [got[i] for i in range(len(texts))] == brute_repeats(texts)
    assert repeats.remove_repeats(docs_of(spark, texts).limit(0)).count() == 0
    few = docs_of(spark, ["short", None])
    assert {x.n_removed for x in repeats.remove_repeats(few.withColumn("tid", F.lit(1))).collect()} == {0}


def test_crowded_anchor_groups_are_cut_without_loss(spark, monkeypatch):
    """A line of 64 to 199 bytes in many surroundings: its group is cut by place, then window by window."""
    monkeypatch.setattr(repeats, "GROUP", 3)
    r = random.Random(9)
    noise = lambda n: "".join(r.choice("abcdefgh ") for _ in range(n))
    lines, texts = [noise(n) for n in (70, 120, 190, 198)], []
    for line in lines:
        near = [noise(150) for _ in range(6)]
        texts += [noise(r.randrange(90, 160)) + r.choice(near)[-r.choice([1, 5, 60, 150]) :] + line + r.choice(near)[: r.choice([1, 4, 70, 150])] + noise(r.randrange(90, 160)) for _ in range(25)]
    got = {x.doc_id: (x.n_bytes, x.n_removed, x.n_spans, x.kept_sha256) for x in repeats.remove_repeats(docs_of(spark, texts)).collect()}
    want = brute_repeats(texts)
    assert [got[i] for i in range(len(texts))] == want and sum(w[1] > 0 for w in want) > 20


def test_anchors_of_pieces_cover_the_same_windows():
    r = random.Random(2)
    texts = ["".join(r.choice("ab c") for _ in range(n)) for n in (500, 10, 3000, 199, 200, 900)]
    buf, off = repeats.utf8_buffer(pa.array(texts))
    windows = lambda *a: sorted((int(d), int(p), int(h), w) for d, p, h, f, z in zip(*repeats.anchors(buf, off, 200, 64, *a)) for w in range(f, z + 1))
    assert windows() == windows(300) == windows(1)


def test_merged_transform_equals_the_transform_of_all():
    r = random.Random(4)
    for letters in (b"ab", b"abcdefgh", b"a"):
        segs = [bytes(r.choice(letters) for _ in range(r.randrange(1, 90))) for _ in range(14)]
        segs += [segs[0][:40], segs[1], segs[1]]
        one = repeats.Transform(segs)
        merge = repeats.Interleave([repeats.Transform(segs[i : i + 5]) for i in range(0, len(segs), 5)])
        row, common = merge.merged()
        assert (merge.head[row] == one.head).all() and (merge.before[row] == one.before)[~one.head].all()
        for a, b in zip(merge.origin[:-1], merge.origin[1:]):
            assert (np.diff(row[(row >= a) & (row < b)]) > 0).all()
        suffixes = sorted((s[j:] + b"", k, j) for k, s in enumerate(segs) for j in range(len(s) + 1))
        shared = lambda a, b: next((i for i, (x, y) in enumerate(zip(a, b)) if x != y), min(len(a), len(b)))
        assert common.tolist() == [0] + [shared(a[0], b[0]) for a, b in zip(suffixes, suffixes[1:])]


def test_merged_interleave_equals_sorted_suffixes():
    r = random.Random(4)
    segs = [bytes(r.choice(b"ab") for _ in range(r.randrange(30, 90))) for _ in range(12)]
    segs += [segs[0][5:60], segs[1]]
    got = repeats.repeated_windows(segs, 24, shards=3)
    count = {}
    for s in segs:
        for j in range(len(s) - 23):
            count[s[j : j + 24]] = count.get(s[j : j + 24], 0) + 1
    for s, ranges in zip(segs, got):
        hit = {j for a, z in zip(ranges[::2], ranges[1::2]) for j in range(a, z + 1)}
        assert hit == {j for j in range(len(s) - 23) if count[s[j : j + 24]] > 1}


# -- pseudonyms -----------------------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("n", [1, 2, 3, 10, 97, 1000, 4096])
def test_feistel_is_a_bijection_without_fixed_points(n):
    f = pseudonym.Feistel(b"key", "t", n)
    out = [f.shift(x) for x in range(n)]
    assert sorted(out) == list(range(n)) and all(f.decrypt(f.encrypt(x)) == x for x in range(n))
    assert n == 1 or all(a != b for a, b in enumerate(out))
    assert [f.shift(y, -1) for y in out] == list(range(n))


def test_pseudonyms(spark, odd):
    text = 'pay 4845168114407329 or 4845-1681-1440-7329, not 9807915762804490; call +1 (017) 555-7713; 97.51.17.173. 300.1.1.1 v4.0. token = "04dbebab91ab85687d33eeaaf9ac699e1188f962" und.34@mail7.example.com### 2024-02-29 2023-02-29 123-45-6789 666-12-1234'
    on, off = pseudonym.Pseudonyms(b"k"), pseudonym.Pseudonyms(b"k", by=-1)
    new, counts = on.replace(text)
    assert counts == {"card": 2, "phone": 1, "ip": 1, "secret": 1, "email": 1, "date": 1, "ssn": 1}
    assert off.replace(new)[0] == text
    for kept in ("9807915762804490", "300.1.1.1", "v4.0.", "2023-02-29", "666-12-1234", "@mail7.example.com###"):
        assert kept in new
    for gone in ("4845168114407329", "4845-1681-1440-7329", "555-7713", "97.51.17.173", "04dbebab", "und.34@", "2024-02-29", "123-45-6789"):
        assert gone not in new
    cards = re.findall(r"\d{16}|\d{4}-\d{4}-\d{4}-\d{4}", new)
    assert cards[0] == cards[1].replace("-", "") and pseudonym.luhn_digit(cards[0][:-1]) == cards[0][-1]
    beside = on.replace("4845168114407329 12 and 7536784127813050 4845168114407329, 4845 1681 1440 7329 5")[0]
    assert "4845" not in beside and "7536784127813050" not in beside and beside.endswith(" 5") and " 12 and " in beside
    assert pseudonym.Pseudonyms(b"other").replace(text)[0] != new
    out = {x.doc_id: x for x in pseudonym.pseudonymise(odd.withColumn("counts", F.lit(1)), "k", counts="counts").collect()}
    assert all(out[i].text == t for i, t in enumerate(odd_texts())) and out[0].text is None
    assert pseudonym.pseudonymise(odd.limit(0), "k").count() == 0


def test_cards_behind_other_numbers():
    on, off = pseudonym.Pseudonyms(b"k"), pseudonym.Pseudonyms(b"k", by=-1)
    card = "4845 1681 1440 7329"
    alone = on.replace(card)[0]
    assert alone != card
    for front in ("2024 ", "12345678 ", "2024 17 ", "12345678 2024 ", "9807915762804490 ", "2024-02-30 ", "12-"):
        for tail in ("", " 5", " 2024", ", 12"):
            new, counts = on.replace(front + card + tail)
            if "-" not in front:
                assert counts == {"card": 1} and new == front + alone + tail, (front, tail)
            assert "4845 1681" not in new
    text = f"2024 {card} 2024-02-29 4845168114407329 123-45-6789"
    new, counts = on.replace(text)
    assert counts == {"card": 2, "date": 1, "ssn": 1} and off.replace(new)[0] == text
    assert new.startswith(f"2024 {alone} ") and alone.replace(" ", "") == new.split()[6]
    call = on.replace(f"+1 (017) 555-7713 {card}")[0]
    assert call.endswith(alone) and call.startswith(on.replace("+1 (017) 555-7713")[0])
    assert on.replace("7 " * 50_000)[0] == "7 " * 50_000


def test_dates_before_times_and_month_first():
    on, off = pseudonym.Pseudonyms(b"k"), pseudonym.Pseudonyms(b"k", by=-1)
    plain = on.replace("2024-02-29")[0]
    for tail in ("T10:00:00", "T10:00:00.123Z", "t10", "T1000+02:00", " 10:00"):
        assert on.replace("2024-02-29" + tail)[0] == plain + tail
    assert on.replace("2023-02-29T10:00")[0] == "2023-02-29T10:00" and on.replace("2024-02-29Total")[0] == "2024-02-29Total"
    for v in ("12/25/2024", "02.29.2024", "12/05/2024", "31/01/1999", "01/13/1900", "12/31/2099"):
        new, counts = on.replace(f"on {v}.")
        assert counts == {"date": 1} and v not in new and off.replace(new)[0] == f"on {v}."
        assert (int(v[:2]) > 12, int(v[3:5]) > 12) != (False, True) or int(new[6:8]) > 12
    assert on.replace("13/13/2024 02/30/2024 25/25/2024")[1] == {}
    late = pseudonym._late_days()
    assert len({on.date((lambda d: f"{d.month:02d}/{d.day:02d}/{d.year}")(pseudonym.dt.date.fromordinal(pseudonym._EPOCH + i))) for i in late[:2000]}) == 2000


def test_phones_before_other_numbers():
    on, off = pseudonym.Pseudonyms(b"k"), pseudonym.Pseudonyms(b"k", by=-1)
    for call in ("+1 (017) 555-7713", "+1 017 555 7713", "+44 20 7946 0958"):
        alone = on.replace(call)[0]
        assert alone != call
        for tail in (" 2021", " 2021 2022", " 20 30 40 50", " 2021-02-03", " 97.51.17.173", " 123-45-6789"):
            text = call + tail
            new = on.replace(text)[0]
            assert new.startswith(alone + " ") and off.replace(new)[0] == text
            assert (new == alone + tail) == (tail.count("-") + tail.count(".") == 0)
    many = "+49 30 1234 5678 9012 3456"
    new, counts = on.replace(many)
    assert counts == {"phone": 1} and "1234" not in new and off.replace(new)[0] == many
    new, counts = on.replace("+49 (30) 1234-5678 2021-02-03")
    assert counts == {"phone": 1, "date": 1} and "2021-02-03" not in new


# -- near duplicates ------------------------------------------------------------------------------------------------------------


def brute_groups(texts, percent=85):
    sets = []
    for t in texts:
        w = WORD.findall(re.sub("[A-Z]+", lambda m: m[0].lower(), t or ""))
        sets.append({tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set()))
    root = list(range(len(texts)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(len(sets)):
        for j in range(i):
            both = len(sets[i] & sets[j])
            if both and 100 * both >= percent * (len(sets[i]) + len(sets[j]) - both):
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    return [len(s) for s in sets], [find(i) for i in range(len(sets))]


@pytest.mark.parametrize("percent", [80, 85])
def test_near_duplicates_match_brute_force(spark, percent):
    r = random.Random(7)
    texts = list(odd_texts())
    for size in (3, 5, 8, 12, 20, 45, 90, 200, 600):
        for _ in range(4):
            base = [f"w{r.randrange(5000)}" for _ in range(size)]
            for edits in (0, 0, 1, 1, 2, size // 40, size // 30, size // 25):
                w = list(base)
                for _ in range(edits):
                    w[r.randrange(size)] = f"e{r.randrange(9999)}"
                texts.append(" ".join(w) if r.random() < 0.5 else "  ".join(w).upper())
    sizes, groups = brute_groups(texts, percent)
    got = {x.doc_id: x for x in neardup.near_duplicates(docs_of(spark, texts), percent).collect()}
    assert [got[i].n_shingles for i in range(len(texts))] == sizes
    assert [got[i].component_id for i in range(len(texts))] == groups
    assert all(got[i].kept == (groups[i] == i) for i in range(len(texts)))


def test_near_duplicate_edges(spark):
    rows = [(None, "a b c d e f"), (1, "a b c d e f"), (1, "a b c d e f"), (2, None), (3, None), (4, "")]
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("sketch", F.lit(1)).withColumn("key", F.lit(1))
    got = sorted((x.doc_id or -1, x.component_id, x.kept) for x in neardup.near_duplicates(df).collect())
    assert got == [(-1, None, False), (1, 1, True), (1, 1, True), (2, 2, True), (3, 3, True), (4, 4, True)]
    assert neardup.near_duplicates(df.limit(0)).count() == 0


def test_estimates_follow_jaccard():
    rng = np.random.default_rng(0)
    for share in (0.5, 0.85, 0.95):
        a = np.unique(rng.integers(0, 2**63, 4000).astype(np.uint64) << np.uint64(1))
        k = int(len(a) * 2 * share / (1 + share))
        b = np.unique(np.concatenate([rng.permutation(a)[:k], rng.integers(0, 2**63, len(a) - k).astype(np.uint64) << np.uint64(1)]))
        e = neardup.estimate_jaccard(neardup.hyper_sketch(a), neardup.hyper_sketch(b))
        true = len(np.intersect1d(a, b)) / len(np.union1d(a, b))
        assert abs(float(e) - true) < 0.15


# -- vectors --------------------------------------------------------------------------------------------------------------------


def vectors(spark, n=400, dim=16, seed=0):
    rng = np.random.default_rng(seed)
    x = rng.normal(size=(n, dim))
    x[7] = x[3]
    rows = [(i, [float(v) for v in r]) for i, r in enumerate(x)]
    rows += [(1000, None), (1020, [0.0] * dim), (1040, [float("nan")] * dim), (1060, [1.0, None] + [0.0] * (dim - 2)), (None, [1.0] * dim), (1100, [float("inf")] * dim)]
    return spark.createDataFrame(rows, "vec_id long, embedding array<double>").withColumn("rank", F.lit(1)), x


def test_nearest_recall_order_and_edges(spark):
    df, x = vectors(spark)
    v = neighbours.valid_vectors(df, "vec_id", "embedding")
    assert v.count() == 400
    rows = neighbours.nearest(v, v.where("id % 20 = 0"), 5).collect()
    u = x / np.linalg.norm(x, axis=1)[:, None]
    hit = total = 0
    for q in range(0, 400, 20):
        s = u @ u[q]
        s[q] = -9
        best = set(np.lexsort((np.arange(400), -s))[:5].tolist())
        mine = sorted((r for r in rows if r.query_id == q), key=lambda r: r["rank"])
        assert [r["rank"] for r in mine] == list(range(1, len(mine) + 1))
        assert all(abs(r.score - s[r.vec_id]) < 1e-12 for r in mine)
        assert [(-r.score, r.vec_id) for r in mine] == sorted((-r.score, r.vec_id) for r in mine)
        hit, total = hit + len(best & {r.vec_id for r in mine}), total + 5
    assert hit / total >= 0.9
    assert neighbours.nearest(v.limit(0), v.limit(0)).count() == 0


def test_nearest_gives_all_that_there_are(spark, monkeypatch):
    rng = np.random.default_rng(1)
    rows = [(d * 100 + i, [float(v) for v in x]) for d, n in ((3, 3), (5, 6), (8, 2), (9, 1)) for i, x in enumerate(rng.normal(size=(n, d)))]
    near = rng.normal(size=16) + 0.01 * rng.normal(size=(60, 16))
    rows += [(2000 + i, [float(v) for v in x]) for i, x in enumerate(near)] + [(3000, [-float(v) for v in near[0]])]
    monkeypatch.setattr(neighbours, "CELL_ROWS", 4)
    v = spark.createDataFrame(rows, "id long, vec array<double>")
    got = {}
    for r in neighbours.nearest(v, v, 5).orderBy("query_id", "rank").collect():
        got.setdefault(r.query_id, []).append((r.vec_id, r.score))
    for q, x in rows:
        others = [(i, float(np.dot(x, y) / np.linalg.norm(x) / np.linalg.norm(y))) for i, y in rows if i != q and len(y) == len(x)]
        mine = got.get(q, [])
        assert len(mine) == min(5, len(others))
        if len(others) <= 5 or q == 3000:
            assert [i for i, _ in mine] == [i for i, _ in sorted(others, key=lambda p: (-p[1], p[0]))[:5]]
    twins = spark.createDataFrame([(1, [1.0, 0.0])] + [(2, [1.0, 0.1])] * 6 + [(i, [0.0, float(i)]) for i in (3, 4, 5, 6)], "id long, vec array<double>")
    monkeypatch.setattr(neighbours, "CELL_ROWS", 100)
    assert [r.vec_id for r in neighbours.nearest(twins, twins.where("id = 1"), 5).orderBy("rank").collect()] == [2, 3, 4, 5, 6]


def test_top_k_is_exact(spark):
    df, x = vectors(spark, 700, 12, 3)
    v = topk.integer_vectors(df, "vec_id", "embedding")
    rows = topk.exact_top_k(v, v.where("id % 20 = 0"), 20).collect()
    z = np.floor(64 * np.vstack([x, np.zeros((1, 12))])).astype(np.int64)
    ids = np.array([*range(700), 1020])
    for q in (i for i in ids if i % 20 == 0):
        s = z @ z[list(ids).index(q)]
        o = [i for i in np.lexsort((ids, -s)) if ids[i] != q][:20]
        mine = sorted((r for r in rows if r.query_id == q), key=lambda r: r["rank"])
        assert [(r.vec_id, r.score) for r in mine] == [(ids[i], s[i]) for i in o]
    small = topk.exact_top_k(v, v.where("id % 20 = 0"), 20, block_rows=100, block_queries=10).collect()
    assert sorted(small) == sorted(rows)
    for n in (1, 4, 5):
        some = v.where(F.col("id") < n)
        assert topk.exact_top_k(some, some, 20).groupBy("query_id").count().where(F.col("count") != n - 1).count() == 0
        assert topk.exact_top_k(some, some, 20).count() == n * (n - 1)
    few = v.limit(3)
    assert topk.exact_top_k(few, few, 20).groupBy("query_id").count().where("count <> 2").count() == 0
    assert topk.exact_top_k(v.limit(0), v.limit(0)).count() == 0


def check_cover(x, node, depth=0):
    """Levels, covering, separation and nesting of a cover tree; returns its rows."""
    assert (np.linalg.norm(x[node.rows] - node.center, axis=1) <= node.radius).all()
    assert node.level is None or 2.0 ** (node.level - 1) < node.radius <= 2.0**node.level
    if node.children:
        half = 2.0 ** (node.level - 1)
        assert (node.children[0].center == node.center).all() and all(c.radius <= half * (1 + 1e-9) for c in node.children)
        gaps = np.linalg.norm(node.centers[:, None] - node.centers[None], axis=2) + np.eye(len(node.children)) * 9 * half
        assert gaps.min() > half
        assert sorted(np.concatenate([check_cover(x, c, depth + 1) for c in node.children]).tolist()) == sorted(node.rows.tolist())
    return node.rows


def test_cover_tree_invariants():
    rng = np.random.default_rng(5)
    flat, deep = rng.normal(0, 1, (800, 2)) * 100, rng.normal(0, 300, (20, 8))[rng.integers(0, 20, 1500)] + rng.normal(0, 2, (1500, 8))
    for x in (flat, deep, np.ones((300, 3)), deep[:1]):
        root = topk.cover_tree(x)
        assert len(check_cover(x, root)) == len(x)
    assert topk.cover_tree(flat).children and topk.cover_tree(deep).children


def test_dual_tree_prunes_clusters():
    rng = np.random.default_rng(0)
    x = np.floor(rng.normal(0, 300, (30, 8))[rng.integers(0, 30, 4000)] + rng.normal(0, 2, (4000, 8))).astype(np.int64)
    ids = np.arange(4000)
    d = topk.DualSearch(ids[::40], x[::40], ids, x, 10)
    assert d.pruned > d.compared / 2
    again = topk.DualSearch(ids[::40], x[::40], ids, x, 10, floor=d.score[:, -1])
    assert (again.score == d.score).all() and (again.found == d.found).all() and again.compared <= d.compared
    big = topk.DualSearch(ids[:5], x[:5] * 10**7, ids[:50], x[:50] * 10**7, 3)
    s = (x[:5].astype(object) * 10**7) @ (x[:50].astype(object) * 10**7).T
    for i in range(5):
        want = sorted((j for j in range(50) if j != i), key=lambda j: (-s[i, j], j))[:3]
        assert big.found[i].tolist() == want


# -- classifiers ----------------------------------------------------------------------------------------------------------------


def accuracy(rows, labels, held):
    got = [(r.predicted, labels[r.doc_id]) for r in rows if r.doc_id in labels and r.held_out == held]
    return sum(a == b for a, b in got) / len(got)


@pytest.mark.parametrize("kind", ["quality", "toxic"])
def test_held_out_accuracy(spark, kind):
    sf = "/root/testdata/sf0.1"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    known = {r.doc_id: r[kind] for r in labels.collect()}
    if kind == "quality":
        rows = quality.score_ids(docs, quality.train_quality(docs, labels), 0.3).collect()
    else:
        rows = toxic.score_toxicity(docs, toxic.train_toxicity(docs, labels)).collect()
    assert len(rows) == docs.count() and all(0 <= r.score <= 1 for r in rows)
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in rows)
    assert accuracy(rows, known, True) > 0.97
    if kind == "toxic":
        held = [(r.predicted, known[r.doc_id]) for r in rows if r.held_out and known.get(r.doc_id) is not None]
        hit = sum(p and t for p, t in held)
        recall, precision = hit / sum(t for _, t in held), hit / sum(p for p, _ in held)
        print("recall", recall, "precision", precision)
        assert recall > 0.9 and precision > 0.9


def test_classifier_edges(spark, odd):
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    for rows in (quality.score_ids(odd, quality.train_quality(odd, none), 0.3).collect(), toxic.score_toxicity(odd, toxic.train_toxicity(odd, none)).collect()):
        assert len(rows) == len(odd_texts()) and all(r.score == pytest.approx(0.5) for r in rows)
    some = spark.createDataFrame([(i, i % 2, None) for i in range(14)] + [(None, 1, 1)], "doc_id long, quality int, toxic int")
    model = quality.train_quality(odd, some)
    out = quality.score_quality(odd.withColumn("quality_score", F.lit("x")), model)
    assert out.count() == len(odd_texts()) and dict(out.dtypes)["quality_score"] == "double"
    assert quality.score_ids(odd.limit(0), model, 0.3).count() == 0
    ids = spark.createDataFrame([(None,), (0,)], "doc_id long").select(held_out(F.col("doc_id")).alias("h")).collect()
    assert [r.h for r in ids] == [True, zlib.crc32(b"0") % 5 == 0]


def edit_distance(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        new = [i]
        for j, y in enumerate(b, 1):
            new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (x != y)))
        row = new
    return row[-1]


def near_terms(terms, word):
    """(edits, term numbers) of the nearest terms that allow so many edits, by brute force."""
    found = [(d, i) for i, t in enumerate(terms) if (d := edit_distance(word, t)) <= toxic.allowed_edits(len(t))]
    best = min(found, default=(None, 0))[0]
    return best, {i for d, i in found if d == best}


def check_hits(terms, said):
    m = toxic.Matcher(toxic.Lexicon(terms, [1.0] * len(terms)))
    (_, got, edits, start, _), _ = m.hits(*toxic.utf8_buffer(pa.array([" ".join(said)])))
    mine, at = dict(zip(start.tolist(), zip(edits.tolist(), got.tolist()))), 0
    for w in said:
        best, which = near_terms(terms, w)
        assert (best is None) == (at not in mine), w
        assert best is None or (mine[at][0] == best and mine[at][1] in which), w
        at += len(w.encode()) + 1


@pytest.mark.parametrize("edits_from", [(4,), (4, 8)])
def test_levenshtein_trie_and_prefilter(monkeypatch, edits_from):
    monkeypatch.setattr(toxic, "EDITS_FROM", edits_from)
    r = random.Random(3)
    word = lambda lo, hi, letters="abcé": "".join(r.choice(letters) for _ in range(r.randrange(lo, hi)))
    terms = list(dict.fromkeys(word(3, 9) for _ in range(40)))
    trie = toxic.Trie(terms)
    some = [word(1, 10) for _ in range(400)] + [terms[0] * 9, ""]
    for d in (1, 2):
        for w, got in zip(some, trie.within(some, d, chunk=100)):
            assert sorted(got) == sorted((i, edit_distance(w, t)) for i, t in enumerate(terms) if edit_distance(w, t) <= d)
    check_hits(terms, [word(2, 11) for _ in range(1500)])
    long = list(dict.fromkeys([*terms[:5], *(word(7, 13, "abcdefghij") for _ in range(12))]))
    said = []
    for t in long:
        for _ in range(60):
            w = list(t)
            for _ in range(r.randrange(4)):
                i = r.randrange(len(w))
                w[i : i + r.randrange(2)] = r.choice(["", "x", "a", "e"])
            said.append("".join(w) or "a")
    check_hits(long, said)


def test_prefilter_with_wide_characters():
    r = random.Random(4)
    letters = "abé\u200b\u2022\u4e2d\U0001f600"
    word = lambda lo, hi: "".join(r.choice(letters) for _ in range(r.randrange(lo, hi)))
    terms = list(dict.fromkeys([word(5, 9) for _ in range(30)] + ["idiots", "aabab", "babba"]))
    said = []
    for t in terms:
        for _ in range(25):
            i, c = r.randrange(len(t)), r.choice(letters)
            said += [t[:i] + c + t[i:], t[:i] + c + t[i + 1 :], t[:i] + t[i + 1 :], t + c]
    check_hits(terms, said)


def test_quotation_lowers_the_score():
    model = toxic.ToxicityModel(toxic.Lexicon(["idiot"], [5.0]), -3.0, toxic.PRIOR)
    m = toxic.Matcher(model.lexicon)
    plain, quoted, said, typo, clean = model.score(m.features(pa.array(["you idiot there", 'they wrote "idiot" on it', "the word idiot is old", "you idi0t there", "good day"]))[0])
    assert plain > typo > clean and quoted < plain and said < plain
