"""The training-data operators against brute force, round trips, held-out accuracy, and odd inputs."""

import hashlib
import random
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from localcomm.llm import audio, chunks, curves, licenses, packing, quality, shingles, templates, unigram, warc
from localcomm.llm.bpe import WordCache, opened, tokenizer_path

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, digest string, row long"
LONG = "the quick brown fox jumps over the lazy dog and runs far away from here " * 400


@pytest.fixture(scope="module")
def docs(spark):
    """Nulls, empty and very long texts, ties, repeated rows, and columns whose names clash with inner ones."""
    base = "one two three four five six seven eight nine ten eleven twelve thirteen fourteen fifteen sixteen seventeen eighteen nineteen twenty"
    texts = [None, "", " \n\t ", "One", "one two", base, base.upper(), base.replace("ten", "TEN x"), LONG, LONG + "end", "a  b\n\nc ", "é漢😀 x", "Released under the MIT License.\nfoo bar", base, "tail\n", "x" * 5000]
    rows = [(i, t, "en", "s", len(t or ""), "d", 1) for i, t in enumerate(texts)] + [(5, base, "en", "s", len(base), "d", 1), (None, "null id text here now", None, None, None, None, None)]
    return spark.createDataFrame(rows, SCHEMA)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def by_row(docs):
    return [(r["doc_id"], r["text"] or "") for r in docs.collect()]


def test_audio_round_trip(docs, empty):
    got = sorted((r.asDict() for r in audio.inspected(audio.archived(docs)).collect()), key=str)
    want = []
    for d, t in by_row(docs):
        raw = t.encode()
        pay = raw + b"\xff" * (-len(raw) % 576 or 576 * (not raw))
        want.append((d, len(raw), len(pay), hashlib.sha256(pay).hexdigest(), zlib.crc32(pay[-32:])))
    assert sorted(((r["doc_id"], r["n_bytes"], r["payload_bytes"], r["payload_sha256"], r["tail_crc32"]) for r in got), key=str) == sorted(want, key=str)
    assert audio.inspected(audio.archived(empty)).count() == 0
    media = audio.archived(docs)
    pcm = {r["pcm"] for r in audio.pcm_archived(media).collect()}
    for r in media.collect():
        sound = audio.decoded([r["media"]])[0].astype(np.int64)
        wide = []  # by the definition, sample by sample
        for k, v in enumerate(sound.tolist()):
            a, b, c = sound[max(0, k - 1)], sound[min(len(sound) - 1, k + 1)], sound[min(len(sound) - 1, k + 2)]
            wide += [v, max(-32768, min(32767, int(9 * (v + b) - a - c + 8) >> 4))]
        assert audio.wave(audio.PCM, np.array(wide, "<i2").tobytes(), 16000) in pcm
        kind, _, _ = audio.parsed(r["media"])
        changes = sum((x < 0) != (y < 0) for x, y in zip(wide, wide[1:], strict=False))
        name = {audio.ULAW: "ulaw", audio.ALAW: "alaw", audio.IMA: "ima"}[kind]
        assert audio.feature(kind, audio.decoded([r["media"]])[0]) == f"{name}:{len(wide)}:{max(map(abs, wide))}:{sum(map(abs, wide)) // len(wide)}:{changes}"


def test_audio_stores_resampled_sound_without_loss(docs, monkeypatch):
    any_sound = np.random.default_rng(2).integers(-32768, 32768, 400).astype(np.int16)  # not what resampling gives
    assert audio.unpacked(*audio.packed(any_sound)).tolist() == any_sound.tolist()
    media, kept = audio.archived(docs), []
    real = audio.resampled_archive
    monkeypatch.setattr(audio, "resampled_archive", lambda m: kept.append(real(m)) or kept[-1])
    told = {(r["media_sha256"], r["feature"]) for r in audio.inspected(media).collect()}
    assert kept and kept[0].inputFiles()  # features come from files
    for r in kept[0].collect():
        sound = audio.unpacked(r["kept"], r["between"])
        assert (r["media_sha256"], audio.described(r["kind"], sound)) in told and len(sound) >= 2 * audio.UNIT
    assert sorted(audio.unpacked(r["kept"], r["between"]).tobytes() for r in kept[0].collect()) == sorted(audio.resampled(audio.decoded([r["media"]])[0]).tobytes() for r in media.collect())


def test_stored_sound_of_few_values_takes_a_byte_a_sample():
    few = np.resize(np.arange(-128, 128, dtype=np.int16) * 200, 4000)
    many = np.arange(4000, dtype=np.int16)
    for sound, most in ((few, 4000 + 600), (many, 8000 + 2), (few[:0], 2)):
        kept, between = audio.packed(audio.resampled(sound) if len(sound) else sound)
        assert len(kept) <= most and not np.frombuffer(between, np.int16).any()
        assert np.array_equal(audio.unpacked(kept, between)[0::2], sound)


def test_audio_codecs():
    assert audio.ULAW_TABLE[[0, 127, 128, 255]].tolist() == [-32124, 0, 32124, 0]
    assert audio.ALAW_TABLE[[0x55, 0xD5, 0x2A, 0xAA]].tolist() == [-8, 8, -32256, 32256]
    codes = np.random.default_rng(1).integers(0, 256, (3, 576), dtype=np.uint8)
    fast = audio.ima_blocks(codes, np.zeros(3, np.int16), np.zeros(3, np.uint8))
    for b in range(3):
        v, i, out = 0, 0, []
        for byte in codes[b].tolist():
            for c in (byte & 15, byte >> 4):
                step = int(audio.IMA_STEPS[i])
                diff = (step >> 3) + (step if c & 4 else 0) + (step >> 1 if c & 2 else 0) + (step >> 2 if c & 1 else 0)
                v = max(-32768, min(32767, v - diff if c & 8 else v + diff))
                i = max(0, min(88, i + int(audio.INDEX_MOVE[c])))
                out.append(v)
        assert fast[b].tolist() == out
    kind, rate, body = audio.parsed(audio.as_pcm(audio.stored(b"\x00" * 576)))
    assert (kind, rate) == (audio.PCM, 16000) and len(body) % 4 == 0


def test_warc_round_trip(spark):
    big = "z" * 1500
    rows = [(1, "http://a b/\r\nX", big), (2, None, big), (3, "u", big), (4, "u", None), (5, "u", ""), (6, "u", "é" * 600), (7, "u", "small"), (8, "u", "small"), (None, "u", big)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("digest", F.lit("clash"))
    index = warc.archived(pages)
    got = {r["page_id"]: (r["payload_bytes"], r["payload_digest"], r["record_type"], r["refers_to"]) for r in warc.read_back(index).collect()}
    for p, _, h in rows:
        raw = (h or "").encode()
        ref = 3 if h == big and p != 3 else None
        assert got[p] == (len(raw), hashlib.sha1(raw).hexdigest(), "revisit" if ref else "response", ref)
    one = warc.fetched(index.where("page_id = 6")).first()
    assert one["block"].endswith(("é" * 600).encode()) and one["headers"]["WARC-Type"] == "response"
    assert warc.archived(pages.limit(0)).count() == 0


def test_tokenizer_cache_equals_library(docs):
    tok = opened(tokenizer_path())
    texts = [t for _, t in by_row(docs)] + ["it's a 12 test\nnew 'll", "<|endoftext|> x", "a\x85b", " x", "x "]
    assert tok.encode(texts) == [np.array(tok.tok.encode(t, add_special_tokens=False).ids, "<u4").tobytes() for t in texts]


def test_tokenizer_cache_on_marks_and_odd_spaces():
    letters, rng = "aBé ñ,.!*#_-'\"1 9ß×ƀɏ中\\ ~`|", random.Random(1)
    some = ["".join(rng.choice(letters) for _ in range(rng.randrange(60))) for _ in range(4000)]
    some = [" ".join(t.split()) if rng.random() < 0.8 else t for t in some] + [""]
    enc = WordCache(tokenizer_path(), words=300)  # so few that words are forgotten on the way
    for lo in range(0, len(some), 512):
        part = some[lo : lo + 512]
        assert enc.encode(part) == [np.array(e.ids, "<u4").tobytes() for e in enc.tok.encode_batch(part, add_special_tokens=False)]


def test_packing(docs, empty):
    tok = opened(tokenizer_path()).tok
    rows = packing.packed_documents(docs).collect()
    assert len({(r["doc_id"], r["piece"], r["sequence_id"], r["offset"]) for r in rows}) == len(rows)
    total, seqs = 0, {}
    ids = {d: np.array([*tok.encode(t, add_special_tokens=False).ids, 0], "<u4") for d, t in by_row(docs)}
    for r in rows:
        x = ids[r["doc_id"]][r["start"] : r["start"] + r["length"]]
        assert zlib.crc32(x.tobytes()) == r["ids_crc32"] and (r["length"] == 2048 or r["piece"] == 0)
        seqs.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
        total += r["length"]
    for v in seqs.values():
        at = 0
        for o, n in sorted(v):
            assert o == at
            at += n
        assert at <= 2048
    assert total == sum(len(tok.encode(t, add_special_tokens=False).ids) + 1 for _, t in by_row(docs))
    assert packing.packed_documents(empty).count() == 0


def test_exchange_empties_a_bin():
    # Best fit leaves 3 bins; one swap of two for one makes it 2.
    sizes = [5, 5, 4, 3, 3]
    assert len(packing.exchanged(sizes, [[0, 1], [2, 3], [4]], 10)) == 2
    rng = np.random.default_rng(5)
    for _ in range(20):
        sizes = rng.integers(1, 60, 200).tolist()
        bins = packing.packed(sizes, 100)
        assert sorted(k for b in bins for k in b) == list(range(200)) and all(sum(sizes[k] for k in b) <= 100 for b in bins)
        assert len(bins) <= len(packing.best_fit(sizes, 100))


def test_templates_against_strings(spark, docs):
    import duckdb

    lines = [f"Order {i} was shipped to our dear customer in the north of town" for i in range(30)]
    rows = [(i, lines[i] + f"\nunique words {chr(97 + i % 26)}{i} stay alone here {i}x") for i in range(30)] + [(100 + i, "only here " + chr(97 + i) * 5 + " for once") for i in range(5)]
    d = spark.createDataFrame(rows, "doc_id long, text string").unionByName(docs.select("doc_id", "text"))
    p = templates.TemplateParams(min_docs=3)
    con = duckdb.connect()
    con.register("docs_in", d.toArrow())
    want = sorted(con.execute(templates.oracle(p, "docs_in")).fetchall(), key=str)
    for q in (p, templates.TemplateParams(min_docs=3, broadcast_most=0)):
        out = templates.cleaned(d, q).select("doc_id", F.col("_lines").cast("long"), F.col("_lost").cast("long"), F.coalesce("text", F.lit(""))).collect()
        assert sorted((tuple(r) for r in out), key=str) == want
    clash = docs.withColumns({c: F.lit(7) for c in ("_key", "_lines", "_lost", "_gone", "_digest", "__lost")})
    for q in (p, templates.TemplateParams(min_docs=3, broadcast_most=0)):
        kept = templates.deduplicated(clash, q)
        assert kept.columns == clash.columns
        assert sorted(map(str, kept.select("doc_id", "text", "_lost").collect())) == sorted(map(str, templates.deduplicated(docs, q).select("doc_id", "text", F.lit(7).alias("_lost")).collect()))
    assert templates.deduplicated(docs.limit(0)).count() == 0


def test_passages_with_production_parameters(spark, docs):
    import duckdb

    words = [f"word{chr(97 + i // 26)}{chr(97 + i % 26)}" for i in range(60)]
    line = " ".join(words)
    stretch = "\n".join([" ".join(words[:30]), "", " ".join(words[30:55]), "7 8", " ".join(words[55:])])
    rows = [(1, f"first own line here\n{line}"), (2, f"{line}\nsecond own line"), (3, f"third\n{stretch}\nand its end"), (4, f"fourth\n{stretch}\nother end"), (5, line.replace("wordaa", "Wordaa")), (6, " ".join(words[:49])), (7, " ".join(words[:49])), (8, line.replace("wordab", "w1")), (9, line.replace("wordab", "w2"))]
    d = spark.createDataFrame(rows, "doc_id long, text string").unionByName(docs.select("doc_id", "text").where("doc_id > 10 OR doc_id IS NULL").withColumn("doc_id", F.col("doc_id") + 100))
    con = duckdb.connect()
    con.register("docs_in", d.toArrow())
    want = sorted(con.execute(templates.passages_oracle(templates.PASSAGES, "docs_in")).fetchall(), key=str)
    for most in (templates.PASSAGES.broadcast_most, 0):
        p = templates.TemplateParams(passage_words=templates.PASSAGES.passage_words, broadcast_most=most)
        out = templates.cleaned(d, p).select("doc_id", F.col("_lines").cast("long"), F.col("_lost").cast("long"), F.coalesce("text", F.lit(""))).collect()
        assert sorted((tuple(r) for r in out), key=str) == want
    text = {r[0]: r[3] for r in want}
    assert text[1] == rows[0][1] and text[2] == "second own line"
    assert text[3] == rows[2][1] and text[4] == "fourth\n\nother end"
    assert all(text[i] == t for i, t in rows[4:])


def test_curves_against_brute_force(spark):
    rng = np.random.default_rng(2)
    x = rng.normal(size=(600, 16)).astype(np.float32)
    x[50:80] = x[40]
    rows = [(i, [float(v) for v in x[i]]) for i in range(600)] + [(1000, None), (1020, [0.0] * 16), (1040, [float("nan")] * 16), (1060, [None] * 16), (None, [1.0] * 16), (1080, [1.0, 2.0]), (1100, [3.0, 1.0])]
    t = spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumn("key", F.lit(1))
    got = {}
    for r in sorted(curves.searched(t, curves.CurveParams(window=8, curves=2, row_block=100, query_block=10)).collect(), key=lambda r: r["rank"]):
        got.setdefault(r["query_id"], []).append((r["vec_id"], r["score"]))
    y = x.astype(np.float64)
    assert set(got) == {*range(0, 600, 20), 1080, 1100}
    assert got.pop(1080) == [(1100, 5.0)] and got.pop(1100) == [(1080, 5.0)]
    for q in got:
        s = np.zeros(600)
        for j in range(16):
            s += y[q, j] * y[:, j]
        s[q] = -np.inf
        o = np.lexsort((np.arange(600), -s))[:20]
        assert got[q] == list(zip(o.tolist(), s[o].tolist(), strict=True))
    assert curves.searched(t.limit(0)).count() == 0


def test_curves_keep_repeated_ids(spark):
    rows = [(0, [1.0, 0.0]), (7, [0.9, 0.0]), (7, [0.2, 0.0]), (7, [0.2, 0.0]), (0, [0.5, 0.0]), (3, [0.9, 0.0])]
    got = curves.searched(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), curves.CurveParams(window=2, curves=2, row_block=2, query_block=1)).collect()
    mine = sorted([(r["rank"], r["vec_id"], r["score"]) for r in got if r["query_id"] == 0])
    assert mine == sorted([(1, 3, 0.9), (2, 7, 0.9), (3, 0, 0.5), (4, 7, 0.2), (5, 7, 0.2), (1, 0, 0.5), (2, 3, 0.45), (3, 7, 0.45), (4, 7, 0.1), (5, 7, 0.1)])


@pytest.mark.parametrize(("n", "window"), [(500, 256), (4000, 256)])
def test_recall_of_windows_alone_on_clustered_vectors(spark, n, window):
    """Where vectors have structure the windows alone find nearly all; the given embeddings have none (README)."""
    rng = np.random.default_rng(3)
    x = (rng.normal(size=(n // 50, 32))[rng.integers(0, n // 50, n)] + 0.2 * rng.normal(size=(n, 32))).astype(np.float64)
    t = spark.createDataFrame([(i, v) for i, v in enumerate(x.tolist())], "vec_id long, embedding array<double>")
    got = {}
    for r in curves.searched(t, curves.CurveParams(window=window, complete=False)).collect():
        got.setdefault(r["query_id"], set()).add(r["vec_id"])
    hits = 0
    for q in range(0, n, 20):
        s = x @ x[q]
        s[q] = -np.inf
        hits += len(set(np.argsort(-s)[:20].tolist()) & got[q])
    assert hits >= 0.9 * 20 * len(range(0, n, 20))


def test_quality_learns(spark):
    rng = np.random.default_rng(4)
    words = ["lorem", "ipsum", "dolor", "sit", "amet", "elit", "sed", "magna"]

    def text(g):
        w = rng.choice(words, 40).tolist()
        return " ".join(x.upper() + "!!" for x in w) if g == 0 else " ".join(["stupid", *w] if g == 1 else w)

    grades = rng.integers(0, 3, 600)
    d = spark.createDataFrame([(i, text(g)) for i, g in enumerate(grades.tolist())] + [(9000, None), (9001, "")], "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(g > 0), int(g == 1)) for i, g in enumerate(grades.tolist()) if i < 300] + [(700, None, None)], "doc_id long, quality int, toxic int")
    model = quality.train(d, quality.graded(labels))
    out = {r["doc_id"]: r for r in quality.score(d, model).collect()}
    held = [(out[i]["rejected"], g < 2) for i, g in enumerate(grades.tolist()) if i >= 300]
    assert sum(a == b for a, b in held) >= 0.97 * len(held) and len(out) == 602
    assert np.all(np.diff(model.thresholds) > 0)
    # Featurising many texts at once equals one by one.
    from localcomm.llm.common import flat
    import pyarrow as pa

    some = ["Ab ab!! 12", "", "x é ZZ zz", "abcdefgh abcdef***"]
    r, p = quality.featurised(*flat(pa.array(some)))
    for i, t in enumerate(some):
        assert sorted(p[r == i].tolist()) == sorted(quality.featurised(*flat(pa.array([t])))[1].tolist())
    none = quality.train(d, quality.graded(labels.limit(0)))
    assert quality.score(d, none).where("rejected").count() == 0 and quality.selected(d, none).count() == 602


WORD = re.compile(r"[^\x20\x09-\x0D]+")


def _brute(rows, n, percent):
    low = str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})
    sets = []
    for _, t in rows:
        w = WORD.findall(t.translate(low))
        sets.append(frozenset(tuple(w[k : k + n]) for k in range(len(w) - n + 1)) if len(w) >= n else frozenset([tuple(w)] if w else []))
    par = list(range(len(rows)))

    def find(x):
        while par[x] != x:
            x = par[x]
        return x

    for i in range(len(rows)):
        for j in range(i):
            if sets[i] and 100 * len(sets[i] & sets[j]) >= percent * len(sets[i] | sets[j]):
                par[find(i)] = find(j)
    least = {}
    for i, (d, _) in enumerate(rows):
        if d is not None:
            least[find(i)] = min(least.get(find(i), d), d)
    return sorted(((d, len(s), least.get(find(i)) if s else d) for i, ((d, _), s) in enumerate(zip(rows, sets, strict=True))), key=str)


def test_shingle_join_against_all_pairs(spark, docs):
    rng = np.random.default_rng(6)
    vocab = [f"w{i}" for i in range(300)]
    rows = by_row(docs)
    for g in range(30):
        base = rng.choice(vocab, int(rng.integers(6, 120))).tolist()
        for c in range(int(rng.integers(1, 6))):
            t = list(base)
            for _ in range(int(rng.integers(0, 3))):
                t[int(rng.integers(len(t)))] = str(rng.choice(vocab))
            rows.append((100 + 10 * g + c, " ".join(t)))
    d = spark.createDataFrame(rows, "doc_id long, text string").withColumn("digest", F.lit("clash")).withColumn("n", F.lit(0))
    # Small levels, stretches and groups, and families that are given up, leave all the work to the index and its blocks.
    for p in (shingles.JoinParams(), shingles.JoinParams(levels=(1, 2, 4), counted=0.3, small=4, agree=9), shingles.JoinParams(group=3)):
        got = sorted((tuple(r) for r in shingles.joined(d, p).collect()), key=str)
        assert got == _brute(rows, 4, 85)
    assert shingles.joined(d.limit(0)).count() == 0


@pytest.mark.parametrize(("words", "percent"), [(4, 85), (5, 80)])
def test_all_links_between_classes(spark, docs, words, percent):
    rng = np.random.default_rng(8)
    rows = by_row(docs)
    for g in range(12):
        base = [f"w{i}" for i in rng.integers(0, 200, int(rng.integers(30, 90)))]
        for c in range(int(rng.integers(1, 12))):
            t = list(base)
            for _ in range(int(rng.integers(0, 4))):
                t[int(rng.integers(len(t)))] = f"w{rng.integers(200)}"
            rows.append((100 + 20 * g + c, " ".join(t)))
    d = spark.createDataFrame(rows, "doc_id long, text string")
    low = str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})
    sets = {}
    for i, t in rows:
        w = WORD.findall(t.translate(low))
        s = frozenset(tuple(w[k : k + words]) for k in range(len(w) - words + 1)) if len(w) >= words else frozenset([tuple(w)] if w else [])
        if s:
            sets.setdefault(s, set()).add(i)
    want = {frozenset((min(sets[x], key=str), min(sets[y], key=str))) for x in sets for y in sets if x != y and 100 * len(x & y) >= percent * len(x | y)}
    for p in (shingles.JoinParams(words=words, percent=percent, group=3), shingles.JoinParams(words=words, percent=percent, agree=9)):
        members, links = shingles.linked_classes(d, p)
        name = {}
        for r in members.collect():
            if r["class_id"] is not None:
                name.setdefault(bytes(r["class_id"]), set()).add(r["doc_id"])
        assert sorted(map(sorted, (map(str, v) for v in name.values()))) == sorted(map(sorted, (map(str, v) for v in sets.values())))
        got = [frozenset(min(name[bytes(r[k])], key=str) for k in "ab") for r in links.collect()]
        assert len(got) == len(set(got)) and set(got) == want


def test_near_sets_decide_pairs(spark):
    """Pairs that the answers of near sets decide are decided rightly, and some are left open."""
    from localcomm.llm.common import Scratch

    rng = np.random.default_rng(9)
    anchors = [frozenset(rng.choice(400, 100, replace=False).tolist()) for _ in range(3)]
    anchors[1] = frozenset(list(anchors[0])[:94]) | frozenset(range(1000, 1006))
    sets = {f"x{k}": a for k, a in enumerate(anchors)}
    star, pairs = [], []
    for k, a in enumerate(anchors):
        for c in range(10):
            s = frozenset(rng.permutation(sorted(a))[: 100 - int(rng.integers(0, 8))].tolist()) | frozenset(rng.integers(2000, 2010, int(rng.integers(0, 6))).tolist())
            sets[f"m{k}{c}"] = s
            star.append((f"m{k}{c}".encode(), f"x{k}".encode(), len(s & a), 100))
    names = sorted(sets)
    for i, x in enumerate(names):
        for y in names[:i]:
            big, small = sorted((x, y), key=lambda z: (-len(sets[z]), z))
            pairs.append((big.encode(), small.encode(), len(sets[big]), len(sets[small])))
    answers = lambda df: spark.createDataFrame([(r["a"], r["b"], len(sets[r["a"].decode()] & sets[r["b"].decode()])) for r in df.collect()], "a binary, b binary, common long")
    p = shingles.JoinParams()
    got = shingles.derived(spark.createDataFrame(pairs, "a binary, b binary, na long, nb long"), spark.createDataFrame(star, "digest binary, anchor binary, common long, size long"), answers, p, Scratch(spark)).collect()
    seen = set()
    for r in got:
        x, y = sets[r["a"].decode()], sets[r["b"].decode()]
        assert r["linked"] is None or r["linked"] == (100 * len(x & y) >= 85 * len(x | y))
        seen.add(r["linked"])
    assert len(got) == len(pairs) and seen == {True, False, None}


def test_licenses(docs, empty):
    got = {r["doc_id"]: (r["n_sentences"], r["licenses"]) for r in licenses.scanned(docs).collect()}
    assert got[12] == (1, "MIT") and got[0] == (0, "") and licenses.scanned(empty).count() == 0


def test_chunk_store(docs, empty):
    tok = opened(tokenizer_path()).tok
    store = chunks.built(docs, chunks.StoreParams(mask_bits=5, least=8, most=200))
    got = sorted((tuple(r) for r in chunks.streams(store, with_ids=True).collect()), key=lambda r: r[1])
    want = sorted(by_row(docs), key=lambda r: (r[0] is not None, r[0] or 0))
    at = 0
    assert [g[0] for g in got] == [w[0] for w in want]
    for (d, start, n, crc, raw), (_, t) in zip(got, want, strict=True):
        ids = np.array([*tok.encode(t, add_special_tokens=False).ids, 0], "<u4").tobytes()
        assert (start, n, crc, raw) == (at, len(ids) // 4, zlib.crc32(ids), ids), d
        at += n
    assert store.chunks.count() == store.chunks.select("digest").distinct().count()
    assert chunks.streams(chunks.built(empty)).count() == 0


def test_unigram_against_plain_viterbi(docs, empty):
    model = unigram.opened(unigram.model_path())
    index = {p: i for i, (p, _, k) in enumerate(model.pieces) if k in (unigram.NORMAL, unigram.USER)}

    def plain(text):
        s = ("▁" + text.replace(" ", "▁")) if text else ""
        best = [(0.0, 0, None)] + [(-np.inf, 0, None)] * len(s)
        for i in range(len(s)):
            for j in range(i + 1, min(len(s), i + model.longest) + 1):
                k = index.get(s[i:j])
                v = model.scores[k] if k is not None else model.low if j == i + 1 else None
                if v is not None and best[i][0] + v > best[j][0]:
                    best[j] = (best[i][0] + v, i, k)
        out, j = [], len(s)
        while j:
            _, i, k = best[j]
            out = ([k] if k is not None else [model.byte_id[b] for b in s[i:j].encode()]) + out
            j = i
        return out

    texts = [t[:300] for _, t in by_row(docs)] + ["  two  blanks ", "Hello world, the end of it"]
    for t, got in zip(texts, model.encode(texts), strict=True):
        mine, ref = np.frombuffer(got, "<u4").tolist(), plain(t)
        score = lambda ids: sum(model.scores[i] for i in ids)
        assert mine == ref or abs(score(mine) - score(ref)) < 1e-6
        assert model.decode(np.frombuffer(got, "<u4")) == t
    assert all(r["decoded_equal"] for r in unigram.digested(docs).collect()) and unigram.digested(empty).count() == 0


def test_ordinal_fit_against_a_plain_one():
    """The fit's weighted, penalised likelihood is that of a descent by numeric slopes on the same few features."""
    rng = np.random.default_rng(12)
    n, d = 400, 3
    x = rng.random((n, d)) < 0.5
    grades = np.digitize(x @ np.array([2.0, -1.5, 1.0]) + rng.logistic(size=n), [-0.5, 1.5])
    p = quality.QualityParams(min_rows=1, min_z=0.0, steps=2000, rate=0.02)
    rows, places = np.nonzero(x)
    model = quality.fit_ordinal(rows, places.astype(np.int64), grades, p)
    weight = np.sqrt(n / (3 * np.bincount(grades, minlength=3)))[grades]

    def loss(v):
        w, cut = v[:d], np.array([v[d], v[d] + np.exp(v[d + 1])])
        tail = 1 / (1 + np.exp(-((x @ w)[:, None] - cut[None, :])))
        full = np.hstack([np.ones((n, 1)), tail, np.zeros((n, 1))])
        like = full[np.arange(n), grades] - full[np.arange(n), grades + 1]
        return float((weight * -np.log(np.maximum(like, 1e-12))).mean() + p.l2 / 2 * (w**2).sum())

    v = np.zeros(d + 2)
    for _ in range(1500):
        slope = np.array([(loss(v + e) - loss(v - e)) / 2e-5 for e in 1e-5 * np.eye(d + 2)])
        v -= 0.3 * slope
    w = np.zeros(d)
    w[model.places] = model.weights
    mine = np.array([*w, model.thresholds[0], np.log(np.diff(model.thresholds)[0])])
    assert abs(loss(mine) - loss(v)) < 1e-4 and np.allclose(w, v[:d], atol=0.05)


def test_pipeline_against_brute_force(spark, docs, tmp_path):
    """Each stage on what the one before kept: row-by-row scores, strings in SQL, all pairs, and plain tokens."""
    import corpus_pipeline as cp
    import duckdb

    rng = np.random.default_rng(21)
    words = [f"w{chr(97 + i % 26)}{chr(97 + i // 26)}" for i in range(200)]
    texts, grades = [], []
    for i in range(360):
        g = int(rng.integers(0, 3))
        w = rng.choice(words, 60).tolist()
        texts.append(" ".join(x.upper() + "!!" for x in w) if g == 0 else " ".join(["stupid", *w] if g == 1 else w))
        grades.append(g)
    clean = [t for t, g in zip(texts, grades, strict=True) if g == 2]
    passage = " ".join(rng.choice(words, 70).tolist())
    extra = [clean[0], clean[1].replace(clean[1].split()[5], "changed", 1), clean[2] + "\n" + passage, clean[3] + "\n" + passage, *(f"{c}\nOrder {k} was shipped to our dear customer in town" for k, c in enumerate(clean[4:16]))]
    rows = [(i, t, "en", "s", len(t), "d", 1) for i, t in enumerate([*texts, *extra], 1000)]
    d = spark.createDataFrame(rows, SCHEMA).unionByName(docs)
    spark.createDataFrame([(1000 + i, int(g > 0), int(g == 1)) for i, g in enumerate(grades)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")

    kept = cp.quality_stage(spark, d, str(tmp_path))
    assert kept.columns == d.columns
    model = quality.train(d, quality.graded(spark.read.parquet(f"{tmp_path}/labels.parquet")))
    dense = model.dense()

    def stays(t):
        from localcomm.llm.common import flat
        import pyarrow as pa

        _, places = quality.featurised(*flat(pa.array([t or ""])))
        return 1 / (1 + np.exp(model.thresholds[1] - dense[places].sum(dtype=np.float64))) >= 0.5

    have = sorted(((r["doc_id"], r["text"]) for r in kept.collect()), key=str)
    assert have == sorted(((r["doc_id"], r["text"]) for r in d.collect() if stays(r["text"])), key=str) and len(have) < d.count()

    def by_sql(frame, query):
        con = duckdb.connect()
        con.register("docs_in", frame.toArrow())
        rows = con.execute(query).fetchall()
        return sorted(((r[0], r[3]) for r in rows if not r[2] or r[3].strip()), key=str)

    lines = cp.line_stage(spark, kept, str(tmp_path))
    assert lines.columns == d.columns
    assert sorted(((r["doc_id"], r["text"] or "") for r in lines.collect()), key=str) == by_sql(kept, templates.oracle(templates.TemplateParams(), "docs_in"))
    near = cp.near_copy_stage(spark, lines, str(tmp_path))
    assert near.columns == d.columns
    flat_rows = by_row(lines)
    groups = {}
    for i, _, c in _brute(flat_rows, 5, 80):
        groups.setdefault(i, c)
    assert sorted(map(str, by_row(near))) == sorted(str(r) for r in flat_rows if r[0] is None or groups[r[0]] is None or groups[r[0]] >= r[0])
    assert near.count() < lines.count()
    last = cp.packing_stage(spark, near, str(tmp_path)).collect()
    tok = opened(tokenizer_path()).tok
    p = templates.ONLY_PASSAGES
    query = templates.passages_oracle(templates.TemplateParams(passage_words=p.passage_words, min_docs=10**9), "docs_in")
    want = sorted((i, n) for i, n in ((i, len(tok.encode(t, add_special_tokens=False).ids) + 1) for i, t in by_sql(near, query) if i is not None))
    lengths = {}
    for r in last:
        lengths.setdefault(r["doc_id"], []).append(r["length"])
    assert sorted((i, sum(v)) for i, v in lengths.items() if i is not None) == sorted((i, sum(n for j, n in want if j == i)) for i in {j for j, _ in want})


MIT = """Permission is hereby granted, free of charge, to any person obtaining a copy
of this software and associated documentation files (the "Software"), to deal
in the Software without restriction, including without limitation the rights
to use, copy, modify, merge, publish, distribute, sublicense, and/or sell
copies of the Software, and to permit persons to whom the Software is
furnished to do so, subject to the following conditions:

The above copyright notice and this permission notice shall be included in all
copies or substantial portions of the Software."""
BSD = """Redistribution and use in source and binary forms, with or without
modification, are permitted provided that the following conditions are met:
1. Redistributions of source code must retain the above copyright notice,
   this list of conditions and the following disclaimer.
2. Redistributions in binary form must reproduce the above copyright notice,
   this list of conditions and the following disclaimer in the documentation
   and/or other materials provided with the distribution."""
GPL = """This program is free software: you can redistribute it and/or modify
it under the terms of the GNU General Public License as published by
the Free Software Foundation, either version 3 of the License, or
(at your option) any later version.

This program is distributed in the hope that it will be useful,
but WITHOUT ANY WARRANTY; without even the implied warranty of
MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE.  See the"""
MPL = "This Source Code Form is subject to the terms of the Mozilla Public\nLicense, v. 2.0."


@pytest.mark.parametrize("mark", ["", "# ", "// ", " * ", ";; "])
def test_wrapped_licence_notices(spark, mark):
    texts = [MIT, BSD, GPL, MPL, MIT.replace("deal\nin", "deal\n\nin"), MIT.replace("copy\nof", "copy.\nof"), "foo\nReleased under the MIT License\nbar", "MIT License\n\n" + MIT]
    rows = [(i, end.join(mark + x for x in t.split("\n"))) for i, (t, end) in enumerate([*((t, "\n") for t in texts), (GPL, "\r\n")])]
    got = [(r["sentences"], r["licenses"]) for r in licenses.scanned(spark.createDataFrame(rows, "doc_id long, text string")).orderBy("doc_id").collect()]
    assert got == [
        ("MitGrant,MitNotice", "MIT"),
        ("BsdGrant,BsdSource,BsdBinary", "BSD-2-Clause"),
        ("GplLater-3,GplHope", "GPL-3.0-or-later"),
        ("MplRef", "MPL-2.0"),
        ("MitNotice", ""),
        ("MitNotice", ""),
        ("MitRef", "MIT"),
        ("MitTitle,MitGrant,MitNotice", "MIT MIT"),
        ("GplLater-3,GplHope", "GPL-3.0-or-later"),
    ]


FULL = {
    "MIT": MIT + """

THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR
IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY,
FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE
AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER
LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM,
OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE
SOFTWARE.""",
    "BSD-3-Clause": BSD + """
3. Neither the name of the copyright holder nor the names of its contributors
   may be used to endorse or promote products derived from this software without
   specific prior written permission.

THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS"
AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE
IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE
DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE
FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL
DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR
SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER
CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY,
OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE
OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.""",
    "ISC": """Permission to use, copy, modify, and/or distribute this software for any
purpose with or without fee is hereby granted, provided that the above
copyright notice and this permission notice appear in all copies.

THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES
WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF
MERCHANTABILITY AND FITNESS.""",
    "LGPL-2.1-or-later": """This library is free software; you can redistribute it and/or
modify it under the terms of the GNU Lesser General Public
License as published by the Free Software Foundation; either
version 2.1 of the License, or (at your option) any later version.

This library is distributed in the hope that it will be useful,
but WITHOUT ANY WARRANTY; without even the implied warranty of
MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE.  See the GNU
Lesser General Public License for more details.""",
    "AGPL-3.0-or-later": """This program is free software: you can redistribute it and/or modify
it under the terms of the GNU Affero General Public License as
published by the Free Software Foundation, either version 3 of the
License, or (at your option) any later version.""",
    "Apache-2.0": """Licensed under the Apache License, Version 2.0 (the "License");
you may not use this file except in compliance with the License.
You may obtain a copy of the License at

    http://www.apache.org/licenses/LICENSE-2.0

Unless required by applicable law or agreed to in writing, software
distributed under the License is distributed on an "AS IS" BASIS,
WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied.
See the License for the specific language governing permissions and
limitations under the License.""",
    "MPL-2.0": """This Source Code Form is subject to the terms of the Mozilla Public
License, v. 2.0. If a copy of the MPL was not distributed with this
file, You can obtain one at http://mozilla.org/MPL/2.0/.""",
    "Zlib": """This software is provided 'as-is', without any express or implied
warranty. In no event will the authors be held liable for any damages
arising from the use of this software.

Permission is granted to anyone to use this software for any purpose,
including commercial applications, and to alter it and redistribute it
freely, subject to the following restrictions:""",
    "GPL-2.0-only": "SPDX-License-Identifier: GPL-2.0-only\nint main() { return 0; }",
    "Unlicense": "This is free and unencumbered software released into the public domain.\n\nAnyone is free to copy, modify, publish, use, compile, sell, or\ndistribute this software, either in source code form or as a compiled\nbinary, for any purpose, commercial or non-commercial, and by any\nmeans.",
    "": "We were granted permission by the licensed dealer, who is liable as is usual; see the license plate.",
}


@pytest.mark.parametrize("mark", ["", "# ", " * "])
def test_whole_licence_texts(spark, mark):
    rows = [(i, "\n".join(mark + x for x in t.split("\n"))) for i, t in enumerate(FULL.values())]
    got = [r["licenses"] for r in licenses.scanned(spark.createDataFrame(rows, "doc_id long, text string")).orderBy("doc_id").collect()]
    assert got == list(FULL)
