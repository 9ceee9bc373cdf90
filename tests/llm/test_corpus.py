"""Suffix dedup, language model, media and the pipeline."""

import hashlib
import math
import os
import random
import re
import zlib
from collections import Counter

import duckdb
import numpy as np
from pyspark.sql import functions as F
from tokenizers import Tokenizer

import corpus_pipeline
from rulegraph.llm import attention, language_id, language_model, media, mixing, suffix_dedup
from rulegraph.llm.common import crc_mod, ensure_checkpoint_dir, words_of
from rulegraph.llm.queries import TOKENIZER
from tests.llm.data import docs, empty
from tests.llm.test_documents import brute_fingerprint, brute_vector, levenshtein


def brute_repeats(texts, length):
    data = [(t or "").encode() for t in texts]
    c = Counter(b[i : i + length] for b in data for i in range(len(b) - length + 1))
    out = []
    for b in data:
        gone = np.zeros(len(b), bool)
        for i in range(len(b) - length + 1):
            if c[b[i : i + length]] > 1:
                gone[i : i + length] = True
        runs = int(gone[0]) + int((gone[1:] & ~gone[:-1]).sum()) if len(b) else 0
        out.append((len(b), int(gone.sum()), runs, hashlib.sha256(np.frombuffer(b, np.uint8)[~gone].tobytes()).hexdigest()))
    return out


def prose_maker(seed):
    rng = random.Random(seed)
    word = lambda: "".join(rng.choice("abcdeé") for _ in range(rng.randint(2, 7)))
    return lambda n: " ".join(word() for _ in range(n))


def brute_passages(text, texts, length=240, words=50):
    """(passages, their words) of a text: runs covered by strings found twice, by plain counting."""
    c = Counter(b[i : i + length] for t in texts for b in [(t or "").encode()] for i in range(len(b) - length + 1))
    data, n, total = (text or "").encode(), 0, 0
    gone = [False] * len(data)
    for i in range(len(data) - length + 1):
        if c[data[i : i + length]] > 1:
            gone[i : i + length] = [True] * length
    for m in re.finditer("1+", "".join("01"[g] for g in gone)):
        whole = [w for w in re.finditer(rb"[^ \t-\r]+", data) if m.start() <= w.start() and w.end() <= m.end()]
        if len(whole) > words:
            n, total = n + 1, total + len(whole)
    return n, total


def test_suffix_dedup_equals_brute_force(spark, monkeypatch):
    prose = prose_maker(5)
    a, b, c = prose(200), prose(150), prose(90)
    texts = [a, prose(30) + a[100:700] + prose(20), b + prose(9) + b, None, "", "short", "z" * 1500, a, c + "x" + c[:-1] + "y", prose(300), b[:450] + "!" + b[451:], "ab" * 700]
    texts += [c[:200] + prose(3) + c[200:] for _ in range(3)] + [prose(20) + " " + b[100:360] + " " + prose(20), a[:399], a[1:400], b[:239]]
    # a passage that many texts share, with different surroundings on each side of it and cuts at other places
    texts += [prose(k % 7) + " " + c[k % 5 : 330 - k % 3] + prose(4) for k in range(40)]
    d = docs(spark, [(i, t, None) for i, t in enumerate(texts)])
    want = brute_repeats(texts, 400)
    passages = [brute_passages(t, texts) for t in texts]
    assert sum(n for n, _ in passages) > 20
    hot = lambda sample, ranges: suffix_dedup.Ranges(sorted(sample)[::40], {k: i for i, k in enumerate(sorted(set(sample))[::2])})
    for huge, block, make in ((20_000, 1 << 22, None), (1, 1 << 22, None), (20_000, 100, hot)):
        monkeypatch.setattr(suffix_dedup, "GROUP_CLASSES", huge)
        monkeypatch.setattr(suffix_dedup, "ANCHOR_BLOCK", block)
        if make:
            monkeypatch.setattr(suffix_dedup, "make_ranges", make)
            monkeypatch.setattr(suffix_dedup, "RUN_SUFFIXES", 20)
        rows = suffix_dedup.remove_repeats(d).collect()
        assert len(rows) == len(texts)
        for r in rows:
            assert (r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) == want[r["doc_id"]], r["doc_id"]
            assert hashlib.sha256(r["kept"]).hexdigest() == r["kept_sha256"]
            assert (r["n_passages"], r["n_passage_words"]) == passages[r["doc_id"]], r["doc_id"]
    twice = docs(spark, [(1, a, None), (1, a, None), (None, b, None), (None, b, None)]).withColumn("doc_id", F.concat(F.lit("id "), F.col("doc_id").cast("string")))
    assert sorted(r["n_removed"] for r in suffix_dedup.remove_repeats(twice).collect()) == sorted([len(a.encode())] * 2 + [len(b.encode())] * 2)
    assert suffix_dedup.remove_repeats(empty(spark)).count() == 0


def test_matches_of_a_group_cover_what_pairs_do():
    rng = random.Random(9)
    for _ in range(30):
        members = sorted((bytes(rng.choice(b"ab") for _ in range(rng.randint(3, 12))), bytes(rng.choice(b"ab") for _ in range(rng.randint(0, 8)))) for _ in range(rng.randint(2, 14)))
        common = lambda x, y: len(os.path.commonprefix([x, y]))
        prefixes = [0, *(common(x[0], y[0]) for x, y in zip(members, members[1:], strict=False))]
        got = suffix_dedup.group_matches([m[1] for m in members], prefixes, 6)
        for i, (right, left) in enumerate(members):
            pairs = {(common(left[::-1], l2[::-1]), common(right, r2)) for j, (r2, l2) in enumerate(members) if j != i}
            cover = lambda found: {(k, n) for k, n in ((s, 6) for s in range(-8, 12)) if any(-a <= k and k + n <= z for a, z in found if a + z >= 6)}
            assert cover({(a, z) for m, a, z in got if m == i}) == cover(pairs)


def test_loser_tree_merges_like_sorting():
    rng = random.Random(2)
    runs, keys = [], []
    for _ in range(7):
        own = sorted(bytes(rng.choice(b"ab") for _ in range(rng.randint(1, 9))) for _ in range(rng.randint(0, 40)))
        keys += own
        if own:
            shared, rests = suffix_dedup.front_code(own)
            runs.append((own, suffix_dedup.Run(shared, np.array([len(x) for x in rests]), b"".join(rests))))
    got, last = [], b""
    for r, i, lcp, k in suffix_dedup.merge_runs([x for _, x in runs]):
        assert k == runs[r][0][i]
        if got:
            assert lcp == len(os.path.commonprefix([last, k]))
        got.append(k)
        last = k
    assert got == sorted(keys)


def test_every_window_has_one_anchor_of_its_content():
    rng = random.Random(1)
    data = bytes(rng.choice(b"abcd ") for _ in range(3000))
    at, first, last = suffix_dedup.anchors(data, 400, 256)
    assert first[0] == 0 and last[-1] == len(data) - 400 and (first[1:] == last[:-1] + 1).all()
    moved = b"#" * 77 + data
    at2, first2, last2 = suffix_dedup.anchors(moved, 400, 256)
    where = {s: a for a, f, z in zip(at2, first2, last2, strict=True) for s in range(f, z + 1)}
    for a, f, z in zip(at, first, last, strict=True):
        assert all(where[s + 77] == a + 77 for s in range(f, z + 1))


SMALL = attention.ModelShape(symbols=12, buckets=3, classes=4, width=4, hidden=5, context=5, stride=3, rounds=2, batch=4, least_steps=6, shard_places=200, head_words=8)


def small_table(s=SMALL, seed=0):
    return attention.make_table(np.random.default_rng(seed).integers(0, 9, (s.symbols, s.symbols)), s)


def test_gradient_is_that_of_the_loss():
    s, rng = SMALL, np.random.default_rng(0)
    flat = attention.initial(s).astype(np.float64)
    flat += rng.standard_normal(len(flat)) * 0.3
    x, y, m = rng.integers(0, 12, (3, 5)), rng.integers(0, 4, (3, 5)), np.ones((3, 5))
    m[2, 3:] = 0
    prior = rng.standard_normal((15, 4))
    _, g = attention.gradient(flat, x, y, m, prior, s)
    for i in rng.integers(0, len(flat), 60):
        e = np.zeros_like(flat)
        e[i] = 1e-4
        slope = (attention.gradient(flat + e, x, y, m, prior, s)[0] - attention.gradient(flat - e, x, y, m, prior, s)[0]) / 2e-4
        assert abs(slope - g[i]) < 2e-4, i


def test_overlapping_windows_make_every_place_fresh_once():
    s = attention.ModelShape(context=8, stride=5)
    for n in (1, 2, 7, 8, 9, 13, 14, 40):
        places = [p for a, f in zip(*attention.windows_of(n, s), strict=True) for p in range(a + f, min(a + 8, n))]
        assert places == list(range(n))


def test_training_sees_every_place_of_every_text_once(spark):
    s, ids = SMALL, [np.arange(n, dtype="<u2") % 40 for n in (0, 1, 3, 600, 1024, 1100)]
    symbols = language_model.Symbols(np.arange(40), s)
    read = spark.createDataFrame([(i * 1_000_003, x.tobytes()) for i, x in enumerate(ids)], "deal bigint, ids binary")
    seen = Counter()
    for turn in range(2):
        for r in language_model.training_chunks(read, symbols, turn, 2, 3).collect():
            x, y, m = attention.training_windows([np.frombuffer(r["chunk"], np.uint16)], s)
            seen.update(zip(x[m > 0].tolist(), y[m > 0].tolist(), strict=True))
    want = Counter()
    for x in ids:
        seq = symbols.sequence(x.tobytes()).tolist()
        want.update(zip([attention.END, *seq], seq, strict=False))
    assert seen == want


def brute_log_probability(flat, table, seq, s):
    """Place by place, in plain loops over the window that scores it."""
    w, out = attention.unpack(flat.astype(np.float64), s), 0.0
    line = [attention.END, *seq]
    for start, fresh in zip(*attention.windows_of(len(seq), s), strict=True):
        x = line[start : min(start + s.context, len(seq))]
        e = [w["E"][c] + w["P"][i] for i, c in enumerate(x)]
        for i in range(fresh, len(x)):
            a = [math.exp(float(e[i] @ w["A"] @ e[j]) / math.sqrt(s.width)) for j in range(i + 1)]
            y = e[i] + (sum(k * e[j] for j, k in enumerate(a)) / sum(a)) @ w["B"]
            o = y + np.maximum(y @ w["W1"] + w["b1"], 0) @ w["W2"]
            g = np.exp(o @ w["U"] + w["c"] + table.after[x[i]])
            to = line[start + i + 1]
            out += math.log(g[table.class_of[to]] / g.sum()) + table.within[x[i], to]
    return out


def test_sequence_scores_equal_plain_loops_and_are_probabilities():
    s, table, rng = SMALL, small_table(), np.random.default_rng(3)
    flat = attention.initial(s)
    flat = (flat + rng.standard_normal(len(flat)) * 0.3).astype(np.float32)
    seqs = [rng.integers(0, 12, n) for n in (1, 2, 5, 6, 9, 30)]
    got = attention.score_sequences(flat, table, seqs, s, batch=3)
    assert np.allclose(got, [brute_log_probability(flat, table, q.tolist(), s) for q in seqs], atol=1e-4)
    past = [3, 1, 7, 7, 2, 5, 9]
    total = sum(math.exp(attention.score_sequences(flat, table, [np.array([*past, k])], s)[0] - attention.score_sequences(flat, table, [np.array(past)], s)[0]) for k in range(12))
    assert abs(total - 1) < 1e-4
    symbols = language_model.Symbols(np.arange(40), s)
    for k in range(1, 12):
        assert abs(np.exp(symbols.inner[symbols.of == k]).sum() - 1) < 1e-9


def test_words_are_split_as_elsewhere(monkeypatch):
    texts = [" a  B\tc\x0bD\x0c\r\n", None, "", "  ", "naïve \xa0x\x1cy\u2003z É", "last"]
    want = [[w.decode() for w in words_of(t)] for t in texts]
    for size in (4_000_000, 3):
        monkeypatch.setattr(language_model, "PIECE_BYTES", size)
        got = [[] for _ in texts]
        for words, owner in language_model.split_words(texts):
            for w, i in zip(words.to_pylist(), owner.tolist(), strict=True):
                got[i].append(w)
        assert got == want


def test_scores_by_brute_force(spark):
    d = docs(spark)
    held = crc_mod("doc_id", 10) == 0
    shape = attention.ModelShape(symbols=64, buckets=8, classes=6, head_words=8, rounds=2, least_steps=10, shard_places=300)
    run = lambda x: sorted((str(r["doc_id"]), r["n_tokens"], r["n_known"], r["train_tokens"], round(r["base_score"], 6), r["score"]) for r in language_model.lm_scores(x, tokenizer=TOKENIZER, held_out=held, shape=shape).collect())
    rows = run(d)
    lower = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))
    tokens = lambda t: [*(t or "").encode().translate(lower).split(), "end"]
    c = Counter()
    for r in d.collect():
        if r["doc_id"] is None or zlib.crc32(str(r["doc_id"]).encode()) % 10:
            c.update(tokens(r["text"]))
    n, v = sum(c.values()), len(c)
    want = sorted((str(r["doc_id"]), len(w := tokens(r["text"])), sum(c[x] > 0 for x in w), n, round(sum(math.log10((c[x] + 0.1) / (n + 0.1 * (v + 1))) for x in w), 6)) for r in d.collect())
    assert [r[:5] for r in rows] == want
    assert all(r[5] < 0 for r in rows)
    # neither the model nor its scores depend on how the rows are partitioned
    for other in (run(d.repartition(1)), run(d.repartition(5))):
        assert [r[:5] for r in other] == want and np.allclose([r[5] for r in other], [r[5] for r in rows], rtol=1e-5)
    assert language_model.lm_scores(empty(spark), tokenizer=TOKENIZER, held_out=held, shape=shape).count() == 0


def test_model_beats_word_counts_on_held_out_texts(spark):
    from rulegraph.llm import queries

    got = queries.op9_lm_scoring(spark, "/root/testdata/sf0.01").where("held_out").agg(F.sum("score"), F.sum("base_score")).first()
    assert got[0] > got[1]


def test_media_round_trip(spark):
    d = docs(spark)
    rows = media.media_columns(d).collect()
    want = []
    for r in d.collect():
        data = (r["text"] or "").encode()
        p = data + bytes(-len(data) % 64 if data else 64)
        want.append((str(r["doc_id"]), len(data), len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-64:])))
    assert sorted((str(r["doc_id"]), r["n_bytes"], r["payload_bytes"], r["payload_sha256"], r["tail_crc32"]) for r in rows) == sorted(want)
    by = {}
    for r in rows:
        assert by.setdefault(r["payload_sha256"], (r["media_sha256"], r["feature"])) == (r["media_sha256"], r["feature"])
    assert media.media_columns(empty(spark)).count() == 0
    for n in (64, 128, 6400):
        data = os.urandom(n)
        assert media.from_png(media.to_png(data)) == data


def test_broken_member_is_reported_and_the_others_are_read(spark):
    folder = f"{ensure_checkpoint_dir(spark)}/broken"
    d = docs(spark, [(i, f"text number {i} " * 50, None) for i in range(9)]).coalesce(1)
    (made,) = media.write_archives(d, folder)
    path = f"{folder}/{made['archive']}".removeprefix("file:")
    with open(path, "r+b") as f:
        data = f.read()
        at = data.index(b"000000004/")
        f.seek(at + 60)
        f.write(b"\0\0\0\0\0\0")
    rows = media.read_archives(spark, folder).collect()
    assert len(rows) == 9 and [r["member"] for r in rows if r["payload"] is None] == [next(r["member"] for r in rows if r["error"])]
    small = spark.read.format("archive_members").option("path", folder).option("rangebytes", "300").load()
    assert {r["member"] for r in small.collect()} == {r["member"] for r in rows}


def brute_languages(rows):
    """(language, cosine) of each text by prototypes that are sums of all labelled texts' vectors."""
    vectors = [brute_vector(r["text"] or "", 1024, 7) for r in rows]
    sums = {}
    for r, v in zip(rows, vectors, strict=True):
        if r["lang"] is not None and r["text"] is not None:
            sums[r["lang"]] = sums.get(r["lang"], 0) + v
    out = []
    for r, v in zip(rows, vectors, strict=True):
        if not any(map(str.isalpha, r["text"] or "")):
            out.append(("und", 0.0))
            continue
        cos = {k: float(v @ p / np.linalg.norm(v) / np.linalg.norm(p)) for k, p in sums.items()}
        best = max(sorted(cos), key=cos.get)
        out.append((best, max(0.0, cos[best])))
    return out


def brute_line_dedup(rows):
    """Texts without lines that an earlier row or line has, or one within an edit of 24 characters or more."""
    order = sorted(range(len(rows)), key=lambda i: (rows[i]["doc_id"] is not None, rows[i]["doc_id"] or 0, rows[i]["th"], i))
    first, lines = {}, {}
    for rank, i in enumerate(order):
        for no, line in enumerate((rows[i]["text"] or "").split("\n")):
            x = line.strip().lower()
            if x:
                first.setdefault(x, (rank, no))
                lines[i, no] = (x, (rank, no))
    long = sorted((x for x in first if len(x) >= 24), key=len)
    near = {x for x in long for y in long if x != y and first[y] < first[x] and abs(len(x) - len(y)) <= 1 and levenshtein(x, y) <= 1}
    keep = lambda i, no: (i, no) not in lines or (first[lines[i, no][0]] == lines[i, no][1] and lines[i, no][0] not in near)
    return ["\n".join(x for no, x in enumerate((r["text"] or "").split("\n")) if keep(i, no)) for i, r in enumerate(rows)]


def test_predictions_equal_brute_force(spark):
    rows = docs(spark).collect()
    got = language_id.identify_language(docs(spark).coalesce(1), held_out=F.lit(False), keep=["doc_id", "text"]).collect()
    want = brute_languages(rows)
    assert Counter((str(r["doc_id"]), r["text"], r["lang_pred"], round(r["score"], 6)) for r in got) == Counter((str(r["doc_id"]), r["text"], k, round(s, 6)) for r, (k, s) in zip(rows, want, strict=True))


def test_pipeline_stages_by_brute_force(spark):
    d = docs(spark)
    stages = dict(corpus_pipeline.STAGES)
    key = lambda r: (str(r["doc_id"]), r["text"], r["lang"], r["source"], r["n_chars"])
    run = lambda name, x: spark.createDataFrame(stages[name](spark, x, "").collect(), "doc_id bigint, text string, lang string, source string, n_chars bigint")

    before, d = d.collect(), run("language_id", d)
    want = [r for r, (k, s) in zip(before, brute_languages(before), strict=True) if k != "und" and round(s, 9) >= corpus_pipeline.MIN_SCORE]
    assert Counter(map(key, d.collect())) == Counter(map(key, want))

    before, d = [r.asDict() for r in d.withColumn("th", F.xxhash64("text")).collect()], run("line_dedup", d)
    want = [r | {"text": t, "n_chars": len(t)} for r, t in zip(before, brute_line_dedup(before), strict=True) if t.split()]
    assert Counter(map(key, d.collect())) == Counter(map(key, want)) and len(want) < len(before)

    before, d = d.collect(), run("simhash_near_dedup", d)
    fps, groups = [brute_fingerprint(r["text"]) for r in before], []
    for i, f in enumerate(fps):
        linked = [g for g in groups if any(bin(f ^ fps[j]).count("1") <= 3 for j in g)]
        groups = [g for g in groups if g not in linked] + [[i, *(j for g in linked for j in g)]]
    kept = d.collect()
    assert len(kept) == len(groups)
    for g in groups:
        best = min((before[j]["doc_id"] is None, before[j]["doc_id"] or 0) for j in g)
        assert sum(key(r) in [key(before[j]) for j in g if (before[j]["doc_id"] is None, before[j]["doc_id"] or 0) == best] for r in kept) == 1

    before, d = d, run("mixing", d)
    con = duckdb.connect()
    con.register("documents", before.toArrow())
    sampled = {str(r[0]) for r in con.execute(f"select doc_id from ({mixing.mixing_sql()}) where sampled").fetchall()}
    assert Counter(map(key, d.collect())) == Counter(key(r) for r in before.collect() if str(r["doc_id"]) in sampled)

    tok = Tokenizer.from_file(TOKENIZER)
    want = Counter()
    for r in d.collect():
        ids = np.array([*tok.encode(r["text"] or "", add_special_tokens=False).ids, 1], "<u4")
        for s in range(0, len(ids), 2048):
            want[(str(r["doc_id"]), s, zlib.crc32(ids[s : s + 2048].tobytes()))] += 1
    packed = stages["packing"](spark, d, "").collect()
    assert Counter((str(r["doc_id"]), r["start"], r["ids_crc32"]) for r in packed) == want
    ends = Counter()
    for r in packed:
        ends[r["sequence_id"]] += r["length"]
    assert max(ends.values()) <= 2048
    none = empty(spark)
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, none, "").count() == 0


def test_held_out_accuracy_of_language_id_on_the_given_table(spark):
    from rulegraph.llm import queries

    t = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "lang")
    got = queries.op1_language_id(spark, "/root/testdata/sf0.001").join(t, "doc_id").where("held_out")
    right, total = got.agg(F.sum((F.col("lang") == F.col("lang_pred")).cast("int")), F.count(F.lit(1))).first()
    assert right >= 0.97 * total
