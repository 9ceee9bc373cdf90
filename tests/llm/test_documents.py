"""Language id, simhash, line dedup, quality, mixing and packing against plain Python and DuckDB."""

import functools
import math
import time
import zlib
from collections import Counter

import duckdb
import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from rulegraph.llm import html_text, language_id, line_dedup, mixing, packing, quality, simhash
from rulegraph.llm.common import crc_mod
from rulegraph.llm.components import connected_components
from rulegraph.llm.queries import TOKENIZER
from tests.llm.data import docs, empty


def duck(df, sql, cols):
    """Rows of the SQL over df as sorted text."""
    con = duckdb.connect()
    con.register("documents", df.toArrow())
    got = con.execute(sql)
    names = [x[0] for x in got.description]
    return sorted(tuple(str(r[names.index(c)]) for c in cols) for r in got.fetchall())


# ---------------------------------------------------------------- language


@functools.cache
def letter_vector(c, dims, seed):
    return np.random.default_rng([seed, ord(c)]).integers(0, 2, dims, dtype=np.int8).astype(float) * 2 - 1


def brute_vector(text, dims, seed):
    marks = " ".join("".join(c if c.isalpha() else " " for c in text.lower()).split())
    marks = f" {marks} " if marks else " "
    v = np.zeros(dims)
    letter = lambda c: letter_vector(c, dims, seed)
    for a, b, c in zip(marks, marks[1:], marks[2:], strict=False):
        v += np.roll(letter(a), 2) * np.roll(letter(b), 1) * letter(c)
    return v


def test_language_vectors_equal_brute_force():
    p = language_id.Profiler(256, 3, 7)
    texts = ["Hello, wörld!", "a", "x1y", "same same", "日本 text"]
    got = p.bundle(texts)
    for t, v in zip(texts, got, strict=True):
        assert np.array_equal(v, brute_vector(t, 256, 7)), t
    both = p.bundle_groups(texts, [0, 1, 0, 1, 0], 2)
    assert np.array_equal(both[0], got[0] + got[2] + got[4])


def test_language_id_cases(spark):
    d = docs(spark)
    held = F.coalesce(crc_mod("doc_id", 4) == 2, F.lit(False))
    rows = language_id.identify_language(d, held_out=held, keep=["doc_id", "text", "k0"]).collect()
    assert len(rows) == d.count()
    for r in rows:
        if not r["text"] or not any(c.isalpha() for c in r["text"]):
            assert (r["lang_pred"], r["score"]) == ("und", 0.0)
        else:
            assert r["lang_pred"] in ("en", "de") and 0 <= r["score"] <= 1
    long = [r for r in rows if r["text"] and len(r["text"]) > 100]
    assert all(r["lang_pred"] == ("de" if "ß" in r["text"] or "der" in r["text"].split() else "en") for r in long if r["doc_id"] != 13)
    none = language_id.identify_language(d.withColumn("lang", F.lit(None).cast("string")), held_out=F.lit(False), keep=["doc_id"])
    assert {r["lang_pred"] for r in none.collect()} == {"und"}
    assert language_id.identify_language(empty(spark), held_out=F.lit(False)).count() == 0


# ---------------------------------------------------------------- simhash


def brute_fingerprint(text):
    t = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    for c in "\t\n\x0b\x0c\r":
        t = t.replace(c, " ")
    w = [x for x in t.split(" ") if x]
    if not w:
        return 0
    sh = [" ".join(w[i : i + 3]) for i in range(len(w) - 2)] or [" ".join(w)]
    h = [xxhash.xxh64_intdigest(s.encode(), 42) for s in sh]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def test_simhash_equals_brute_force(spark):
    d = docs(spark)
    rows = simhash.near_duplicates(d).collect()
    expected = sorted((str(r["doc_id"]), brute_fingerprint(r["text"])) for r in d.collect())
    assert sorted((str(r["doc_id"]), r["fp"] % (1 << 64)) for r in rows) == expected
    fps = [(r["doc_id"], r["fp"] % (1 << 64)) for r in rows]
    groups = set()
    for r in rows:
        seen, todo = set(), [r["fp"] % (1 << 64)]
        while todo:
            f = todo.pop()
            for _, g in fps:
                if g not in seen and bin(f ^ g).count("1") <= 3:
                    seen.add(g)
                    todo.append(g)
        assert r["component_id"] == min((i for i, g in fps if g in seen and i is not None), default=None)
        groups.add(min(seen | {r["fp"] % (1 << 64)}))
    assert simhash.near_duplicates(empty(spark)).count() == 0
    kept = simhash.drop_near_duplicates(d).collect()
    assert len(kept) == len(groups)


def test_close_links_find_every_component(spark):
    rng = np.random.default_rng(1)
    centres = rng.integers(0, 2**63, 20, dtype=np.int64)
    fps = set(map(int, centres))
    for c in centres:
        for _ in range(12):
            f = int(c)
            for b in rng.integers(0, 63, rng.integers(1, 6)):
                f ^= 1 << int(b)
            fps.add(f)
    fps |= {-1, 0, -(1 << 63), 7, 255}
    nodes = spark.createDataFrame([(f,) for f in fps], "fp bigint")
    got = {r["node"]: r["root"] for r in connected_components(simhash.close_links(nodes)).collect()}
    label = {f: f for f in fps}
    changed = True
    while changed:
        changed = False
        for f in fps:
            low = min(label[g] for g in fps if bin((f ^ g) % (1 << 64)).count("1") <= 3)
            if low < label[f]:
                label[f], changed = low, True
    assert {f: got.get(f, f) for f in fps} == label


def test_vectors_at_three_bits_share_a_cell():
    rng = np.random.default_rng(6)
    counts = lambda f: (f & 0x5555555555555555) + (f >> 1 & 0x5555555555555555)
    masks = simhash.cell_masks()
    assert len(masks) == 64
    for _ in range(2000):
        f = int(rng.integers(0, 2**63)) * 2 + int(rng.integers(0, 2))
        g = f
        for b in rng.integers(0, 64, 3):
            g ^= 1 << int(b)
        assert any(counts(f) & m == counts(g) & m for m in masks)


def test_unlike_rows_that_share_an_id_both_stay(spark):
    base = " ".join(f"w{i}" for i in range(60))
    other = " ".join(f"v{i}" for i in range(60))
    d = docs(spark, [(1, base, None), (1, other, None), (2, base, None), (3, base, None), (None, other + " x", None), (None, None, None), (4, None, None)])
    assert sorted((str(r["doc_id"]), str(r["text"])[:2]) for r in simhash.drop_near_duplicates(d, max_bits=0).collect()) == sorted([("1", "w0"), ("1", "v0"), ("None", "v0"), ("4", "No")])
    assert simhash.drop_near_duplicates(d).columns == d.columns
    assert simhash.drop_near_duplicates(empty(spark)).count() == 0


def test_components_of_chains_have_one_root(spark):
    chain = [1, 10, 5, 11, 2]
    rng = np.random.default_rng(4)
    paths = [[100 * k + int(x) for x in rng.permutation(8)] for k in range(1, 13)]
    edges = [e for p in [chain, *paths] for e in zip(p, p[1:], strict=False)]
    rows = connected_components(spark.createDataFrame(edges, "a bigint, b bigint")).collect()
    assert sorted((r["node"], r["root"]) for r in rows) == sorted((x, min(p)) for p in [chain, *paths] for x in p)
    with pytest.raises(RuntimeError):
        connected_components(spark.createDataFrame(edges, "a bigint, b bigint"), max_rounds=1)


# ---------------------------------------------------------------- lines


def levenshtein(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        new = [i]
        for j, y in enumerate(b, 1):
            new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (x != y)))
        row = new
    return row[-1]


def test_line_dedup_equals_brute_force(spark):
    base = "this is a line of some length that repeats"
    rows = [
        (1, f"{base}\nshort\n{base}", None), (2, f"{base}s\nanother line that stays here for good", None), (3, base.replace("some", "sume") + "\n\nshort", None),
        (4, f"  {base.upper()}  ", None), (5, None, None), (6, "", None), (7, base[1:] + "\n" + base[:-1], None), (8, "aaaaaaaaaaaaaaaaaaaaaaaaaaaaaa\naaaaaaaaaaaaaaaaaaaaaaaaaaaaaaa", None),
        (9, base.replace("line", "lint").replace("some", "same"), None), (10, "aaaaaaaaaaaaaaaaaaaaaaaaaaaaab", None),
    ]
    d = docs(spark, rows)
    first, occ = {}, []
    for i, t, _ in rows:
        for no, line in enumerate((t or "").split("\n")):
            x = line.strip().lower()
            if x:
                first.setdefault(x, (i, no))
                occ.append((i, no, x))
    near = {x for x in first if len(x) >= 24 and any(len(y) >= 24 and first[y] < first[x] and x != y and levenshtein(x, y) <= 1 for y in first)}
    expected = {(i, no) for i, no, x in occ if first[x] != (i, no) or x in near}
    assert {(r["id"], r["no"]) for r in line_dedup.repeated_lines(d).collect()} == expected
    out = {r["doc_id"]: r for r in line_dedup.dedup_lines(d).collect()}
    for i, t, _ in rows:
        want = None if t is None else "\n".join(x for no, x in enumerate(t.split("\n")) if (i, no) not in expected)
        assert out[i]["text"] == want and out[i]["n_removed"] == sum(a == i for a, _ in expected)
    assert line_dedup.dedup_lines(docs(spark)).count() == docs(spark).count()
    assert line_dedup.dedup_lines(empty(spark)).count() == 0


def test_lines_of_rows_with_equal_or_null_ids_stay_apart(spark):
    a, b = "alpha line that is long enough to compare", "beta line that is quite another one here"
    c, e = "gamma line which nobody else has written", "delta line and the last of all of these"
    rows = [(0, a, None), (1, f"{a}\n{c}", None), (1, f"{b}\n{e}", None), (2, "dup line of a row that comes twice\nx", None), (2, "dup line of a row that comes twice\nx", None)]
    out = [(r["doc_id"], r["text"], r["n_removed"]) for r in line_dedup.dedup_lines(docs(spark, rows)).collect()]
    assert sorted(out) == sorted([(0, a, 0), (1, c, 1), (1, f"{b}\n{e}", 0), (2, rows[3][1], 0), (2, "", 2)])
    # a null id comes first, and its line's near copy is found
    rows = [(None, a, None), (5, a.replace("alpha", "alphas"), None), (None, b, None)]
    out = [(r["doc_id"], r["text"]) for r in line_dedup.dedup_lines(docs(spark, rows)).collect()]
    assert sorted(map(str, out)) == sorted(map(str, [(None, a), (None, b), (5, "")]))
    named = docs(spark, rows).withColumn("doc_id", F.concat(F.lit("id "), F.col("doc_id").cast("string"))).withColumn("row", F.lit(7)).withColumn("text_hash", F.lit(7))
    got = line_dedup.dedup_lines(named)
    assert got.columns == [*named.columns, "n_lines", "n_removed"] and {r["row"] for r in got.collect()} == {7}
    assert got.where("n_removed > 0").count() == 1


def test_a_line_in_most_rows_is_removed_from_all_but_one(spark):
    line = "a line that nearly every row of the table has"
    rows = [(i, f"{line}\nown line of row {i:04d} with the number {i * 7919 % 1000:03d} {i * 31 % 977:03d}", None) for i in range(300)]
    out = line_dedup.dedup_lines(docs(spark, rows).repartition(7)).collect()
    assert sum(line in r["text"] for r in out) == 1 and next(r["doc_id"] for r in out if line in r["text"]) == 0


def test_half_keys_are_shared_by_all_lines_within_one_edit():
    s = "abcdefghijk"
    others = [s[:i] + s[i + 1 :] for i in range(len(s))] + [s[:i] + "z" + s[i:] for i in range(len(s) + 1)] + [s[:i] + "z" + s[i + 1 :] for i in range(len(s))]
    assert all(set(line_dedup.half_keys(s)) & set(line_dedup.half_keys(t)) for t in others)


# ---------------------------------------------------------------- quality and mixing


def test_quality_equals_sql(spark):
    d = docs(spark)
    got = quality.quality_signals(d.select("doc_id", "text", "k0")).drop("text", "clean_text", "k0")
    cols = sorted(got.columns)
    assert sorted(tuple(str(r[c]) for c in cols) for r in got.collect()) == duck(d, quality.QUALITY_SQL, cols)
    assert quality.quality_signals(empty(spark)).count() == 0


def test_quality_repeats_by_brute_force(spark):
    texts = ["a b c d e f g h " * 3, "x " * 40, "one two three", " ".join(map(str, range(50))) + " " + " ".join(map(str, range(20, 40)))]
    d = docs(spark, [(i, t, None) for i, t in enumerate(texts)])
    for r in quality.quality_signals(d).collect():
        w = texts[r["doc_id"]].split()
        c = Counter(tuple(w[i : i + 8]) for i in range(len(w) - 7))
        cover = {p for i in range(len(w) - 7) if c[tuple(w[i : i + 8])] > 1 for p in range(i, i + 8)}
        assert (r["n_words"], r["n_repeat_words"]) == (len(w), len(cover))


def test_mixing_equals_sql_and_meets_its_targets(spark):
    d = docs(spark)
    got = mixing.mix(d).collect()
    cols = ["doc_id", "lang", "n_tokens", "probability", "sampled", "source", "topic"]
    assert sorted(tuple(str(r[c]) for c in cols) for r in got) == duck(d, mixing.mixing_sql(), cols)
    total = sum(r["n_tokens"] for r in got)
    assert math.isclose(sum(r["n_tokens"] * r["probability"] for r in got), 0.7 * total, rel_tol=0.02)
    kept = {(r["doc_id"], r["text"]) for r in mixing.sample_mix(d).collect()}
    assert {k for k, _ in kept} == {r["doc_id"] for r in got if r["sampled"]}
    assert mixing.mix(empty(spark)).count() == 0 and mixing.sample_mix(empty(spark)).count() == 0


def test_mixing_follows_given_targets(spark):
    d = docs(spark).where("doc_id is not null and text is not null")
    target = spark.createDataFrame([("en", 0.9), ("de", 0.1), ("", 0.0)], "label string, share double")
    p = {r["lang"]: r["probability"] for r in mixing.mix(d, fraction=0.2, targets={"lang": target}).where("n_tokens > 0").collect()}
    assert p["en"] > p["de"] and p[""] == 0


# ---------------------------------------------------------------- packing


@pytest.mark.parametrize("histogram", [{5: 3, 3: 4, 1: 9}, {10: 1}, {}, {7: 5, 4: 5}, {2: 101}, {9: 2, 1: 1}])
def test_shortest_pack_first_places_everything(histogram):
    patterns = packing.shortest_pack_first(histogram, 10)
    placed = Counter()
    for lengths, n in patterns:
        assert sum(lengths) <= 10 and n > 0
        for x in lengths:
            placed[x] += n
    assert placed == Counter(histogram)


def test_packing_is_gapless_and_exact(spark):
    from tokenizers import Tokenizer

    d = docs(spark)
    tok = Tokenizer.from_file(TOKENIZER)
    rows = packing.pack(d, tokenizer=TOKENIZER, max_tokens=64).collect()
    want = Counter()
    for r in d.collect():
        ids = np.array([*tok.encode(r["text"] or "", add_special_tokens=False).ids, 1], "<u4")
        for s in range(0, len(ids), 64):
            want[(r["doc_id"], s, len(ids[s : s + 64]), zlib.crc32(ids[s : s + 64].tobytes()), len(ids))] += 1
    assert Counter((r["doc_id"], r["start"], r["length"], r["ids_crc32"], r["doc_tokens"]) for r in rows) == want
    by = {}
    for r in sorted(rows, key=lambda r: (r["sequence_id"], r["offset"])):
        assert by.get(r["sequence_id"], 0) == r["offset"]
        by[r["sequence_id"]] = r["offset"] + r["length"]
    assert max(by.values()) <= 64
    assert packing.pack(empty(spark), tokenizer=TOKENIZER).count() == 0


# ---------------------------------------------------------------- pages

PAGES = [
    ("<html><body><nav><a href=1>Menu</a></nav><div class='ad'>Buy</div><article><h1>Title &amp; more</h1><p>One, two.<p>Three <b>four<br>five</p></article><footer>&copy;</footer></body></html>", "Title & more\nOne, two.\nThree four five"),
    ("<body><header>Site</header><div id=main><p>First paragraph, with some commas, and length enough to count.</p><p>Second one, also long enough, to be counted here.</p></div><div class='sidebar'><p>Side, text, here, with, commas, and, so, on, for, ever.</p></div><section id='comments'><p>Nice, post, friend, I, agree, with, this, very, much.</p></section></body>", "First paragraph, with some commas, and length enough to count.\nSecond one, also long enough, to be counted here."),
    ("<p>Unclosed <i>and plain", "Unclosed and plain"),
    ("just text &lt;3  with\n spaces", "just text <3 with spaces"), ('<p class="x>First', "First"), ('<p class="x>First</p><p>Second, and more</p><b', "First\nSecond, and more"),
    ("<body><article><p>Short teaser.</p></article><div>" + "<p>Long paragraph, with many commas, and much text, which goes on, and on.</p>" * 3 + "</div></body>", "\n".join(["Long paragraph, with many commas, and much text, which goes on, and on."] * 3)),
    ("<body><script>var a='<p>no</p>';</script><style>p{}</style><!-- <p>no</p> --><p>Yes</p><form><p>Your name</p></form></body>", "Yes"),
    ("<article><p>Body text.</p><ul><li><a href=1>Link one</a><li><a href=2>Link two</a><li><a href=3>Link three</a></ul><ul><li>Point one<li>Point two</ul></article>", "Body text.\nPoint one\nPoint two"),
    ("", ""), (None, ""), ("<nav><p>only menu</p></nav>", ""),
]


def test_deep_and_broken_pages_take_linear_time():
    n = 100_000
    pages = ["<div>" * n + "text, here", "<b>" * n + "<p>x</p>y" * n, '<p class="x>a ' * n, "<a b='x \" " * n, "<a " * n, "<p " + "a" * 10 * n + ">t", "<table>" + "<span>" * n + "<tr><td>x" * n, "<article>" * n + "<p>t", "<div>" * n + "<a href=1>x</a>" * n, "x" * 50 * n]
    began = time.perf_counter()
    texts = [html_text.main_text(p) for p in pages]
    assert time.perf_counter() - began < 60
    assert texts[0] == "text, here" and texts[4] == "" and texts[5] == "t" and texts[7] == "t" and len(texts[-1]) == 50 * n


def test_main_text_of_pages(spark):
    for html, want in PAGES:
        assert html_text.main_text(html) == want
    d = spark.createDataFrame([(i, f"u{i}", h, "x", 1) for i, (h, _) in enumerate(PAGES)] + [(0, "u0", PAGES[0][0], "x", 1)], "page_id bigint, url string, html string, text string, k0 int")
    rows = html_text.extract_main_text(d, keep=["page_id", "url"]).collect()
    assert len(rows) == len(PAGES) + 1
    assert all(r["text"] == PAGES[r["page_id"]][1] and r["n_chars"] == len(r["text"]) for r in rows)
