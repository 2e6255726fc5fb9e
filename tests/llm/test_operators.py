"""The training-data operators against brute force on small tables, and their edge cases."""

import hashlib
import zlib
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from crawltracks.llm import chat, decontamination, fingerprints, jaccard, licenses, packing, quality, sharding, substrings, template, toxicity
from crawltracks.llm.queries import public_tokenizer
from crawltracks.llm.training import keep_documents, labelled_sample, score_documents
from crawltracks.llm.words import windows, words_of

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def prose(seed: int, n: int, vocabulary: int = 400) -> str:
    r = np.random.default_rng(seed)
    return " ".join(f"w{i}" for i in r.integers(0, vocabulary, n))


@pytest.fixture(scope="module")
def texts():
    base = [prose(i, 60) for i in range(6)]
    near = base[0].split()
    near[30] = "changed"
    return [
        *base, base[1], base[1], " ".join(near), None, "", "one two", "one two", "  spaced\tout \n text  ", prose(9, 3000), prose(9, 3000) + " tail",
        base[2] + "\n" + base[3], "ha " * 50, "Licensed under CC BY-NC 4.0.", "All rights reserved. all RIGHTS reserved GNU General Public License", "é ü 漢字 " + base[4],
    ]


@pytest.fixture(scope="module")
def docs(spark, texts):
    return spark.createDataFrame([(3 * i - 5, t, None, None, None) for i, t in enumerate(texts)], DOCS).cache()


@pytest.fixture(scope="module")
def rows(docs):
    return sorted((r["doc_id"], r["text"] or "") for r in docs.collect())


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], DOCS)


@pytest.fixture(scope="module")
def clashing(docs):
    """Extra columns named like those the operators make."""
    extra = {c: F.lit("x") for c in ("shard", "bucket", "slice", "size", "key", "w", "sketch", "part", "score", "label", "class_id", "node", "rep")}
    return docs.withColumns(extra)


def shingles(text, n=5):
    w = [x for x in text.replace("\t", " ").replace("\n", " ").split(" ") if x]
    return {tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if len(w) >= n else {tuple(w)} if w else set()


def test_word_hashes_follow_texts():
    a = words_of(pa.array(["x yy\tz", None, "", "yy z"]))
    assert a.counts.tolist() == [3, 0, 0, 2] and a.hashes[1] == a.hashes[3] and a.hashes[2] == a.hashes[4]
    assert windows(a.hashes, 2)[1] == windows(a.hashes, 2)[3]
    assert len(set(words_of(pa.array([prose(1, 500)])).hashes.tolist())) == len(set(prose(1, 500).split()))


# ---- 1


def test_shards(docs, clashing, rows, spark):
    r = sharding.assign_shards(docs, shards=4).toPandas()
    assert sorted(r.doc_id) == [i for i, _ in rows] and set(r.shard) <= set(range(4))
    assert all(sorted(g) == list(range(len(g))) for _, g in r.groupby("shard").slot)
    by = dict(rows)
    assert all(x.size_ == len(by[x.doc_id].encode()) + 16 and x.text_crc32 == zlib.crc32(by[x.doc_id].encode()) for x in r.rename(columns={"size": "size_"}).itertuples())
    assert r.assign(t=r.doc_id.map(by)).groupby("t").shard.nunique().max() == 1
    again = sharding.assign_shards(clashing, shards=4).toPandas()
    key = ["doc_id", "shard", "slot"]
    assert again[key].sort_values(key).to_numpy().tolist() == r[key].sort_values(key).to_numpy().tolist()


def test_shards_are_even_with_a_hot_group(spark):
    df = spark.createDataFrame([(i, "same text" if i % 3 else prose(i, 20), None, None, None) for i in range(600)], DOCS)
    b = sharding.assign_shards(df, shards=8).groupBy("shard").agg(F.sum("size").alias("b")).toPandas().b
    assert len(b) == 8 and b.max() - b.min() <= 0.05 * b.mean() + 200
    assert sharding.assign_shards(df, target_bytes=int(b.sum()) // 3).select("shard").distinct().count() in (3, 4)


@pytest.mark.parametrize("ids", [[None] * 300, [7] * 300, [(1 << 63) - 1 - i for i in range(300)], [-(1 << 63) + i for i in range(300)], [None] * 100 + [(1 << 63) - 1, -(1 << 63)] * 100])
def test_shards_of_copies_with_extreme_ids(spark, ids):
    df = spark.createDataFrame([(i, "same text") for i in ids], "doc_id long, text string")
    got = sharding.assign_shards(df, shards=8).toPandas()
    n = got.groupby("shard").size()
    assert len(n) == 8 and n.max() - n.min() <= 3 and all(sorted(g) == list(range(len(g))) for _, g in got.groupby("shard").slot)


def brute_tree(points, sizes, leaves, first=0):
    """Shard of every point by medians over sorted points."""
    if leaves == 1 or not len(points):
        return {tuple(p): first for p in points}
    widest = int(np.argmax(points.max(axis=0).astype(object) - points.min(axis=0).astype(object)))
    order = np.argsort(points[:, widest], kind="stable")
    run, target, half = np.concatenate([[0], np.cumsum(sizes[order])]), sizes.sum() * (leaves // 2) / leaves, leaves // 2
    at = int(np.argmin(np.abs(run - target)))
    out = brute_tree(points[order[:at]], sizes[order[:at]], half, first)
    return out | brute_tree(points[order[at:]], sizes[order[at:]], leaves - half, first + half)


def test_shards_are_those_of_a_tree_over_sorted_points(spark):
    r = np.random.default_rng(6)
    df = spark.createDataFrame([(i, prose(i, int(n))) for i, n in enumerate(r.integers(1, 300, 400))], "doc_id long, text string")
    got = {x["doc_id"]: x["shard"] for x in sharding.assign_shards(df, shards=11, bins=16, slack=0.0).collect()}
    text, size = F.col("text"), (F.octet_length("text") + 16).cast("long")
    dims = sharding.default_dimensions(text, size)
    rows = df.select("doc_id", size.alias("size"), F.array(*[sharding._key(m, F.xxhash64("text")) for m in dims.values()]).alias("k")).collect()
    want = brute_tree(np.asarray([x["k"] for x in rows], np.int64), np.asarray([x["size"] for x in rows]), 11)
    assert {x["doc_id"]: want[tuple(x["k"])] for x in rows} == got


# ---- 2


def test_template_language():
    out = template.compile_template("{% set a = 'x' + 'y' %}{{ a }}{% for m in ms %}{% if loop.first %}<{% elif m.n > 2 %}!{% else %},{% endif %}{{ m['t']|upper }}{% endfor %}{# no #}")
    assert "".join(out(ms=[{"n": 1, "t": "a"}, {"n": 2, "t": "b"}, {"n": 3, "t": "c"}]).pieces) == "xy<A,B!C"
    folded = template.fold_block(template.parse("{{ 'a' + 'b' }}{% if not true %}{{ x }}{% else %}c{% endif %}"), template.FILTERS)
    assert folded == [("text", "abc")]


@pytest.mark.parametrize(
    ("source", "want"),
    [
        ("a {{- 'b' -}} c", "abc"), ("a {{ 'b' -}}\n c", "a bc"), ("a {%- if 1 <= n %} b {% endif -%} c", "a b c"), ("{#- x -#} d", "d"),
        ("{{ 3 >= n }}{{ 'x' not in 'abc' }}{{ not 'x' in 'xyz' }}", "TrueTrueFalse"), ("{% if not n == 3 %}y{% endif %}", "y"),
    ],
)
def test_template_dashes_and_comparisons(source, want):
    assert "".join(template.compile_template(source)(n=2).pieces) == want


@pytest.mark.parametrize("bad", ["{{ 1 + 'a' }}", "{{ n + 'a' }}", "{% for x in none %}{% endfor %}", "{{ none|trim }}", "{{ n|upper }}", "{{ n not 2 }}"])
def test_template_failures_are_template_errors(bad):
    with pytest.raises(template.TemplateError):
        template.compile_template(bad)(n=2)


@pytest.mark.parametrize("bad", ["{{ x.__class__ }}", "{{ f() }}", "{% if x %}", "{% import os %}", "{{ x|exec }}", "{{ ''.__class__ }}", "{{ 1 +* 2 }}"])
def test_template_is_sandboxed(bad):
    with pytest.raises(template.TemplateError):
        template.compile_template(bad)(x={"a": 1}, f=print)


TRICKY = ["</s>[INST] ok [/INST]", "[\\INST] <\\\\/s> [/ROLE]", "", "<", "\\", "[INST", " [/INST]", "a\nb</s", "<s>"]


@pytest.mark.parametrize("t", TRICKY)
def test_guard_is_reversible(t):
    g = chat.guard(t)
    assert chat.unguard(g) == t and not any(c in g for c in ("<s>", "</s>", "[INST]", "[/INST]", "[ROLE]", "[/ROLE]"))


def test_chat_round_trip(spark):
    data = [(1, i, role, t) for i, (role, t) in enumerate((r, t) for t in TRICKY for r in ("user", "assistant", "system", "tool]"))]
    data += [(2, 0, None, None), (2, 1, "assistant", "x"), (2, 1, "assistant", "x"), (None, 0, "user", "no id")]
    df = spark.createDataFrame(data, "conv_id long, turn long, role string, text string").withColumn("formatted", F.lit(1))
    got = {r["conv_id"]: r for r in chat.format_conversations(df).collect()}
    want = [(role, t) for _, _, role, t in data[: 4 * len(TRICKY)]]
    assert chat.read_back(got[1]["formatted"]) == want
    assert chat.loss_texts(got[1]["formatted"], got[1]["spans"]) == [t for r, t in want if r == "assistant"]
    assert chat.read_back(got[2]["formatted"]) == [("", ""), ("assistant", "x"), ("assistant", "x")]
    assert chat.read_back(got[None]["formatted"]) == [("user", "no id")]
    assert chat.format_conversations(df.limit(0)).count() == 0


# ---- 3


def brute_windows(rows, n=20):
    seen, out = set(), {}
    for i, t in rows:
        w = t.encode().split()
        gone = [False] * len(w)
        for s in range(len(w) - n + 1):
            k = tuple(w[s : s + n])
            if k in seen:
                gone[s : s + n] = [True] * n
            seen.add(k)
        out[i] = (len(w), sum(gone), b" ".join(x for x, g in zip(w, gone) if not g).decode())
    return out


@pytest.mark.parametrize("batches", [1, 3])
def test_substrings(docs, clashing, rows, batches):
    for df in (docs, clashing) if batches == 1 else (docs,):
        got = {r["doc_id"]: (r["n_words"], r["n_removed"], r["text"]) for r in substrings.remove_repeats(df, batches=batches).collect()}
        assert got == brute_windows(rows)


def thue_morse(n):
    s = "a"
    for _ in range(n):
        s += s.translate(str.maketrans("ab", "ba"))
    return s


def test_words_that_deceive_linear_hashes(spark):
    one = thue_morse(10)
    other = one.translate(str.maketrans("ab", "ba"))
    rest = [f"w{i}" for i in range(19)]
    df = spark.createDataFrame([(1, " ".join([one, *rest])), (2, " ".join([other, *rest]))], "doc_id long, text string")
    assert [r["n_removed"] for r in substrings.remove_repeats(df).collect()] == [0, 0]
    # a window's own hash, at the level of words
    words = [[x if c == "a" else y for c in thue_morse(4)] for x, y in (("u", "v"), ("v", "u"))]
    a, b = (words_of(pa.array([" ".join(w)])).hashes for w in words)
    assert windows(a, 16)[0] != windows(b, 16)[0]


def test_windows_are_verified_by_their_words(spark, docs, rows, monkeypatch):
    monkeypatch.setattr(substrings, "windows", lambda hashes, size: np.zeros(max(0, len(hashes) - size + 1), np.uint64))  # all fingerprints collide
    got = {r["doc_id"]: (r["n_words"], r["n_removed"], r["text"]) for r in substrings.remove_repeats(docs).collect()}
    assert got == brute_windows(rows)


def test_index_compacts_and_tells_both_sides(spark, tmp_path):
    index = substrings.FingerprintIndex(spark, parts=4, max_runs=2, folder=f"file://{tmp_path}")
    shared = prose(77, 40)
    told = []
    for b in range(4):
        df = spark.createDataFrame([(b, shared if b in (0, 3) else prose(b, 40), b)], "doc_id long, text string, slice long")
        told.append({r["slice"] for r in index.append(df).collect()})
    assert told == [set(), set(), set(), {0, 3}] and len(index.runs) <= 3
    assert sum(len(r["fps"]) // 8 for r in index._entries().collect()) >= 4
    assert len(index.replaced) >= 2
    index.vacuum()
    assert index.replaced == [] and index._entries().count() > 0


@pytest.mark.parametrize("reopened", [False, True])
def test_days_one_after_the_other(spark, texts, tmp_path, monkeypatch, reopened):
    monkeypatch.setattr(substrings, "PART_PRINTS", 16)  # compaction deals to more parts
    folder = f"file://{tmp_path}"
    index = substrings.FingerprintIndex(spark, parts=2, max_runs=2, folder=folder)
    days = [[(100 * (3 - d) + i, t) for i, t in enumerate(texts[d::3] + texts[:3])] for d in range(3)]  # later days have smaller ids
    seen = []
    for day in days:
        got = {r["doc_id"]: (r["n_words"], r["n_removed"], r["text"]) for r in substrings.remove_repeats(spark.createDataFrame(day, "doc_id long, text string"), batches=2, index=index).collect()}
        seen += [(i, t or "") for i, t in sorted(day)]
        want = brute_windows(seen)
        assert got == {i: want[i] for i, _ in day}
        if reopened:
            index.save()
            index = substrings.FingerprintIndex.open(spark, folder)
    assert index.parts > 2


def test_the_same_text_on_the_second_day(spark):
    index = substrings.FingerprintIndex(spark)
    df = spark.createDataFrame([(1, prose(3, 60, 9999))], "doc_id long, text string")
    assert [substrings.remove_repeats(df, index=index).first()["n_removed"] for _ in range(3)] == [0, 60, 60]


def test_repeated_and_missing_ids_lose_all_but_one(spark):
    a, b = prose(11, 40, 9999), prose(12, 40, 9999)
    data = [(7, a), (7, a), (7, b), (None, b), (None, b), (None, None), (9, a + " " + b)]
    df = spark.createDataFrame(data, "doc_id long, text string").withColumns({"slice": F.lit(1), "n_chars": F.lit(5), "row": F.lit("x"), "h": F.lit(2.0)})
    got = sorted(((r["doc_id"] or 0, r["n_words"], r["n_removed"]) for r in substrings.remove_repeats(df).collect()))
    assert got == [(0, 0, 0), (0, 40, 0), (0, 40, 40), (7, 40, 0), (7, 40, 40), (7, 40, 40), (9, 80, 80)]
    short = substrings.shorten(df)
    assert short.columns == df.columns
    found = sorted((r["doc_id"] or 0, len(r["text"]), r["n_chars"], r["row"], r["slice"], r["h"]) for r in short.collect())
    assert found == [(0, 0, 0, "x", 1, 2.0)] * 2 + [(0, len(b), len(b), "x", 1, 2.0)] + [(7, 0, 0, "x", 1, 2.0)] * 2 + [(7, len(a), len(a), "x", 1, 2.0), (9, 0, 0, "x", 1, 2.0)]


# ---- 4


def test_licenses(docs, clashing, rows):
    got = {r["doc_id"]: r for r in licenses.scan_licenses(docs).collect()}
    assert sorted(got) == [i for i, _ in rows]
    by = {t: got[i] for i, t in rows}
    cc = by["Licensed under CC BY-NC 4.0."]
    assert (cc["n_words"], cc["n_base"], cc["first_word"], cc["labels"]) == (7, 1, 2, "cc-by,cc-by-nc-4") and cc["score"] == 1.0
    r = by["All rights reserved. all RIGHTS reserved GNU General Public License"]
    assert (r["n_base"], r["first_word"], r["last_word"], r["base_labels"]) == (3, 0, 7, "gpl,reserved")
    assert by[""]["n_words"] == 0 and by[""]["first_word"] is None and by[""]["labels"] == ""
    again = {r["doc_id"]: r for r in licenses.scan_licenses(clashing).collect()}
    assert again == got


def test_licence_with_a_word_more(spark):
    t = "licensed under the free gnu general public license version 3"
    r = licenses.scan_licenses(spark.createDataFrame([(1, t)], "doc_id long, text string")).first()
    assert r["labels"] == "gpl,gpl-3"  # two neighbouring diagonals together


def test_licence_spans_are_verified(spark):
    mit = next(t for t in licenses.TEMPLATES if t.startswith("permission is hereby"))
    w = mit.split()
    data = [
        (1, f"see here {mit.upper()}, and more"), (2, " ".join([*w[:10], "indeed", *w[10:]])), (3, " ".join(w[:8])),  # less than three quarters
        (4, " ".join(["licensed under the mit"] * 9)), (5, "released under released under the the mit license license"), (None, mit),
    ]
    got = {r["doc_id"]: r for r in licenses.scan_licenses(spark.createDataFrame(data, "doc_id long, text string")).collect()}
    assert (got[1]["labels"], got[1]["spans"], got[1]["score"]) == ("mit", f"mit:2-{1 + len(w)}", 1.0)
    assert got[2]["labels"] == "mit" and got[2]["spans"] == f"mit:0-{len(w)}" and got[2]["score"] < 1
    assert got[3]["labels"] == got[4]["labels"] == "" and 0 < got[3]["score"] < 0.75
    assert got[4]["score"] <= 1 and got[None]["labels"] == "mit"  # positions count once, however often they are hit


def test_licences_of_repeated_rows(spark):
    texts = ["CC BY. All rights reserved", "all rights", "licensed under the gnu works", "released under the mit license", ""]
    alone = licenses.scan_licenses(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"))
    want = Counter(tuple(r[1:]) for r in alone.collect() for _ in range(3))
    for ids in ([7] * 15, [None] * 15, [1, 1, 1] * 5):
        df = spark.createDataFrame(list(zip(ids, texts * 3)), "doc_id long, text string").repartition(4)
        assert Counter(tuple(r[1:]) for r in licenses.scan_licenses(df).collect()) == want


# ---- 5


def test_fingerprints(docs, rows):
    got = {r["doc_id"]: r for r in fingerprints.compare_with_next(docs, 32).collect()}
    j = lambda a, b: 1.0 if not a | b else len(a & b) / len(a | b)
    for k, (i, t) in enumerate(rows):
        following = rows[(k + 1) % len(rows)][1]
        h = len(t) // 2
        edited = t[: len(t) - h] + following[:h]
        assert got[i]["n_chars"] == len(t) and got[i]["edited"] == edited
        assert got[i]["near_edited"] == pytest.approx(j(shingles(t), shingles(edited)), abs=0.3)
        assert got[i]["near_next"] == pytest.approx(j(shingles(t), shingles(following)), abs=0.3)
    same = defaultdict(set)
    for i, t in rows:
        same[t].add(tuple(got[i]["sketch"]))
    assert all(len(s) == 1 for s in same.values())


def test_sketch_algebra(spark):
    a, b = prose(5, 800, 5000), prose(6, 800, 5000)
    df = spark.createDataFrame([(a, a + " " + b)], "a string, ab string")
    df = fingerprints.with_sketch(fingerprints.with_sketch(df, "a", "sa"), "ab", "sab")
    A, B = F.col("sa"), F.col("sab")
    n, inside, merged = df.select(fingerprints.distinct_shingles(A), fingerprints.containment(A, B), fingerprints.merge(A, B) == B).first()
    assert n == pytest.approx(796, rel=0.3) and inside > 0.8 and merged


@pytest.mark.parametrize("k", [8, 128])
def test_sketches_are_the_least_hashes_of_all_shingles(spark, docs, rows, k):
    pieces = [(i, " ".join(x), len(x)) for i, t in rows for x in shingles(t)]
    got = {r["doc_id"]: r for r in fingerprints.with_sketch(docs.fillna({"text": ""}), "text", "sketch", k).collect()}
    five = F.split("w", " ")
    each = F.when(F.col("n") == 5, F.xxhash64(*[F.get(five, F.lit(j)) for j in range(5)])).otherwise(F.xxhash64("w"))
    want = defaultdict(set)
    for r in spark.createDataFrame(pieces, "i long, w string, n int").select("i", each.alias("h")).collect():
        want[r["i"]].add(r["h"])
    assert all(got[i]["sketch"] == sorted(want[i])[:k] for i, _ in rows)


def test_printed_sketches_can_be_read_and_merged(spark):
    a, b = prose(5, 400, 5000), prose(6, 300, 5000)
    df = spark.createDataFrame([(a, b, ""), ("", "one two", b)], "a string, b string, c string")
    for c in "abc":
        df = fingerprints.with_sketch(df, c, f"s{c}")
    back = [fingerprints.from_string(fingerprints.as_string(F.col(f"s{c}"))) == F.col(f"s{c}") for c in "abc"]
    assert [tuple(r) for r in df.select(*back).collect()] == [(True,) * 3] * 2
    whole = df.agg(fingerprints.merge_all("sa").alias("m")).first()["m"]
    assert whole == df.select("sa").first()["sa"]


@pytest.mark.parametrize("ids", [[None, 3, -(1 << 62), (1 << 63) - 1, 5, 4], [None, None, 7, 7, 7, 8]])
def test_edited_texts_of_extreme_and_missing_ids(spark, ids):
    data = [(i, f"{prose(k, 12)} t{k}") for k, i in enumerate(ids)]
    order = sorted(data, key=lambda x: (-(1 << 63) if x[0] is None else x[0], x[1]))
    got = sorted((-(1 << 63) if r["doc_id"] is None else r["doc_id"], r["edited"]) for r in fingerprints.compare_with_next(spark.createDataFrame(data, "doc_id long, text string")).collect())
    want = []
    for k, (i, t) in enumerate(order):
        after, h = order[(k + 1) % len(order)][1], len(t) // 2
        want.append((-(1 << 63) if i is None else i, t[: len(t) - h] + after[:h]))
    assert got == sorted(want)


# ---- 6


def test_passages(spark, rows, docs):
    item = prose(100, 40, 5000).split()
    odd = list(item)
    for k in (5, 14, 23, 32):
        odd[k] = "other"
    body = prose(101, 50, 5000)
    data = [(1, f"{body} {' '.join(item)} {body}"), (2, f"{body} {' '.join(odd)}."), (3, body), (4, None), (5, " ".join(item[:13]).upper()), (6, "tiny item here now")]
    df = spark.createDataFrame(data, "doc_id long, text string")
    bench = spark.createDataFrame([(10, " ".join(item)), (11, None), (12, ""), (13, "tiny item here now")], "item_id long, text string")
    got = {(r["doc_id"], r["item_id"]): r for r in decontamination.find_passages(df, bench).collect()}
    assert set(got) == {(1, 10), (2, 10), (5, 10), (6, 13)}
    assert (got[1, 10]["start"], got[1, 10]["end"], got[1, 10]["matched"]) == (50, 90, 40) and got[2, 10]["matched"] == 36
    assert [r["doc_id"] for r in decontamination.drop_contaminated(df, bench).collect()] == [3, 4]
    assert decontamination.find_passages(df, bench.limit(0)).count() == 0


def test_passages_with_words_changed_anywhere(spark):
    from itertools import combinations

    items = {n: [f"i{n}x{k}" for k in range(n)] for n in (5, 9, 15, 16, 17, 19, 25, 40)}
    bench = spark.createDataFrame([(n, " ".join(w)) for n, w in items.items()], "item_id long, text string")
    data, want = [], set()
    for n, w in items.items():
        changed = [c for k in (1, 2, 3) for c in combinations(range(n), k)] if n < 20 else [range(i, n, 5) for i in range(5)]
        for c in changed:
            text = [f"other{i}" if i in c else x for i, x in enumerate(w)]
            data.append((len(data), " ".join(["before", *text, "after"])))
            if n - len(c) >= 0.8 * n:
                want.add((len(data) - 1, n, n - len(c)))
    got = decontamination.find_passages(spark.createDataFrame(data, "doc_id long, text string").repartition(8), bench)
    got = {(r["doc_id"], r["item_id"], r["matched"]) for r in got.collect()}
    assert want <= got
    # beyond that, only parts of longer items
    assert all(m >= 13 and n > 16 for _, n, m in got - want)


def brute_passages(docs, items, least=13):
    """All diagonals of all pairs."""
    import re

    split = lambda t: re.findall("[0-9a-z\\u0080-\\U0010ffff]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
    out = []
    for i, t in docs:
        d = split(t)
        for k, u in items:
            w = split(u)
            need = -(-len(w) * 4 // 5)
            for o in range(-len(w) + 1, len(d)) if w else ():
                a, b = max(o, 0), min(o + len(w), len(d))
                same = np.asarray([d[x] == w[x - o] for x in range(a, b)])
                lo, hi, m = 0, b - a, int(same.sum())
                if m < need:
                    lo, hi, m = decontamination._best_run(same)
                if m >= min(least, need):
                    out.append((i, k, a + lo, a + hi, a + lo - o, m))
    return sorted(out)


def test_passages_are_those_of_all_diagonals(spark):
    r = np.random.default_rng(2)
    docs = [(i, " ".join(f"{'Wx'[i % 2]}{x}" if i % 7 else "ha" for x in r.integers(0, 3 + 2 * (i % 5), int(r.integers(0, 70))))) for i in range(60)]
    items = [(k, " ".join(f"w{x}" for x in r.integers(0, 4 + k % 5, int(r.integers(0, 30))))) for k in range(25)] + [(99, "ha " * 20), (100, "ha ha")]
    df = spark.createDataFrame(docs, "doc_id long, text string").withColumns({"row": F.lit(1), "seed": F.lit("x")})
    got = decontamination.find_passages(df.repartition(4), spark.createDataFrame(items, "item_id long, text string").repartition(3))
    assert sorted(tuple(x)[:6] for x in got.collect()) == brute_passages(docs, items)


def test_a_word_that_fills_texts(spark, monkeypatch):
    monkeypatch.setattr(decontamination, "CHUNK", 1 << 10)
    places, item = np.sort(np.random.default_rng(1).choice(9000, 4000, replace=False)), np.arange(5, 300, 2)
    got, want = decontamination._votes(places, item), np.unique((places[:, None] - item[None, :]).ravel(), return_counts=True)
    assert (got[0] == want[0]).all() and (got[1] == want[1]).all()
    df = spark.createDataFrame([(1, "na " * 40_000), (None, "na " * 10), (1, "clean")], "doc_id long, text string")
    bench = spark.createDataFrame([(1, "na " * 300)], "item_id long, text string")
    assert decontamination.find_passages(df, bench).count() == 40_000 + 300 - 2 * 13 + 1
    kept = [tuple(x) for x in decontamination.drop_contaminated(df, bench).collect()]
    assert (1, "clean") in kept and (1, "na " * 40_000) not in kept


# ---- 7, 10


@pytest.mark.parametrize(("make", "good", "bad"), [(quality.ByteConvNet, lambda i: prose(i, 80), lambda i: " ".join(f"{w}###" for w in prose(i, 80).split())), (toxicity.ToxicityNet, lambda i: prose(i, 120), lambda i: prose(i, 60) + " vile " + prose(i + 9999, 59))])
def test_models_learn(spark, make, good, bad):
    texts = [f(i) for i in range(150) for f in (bad, good)]
    y = np.asarray([0, 1] * 150, np.float32) if make is quality.ByteConvNet else np.asarray([1, 0] * 150, np.float32)
    net = make().fit(texts, y, epochs=8)
    test = [f(i) for i in range(1000, 1040) for f in (bad, good)]
    p = net(pa.array([*test, None, ""]))
    assert ((p[:-2] > 0.5) == np.tile(y[:2], 40)).mean() > 0.95 and p[-1] == p[-2]
    long = " ".join(good(i) for i in range(3000, 3100))
    both = net(pa.array([long, long + " " + bad(7)]))
    assert both[0] != both[1]  # the end of a long text counts
    df = spark.createDataFrame([(i, t, 5.0) for i, t in enumerate([*test, None])], "doc_id long, text string, score double")
    assert {r["doc_id"]: r["score"] for r in score_documents(df, net).collect()} == pytest.approx(dict(enumerate(net(pa.array([*test, None])))), abs=1e-5)
    kept = keep_documents(df, net, 0.5)
    assert kept.columns == df.columns and kept.count() == int((net(pa.array([*test, None])) < 0.5).sum())
    alone = make().fit(texts[:1], y[:1])
    assert alone(pa.array(["x"]))[0] == y[0] and make().fit([], np.zeros(0, np.float32))(pa.array(["x"]))[0] == 0.5


def test_held_out_labels_are_not_learnt(spark):
    docs = spark.createDataFrame([(i, f"t{i}") for i in range(200)], "doc_id long, text string")
    labels = spark.createDataFrame([(i, i % 2 if i % 7 else None) for i in range(200)], "doc_id long, quality int")
    got, y = labelled_sample(docs, labels, "quality", 1000, 1 << 20)
    ids = [int(t[1:]) for t in got]
    assert all(zlib.crc32(str(i).encode()) % 5 for i in ids) and len(ids) > 100 and list(y) == [i % 2 for i in ids]


# ---- 8


def brute_links(rows):

    ids = [i for i, _ in rows]
    found = {i: shingles(t) for i, t in rows}
    links, parent = Counter(), {i: i for i in ids}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a in range(len(ids)):
        for b in range(a + 1, len(ids)):
            x, y = found[ids[a]], found[ids[b]]
            if x and y and len(x & y) >= 0.8 * len(x | y):
                links[ids[a]] += 1
                links[ids[b]] += 1
                p, q = root(ids[a]), root(ids[b])
                parent[max(p, q)] = min(p, q)
    return {i: (root(i), links[i]) for i in ids}


def test_near_classes(docs, clashing, rows):
    got = {r["doc_id"]: (r["class_id"], r["n_links"]) for r in jaccard.near_classes(clashing).collect()}
    assert got == brute_links(rows)
    kept = sorted(r["doc_id"] for r in jaccard.one_of_each_class(docs).collect())
    assert kept == sorted({c for c, _ in got.values()})


def test_near_classes_of_a_large_group(spark):
    base = prose(500, 200).split()
    data = []
    for i in range(700):
        w = list(base)
        w[i % 200] = f"x{i}"
        data.append((i, " ".join(w)))
    got = {r["doc_id"]: (r["class_id"], r["n_links"]) for r in jaccard.near_classes(spark.createDataFrame(data, "doc_id long, text string")).collect()}
    assert got == brute_links(data)


def test_near_pairs_in_large_buckets(spark, monkeypatch):
    monkeypatch.setattr(jaccard, "SMALL", 8)  # buckets of the last depth are large, their cells of 32
    monkeypatch.setattr(jaccard, "DEPTH", 2)
    monkeypatch.setattr(jaccard, "CELL", 16, raising=False)
    r = np.random.default_rng(5)
    shared = [f"s{i}" for i in range(90)]
    data = []
    for k in range(150):  # pairs of near-copies around a passage that all share
        family = [f"f{k}x{i}" for i in range(30)]
        for _ in range(2):
            data.append((len(data), " ".join([*shared, *family, *(f"o{x}" for x in r.integers(0, 1 << 40, 6))])))
    got = {r["doc_id"]: (r["class_id"], r["n_links"]) for r in jaccard.near_classes(spark.createDataFrame(data, "doc_id long, text string"), recall=0.9999).collect()}
    assert got == brute_links(data)
    assert got[1] == (0, 1) and {n for _, n in got.values()} == {1}


def test_runs_count_shared_coordinates():
    n, r = 200_000, np.random.default_rng(3)
    share = r.binomial(jaccard.COORDS, 0.8, n) / jaccard.COORDS
    runs = jaccard.runs_needed(0.8, 0.999)
    lost = np.where(share * jaccard.COORDS >= jaccard.least_alike(0.8), jaccard.miss(share, 0.8) ** runs, 1.0)
    assert lost.mean() <= 0.001
    # one run of the branching itself
    alive = np.ones(50_000, int)
    for _ in range(jaccard.DEPTH):
        alive = r.binomial(alive + r.binomial(alive, 0.25), 0.8)
    assert (alive == 0).mean() == pytest.approx(float(jaccard.miss(np.asarray([0.8]), 0.8)[0]), abs=0.03)


def headed(n, shared, own, r, first=0):
    """Texts that share a header and nothing else."""
    head = [f"h{i}" for i in range(shared)]
    return [(first + k, " ".join([*head, *(f"o{x}" for x in r.integers(0, 1 << 40, own))])) for k in range(n)]


def classes_of(spark, data):
    df = spark.createDataFrame(data, "doc_id long, text string").repartition(8)
    sets = jaccard._sets(df, 5).cache()
    rough = jaccard.candidate_classes(sets.where("sign is not null").select("rep", "sign"), 0.8, 0.999)
    return {(r["first_id"], r["label"]) for r in rough.join(sets, rough.id == sets.rep).collect()}


def test_candidates_meet_and_unrelated_texts_do_not(spark, monkeypatch):
    monkeypatch.setattr(jaccard, "SMALL", 6)  # buckets are split to the last depth
    monkeypatch.setattr(jaccard, "CELL", 64)
    r = np.random.default_rng(8)
    data = headed(1200, 70, 41, r)  # similarity about 0.46
    pairs = []
    for k in range(200):  # and pairs at 0.8 to 0.85 with the same header
        words = [*(f"h{i}" for i in range(70)), *(f"o{x}" for x in r.integers(0, 1 << 40, 45))]
        other = list(words)
        other[80], other[100] = "x", "y"
        data += [(5000 + 2 * k, " ".join(words)), (5001 + 2 * k, " ".join(other))]
        pairs.append((5000 + 2 * k, 5001 + 2 * k))
    found = dict(classes_of(spark, data))
    sizes = Counter(found.values())
    met = sum(a in found and found.get(a) == found.get(b) for a, b in pairs)
    assert met / len(pairs) >= 0.99
    assert max(sizes.values()) <= 12  # one class held 813 of 1,200 with half as many coordinates


def test_links_of_texts_whose_ids_repeat_or_are_missing(spark):
    a, b = prose(1, 60), prose(2, 60)
    near = b.split()
    near[3] = "changed"
    near = " ".join(near)
    for ids in ((5, 5, 7), (None, None, 7), (None, None, None), (5, 5, 5)):
        df = spark.createDataFrame(list(zip(ids, (a, b, near))), "doc_id long, text string")
        got = sorted(r["n_links"] for r in jaccard.near_classes(df).collect())
        assert got == [0, 1, 1], ids
        assert jaccard.one_of_each_class(df).count() == 2
    got = {r["n_links"]: r["class_id"] for r in jaccard.near_classes(spark.createDataFrame([(None, b), (7, near), (9, a)], "doc_id long, text string")).collect()}
    assert got == {1: 7, 0: 9}


def test_one_row_of_each_class_stays(spark):
    a, b = prose(1, 60), prose(2, 60)
    data = [(4, a, 1), (4, a, 2), (None, a, 3), (None, b, 4), (None, b, 5), (6, None, 6), (6, "", 7), (6, " ", 8), (None, None, 9)]
    df = spark.createDataFrame(data, "doc_id long, text string, key int").repartition(5)
    kept = jaccard.one_of_each_class(df)
    assert kept.columns == df.columns
    rows = [tuple(r) for r in kept.collect()]
    assert sorted(r[2] for r in rows if not (r[1] or "").strip()) == [6, 7, 8, 9]
    assert sorted((r[0] or 0, r[1]) for r in rows if (r[1] or "").strip()) == sorted([(4, a), (0, b)])


# ---- 9


def test_packing(docs, clashing, rows):
    from tokenizers import Tokenizer

    encode = Tokenizer.from_file(public_tokenizer()[0])
    for df in (docs.repartition(3), clashing):
        got = packing.pack(df, public_tokenizer(), capacity=256, open_windows=4).toPandas()
        by = dict(rows)
        for i, pieces in got.groupby("doc_id"):
            pieces = pieces.sort_values("start")
            ids = np.concatenate([np.frombuffer(x, np.uint32) for x in pieces.ids]).tolist()
            assert ids == [*encode.encode(by[i], add_special_tokens=False).ids, 0] and (pieces.doc_tokens == len(ids)).all()
        for _, seq in got.groupby("sequence_id"):
            seq = seq.sort_values("offset")
            assert seq.offset.tolist() == [0, *seq.length.cumsum()[:-1]] and seq.length.sum() <= 256
        assert len(got.doc_id.unique()) == len(rows)


def test_end_of_text_strings_and_odd_spaces():
    b = packing.ByteBpe(*public_tokenizer())
    for t in ("a <|endoftext|> b", "  two  spaces ", "tab\tand\r\nline", "é漢字", "x" * 3000):
        assert np.frombuffer(b(t), np.uint32).tolist() == b.encoder.encode(t, add_special_tokens=False).ids


# ---- all


def test_empty_tables(spark, empty):
    bench = spark.createDataFrame([(1, "a b c d e f g h i j k l m n")], "item_id long, text string")
    for made in (
        sharding.assign_shards(empty), substrings.remove_repeats(empty), licenses.scan_licenses(empty), fingerprints.compare_with_next(empty),
        decontamination.find_passages(empty, bench), jaccard.near_classes(empty), packing.pack(empty, public_tokenizer()),
    ):
        assert made.count() == 0


def test_null_ids_are_kept(spark):
    df = spark.createDataFrame([(None, "a b c"), (1, "d e f"), (2, None)], "doc_id long, text string")
    assert {r["doc_id"] for r in jaccard.one_of_each_class(df).collect()} == {None, 1, 2}
    assert {r["doc_id"] for r in substrings.remove_repeats(df).collect()} == {None, 1, 2}


def test_pipeline_stages(spark, small, tmp_path):
    import corpus_pipeline as cp

    docs = spark.read.parquet(f"{small}/documents.parquet")
    assert [n for n, _ in cp.STAGES] == ["toxicity", "jaccard", "substring", "decontamination", "packing"]
    before = docs
    for name, stage in cp.STAGES[1:4]:
        after = stage(spark, before, small)
        assert after.columns == docs.columns, name
        after.write.parquet(str(tmp_path / name))
        before = spark.read.parquet(str(tmp_path / name))
    texts = docs.toPandas()
    links = brute_links(sorted((int(i), t or "") for i, t in zip(texts.doc_id, texts.text)))
    kept = sorted({c for c, _ in links.values()})
    assert sorted(r["doc_id"] for r in spark.read.parquet(str(tmp_path / "jaccard")).select("doc_id").collect()) == kept
    by = dict(zip(texts.doc_id, texts.text))
    want = brute_windows([(i, by[i] or "") for i in kept])
    left = {r["doc_id"]: r["text"] for r in spark.read.parquet(str(tmp_path / "substring")).collect()}
    assert left == {i: x[2] for i, x in want.items()}
    hashes = {hashlib.sha256(t.encode()).hexdigest() for t in left.values()}
    assert len(hashes) > 1
