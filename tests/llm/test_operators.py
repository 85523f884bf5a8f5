"""Each corpus operator on small tables with nulls, empty and long texts, ties, repeats and clashing names, against
brute force, a round trip or SQL."""

import hashlib
import re
import zlib

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from relseq.llm import ann, language_id, line_dedup, media, mixing, near_dup, packing, quality, suffix_dedup, warc

DATA = "/root/testdata"
WORD = re.compile(r"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
CLASH = ["id", "key", "rank", "value", "size", "block", "lines", "runs", "row", "taken", "k1", "features"]


def words(n, seed=0, kinds=400):
    draw = np.random.default_rng(seed)
    return " ".join(f"w{i}" for i in draw.integers(0, kinds, n))


@pytest.fixture(scope="module")
def odd(spark):
    base = words(120, 1)
    near = base.split(" ")
    near[60] = "changed"
    rows = [
        (1, base, "en", "a", 1), (2, base, "en", "a", 1), (3, " ".join(near), "fr", "b", 1), (4, None, None, None, None), (5, "", "en", "a", 0), (6, " \n\t ", "en", "b", 0),
        (7, "one two", "de", "c", 7), (8, "ONE  two", "de", "c", 8), (9, words(30_000, 2), "en", "a", 1), (10, "é漢字🙂 " * 40, "xx", None, 1), (11, words(40, 3) + " " + base[100:400], "en", "b", 1),
        (12, "a" * 5000, None, "a", 1), (13, "ab" * 3000, "en", "c", 1), (7, "one two", "de", "c", 7), (None, base, "en", "a", 1), (14, "l1 x\nl2 y\nl3 z\n\nl4", "en", "a", 1), (15, "q\nl1 x\nl2 y\nl3 z\nl9", "en", "a", 1), (16, "l2 y\nl3 z\nl2 y\nl3 z", "en", "b", 1),
    ]
    df = spark.createDataFrame(rows, SCHEMA)
    return df.select("*", *[F.lit(i).alias(c) for i, c in enumerate(CLASH)]).persist()


@pytest.fixture(scope="module")
def empty(odd):
    return odd.limit(0)


def text_rows(df):
    return [(r["doc_id"], r["text"]) for r in df.select("doc_id", "text").collect()]


# -- 1 ----------------------------------------------------------------------------------------------------------


def brute_removed(rows, length=50):
    rows = sorted({(-(2**63) if i is None else i, t or "") for i, t in rows})
    first = {}
    out = {}
    for i, t in rows:
        raw = t.encode()
        for p in range(len(raw) - length + 1):
            first.setdefault(raw[p : p + length], i)
    for i, t in rows:
        raw = t.encode()
        gone = np.zeros(len(raw), bool)
        for p in range(len(raw) - length + 1):
            if first[raw[p : p + length]] < i:
                gone[p : p + length] = True
        spans = int(gone[0]) + int((gone[1:] & ~gone[:-1]).sum()) if len(gone) else 0
        out[i] = (len(raw), int(gone.sum()), spans, hashlib.sha256(bytes(np.frombuffer(raw, np.uint8)[~gone])).hexdigest())
    return out


def check_removed(df):
    want = brute_removed(text_rows(df))
    got = suffix_dedup.remove_repeats(df).collect()
    assert len(got) == df.count()
    for r in got:
        i = -(2**63) if r["doc_id"] is None else r["doc_id"]
        assert (r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) == want[i]
        assert hashlib.sha256(r["kept"]).hexdigest() == r["kept_sha256"]


def test_suffix_dedup(odd):
    check_removed(odd)


def test_suffix_dedup_on_shifted_passages(spark):
    draw = np.random.default_rng(5)
    passage = words(60, 8)
    rows = []
    for i in range(40):
        a = int(draw.integers(0, len(passage) - 49))
        b = int(draw.integers(a + 49, len(passage) + 1))
        rows.append((i, words(20, i + 50) + passage[a:b] + words(20, i + 90), "en", "s", 1))
    check_removed(spark.createDataFrame(rows, SCHEMA))


def test_suffix_dedup_empty(empty):
    assert suffix_dedup.remove_repeats(empty).count() == 0


@pytest.mark.parametrize("seed", range(5))
def test_merge_of_front_coded_runs(seed):
    draw = np.random.default_rng(seed)
    runs, every = [], []
    for _ in range(draw.integers(1, 7)):
        rows = np.sort(draw.integers(0, 3, (draw.integers(1, 60), suffix_dedup.SPAN)).astype(np.uint8).view(f"S{suffix_dedup.SPAN}"), axis=0).view(np.uint8).reshape(-1, suffix_dedup.SPAN)
        rows[:, : draw.integers(20, 84)] = 1
        rows = rows[suffix_dedup._order(rows)]
        shared, rest = suffix_dedup.front_code(rows)
        assert (suffix_dedup.unfold(shared, rest) == rows).all()
        runs.append((shared.tobytes(), rest.tobytes()))
        every.append(rows)
    run, at, shared = suffix_dedup.merge_runs(runs)
    merged = np.array([every[r][a] for r, a in zip(run, at)])
    whole = np.concatenate(every)
    assert (merged == whole[suffix_dedup._order(whole)]).all()
    assert (shared[1:] == suffix_dedup._shared_prefix(merged)[1:]).all()


# -- 2 ----------------------------------------------------------------------------------------------------------


def test_media(odd, empty):
    want = text_rows(odd)
    got = media.media_features(media.encode_media(odd)).collect()
    assert len(got) == len(want)
    payloads = {}
    for i, t in want:
        raw = (t or "").encode()
        p = raw + b" " * (-len(raw) % 192 if raw else 192)
        payloads[i] = (len(raw), len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-16:]))
    for r in got:
        assert (r["n_bytes"], r["payload_bytes"], r["payload_sha256"], r["tail_crc32"]) == payloads[r["doc_id"]]
    by_text = {}
    for (i, t), r in zip(sorted(want, key=str), sorted(got, key=lambda r: str((r["doc_id"], None)))):
        by_text.setdefault(r["payload_sha256"], set()).add((r["media_sha256"], r["feature"]))
    assert all(len(v) == 1 for v in by_text.values())
    assert media.media_features(media.encode_media(empty)).count() == 0


def test_long_text_takes_several_files():
    raw = bytes(range(256)) * 13_000
    [pixels] = media.from_media(media.to_media([raw]))
    assert pixels[..., :3].tobytes()[: len(raw)] == raw and len(pixels) > media.webp.SIDE


# -- 3 ----------------------------------------------------------------------------------------------------------


def test_archives(spark, tmp_path):
    big = "<html>" + "x" * 200 + "\r\n\r\nWARC/1.1\r\n</html>"
    rows = [(5, "http://a/", big), (3, "http://b/\r\n", big), (9, None, big), (1, "http://c/", "short"), (2, "http://d/", "short"), (4, "http://e/", None), (6, "http://f/", ""), (7, "http://g/", "é" * 60), (3, "http://b/\r\n", big), (None, "http://h/", "<p>" * 50)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("digest", F.lit(1)).withColumn("n", F.lit(2))
    path = str(tmp_path / "w")
    warc.write_archives(pages, path)
    records = warc.read_archives(spark, path)
    assert records.groupBy("type").count().collect()
    every = warc.captures(warc.assemble(records)).collect()
    assert len(every) == len(rows) == records.select("record_id").distinct().count() / 3
    got = {r["page_id"]: r for r in every}
    assert sum(r["page_id"] == 3 for r in every) == 2 and {r["refers_to"] for r in every if r["page_id"] == 3} == {None}
    assert (got[3]["record_type"], got[3]["refers_to"]) == ("response", None)
    assert all((got[i]["record_type"], got[i]["refers_to"]) == ("revisit", 3) for i in (5, 9))
    for i, _, html in rows:
        raw = (html or "").encode()
        assert (got[i]["payload_bytes"], got[i]["payload_digest"]) == (len(raw), hashlib.sha256(raw).hexdigest())
    assert all(got[i]["record_type"] == "response" for i in (1, 2, 4, 6, 7, None))
    none = str(tmp_path / "none")
    warc.write_archives(pages.limit(0), none)
    assert warc.captures(warc.assemble(warc.read_archives(spark, none))).count() == 0


def test_repeated_pages_all_come_back(spark, tmp_path, monkeypatch):
    """Rows equal in everything, pages of one id with other urls, and files of few records for long pages."""
    monkeypatch.setattr(warc, "AGAIN", 3)
    monkeypatch.setattr(warc, "FILE_BYTES", 1 << 19)
    html, long = "<html>" + "y" * 150, "z" * 300_000
    rows = [(4, "http://a/", html)] * 8 + [(4, "http://b/", html)] * 2 + [(6, "http://a/", html)] * 4 + [(None, "http://a/", html)] * 2 + [(7, None, "tiny")] * 5 + [(8, "http://l/", long), (9, "http://l/", long + "!"), (10, "http://l/", long)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    path = str(tmp_path / "w")
    warc.write_archives(pages, path)
    found = warc.read_archives(spark, path)
    assert found.count() == 3 * len(rows) == found.select("record_id").distinct().count()
    got = sorted((r["page_id"] is None, r["page_id"], r["url"] or "", r["record_type"], r["refers_to"]) for r in warc.captures(warc.assemble(found)).collect())
    def kind(page, text):
        lead = {html: 4, long: 8}.get(text)
        return ("response", None) if lead is None or page == lead else ("revisit", lead)
    assert got == sorted((i is None, i, u or "", *kind(i, t)) for i, u, t in rows)
    missing = found.where("type = 'revisit'").join(found.where("type = 'response'").selectExpr("record_id as refers_to"), "refers_to", "left_anti")
    assert missing.count() == 0


def test_parser_takes_any_pieces_and_refuses_damage():
    block = b"HTTP/1.1 200 OK\r\n\r\nbody\r\n\r\nWARC/1.1"
    head = f"WARC/1.1\r\nWARC-Type: response\r\nWARC-Record-ID: <x>\r\nContent-Type: application/http\r\nContent-Length: {len(block)}\r\n\r\n".encode()
    data = (head + block + b"\r\n\r\n") * 3
    whole = list(warc.parse(iter([data])))
    assert len(whole) == 3 and whole[0][5] == len(block) - 19
    for n in (1, 7, 50):
        assert list(warc.parse(data[i : i + n] for i in range(0, len(data), n))) == whole
    with pytest.raises(ValueError):
        list(warc.parse(iter([data[:-20]])))


# -- 4 ----------------------------------------------------------------------------------------------------------


def brute_lines(rows, least=2, long=50):
    """Windows of ``least`` lines, and single lines of ``long`` words, that stood earlier."""
    rows = sorted({(-(2**63) if i is None else i, t or "") for i, t in rows})
    seen, single, out = set(), set(), {}
    full = {i: [(n, x) for n, x in enumerate(t.split("\n")) if WORD.search(x)] for i, t in rows}
    for i, t in rows:
        gone = set()
        for p in range(len(full[i]) - least + 1):
            w = tuple(x for _, x in full[i][p : p + least])
            if w in seen:
                gone |= {full[i][q][0] for q in range(p, p + least)}
            seen.add(w)
        for n, x in full[i]:
            if x in single and len(WORD.findall(x)) >= long:
                gone.add(n)
            single.add(x)
        out[i] = "\n".join(x for n, x in enumerate(t.split("\n")) if n not in gone)
    return out


@pytest.mark.parametrize("least", [1, 2, 3])
def test_lines(odd, least):
    want = brute_lines(text_rows(odd), least)
    got = line_dedup.dedupe_lines(odd, min_lines=least, drop_emptied=False)
    assert got.columns == odd.columns and got.count() == odd.count()
    for r in got.collect():
        assert (r["text"] or "") == want[-(2**63) if r["doc_id"] is None else r["doc_id"]]


@pytest.mark.parametrize("hot", [2, 10_000])
def test_lines_of_shared_passages(spark, monkeypatch, hot):
    """Passages on one line between other neighbours, copies, long runs and a line that is everywhere."""
    monkeypatch.setattr(line_dedup.store.with_groups, "__defaults__", (hot,))
    draw = np.random.default_rng(6)
    passage, short, run = words(51, 21), words(49, 22), [f"part {i}" for i in range(37)]
    rows = []
    for i in range(60):
        own = [f"own {i} {k}" for k in range(int(draw.integers(1, 9)))]
        own.insert(int(draw.integers(0, len(own))), [passage, short, "Menu"][i % 3])
        if i % 4 == 0:
            a = int(draw.integers(0, 30))
            own += run[a : a + int(draw.integers(1, 37))]
        rows.append((i, "\n".join([*own, "Menu"][:: 1 if i % 2 else -1])))
    rows += [(100 + i, rows[7 * i][1]) for i in range(8)] + [(200, passage), (201, passage), (202, short), (203, short), (204, "Menu"), (205, "Menu")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    want = brute_lines(rows)
    assert not want[201] and want[203] == short and want[205] == "Menu"
    assert {r["doc_id"]: r["text"] for r in line_dedup.dedupe_lines(df, drop_emptied=False).collect()} == want


def test_suffix_order_and_runs(spark):
    draw = np.random.default_rng(2)
    base = [f"line {i}" for i in range(30)]
    rows = [(0, "\n".join(base)), (1, "\n".join(["x", *base[3:14], "y", *base[20:22]])), (2, "\n".join(f"line {i}" for i in draw.integers(0, 4, 40))), (3, "\n".join([*base[3:14], "", "z"]))]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    seqs = {i: [x for x in t.split("\n") if x] for i, t in rows}
    places = [(i, p) for i, own in seqs.items() for p in range(len(own))]
    got = {(r["k1"], r["seq"]): (r["length"], r["rank"]) for r in line_dedup.suffix_order(df).collect()}
    for i, p in places:
        longest = 0
        for j, q in places:
            if (i, p) != (j, q):
                n = 0
                while p + n < len(seqs[i]) and q + n < len(seqs[j]) and seqs[i][p + n] == seqs[j][q + n]:
                    n += 1
                longest = max(longest, n)
        assert ((i, p) in got) == (longest > 0) and (not longest or got[(i, p)][0] <= longest < 2 * got[(i, p)][0])
    runs = {(r["k1"], r["seq"], r["lines"], r["f1"], r["fseq"]) for r in line_dedup.repeated_runs(df).collect()}
    assert {(1, 1, 11, 0, 3), (1, 13, 2, 0, 20), (3, 0, 11, 0, 3)} <= runs
    assert line_dedup.suffix_order(df.limit(0)).count() == 0 and line_dedup.repeated_runs(df.limit(0)).count() == 0


def test_lines_empty(empty):
    assert line_dedup.dedupe_lines(empty).count() == 0


# -- 5 ----------------------------------------------------------------------------------------------------------


def test_language_profiles(spark, odd, empty):
    docs = spark.read.parquet(f"{DATA}/sf0.01/documents.parquet")
    got = language_id.op5_language_id(spark, f"{DATA}/sf0.01").join(docs.select("doc_id", "lang"), "doc_id").where("held_out")
    right, n = got.select(F.sum((F.col("lang") == F.col("lang_pred")).cast("int")), F.count("*")).first()
    assert right / n > 0.97
    labels, model = language_id.learn(docs)
    out = language_id.classify(odd.select("doc_id", "text", "key"), labels, model).collect()
    assert len(out) == odd.count() and all(0 <= r["score"] <= 1 for r in out)
    assert all(r["lang_pred"] == "und" for r in out if r["doc_id"] in (4, 5, 6))
    assert language_id.learn(empty)[0] == [] and language_id.classify(odd.select("doc_id", "text"), *language_id.learn(empty)).where("lang_pred <> 'und'").count() == 0
    assert language_id.classify(empty.select("doc_id", "text"), labels, model).count() == 0


def brute_profile(text):
    """The bound and bundled vector of a text, letter by letter; None without letters."""
    table, base, symbols = language_id.symbol_table(), language_id.letters().astype(float), [0]
    for ch in (text or "") + " ":
        s = int(table[ord(ch)])
        if s or symbols[-1]:
            symbols.append(s)
    bound = [np.roll(base[a], 2) * np.roll(base[b], 1) * base[c] for a, b, c in zip(symbols, symbols[1:], symbols[2:])]
    return np.mean(bound, axis=0) if bound else None


def test_language_profiles_equal_brute_force(spark):
    texts = [("the cat sat on the mat, the end", "en"), ("this thing that then", "en"), ("der hund und die katze", "de"), ("und nicht auch ich", "de"), ("le chat et la souris", "fr"), ("12 34", "fr"), (None, "en"), ("les gens", None)]
    asked = [*(t for t, _ in texts), "", "a", "Ünd DIE", "\U00030000\U00030001 \U00031350", "the\n\tthe " * 3000, "漢字 кот", "🙂 -- 9"]
    by_lang = {}
    for text, lang in texts:
        if lang and (one := brute_profile(text)) is not None:
            by_lang.setdefault(lang, []).append(one)
    names = sorted(by_lang)
    means = np.array([np.mean(by_lang[x], axis=0) for x in names])
    centre = means.mean(axis=0)
    labels, model = language_id.learn(spark.createDataFrame(texts, "text string, lang string"))
    assert labels == names
    np.testing.assert_allclose(model, np.vstack((means - centre, centre)), atol=1e-4)
    out = language_id.classify(spark.createDataFrame(list(enumerate(asked)), "doc_id long, text string"), labels, model).collect()
    assert len(out) == len(asked)
    for r in out:
        vector = brute_profile(asked[r["doc_id"]])
        if vector is None:
            assert (r["lang_pred"], r["score"]) == ("und", 0)
            continue
        vector = vector - centre
        cosines = [vector @ m / np.linalg.norm(vector) / np.linalg.norm(m) for m in means - centre]
        assert r["score"] == pytest.approx((1 + max(cosines)) / 2, abs=1e-3)
        assert cosines[names.index(r["lang_pred"])] == pytest.approx(max(cosines), abs=1e-3)
    assert {r["doc_id"] for r in out if r["lang_pred"] == "und"} == {5, 6, 8, 14}


# -- 6 ----------------------------------------------------------------------------------------------------------


def brute_components(rows, width, percent=80):
    low = str.maketrans({chr(65 + i): chr(97 + i) for i in range(26)})
    sets = {}
    for i, t in rows:
        w = WORD.findall((t or "").translate(low))
        sets[i] = {tuple(w[j : j + width]) for j in range(max(1, len(w) - width + 1))} if w else set()
    ids = sorted(i for i in sets if i is not None)
    parent = {i: i for i in ids}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a in ids:
        for b in ids:
            if a < b and sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                x, y = sorted((root(a), root(b)))
                parent[y] = x
    return {i: (len(sets[i]), root(i)) for i in ids}


@pytest.mark.parametrize("width", [4, 5])
def test_near_duplicates(odd, width):
    want = brute_components(text_rows(odd), width)
    got = near_dup.near_duplicates(odd, width=width).collect()
    assert len(got) == odd.count()
    for r in got:
        if r["doc_id"] is None:
            assert r["component_id"] is None and r["kept"]
        else:
            assert (r["n_shingles"], r["component_id"]) == want[r["doc_id"]] and r["kept"] == (r["doc_id"] == r["component_id"])


def test_near_duplicates_in_a_large_family(spark):
    """Chains and copies with more and fewer changes than the threshold allows, around one original."""
    draw = np.random.default_rng(3)
    base = words(150, 4, 5000).split(" ")
    rows = []
    for i in range(160):
        w = list(base)
        for p in draw.integers(0, len(w), int(draw.integers(0, 9))):
            w[p] = f"x{draw.integers(0, 10**6)}"
        if i % 5 == 0:
            del w[: int(draw.integers(0, 40))]
        rows.append((i, " ".join(w), "en", "s", 1))
    step = list(base[:80])
    for i in range(30):
        step = step[2:] + [f"c{i}", f"d{i}"]
        rows.append((500 + i, " ".join(step), "en", "s", 1))
    df = spark.createDataFrame(rows, SCHEMA)
    want = brute_components([(r[0], r[1]) for r in rows], 4)
    assert {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in near_dup.near_duplicates(df, width=4).collect()} == want


def test_near_duplicates_empty(empty):
    assert near_dup.near_duplicates(empty).count() == 0


# -- 7 ----------------------------------------------------------------------------------------------------------


def test_neighbours(spark):
    draw = np.random.default_rng(1)
    points = draw.normal(size=(3000, 16))
    rows = [(i, [float(x) for x in p]) for i, p in enumerate(points)]
    rows += [(4000 + i, rows[7][1]) for i in range(40)]
    rows += [(5000, None), (5001, [0.0] * 16), (5002, [float("nan")] * 16), (5003, [None] * 16), (5004, [1.0, 2.0]), (None, rows[0][1])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").withColumn("rank", F.lit(1))
    good = ann.usable(df, "vec_id", "embedding").persist()
    ids = np.array([r[0] for r in rows[:3040]])
    x = np.array([r[1] for r in rows[:3040]])
    x = x / np.linalg.norm(x, axis=1)[:, None]
    three = ann.shard_counts(good, 1100)
    assert sorted(map(tuple, three.collect())) == [(2, 1), (16, 3)]
    got = ann.search(ann.build(good, three), good.where("vec_id % 50 = 0 and vec_id < 5000"), three).toPandas()
    hit = n = 0
    for q in [i for i in ids if i % 50 == 0]:
        at = int(np.flatnonzero(ids == q)[0])
        s = x @ x[at]
        s[at] = -9
        best = np.lexsort((ids, -np.round(s, 12)))[:5]
        own = got[got.query_id == q].sort_values("rank")
        assert list(own["rank"]) == [1, 2, 3, 4, 5] and q not in set(own.vec_id)
        assert np.allclose(own.score, [float(x[at] @ x[np.flatnonzero(ids == v)[0]]) for v in own.vec_id])
        hit += len(set(ids[best]) & set(own.vec_id))
        n += 5
    assert hit / n >= 0.9
    copies = got[got.query_id == 4000].sort_values("rank")
    assert list(copies.vec_id) == [7, 4001, 4002, 4003, 4004]
    few = ann.usable(df.where("vec_id < 3"), "vec_id", "embedding")
    one = ann.shard_counts(few)
    assert ann.search(ann.build(few, one), few.where("vec_id = 0"), one).count() == 2
    none = ann.usable(df.limit(0), "vec_id", "embedding")
    assert ann.search(ann.build(none, one), none, one).count() == 0


@pytest.mark.parametrize("shard_rows", [4, 1000])
def test_neighbours_of_scaled_copies_and_other_lengths(spark, shard_rows):
    """Multiples of a vector tie and go by id, whatever their scale; other lengths are another space."""
    rows = [(0, [1.0, 0.0, 0.0])] + [(989 + j, [2.0**j, 0.0, 0.0]) for j in range(11)] + [(50, [3.0, 1.0, 2.0])]
    rows += [(2000 + j, [0.3 * x * (j + 1) for x in (3.0, 1.0, 2.0)]) for j in range(9)] + [(100, [1.0, 1.0]), (3001, [2.0, 2.0]), (3002, [1e-300, 1e-300]), (3003, [1e300, 1.1e300])]
    good = ann.usable(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), "vec_id", "embedding")
    counts = ann.shard_counts(good, shard_rows)
    got = {}
    for r in ann.search(ann.build(good, counts), good.where("vec_id % 50 = 0 and vec_id < 900"), counts).orderBy("query_id", "rank").collect():
        got.setdefault(r["query_id"], []).append((r["vec_id"], r["score"]))
    assert [v for v, _ in got[0]] == [989, 990, 991, 992, 993] and all(s == 1.0 for _, s in got[0])
    assert [v for v, _ in got[50]] == [2000, 2001, 2002, 2003, 2004] and all(abs(s - 1) < 1e-12 for _, s in got[50])
    assert [v for v, _ in got[100]] == [3001, 3002, 3003]


def test_neighbours_recall_of_the_query(spark):
    c = duckdb.connect()
    d = f"{DATA}/sf0.1"
    rows = c.execute(f"select vec_id, embedding from '{d}/embeddings.parquet' where embedding is not null").fetchall()
    ids = np.array([r[0] for r in rows])
    x = np.array([r[1] for r in rows], float)
    x = x / np.linalg.norm(x, axis=1)[:, None]
    got = {}
    for r in ann.op7_hnsw_neighbours(spark, d).collect():
        got.setdefault(r["query_id"], []).append(r["score"])
    hit = n = 0
    for at in np.flatnonzero(ids % 50 == 0):
        s = x @ x[at]
        s[at] = -9
        fifth = np.sort(s)[-5]
        hit += sum(v >= fifth - 1e-9 for v in got[int(ids[at])])
        n += 5
    assert hit / n >= 0.95


# -- 8 ----------------------------------------------------------------------------------------------------------


def water(sizes, weights=(5, 2, 1), cap=3):
    names = sorted(sizes, key=lambda s: (s is None, s or ""))
    w = {s: weights[i % 3] for i, s in enumerate(names)}
    left, open_, out = float(sum(sizes.values())), set(names), {}
    while open_:
        share = left / sum(w[s] for s in open_)
        full = {s for s in open_ if share * w[s] > cap * sizes[s]}
        for s in full or open_:
            out[s] = cap * sizes[s] if full else share * w[s]
            left -= out[s]
        open_ -= full or open_
    return out


def test_mix(odd, empty):
    got = mixing.plan_mix(odd).collect()
    docs = [(r["doc_id"], r["text"], r["source"]) for r in odd.collect()]
    sizes = {}
    for _, t, s in docs:
        sizes[s] = sizes.get(s, 0) + len(WORD.findall(t or ""))
    want = water(sizes)
    assert len(got) == len(docs)
    source = {i: s for i, _, s in docs}
    taken = {}
    for r in got:
        s = source[r["doc_id"]]
        assert r["source_size"] == sizes[s] and r["target"] == pytest.approx(want[s]) and 0 <= r["taken"] <= 3 * r["size"]
        taken[s] = taken.get(s, 0) + r["taken"]
    assert all(abs(taken[s] - want[s]) <= 0.5 for s in sizes)
    again = {(r["doc_id"], r["size"], r["taken"]) for r in mixing.plan_mix(odd.repartition(5)).collect()}
    assert again == {(r["doc_id"], r["size"], r["taken"]) for r in got}
    assert mixing.plan_mix(empty).count() == 0
    mixed = mixing.apply_mix(odd)
    assert mixed.columns == odd.columns and mixed.groupBy("doc_id", "text").count().agg(F.max("count")).first()[0] <= 6


@pytest.mark.parametrize("broadcast", [0, 1000])
def test_mix_of_clashing_names_and_an_id_in_two_sources(spark, monkeypatch, broadcast):
    monkeypatch.setattr(mixing, "BROADCAST_SOURCES", broadcast)
    rows = [(i, words(10 + i, i), "big", i, "r") for i in range(40)] + [(i, words(3, i), "small", i, "r") for i in range(3)] + [(100 + i, words(9, i), None, i, "r") for i in range(20)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string, __copy int, row string")
    plan = mixing.plan_mix(docs, partial=False)
    want = {}
    for r in plan.collect():
        want[(r["doc_id"], r["size"])] = want.get((r["doc_id"], r["size"]), 0) + r["repeats"]
    mixed = mixing.apply_mix(docs)
    assert mixed.columns == docs.columns
    got = {}
    for r in mixed.collect():
        assert (r["doc_id"], r["text"], r["source"], r["__copy"], r["row"]) in rows
        key = (r["doc_id"], len(r["text"].split()))
        got[key] = got.get(key, 0) + 1
    assert got == {k: n for k, n in want.items() if n} and len({i for i, _ in got if i < 3}) == 3


def test_mix_equals_sql(spark):
    c = duckdb.connect()
    c.execute(f"create view documents as select * from '{DATA}/sf0.001/documents.parquet'")
    want = sorted(c.execute(mixing.OP8_SQL).fetchall())
    assert sorted(map(tuple, mixing.op8_mix_sources(spark, f"{DATA}/sf0.001").collect())) == want


# -- 9 ----------------------------------------------------------------------------------------------------------


def test_packing(odd, empty):
    import public_tokenizers
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(public_tokenizers.path(packing.VOCABULARY))
    want = []
    for i, text in text_rows(odd):
        ids = t.encode(text or "", add_special_tokens=False).ids + [0]
        for k in range(0, len(ids), 2048):
            part = np.array(ids[k : k + 2048], "<u4")
            want.append((i, k // 2048, k, len(part), zlib.crc32(part.tobytes())))
    got = packing.best_fit_pack(odd).toPandas()
    assert sorted(map(str, want)) == sorted(str((None if np.isnan(r.doc_id) else int(r.doc_id), int(r.piece), int(r.start), int(r.length), int(r.ids_crc32))) for r in got.itertuples())
    check_bins(got)
    assert packing.best_fit_pack(empty).count() == 0


def check_bins(got):
    got = got.sort_values(["sequence_id", "offset"])
    by = got.groupby("sequence_id")
    assert (by.length.cumsum() - got.length == got.offset).all() and by.length.sum().max() <= 2048


def test_short_way_equals_the_tokenizer():
    e = packing.encoder(packing.VOCABULARY)
    for text in ("it's Don't <|endoftext|> a", "a\x1cb", "É'ÉS ½ ²x _a__b 12 '", "ǅ x", "ﬁ á", "a b  c\n\td e", "it’s “q” Ω", "İx ıI", "a1b22 ª º ß", "漢字🙂 x", "''s 're'", "x\u0085y"):
        assert e(text) == e.whole(text), text


@pytest.mark.parametrize("seed", range(6))
def test_plan_places_every_piece_and_is_tight(seed):
    draw = np.random.default_rng(seed)
    low, high = ((1, 2049), (683, 2049), (1, 683), (1, 60), (600, 1100), (1024, 1026))[seed]
    lengths = draw.integers(low, high, 700)
    histogram = {int(a): int(b) for a, b in zip(*np.unique(lengths, return_counts=True))}
    bins, count = {}, 0
    for length, lo, hi, first, per, at in packing.plan_packing(histogram):
        for r in range(hi - lo):
            bins.setdefault(first + r // per, []).append((at + r % per * length, length))
            count += 1
    assert count == 700
    for own in bins.values():
        end = 0
        for at, length in sorted(own):
            assert at == end
            end += length
        assert end <= 2048
    assert len(bins) <= item_by_item(lengths)


def item_by_item(lengths, capacity=2048):
    """Sequences that best fit in descending order takes, a piece at a time."""
    gaps = []
    for x in sorted(map(int, lengths), reverse=True):
        at = min((i for i, g in enumerate(gaps) if g >= x), key=lambda i: gaps[i], default=None)
        if at is None:
            gaps.append(capacity - x)
        else:
            gaps[at] -= x
    return len(gaps)


# -- 10 ---------------------------------------------------------------------------------------------------------


def test_quality(spark, odd, empty):
    d = f"{DATA}/sf0.1"
    docs = spark.read.parquet(f"{d}/documents.parquet").select("doc_id", "text")
    grades = quality.label_grades(spark, d).withColumn("held", F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0)
    model = quality.train(docs, grades.where("not held"))
    got = quality.score(docs, model).join(grades.where("held"), "doc_id").withColumn("kept", F.col("tail_prob") >= 0.5)
    share = {r["grade"]: r["share"] for r in got.groupBy("grade").agg(F.avg(F.col("kept").cast("double")).alias("share")).collect()}
    assert share[2] > 0.97 and share[0] < 0.15 and share[1] < 0.4  # from 3200 labelled rows
    assert list(model.thresholds) == sorted(model.thresholds)
    out = quality.score(odd, model)
    assert out.count() == odd.count() and out.where("tail_prob is null or expected_grade < 0 or expected_grade > 2").count() == 0
    kept = quality.select_quality(odd, grades.select("doc_id", "grade"))
    assert kept.columns == odd.columns
    none = grades.limit(0).select("doc_id", "grade")
    assert quality.select_quality(odd, none).count() == odd.count()
    assert quality.select_quality(empty, none).count() == 0


def test_gradient_of_the_ordinal_fit():
    """Separable grades along one feature come out in order, with ordered thresholds."""
    grades = np.repeat([0, 1, 2], 40)
    feature = grades + 7
    model = quality.fit(grades, feature, np.arange(121), 3)
    w = model.weights[[7, 8, 9]]
    assert w[0] < w[1] < w[2]
    tails = model.tails(w)
    assert (tails[:, 0] >= tails[:, 1]).all() and tails[0, 0] < 0.5 < tails[2, 1] and tails[1, 1] < 0.5 < tails[1, 0]


# -- pipeline ---------------------------------------------------------------------------------------------------


def test_pipeline_stages(spark):
    import corpus_pipeline as p

    d = f"{DATA}/sf0.01"
    docs = spark.read.parquet(f"{d}/documents.parquet")
    names = docs.columns
    for name, stage in p.STAGES:
        before = docs
        docs = p.store.materialise(stage(spark, before, d), name)
        if name == "line_dedup":
            want = brute_lines(text_rows(before))
            got = dict(text_rows(docs))
            assert all(want[i] == t for i, t in got.items())
            assert all(not WORD.search(want[i]) for i, _ in text_rows(before) if i not in got)
        if name == "near_duplicates":
            low = brute_components([(i, t) for i, t in text_rows(before) if i % 3 == 0], 5)
            assert {i for i, _ in text_rows(docs)} <= {i for i, _ in text_rows(before)}
            kept = {i for i, _ in text_rows(docs)}
            assert all(r in kept or i not in kept for i, (_, r) in low.items())
        if name == "best_fit_packing":
            check_bins(docs.toPandas())
        else:
            assert docs.columns == names
    assert docs.count() and [n for n, _ in p.STAGES] == ["quality_classifier", "line_dedup", "near_duplicates", "source_mixing", "best_fit_packing"]


def test_stages_take_odd_tables(spark, odd, empty):
    import corpus_pipeline as p

    for docs in (odd.select("doc_id", "text", "lang", "source", "n_chars"), empty.select("doc_id", "text", "lang", "source", "n_chars")):
        for name, stage in p.STAGES:
            out = stage(spark, docs, f"{DATA}/sf0.01")
            assert out.count() >= 0 and (name == "best_fit_packing" or out.columns == docs.columns)
