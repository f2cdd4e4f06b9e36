"""The operators on Spark: defined results for odd rows, and brute force on small tables."""

import hashlib
import math
import random
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from overlapgraph.llm import audio, bpe, exact_dedup, html_main, langid, licenses, mixing, probminhash, quality, quotes, textvec
from overlapgraph.llm.common import materialise, read_table
from overlapgraph.llm.queries import QUERIES, bpe_path

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
#: Columns whose names operators use inside or return.
CLASH = ["kept", "k", "key", "size", "score", "file", "row", "a.b", "at", "digest", "words", "src", "target", "copies", "n", "id", "v", "predicted", "class_id", "rec", "each", "tag", "cut", "sub", "__file", "__row", "__copies", "__copy"]


def odd_docs(spark):
    rng = random.Random(5)
    long = " ".join(rng.choice(["river", "stone", "light", "fleuve", "maison"]) for _ in range(30_000))
    rows = [
        (1, "a  b\tc", "en", "s1", 6), (2, "a b c", None, "s1", 5), (2, "a b c", None, "s1", 5), (3, None, "en", None, None), (4, "", "fr", "s2", 0), (5, " \n", None, None, 2),
        (None, "a b c", "en", "s1", 5), (None, None, None, None, None), (6, long, "en", "s1", len(long)), (7, long + " end", "en", "", len(long)), (8, "日本 é 😀 <|endoftext|>", "fr", "s3", 1),
    ]
    df = spark.createDataFrame(rows, DOCS)
    for c in CLASH:
        df = df.withColumn(c, F.lit("x"))
    return df


def none_of(df):
    return df.where(F.lit(False))


def norm(t):
    return re.sub(r"[\x20\x09-\x0D]+", " ", t or "")


def brute_groups(rows):
    groups = {}
    for i, t in rows:
        groups.setdefault(norm(t), []).append(i)
    return groups


@pytest.mark.parametrize("weak", [False, True])
def test_exact_dedup_odd_rows(spark, weak):
    df = odd_docs(spark)
    kw = {"digest": lambda t: F.substring(F.sha2(t.cast("binary"), 256), 1, 1)} if weak else {}
    got = exact_dedup.exact_duplicates(df, files_per_batch=1 if weak else None, **kw).collect()
    groups = brute_groups([(r.doc_id, r.text) for r in df.collect()])
    assert len(got) == df.count()
    for r in got:
        ids = next(g for t, g in groups.items() if hashlib.sha256(t.encode()).hexdigest() == r.text_sha256)
        known = [i for i in ids if i is not None]
        assert r.group_size == len(ids) and r.keep_id == (min(known) if known else None)
    assert sum(r.kept for r in got) == len(groups)
    assert exact_dedup.exact_duplicates(none_of(df)).count() == 0
    assert exact_dedup.drop_copies(df).columns == df.columns


def test_exact_dedup_over_runs_and_a_restart(spark, tmp_path):
    days = [[(5, "a b"), (6, "c"), (7, "a  b")], [(2, "a\tb"), (8, "d"), (9, "c"), (None, "d")], [(1, "e"), (10, "a b"), (11, "d")]]
    state, seen, got = f"file://{tmp_path}/state", [], {}
    for i, day in enumerate(days):
        spark.createDataFrame(day, "doc_id long, text string").write.parquet(f"{tmp_path}/docs/day{i}")
        seen += day
        docs = spark.read.parquet(f"{tmp_path}/docs/day{i}")
        archive = spark.read.option("recursiveFileLookup", "true").parquet(f"{tmp_path}/docs")
        for _ in range(2 if i == 1 else 1):  # the second day's run is repeated, as after a failure
            got[i] = exact_dedup.exact_duplicates(docs, state_dir=state, run=f"day{i}", archive=archive).collect()
        groups = brute_groups(seen)
        assert len(got[i]) == len(day)
        for r in got[i]:
            ids = next(g for t, g in groups.items() if hashlib.sha256(t.encode()).hexdigest() == r.text_sha256)
            known = [d for d in ids if d is not None]
            assert (r.group_size, r.keep_id) == (len(ids), min(known)) and r.kept == (r.doc_id == r.keep_id)
    # a digest that different texts share is told apart across runs too
    weak = {"digest": lambda t: F.lit("same")}
    state = f"file://{tmp_path}/weak"
    for i in range(2):
        docs = spark.read.parquet(f"{tmp_path}/docs/day{i}")
        archive = spark.read.parquet(*[f"{tmp_path}/docs/day{j}" for j in range(i + 1)])
        out = exact_dedup.exact_duplicates(docs, state_dir=state, run=f"day{i}", archive=archive, **weak).collect()
    groups = brute_groups(days[0] + days[1])
    assert sorted((r.doc_id or 0, r.group_size) for r in out) == sorted((d or 0, len(groups[norm(t)])) for d, t in days[1])


def test_exact_dedup_of_a_hot_text(spark, monkeypatch):
    from overlapgraph.llm import common

    monkeypatch.setattr(common, "HOT_ROWS", 20)
    monkeypatch.setattr(exact_dedup, "BROADCAST_ROWS", 30)
    rows = [(i, "the same text" if i % 3 == 0 else f"text {i // 2}") for i in range(300)]
    got = exact_dedup.exact_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    groups = brute_groups(rows)
    text = dict(rows)
    assert len(got) == 300 and all((r.keep_id, r.group_size) == (min(groups[text[r.doc_id]]), len(groups[text[r.doc_id]])) for r in got)


@pytest.mark.parametrize("shape", ["chain", "star", "comb", "random", "none"])
def test_components(spark, shape, monkeypatch):
    from overlapgraph.llm import components as cc

    rng, n = random.Random(9), 300
    links = {
        "chain": [(i, i + 1) for i in range(n)], "star": [(n + 5, i) for i in range(n)], "none": [],
        "comb": [(i, i + 1) for i in range(0, n, 3)] + [(1000 - i, i) for i in range(n)], "random": [(rng.randrange(n), rng.randrange(n)) for _ in range(n // 2)],
    }[shape]
    tables, write = [], cc.materialise
    monkeypatch.setattr(cc, "materialise", lambda df, name: tables.append(name) or write(df, name))
    got = {r.v: r.root for r in cc.components(spark.createDataFrame(links, "a long, b long")).collect()}
    up = {v: v for a, b in links if a != b for v in (a, b)}

    def root(a):
        while up[a] != a:
            a = up[a]
        return a

    for a, b in links:
        if a != b:
            up[max(root(a), root(b))] = min(root(a), root(b))
    assert got == {v: root(v) for v in up}
    # a chain of 300 links is contracted in one round of about log2(300) doublings
    assert tables.count("cc-label") <= 4 and len(tables) < 30


def test_scratch_tables_are_dropped(spark, sf):
    from overlapgraph.llm import common

    docs = read_table(spark, sf, "documents").limit(50)
    mark = common.scratch_mark()
    assert probminhash.near_duplicates(docs).count() == 50 and exact_dedup.drop_copies(docs).count() <= 50
    left = [p.rsplit("/", 1)[1].rsplit("-", 1)[0] for p in common._made[mark:]]
    assert len(left) <= 8
    common.drop_scratch(spark, mark)
    assert len(common._made) == mark


def test_a_cluster_must_name_the_shared_folder(spark, monkeypatch):
    from overlapgraph.llm import common

    class Conf:
        def get(self, *_):
            return None

    class Session:
        conf = Conf()
        sparkContext = type("C", (), {"master": "spark://host:7077"})()

    with pytest.raises(ValueError):
        common.shared_dir(Session())


def edited(rng, base, edits):
    t = list(base)
    for at in rng.sample(range(len(t)), edits):
        t[at] = f"y{rng.randrange(10**8)}"
    return t


def near_corpus(rng):
    """Small groups, repeating texts, families around the threshold, cousins below it, texts longer than a block, odd texts."""
    texts, vocab = [], [f"w{i}" for i in range(400)]
    for _ in range(12):
        base = [rng.choice(vocab) for _ in range(rng.choice([30, 60, 200]))]
        texts += [edited(rng, base, rng.choice([0, 0, 1, 2])) for _ in range(rng.choice([1, 2, 6]))]
    # shingles that repeat weigh more: the probability Jaccard similarity decides, not that of the sets
    for _ in range(12):
        base, loop = [f"b{rng.randrange(10**6)}" for _ in range(120)], [f"l{rng.randrange(10**6)}" for _ in range(6)]
        texts += [edited(rng, base, rng.choice([0, 1, 2, 3])) + loop * rng.choice([1, 2, 20, 60]) for _ in range(4)]
    for f in range(2):
        base = [f"f{f}w{rng.randrange(10**6)}" for _ in range(230)]
        texts += [edited(rng, base, rng.choice([2, 4, 5, 6, 7])) for _ in range(130)]
    # a core of 200 shingles and a tail of 26: cousins have similarity 0.794, pairs with two common words after the core 0.808
    core, at = [f"c{rng.randrange(10**9)}" for _ in range(204)], len(texts)
    texts += [core + [f"t{i}x{j}" for j in range(26)] for i in range(400)]
    for i in range(0, 160, 20):
        texts[at + i + 200][204:206] = texts[at + i][204:206]
    long = [f"z{rng.randrange(5000)}" for _ in range(60_000)]
    texts += [long, [*long, "tail"], [*long, "other", "tail"]]
    rows = [(i, " ".join(t)) for i, t in enumerate(texts)]
    n = len(rows)
    rows += [(n, rows[0][1]), (n + 1, "  " + rows[0][1].upper()), (n + 2, None), (n + 3, ""), (n + 4, "one"), (None, "one")]
    return rows + [(None, rows[5][1]), (None, "an id is null for this text of ten words too"), (7, "and this text has the id of another one"), (7, "an id is null for this text of ten words too")]


def test_near_duplicates_against_brute_force(spark):
    """Links by the definition of the similarity for all pairs: none is lost, none is added."""
    rows = near_corpus(random.Random(6))
    assert max(len(t or "") for _, t in rows) > 1 << 18
    sets, holders = [], {}
    for i, (_, t) in enumerate(rows):
        w = [x for x in re.split(r"[\x20\x09-\x0D]+", (t or "").lower()) if x]
        count = {}
        for a in range(max(1, len(w) - 4)) if w else ():
            count[tuple(w[a : a + 5])] = count.get(tuple(w[a : a + 5]), 0) + 1
        sets.append({s: 1 + math.log(c) for s, c in count.items()})
        for s in count:
            holders.setdefault(s, []).append(i)
    up = list(range(len(rows)))

    def root(a):
        while up[a] != a:
            a = up[a]
        return a

    blank = [i for i, s in enumerate(sets) if not s]
    links = [(blank[0], b) for b in blank[1:]]
    for a, b in {(a, b) for some in holders.values() for b in some for a in some if a < b}:
        share = [sum(x[k] for k in sets[a].keys() & sets[b].keys()) / sum(x.values()) for x in (sets[a], sets[b])]
        plain = max(*sets[a].values(), *sets[b].values()) == 1
        if plain:
            sim = len(sets[a].keys() & sets[b].keys()) / len(sets[a].keys() | sets[b].keys())
        else:
            # the definition takes quadratic time: not for pairs that cannot reach it, nor for the long texts, which are alike
            sim = 0 if min(share) < 0.7 else min(share) if len(sets[a]) > 2000 else probminhash.probability_jaccard(sets[a], sets[b])
        if sim >= 0.8:
            links.append((a, b))
    for a, b in links:
        up[max(root(a), root(b))] = min(root(a), root(b))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    out = probminhash.near_duplicates(docs)
    mates = {}
    for a in range(len(rows)):
        mates.setdefault(root(a), []).append(a)
    want = sorted(((rows[a][0] is None, rows[a][0] or 0), min((rows[b][0] for b in m if rows[b][0] is not None), default=None), len(m)) for m in mates.values() for a in m)
    have = sorted(((r.doc_id is None, r.doc_id or 0), r.class_id, r.class_size) for r in out.collect())
    print(f"links of brute force: {len(links)}; classes: {len(mates)}")
    assert have == want and out.where("kept").count() == len(mates)


def test_near_duplicates_odd_rows(spark):
    df = odd_docs(spark)
    out = probminhash.near_duplicates(df)
    assert out.count() == df.count() and out.where("kept").count() == out.select("class_id").distinct().count()
    assert probminhash.near_duplicates(none_of(df)).count() == 0
    assert probminhash.drop_near_copies(df).columns == df.columns


def brute_mix(rows, seed=mixing.SEED):
    """The mix by plain loops: rows of (doc, source, words)."""
    key = lambda s: "1" if s is None else "0" + s
    size = {}
    for _, s, w in rows:
        size[key(s)] = size.get(key(s), 0) + w
    weight = {s: float(mixing.WEIGHTS[i % 3]) for i, s in enumerate(sorted(size))}
    total, open_, target = float(sum(size.values())), set(size), {}
    while True:
        share = (total - sum(target.values())) / sum(weight[s] for s in open_) if open_ else 0
        full = {s for s in open_ if 3.0 * size[s] <= share * weight[s]}
        if not full:
            return size, {**target, **{s: share * weight[s] for s in open_}}
        target |= {s: 3.0 * size[s] for s in full}
        open_ -= full


def test_mixing(spark, sf):
    docs = read_table(spark, sf, "documents")
    got = mixing.mix(docs).collect()
    rows = [(r.doc_id, r.source, len(re.findall(r"[^\x20\x09-\x0D]+", r.text or ""))) for r in docs.collect()]
    size, target = brute_mix(rows)
    src = {r[0]: r[1] for r in rows}
    taken = {}
    for r in got:
        s = "1" if src[r.doc_id] is None else "0" + src[r.doc_id]
        assert r.source_size == size[s] and r.target == pytest.approx(target[s]) and r.taken <= 3 * r.size
        taken[s] = taken.get(s, 0) + r.taken
    biggest = {s: max(r.size for r in got if ("1" if src[r.doc_id] is None else "0" + src[r.doc_id]) == s) for s in size}
    assert all(abs(taken[s] - target[s]) <= biggest[s] for s in size)
    assert sorted(map(tuple, got)) == sorted(map(tuple, mixing.mix(docs.repartition(7)).collect()))
    assert mixing.emit(docs).groupBy("doc_id").count().collect().__len__() == sum(1 for r in got if r.copies)


def test_mixing_odd_rows(spark):
    df = odd_docs(spark)
    out = mixing.mix(df).collect()
    assert len(out) == df.count() and all(r.taken <= 3 * r["size"] for r in out)
    assert mixing.mix(none_of(df)).count() == 0 and mixing.emit(df).columns == df.columns
    blank = spark.createDataFrame([(1, None, "en", "a", 0)], DOCS)
    assert [tuple(r) for r in mixing.mix(blank).collect()] == [(1, 0, 0, 0.0, 0, 0)]


def test_mixing_of_repeated_and_null_ids(spark, monkeypatch):
    monkeypatch.setattr(mixing, "BLOCK_ROWS", 20)
    rng = random.Random(2)
    rows = [(None if i % 3 else 64 * (i // 200), " ".join(["w"] * rng.choice([1, 2, 5])) + (f" t{i}" if i % 2 else ""), "hot" if i % 3 else "s") for i in range(900)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    size, target = brute_mix([(d, s, len(t.split())) for d, t, s in rows])
    out = mixing.mix(df).collect()
    assert len(out) == 900
    for s in size:
        mine = [r for r in out if r.source_size == size[s]]
        assert abs(sum(r.taken for r in mine) - target[s]) <= 10
    assert sorted(map(str, out)) == sorted(map(str, mixing.mix(df).collect()))
    assert mixing.emit(df).count() == sum(r.copies for r in out)


def test_bpe(spark):
    from tokenizers import Tokenizer

    df, lib = odd_docs(spark), Tokenizer.from_file(bpe_path())
    want = sorted((r.doc_id or -1, len(ids := lib.encode(r.text or "", add_special_tokens=False).ids), hashlib.sha256((r.text or "").encode()).hexdigest(), ids) for r in df.collect())
    got = sorted((r.doc_id or -1, r.n_tokens, r.decoded_sha256, list(r.ids)) for r in bpe.encode(df, bpe_path()).collect())
    assert got == want and bpe.encode(none_of(df), bpe_path()).count() == 0


def test_audio(spark):
    df = odd_docs(spark)
    got = audio.audio_features(df).collect()
    texts = df.collect()
    assert len(got) == len(texts)
    by_len = sorted((len((r.text or "").encode()), r.doc_id or -1) for r in texts)
    assert sorted((r.n_bytes, r.doc_id or -1) for r in got) == by_len
    payloads = {hashlib.sha256(p).hexdigest(): p for p in (audio.as_payload(r.text or "")[0] for r in texts)}
    for r in got:
        assert r.tail_crc32 == zlib.crc32(payloads[r.payload_sha256][-64:]) and r.payload_bytes == len(payloads[r.payload_sha256])
        table = audio.load_tensors(r.tensors)
        assert len(table) == r.n_tensors and f"tensors={r.n_tensors}" in r.feature and table.schema.field("values").type.shape == [64, 32]
    assert audio.audio_features(none_of(df)).count() == 0


def test_language_and_quality(spark, sf):
    docs, labels = read_table(spark, sf, "documents"), read_table(spark, sf, "labels")
    out = langid.predict(docs, langid.fit(docs)).join(docs.select("doc_id", "lang"), "doc_id").where("held_out").collect()
    assert sum(r.lang == r.lang_pred for r in out) / len(out) > 0.85
    for r in out:
        assert 0 <= r.score <= 1 and zlib.crc32(str(r.doc_id).encode()) % 3 == 1
    model = quality.fit(docs, labels)
    scored = quality.predict(docs, model)
    out = scored.join(labels, "doc_id").where("held_out").collect()
    assert sum(r.predicted == r.quality for r in out) / len(out) > 0.8
    odd = odd_docs(spark)
    assert {r.lang_pred for r in langid.predict(odd, langid.fit(odd)).where("doc_id in (3, 4, 5)").collect()} == {"und"}
    assert langid.predict(odd, langid.fit(none_of(odd))).where("score <> 0").count() == 0
    assert quality.predict(odd, quality.fit(odd, none_of(labels))).where("score = 0.5 and predicted = 1").count() == odd.count()
    assert quality.keep_good(odd, model).columns == odd.columns and quality.predict(none_of(odd), model).count() == 0


def test_pages(spark):
    model = html_main.train(300)
    rows = [(1, "u", "<article><p>Text &amp; more.</p></article><footer>&copy; x</footer>"), (None, None, None), (2, "u", ""), (2, "u", "")]
    df = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("text", F.lit("clash")).withColumn("n_chars", F.lit(9))
    got = sorted(((r.page_id or 0), r.text, r.n_chars) for r in html_main.extract(df, model).collect())
    assert got == [(0, "", 0), (1, "Text & more.", 12), (2, "", 0), (2, "", 0)]
    assert html_main.extract(none_of(df), model).count() == 0


def brute_licenses(text):
    body = re.sub(r"[^\w\n]+|_+", " ", (text or "").lower())
    body = re.sub(r" *\n *", "\n", body).strip(" \n")
    parts = set(re.split(r"\n+", body)) | {p.replace("\n", " ") for p in re.split(r"\n{2,}", body)} | {re.sub(r"\n+", " ", body)}
    hits = []
    for p in parts:
        a = set(licenses.bigrams(p.split(" ")))
        found = []
        for name, t in licenses.TEMPLATES:
            b = set(licenses.bigrams(licenses.normal_words(t)))
            d = 2 * len(a & b) / (len(a) + len(b))
            if d >= 0.8:
                found.append((-d, name))
        if found:
            hits.append(found)
    flat = sorted(f for h in hits for f in h)
    return len(hits), ",".join(sorted({n for _, n in flat})), flat[0][1] if flat else None, -flat[0][0] if flat else None


def test_licenses_against_brute_force(spark, sf):
    extra = [(900, licenses.TEMPLATES[5][1].replace(", ", ",\n")), (901, "x\n\n" + licenses.TEMPLATES[0][1].upper() + "\n\nRELEASED  under the MIT licence"), (902, None), (903, ""), (None, "Released under the MIT License.")]
    extra += [(904, licenses.TEMPLATES[6][1].replace("WARRANTY", "PROMISE").replace("CLAIM", "SUIT")), (905, " ".join(t for _, t in licenses.TEMPLATES))]
    df = read_table(spark, sf, "documents").select("doc_id", "text").unionByName(spark.createDataFrame(extra, "doc_id long, text string"))
    got = {(r.doc_id): (r.n_hits, r.licences, r.best_licence, r.best_dice) for r in licenses.scan(df).collect()}
    for r in df.collect():
        n, names, best, dice = brute_licenses(r.text)
        assert got[r.doc_id][:3] == (n, names, best), r.doc_id
        assert got[r.doc_id][3] == (None if dice is None else pytest.approx(dice))
    odd = odd_docs(spark)
    assert licenses.scan(odd).count() == odd.count() and licenses.scan(none_of(odd)).count() == 0


def test_licenses_and_quotes_run_no_python(spark, sf):
    for df in (licenses.scan(read_table(spark, sf, "documents")), quotes.link_quotes(read_table(spark, sf, "conversations"))):
        plan = df._jdf.queryExecution().toString()
        assert "Python" not in plan and "Arrow" not in plan and "Pandas" not in plan


def test_quotes(spark):
    rows = [
        (1, 0, "user", "Shall we meet at noon?\nBring the map."),
        (1, 1, "assistant", "On Monday A wrote:\n> Shall we meet  at NOON?\n\nYes, noon is fine."),
        (1, 2, "user", "> > Shall we meet at noon?\n> Yes, noon is fine.\nGood."),
        (1, 3, "user", "> Bring the map.\nWhich map?\n> nobody said this"),
        (1, 4, "user", "no quotes here"),
        (1, 5, "user", "> Good.\nthanks"),
        (2, 0, "user", "> Shall we meet at noon?"),
        (2, 1, None, None),
        (None, 3, "user", "> Good.\nhm"),
        (1, 4, "user", "no quotes here"),
    ]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    for c in ("conv", "level", "unit", "path", "own_text", "sha"):
        df = df.withColumn(c, F.lit("clash"))
    got = sorted((r for r in quotes.link_quotes(df).collect()), key=lambda r: (r.conv_id or 0, r.turn))
    short = [(r.conv_id, r.turn, r.own_text, r.n_quotes, r.n_linked, r.max_level, r.parent_turn, r.root_turn, r.reply_path and [int(x) for x in r.reply_path.split("/")]) for r in got]
    assert short == [
        (None, 3, "hm", 1, 0, 1, None, None, None),
        (1, 0, "Shall we meet at noon?\nBring the map.", 0, 0, 0, None, 0, [0]),
        (1, 1, "Yes, noon is fine.", 1, 1, 1, 0, 0, [0, 1]),
        (1, 2, "Good.", 2, 2, 2, 1, 0, [0, 1, 2]),
        (1, 3, "Which map?", 2, 1, 1, 0, 0, [0, 3]),
        (1, 4, "no quotes here", 0, 0, 0, None, 4, [4]),
        (1, 4, "no quotes here", 0, 0, 0, None, 4, [4]),
        (1, 5, "thanks", 1, 1, 1, 2, 0, [0, 1, 2, 5]),
        (2, 0, "", 1, 0, 1, None, 0, [0]),
        (2, 1, "", 0, 0, 0, None, 1, [1]),
    ]
    assert quotes.link_quotes(none_of(df)).count() == 0


def test_excerpts_are_linked(spark):
    rows = [
        (1, 0, "First paragraph here.\n\nSecond one, in two\nlines of text.\n\nThird paragraph ends it."),
        (1, 1, "Line one of many\nline two of many\nline three of many\nline four of many"),
        (1, 2, "> Second one, in two\n> lines of text.\n>\n> Third paragraph ends it.\nTwo of three paragraphs."),
        (1, 3, "> line two of many\n> line three of many\nTwo of four lines."),
        (1, 4, "A long line says this. It goes on with that! Does it end?"),
        (1, 5, "> It goes on\n> with that!\nOne sentence, wrapped anew."),
        (1, 6, "> First paragraph here.\n> [...]\n> Third paragraph ends it.\n>> line four of many\nCut in the middle."),
        (1, 7, "> First words of no message\n>\n> and others\nNothing to link."),
    ]
    df = spark.createDataFrame([(c, t, "user", x) for c, t, x in rows], "conv_id long, turn long, role string, text string")
    got = {r.turn: (r.n_quotes, r.n_linked, r.parent_turn, r.root_turn) for r in quotes.link_quotes(df).collect()}
    assert {t: got[t] for t in (2, 3, 5, 6, 7)} == {2: (1, 1, 0, 0), 3: (1, 1, 1, 1), 5: (1, 1, 4, 4), 6: (2, 2, 0, 0), 7: (1, 0, None, 7)}


def test_turns_of_any_size_sort_as_numbers(spark):
    big = 9 * 10**18
    rows = [(1, t, "u", x) for t, x in [(-5, "First of all."), (-4, "> First of all.\nReply."), (12345678901234, "> Reply.\nLate."), (big, "> Late.\nLast.")]]
    got = quotes.link_quotes(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")).orderBy("reply_path").collect()
    assert [r.turn for r in got] == [-5, -4, 12345678901234, big] and {r.root_turn for r in got} == {-5}
    long = "x" * 300_000
    rows = [(1, 0, "u", long), (1, 1, "u", f"> {long}\nYes.")]
    assert quotes.link_quotes(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")).where("parent_turn = 0").count() == 1


def test_page_query_against_plain_decoding(spark, sf):
    """The query's rows, against the best label sequence over features spelt out, by another recursion."""
    from overlapgraph.llm import queries

    model = queries._page_model()
    got = {r.page_id: (r.url, r.text, r.n_chars) for r in QUERIES["op2_html_extraction"](spark, sf).collect()}
    pages = read_table(spark, sf, "pages").collect()
    assert len(got) == len(pages)
    for p in pages:
        blocks = html_main.leaf_blocks(p.html or "")
        best = {(): 0.0}
        for feats in html_main.block_features(blocks):
            emit = [sum(model.weights[f][c] for f in feats if f in model.weights) for c in (0, 1)]
            grown = {path + (c,): v + emit[c] + (model.transitions[path[-1]][c] if path else 0) for path, v in best.items() for c in (0, 1)}
            best = {}
            for c in (0, 1):
                path = max((q for q in grown if q[-1] == c), key=grown.get)
                best[path] = grown[path]
        text = " ".join(b.text for b, y in zip(blocks, max(best, key=best.get), strict=True) if y)
        assert got[p.page_id] == (p.url, text, len(text))


def test_classifier_queries_against_loops(spark, sf):
    docs = read_table(spark, sf, "documents")
    rows = {r.doc_id: r for r in docs.collect()}
    model = quality.fit(docs, read_table(spark, sf, "labels"))
    got = {r.doc_id: r for r in QUERIES["op7_quality"](spark, sf).collect()}
    assert got.keys() == rows.keys()
    for i in sorted(rows)[::4]:
        z = [float(model.projected[b]) for _, ids in quality.features(textvec.Block([rows[i].text or ""]), len(model.vectors)) for b in ids]
        want = 1 / (1 + math.exp(-(sum(z) / max(len(z), 1) + model.offset)))
        assert got[i].score == pytest.approx(want, abs=1e-6) and got[i].predicted == int(want >= 0.5) and got[i].held_out == (zlib.crc32(str(i).encode()) % 3 == 1)
    lang = langid.fit(docs)
    got = {r.doc_id: r for r in QUERIES["op3_language_id"](spark, sf).collect()}
    assert got.keys() == rows.keys()
    for i in sorted(rows)[::10]:
        block = textvec.Block([(rows[i].text or "").lower()], langid.letters())
        n = len(block.w_start)
        if not n:
            assert (got[i].lang_pred, got[i].score) == ("und", 0)
            continue
        emit = np.zeros((n, len(lang.langs)))
        for word, bucket in langid.word_features(block, len(lang.weights)):
            for w, b in zip(word, bucket):
                emit[w] += lang.weights[b]
        fore, back = [emit[0]], [np.zeros(len(lang.langs))]
        add = lambda m: np.logaddexp.reduce(m, axis=0)
        for j in range(1, n):
            fore.append(emit[j] + add(fore[-1][:, None] + lang.transitions))
        for j in range(n - 1, 0, -1):
            back.append(add((lang.transitions + emit[j] + back[-1]).T))
        post = np.array(fore) + np.array(back[::-1])
        mean = np.exp(post - np.logaddexp.reduce(post, axis=1)[:, None]).mean(axis=0)
        assert got[i].score == pytest.approx(mean.max(), abs=1e-4) and (got[i].lang_pred == lang.langs[int(mean.argmax())] or np.sort(mean)[-2] > mean.max() - 1e-4)


def test_every_operator_has_a_query():
    assert sorted(int(n[2:].split("_")[0]) for n in QUERIES) == list(range(1, 11))


def test_pipeline_against_brute_force(spark, sf):
    import corpus_pipeline

    docs = read_table(spark, sf, "documents")
    rows = {r.doc_id: r for r in docs.collect()}
    model = quality.fit(docs, read_table(spark, sf, "labels"))
    good = {i for i, r in rows.items() if quality.score([r.text or ""], model.projected, model.offset)[0] >= 0.5}
    first = {}
    for i in sorted(good):
        first.setdefault(norm(rows[i].text), i)
    once = set(first.values())
    sets = {i: brute_shingles(rows[i].text) for i in once}
    up = {i: i for i in once}

    def root(a):
        while up[a] != a:
            a = up[a]
        return a

    for a in once:
        for b in once:
            if a < b and sets[a] | sets[b] and len(sets[a] & sets[b]) / len(sets[a] | sets[b]) >= 0.8:
                up[max(root(a), root(b))] = min(root(a), root(b))
    kept = {i for i in once if root(i) == i}
    # each stage by itself: what it keeps is what brute force keeps, no more and no less
    stages = dict(corpus_pipeline.STAGES)
    step = docs
    for name, want in (("quality classifier", good), ("exact dedup", once), ("near-duplicate removal", kept)):
        step = materialise(stages[name](spark, step, sf), "test-stage")
        assert sorted(r.doc_id for r in step.select("doc_id").collect()) == sorted(want), name
    out = corpus_pipeline.run(spark, sf).collect()
    seen = {}
    for r in out:
        seen[r.doc_id] = seen.get(r.doc_id, 0) + 1
    assert set(seen) <= kept
    assert seen == {r.doc_id: r.copies for r in mixing.mix(step).where("copies > 0").collect()}
    sizes = [(i, rows[i].source, len(re.findall(r"[^\x20\x09-\x0D]+", rows[i].text or ""))) for i in kept]
    size, target = brute_mix(sizes)
    for s in size:
        mine = [(i, w) for i, src, w in sizes if ("1" if src is None else "0" + src) == s]
        assert abs(sum(seen.get(i, 0) * w for i, w in mine) - target[s]) <= max(w for _, w in mine)
    for r in out:
        assert r.decoded_sha256 == hashlib.sha256((rows[r.doc_id].text or "").encode()).hexdigest()


def test_stages_of_odd_and_empty_tables(spark, sf, tmp_path):
    import corpus_pipeline

    odd = odd_docs(spark)
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, none_of(odd), sf).count() == 0
    read_table(spark, sf, "labels").where("false").write.parquet(f"{tmp_path}/labels.parquet")
    odd.select("doc_id", "text", "lang", "source", "n_chars").write.parquet(f"{tmp_path}/documents.parquet")
    # without labels every text scores one half and stays
    assert corpus_pipeline.STAGES[0][1](spark, read_table(spark, str(tmp_path), "documents"), str(tmp_path)).count() == odd.count()
    assert corpus_pipeline.run(spark, str(tmp_path)).count() > 0


def brute_shingles(t):
    w = [x for x in re.split(r"[\x20\x09-\x0D]+", (t or "").lower()) if x]
    return {tuple(w[a : a + 5]) for a in range(max(1, len(w) - 4))} if w else set()


def test_stages_keep_the_columns_of_documents(spark, sf):
    import corpus_pipeline

    docs = read_table(spark, sf, "documents").limit(40)
    for _, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, docs, sf).columns == docs.columns
