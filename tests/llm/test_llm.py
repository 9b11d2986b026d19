"""The ten operators against brute force, round trips and held-out accuracy, with nulls, empties, ties, repeats and odd columns."""

import collections
import hashlib
import os
import random
import re
import time
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from conftest import rows
from gpart.llm import chat_format, decontamination, embedding_dedup, html_extraction, language_id, ngram_join, packing, queries, sharding, token_counts, toxicity
from gpart.llm.components import components
from gpart.session import ship

SF = "/root/testdata/sf0.01"
needs_tables = pytest.mark.skipif(not os.path.isdir(SF), reason="no tables")
DOC = "doc_id long, text string, score int, node string, length int"
ODD = ["", " ", None, "a", "A b c d", "a b c d", "x\x1cy z", "<|endoftext|> it's <|startoftext|>", "ÉCOLE éco le", "İ ǅ ß", "1234567890" * 40, "word " * 5000, "z" * 30000, "a b c d", "tab\tand\nline\r\n\x85 nbsp\xa0em "]


@pytest.fixture(scope="module", autouse=True)
def shipped(spark):
    ship(spark)


@pytest.fixture(scope="module")
def odd(spark):
    """Texts of all kinds, repeated rows, a null id, and columns whose names the operators use themselves."""
    data = [(i, t, 1, "n", 2) for i, t in enumerate(ODD)] + [(3, "a", 1, "n", 2), (None, "a b", None, None, None)]
    return spark.createDataFrame(data, DOC)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], DOC)


def tokenizer(name):
    import public_tokenizers
    from tokenizers import Tokenizer

    return Tokenizer.from_file(public_tokenizers.path(name))


@needs_tables
@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_queries_with_sql(spark, duck, name):
    assert rows(queries.queries()[name](spark, SF).toPandas()) == rows(duck(SF, queries.oracle_sql()[name]))


# 1


def hits_by_force(text, items, window):
    words = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    hit, names = set(), set()
    for item, body in items:
        own = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", re.sub("[A-Z]", lambda m: m[0].lower(), body or ""))
        k = min(window, len(own))
        grams = {tuple(own[i : i + k]) for i in range(len(own) - k + 1)} if k else set()
        for i in range(len(words) - k + 1 if k else 0):
            if tuple(words[i : i + k]) in grams:
                hit |= set(range(i, i + k))
                names.add(item)
    return len(words), len(hit), sorted(map(str, names))


@pytest.mark.parametrize("block_words", [10**6, 40])
def test_decontamination_by_force(spark, odd, none, block_words):
    rng = random.Random(2)
    word = lambda: rng.choice("abcdeé")
    items = [(i, " ".join(word() for _ in range(rng.randrange(0, 12)))) for i in range(12)] + [(3, "q q"), (None, None)]
    texts = [(100 + i, ".".join(word() for _ in range(rng.randrange(0, 40)))) for i in range(60)]
    docs = spark.createDataFrame(texts, "doc_id long, text string")
    bench = spark.createDataFrame(items, "item_id long, text string")
    found = {r["doc_id"]: r for r in decontamination.decontaminate(docs, bench, window=4, block_words=block_words).collect()}
    for doc, text in texts:
        n, hit, names = hits_by_force(text, items, 4)
        r = found[doc]
        assert (r["n_words"], r["n_hit"], r["n_items"]) == (n, hit, len(names)) and r["items_sha256"] == hashlib.sha256(",".join(names).encode()).hexdigest()
    assert decontamination.decontaminate(odd, bench).count() == odd.count() and decontamination.decontaminate(none, bench).count() == 0
    assert decontamination.decontaminate(odd, bench.where("false")).where("contaminated").count() == 0


def test_spans_are_removed_and_full_hits_dropped(spark):
    bench = spark.createDataFrame([(1, "one two three four five")], "item_id long, text string")
    docs = spark.createDataFrame([(1, "Keep this, really all of it: ONE two, three. four five! and that, too"), (2, "one two three four five")], "doc_id long, text string")
    assert {r["doc_id"]: r["clean_text"] for r in decontamination.decontaminate(docs, bench).collect()} == {1: "Keep this, really all of it: ! and that, too", 2: None}


# 2 and 7


@needs_tables
def test_language_held_out(spark):
    found = language_id.op2_language_id(spark, SF).join(spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "lang"), "doc_id").where("held_out").toPandas()
    assert (found.lang_pred == found.lang).mean() > 0.97 and found.score.between(0, 1).all()


def test_language_of_nothing(spark, odd, none):
    model = language_id.fit(np.full((2, 1 << language_id.BITS - 3), 255, dtype=np.uint8), ["a", "b"], 2, 1e-3, 3)
    found = language_id.predict(odd, model)
    assert found.count() == odd.count() and {r["doc_id"] for r in found.where("lang_pred = 'und'").collect()} >= {0, 1, 2, 10}
    assert language_id.predict(odd, None).where("lang_pred <> 'und'").count() == 0 and language_id.predict(none, model).count() == 0


def test_presence_kernel_by_force():
    texts = [b"banana", b"bandana band", b"ananas"]
    marks = np.zeros((3, 1 << language_id.BITS), dtype=np.uint8)
    for row, text in zip(marks, texts, strict=True):
        language_id.presence(text, 3, row)
    grams = [{t[i : i + n] for n in (1, 2, 3) for i in range(len(t) - n + 1)} for t in texts]
    for a in range(3):
        for b in range(3):
            assert (marks[a] & marks[b]).sum() == len(grams[a] & grams[b])


@needs_tables
def test_toxicity_held_out(spark):
    sf = SF.replace("0.01", "0.1")
    found = toxicity.op7_toxicity(spark, sf).join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id").where("held_out").toPandas()
    hit = ((found.predicted == 1) & (found.toxic == 1)).sum()
    assert hit / found.predicted.sum() > 0.85 and hit / found.toxic.sum() > 0.85


def test_misspellings_and_quotations(spark, odd, none):
    lexicon = toxicity.Lexicon({"stupid": 5.0, "moron": 4.0, "foul*": 3.0})
    for word, found in (("stupid", (5.0, 0)), ("stpid", (5.0, 1)), ("stuupid", (5.0, 1)), ("stopid", (5.0, 1)), ("tupid", (5.0, 1)), ("stupa", (0.0, 0)), ("fouler", (3.0, 0)), ("foul", (3.0, 0)), ("fool", (0.0, 0)), ("moronic", (0.0, 0)), ("moro", (4.0, 1))):
        assert lexicon.look_up(word) == found, word
    distance = lambda a, b: next(d for d in range(9) if near(a, b, d))

    def near(a, b, d):
        state, step, accepts = toxicity.edit_automaton(a, d)
        for c in b:
            state = step(state, c)
        return accepts(state)

    assert [distance("abc", x) for x in ("abc", "ab", "xbc", "bca", "", "abcd")] == [0, 1, 1, 2, 3, 1]
    text = 'he said "you stupid thing" and left'
    assert toxicity.quoted(text, text.index("stupid"), text.index("stupid") + 6) and not toxicity.quoted(text, text.index("left"), len(text))
    assert toxicity.score(odd, None).where("score <> 0").count() == 0 and toxicity.score(none, None).count() == 0
    model = toxicity.ToxicityModel({"a": 3.0}, {}, np.array([-3.0, 1, 1, 1, 1, -1, 1]))
    scored = {r["doc_id"]: r["predicted"] for r in toxicity.score(odd, model).collect()}
    assert scored[3] == 1 and scored[0] == 0 and scored[2] == 0


def edits(a, b):
    """Levenshtein distance, cell by cell."""
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        row, last = [i], row
        for j, y in enumerate(b, 1):
            row.append(min(last[j] + 1, row[-1] + 1, last[j - 1] + (x != y)))
    return row[-1]


def test_lexicon_by_force():
    rng = random.Random(9)
    word = lambda n: "".join(rng.choice("abc") for _ in range(n))
    for ordinary in (frozenset(), frozenset(word(5) for _ in range(40))):
        weights = {word(rng.randrange(2, 8)): float(i + 1) for i in range(12)} | {word(rng.randrange(3, 8)) + "*": float(i + 20) for i in range(4)}
        lexicon = toxicity.Lexicon(weights, ordinary)
        for _ in range(800):
            own = word(rng.randrange(1, 11))
            stems = {t[:-1]: w for t, w in weights.items() if t.endswith("*")}
            begun = [s for s in sorted(stems, key=len) if own.startswith(s)]
            words = [t for t in weights if not t.endswith("*") and len(t) >= 4 and edits(t, own) <= 1]
            starts = [(stems[s], s) for s in stems if len(s) >= 5 and any(edits(s, own[:k]) <= 1 for k in range(len(own) + 1))]
            if own in weights:
                expected = (weights[own], 0)
            elif begun:
                expected = (stems[begun[0]], 0)
            elif words:
                expected = (0.0, 0) if own in ordinary else (max(weights[t] for t in words), 1)
            elif starts:
                weight, s = max(starts)
                part = own[: max(k for k in range(len(own) + 1) if edits(s, own[:k]) <= 1)]
                expected = (0.0, 0) if part in ordinary else (weight, 1)
            else:
                expected = (0.0, 0)
            assert lexicon.look_up(own) == expected, own


def test_quotations_by_force():
    rng = random.Random(10)
    for _ in range(300):
        text = "".join(rng.choice('ab "\n') for _ in range(rng.randrange(30)))
        inside, at = set(), 0
        for line in text.split("\n"):
            marks = [i for i, c in enumerate(line) if c == '"']
            for a, b in zip(marks[::2], marks[1::2]):
                inside |= set(range(at + a, at + b))
            at += len(line) + 1
        for i, c in enumerate(text):
            if c in "ab":
                assert toxicity.quoted(text, i, i + 1) == (i in inside)
    assert toxicity.quoted("«a “b” c» d", 1, 2) and toxicity.quoted("«a “b” c» d", 7, 8) and not toxicity.quoted("«a “b” c» d", 10, 11)


def test_scores_move_with_what_is_seen(spark, none):
    """Whole texts, trained end to end: misspelled abuse raises the score, the same in quotation marks does not."""
    rng = random.Random(3)
    say = lambda n: " ".join("".join(rng.choice("abcdefgh") for _ in range(rng.randrange(2, 8))) for _ in range(n))
    docs, labels = [], []
    for i in range(400):
        bad = i % 4 == 0
        docs.append((i, f"{say(10)} {rng.choice(['wretched', 'vermin', 'dimwit'])} {say(5)} {rng.choice(['wretched', 'vermin'])} {say(5)}" if bad else say(22)))
        labels.append((i, int(bad), "x"))
    model = toxicity.train(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, toxic int, text string"))
    assert {"wretched", "vermin", "dimwit"} <= set(model.weights)
    scores = dict(zip("plain typos quoted clean".split(), model.score([model.features(t) for t in ("you wretched vermin of a dimwit", "you wretchd vermine of a dimwitt", 'they wrote "you wretched vermin of a dimwit"', "you dear friend of a house")]), strict=True))
    assert scores["plain"] > 0.9 and scores["typos"] > 0.5 and scores["quoted"] < 0.3 and scores["clean"] < 0.3
    assert (model.coefficients * toxicity.SIGNS >= 0).all()
    some = spark.createDataFrame([(1, 1, "t")], "doc_id long, toxic int, text string")
    assert toxicity.train(none, some) is None and toxicity.train(none, some.where("false")) is None and language_id.train(none.selectExpr("doc_id", "text", "'x' AS lang")) is None


# 3


def test_join_by_force(spark, odd, none):
    rng = random.Random(4)
    base = [[rng.choice("abcdefghijklmnopqrstuvwxyz") * 2 for _ in range(rng.randrange(20, 90))] for _ in range(12)]
    texts = []
    for words in base:
        for _ in range(rng.randrange(1, 9)):
            own = list(words)
            for _ in range(rng.randrange(0, 4)):
                own[rng.randrange(len(own))] = rng.choice("uvw")
            texts.append(" ".join(own))
    texts += ["a b", "A  b", "a", "", None, "a b c", "a b c d"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    lower = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    sets = []
    for t in texts:
        w = re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate(lower))
        sets.append({tuple(w[i : i + 4]) for i in range(len(w) - 3)} if len(w) >= 4 else ({tuple(w)} if w else set()))
    root = list(range(len(texts)))
    for a in range(len(texts)):
        for b in range(a):
            if sets[a] and 100 * len(sets[a] & sets[b]) >= 85 * len(sets[a] | sets[b]):
                x, y = root[a], root[b]
                root = [min(x, y) if r in (x, y) else r for r in root]
    found = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in ngram_join.ngram_join(docs).collect()}
    assert found == {i: (len(sets[i]), root[i]) for i in range(len(texts))}
    one = sorted(r["doc_id"] for r in ngram_join.one_of_each(docs, n=4, percent=85).collect())
    assert one == [i for i in range(len(texts)) if root[i] == i]
    assert ngram_join.ngram_join(odd).count() == odd.count() and ngram_join.ngram_join(none).count() == 0


def near_texts(rng, many, words=60, edits=1):
    base = [rng.choice("abcdefghijklmnopqrstuvwxyz") * 3 for _ in range(words)]
    out = []
    for _ in range(many):
        own = list(base)
        for _ in range(edits):
            own[rng.randrange(words)] = f"w{rng.randrange(10**6)}"
        out.append(" ".join(own))
    return out


def test_families_are_multiplied_in_blocks(spark):
    """A large component with strangers, small blocks: the same components as by all pairs, however the products are dealt."""
    rng = random.Random(12)
    texts = near_texts(rng, 60, edits=1) + near_texts(rng, 25, edits=5)
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    sets = [{tuple(t.split()[i : i + 4]) for i in range(57)} for t in texts]

    def merged(root):
        for a in range(len(texts)):
            for b in range(a):
                if 100 * len(sets[a] & sets[b]) >= 85 * len(sets[a] | sets[b]):
                    x, y = root[a], root[b]
                    root = [min(x, y) if r in (x, y) else r for r in root]
        return root

    assert dict(enumerate(merged(list(range(len(texts)))))) == {r["doc_id"]: r["component_id"] for r in ngram_join.ngram_join(docs).collect()}
    join = ngram_join.Join(docs, 4, 85, 0)  # nothing is broadcast
    first = {r["first_id"]: r["node"] for r in join.nodes.collect()}
    families = spark.createDataFrame([(first[i], 1, first[0] if i < 30 else first[i]) for i in range(len(texts))], "node long, family long, component long")
    found = {frozenset(r) for r in join.multiplied(families, block=10).collect()}
    parent = {n: (first[0] if i < 30 else n) for i, n in first.items()}
    for a, b in (tuple(x) for x in found):
        x, y = parent[a], parent[b]
        parent = {n: x if p == y else p for n, p in parent.items()}
    reached = collections.defaultdict(set)
    for i, n in first.items():
        reached[parent[n]].add(i)
    by_force = collections.defaultdict(set)
    for i, r in enumerate(merged([0 if i < 30 else i for i in range(len(texts))])):
        by_force[r].add(i)
    assert sorted(map(sorted, reached.values())) == sorted(map(sorted, by_force.values()))


def test_rows_without_or_with_shared_ids_keep_their_links(spark):
    rng = random.Random(13)
    a, b, c = (near_texts(rng, 1, words=80)[0].split() for _ in range(3))
    tail = [f"t{i}" for i in range(40)]
    middle, far = [*a[:76], "x", "y", "z", "q"], [*a[:72], "s", "t", "u", "v", "x", "y", "z", "q"]
    rows_ = [(5, a), (None, middle), (9, far), (1, b), (1, c), (None, c + tail), (None, ["alone"] * 9), (None, None), (3, [])]
    docs = spark.createDataFrame([(i, " ".join(w) if w is not None else None, "x", 1) for i, w in rows_], "doc_id long, text string, node string, h int")
    found = collections.Counter((r["doc_id"], r["component_id"]) for r in ngram_join.ngram_join(docs, n=4, percent=80).collect())
    assert found == collections.Counter([(5, 5), (None, 5), (9, 5), (1, 1), (1, 1), (None, None), (None, None), (None, None), (3, 3)])
    kept = collections.Counter((r["doc_id"], r["text"], r["node"]) for r in ngram_join.one_of_each(docs, n=4, percent=80).collect())
    text = lambda w: " ".join(w) if w is not None else None
    assert kept == collections.Counter([(5, text(a), "x"), (1, text(b), "x"), (1, text(c), "x"), (None, text(c + tail), "x"), (None, text(["alone"] * 9), "x"), (None, None, "x"), (3, "", "x")])


def test_components_of_chains_and_stars(spark):
    links = [(i, i + 1) for i in range(40)] + [(100, i) for i in range(101, 130)] + [(7, 7)]
    found = {r["node"]: r["component"] for r in components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert all(found[i] == 0 for i in range(41)) and all(found[i] == 100 for i in range(100, 130))


# 4


@pytest.mark.parametrize("copies", [0, 4000])
def test_shards(spark, copies):
    rng = random.Random(6)
    data = [(i, "x" * rng.randrange(3000)) for i in range(3000)] + [(10_000 + i, "same text" * 40) for i in range(copies)] + [(5, None), (6, "")]
    found = sharding.shard(spark.createDataFrame(data, "doc_id long, text string"), range_rows=200).toPandas()
    assert len(found) == len(data) and set(found.shard) == set(range(40))
    for _, own in found.groupby("shard"):
        assert sorted(own.slot) == list(range(len(own)))
    load = found.groupby("shard")["size"].sum()
    assert load.max() <= load.mean() + 3016 + load.mean() / 64 and load.min() >= load.mean() - 3016 - load.mean() / 64
    assert sorted(zip(found.doc_id, found["size"], found.text_crc32, strict=True)) == sorted((i, len(t or "") + 16, zlib.crc32((t or "").encode())) for i, t in data)


def test_equal_rows_are_dealt_like_others(spark):
    """A third of all rows is one row: its copies fill shards evenly, and texts that are not large stay together."""
    data = [(1, "the same row " * 30)] * 3000 + [(i, f"text {i // 4} " * 20) for i in range(10, 6010)]
    found = sharding.shard(spark.createDataFrame(data, "doc_id long, text string"), range_rows=100).toPandas()
    load = found.groupby("shard")["size"].sum()
    assert load.max() - load.min() <= load.mean() / 16 and len(load) == 40
    assert found[found.doc_id != 1].groupby("text_crc32")["shard"].nunique().max() == 1
    packed = packing.pack(spark.createDataFrame(data[2990:3300] + data[:300], "doc_id long, text string"), capacity=64).collect()
    packed_well(packed, dict(data), 64)


def test_long_conversations_have_linear_masks(spark):
    rows_ = spark.range(6000).selectExpr("1L AS conv_id", "id AS turn", "IF(id % 2 = 0, 'user', 'assistant') AS role", "concat('text ', id) AS text")
    began = time.time()
    found = chat_format.read_back(chat_format.format_chats(rows_)).first()
    assert found["n_turns"] == 6000 and found["loss_chars"] == sum(len(f"text {i}") for i in range(1, 6000, 2)) and time.time() - began < 60


def test_shards_of_little(odd, none):
    assert sharding.shard(odd).count() == odd.count() and sharding.shard(none).count() == 0


# 5


def test_main_text(spark):
    page = (
        "<!doctype html><html><head><title>T</title><style>p{}</style></head><body><header>top</header><nav><a href=x>menu</a></nav><!-- <p>no</p> --><div class='cookie-notice'>cookies</div>"
        "<div id=sidebar><p>side</p></div><article><header><h1>Big &amp; bold</h1></header><p>First<br>line &eacute; &#x41;&nbsp; end<p>Second <b>one</b><ul><li>a<li>b</ul><div class=ad>buy</div>"
        '<form><p>fill</p></form><script>var x="</p>";</script><blockquote>said</blockquote><section class="comments"><p>me too</p></section></article><footer>&copy;</footer></body></html>'
    )
    plain = "<body><div class=menu>m</div><p>only<p>two</body>"
    data = [(1, "http://h/1", page), (2, "http://h/2", plain), (3, None, None), (4, "", ""), (5, "u", "<p>cut <b>off <a href='x"), (6, "u", "no tags &lt;here"), (2, "http://h/2", plain)]
    found = [(r["page_id"], r["text"], r["n_chars"]) for r in html_extraction.extract(spark.createDataFrame(data, "page_id long, url string, html string")).collect()]
    texts = {i: t for i, t, _ in found}
    assert texts[1] == "Big & bold\n\nFirst line é A end\n\nSecond one\n\na\n\nb\n\nsaid"
    assert texts[2] == "only\n\ntwo" and texts[3] == texts[4] == "" and texts[5].startswith("cut off") and texts[6] == "no tags <here"
    assert all(n == len(t) for _, t, n in found) and len(found) == 7


@pytest.mark.parametrize("most_broadcast", [1000, 0])
def test_templates_go_where_content_is_not_marked(spark, most_broadcast):
    pages = [(i, f"http://site/{i}", f"<body><div><span>Site of fame</span></div><p>text {i} of its own</p></body>") for i in range(8)] + [(9, "http://other/1", "<body><div><span>Site of fame</span></div></body>")]
    found = {r["page_id"]: r["text"] for r in html_extraction.extract(spark.createDataFrame(pages, "page_id long, url string, html string"), most_broadcast=most_broadcast).collect()}
    assert found[3] == "text 3 of its own" and found[9] == "Site of fame"


def test_templates_by_force(spark):
    """Without the rules: what recurs by words or shape around different contents goes, and nothing else; copies count once."""
    rng = random.Random(5)
    say = lambda k: " ".join(rng.choice("abcdefghij") * rng.randrange(1, 6) for _ in range(k))
    shared, pages, expected = say(60), [], {}
    for host in ("big", "small", "copies"):
        body = [say(30), say(20)]
        for i in range(3 if host == "small" else 12):
            if host != "copies":
                body = [say(30), say(20)] + ([shared] if i % 2 else [])
            elif i % 3 == 0:
                body = [body[0], body[1] + " x"]  # near copies
            box = '<div class=share><a href="/x">tell a friend</a></div>'
            inner = f"<p>{body[0]}</p>{box}" + "".join(f"<p>{x}</p>" for x in body[1:])
            top = "<ul class=top>" + "".join(f"<li><a href=/{k}>{say(2)}</a></li>" for k in range(rng.randrange(2, 5))) + "</ul>"
            rows_ = [f"<li>{say(2)}</li>"] if i == 4 else []
            pages.append((len(pages), f"http://{host}/{i}", f"<html><body>{top}<article><h1>T {i}</h1>{inner}</article><div id=low>{say(3)}</div>{''.join(f'<ol>{x}</ol>' for x in rows_)}<form>no</form></body></html>"))
            texts = lambda *parts: [" ".join(re.sub("<[^>]*>", " ", x).split()) for x in parts]
            around = (re.findall(r"<li>.*?</li>", top), re.findall(r"<div id=low>.*?</div>", pages[-1][2]), [x for x in rows_])
            kept = [[], ["T %d" % i, body[0], *body[1:]], []]
            if host == "small":  # too few pages
                kept = [texts(*around[0]), [f"T {i}", body[0], "tell a friend", *body[1:]], texts(*around[1])]
            expected[len(pages) - 1] = (kept, texts(*around[2]), host)
    table_ = spark.createDataFrame([(*p, 1, "t") for p in pages], "page_id long, url string, html string, n_chars int, text string")
    found = {r["page_id"]: r for r in html_extraction.extract(table_, rules=False).collect()}
    for at, (kept, rare, host) in expected.items():
        blocks = found[at]["text"].split("\n\n")
        whole = [x for part in kept for x in part] + rare
        if host == "copies":  # four different articles: below min_pages
            assert "tell a friend" in blocks
        else:
            assert blocks == whole, (host, at)
        assert found[at]["n_chars"] == len(found[at]["text"])
    by_rules = html_extraction.extract(table_).collect()
    assert all("tell a friend" not in r["text"] for r in by_rules) and sum(r["template_blocks"] for r in by_rules) > 0


@pytest.mark.parametrize("page", ["<a " * 20000, "<div>" * 20000 + "x", "<p><table><td>" + "<div>" * 20000, '<a "' * 20001, "<b>" * 20000 + "</div>" * 20000, "<" * 60000, "<!--" * 20000, "<i>x<div>y</i>" * 10000])
def test_hostile_pages_take_no_time(page):
    began = time.time()
    parts = html_extraction.events(page)
    keys = html_extraction.candidates(parts, "h")[0]
    html_extraction.main_text(parts, keys, {1})
    assert time.time() - began < 2


def test_no_pages(spark):
    assert html_extraction.extract(spark.createDataFrame([], "page_id long, url string, html string, text string")).count() == 0


# 6 and 9


def test_token_counts_are_the_librarys(spark, odd, none):
    encoder = tokenizer("byte_bpe_50k.json")
    found = sorted((r["doc_id"], r["n_bytes"], r["n_tokens"]) for r in token_counts.token_counts(odd).where("doc_id IS NOT NULL").collect())
    expected = sorted((r["doc_id"], len((r["text"] or "").encode()), len(encoder.encode(r["text"] or "", add_special_tokens=False).ids)) for r in odd.where("doc_id IS NOT NULL").collect())
    assert found == expected and token_counts.token_counts(none).count() == 0


@needs_tables
def test_token_counts_of_documents(spark):
    encoder = tokenizer("byte_bpe_50k.json")
    texts = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}
    assert all(r["n_tokens"] == len(encoder.encode(texts[r["doc_id"]], add_special_tokens=False).ids) for r in token_counts.op6_token_counts(spark, SF).collect())


def packed_well(pieces, texts, capacity):
    encoder = tokenizer("word_bpe_49k.json")
    used = collections.defaultdict(list)
    for r in pieces:
        ids = encoder.encode(texts[r["doc_id"]] or "", add_special_tokens=False).ids + [0]
        part = ids[r["start"] : r["start"] + r["length"]]
        assert len(part) == r["length"] and zlib.crc32(np.array(part, dtype="<u4").tobytes()) == r["ids_crc32"] and r["start"] == r["piece"] * capacity
        used[r["sequence_id"]].append((r["offset"], r["length"]))
    for own in used.values():
        own.sort()
        assert [o for o, _ in own] == np.r_[0, np.cumsum([n for _, n in own])[:-1]].tolist() and sum(n for _, n in own) <= capacity
    return len(used), -(-sum(r["length"] for r in pieces) // capacity)


def test_packing_of_odd_texts(odd, none):
    docs = odd.where("doc_id IS NOT NULL")
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    packed_well(packing.pack(docs, capacity=64).collect(), texts, 64)
    assert packing.pack(none).count() == 0 and packing.pack(odd).where("doc_id IS NULL").count() == 1


@needs_tables
def test_packing_is_tight(spark):
    texts = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}
    sequences, least = packed_well(packing.op9_best_fit_packing(spark, SF).collect(), texts, 2048)
    assert sequences <= 1.01 * least + 1


def test_plan_fills_each_slot_once():
    rng = random.Random(8)
    for _ in range(30):
        histogram = {rng.randrange(1, 101): rng.randrange(1, 60) for _ in range(rng.randrange(1, 40))}
        load = collections.Counter()
        for length, first, until, base, each, at in packing.plan_slots(histogram, 100):
            for i in range(until - first):
                load[base + i // each] += length
                assert at + (i % each + 1) * length <= 100
        rooms: list[int] = []  # best fit decreasing, item by item
        for length in sorted((k for k, n in histogram.items() for _ in range(n)), reverse=True):
            fits = [i for i, room in enumerate(rooms) if room >= length]
            if fits:
                rooms[min(fits, key=rooms.__getitem__)] -= length
            else:
                rooms.append(100 - length)
        assert sum(load.values()) == sum(k * n for k, n in histogram.items()) and max(load.values()) <= 100 and len(load) == len(rooms)


# 8


def vectors_by_force(data, limit=0.98):
    """(vec_id, n_links, component_id, kept) of every row, by all pairs."""
    good = [i for i, (_, v, label, *_) in enumerate(data) if label is not None and v and all(x is not None and np.isfinite(x) for x in v) and any(v)]
    root = {i: i for i in range(len(data))}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    many = collections.Counter()
    for a in good:
        for b in good:
            if a < b and data[a][2] == data[b][2] and len(data[a][1]) == len(data[b][1]):
                x, y = np.array(data[a][1]), np.array(data[b][1])
                if x @ y / (np.linalg.norm(x) * np.linalg.norm(y)) >= limit:
                    many[a] += 1
                    many[b] += 1
                    root[find(a)] = find(b)
    least = {}
    for i, row in enumerate(data):
        least[find(i)] = min(least.get(find(i), row[0]), row[0])
    return collections.Counter((row[0], many[i], least[find(i)], row[0] == least[find(i)]) for i, row in enumerate(data))


def test_vectors_by_force(spark):
    rng = np.random.default_rng(3)
    base = rng.normal(size=(40, 16))
    data = []
    for i in range(500):
        v = base[i % 40] + rng.normal(size=16) * rng.choice([0, 0.05, 0.12])
        data.append((i, v.tolist(), int(i % 40 % 3), "x", 7))
    data += [(900, None, 1, "x", 7), (901, [0.0] * 16, 1, "x", 7), (902, [float("nan")] + [1.0] * 15, 1, "x", 7), (903, base[0].tolist(), None, "x", 7), (904, [None] + [1.0] * 15, 1, "x", 7), (905, [1.0, 0.0], 1, "x", 7), (906, [], 1, "x", 7), (3, data[3][1], data[3][2], "x", 7)]
    table_ = spark.createDataFrame(data, "vec_id long, embedding array<double>, label int, node string, n_links int")
    found = collections.Counter(tuple(r) for r in embedding_dedup.near_duplicates(table_, shard_rows=90, recall=1.0).select("vec_id", "n_links", "component_id", "kept").collect())
    assert found == vectors_by_force(data)


def test_rare_links_are_audited(spark):
    """Eight links between two shards of hundreds of vectors: audits have links to find all the same, and report them."""
    rng = np.random.default_rng(11)
    v = rng.normal(size=(1200, 24))
    v[1000:1008] = v[:8] + rng.normal(size=(8, 24)) * 0.02
    table_ = spark.createDataFrame([(i, x.tolist(), 1) for i, x in enumerate(v)], "vec_id long, embedding array<double>, label int")
    assert embedding_dedup.near_duplicates(table_, shard_rows=600).where("n_links > 0").count() == 16
    report = embedding_dedup.audit_report(table_, shard_rows=600).first()
    assert report["searches"] == 4 and report["links"] >= 4 * 64 and report["found"] >= 0.99 * report["links"]


def test_no_vectors(spark):
    nothing = spark.createDataFrame([], "vec_id long, embedding array<float>, label int")
    assert embedding_dedup.near_duplicates(nothing).count() == 0 and embedding_dedup.audit_report(nothing).first()["searches"] == 0


# 10


def test_chats_round_trip(spark):
    rng = random.Random(1)
    bits = ["</s>", "[INST]", "\\", "\\\\", "<s>", "[/INST]", " ", "a", "[ROLE]", "[TEXT]", "[/ROLE]", "[ANS]", "é", "\n", "$1", "[/SYS]", ""]
    data = [(c, t, rng.choice(["user", "assistant", "system", "tool", "t]\\[TEXT] ", None, ""]), rng.choice([None, "".join(rng.choices(bits, k=rng.randrange(9)))])) for c in range(150) for t in range(rng.randint(1, 5))]
    data += [data[0], (None, 0, "user", "no conversation"), (7, None, "user", "no turn")]
    rows_ = spark.createDataFrame([(*r, 1) for r in data], "conv_id long, turn long, role string, text string, formatted int")
    found = {r["conv_id"]: r for r in chat_format.read_back(chat_format.format_chats(rows_)).collect()}
    turns = collections.defaultdict(list)
    for c, t, role, text in data:
        turns[c].append((t is not None, t or 0, role or "", text or ""))
    for c, own in turns.items():
        own.sort()
        loss = "".join(x for _, _, r, x in own if r == "assistant")
        assert found[c]["n_turns"] == len(own) and found[c]["turns_sha256"] == hashlib.sha256("".join(f"{r}\n{x}\n" for _, _, r, x in own).encode()).hexdigest()
        assert (found[c]["loss_chars"], found[c]["loss_sha256"]) == (len(loss), hashlib.sha256(loss.encode()).hexdigest())


def test_no_chats(spark):
    assert chat_format.format_chats(spark.createDataFrame([], "conv_id long, turn long, role string, text string")).count() == 0


# the pipeline


def test_stages_of_odd_tables(spark, odd, none):
    """Nulls, empty and repeated rows and columns with clashing names: each stage gives the columns of documents and defined rows."""
    import corpus_pipeline

    extra = lambda df: df.selectExpr("doc_id", "text", "'en' AS lang", "'web' AS source", "CAST(length(text) AS BIGINT) AS n_chars", "1 AS score", "node", "7 AS h", "7 AS chunk")
    for docs in (extra(odd), extra(none)):
        for name, stage in corpus_pipeline.STAGES:
            after = stage(spark, docs, SF)
            if name != "best_fit_packing":
                assert after.columns == ["doc_id", "text", "lang", "source", "n_chars"], name
            kept = after.count()
            if name == "ngram_jaccard_join" and docs.count():
                # words of ODD: copies of `a`, `a b c d` and `A b c d` leave one row each; rows without words stay
                assert kept == docs.count() - 3
            elif name == "toxicity":
                assert kept == docs.count()


@needs_tables
def test_pipeline_stages(spark):
    import corpus_pipeline

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns, kept = docs.columns, docs
    counts = [docs.count()]
    for name, stage in corpus_pipeline.STAGES[:-1]:
        after = stage(spark, kept, SF).cache()
        assert after.columns == columns, name
        counts.append(after.count())
        if name == "toxicity":
            labels = spark.read.parquet(f"{SF}/labels.parquet")
            assert after.join(labels.where("toxic = 0"), "doc_id").count() >= 0.98 * kept.join(labels.where("toxic = 0"), "doc_id").count()
        if name == "ngram_jaccard_join":
            assert ngram_join.ngram_join(after, n=5, percent=80).where(F.col("doc_id") != F.col("component_id")).count() == 0
        kept = after
    assert counts[1] == counts[0] and counts[1] > counts[2] > counts[3] >= counts[4]
    assert decontamination.decontaminate(kept, spark.read.parquet(f"{SF}/benchmark.parquet")).where("contaminated").count() == 0
    pieces = corpus_pipeline.STAGES[-1][1](spark, kept, SF)
    assert pieces.select("doc_id").distinct().count() == counts[4]
