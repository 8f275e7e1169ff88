"""The corpus operators against brute force, on hand-made tables with awkward rows."""

import collections
import hashlib
import html
import math
import random
import re
import zlib

import numpy as np
import pytest

from itemlens.llm import chat, common, exact_dedup, fingerprints, html_text, language_id, mixing, packing, pii, quality, similarity_join
from itemlens.llm.textkernel import mix64, shingle_sets
from itemlens.llm.textkernel import words as hashed_words

WORD = re.compile(r"[^\x20\x09-\x0D]+")
DOCS = "doc_id long, text string, lang string, source string, n_chars long, name string, key string, id long"


def lower(text):
    return re.sub("[A-Z]", lambda m: m.group().lower(), text or "")


def shingles(text):
    w = WORD.findall(lower(text))
    return frozenset(tuple(w[i : i + 5]) for i in range(len(w) - 4)) if len(w) >= 5 else frozenset([tuple(w)] if w else [])


def words(n, seed):
    r = random.Random(seed)
    return ["".join(r.choice("abcdefghijklmnop") for _ in range(r.randint(2, 7))) for _ in range(n)]


def awkward():
    base = words(120, 1)
    texts = [None, "", " \n\t ", "One", "two Words", "TWO words", "x" * 5000, " ".join(words(4000, 2)), " ".join(base), " ".join(base).upper(), " ".join(base) + " é ß 中文 😀"]
    for i in range(30):
        edited = list(base)
        for k in range(i % 9):
            edited[(17 * k + i) % len(edited)] = f"new{i}x{k}"
        texts.append(" ".join(edited))
    texts += [" ".join(words(60, 100 + i)) for i in range(10)] + ["the same"] * 5
    rows = [(i * 7 - 3, t, "en" if i % 3 else None, [None, "a", "b", "ä"][i % 4], len(t or ""), "n", "k", i) for i, t in enumerate(texts)]
    return rows


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(awkward(), DOCS)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], DOCS)


def closure(sets, num=3, den=4):
    parent = {i: i for i in sets}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in sets:
        for j in sets:
            if i < j and sets[i] and den * len(sets[i] & sets[j]) >= num * len(sets[i] | sets[j]):
                a, b = root(i), root(j)
                parent[max(a, b)] = min(a, b)
    return {i: root(i) for i in sets}


@pytest.mark.parametrize("block", [2048, 6])
def test_similarity_classes(docs, block, monkeypatch):
    monkeypatch.setattr(similarity_join, "BLOCK_SETS", block)
    monkeypatch.setattr(similarity_join, "BROADCAST_IDS", 300_000 if block > 6 else -1)
    monkeypatch.setattr(similarity_join, "FREQUENT_LEAST", 64 if block > 6 else 4)
    monkeypatch.setattr(similarity_join, "FOLD_ROWS", 1 << 20 if block > 6 else 50)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in similarity_join.similarity_classes(docs).collect()}
    sets = {r[0]: shingles(r[1]) for r in awkward()}
    roots = closure(sets)
    assert got == {i: (len(s), roots[i]) for i, s in sets.items()}


def test_similarity_repeated_and_null_ids(spark):
    text = " ".join(words(30, 3))
    rows = [(1, text), (1, text), (2, text.upper()), (None, text), (5, " ".join(words(30, 4))), (5, text)]
    got = similarity_join.similarity_classes(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert len(got) == len(rows)
    assert {r["component_id"] for r in got if r["doc_id"] in (1, 2, 5)} == {1}


@pytest.mark.parametrize("seed", range(6))
def test_prefix_signatures_meet(seed):
    r = random.Random(seed)
    universe = list(range(1, 3000))
    weight = {t: r.choice([1, 2, 3, 500, 900]) for t in universe}
    for _ in range(60):
        n = r.choice([1, 2, 3, 4, 5, 8, 11, 12, 16, 23, 40, 44, 58, 86, 87, 88, 116, 117, 200, 400])
        x = set(r.sample(universe, n))
        y = set(x)
        for _ in range(r.randint(0, n // 6)):
            y.discard(r.choice(sorted(y)))
            y.add(r.choice(universe))
        if not y or 4 * len(x & y) < 3 * len(x | y):
            continue
        sigs = []
        for s in (x, y):
            t = np.array(sorted(s), np.uint64)
            w = np.array([weight[int(v)] for v in t])
            sigs.append(set(similarity_join.prefix_signatures(t, w, w > 100, 3, 4).tolist()))
        assert sigs[0] & sigs[1]


@pytest.mark.parametrize("dense", [True, False])
def test_family_links(dense, monkeypatch):
    rows = [s for s in (shingle_sets([(r[1] or "").encode()])[0] for r in awkward()) if len(s)]
    monkeypatch.setattr(similarity_join, "DENSE_BYTES", 1 << 30 if dense else 0)
    sets = {i: frozenset(s.tolist()) for i, s in enumerate(rows)}
    links = similarity_join.family_links(np.arange(len(rows)), rows, 3, 4)
    parent = {i: i for i in sets}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in links:
        assert 4 * len(sets[a] & sets[b]) >= 3 * len(sets[a] | sets[b])
        a, b = root(a), root(b)
        parent[max(a, b)] = min(a, b)
    assert {i: root(i) for i in sets} == closure(sets)


def test_components_both_ways(spark):
    r = random.Random(5)
    edges = [(r.randrange(200), r.randrange(200)) for _ in range(120)]
    df = spark.createDataFrame(edges, "a long, b long")
    one = {x["id"]: x["component"] for x in common.components(df).collect()}
    many = {x["id"]: x["component"] for x in common.components(df, one_task=-1).collect()}
    parent = {i: i for e in edges for i in e}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in edges:
        a, b = root(a), root(b)
        parent[max(a, b)] = min(a, b)
    linked = {i for a, b in edges if a != b for i in (a, b)}
    assert one == many == {i: root(i) for i in linked}


def test_exact_duplicates(docs):
    want = collections.defaultdict(list)
    for r in awkward():
        want[lower(r[1])].append(r[0])
    for size in (8192, 50):
        got = exact_dedup.exact_duplicates(docs, size).collect()
        assert len(got) == len(awkward())
        texts = {r[0]: lower(r[1]) for r in awkward()}
        for g in got:
            ids = want[texts[g["doc_id"]]]
            assert (g["keep_id"], g["group_size"], g["kept"]) == (max(ids), len(ids), g["doc_id"] == max(ids))
            assert g["text_sha256"] == hashlib.sha256(texts[g["doc_id"]].encode()).hexdigest()


def test_exact_duplicates_with_colliding_digests(docs, monkeypatch):
    monkeypatch.setattr(exact_dedup, "digest", lambda block: exact_dedup.F.length(block).cast("long") % 3)
    texts = {r[0]: lower(r[1]) for r in awkward()}
    got = exact_dedup.exact_duplicates(docs, 50).collect()
    assert len(got) == len(texts) and all(g["keep_id"] == max(i for i, t in texts.items() if t == texts[g["doc_id"]]) for g in got)


def test_block_names_do_not_depend_on_partitions(spark, docs):
    want = None
    for n in (3, 8):
        spark.conf.set("spark.sql.shuffle.partitions", n)
        got = sorted((r["doc_id"], r["level"], r["name"]) for r in exact_dedup.block_names(docs.repartition(n), "doc_id", 50).collect())
        want = want or got
        assert got == want
    spark.conf.set("spark.sql.shuffle.partitions", 4)
    assert len({(level, name) for _, level, name in got}) == len({lower(r[1]) for r in awkward()})


def test_exact_duplicates_with_null_and_repeated_ids(spark):
    rows = [(1, "Same"), (1, "same"), (None, "SAME"), (None, None), (None, ""), (4, "other"), (4, "same")]
    got = sorted(((r["doc_id"], r["keep_id"], r["group_size"], r["kept"]) for r in exact_dedup.exact_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()), key=str)
    want = [(1, 4, 4, False), (1, 4, 4, False), (None, 4, 4, False), (None, None, 2, True), (None, None, 2, True), (4, 4, 1, True), (4, 4, 4, True)]
    assert got == sorted(want, key=str)


def test_shared_folder_is_needed_on_a_cluster():
    from types import SimpleNamespace as fake

    unset = lambda master: fake(conf=fake(get=lambda k, d=None: d), sparkContext=fake(master=master))
    assert common.shared_folder(unset("local[8]")) and common.shared_folder(unset("local"))
    for master in ("local-cluster[3,2,1024]", "yarn", "spark://host:7077"):
        with pytest.raises(ValueError):
            common.shared_folder(unset(master))


def reference_ids():
    """A fresh encoder, as the contract words it."""
    import public_tokenizers
    from tokenizers import Tokenizer

    encoder = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    return lambda text: encoder.encode(text, add_special_tokens=False).ids


def test_packing(spark):
    encode = reference_ids()
    rows = [(r[0], r[1]) for r in awkward()] + [(500, "a <|endoftext|> b"), (501, "<|endoftext|>" * 40), (600, "twice the same"), (600, "twice the same"), (None, "without an id")]
    docs = spark.createDataFrame([(*r, 7) for r in rows], "doc_id long, text string, length int")
    got = packing.packed(docs, 64).collect()
    want, by_seq = collections.Counter(), collections.defaultdict(list)
    for doc_id, text in rows:
        ids = np.array([*(encode(text) if text else []), 0], "<u4")
        want.update((doc_id, at, min(64, len(ids) - at), zlib.crc32(ids[at : at + 64].tobytes()), len(ids)) for at in range(0, len(ids), 64))
    assert collections.Counter((g["doc_id"], g["start"], g["length"], g["ids_crc32"], g["doc_tokens"]) for g in got) == want
    for g in got:
        by_seq[g["sequence_id"]].append((g["offset"], g["length"]))
    for parts in by_seq.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 64
    tokens = sum(g["length"] for g in got)
    assert len(by_seq) * 64 < tokens * 1.1 + 64


def test_pack_histogram_holds_everything():
    r = random.Random(1)
    counts = {n: r.randint(1, 50) for n in range(1, 65)}
    held = collections.Counter()
    for pattern, n in packing.pack_histogram(counts, 64):
        assert sum(pattern) <= 64
        for length in pattern:
            held[length] += n
    assert held == counts


def test_encoders_agree():
    encode, exact = packing.Encoder(), reference_ids()
    for text in ["a b  c\n\n d", "don't <|endoftext|> 123,456", "<|endoftext|>", "x<|endoftext|><|endoftext|>y", "<|endoftext", "été ß — “quotes”  x", "😀 中文 ж", "x" * 300]:
        assert encode(text) == exact(text), text
    assert exact("<|endoftext|>") == [50256]


def test_fingerprints_with_null_and_repeated_ids(spark):
    rows = [(None, "first text of all"), (3, "b " * 9), (3, "a " * 9), (None, None), (9, "last one")]
    got = fingerprints.edited_fingerprints(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    chain = [(None, ""), (None, "first text of all"), (3, "a " * 9), (3, "b " * 9), (9, "last one")]
    want = collections.Counter()
    for (i, t), (_, after) in zip(chain, chain[1:] + chain[:1], strict=True):
        q = len(t) // 4
        want[i, len(t), hashlib.sha256((t[: len(t) - q] + after[:q]).encode()).hexdigest()] += 1
    assert collections.Counter((g["doc_id"], g["n_chars"], g["edited_sha256"]) for g in got) == want


def test_empty_bins_ask_in_order():
    order, _ = fingerprints._donors(512)
    for k in (1, 3, 24, 25, 60, 400):
        values = np.sort(mix64(np.arange(k, dtype=np.uint64) + np.uint64(1000 * k)))
        got = fingerprints.sketch([values, values[:0]], 512, 8)[0]
        first = {}
        for v in values:
            first.setdefault(int(v >> np.uint64(55)), int(v) >> 1)
        taken = [first[next(int(d) for d in ([b] if b in first else order[b]) if int(d) in first)] ^ (b << 32) for b in range(512)]
        assert got.tolist() == (mix64(np.array(taken, np.uint64)) & np.uint64(255)).tolist()


def test_fingerprints(docs, monkeypatch):
    monkeypatch.setattr(fingerprints, "RANGE_ROWS", 7)
    got = {r["doc_id"]: r for r in fingerprints.edited_fingerprints(docs).collect()}
    rows = sorted(awkward())
    assert len(got) == len(rows)
    for i, (doc_id, text, *_) in enumerate(rows):
        text, after = text or "", rows[(i + 1) % len(rows)][1] or ""
        quarter = len(text) // 4
        edited = text[: len(text) - quarter] + after[:quarter]
        g = got[doc_id]
        assert (g["n_chars"], g["edited_sha256"]) == (len(text), hashlib.sha256(edited.encode()).hexdigest())
        a, b = shingles(text), shingles(edited)
        true = len(a & b) / len(a | b) if a | b else 1.0
        assert abs(g["near_edited"] - true) < 0.12
    plain = {r["doc_id"]: r["fingerprint"] for r in fingerprints.fingerprints(docs).collect()}
    assert plain == {i: g["fingerprint"] for i, g in got.items()}


def test_mixing(docs):
    got = mixing.mixed(docs).collect()
    sizes = {r[0]: len(WORD.findall(r[1] or "")) for r in awkward()}
    per = collections.Counter()
    for r in awkward():
        per[r[3]] += sizes[r[0]]
    order = sorted((s for s in per if s is not None)) + [None]
    weight = {s: (3, 1, 2)[i % 3] for i, s in enumerate(order)}
    target, left, open_ = collections.Counter(), 1.5 * sum(per.values()), set(order)
    while left > 1e-9 and open_:
        share, total, left = left, sum(weight[s] for s in open_), 0.0
        for s in sorted(open_, key=str):
            target[s] += share * weight[s] / total
        for s in list(open_):
            if target[s] > 2 * per[s]:
                left += target[s] - 2 * per[s]
                target[s] = 2 * per[s]
                open_.discard(s)
    taken = collections.Counter()
    for g in got:
        assert g["size"] == sizes[g["doc_id"]] and g["source_size"] == per[g["source"]]
        assert g["taken"] in (0, g["size"], 2 * g["size"])
        assert abs(g["target"] - target[g["source"]]) < 1e-6
        taken[g["source"]] += g["taken"]
    for s in per:
        assert abs(taken[s] - target[s]) <= max(x for i, x in sizes.items() if {r[0]: r[3] for r in awkward()}[i] == s) / 2 + 1e-6
    assert sorted(got) == sorted(mixing.mixed(docs.repartition(7)).collect())


def test_balance_is_the_optimum_of_the_joint_dual(spark):
    r = random.Random(4)
    rows = [(s, r.randint(1, 40) * (9 if s == "b" else 1)) for s, n in (("a", 60), ("b", 50), (None, 40), ("d", 30)) for _ in range(n)]
    sizes = spark.createDataFrame(rows, "source string, size long")
    targets = mixing.source_targets(sizes)
    state, slope, centre = mixing.balanced(sizes, targets)
    got = {r["key"]["source"]: r for r in state.collect()}
    size = np.array([x for _, x in rows], float)
    z = np.log(size) - centre
    assert abs((size * z).sum()) < 1e-6 * size.sum()
    rate = np.array([2.0 if got[s]["full"] else 2 / (1 + np.exp(-(got[s]["multiplier"] + slope * x))) for (s, _), x in zip(rows, z, strict=True)])
    total = 0.0
    for s in got:
        own = np.array([x == s for x, _ in rows])
        total += got[s]["target"]
        assert abs((rate * size)[own].sum() - got[s]["target"]) < 1e-6 * got[s]["target"]
    # The slope's own equation, with its ridge; without a slope the mix would lean further.
    assert abs((rate * size * z).sum() + mixing.RIDGE * total * slope) < 1e-6 * total
    flat = np.array([min(2.0, got[s]["target"] / got[s]["source_size"]) for s, _ in rows])
    assert abs(slope) > 0.01 and abs((rate * size * z).sum()) < 0.8 * abs((flat * size * z).sum())
    assert all(got[t]["full"] or len({round(x, 6) for (s, _), x in zip(rows, rate, strict=True) if s == t}) > 5 for t in got)


def test_mixing_with_null_and_repeated_ids(spark):
    rows = [(None, "one two three", "a"), (None, "one two three", "a"), (1, "x " * 40, None), (1, "x " * 40, None), (2, None, "b"), (3, "y " * 9, "b")]
    docs = spark.createDataFrame([(*r, 5) for r in rows], "doc_id long, text string, source string, size int")
    got = mixing.mixed(docs).collect()
    assert collections.Counter((g["doc_id"], g["source"], g["size"]) for g in got) == collections.Counter((i, s, len((t or "").split())) for i, t, s in rows)
    assert all(g["taken"] <= 2 * g["size"] for g in got)


def greedy_windows(turns, budget, history):
    """(repeated turns, own turns) of each window, by a plain loop over turns (role, text, cost)."""
    out, at = [], 0
    system = turns[0][2] if turns[0][0] == "system" else 0
    while at < len(turns):
        back, past = at, 0
        while back > (1 if system else 0) and past + turns[back - 1][2] <= history:
            back -= 1
            past += turns[back][2]
        lead = system if at else 0
        if lead + past + turns[at][2] > budget:
            back, past = at, 0
        used, end = lead + past + turns[at][2], at + 1
        while end < len(turns) and used + turns[end][2] <= budget:
            used += turns[end][2]
            end += 1
        out.append((([0] if lead else []) + list(range(back, at)), list(range(at, end)), used))
        at = end
    return out


def test_chat(spark):
    rows = [(-7, 0, "user", "</s>[INST] ok [/INST]"), (-7, 1, "assistant", "</s>[INST] ok [/INST]"), (1, 0, "system", "be ~ kind <end>"), (2, None, None, None), (3, 1, "a>b~2", "x"), (3, 1, "a>b~2", "x")]
    rows += [(1, i, ("user", "assistant")[i % 2], f"turn {i} <user> ~1 " * (i * 9 % 60)) for i in range(1, 40)] + [(None, 0, "assistant", "😀 é")]
    rows += [(4, i, ("user", "assistant")[i % 2], "word " * n) for i, n in enumerate([3, 700, 2, 2, 500, 1, 1, 1, 230, 40, 9, 9])] + [(5, 0, "system", "long " * 900), (5, 1, "user", "hi"), (5, 2, "assistant", "there")]
    turns = spark.createDataFrame([(*r, "extra", 1) for r in rows], "conv_id long, turn long, role string, text string, window string, number int")
    made = chat.windows(turns, 300, 100).collect()
    got = {r["conv_id"]: r for r in chat.read_back(chat.windows(turns, 300, 100)).collect()}
    want = collections.defaultdict(list)
    for c, t, r, x in rows:
        want[c].append((-1 if t is None else t, r or "", x or ""))
    assert set(got) == set(want)
    mark = lambda t: t.replace("~", "~0").replace("<", "~1")
    for c, turns_ in want.items():
        turns_.sort()
        text, loss = "".join(f"{r}\n{x}\n" for _, r, x in turns_), "".join(x for _, r, x in turns_ if r == "assistant")
        g = got[c]
        assert (g["n_turns"], g["turns_sha256"]) == (len(turns_), hashlib.sha256(text.encode()).hexdigest())
        assert (g["loss_chars"], g["loss_sha256"]) == (len(loss), hashlib.sha256(loss.encode()).hexdigest())
        lines = [f"<{mark(r).replace('>', '~2')}>{mark(x)}<end>" for _, r, x in turns_]
        plan = greedy_windows([(r, x, -(-len(line.encode()) // 4)) for (_, r, x), line in zip(turns_, lines, strict=True)], 300, 100)
        own = sorted((r for r in made if r["conv_id"] == c), key=lambda r: r["window"])
        assert [r["formatted"] for r in own] == ["".join(lines[k] for k in [*old, *new]) for old, new, _ in plan]
        assert [(r["fresh_from"], r["turns_in"]) for r in own] == [(1 + sum(len(lines[k]) for k in old), len(new)) for old, new, _ in plan]
        for r, (_, new, used) in zip(own, plan, strict=True):
            assert used <= 300 and len(r["formatted"].encode()) <= 4 * 300 or len(new) == 1
    assert any(len(old) > 2 for old, _, _ in greedy_windows([("user", "x", 60)] * 9, 300, 180))


PAGE = """<!DOCTYPE html><html><head><title>t</title><script>var a="<p>no</p>";</script></head><body><header>Site</header><nav><ul><li><a href=x>Home</a></li></ul></nav>
<div class="cookie-notice">We use cookies</div><article><header><h1>Title &amp; more</h1></header><p>First <b>bold</b> par&shy;agraph.<br>Second&nbsp;line<div class="ad">Buy</div>
<p>Third <a href="y">link</a> text.</p><form>Mail <input></form><section id="comments"><p>Nice read, thanks a lot for it!</p></section></article><aside>More</aside><footer>&copy; 2024</footer></body></html>"""


def test_html(spark):
    pages = [(1, "u", PAGE), (2, None, None), (3, "v", ""), (4, "w", "<p>A page without an article element, whose text is long enough to be told from menus.</p><p>It goes on with a second paragraph of some length, for the neighbours.</p>"), (5, "x", "<<p>broken <b>mark")]
    got = {r["page_id"]: r for r in html_text.extracted(spark.createDataFrame([(*p, 1) for p in pages], "page_id long, url string, html string, text int")).collect()}
    assert got[1]["text"] == "Title & more First bold par­agraph. Second line Third link text."
    assert (got[2]["text"], got[3]["text"], got[2]["n_chars"]) == ("", "", 0)
    assert got[4]["text"].startswith("A page") and got[4]["text"].endswith("neighbours.")
    assert html.unescape("&amp;") == "&" and len(got) == 5


def test_html_scripts_end_at_their_own_tag():
    body = "<article><h1>Head line</h1><p>A first paragraph of the article, long enough to be told from menus.</p>{}<p>And a second one after it.</p></article>"
    want = "Head line A first paragraph of the article, long enough to be told from menus. And a second one after it."
    tree = html_text.default_tree()
    for inside in (
        "<script>for(i=0;i<n;i++){f(i)}</script>", '<script>t="<a href=\'";</SCRIPT >', "<script>s='<div class=\"x';</script>", "<style>a:after{content:'<b'}</style>",
        "<textarea>a <b c='</textarea>", "<script>x='</scripted>'; if(a<b){}</script>", "<noscript><style>i<n{</style></noscript>", "<script>x='<!--'</script>",
    ):
        assert html_text.main_text("<html><body>" + body.format(inside) + "</body></html>", tree) == want, inside
    head = "<head><title>a <b or 'c</title><script>if(i<n){}</script></head>"
    assert html_text.main_text("<html>" + head + "<body>" + body.format("") + "</body></html>", tree) == want
    assert html_text.main_text(body.format("") + "<script>for(i=0;i<n;i++)", tree) == want


def test_html_tree_fits_its_table():
    tree, used = html_text.default_tree(), set()
    table = html_text.labelled_rows()
    assert all(html_text.decide(tree, row[:-1]) == row[-1] for row in table)

    def walk(node):
        if isinstance(node, tuple):
            used.add(html_text.FEATURES[node[0]])
            walk(node[2])
            walk(node[3])

    walk(tree)
    assert {"words", "link_density", "around", "centre", "against"} <= used and used & {"link_density_before", "link_density_after"}


def test_html_class_names_do_not_decide_alone():
    tree = html_text.default_tree()
    prose = lambda n, w="word": " ".join([w] * n)
    assert html_text.main_text(f'<body><nav><a>Home</a></nav><div class="legal-news story"><p>{prose(60)}</p></div></body>', tree) == prose(60)
    inside = f'<body><article><p>{prose(50)}</p><div class="content-share"><p>{prose(30, "more")}</p></div><div class="content-share"><a>Tweet</a> <a>Post</a></div><p>{prose(40)}</p></article></body>'
    assert html_text.main_text(inside, tree) == " ".join([prose(50), prose(30, "more"), prose(40)])
    for bad in ("ad", "cookie-notice", "post-comments", "sidebar left", "newsletter-box", "alert"):
        page = f'<body><article><h1>Head</h1><p>{prose(50)}</p><div class="{bad}"><p>{prose(30, "less")}</p></div><p>{prose(40)}</p></article></body>'
        assert html_text.main_text(page, tree) == " ".join(["Head", prose(50), prose(40)]), bad
    links = "".join(f"<li><a href={i}>See also</a></li>" for i in range(8))
    assert "See also" not in html_text.main_text(f"<body><article><p>{prose(60)}</p><ul>{links}</ul><p>{prose(50)}</p></article></body>", tree)
    assert html_text.main_text(f"<body><article><p>{prose(60)}</p><p><a href=x>one link</a></p><p>{prose(50)}</p></article></body>", tree) == " ".join([prose(60), "one link", prose(50)])


def test_html_of_the_given_pages(spark, small):
    """Of pages whose main text is one article, all of the article and nothing else."""
    pages = common.table(spark, small, "pages")
    raw = {r["page_id"]: r["html"] for r in pages.collect()}
    for r in html_text.extracted(pages).collect():
        body = re.search("<article>(.*)</article>", raw[r["page_id"]], re.S).group(1)
        body = html.unescape(re.sub("<[^>]*>", "", re.sub(r"<(?:br|/?p|/?h[1-6]|/?li|/?ul)[^>]*>", " ", body)))
        assert r["text"] == " ".join(body.split()) and r["n_chars"] == len(r["text"])


def test_pii(spark):
    text = "Mail a.b@c.de or x@y@z.org; ip 1.2.3.4.5 and 999.1.1.1, card 4111 1111 1111 1111, phone +49 (30) 123-4567. Dr. Maria Weber; token = \"9b0b3c6a43eb78aa99cbd7049c5723915243\" v1.2.3"
    rows = [(1, text), (2, None), (3, ""), (4, "clean words only"), (1, text)]
    found = pii.detected(spark.createDataFrame([(*r, 0) for r in rows], "doc_id long, text string, spans int"))
    got = pii.digest(found).collect()
    assert len(got) == 5
    got.sort()
    patterns = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}
    for g in got:
        base = []
        body = dict(rows)[g["doc_id"]] or ""
        for k, (kind, pattern) in enumerate(patterns.items()):
            for m in re.finditer(pattern, body):
                digits = re.sub(r"\D", "", m.group())
                fine = {"email": lambda: True, "ip": lambda m=m: all(int(p) <= 255 for p in m.group().split(".")), "card": lambda d=digits: 12 <= len(d) <= 19 and pii._luhn(d), "phone": lambda d=digits: 9 <= len(d) <= 15}
                if fine[kind]():
                    base.append((m.start(), k, f"{kind}:{m.start()}:{m.end()}"))
        lines = [b[2] for b in sorted(base)]
        assert g["n_spans"] == len(list(filter(None, g["spans"].split(","))))
        assert g["base_sha256"] == hashlib.sha256(",".join(lines).encode()).hexdigest()
        assert set(lines) <= set(filter(None, g["spans"].split(",")))
    assert got[0]["n_card"] == 1 and got[0]["n_phone"] == 1


def test_pii_labelers_are_told_apart():
    post, prior, chance = pii.reliabilities({"++0+000": 50, "++00000": 30, "--0-000": 40, "+-0-0--": 5, "0000000": 20})
    assert post["++0+000"] > 0.9 > 0.1 > post["--0-000"]
    assert 0 < prior < 1 and np.allclose(chance.sum(2), 1)


def planted(seed=7, n=900):
    """(texts, for each the spans that were planted): personal data and look-alikes that are harmless, amid words."""
    r = random.Random(seed)
    hexes = lambda k: "".join(r.choice("0123456789abcdef") for _ in range(k))
    mixed = lambda k: "".join(r.choice("abcdefghijkmnpqrstuvwxyzABCDEFGHJKLMNPQRSTUVWXYZ23456789") for _ in range(k))
    good = [
        lambda: ('token = "', hexes(40), '" is'), lambda: ("api key: ", "AKIA" + mixed(16) + "7", " ok"), lambda: ("the secret is ", mixed(32) + "4x", " today"),
        lambda: ("call phone ", f"{r.randint(201, 989)}-{r.randint(200, 999)}-{r.randint(1000, 9999)}", " now"), lambda: ("social security ", f"{r.randint(100, 600)}-{r.randint(10, 99)}-{r.randint(1000, 9999)}", " there"),
        lambda: ("", f"Dr. {r.choice(['Maria', 'Peter', 'Anna'])} {r.choice(['Weber', 'Stone', 'Rey'])}", " said"), lambda: ("mac address ", ":".join(hexes(2) for _ in range(6)), " up"),
    ]
    bad = [
        lambda: ("isbn ", f"978-{r.randint(10, 99)}-{r.randint(1000, 9999)}-{r.randint(100, 999)}", " and"), lambda: ("in order ", str(r.randint(10**7, 10**8)), " shipped"), lambda: ("see ", "the-second-edition-of-2021-report", " for"),
        lambda: ("build ", f"{r.randint(1000, 9999)}.{r.randint(1000, 9999)}.{r.randint(100, 999)}", " of"), lambda: ("version_", "", ""), lambda: ("sold ", f"{r.randint(100, 999)} {r.randint(100, 999)} {r.randint(100, 999)}", " pages"),
        lambda: ("file ", "linux-headers-generic-5-lts-package", " of"),
    ]
    rows, truth = [], []
    for i in range(n):
        before, after = " ".join(words(r.randint(3, 30), i)), " ".join(words(r.randint(3, 30), i + 10**6))
        kind = (good, bad, None)[i % 3]
        if kind:
            a, body, b = r.choice(kind)()
            rows.append(f"{before} {a}{body}{b} {after}")
            truth.append((len(before) + 1 + len(a), len(before) + 1 + len(a) + len(body)) if kind is good else None)
        else:
            rows.append(f"{before} {after}")
            truth.append(None)
    return rows, truth


def test_pii_recall_on_planted_data(spark, monkeypatch):
    texts, truth = planted()
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    found = {r["doc_id"]: [s for s in r["spans"] if not s["base"]] for r in pii.detected(docs).collect()}
    caught = [any(s["start"] <= t[0] + 4 and s["end"] >= t[1] for s in found[i]) for i, t in enumerate(truth) if t]
    clean = [not found[i] for i, t in enumerate(truth) if not t]
    assert sum(caught) >= 0.9 * len(caught) and sum(clean) >= 0.95 * len(clean)
    # Every candidate of the loose patterns would mark far more of the clean texts: the method decides.
    loose = [bool(pii.more_spans(texts[i], pii.base_spans(texts[i]))) for i, t in enumerate(truth) if not t]
    assert sum(loose) >= 0.2 * len(loose)
    again = {r["doc_id"]: [s for s in r["spans"] if not s["base"]] for r in pii.detected(docs.repartition(7)).collect()}
    assert again == found


def test_pii_between_dense_base_spans():
    text = " ".join(f"a{i}@b.cd" for i in range(40)) + " 1.2.3.4 " + "5.6.7.8,9.8.7.6 123-45-6789 x@y.zz"
    base = pii.base_spans(text)
    got = pii.more_spans(text, base)
    assert ("ssn", "123-45-6789") in [(k, text[a:b]) for a, b, k in got]
    assert all(b <= s or a >= e for a, b, _ in got for s, e, _ in base)


def test_language(spark):
    bases = {"en": "the of and to in is that it was for", "fr": "le la les des une et est pour que dans", "de": "der die das und ist nicht ein mit von den"}
    r = random.Random(1)
    rows = [(i, " ".join(r.choice(bases[lang].split()) for _ in range(r.randint(5, 60))), lang) for i, lang in enumerate(sorted(bases) * 40)]
    rows += [(1000, None, "en"), (1001, "", None), (1002, "123 !!", "en"), (1003, "the" * 100, None), (5, "the of and", "en")]
    got = language_id.identified(spark.createDataFrame([(*x, 9) for x in rows], "doc_id long, text string, lang string, score int")).collect()
    assert len(got) == len(rows)
    truth = {i: lang for i, _, lang in rows[:120]}
    held = [g for g in got if g["held_out"] and g["doc_id"] in truth]
    assert held and all((zlib.crc32(str(g["doc_id"]).encode()) % 4 == 2) for g in held)
    assert sum(g["lang_pred"] == truth[g["doc_id"]] for g in held) >= 0.95 * len(held)
    und = {g["doc_id"]: g for g in got if g["doc_id"] >= 1000}
    assert [und[i]["lang_pred"] for i in (1000, 1001, 1002)] == ["und"] * 3 and 0 <= und[1003]["score"] <= 1


def test_language_sums_all_segmentations():
    pieces = {p: i for i, p in enumerate(["▁", "a", "b", "▁a", "ab", "ba", "▁ab"])}
    model = language_id.Pieces(pieces, np.log(np.random.default_rng(1).dirichlet(np.ones(len(pieces)), 2)))
    chances = [{p: float(model.rows[p][k]) for p in pieces} for k in range(2)]

    def total(text, k):
        return 1.0 if not text else sum((model.rows[text[:n]][k] if text[:n] in model.rows else model.unknown if n == 1 else 0) * total(text[n:], k) for n in range(1, min(len(text), 3) + 1))

    def uses(text, k):
        """Chance of each segmentation, with its pieces."""
        if not text:
            return [(1.0, ())]
        return [(q * p, (text[:n], *rest)) for n in range(1, min(len(text), 3) + 1) if (q := model.rows[text[:n]][k] if text[:n] in model.rows else model.unknown if n == 1 else 0) for p, rest in uses(text[n:], k)]

    for word in ("a", "ab", "abba", "bxa"):
        assert np.allclose(model.scores([word])[0], [np.log(total("▁" + word, k)) for k in range(2)])
        assert np.allclose(model._rescaled(word), model.scores([word])[0])
        every = uses("▁" + word, 1)
        want = collections.Counter()
        for p, parts in every:
            for part in parts:
                want[part] += p / sum(q for q, _ in every)
        got = language_id.segment_uses(word, chances[1], model.unknown, model.longest)
        assert set(got) == set(want) and all(abs(got[x] - want[x]) < 1e-9 for x in want)
    # Long words, and words of unknown letters beyond the range of numbers, are summed whole.
    for word in ("ab" * 24, "ab" * 200, "x" * 40, "xy" * 500, "abx" * 90):
        logs = [[0.0], [0.0]]
        for j in range(1, len(word) + 2):
            for k in range(2):
                terms = [logs[k][j - n] + math.log(model.rows[s][k] if s in model.rows else model.unknown) for n in range(1, min(j, 3) + 1) if (s := ("▁" + word)[j - n : j]) in model.rows or n == 1]
                logs[k].append(float(np.logaddexp.reduce(terms)))
        assert np.allclose(model.scores([word])[0], [logs[0][-1], logs[1][-1]])
        assert abs(sum(len(p) * n for p, n in language_id.segment_uses(word, chances[0], model.unknown, model.longest).items()) - len(word) - 1) < 1e-6


def test_letters_are_of_one_definition(spark):
    assert language_id.words("x² ½ ① Ⅷ aⅧb 3a_b É") == ["x", "a", "b", "a", "b", "é"]
    rows = [(1, "the of", "en"), (3, "² ½ ① Ⅷ", "en"), (4, "Ⅷx", None), (7, "le la", "fr"), (None, "the the", "en"), (1, "the of", "en")]
    got = language_id.identified(spark.createDataFrame(rows, "doc_id long, text string, lang string")).collect()
    assert len(got) == len(rows)
    pred = {g["doc_id"]: g["lang_pred"] for g in got}
    assert pred[3] == "und" and pred[4] != "und" and pred[None] != "und"


def test_scores_do_not_depend_on_what_was_kept(monkeypatch):
    pieces = {p: i for i, p in enumerate(["▁", "a", "b", "▁a", "ab"])}
    model = language_id.Pieces(pieces, np.log(np.random.default_rng(2).dirichlet(np.ones(len(pieces)), 3)))
    texts = ["a ab b", "ab ab " + "b" * 70, None, "ba bab a", "", "a"]
    once = model.totals(texts)[0]
    monkeypatch.setattr(language_id, "KEPT_WORDS", 2)
    again = language_id.Pieces(pieces, np.log(np.random.default_rng(2).dirichlet(np.ones(len(pieces)), 3)))
    assert np.allclose(once, np.concatenate([again.totals([t])[0] for t in texts]))


def test_quality(spark):
    r = random.Random(2)
    rows, labels = [], []
    for i in range(300):
        good = i % 3 > 0
        text = " ".join(r.choice("alpha beta gamma delta".split()) + ("" if good else r.choice(["***", "###", "!!"])) for _ in range(r.randint(3, 50)))
        rows.append((i, text))
        labels.append((i, int(good), 0))
    rows += [(900, None), (901, ""), (902, "x" * 3000)]
    got = {g["doc_id"]: g for g in quality.scored(spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, quality int, toxic int")).collect()}
    assert len(got) == len(rows) and all(0 <= g["score"] <= 1 and g["predicted"] == int(g["score"] >= 0.3) for g in got.values())
    held = [i for i in range(300) if zlib.crc32(str(i).encode()) % 5 == 0]
    assert all(got[i]["held_out"] for i in held)
    assert sum((got[i]["score"] >= 0.5) == (i % 3 > 0) for i in held) >= 0.95 * len(held)


def test_empty_tables(spark, empty):
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    made = [
        similarity_join.similarity_classes(empty), exact_dedup.exact_duplicates(empty), packing.packed(empty), fingerprints.edited_fingerprints(empty), mixing.mixed(empty), language_id.identified(empty),
        quality.scored(empty, labels), pii.digest(pii.detected(empty)), chat.read_back(chat.windows(spark.createDataFrame([], "conv_id long, turn long, role string, text string"))),
        html_text.extracted(spark.createDataFrame([], "page_id long, url string, html string")),
    ]
    assert all(d.collect() == [] for d in made)


def test_short_sets_use_combinations():
    tokens = np.arange(1, 31, dtype=np.uint64)
    every = np.ones(30, bool)
    sigs = set(similarity_join.prefix_signatures(tokens, np.full(30, 900), every, 3, 4).tolist())
    assert sigs and not sigs & set(similarity_join.mix64(tokens).tolist())
    assert similarity_join.class_counts(2, 3, 4) == [0] and similarity_join.class_counts(87, 3, 4) == [64, 32]


def test_packed_counts():
    r = np.random.default_rng(1)
    low = r.poisson(0.4, 4096).astype(np.uint8)
    low[7] = 255
    at, carry = np.array([3, 7, 4095]), np.array([1, 2**40, 300])
    want = low.astype(np.uint64)
    want[at] += carry.astype(np.uint64) * np.uint64(256)
    assert (similarity_join._unpacked_counts(similarity_join._packed_counts(low, at, carry), 4096) == want).all()
    nothing, none = np.zeros(64, np.uint8), np.zeros(0, np.int64)
    assert (similarity_join._unpacked_counts(similarity_join._packed_counts(nothing, none, none), 64) == nothing).all()


def test_sketch_counts_sets(docs, spark):
    cells = 1 << 12
    for texts in ([r[1] for r in awkward() if r[1] is not None], ["a b c d e f"] * 700 + ["x y"]):
        rows = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
        got = similarity_join.count_sketch(rows.repartition(3), cells)
        tokens = np.concatenate(shingle_sets([t.encode() for t in texts]))
        want = np.bincount(similarity_join._cells(tokens, cells), minlength=cells)
        assert (got == similarity_join.step_of(want)).all()
    assert similarity_join.step_of(1e13) > similarity_join.step_of(1e13 * 0.99) and len(set(similarity_join.step_of(np.arange(1000)).tolist())) == 1000


@pytest.mark.parametrize("seed", range(4))
def test_folding_keeps_groups_together(seed):
    r = np.random.default_rng(seed)
    n = r.integers(3, 4000, 600).astype(np.int32)
    ids, sig, task = np.arange(600), r.integers(0, 4, 600).astype(np.uint64), r.integers(0, 5, 600)

    def chained(sig, ids, n, links):
        order = np.lexsort((ids, n, sig))
        sig, ids, n = sig[order], ids[order], n[order]
        near = (sig[1:] == sig[:-1]) & (4 * n[:-1].astype(int) >= 3 * n[1:].astype(int))
        parent = {i: i for i in range(600)}

        def root(x):
            while parent[x] != x:
                x = parent[x]
            return x

        for a, b in [*links, *zip(ids[:-1][near].tolist(), ids[1:][near].tolist(), strict=True)]:
            a, b = root(int(a)), root(int(b))
            parent[max(a, b)] = min(a, b)
        return [root(i) for i in range(600)]

    kept, links = [], []
    for t in range(5):
        rows, pairs = similarity_join.folded(sig[task == t], ids[task == t], n[task == t], 3, 4)
        kept.append(rows)
        links += pairs.tolist()
    assert chained(*(np.concatenate(c) for c in zip(*kept, strict=True)), links) == chained(sig, ids, n, [])
    assert sum(len(k[0]) for k in kept) < 600


def test_words_of_one_pattern_do_not_collide():
    a = "0"
    for _ in range(10):
        a += a.translate(str.maketrans("01", "10"))
    x, y = a.translate(str.maketrans("01", "ab")), a.translate(str.maketrans("01", "ba"))
    hashes, _ = hashed_words([x.encode(), y.encode(), b"q" * 64, b"q" * 64 + b"   ", b"z" * 200, b"z" * 200 + b" " * 300])
    assert hashes[0] != hashes[1] and hashes[2] == hashes[3] and hashes[4] == hashes[5]


STAGE_DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def stage_rows():
    near = words(60, 9)
    changed = [*near[:30], "changed", *near[31:]]
    texts = ["one text of a few words", "ONE text of a few words", "another text", "one text of a few words", "a text without an id", "last text of these", None, "", " ".join(near), " ".join(changed), " ".join(near), "² ½"]
    ids = [1, 2, 2, 2, None, 5, 6, 7, 8, 9, 9, 10]
    return [(i, t, "en", "ab"[k % 2] if k % 5 else None, len(t or "")) for k, (i, t) in enumerate(zip(ids, texts, strict=True))]


def collected(df):
    return sorted(((r["doc_id"], r["text"]) for r in df.collect()), key=str)


def test_stages_decide_on_rows(spark, small):
    import corpus_pipeline as cp

    rows = stage_rows()
    docs = spark.createDataFrame([(*r, "extra") for r in rows], STAGE_DOCS + ", row string")
    # Of equal texts the row with the largest doc_id, one of each.
    best = {}
    for i, t, *_ in rows:
        key = lower(t)
        if key not in best or (i is not None, i or 0, t or "") > (best[key][0] is not None, best[key][0] or 0, best[key][1] or ""):
            best[key] = (i, t)
    assert collected(cp.drop_exact_copies(spark, docs, small)) == sorted(best.values(), key=str)
    # Of near copies the row with the smallest doc_id, and all rows without words.
    order = sorted(range(len(rows)), key=lambda k: (rows[k][0] is not None, rows[k][0] or 0, rows[k][1] is not None, rows[k][1] or ""))
    sets = {n: shingles(rows[k][1]) for n, k in enumerate(order)}
    roots = closure(sets)
    assert collected(cp.drop_near_copies(spark, docs, small)) == sorted((rows[order[n]][:2] for n, root in roots.items() if n == root), key=str)
    # Languages: letterless rows go, a row without an id stays.
    kept = collected(cp.identify_language(spark, docs, small))
    assert kept == sorted(((i, t) for i, t, *_ in rows if t and any(c.isalpha() for c in t)), key=str)
    mixed = collections.Counter(collected(cp.mix_sources(spark, docs, small)))
    assert set(mixed) <= {(i, t) for i, t, *_ in rows if WORD.findall(t or "")} and max(mixed.values()) <= 4
    assert all(set(stage(spark, docs, small).columns) == set(cp.COLUMNS) for _, stage in cp.STAGES[:-1])


def test_pipeline_on_the_smallest_tables(spark, small):
    """Each stage's result against plain Python on what the stage before it kept."""
    import corpus_pipeline as cp

    docs = common.table(spark, small, "documents")
    langs = common.checkpointed(cp.identify_language(spark, docs, small))
    before = {r["doc_id"]: r for r in docs.collect()}
    now = {r["doc_id"]: r for r in langs.collect()}
    clean = [i for i, r in before.items() if r["text"] and len(re.findall(r"[^\W\d_]+", r["text"])) > 20]
    assert set(now) <= set(before) and sum(i in now for i in clean) >= 0.99 * len(clean)
    exact = common.checkpointed(cp.drop_exact_copies(spark, langs, small))
    want = {lower(r["text"]): i for i, r in sorted(now.items())}
    now = {r["doc_id"]: r for r in exact.collect()}
    assert set(now) == set(want.values())
    near = common.checkpointed(cp.drop_near_copies(spark, exact, small))
    roots = closure({i: shingles(r["text"]) for i, r in now.items()})
    now = {r["doc_id"]: r for r in near.collect()}
    assert set(now) == {i for i, root in roots.items() if i == root}
    mixed = common.checkpointed(cp.mix_sources(spark, near, small))
    copies = collections.Counter(r["doc_id"] for r in mixed.collect())
    assert copies == {r["doc_id"]: r["copies"] for r in mixing.mixed(near).collect() if r["copies"]}
    encode, want = reference_ids(), collections.Counter()
    for i, n in copies.items():
        ids = np.array([*encode(now[i]["text"] or ""), 0], "<u4")
        want.update({(i, at, zlib.crc32(ids[at : at + 1024].tobytes())): n for at in range(0, len(ids), 1024)})
    assert collections.Counter((r["doc_id"], r["start"], r["ids_crc32"]) for r in cp.pack_sequences(spark, mixed, small).collect()) == want


def test_stages_on_an_empty_table(spark, small):
    import corpus_pipeline as cp

    nothing = spark.createDataFrame([], STAGE_DOCS)
    assert all(stage(spark, nothing, small).collect() == [] for _, stage in cp.STAGES)


def test_training_bounds_are_in_the_readme():
    from pathlib import Path

    told = (Path(__file__).resolve().parents[2] / "README.md").read_text()
    assert "language_id.TRAINING_ROWS" in told and "quality.TRAINING_ROWS" in told


def _met_in_prefixes(rows):
    sigs = [set(similarity_join.prefix_signatures(t, w, w > 100, 3, 4).tolist()) for t, w in rows]
    return len(sigs[0] & sigs[1])


@pytest.mark.parametrize("seed", range(6))
def test_prefix_signatures_meet_often_enough(seed):
    r = random.Random(seed)
    universe = list(range(1, 3000))
    weight = {t: r.choice([1, 2, 3, 500, 900]) for t in universe}
    tried = 0
    for _ in range(200):
        n = r.choice([3, 4, 5, 6, 7, 8, 11, 12, 16, 23, 40, 44, 58, 86, 87, 88, 116, 117, 200, 400])
        x = set(r.sample(universe, n))
        y = set(x)
        for _ in range(r.randint(0, max(1, n // 4))):
            y.discard(r.choice(sorted(y)))
            if r.random() < 0.4:
                y.add(r.choice(universe))
        if len(y) < 3 or 4 * len(x & y) < 3 * len(x | y):
            continue
        tried += 1
        rows = [(np.array(sorted(s), np.uint64), np.array([weight[v] for v in sorted(s)])) for s in (x, y)]
        assert _met_in_prefixes(rows) >= similarity_join.SHARED
    assert tried > 30


def test_chance_meetings_tie_no_families(spark):
    # A ring of 400 unlike texts: each shares one shingle with the next, so a single common signature joins all of them.
    texts = [" ".join([f"s{i}_{j}" for j in range(5)] + [f"w{i}_{j}" for j in range(14)] + [f"s{(i + 1) % 400}_{j}" for j in range(5)]) for i in range(400)]
    texts += [f"{texts[i]} more" for i in range(20)]
    rows = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    found = {r["id"]: r["component"] for r in similarity_join.candidates(rows, 400 * 20, 3, 4).collect()}
    assert all(found[400 + i] == found[i] for i in range(20)) and len(found) == 40 and len(set(found.values())) == 20


def test_candidates_in_large_and_split_groups(spark, monkeypatch):
    monkeypatch.setattr(similarity_join, "WHOLE_GROUP", 3)
    sets = [(k, i, 40 + i % 3) for k in range(30) for i in range(k % 8 + 1)]
    rows = [(s, 100 * k + i, n, None) for k, i, n in sets for s in (3 * k, 3 * k + 1, 3 * k + 2)]
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "5")
    try:
        got = similarity_join.chains(spark.createDataFrame(rows, "sig long, id long, n int, other long"), 3, 4).collect()
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    parent = {100 * k + i: 100 * k + i for k, i, _ in sets}
    for a, b in got:
        low, high = sorted((parent[a], parent[b]))
        parent = {x: low if y == high else y for x, y in parent.items()}
    assert all(y == x // 100 * 100 for x, y in parent.items()) and len({(a, b) for a, b in got}) == len(got)
