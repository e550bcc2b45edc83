import random
import re

from windowforge.llm import jaccard
from windowforge.llm.jaccard import components, jaccard_groups
from windowforge.llm.shingles import shingles, word_hashes


def brute(rows):
    def of(text):
        w = re.findall("[^\x20\x09-\x0d]+", "".join(c.lower() if c.isascii() else c for c in text or ""))
        return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} or ({tuple(w)} if w else set())

    sets, root = {i: of(t) for i, t in rows}, {i: i for i, _ in rows}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for a in sets:
        for b in sets:
            if a < b and sets[a] and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b]):
                x, y = sorted((find(a), find(b)))
                root[y] = x
    return {i: (len(sets[i]), find(i)) for i in sets}


def corpus(seed, n=260):
    rng = random.Random(seed)
    words = ["w%d" % k for k in range(400)] + ["É", "É", "a\x1fb", "A b"]
    passage = [rng.choice(words) for _ in range(60)]
    texts = [None, "", " \t\n", "one", "ONE", "one two", "one two three four five", "x " * 50, "x " * 80]
    while len(texts) < n:
        kind = rng.random()
        if kind < 0.35 or len(texts) < 12:
            w = [rng.choice(words) for _ in range(rng.choice([3, 8, 40, 120]))]
            if rng.random() < 0.3:
                w += passage
        else:
            w = (rng.choice(texts[9:]) or "").split()
            for _ in range(rng.choice([0, 1, 1, 2, 3, 5, 8])):
                if w:
                    w[rng.randrange(len(w))] = rng.choice(words)
            w += [rng.choice(words) for _ in range(rng.choice([0, 0, 2, 9]))]
        texts.append(" ".join(w))
    return list(enumerate(texts))


def check(spark, rows):
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard_groups(spark.createDataFrame(rows, "doc_id long, text string").repartition(3)).collect()}
    assert got == brute(rows)


def test_against_brute_force(spark, monkeypatch):
    check(spark, corpus(1))
    monkeypatch.setattr(jaccard, "PIVOTS", 1)
    monkeypatch.setattr(jaccard, "COUNTED", 0.9)
    monkeypatch.setattr(jaccard, "BROADCAST_IDS", 0)
    check(spark, corpus(2))


def test_chains_within_one_region(spark, monkeypatch):
    """A line of documents, each linked to its neighbours alone, mixed with boilerplate that all share."""
    rng = random.Random(4)
    rows, w = [], ["c%d" % k for k in range(60)]
    for i in range(40):
        rows.append((i, " ".join(w)))
        w = w[3:] + ["d%d_%d" % (i, k) for k in range(3)]
    rng.shuffle(rows)
    rows = [(k, t) for k, (_, t) in enumerate(rows)]
    for pivots in (1, 32):
        monkeypatch.setattr(jaccard, "PIVOTS", pivots)
        check(spark, rows)


def test_links_across_cells_are_found_in_windows(spark, monkeypatch):
    """Lines of texts that slide on by four words, so that each is linked to the next two alone, and cells hold several; all that is
    bounded by a parameter is over its bound."""
    rng, rows, labels = random.Random(6), [], []
    for line in range(4):
        w = ["l%d_%d" % (line, k) for k in range(60 + 4 * 14)]
        rows += [" ".join(w[4 * k : 4 * k + 60]) for k in range(14)]
    rng.shuffle(rows)
    keep = jaccard.materialize
    monkeypatch.setattr(jaccard, "materialize", lambda df, label: (labels.append(label), keep(df, label))[1])
    for name, value in {"PIVOTS": 2, "LEAF": 1, "HOT": 2, "HOT_KEYS": 10**9, "BROADCAST_PAIRS": 0, "BROADCAST_SHINGLES": 0}.items():
        monkeypatch.setattr(jaccard, name, value)
    check(spark, list(enumerate(rows)))
    assert {"windows-0", "leaves-0", "distances-1"} <= set(labels)


def test_a_large_group_keeps_few_links(spark, monkeypatch):
    """Near copies that are all linked with each other: what is kept to connect them grows with the documents, not with pairs."""
    w, counts, inside = ["g%d" % k for k in range(60)], [], jaccard.components
    monkeypatch.setattr(jaccard, "PIVOTS", 8)
    monkeypatch.setattr(jaccard, "components", lambda edges, *more: (counts.append(edges.count()), inside(edges, *more))[1])
    got = jaccard_groups(spark.createDataFrame([(i, " ".join([*w, "end%d" % i])) for i in range(80)], "doc_id long, text string")).collect()
    assert {r.component_id for r in got} == {0} and max(counts) <= 2 * 80


def test_boundary_documents_bring_their_shingles_once(spark, monkeypatch):
    """However many cells a document is a boundary of, each of its shingles is one row when it meets what lies in them."""
    rng, rows = random.Random(6), []
    for line in range(4):
        w = ["l%d_%d" % (line, k) for k in range(60 + 4 * 24)]
        rows += [" ".join(w[4 * k : 4 * k + 60]) for k in range(24)]
    rng.shuffle(rows)
    monkeypatch.setattr(jaccard, "PIVOTS", 16)
    frame = type(spark.range(1))
    join, counts = frame.join, []

    def counted(self, other, on=None, how=None):
        out = join(self, other, on, how)
        if isinstance(on, str) and on == "id" and how is None and {"key", "place"} <= set(self.columns):
            counts.append((out.count(), out.select("id", "key").distinct().count()))
        return out

    monkeypatch.setattr(frame, "join", counted)
    check(spark, list(enumerate(rows)))
    assert any(n for n, _ in counts) and all(n == distinct for n, distinct in counts)


def test_repeated_rows_and_empty_table(spark):
    got = jaccard_groups(spark.createDataFrame([(5, "a b c d e f"), (5, "a b c d e f"), (3, "A b c D e f"), (None, "z")], "doc_id long, text string").withColumn("id", jaccard.F.lit("clash"))).collect()
    assert sorted((r.doc_id or -1, r.n_shingles, r.component_id or -1) for r in got) == [(-1, 1, -1), (3, 2, 3), (5, 2, 3), (5, 2, 3)]
    assert jaccard_groups(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_components_of_a_long_path(spark):
    n = 200
    order = list(range(n))
    random.Random(8).shuffle(order)
    got = components(spark.createDataFrame(list(zip(order, order[1:])), "a long, b long")).collect()
    assert {(r.node, r.root) for r in got} == {(k, 0) for k in range(1, n)}


def test_shingles_follow_the_words():
    assert len(shingles("")) == 0 and len(shingles(None)) == 0
    assert len(shingles("a b c d")) == 1 and len(shingles("a b c d e")) == 1 and len(shingles("a a a a a a a")) == 1
    assert (shingles("A b\tC\x0bd e f") == shingles("a B c d\r\nE f")).all()
    assert len(shingles("a b c d e f")) == 1


def test_word_hashes_tell_words_apart():
    words = ["a", "a\x00", "\x00a", "ab", "é", "12345678", "12345678\x00", "123456789", "x" * 16, "x" * 17, "y" * 256, "y" * 257, "y" * 300]
    h = word_hashes(" \t".join([*words, *words[::-1]]).encode())
    assert list(h[: len(words)]) == list(h[len(words) :][::-1]) and len(set(h)) == len(words)
    assert len(word_hashes(b"")) == 0 and len(word_hashes(b" \n\x0b\x0c\r\t")) == 0
