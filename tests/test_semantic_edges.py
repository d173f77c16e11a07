"""Semantic edges, families and contradictions of texts against brute force, with shingles that many texts hold."""

import random

from factlake.operators import maintenance as M


def shingles(text):
    w = (text or "").lower().split()
    return {tuple(w[i : i + 4]) for i in range(len(w) - 3)}


def test_large_groups_are_whole(spark):
    rnd = random.Random(1)
    word = lambda: f"w{rnd.randint(0, 400)}"
    base = [word() for _ in range(40)]
    texts = ["Same words in all of these copies here"] * 40 + [" ".join(base)] * 5
    for _ in range(45):
        w = list(base)
        for _ in range(rnd.randint(0, 5)):
            w[rnd.randrange(len(w))] = word()
        texts.append(" ".join(w))
    line = " ".join(word() for _ in range(12))
    texts += [f"{line} {' '.join(word() for _ in range(rnd.randint(1, 20)))}" for _ in range(40)]
    texts += [None, "", "one two three", "ONE two three four", "one\ttwo\nthree  four"]
    rnd.shuffle(texts)
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    sets = [shingles(t) for t in texts]
    want = {}
    for i, a in enumerate(sets):
        for j in range(i):
            if a and sets[j] and (x := round(len(a & sets[j]) / len(a | sets[j]), 6)) >= 0.5:
                want[i, j] = x
    got = M.semantic_edges(df).collect()
    assert len(got) == len(want) and {(r["src"], r["dst"]): r["jaccard"] for r in got} == want
    near = M.semantic_edges(df, most=0.95).collect()
    assert {(r["src"], r["dst"]) for r in near} == {k for k, x in want.items() if x <= 0.95}
    family = {i: i for k in want for i in k}  # components: the least id that is reached

    def root(i):
        while family[i] != i:
            i = family[i]
        return i

    for a, b in want:
        a, b = root(a), root(b)
        family[max(a, b)] = min(a, b)
    family = {i: root(i) for i in family}
    assert {r["doc_id"]: r["family"] for r in M.semantic_families(df).collect()} == family


def test_texts_without_a_partner_leave_little_on_disk(spark):
    """What is stored for texts that share nothing is far less than the texts, which hold some eight bytes a shingle."""
    from pathlib import Path

    from factlake.sources.scratch import scratch_root

    rnd = random.Random(2)
    texts = [" ".join(f"w{rnd.randint(0, 50_000)}" for _ in range(2000)) for _ in range(100)]
    texts += [texts[0] + " and more", texts[1]]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    root = Path(scratch_root(spark)) / "factlake"
    stored = lambda: sum(f.stat().st_size for f in root.glob("edges-*/*.parquet"))
    before = stored()
    got = {(r["src"], r["dst"]) for r in M.semantic_edges(df).collect()}
    assert got == {(100, 0), (101, 1)}
    assert stored() - before < sum(map(len, texts)) / 4
