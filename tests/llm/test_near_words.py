from purchase_planner.llm import pii_disclosure


def test_all_words_of_a_text_are_candidates(spark):
    """The first and last word of a text, words far from the mention, short ones, and words in texts whose length changes in lower case."""
    far = " ".join(f"common{k}" for k in range(30))
    rows = [(i, f"zebrafish a@b.org okapi common{i}" if i < 2 else f"Wu {far} c@d.org \u0130x{i}" if i < 4 else f"nothing here {far} common{i % 2}") for i in range(40)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    spans = {r["doc_id"]: r["spans"] for r in pii_disclosure.report(docs).collect()}
    assert "term:0:9" in spans[0] and "term:18:23" in spans[0] and "term:0:2" in spans[2] and spans[20] == ""
    assert spans[2].count("term") == 2  # the other one is the word with U+0130


def test_copies_of_one_text_are_no_evidence(spark):
    docs = spark.createDataFrame([(i, "zebrafish a@b.org" if i < 5 else "x") for i in range(40)], "doc_id long, text string")
    assert all("term" not in r["spans"] for r in pii_disclosure.report(docs).collect())


def test_terms_against_brute_force(spark):
    """Terms and their disclosure by the definition, over rows with hot and rare entities."""
    import math
    import random
    import re

    rnd = random.Random(4)
    vocabulary = [f"w{chr(97 + k // 26)}{chr(97 + k % 26)}" for k in range(300)]
    rows = []
    for i in range(120):
        words = rnd.choices(vocabulary, k=rnd.randint(3, 20))
        entity = "hot@x.org" if i % 3 == 0 else f"e{i % 25}@y.org" if i % 5 == 1 else None
        if entity and rnd.random() < 0.7:
            words += [f"Name{'abcdefghij'[i % 10]}{entity[0]}"]
        rows.append((i, " ".join([*words, *([entity] if entity else [])])))
    email = re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
    has = {i: {w.lower() for w in re.findall(r"[^\W\d_]+", t)} for i, t in rows}
    said = {i: set(email.findall(t)) for i, t in rows}
    want = {}
    for e in {e for s in said.values() for e in s}:
        of = [i for i in said if e in said[i]]
        if len({dict(rows)[i] for i in of}) < 2:
            continue
        for w in {w for i in of for w in has[i]}:
            together = [i for i in of if w in has[i]]
            if len({dict(rows)[i] for i in together}) < 2:
                continue
            d = 1 + math.log2(len(together) / sum(w in x for x in has.values())) / math.log2(len(rows) / len(of))
            if d >= pii_disclosure.GENERALISE:
                for i in together:
                    want[i, w] = max(want.get((i, w), 0), d)
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    base = pii_disclosure.base_table(docs)
    ids = {r["key"]: r["id"] for r in base.collect()}
    got = {(ids[r["key"]], w): d for r in pii_disclosure.disclosing_terms(docs, base).collect() for w, d in r["terms"].items()}
    assert got.keys() == want.keys() and all(abs(got[k] - want[k]) < 1e-9 for k in want) and want
