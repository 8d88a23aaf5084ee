import random

from rowsketch.llm import line_dedup


def words(line):
    return len(line.split())


def plain(docs, t):
    """Repeats of whole-line runs of at least t words, deleted until none is left: by looking at every earlier line."""
    live = {i: [(k, line) for k, line in enumerate(text.split("\n")) if words(line)] for i, text in docs}
    key = lambda line: line.strip(" ").lower()
    while True:
        gone = set()
        order = sorted(live)
        for i in order:
            for j in order:
                if j > i:
                    break
                a, b = live[i], live[j]
                for x in range(len(a)):
                    for y in range(len(b)):
                        if i == j and y >= x:
                            break
                        if key(a[x][1]) != key(b[y][1]) or (x and y and key(a[x - 1][1]) == key(b[y - 1][1])):
                            continue
                        run = []
                        while x + len(run) < len(a) and y + len(run) < len(b) and key(a[x + len(run)][1]) == key(b[y + len(run)][1]):
                            run.append(a[x + len(run)])
                        if sum(words(line) for _, line in run) >= t:
                            gone |= {(i, k) for k, _ in run}
        if not gone:
            return live
        live = {i: [(k, line) for k, line in lines if (i, k) not in gone] for i, lines in live.items()}


def repeated_runs(texts, t):
    """Runs of at least t words that occur twice among the texts."""
    seen, twice = set(), []
    for text in texts:
        lines = [x.strip(" ").lower() for x in text.split("\n") if words(x)]
        for a in range(len(lines)):
            n = 0
            for b in range(a, len(lines)):
                n += words(lines[b])
                if n >= t:
                    run = tuple(lines[a : b + 1])
                    if run in seen:
                        twice.append(run)
                    seen.add(run)
                    break
    return twice


def build(seed, n=40):
    rng = random.Random(seed)
    pool = [" ".join(rng.choice("abcdefgh") * rng.randint(1, 3) for _ in range(rng.randint(1, 8))) for _ in range(60)]
    passages = [[rng.choice(pool) for _ in range(rng.randint(2, 6))] for _ in range(6)]
    docs = []
    for i in range(n):
        lines = []
        for _ in range(rng.randint(0, 4)):
            lines += rng.choice(passages) if rng.random() < 0.5 else [rng.choice(pool), ""]
        docs.append((i, "\n".join(lines)))
    return docs


def test_nothing_repeats_afterwards_and_first_places_stay(make):
    for seed in (1,):
        docs = build(seed)
        got = {r["doc_id"]: r["text"] for r in line_dedup.dedup_lines(make(docs)).collect()}
        assert not repeated_runs([got[i] for i, _ in sorted(docs)], 20)
        # every line of the input is still somewhere
        lines = {x.strip().lower() for _, t in docs for x in t.split("\n")}
        kept = {x.strip().lower() for t in got.values() for x in t.split("\n")}
        assert lines - {""} == kept - {""}
        # only whole lines went, in place
        for i, t in docs:
            it = iter(t.split("\n"))
            assert all(any(x == y for y in it) for x in got[i].split("\n") if x)


def test_matches_plain_deletion_on_separate_passages(make):
    a = "the first line of a passage that is long enough\nand the second line of it"
    b = "another passage stands here with more than ten words in all of it"
    docs = [(1, f"start of one\n{a}\nend of one"), (2, f"{b}\nstart of two\n{a}"), (3, f"x\n{a.upper()}\ny\n{b}\nshort"), (4, "short\nshort"), (5, a)]
    got = {r["doc_id"]: (r["text"], r["n"]) for r in line_dedup.dedup_lines(make(docs), count="n").collect()}
    want = plain(docs, 10)
    for i, text in docs:
        assert got[i][0] == "\n".join(line for _, line in want[i])
        assert got[i][1] == len(text.split("\n")) - len(want[i])
    assert got[3][0] == "x\ny\nshort" and got[5][0] == "" and got[4][0] == "short\nshort"


def test_another_context_first(make):
    """The selected hash comes first elsewhere; the rest of the shared run is found in a later round."""
    lines = [f"line number {k} holds these few words" for k in range(6)]
    docs = [(k, lines[k % 6]) for k in range(6)] + [(10, "p\n" + "\n".join(lines)), (11, "q\n" + "\n".join(lines))]
    got = {r["doc_id"]: r["text"] for r in line_dedup.dedup_lines(make(docs)).collect()}
    assert not repeated_runs([got[i] for i, _ in docs], 20)


def test_odd(odd, none, spark):
    out = line_dedup.dedup_lines(odd)
    assert out.columns == odd.columns and out.count() == odd.count()
    texts = {r["doc_id"]: r["text"] for r in out.collect() if r["doc_id"] != 1}
    assert texts[2] is None and texts[3] == ""
    assert sorted(r["text"] for r in out.where("doc_id = 1").collect()) == ["", "The cat sat on the mat and looked at the dog."]
    assert line_dedup.dedup_lines(none).count() == 0


def test_stays_in_the_jvm(documents):
    from rowsketch.shared import materialise

    plan = line_dedup.dedup_lines(materialise(documents))._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan


def test_matches_plain_deletion_on_random_lines(make):
    """Lines of ten words and more: each repeat goes, and nothing else."""
    for seed in (2, 3, 4):
        rng = random.Random(seed)
        pool = [" ".join(rng.choice("abcdef") * rng.randint(1, 3) for _ in range(rng.randint(10, 14))) for _ in range(25)]
        docs = []
        for i in range(30):
            lines = [rng.choice([x, x.upper(), f"  {x}", f"{x}\t", f"{x}\r", ""]) for x in rng.choices(pool, k=rng.randint(0, 6))]
            docs.append((i, "\n".join(lines)))
        got = {r["doc_id"]: (r["text"], r["n"]) for r in line_dedup.dedup_lines(make(docs), count="n").collect()}
        want = plain([(i, t.replace("\t", " ").replace("\r", " ")) for i, t in docs], 10)
        assert sum(n for _, n in got.values()) > 20
        for i, text in docs:
            gone = {k for k, line in enumerate(text.split("\n")) if words(line)} - {k for k, _ in want[i]}
            assert got[i] == ("\n".join(x for k, x in enumerate(text.split("\n")) if k not in gone), len(gone)), (seed, i)


def test_random_runs_of_short_lines(make):
    for seed in (5, 6):
        docs = build(seed, 25)
        got = {r["doc_id"]: r["text"] for r in line_dedup.dedup_lines(make(docs)).collect()}
        assert not repeated_runs([got[i] for i, _ in docs], 20)


def test_one_document_that_many_repeat(make):
    """The join with it is dealt out by salt, so no one task gets them all."""
    lines = [f"line number {k} of a passage with quite enough words to be found" for k in range(4)]
    docs = [(0, "\n".join(lines))] + [(k, f"own beginning of {k}\n" + "\n".join(lines[k % 3 :])) for k in range(1, 120)]
    got = {r["doc_id"]: r["text"] for r in line_dedup.dedup_lines(make(docs)).collect()}
    assert got[0] == docs[0][1] and all(got[k] == f"own beginning of {k}" for k in range(1, 120))
