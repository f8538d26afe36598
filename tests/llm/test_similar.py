import random
import re

from hazemedian.llm.chunks import chunk_ends, repeated_passages, without_repeated_passages
from hazemedian.llm.jaccard import linked_components, ngram_components, ngram_links
from hazemedian.llm.lines import line_components, without_repeated_lines

from .conftest import HARD

LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def shingles(text):
    w = re.findall(r"[^\x20\x09-\x0D]+", (text or "").translate(LOWER))
    return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())


def brute_components(sets, linked):
    label = {d: d for d in sets}
    names = sorted(sets)
    changed = True
    edges = [(a, b) for i, a in enumerate(names) for b in names[:i] if linked(sets[a], sets[b])]
    while changed:
        changed = False
        for a, b in edges:
            low = min(label[a], label[b])
            if label[a] != low or label[b] != low:
                label[a] = label[b] = low
                changed = True
    return label


def edited(text, share, seed):
    rng = random.Random(seed)
    w = text.split(" ")
    for _ in range(int(len(w) * share)):
        w[rng.randrange(len(w))] = "edit" + str(rng.random())
    return " ".join(w)


def test_components_equal_brute_force(frame, words):
    base = [words(n, n) for n in (6, 9, 40, 120, 300)]
    rows = [(100 + k, edited(base[k % 5], (k % 7) / 100, k)) for k in range(150)]
    rows += [(1000 + k, base[4] + " " + words(k * 4, k)) for k in range(60)]  # lengths round the limit
    rows += [(2000 + k, words(60, 77) + " " + words(60, k)) for k in range(40)]  # one shared passage
    rows += HARD + [(40, "A b C d"), (41, "word")]
    sets = {d: shingles(t) for d, t in rows}
    want = brute_components(sets, lambda a, b: bool(a and b) and 100 * len(a & b) >= 75 * len(a | b))
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in ngram_components(frame([*rows, (None, base[3])])).collect()}
    assert got == {d: (len(sets[d]), want[d]) for d in sets}
    assert len({c for _, c in got.values()}) < len(got) - 50
    assert ngram_components(frame([])).count() == 0


def test_repeated_rows_each_give_a_row(frame, words):
    t = words(30, 1)
    got = ngram_components(frame([(5, t), (5, t), (9, t), (8, None)])).collect()
    assert sorted((r["doc_id"], r["component_id"]) for r in got) == [(5, 5), (5, 5), (8, 8), (9, 5)]


def test_every_link_inside_a_group_is_found(frame, words, monkeypatch):
    from hazemedian.llm import jaccard

    base = words(200, 5)
    rows = [(k, edited(base, (k % 9) / 100, k)) for k in range(70)] + [(200, words(60, 1)), (201, words(60, 1)), (201, words(60, 1) + " end"), (202, words(50, 2))] + HARD[:7]
    sets = [shingles(t) for _, t in rows]
    link = lambda a, b: bool(a and b) and 100 * len(a & b) >= 75 * len(a | b)
    want = sorted((d, sum(link(a, b) for j, b in enumerate(sets) if j != k)) for k, ((d, _), a) in enumerate(zip(rows, sets, strict=True)))
    differing = {frozenset(map(frozenset, (a, b))) for a in sets for b in sets if a != b and link(a, b)}
    df = frame([*rows, (None, base)])
    for size in (1 << 21, 20_000):
        monkeypatch.setattr(jaccard, "BLOCK_BYTES", size)
        got = linked_components(df).collect()
        assert sorted((r["doc_id"], r["n_links"]) for r in got) == want
        links, members = ngram_links(df)
        links, of = links.collect(), members.collect()
        assert len({(r["a"], r["b"]) for r in links}) == len(links) == len(differing)
        assert all(r["a"] < r["b"] for r in links) and {r["node"] for r in of} >= {r["a"] for r in links} | {r["b"] for r in links}
    assert sorted((r["doc_id"], r["n_shingles"], r["component_id"]) for r in got) == sorted(map(tuple, ngram_components(df).collect()))
    assert linked_components(frame([])).count() == 0 and ngram_links(frame([]))[0].count() == 0


def test_star_rounds_and_crossing_round_agree(spark, frame, words, monkeypatch):
    """However many pairs star rounds leave to the crossing round, the components are the same."""
    from hazemedian.llm import components

    base = words(200, 5)
    df = frame([(k, edited(base, 0.02 + (k % 5) / 100, k)) for k in range(80)])
    found = []
    for few, turns in ((0, 5), (10**9, 5), (4, 0)):
        monkeypatch.setattr(components, "FEW_PAIRS", few)
        monkeypatch.setattr(components, "STAR_ROUNDS", turns)
        found.append(sorted(map(tuple, ngram_components(df).collect())))
    assert found[0] == found[1] == found[2]


def test_components_whatever_a_task_holds(spark, monkeypatch):
    from hazemedian.llm import components
    from hazemedian.llm.common import Scratch

    rng = random.Random(1)
    edges = [(rng.randrange(300), rng.randrange(300)) for _ in range(140)] + [(1000 + k, 1001 + k) for k in range(40)]
    df, found = spark.createDataFrame(edges, "a long, b long"), []
    want = brute_components({x: x for e in edges for x in e}, lambda x, y: (x, y) in edges or (y, x) in edges)
    for most in (10**6, 20):
        monkeypatch.setattr(components, "EDGES_A_TASK", most)
        found.append({r["node"]: r["label"] for r in components.connected(Scratch(spark), df).collect()})
    assert found[0] == found[1] == {k: want[k] for k in found[0]}
    assert len(found[0]) > 150 and components.connected(Scratch(spark), df.limit(0)).count() == 0


def line_set(line):
    line = line.translate(LOWER).strip(" \t\r\x0b\x0c")
    return {line[i : i + 8] for i in range(len(line) - 7)} if len(line) >= 8 else {line}


def test_lines_equal_brute_force(frame, words):
    a, b = words(25, 1), words(30, 2)
    rows = [(1, f"{a}\n{words(9, 3)}\n{b}"), (2, f"{a.upper()}  \nshort\n{b} tail"), (3, f"{b[:-1]}z\n\nshort"), (4, words(20, 9)), (5, None), (6, ""), (7, " \n \n"), (8, "日本語の長い一行です。同じ。\n日本語の長い一行です。同じ。")]
    lines = {(d, k): x for d, t in rows if t for k, x in enumerate(t.split("\n")) if x.strip(" \t\r\x0b\x0c")}
    sets = {k: line_set(x) for k, x in lines.items()}
    label = brute_components(sets, lambda x, y: 100 * len(x & y) >= 75 * len(x | y))
    groups = [k for k in label if sum(v == label[k] for v in label.values()) > 1]
    got = {(r["doc_id"], r["line_no"]): ((r["keep_doc_id"], r["keep_line_no"]), r["kept"]) for r in line_components(frame(rows)).collect()}
    assert got == {k: (label[k], k == label[k]) for k in groups}
    clean = {r["doc_id"]: r["text"] for r in without_repeated_lines(frame(rows)).collect()}
    assert clean[1] == rows[0][1] and clean[2] == "short" and clean[3] == "" and clean[8].count("\n") == 0 and clean[5] is None
    assert line_components(frame([])).count() == 0


def test_line_recall_at_the_limit(frame):
    """Pairs a little above the limit are found in almost all cases."""
    rng = random.Random(4)
    rows = []
    for k in range(200):
        line = "".join(rng.choice("abcdefghij klmno") for _ in range(160)).strip("k ") + "q"
        rows += [(2 * k, "x" + line), (2 * k + 1, "x" + line[:-18] + "".join(rng.choice("uvwxyz") for _ in range(18)))]
    sets = {d: line_set(t) for d, t in rows}
    pairs = [k for k in range(200) if 100 * len(sets[2 * k] & sets[2 * k + 1]) >= 75 * len(sets[2 * k] | sets[2 * k + 1])]
    got = {r["doc_id"] for r in line_components(frame(rows)).collect()}
    assert len(pairs) > 100 and sum(2 * k in got for k in pairs) >= 0.97 * len(pairs)


def test_chunk_ends_resist_an_insertion(words):
    import numpy as np

    text = words(3000, 8).encode()
    moved = text[:5000] + b"inserted" + text[5000:]
    cut = lambda t: {t[a:b] for e in [chunk_ends(np.frombuffer(t, np.uint8))] for a, b in zip([0, *e], e, strict=False)}
    assert b"".join(sorted(cut(text))) and len(cut(text) & cut(moved)) >= len(cut(text)) - 6
    ends = chunk_ends(np.frombuffer(text, np.uint8))
    assert ends[-1] == len(text) and max(np.diff([0, *ends])) <= 1024


def test_repeated_passages_are_found_and_cut(frame, words):
    passage = words(90, 50)
    rows = [(1, words(80, 1) + " " + passage + " " + words(40, 2)), (2, words(33, 3) + " " + passage), (3, words(200, 4)), (4, None), (5, ""), (6, "a" * 5000), (7, words(100, 6)), (8, words(100, 6))]
    got = {}
    for r in repeated_passages(frame(rows)).collect():
        got.setdefault(r["doc_id"], []).append(r)
    assert {1, 2, 7, 8} <= got.keys() and not {3, 4, 5} & got.keys()
    for d, t in rows:
        for r in got.get(d, []):
            part = t.encode()[r["begin"] : r["stop"]].decode(errors="ignore")
            assert d in (6, 7, 8) or part in passage or passage in part or len(set(part.split()) & set(passage.split())) > 15
    clean = {r["doc_id"]: r["text"] for r in without_repeated_passages(frame(rows)).collect()}
    assert clean[1] == rows[0][1] and len(clean[2]) < len(rows[1][1]) - 200 and clean[3] == rows[2][1] and clean[4] is None and clean[7] == rows[6][1] and len(clean[8]) < 60
    assert repeated_passages(frame([])).count() == 0


def test_a_repeat_beside_a_first_occurrence_is_cut(frame, words):
    p, q, own = words(120, 60), words(120, 61), words(60, 62)
    rows = [(1, p), (2, p + " " + q), (3, p + " " + q), (4, own + " " + own.upper() + " " + own)]
    clean = {r["doc_id"]: r["text"] for r in without_repeated_passages(frame(rows)).collect()}
    assert clean[1] == p and len(clean[3]) < 60
    assert clean[2].endswith(q) and len(clean[2]) < len(q) + 120
    assert clean[4].startswith(own) and len(clean[4]) < len(rows[3][1]) - 150
    for r in repeated_passages(frame(rows)).collect():
        assert sum(x["stop"] - x["begin"] for x in r["removed"]) == r["removed_bytes"]


def test_copies_of_every_length_are_found(frame):
    """Equal texts from 64 bytes up repeat whole, the short last chunk too."""
    rng = random.Random(9)
    texts = ["".join(rng.choice("abcdefghij klmnoüé") for _ in range(n)) for n in [*range(64, 100, 3), 150, 400]]
    rows = [(2 * k + j, t) for k, t in enumerate(texts) for j in (0, 1)]
    found = {r["doc_id"]: (r["begin"], r["stop"], r["removed_bytes"]) for r in repeated_passages(frame(rows)).collect()}
    for k, t in enumerate(texts):
        n = len(t.encode())
        assert found[2 * k] == (0, n, 0) and found[2 * k + 1] == (0, n, n)


def brute_passages(texts):
    """Repeats of chunks straight from their definition: the bytes of each text that an earlier chunk stands for."""
    import numpy as np

    seen, removed = set(), []
    for t in texts:
        raw, last, gone = t.encode(), 0, 0
        for end in chunk_ends(np.frombuffer(raw, np.uint8)):
            gone += (end - last) * (raw[last:end] in seen)
            seen.add(raw[last:end])
            last = end
        removed.append(gone)
    return removed


def test_passages_equal_brute_force(frame, words):
    parts = [words(60, k) for k in range(6)]
    texts = [" ".join(random.Random(k).sample(parts, 3)) + " " + words(30, 100 + k) for k in range(25)] + ["日本語の文。" * 40, "日本語の文。" * 40]
    got = {}
    for r in repeated_passages(frame(list(enumerate(texts))), 1).collect():
        got[r["doc_id"]] = got.get(r["doc_id"], 0) + r["removed_bytes"]
    assert [got.get(k, 0) for k in range(len(texts))] == brute_passages(texts)


def test_rows_of_one_id_lose_their_own_repeats_only(frame, words):
    p, own = words(90, 1), words(80, 2)
    rows = [(1, p + "\n" + words(30, 3)), (5, p + "\n" + own), (5, own.upper() + "z\n" + words(40, 4)), (None, p + "\nend " + words(9, 6)), (7, words(70, 7)), (7, words(70, 7)), (8, None)]
    for clean in (without_repeated_passages, without_repeated_lines):
        out = clean(frame(rows).coalesce(1))
        assert out.columns == frame(rows).columns
        texts = [r["text"] for r in out.collect()]
        assert len(texts) == len(rows) and None in texts
        whole = " ".join(t for t in texts if t)
        for piece in (words(30, 3).split()[-5:], words(40, 4).split()[-5:], words(9, 6).split()[-3:], own.split()[10:15], words(70, 7).split()[20:25], p.split()[30:35]):
            assert " ".join(piece) in whole
        assert whole.count(" ".join(p.split()[30:35])) == 1 and whole.count(" ".join(words(70, 7).split()[20:25])) == 1


def test_hot_keys_of_lines_give_the_same_components(frame, words, monkeypatch):
    from hazemedian.llm import lines

    base = words(40, 5)
    rows = [(k, edited(base, (k % 12) / 40, k) + "\n" + words(12, k % 9)) for k in range(60)]
    found = []
    for most in (4096, 3):
        monkeypatch.setattr(lines, "KEY_LINES", most)
        found.append(sorted(map(tuple, line_components(frame(rows)).collect())))
    assert found[0] == found[1] and len(found[0]) > 60


def test_line_codes_are_exact_for_all_scripts():
    import numpy as np

    from hazemedian.llm.lines import line_sets

    texts = ["abcdefgh", "abcdefghé", "日本語の長い一行です", "Ā" + "b" * 9, "Ă" + "b" * 9, "b" * 9, "short", "shor", "日本", "日", "\U0001f600 smile and more"]
    raw = [x.encode() for x in texts]
    ends = np.cumsum([len(x) for x in raw])
    codes, bounds = line_sets(np.frombuffer(b"".join(raw), np.uint8), np.r_[0, ends[:-1]], ends)
    sets = [set(codes[a:b].tolist()) for a, b in zip(bounds[:-1], bounds[1:], strict=True)]
    want = [line_set(x) for x in texts]
    assert [len(x) for x in sets] == [len(x) for x in want]
    for x, a in zip(sets, want, strict=True):
        for y, b in zip(sets, want, strict=True):
            assert len(x & y) == len(a & b)
