import random

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from dictparse.kernels import lce
from dictparse.kernels.parse import LOOKAHEADS, PAIRS, SCHEMES, Parse, count_pairs, count_seeded, count_step
from dictparse.kernels.tokens import decode, written
from dictparse.sources.family_source import four_letter
from dictparse.streaming.online import OnlineParser

EXAMPLE, LOOK = "aabbaabbbaabbbbbababaabccccbababc", "aaababaaaaaabaaab"
PARSES = [(s, look) for s in SCHEMES for look in LOOKAHEADS if not (look != "none" and s == "pair") and not (look == "flex_own" and s == "seeded")]
texts = st.one_of(*(st.text(alphabet="abcdefghijklmnopqrstuvwxyz"[:k], max_size=120) for k in (1, 2, 4, 26)), st.text(alphabet="aé😀\n\0", max_size=60))


def pieces(p, text):
    return [text[f[0] : f[0] + f[1]] for f in p.phrases]


def test_worked_example_tokens():
    cut = Parse(EXAMPLE, "pair_cut")
    assert pieces(cut, EXAMPLE) == "aa bb aabb baabb bbba ba baab cc ccba bab c".split()
    assert [written(f) for f in cut.phrases] == ["'a'+'a'|2", "'b'+'b'|2", "#1+#2|4", "'b'+#3|5", "#2+#4|4", "'b'+'a'|2", "#4|4", "'c'+'c'|2", "#8+#6|4", "#6+'b'|3", "'c'+0|1"]
    run = Parse(EXAMPLE, "pair_run")
    assert [written(f) for f in run.phrases][6:] == ["#4|4", "'c'^4|4", "#6^3|5", "'c'+0|1"]


def test_worked_example_tries():
    assert Parse(EXAMPLE[:2], "pair_cut").rules.trie.rows() == [("", 0, 0), ("aa", 1, 1)]
    assert Parse(EXAMPLE, "pair_cut").rules.trie.rows() == [
        ("", 0, 0), ("aa", 1, 1), ("aabb", 3, 3), ("b", 0, 2), ("ba", 6, 6), ("baab", 7, 7), ("baabb", 4, 4), ("bab", 10, 10), ("bb", 2, 2), ("bbba", 5, 5), ("c", 11, 11), ("cc", 8, 8), ("ccba", 9, 9),
    ]
    assert len(Parse(EXAMPLE, "pair_run").rules.trie.rows()) == 12


def test_baselines_on_the_example():
    assert pieces(Parse(EXAMPLE, "pair"), EXAMPLE) == "aa bb aabb baabb bbb ab abaa bc cc cb abab c".split()
    assert len(Parse(EXAMPLE, "step").phrases) == 15
    assert len(Parse(EXAMPLE, "seeded").phrases) == 18


@pytest.mark.parametrize(("look", "expected"), [("none", "aaa ba baaaa aa baaa b"), ("flex_fixed", "aaa ba baaa aaaba aab"), ("flex_own", "aaa ba baaa aaabaaa b"), ("flex_longest", "aaa ba baaa aaab aaab")])
def test_lookahead_example(look, expected):
    p = Parse(LOOK, "pair_run", look)
    assert pieces(p, LOOK) == expected.split()
    if look == "flex_longest":
        assert [LOOK[f[0] : f[0] + f[1]] for f in p.entries] == ["aaa", "ba", "baaaa", "aaaba", "aaab"]


@pytest.mark.parametrize(("k", "n", "counts"), [(4, 124, (24, 24, 24)), (8, 566, (56, 56, 51)), (16, 3178, (144, 144, 99)), (32, 20690, (416, 416, 195)), (64, 147874, (1344, 1344, 387))])
def test_family(k, n, counts):
    text = four_letter(k)
    assert len(text) == n
    assert tuple(len(Parse(text, s).phrases) for s in PAIRS) == counts


def test_unary():
    for k in range(1, 11):
        text = "a" * (2 ** (k + 1) - 2)
        assert [len(f) for f in pieces(Parse(text, "pair"), text)] == [2**i for i in range(1, k + 1)]
        assert len(Parse(text, "pair_run").phrases) == 1
    assert [written(f) for f in Parse("a", "pair_run").phrases] == ["'a'+0|1"]
    assert Parse("", "pair_cut").phrases == []


@settings(max_examples=150, deadline=None)
@given(texts)
def test_parses_decode_and_keep_their_laws(text):
    for scheme, look in PARSES:
        p = Parse(text, scheme, look)
        assert decode(p.phrases, p.entries, scheme) == text
        at = 0
        for x, f in enumerate(p.phrases, 1):
            assert f[0] == at and f[1] > 0
            at += f[1]
            if look == "none":
                assert (f[3] or 0) < x and (f[5] or 0) < x
            elif p.entries is not None and scheme != "seeded":
                for ref in (f[3], f[5]):
                    assert not ref or p.entries[ref - 1][0] + p.entries[ref - 1][1] <= f[0]
        assert p.rules.trie.nodes <= 2 * len(p.entries if p.entries is not None else p.phrases) + 1
    for scheme in ("pair_cut", "pair_run", "seeded"):
        assert len(Parse(text, scheme, "flex_fixed").phrases) <= len(Parse(text, scheme).phrases)
    assert all(f[1] >= 2 for s in PAIRS for f in Parse(text, s).phrases[:-1])
    steps = pieces(Parse(text, "step"), text)
    assert len(set(steps[:-1])) == len(steps[:-1])
    for scheme in PAIRS:
        p = Parse(text, scheme)
        kinds = [f[2] for f in p.phrases]
        assert count_pairs(text, scheme) == (*(kinds.count(k) for k in ("combine", "cut", "repeat")), p.rules.trie.nodes, p.rules.trie.split_nodes)
    assert count_step(text) == len(steps) and count_seeded(text) == len(Parse(text, "seeded").phrases)


@settings(max_examples=60, deadline=None)
@given(texts)
def test_options_change_nothing(text):
    for scheme in SCHEMES:
        expected = Parse(text, scheme).phrases
        for options in ({"children": "sorted"}, {"fused": False}, {"lce_kind": "rank"}, {"lce_kind": "rolling"}, *([{"children": "ternary"}] if scheme in ("step", "seeded") else [])):
            assert Parse(text, scheme, **options).phrases == expected


@settings(max_examples=80, deadline=None)
@given(texts, st.lists(st.integers(1, 20), max_size=30))
def test_online_parses_equal_batch_parses(text, cuts):
    for scheme in PAIRS:
        parser, out, at = OnlineParser(scheme), [], 0
        for c in cuts:
            out += parser.feed(text[at : at + c])
            at += c
        out += parser.feed(text[at:])
        assert out + parser.close() == Parse(text, scheme).phrases


def test_prefixes_parse_alike():
    rng = random.Random(3)
    text = "".join(rng.choice("ab") for _ in range(300))
    for scheme in ("pair_cut", "pair_run"):
        whole = Parse(text, scheme).phrases
        for n in range(1, 300, 17):
            part = Parse(text[:n], scheme).phrases
            inside = [f for f in whole if f[0] + f[1] < n]
            assert part[: len(inside)] == inside


@settings(max_examples=60, deadline=None)
@given(texts)
def test_extensions(text):
    backends = [lce.make(text, k) for k in lce.BACKENDS]
    n = len(text)
    for i in range(0, n, 7):
        for j in range(0, n, 5):
            naive = next((k for k in range(n - max(i, j)) if text[i + k] != text[j + k]), n - max(i, j))
            assert {b(i, j) for b in backends} == {naive}


def test_extension_example():
    assert lce.suffix_match("babababb", 2, 4) == 4
    assert lce.bounded_match("babababb", 2, 4, 3) == 3
    assert lce.suffix_match("babababb", 3, 3) == 6
    assert lce.suffix_match("babababb", 9, 1) == 0
    long = "ab" * 5000 + "c"
    assert lce.RollingHash(long, 64)(0, 2) == lce.Direct(long)(0, 2) == 9998


def plain(text, scheme):
    """Lengths of the greedy factors, by comparing every earlier string."""
    out, at, entries, n = [], 0, [], len(text)

    def common(e, p):
        k = 0
        while k < len(e) and p + k < n and e[k] == text[p + k]:
            k += 1
        return k

    def power(e, p):
        k = 0
        while p + k < n and text[p + k] == e[k % len(e)]:
            k += 1
        return k

    while at < n:
        whole = max((len(e) for e in entries if text.startswith(e, at)), default=0)
        cut = max((common(e, at) for e in entries), default=0)
        if scheme in PAIRS:
            first = whole or 1
            p = at + first
            second = max((len(e) if text.startswith(e, p) else 0 for e in entries) if scheme == "pair" else (common(e, p) for e in entries), default=0)
            length = first + (max(1, second) if p < n else 0)
        elif scheme == "seeded":
            length = max(1, whole)
        else:
            length = whole + (at + whole < n)
        if scheme in ("pair_cut", "pair_run", "step_run"):
            length = max(length, cut)
        if scheme in ("pair_run", "step_run"):
            length = max(length, *(power(e, at) for e in {*entries, text[at]} if text.startswith(e, at)))
        out.append(length)
        if scheme == "seeded":
            if at + length < n:
                entries.append(text[at : at + length + 1])
        else:
            entries.append(text[at : at + length])
        at += length
    return out


def test_whole_documents_against_plain_search():
    import pyarrow.parquet as pq

    for table, column, few in (("documents", "text", 12), ("pages", "html", 4), ("conversations", "text", 30)):
        listed = [t for t in pq.read_table(f"/root/testdata/sf0.001/{table}.parquet").column(column).to_pylist() if t]
        for text in sorted(listed, key=len)[len(listed) // 2 :][:few]:
            for scheme in SCHEMES:
                assert [f[1] for f in Parse(text, scheme).phrases] == plain(text, scheme)


def test_plain_search_knows_power_of_one_symbol():
    assert plain("aaaaab", "pair_run") == [5, 1] and plain("abababab", "pair_run")[0] == 2


def _look(text, scheme):
    """Lengths chosen by the look-ahead over greedy entries, from its definition."""
    rules, at, ends = Parse(text, scheme).rules, 0, []
    reach = [rules.best(p, p)[1] for p in range(len(text))] + [0]
    while at < len(text):
        best = max(range(1, reach[at] + 1), key=lambda k: (k + reach[at + k], k))
        ends.append(best)
        at += best
    return ends


@settings(max_examples=80, deadline=None)
@given(texts.filter(len))
def test_lookahead_over_greedy_entries_from_its_definition(text):
    for scheme in ("pair_cut", "pair_run", "seeded", "step", "step_run"):
        assert [f[1] for f in Parse(text, scheme, "flex_fixed").phrases] == _look(text, scheme)
