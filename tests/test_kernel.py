import random

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from winsub.kernel.automaton import ManyPatterns, OnePattern
from winsub.kernel.link_tree import LinkTree, OrderList
from winsub.kernel.scan import kmp_find, native_find, skip_find
from winsub.kernel.static_index import BackwardSearch, SuffixArray
from winsub.kernel.window_index import ANCESTORS, RULES, Steps, WindowIndex


def places(text, pattern, start=0):
    return [start + i for i in range(len(text) - len(pattern) + 1) if text[i : i + len(pattern)] == pattern]


def tail(text):
    return next((k for k in range(len(text) - 1, 0, -1) if text.find(text[-k:]) < len(text) - k), 0)


def invariants(index):
    """What holds after every push."""
    x, text = index, "".join(index.window())
    assert x.tail_len == tail(text) and (x.tail_len < x.size or not x.size)
    assert sorted(x.leaf_at) == list(range(x.start, x.tail_start))
    inner = set(x.links.parent)
    assert len(inner) + len(x.leaf_at) <= 2 * max(1, x.size)
    for v in inner:
        rep = x.rep[v] if v else x.start
        assert x.start <= rep <= x.n_seen - x.depth[v]
        if v:
            assert len(x.kids[v]) >= 2
            to = x.jump[v]
            assert to in inner and x.depth[to] == x.depth[v] - 1 == x.links.depth[v] - 1
            own, linked = x.symbols(rep, rep + x.depth[v]), x.symbols(x.rep[to] if to else 0, (x.rep[to] if to else 0) + x.depth[to])
            assert own[1:] == linked


FIXTURES = [  # text, tail start, cursor, pattern, leaf matches, tail matches, tail after dropping one symbol
    ("aaaa", 1, "leaf", "aa", [0], [1, 2], "aa"),
    ("cac", 2, "leaf", "c", [0], [2], ""),
    ("abcab", 3, "leaf", "ab", [0], [3], "b"),
    ("abcabcabcab", 3, "leaf", "ab", [0], [3, 6, 9], "bcabcab"),
    ("abcabcabcab", 3, "leaf", "bcab", [1], [4, 7], "bcabcab"),
    ("abaabab", 5, "internal", "a", [0, 2, 3], [5], "ab"),
    ("aaba", 3, "internal", "a", [0, 1], [3], "a"),
    ("aacaba", 5, "internal", "a", [0, 1, 3], [5], "a"),
    ("babbbba", 5, "leaf", "b", [0, 2, 3, 4], [5], "a"),
    ("abcabdab", 6, "internal", "ab", [0, 3], [6], "ab"),
    ("mississippi", 10, "internal", "i", [1, 4, 7], [10], "i"),
    ("mississippi", 10, "internal", "issi", [1, 4], [], "i"),
    ("aabaabaabxaab", 10, "internal", "ab", [1, 4, 7], [11], "aab"),
]


@pytest.mark.parametrize("row", FIXTURES)
def test_worked_fixtures(row):
    text, begin, kind, pattern, leaf, in_tail, after = row
    for rule in RULES:
        for ancestor in ANCESTORS:
            x = WindowIndex(len(text)).extend(text)
            assert (x.tail_start, x.cursor_kind()) == (begin, kind)
            a, b = x.parts(pattern, rule, ancestor)
            assert (sorted(a), sorted(b)) == (leaf, in_tail)
    x._evict_oldest()
    assert "".join(x.symbols(x.tail_start, x.n_seen)) == after
    assert x.locate(pattern) == places(text[1:], pattern, 1)
    invariants(x)


@settings(max_examples=120, deadline=None)
@given(st.integers(1, 12), st.integers(1, 4), st.lists(st.integers(0, 3), max_size=40), st.sampled_from(["hash", "sorted", "dense"]), st.sampled_from(["credit", "walk"]))
def test_every_push(capacity, sigma, codes, children, refresh):
    text = "".join("abcd"[c % sigma] for c in codes)
    x = WindowIndex(capacity, children=children, refresh=refresh)
    for n, sym in enumerate(text, 1):
        x.push(sym)
        start = max(0, n - capacity)
        window = text[start:n]
        assert "".join(x.window()) == window
        invariants(x)
        for pattern in {window[:2], window[-1:], window[-2:], window[-4:], "ab", "z"} - {""}:
            want = places(window, pattern, start)
            for rule in RULES:
                assert x.locate(pattern, rule) == want
            for ancestor in ANCESTORS:
                assert x.locate(pattern, ancestor=ancestor) == want


def _words():
    fib = ["a", "ab"]
    while len(fib[-1]) < 60:
        fib.append(fib[-1] + fib[-2])
    thue = "".join("ab"[bin(i).count("1") % 2] for i in range(64))
    return [fib[-1], thue, "a" * 60, "abc" * 20, "abcabcabd" * 7]


@pytest.mark.parametrize("text", _words())
def test_structured_words(text):
    for capacity in (1, 2, 7, 16):
        x = WindowIndex(capacity)
        for n, sym in enumerate(text, 1):
            x.push(sym)
            invariants(x)
            window = text[max(0, n - capacity) : n]
            for k in range(1, min(6, len(window)) + 1):
                assert x.locate(window[-k:]) == places(window, window[-k:], max(0, n - capacity))


def test_expected_symbol_is_what_follows_the_twin():
    r = random.Random(1)
    for _ in range(300):
        text = "".join(r.choice("ab") for _ in range(r.randint(2, 20)))
        x = WindowIndex(20).extend(text)
        if x.cursor_kind() == "leaf":
            twin, _ = x.tail_period()
            assert x.expected_symbol() == text[twin + x.tail_len]


def test_fresh_symbol_empties_the_tail():
    assert WindowIndex(50).extend("ab" * 20).extend("#").tail_len == 0


def test_finalised_has_all_leaves():
    x = WindowIndex(9).extend("abaababaab")
    done = x.finalised()
    assert done.tail_len == 0 and len(done.leaf_at) == 10 and x.tail_len > 0
    assert done.locate("ab") == x.locate("ab")


def test_snapshot_goes_on_alike():
    r = random.Random(2)
    text = "".join(r.choice("abc") for _ in range(200))
    a = WindowIndex(17, children="sorted").extend(text[:90])
    b = WindowIndex.restore(a.snapshot())
    a.extend(text[90:])
    b.extend(text[90:])
    assert a.window() == b.window() and a.tail_len == b.tail_len and a.locate("ab") == b.locate("ab")
    invariants(b)


def test_resize_expire_and_derived_answers():
    x = WindowIndex(12).extend("abcabcabcabc")
    assert (x.count("ab"), x.exists("zz"), x.first("b"), x.last("b"), x.longest_repeat()) == (4, False, 1, 10, 9)
    x.resize(5)
    assert "".join(x.window()) == "bcabc" and x.locate("bc") == [7, 10]
    x.expire(10)
    assert "".join(x.window()) == "bc"
    x.expire(99)
    assert x.size == 0 and x.extend("aa").locate("a") == [12, 13]


def test_integer_symbols_and_long_unary_word():
    assert WindowIndex(9).extend([5, 7, 5, 7, 5]).locate([5, 7]) == [0, 2]
    x = WindowIndex(10_000).extend("a" * 10_000)
    assert x.tail_len == 9_999 and len(x.locate("aaa")) == 9_998


@pytest.mark.parametrize("bad", [lambda: WindowIndex(0), lambda: WindowIndex(3).locate(""), lambda: WindowIndex(3, ancestor="x"), lambda: WindowIndex(3, children="x"), lambda: OnePattern(""), lambda: ManyPatterns([""])])
def test_refused(bad):
    with pytest.raises(ValueError):
        bad()


def test_query_steps_do_not_grow_with_the_window():
    r = random.Random(5)
    text = "".join(r.choice("abcde") for _ in range(1 << 14))
    ratios = []
    for k in range(6, 15, 2):
        x = WindowIndex(1 << k).extend(text[-(1 << k) :])
        worst = 0
        for m in (1, 3, 6, 12):
            work = Steps()
            occ = len(x.locate(text[-m:], work=work, ordered=False))
            worst = max(worst, work.total() / (m + occ + 1))
        ratios.append(worst)
    assert max(ratios) <= 6


def fibonacci_word(n):
    a, b = "a", "ab"
    while len(b) < n:
        a, b = b, b + a
    return b[:n]


@pytest.mark.parametrize("text", ["abcde" * 2000, "a" * 8000, "".join(random.Random(6).choice("ab") for _ in range(8000)), ("a" * 500 + "b" + "a" * 500 + "c") * 12, fibonacci_word(12_000)])
def test_push_steps_are_amortised_constant(text):
    """All upkeep counts, that of the order list too."""
    for capacity in (64, 512, 4096):
        assert WindowIndex(capacity).extend(text).steps.total() <= 20 * len(text)


def test_order_list_moves_are_amortised_constant():
    for n in (500, 5_000, 50_000):
        front, middle, r, spread = OrderList(), OrderList(), random.Random(n), OrderList()
        marks = [0]
        for k in range(n):
            front.after(0)
            middle.after(min(k, 7))
            marks.append(spread.after(r.choice(marks[-50:])))
        assert max(front.moves, middle.moves, spread.moves) <= 4 * n
        assert front.words() <= 5 * (n + 1)
    order = []
    x = middle.next[0]
    while x:
        order.append(middle.key(x))
        x = middle.next[x]
    assert order == sorted(order) and len(set(order)) == len(order) == 50_000
    gone = [x for x in range(1, 50_001) if x % 3]
    for x in gone:
        middle.remove(x)
    assert sum(middle.size.values()) == 50_001 - len(gone)


def test_fingerprints_follow_the_window():
    r = random.Random(8)
    for capacity in (5, 40):
        x, text = WindowIndex(capacity, ancestor="fingerprint"), ""
        for _ in range(400):
            text += r.choice("ab")
            x.push(text[-1])
            w = text[-capacity:]
            for p in ("a", "ab", "ba", "aab", w[-3:]):
                want = [len(text) - len(w) + i for i in range(len(w)) if w.startswith(p, i)]
                assert x.locate(p) == want == sorted(x.locate(p, ancestor="jump", ordered=False))
    assert WindowIndex.restore(x.snapshot()).locate("ab") == x.locate("ab")


def test_link_tree_tests_agree_under_updates():
    r, tree, depth = random.Random(3), LinkTree(), {0: 0}
    for node in range(1, 400):
        parent = r.choice(list(depth))
        tree.attach(node, parent, depth[parent] + 1)
        depth[node] = depth[parent] + 1
        if r.random() < 0.3:
            leaf = r.choice([v for v in depth if v and not tree.fan_in[v]])
            tree.detach(leaf)
            del depth[leaf]
        tags = [tree.order.key(tree.open[v]) for v in depth]
        assert len(set(tags)) == len(tags)
        for _ in range(4):
            a, b = r.choice(list(depth)), r.choice(list(depth))
            want = a in tree.chain(b)
            assert all(tree.is_ancestor(a, b, kind) == want for kind in ("order_list", "interval", "lca", "jump", "chain"))
            assert tree.common(a, b) == tree.lca(a, b)


def test_crowded_order_list():
    tree = LinkTree()
    for node in range(1, 3000):  # always at the same place
        tree.attach(node, 0, 1)
    assert all(tree.is_ancestor(0, v) and not tree.is_ancestor(v, 0) for v in range(1, 3000, 97))


@settings(max_examples=200, deadline=None)
@given(st.text("ab", max_size=30), st.text("ab", min_size=1, max_size=6))
def test_scans_and_static_indexes(text, pattern):
    want = places(text, pattern)
    for find in (kmp_find, skip_find, native_find):
        assert find(text, pattern)[0] == want
    assert SuffixArray(text).find(pattern)[0] == want
    assert BackwardSearch(text).find(pattern)[0] == want
    assert [off for p, off in ManyPatterns([pattern, "ba"]).run(text)[0] if p == pattern] == want
    one = OnePattern(pattern)
    assert [x for x in map(one.feed, text) if x is not None] == want


@pytest.mark.parametrize("children", ["hash", "sorted", "dense"])
def test_finalised_copies_flat_structures(children, monkeypatch):
    """An object-by-object copy takes longer than building the window did."""
    import copy

    monkeypatch.setattr(copy, "deepcopy", lambda *a: pytest.fail("copied object by object"))
    x, same = (WindowIndex(40, children=children).extend("abaababaabcabdabab" * 3) for _ in range(2))
    done = x.finalised().extend("zzabz" * 9)
    assert done.links is not x.links and x.snapshot() == same.snapshot() and x.compares.n == same.compares.n
    assert x.extend("cabzq" * 5).snapshot() == same.extend("cabzq" * 5).snapshot() and x.locate("ab") == same.locate("ab")
    invariants(done)
    invariants(x)
