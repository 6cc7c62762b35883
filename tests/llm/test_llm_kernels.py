"""Kernels of the corpus operators against brute force; no Spark."""

import hashlib
import io
import itertools
import random
import re
import zlib
from collections import Counter

import numpy as np
import pytest

import planted_pages
from congraph.llm import best_fit, bitpack, exact_dedup, html_extract, merkle, ngram_join, shingles, toxicity
from congraph.llm.patricia import PatriciaTrie, common_prefix
from congraph.llm.sentencepiece_viterbi import BPE, UNIGRAM, PieceModel, SharedPrefixViterbi, encoder

R = random.Random(5)


def test_common_prefix():
    for _ in range(300):
        a = bytes(R.choice(b"ab") for _ in range(R.randrange(90)))
        b = a[: R.randrange(len(a) + 1)] + bytes(R.choice(b"ab") for _ in range(R.randrange(5)))
        k = 0
        while k < min(len(a), len(b)) and a[k] == b[k]:
            k += 1
        assert common_prefix(a, b) == k


@pytest.mark.parametrize("budget", [1 << 40, 4000])
def test_trie_owners_with_and_without_spill(budget):
    words = [bytes(R.choice(b"abc") for _ in range(R.randrange(0, 12))) for _ in range(1500)]
    trie, expected = PatriciaTrie(budget), {}
    for k, w in enumerate(words):
        owner = R.randrange(10_000)
        trie.insert(w, owner, 2, hashlib.md5(w).digest())
        old = expected.get(w, (1 << 60, 0))
        expected[w] = (min(old[0], owner), old[1] + 2)
    got = list(trie.items())
    assert len(got) == len(expected) and {k: (o, n) for k, o, n, _ in got} == expected
    assert all(load == hashlib.md5(k).digest() for k, _, _, load in got)


@pytest.mark.parametrize("text", [b"", b" ", b"a", b"\ta \n b\r\n", b"a  b", b"\x0b\x0cx"])
def test_normalised(text):
    assert exact_dedup.normalised(text) == re.sub(rb"[\x20\x09-\x0D]+", b" ", text)


@pytest.mark.parametrize("bits", [1, 2, 7, 13, 16, 17, 31, 32])
@pytest.mark.parametrize("n", [0, 1, 63, 64, 65, 1000])
def test_bit_packing_round_trip(bits, n):
    ids = np.array([R.randrange(1 << bits) for _ in range(n)], "<u4")
    data = bitpack.pack(ids, bits)
    assert len(data) == -(-n // 64) * bits * 8 and (bitpack.unpack(data, n, bits) == ids).all()


def test_packed_file_random_access():
    rows = [(7 * k, np.array([R.randrange(50257) for _ in range(R.choice([0, 1, 50, 9000]))], "<u4")) for k in range(40)]
    reader = bitpack.in_memory(rows, bitpack.id_bits(50257))
    every = np.concatenate([x for _, x in rows])
    for _ in range(100):
        a = R.randrange(len(every))
        b = min(len(every), a + R.randrange(6000))
        assert (reader.ids(a, b) == every[a:b]).all()
    got = list(reader.documents(10_000))
    assert [d for d, _, _ in got] == [d for d, _ in rows] and all((x == y).all() for (_, _, x), (_, y) in zip(got, rows))
    empty = bitpack.in_memory([], 16)
    assert list(empty.documents()) == [] and empty.n_ids == 0
    with pytest.raises(ValueError):
        bitpack.PackReader(io.BytesIO(b"x" * 200))


def test_fullest_is_the_best_subset():
    for _ in range(200):
        counts = {R.randrange(1, 12): R.randrange(1, 3) for _ in range(4)}
        room = R.randrange(0, 30)
        items = [x for x, n in counts.items() for _ in range(n)]
        best = max(sum(c) for k in range(len(items) + 1) for c in itertools.combinations(items, k) if sum(c) <= room)
        got = best_fit.fullest(counts, room)
        assert sum(x * n for x, n in got.items()) == best and all(n <= counts[x] for x, n in got.items())


def test_bin_plan_uses_every_piece_once():
    counts = {R.randrange(1, 2049): R.randrange(1, 40) for _ in range(300)}
    plan, used = best_fit.bin_plan(counts), {}
    for chosen, times in plan:
        assert sum(x * n for x, n in chosen.items()) <= 2048
        for x, n in chosen.items():
            used[x] = used.get(x, 0) + n * times
    assert used == counts
    total = sum(x * n for x, n in counts.items())
    assert sum(t for _, t in plan) <= -(-total // 2048) * 1.02 + 1
    assert best_fit.bin_plan({}) == []


def brute_shingles(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text))
    return {tuple(words[k : k + 5]) for k in range(len(words) - 4)} if len(words) >= 5 else {tuple(words)} if words else set()


def test_shingles_stand_for_word_runs():
    texts = [" ".join(R.choice(["a", "B", "cé", "d\td", "É"]) for _ in range(R.randrange(12))) for _ in range(150)] + ["", " \n", "A b\tC  d E f"]
    for x, y in itertools.product(texts[:60] + texts[-3:], repeat=2):
        a, b = shingles.shingle_set(x.encode()), shingles.shingle_set(y.encode())
        assert len(a) == len(brute_shingles(x)) and len(np.intersect1d(a, b)) == len(brute_shingles(x) & brute_shingles(y))


def test_filters_lose_no_link():
    for _ in range(400):
        base = set(R.sample(range(200), R.randrange(5, 40)))
        x, y = ({*base, *R.sample(range(200), R.randrange(6))} for _ in range(2))
        common = len(x & y)
        if 100 * common < 80 * len(x | y):
            continue
        order = R.sample(range(200), 200)
        a, b = sorted(x, key=order.index), sorted(y, key=order.index)
        assert common >= ngram_join.least_overlap(len(a), len(b), 80)
        pa, pb = a[: ngram_join.prefix_length(len(a), 80)], b[: ngram_join.prefix_length(len(b), 80)]
        shared = set(pa) & set(pb)
        assert shared
        for s in shared:
            v = lambda k: np.array([k])
            assert ngram_join.passes(v(len(a)), v(a.index(s)), v(len(b)), v(b.index(s)), 80).all()
        p, q = (np.frombuffer(ngram_join.part_counts(np.array(sorted(z), "u8")), "u1").astype("i4") for z in (x, y))
        assert np.abs(p - q).sum() <= len(a) + len(b) - 2 * ngram_join.least_overlap(len(a), len(b), 80)


def prose(n, seed=3):
    r = random.Random(seed)
    words = ["".join(r.choice("abcdefghiklmnoprstu") for _ in range(r.randrange(2, 9))) for _ in range(400)]
    return "\n".join(" ".join(r.choice(words) for _ in range(r.randrange(5, 60))) + "." for _ in range(n))


def test_merkle_equality_edits_and_likeness():
    text = prose(40)
    tree = merkle.merkle_tree(text)
    assert b"".join(merkle.segments(text.encode())) == text.encode()
    mark = merkle.fingerprint(tree)
    assert merkle.likeness(mark, mark) == 1.0 and merkle.edits(tree, tree) == []
    at = text.index(" ", len(text) // 2)
    other = merkle.merkle_tree(text[:at] + " inserted" + text[at:])
    assert 0.95 < merkle.likeness(mark, merkle.fingerprint(other)) < 1
    assert len(merkle.edits(other, tree)) == 1
    # A word in front of a sentence of twelve shifts none of its later segments.
    short = "The river runs below the old bridge where market people carry stones"
    assert merkle.likeness(merkle.fingerprint(merkle.merkle_tree(short)), merkle.fingerprint(merkle.merkle_tree("Now " + short))) > 0.5
    assert merkle.likeness(mark, merkle.fingerprint(merkle.merkle_tree(""))) == 0.0
    assert merkle.merkle_tree("") == [] and merkle.likeness(merkle.fingerprint([]), merkle.fingerprint([])) == 1.0
    back = merkle.Mark.parse(mark)
    assert back.text() == mark and len(back.leaves) == sum(len(p) for s in tree for p in s)
    assert [b - a for _, a, b in back.paragraphs] == [len(p) for s in tree for p in s]


def test_likeness_is_the_common_leaves():
    """Against the definition: of every shared section all leaves, of the rest shared paragraphs, then shared leaves."""
    for seed in range(60):
        r = random.Random(seed)
        lines = prose(12, seed % 5).split("\n")
        x, y = ("\n".join(r.choice(lines[:8]) for _ in range(r.randrange(1, 9))) for _ in range(2))
        a, b = merkle.merkle_tree(x), merkle.merkle_tree(y)
        key = lambda z: repr(z)
        common, left = 0, []
        sections = Counter(map(key, a)) & Counter(map(key, b))
        for tree in (a, b):
            held, rest = Counter(sections), []
            for s in tree:
                if held[key(s)]:
                    held[key(s)] -= 1
                    common += sum(map(len, s))
                else:
                    rest += s
            left.append(rest)
        shared = Counter(map(key, left[0])) & Counter(map(key, left[1]))
        leaves = []
        for rest in left:
            held, out = Counter(shared), Counter()
            for p in rest:
                if held[key(p)]:
                    held[key(p)] -= 1
                    common += len(p)
                else:
                    out.update(p)
            leaves.append(out)
        common += 2 * sum((leaves[0] & leaves[1]).values())
        total = sum(len(p) for t in (a, b) for s in t for p in s)
        assert merkle.likeness(merkle.fingerprint(a), merkle.fingerprint(b)) == pytest.approx(common / total if total else 1.0)


def brute_cut(odds, edges):
    best = None
    for labels in itertools.product([False, True], repeat=len(odds)):
        cost = sum(x if x > 0 and not on else -x if x < 0 and on else 0 for x, on in zip(odds, labels))
        cost += sum(w for a, b, w in edges if labels[a] != labels[b])
        best = cost if best is None else min(best, cost)
    return best


def test_minimum_cut():
    for _ in range(60):
        n = R.randrange(1, 8)
        odds = [R.choice([-3, -1, 0.5, 2]) for _ in range(n)]
        edges = [(a, b, R.random()) for a in range(n) for b in range(a + 1, n) if R.random() < 0.5]
        labels = html_extract.minimum_cut(odds, edges)
        cost = sum(x if x > 0 and not on else -x if x < 0 and on else 0 for x, on in zip(odds, labels))
        cost += sum(w for a, b, w in edges if labels[a] != labels[b])
        assert cost == pytest.approx(brute_cut(odds, edges))


def test_main_text():
    page = (
        "<html><head><title>T</title><style>p{}</style></head><body><header><h1>Site</h1></header><nav><a href=x>Home</a></nav>"
        '<script>var t="</p>";</script><div class="cookie-notice"><p>We use cookies, please accept all of them.</p></div>'
        '<article><h1>Title &amp; more</h1><p>First   part<br>goes <b>on.<p>A < b, &copy; x &am</p><div class="comments"><p>I, a reader, say that this is good.</p></div></article>'
        "<aside><p>Related stuff that is long enough to look like content.</p></aside><form><p>Sign up</p></form><footer>&copy; me</footer>"
    )
    assert html_extract.main_text(page) == "Title & more\n\nFirst part goes on.\n\nA < b, © x &am"
    assert html_extract.main_text("") == "" and html_extract.main_text("<nav><a>x</a></nav>") == ""


def test_names_of_paragraphs_and_captions():
    long = "A sentence of the article that goes on for long enough to be read as content."
    out = ['<p class="advert">Buy this now, it is cheap.</p>', '<p hidden>Not for eyes at all.</p>', '<h3 class="related">Other things to read</h3>', '<pre id="cookie-notice">We use cookies here</pre>']
    kept = ["<figcaption>A bird on a roof.</figcaption>", "<address>12 Hill Road, Town</address>", '<p class="text">A named part.</p>']
    page = f"<article><p>{long}</p>" + f"<p>{long}</p>".join(out) + f"<p>{long}</p><figure><img src=x>" + "</figure><figure>".join(kept) + f"</figure><p>{long}</p></article><address>Site owner, nowhere</address><footer>x</footer>"
    assert html_extract.main_text(page) == "\n\n".join([long] * 5 + ["A bird on a roof.", "12 Hill Road, Town", "A named part.", long])


def test_planted_pages_with_and_without_the_cut():
    """Block by block: the cut finds more of the main text than the classifier's sign, and takes in no more of the rest."""
    found = {"cut": [0, 0, 0], "sign": [0, 0, 0]}
    whole = changed = 0
    for seed in range(300):
        markup, texts = planted_pages.page(seed)
        want, rows = Counter(texts), html_extract.labelled(markup)
        changed += sum((odds > 0) != keep for _, odds, keep in rows)
        for name, got in (("cut", Counter(b.text for b, _, keep in rows if keep)), ("sign", Counter(b.text for b, odds, _ in rows if odds > 0))):
            for k, part in enumerate((want & got, got - want, want - got)):
                found[name][k] += sum(part.values())
        whole += html_extract.main_text(markup) == "\n\n".join(texts)
    (right, extra, lost), (plain, plain_extra, plain_lost) = found["cut"], found["sign"]
    assert changed > 20 and lost < plain_lost and extra <= plain_extra + 2
    assert right / (right + lost) > 0.99 and right / (right + extra) > 0.99 and whole > 280


def test_parts_of_an_article_stay():
    long = "A sentence of the article that goes on for long enough to be read as content, with a second half."
    named = "".join(f'<div class="{c}"><p>{long} {c}.</p></div>' for c in ("tags", "post-meta", "search-note", "form", "skip", "legal", "copyright"))
    page = f'<div class="post-header"><h1>Headline of it</h1></div><article><p>{long}</p>{named}<ul><li><a href="/x">A linked item</a></li><li>Another</li></ul><figure><figcaption>A caption</figcaption></figure></article>'
    got = html_extract.main_text(page).split("\n\n")
    assert got == ["Headline of it", long, *[f"{long} {c}." for c in ("tags", "post-meta", "search-note", "form", "skip", "legal", "copyright")], "A linked item", "Another", "A caption"]


def test_decoding_of_disguises():
    corpus = " ".join(["the idiot was a clown and a moron in this place", "that is pathetic of him to say so there"] * 30)
    counts = np.bincount(toxicity.trigram_counts(corpus), minlength=toxicity.LETTERS**3).reshape((toxicity.LETTERS,) * 3) + 0.01
    model = np.log(counts / counts.sum(2, keepdims=True)).astype("f4")
    for disguise, word in (("1d10t", "idiot"), ("m0r0n", "moron"), ("i.d.i.o.t", "idiot"), ("c1own", "clown"), ("idiooooot", "idiot"), ("p@thet1c", "pathetic"), ("m o r o n", "moron")):
        assert toxicity.decode(disguise, model) == word
    words = toxicity.Restorer(model).words("You 1D10T, m-o-r-o-n and c l o w n! 123 plain.")
    assert {"idiot", "moron", "clown", "plain"} <= words


def test_every_kind_of_disguise_is_read():
    corpus = " ".join(["you are an idiot and a moron", "what an ass he is", "you whore", "that is shit", "a cunt said so"] * 30)
    counts = np.bincount(toxicity.trigram_counts(corpus), minlength=toxicity.LETTERS**3).reshape((toxicity.LETTERS,) * 3) + 0.01
    restorer = toxicity.Restorer(np.log(counts / counts.sum(2, keepdims=True)).astype("f4"))
    kinds = {
        "the only stand-in last": [("whor3", "whore"), ("shi7", "shit"), ("as$", "ass"), ("as$.", "ass")],
        "stand-ins only": [("@$$", "ass"), ("5#17", "shit")],
        "a leading (": [("(unt", "cunt"), ('"(unt"', "cunt")],
        "apart": [("an i d 1 0 t here", "idiot"), ("s h 1 t", "shit"), ("m  o  r  o  n", "moron"), ("m. o. r. o. n.", "moron")],
        "words apart": [("y o u i d i o t", "idiot"), ("y o u  m 0 r o n", "moron")],
    }
    for kind, pairs in kinds.items():
        for text, word in pairs:
            assert word in restorer.words(text), (kind, text, restorer.readings(text))
    assert {"you", "idiot"} <= restorer.words("y o u i d i o t")
    assert restorer.reading("m o r o n  " * 4000).count("moron") == 4000


def test_logistic_fit_separates():
    found = [[0] if k % 4 == 0 else [1] for k in range(400)]
    labels = np.array([float(k % 4 == 0) for k in range(400)])
    w = toxicity.fit(found, labels, 2)
    z = np.array([w[f[0]] + w[-1] for f in found])
    assert ((z > 0) == (labels == 1)).all()


def test_pieces_equal_the_library():
    spm = pytest.importorskip("sentencepiece")
    tokenizers = pytest.importorskip("public_tokenizers")
    library = spm.SentencePieceProcessor(model_file=tokenizers.path("piece_bpe_32k.model"))
    texts = ["", " ", "a  b", "Hello, world 12345", "x\n\ny", "naïve 日本語 😀", "aaaaaaaaaaaaaaaaaaaaaaa", " lead", "trail "]
    texts += ["".join(R.choice("abcdeé .,\n1") for _ in range(R.randrange(80))) for _ in range(200)]
    sp = encoder()
    for text, ids in zip(texts, sp.encode(texts)):
        assert ids.tolist() == library.encode(text), text
        assert sp.decode(ids) == text


def test_unigram_pass_is_the_best_path():
    model = PieceModel.__new__(PieceModel)
    model.kind, model.bytes, model.unknown, model.dtype = UNIGRAM, {}, 0, "<u2"
    model.scores = {"a": -2.1, "b": -2.3, "ab": -3.2, "ba": -3.9, "aba": -5.05, "bb": -4.0}
    model.ids, model.least, model.endings = {p: k for k, p in enumerate(model.scores)}, -5.05, {}
    for p in model.scores:
        node = model.endings
        for c in reversed(p):
            node = node.setdefault(c, {})
        node[""] = p
    assert BPE != UNIGRAM

    def best(word):
        if not word:
            return 0.0
        return max(best(word[len(p) :]) + s for p, s in model.scores.items() if word.startswith(p))

    words = ["".join(x) for n in range(1, 8) for x in itertools.product("ab", repeat=n)]
    steps = 0
    for word, pieces, new in SharedPrefixViterbi(model).encode_words(words):
        assert "".join(pieces) == word and sum(model.scores[p] for p in pieces) == pytest.approx(best(word))
        steps += new
    assert steps < sum(map(len, words)) / 2  # prefixes are scored once


@pytest.mark.parametrize("name, words", [("byte_bpe_50k.json", False), ("word_bpe_49k.json", True)])
def test_ids_equal_the_unchanged_library(name, words):
    tokenizers = pytest.importorskip("tokenizers")
    path = pytest.importorskip("public_tokenizers").path(name)
    from congraph.llm import tokens

    library = tokenizers.Tokenizer.from_file(path)
    cache = tokens.PieceCache(path, words)
    parts = ["a", "b.", " ", "\n", "  ", "<|endoftext|>", "<|startoftext|>", "<|ENDOFTEXT|>", "<|", "Word", "é", "\t", "don't"]
    texts = ["a <|endoftext|> b", "<|endoftext|>\nq", *("".join(R.choice(parts) for _ in range(R.randrange(12))) for _ in range(800))]
    for text in texts:
        assert np.frombuffer(cache.encode(text), cache.dtype).tolist() == library.encode(text, add_special_tokens=False).ids, text


def test_crc_is_unsigned():
    assert zlib.crc32(b"x") >= 0
