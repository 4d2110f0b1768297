"""The ten operators against plain versions, with nulls, empty and long texts, ties, repeats and clashing columns."""

import hashlib
import random
import re

import numpy as np
import pytest

SF = "/root/testdata/sf0.001"
WORD = re.compile(r"[^\x20\x09-\x0D]+")
LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def docs(spark, rows):
    return spark.createDataFrame([(i, t, "x") for i, t in rows], "doc_id long, text string, h string")


@pytest.fixture(scope="module")
def mixed():
    rng = random.Random(5)
    vocab = [f"w{i}" for i in range(60)]
    base = [" ".join(rng.choice(vocab) for _ in range(n)) for n in (40, 60, 90, 7, 5)]
    rows = []
    for t in base:
        for _ in range(8):
            w = t.split()
            for _ in range(rng.randint(0, 3)):
                w[rng.randrange(len(w))] = rng.choice(vocab)
            rows.append(" ".join(w))
    rows += ["", None, "  \n ", "one two", "one two", "ONE two", "é ü", rows[0].upper(), "x " * 3000]
    return list(enumerate(rows))


def components(rows, linked):
    up = {i: i for i, _ in rows}

    def top(i):
        while up[i] != i:
            i = up[i]
        return i

    for a, b in linked:
        a, b = top(a), top(b)
        up[max(a, b)] = min(a, b)
    return {i: top(i) for i in up}


def shingles(text):
    w = WORD.findall((text or "").translate(LOWER))
    return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set()


@pytest.mark.parametrize("crowd", [64, 2])
def test_ngram_components(spark, mixed, crowd, monkeypatch):
    from tilesketch.llm import ngram_join

    monkeypatch.setattr(ngram_join.links, "__defaults__", (80, 1, crowd))
    sets = {i: shingles(t) for i, t in mixed}
    linked = [(a, b) for a in sets for b in sets if a < b and sets[a] and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b])]
    want = components(mixed, linked)
    got = ngram_join.ngram_components(docs(spark, [*mixed, mixed[3], (None, "a b")])).collect()
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in got} == {i: (len(sets[i]), want[i]) for i in sets}
    assert len(got) == len(sets)


def test_no_documents(spark):
    from tilesketch.llm import chat_format, decontaminate, line_dedup, ngram_join, personal_data, sentencepiece_codec, token_counts

    none = docs(spark, [])
    model = sentencepiece_codec.model_bytes()
    bench = spark.createDataFrame([(1, "a b c d e f g h i")], "item_id long, text string")
    turns = spark.createDataFrame([], "conv_id long, turn long, role string, text string")
    for out in (ngram_join.ngram_components(none), line_dedup.dedup_lines(none), personal_data.personal_data(none), sentencepiece_codec.encoded(none, model), token_counts.token_counts(none, model), decontaminate.contaminated(none, bench), chat_format.perspectives(turns)):
        assert out.count() == 0


def test_line_windows(spark):
    from tilesketch.llm.line_dedup import dedup_lines

    rows = [(1, "a\nb\n\n c \nd"), (2, "x\na\nb\nc\ny"), (3, "a\nb\nc\nd"), (4, None), (5, ""), (6, "q\nq\nq\nq"), (None, "a\nb\nc")]
    got = {r.doc_id: (r.text, r.n_removed_lines) for r in dedup_lines(docs(spark, rows)).collect()}
    assert got == {1: ("a\nb\n\n c \nd", 0), 2: ("x\ny", 3), 3: ("", 4), 4: (None, 0), 5: ("", 0), 6: ("q", 3), None: ("a\nb\nc", 0)}


def test_templates(spark):
    from tilesketch.llm.decontaminate import contaminated

    item = "Yesterday Tom bought 3 red apples for 12 km of road and then Tom sold 3 of them to his old friend Anna"
    other = item.replace("Tom", "Bob").replace(" 3 ", " 7 ").replace("12", "55").replace("Anna", "Eve")
    broken = item.replace("then Tom", "then Jim").replace("sold 3", "sold 9")
    rows = [(1, f"Some words. {item} and more"), (2, f"Some words. {other}"), (3, "Some words. " + broken), (4, "nothing of it here"), (5, None), (6, "")]
    bench = spark.createDataFrame([(10, item), (11, None), (12, "short item"), (13, "")], "item_id long, text string")
    for small in (4_000_000, 0):
        got = {(r.doc_id, r.item_id, r.exact) for r in contaminated(docs(spark, rows), bench, small=small).collect()}
        assert got == {(1, 10, True), (2, 10, False)}


def test_templates_with_names_at_sentence_starts(spark):
    from tilesketch.llm.decontaminate import contaminated

    item = "Tom has 3 red apples in his bag. Tom buys 5 more apples at the shop. Tom gives 2 apples to Anna. How many apples does Tom have now?"
    other = item.replace("Tom", "Bob").replace("Anna", "Eve").replace("3", "8").replace("5", "11").replace("2", "4")
    rows = [(1, item), (2, "Read this. " + other), (3, other.replace("Bob gives", "Jim gives")), (4, other.replace("Eve", "Bob")), (5, "Solve this: What is 12 + 30, then?"), (6, "what is 12 + 31"), (7, f"Ann said: {item[:1].lower()}{item[1:]}")]
    bench = spark.createDataFrame([(1, item), (2, "What is 12 + 30?")], "item_id long, text string")
    got = {(r.doc_id, r.item_id, r.exact) for r in contaminated(docs(spark, rows), bench).collect()}
    assert got == {(1, 1, True), (2, 1, False), (5, 2, True), (7, 1, True)}


STORIES = [
    "{A} has {x} red apples in a bag. {A} buys {y} more apples at the old shop. {A} then gives {z} apples to {B}. How many apples does {A} have now?",
    "Every week {A} drives {x} km to the city of {C} and back again. {B} drives {y} km more than {A} does. How far do they drive in {z} weeks?",
    "A train leaves {C} at a speed of {x} km an hour while {A} waits for {y} hours at the station with {B}. {B} pays {z} dollars for the two tickets.",
    "The baker {A} sells {x} loaves of bread and {y} small cakes before noon. {B} bakes {z} loaves in the same time. Who of the two bakes more?",
]


def _filled(rng, story):
    names = rng.sample(["Tom", "Anna", "Bob", "Eve", "Carl", "Dora", "Finn", "Gina"], 2)
    numbers = rng.sample(range(2, 90), 3)
    return story.format(A=names[0], B=names[1], C=rng.choice(["Paris", "Rome", "Oslo", "Lima"]), x=numbers[0], y=numbers[1], z=numbers[2])


def _plain_template_match(item, text, size=8, literals=4):
    """The rule read plainly: all windows of both sides, word by word."""
    from tilesketch.llm.decontaminate import UNITS

    def tokens(t):
        out, opens = [], True
        for m in re.finditer(r"[A-Za-z]+|[0-9]+(?:[.,][0-9]+)*|[.!?\n]", t):
            w = m[0]
            if w in ".!?\n":
                opens = True
                continue
            close = out and out[-1][0] == "#" and m.start() - out[-1][3] <= 1
            kind = "#" if w[0].isdigit() else "%" if close and w.lower() in UNITS else "^" if w[0].isupper() and opens else "@" if w[0].isupper() else ""
            out.append((kind, w.lower(), opens, m.end()))
            opens = False
        return out

    def windows(toks, typed):
        view = [("" if k == "^" and not typed else "@" if k == "^" else k, w, k == "^") for k, w, _, _ in toks]
        for i in range(len(view) - size + 1):
            part = view[i : i + size]
            if sum(not k for k, _, _ in part) >= literals and (not typed or any(o for _, _, o in part)):
                yield i, tuple(k or w for k, w, _ in part), [(w if k else None) for k, w, _ in part]

    mine, theirs = tokens(item), tokens(text)
    total, lines = set(), {}
    for typed in (False, True):
        found = {}
        for i, key, slots in windows(theirs, typed):
            found.setdefault(key, []).append((i, slots))
        for i, key, slots in windows(mine, typed):
            total.add(i)
            for j, others in found.get(key, ()):
                places, pairs = lines.setdefault(j - i, (set(), set()))
                places.add(i)
                pairs |= {(a, b) for a, b in zip(slots, others, strict=True) if a is not None}
    sound = lambda pairs: len({a for a, _ in pairs}) == len({b for _, b in pairs}) == len(pairs)
    return any(sound(pairs) and (2 * len(places) >= len(total) or len(places) + size - 1 >= 13) for places, pairs in lines.values())


def test_renamed_problems_against_a_plain_version(spark):
    from tilesketch.llm.decontaminate import contaminated

    rng = random.Random(8)
    items = [_filled(rng, s) for s in STORIES]
    texts, truth = [], {}
    for n in range(120):
        which = rng.randrange(len(STORIES))
        t = _filled(rng, STORIES[which])
        if n % 3 == 1:  # a swapped name or a word taken out
            t = t.replace(" the ", " ", 1) if n % 2 else re.sub(r"\b(Tom|Anna|Bob|Eve|Carl|Dora|Finn|Gina)\b", "Hugo", t, count=1)
        else:
            truth[n] = which
        texts.append("Some words before it. " * (n % 2) + t)
    texts += ["The shop sells apples and bread. Tom has 3 of them in his bag and goes to the station."] * 2
    got = {(r.doc_id, r.item_id) for r in contaminated(docs(spark, list(enumerate(texts))), spark.createDataFrame(list(enumerate(items)), "item_id long, text string")).collect()}
    assert got == {(i, j) for i, t in enumerate(texts) for j, item in enumerate(items) if _plain_template_match(item, t)}
    assert sum((n, which) in got for n, which in truth.items()) >= 0.9 * len(truth)
    assert not any(i >= 120 for i, _ in got)


def test_grid_join(spark):
    from tilesketch.llm.grid_join import near_vectors

    rng = np.random.default_rng(1)
    x = rng.normal(size=(60, 8))
    x[20:40] = x[0] + rng.normal(size=(20, 8)) * 0.3
    x[41] = x[40]
    rows = [(i, i % 2 if i < 40 else 3, [float(v) for v in x[i].astype(np.float32)]) for i in range(60)]
    odd = [(100, None, rows[0][2]), (101, 0, None), (102, 0, [0.0] * 8), (103, 0, [float("nan")] * 8), (104, 0, []), (105, 0, [1.0] * 3)]
    df = spark.createDataFrame(rows + odd, "vec_id long, label int, embedding array<float>")
    got = {r.vec_id: (r.n_links, r.component_id, r.kept) for r in near_vectors(df, size=7).collect()}
    v = np.array([r[2] for r in rows])
    cos = v @ v.T / np.outer(np.linalg.norm(v, axis=1), np.linalg.norm(v, axis=1))
    linked = [(a, b) for a in range(60) for b in range(60) if a < b and rows[a][1] == rows[b][1] and cos[a, b] >= 0.93]
    top = components([(r[0], None) for r in rows], linked)
    assert linked and {i: got[i] for i in range(60)} == {i: (sum(i in p for p in linked), top[i], top[i] == i) for i in range(60)}
    assert all(got[i] == (0, i, True) for i in range(100, 106))


PATTERNS = [("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"), ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"), ("card", r"[0-9]([\x20-]?[0-9])+"), ("phone", r"\+[0-9][\x20().0-9-]+[0-9]")]


def luhn(d):
    return sum(int(c) if i % 2 == 0 else sum(map(int, str(2 * int(c)))) for i, c in enumerate(reversed(d))) % 10 == 0


def base(text):
    out = []
    for place, (kind, pattern) in enumerate(PATTERNS):
        for m in re.finditer(pattern, text or ""):
            d = re.sub("[^0-9]", "", m[0])
            if {"email": True, "ip": kind == "ip" and all(int(p) <= 255 for p in m[0].split(".")), "card": 14 <= len(d) <= 19 and luhn(d), "phone": 10 <= len(d) <= 15}[kind]:
                out.append((m.start(), place, f"{kind}:{m.start()}:{m.end()}"))
    return ",".join(x[2] for x in sorted(out))


def test_personal_data(spark):
    from tilesketch.llm.personal_data import personal_data

    rng = random.Random(3)
    parts = ["a.b@c.de", "x@y", "@", "1.2.3.4", "999.1.1.1", "0001.02.3.255", "4111 1111 1111 1111", "4111-1111-1111-1112", "+1 (017) 555-7713", "+49.30.1234567", "é🎉", " ", ".", "_", "%", "12", "-", "z@q.io.x"]
    rows = [(i, "".join(rng.choice(parts) + rng.choice(["", " "]) for _ in range(12))) for i in range(150)] + [(900, None), (901, ""), (902, "1" * 5000 + " " + "a" * 9000)]
    got = {r.doc_id: r for r in personal_data(docs(spark, rows)).collect()}
    for i, t in rows:
        assert got[i].base_sha256 == hashlib.sha256(base(t).encode()).hexdigest(), t
        assert set(filter(None, base(t).split(","))) <= set(got[i].spans.split(","))


def test_contexts_find_unseen_identifiers(spark):
    from tilesketch.llm.personal_data import personal_data

    rows = [(i, f"please mailto: u{i}@ex{i}.org and go") for i in range(12)] + [(50, "please mailto: agent47badge now"), (51, "the room agent47x is empty")]
    got = {r.doc_id: r.spans for r in personal_data(docs(spark, rows)).collect()}
    assert got[50] == "other:15:27" and got[51] == ""


def test_spans_of_several_words_are_seeds(spark):
    from tilesketch.llm.personal_data import personal_data

    def card(i):
        d = f"4111 1111 11{i:02d} 111"
        return next(d + c for c in "0123456789" if luhn((d + c).replace(" ", "")))

    rows = [(i, f"do call: +1 (017) 555-77{i:02d} or pay1: {card(i)} ok") for i in range(12)] + [(20 + i, f"zip99 u{i}@ex{i}.org") for i in range(12)]
    rows += [(50, "do call:" + " " * 99 + "017x now"), (51, "see pay2: n0 ok"), (52, "zip98 (q7)"), (53, "a room 017x is n0")]
    got = {r.doc_id: r for r in personal_data(docs(spark, rows)).collect()}
    assert {i: got[i].spans for i in (50, 51, 52, 53)} == {50: "other:107:111", 51: "other:10:12", 52: "other:7:9", 53: ""}
    assert all(got[i].n_card == 1 and got[i].n_phone == 1 and got[i].n_other == 0 for i in range(12))


def _word_spans(text):
    """Words with a digit or an at sign: start and end of the core, or of each key in it, the context, and whether a key."""
    from tilesketch.llm.personal_data import SECRET

    def context(start):
        head = re.split(r"[\x20\x09-\x0D]+", text[:start])
        return re.sub("[0-9]", "0", head[-2].lower()) if len(head) > 1 else ""

    out = []
    for m in WORD.finditer(text):
        if not re.search("[0-9@]", m[0]):
            continue
        keys = [(m.start() + k.start(), m.start() + k.end(), k[0]) for k in re.finditer(SECRET, m[0])]
        core = re.match(r"[\W_]*?(?=[^\W_]|\+|$)", m[0]).end()
        tail = re.sub(r"[\W_]+$", "", m[0][core:])
        out += [(*k, context(m.start()), True) for k in keys] or ([(m.start() + core, m.start() + core + len(tail), tail, context(m.start()), False)] if tail else [])
    return out


def _plain_bootstrap(texts, rounds=5, seeds=3, least=0.8):
    words, graph, known = {}, {}, set()
    for i, t in texts.items():
        spans = [tuple(map(int, x.split(":")[1:])) for x in base(t).split(",") if x]
        for a, b in spans:
            before = re.split(r"[\x20\x09-\x0D]+", t[:a])
            known.add(t[a:b])
            if len(before) > 1 and before[-2]:
                graph.setdefault(re.sub("[0-9]", "0", before[-2].lower()), set()).add(t[a:b])
        words[i] = [w for w in _word_spans(t) if not any(a < w[1] and b > w[0] for a, b in spans)]
        for _, _, value, context, key in words[i]:
            known |= {value} if key else set()
            if context:
                graph.setdefault(context, set()).add(value)
    score, trusted = dict.fromkeys(known, 1.0), set()
    for _ in range(rounds):
        conf = {p: sum(score.get(x, 0.0) for x in v) / (len(v) + 1) for p, v in graph.items()}
        now = {p for p, v in graph.items() if round(conf[p], 9) >= least and sum(score.get(x, 0.0) >= least for x in v) >= seeds}
        if now == trusted:
            break
        trusted = now
        wrong = {}
        for p in trusted:
            for x in graph[p]:
                wrong[x] = wrong.get(x, 1.0) * (1 - min(conf[p], 0.999))
        score = {x: 1.0 if x in known else 1 - wrong.get(x, 1.0) for x in {*known, *wrong}}
    return {i: {(a, b) for a, b, _, context, key in w if key or context in trusted} for i, w in words.items()}


def test_found_spans_against_a_plain_bootstrap(spark):
    from tilesketch.llm.personal_data import personal_data

    rng = random.Random(11)
    heads = ["mailto:", "call:", "badge", "room", "the", "staff"]
    ids = [f"zx{i}q" for i in range(12)]

    def part():
        n = rng.randrange(1000)
        kind = rng.random()
        if kind < 0.3:
            return f"mailto: u{n}@ex{n}.org"
        if kind < 0.45:
            return f"mailto: {rng.choice(ids)}"
        if kind < 0.6:
            return f"badge {rng.choice(ids)}"
        if kind < 0.65:
            return "badge 7new"
        if kind < 0.7:
            return f'token = "{hashlib.md5(str(n).encode()).hexdigest()}"'
        if kind < 0.75:
            return f"pin = 77{n}"
        return f"{rng.choice(heads[3:])} {rng.choice(['9a', 'x1', 'plain', '(b7)', '10.0.0.1'])}"

    texts = {i: " ".join(part() for _ in range(rng.randrange(1, 9))) for i in range(160)}
    want = _plain_bootstrap(texts)
    got = {r.doc_id: r for r in personal_data(docs(spark, list(texts.items()))).collect()}
    for i, t in texts.items():
        assert {tuple(map(int, x.split(":")[1:])) for x in got[i].spans.split(",") if x.startswith("other")} == want[i], t
    caught = [(t.index("7new"), t.index("7new") + 4) in want[i] for i, t in texts.items() if "7new" in t]
    assert caught and all(caught)  # by a context that no seed has, only what the first round found


def test_a_million_matches_in_one_text(spark):
    import time

    from tilesketch.llm.personal_data import personal_data

    n = 1_000_000
    began = time.time()
    r = personal_data(docs(spark, [(1, " ".join(map(str, range(n)))), (2, "1.2.3.4 " * 20_000)])).select("doc_id", "n_ip", "n_found").collect()
    assert {x.doc_id: x.n_ip for x in r} == {1: 0, 2: 20_000}
    assert time.time() - began < 120


def test_chat(spark):
    from tilesketch.llm.chat_format import perspectives, whole_dialogues

    turns = [(1, 0, "system", "be kind"), (1, 1, "ann", "hi"), (1, 2, "bob", None), (1, 200, "ann", "bye 🎉"), (1, 200, "ann", "bye 🎉"), (2, 0, None, "solo"), (None, 0, "ann", "x"), (3, 0, "system", "alone")]
    segments = perspectives(spark.createDataFrame(turns, "conv_id long, turn long, role string, text string"))
    whole = {(r.conv_id, r.perspective): r for r in whole_dialogues(segments).collect()}
    assert set(whole) == {(1, "ann"), (1, "bob"), (2, "unknown")}
    ann = whole[1, "ann"]
    assert ann.rendered == "<|system|>\nbe kind<|end|>\n<|assistant|>\nhi<|end|>\n<|user name=bob|>\n<|end|>\n<|assistant|>\nbye 🎉<|end|>\n"
    assert [ann.rendered[slice(*map(int, m.split(":")))] for m in ann.masks.split(",")] == ["hi<|end|>\n", "bye 🎉<|end|>\n"]
    for r in segments.collect():
        assert whole[r.conv_id, r.perspective].rendered[r.start : r.end] == r.segment


def test_codec_parity():
    from sentencepiece import sentencepiece_model_pb2 as pb

    from tilesketch.llm import sentencepiece_codec as codec

    model = codec.model_bytes()
    texts = ["", " ", "  a  b", "日本語 🎉\n\n \t", "</s> <unk> <0x41>", "ab   cd\n ef", "x" * 3000, "Thing of the\nThat  one"]
    assert codec.parity(model, texts) == []
    m = pb.ModelProto.FromString(model)
    m.trainer_spec.model_type = 1
    for p in m.pieces:
        p.score = max(p.score, -50_000.0)
    assert codec.parity(m.SerializeToString(), texts) == []


def test_decoder_equals_the_library():
    from tilesketch.llm import sentencepiece_codec as codec

    model = codec.model_bytes()
    coder, ours = codec.build(model), codec.Decoder(model)
    texts = ["", " ", "  a  b", "日本語 🎉\n\n \t", "</s> <unk> <0x41>", "ab   cd\n ef", "x" * 3000, "\ufffd é"]
    ids = [x.ids for x in coder.encode_batch_fast(texts, add_special_tokens=False)]
    flat, offs = np.concatenate([np.array(x, np.int64) for x in ids]), np.cumsum([0, *map(len, ids)])
    for step in (3, 1 << 18):
        assert [x.decode() for x in ours.decode(flat, offs, step)] == coder.decode_batch(ids, skip_special_tokens=False)
    with pytest.raises(ValueError):
        ours.decode(np.array([10**6]), np.array([0, 1]))


def test_encoded_texts_come_back(spark):
    from tilesketch.llm import sentencepiece_codec as codec

    model = codec.model_bytes()
    rows = [(1, "a  b\n"), (2, ""), (3, None), (4, "é🎉 " * 2000), (4, "twice"), (None, "no id")]
    out = codec.encoded(docs(spark, rows), model)
    assert out.where("not round_trip").count() == 0
    back = codec.decoded(out.unionByName(spark.createDataFrame([(9,)], "doc_id long"), allowMissingColumns=True), model)
    assert sorted((r.doc_id or 0, r.text) for r in back.collect()) == sorted([(i or 0, t or "") for i, t in rows] + [(9, "")])


def whole_unigram(text, scores):
    """Tokens of the best segmentation of the whole normalised text, and the fewest of equals."""
    t = "▁" + text.replace(" ", "▁") if text else ""
    unknown, longest = min(scores.values()) - 10, max(map(len, scores))
    best = [(0.0, 0)]
    for j in range(1, len(t) + 1):
        ways = [(best[i][0] + scores[t[i:j]], best[i][1] - 1) for i in range(max(0, j - longest), j) if t[i:j] in scores]
        best.append(max([*ways, (best[j - 1][0] + unknown, best[j - 1][1] - len(t[j - 1].encode()))]))
    return -best[-1][1]


def test_token_counts(spark):
    from tilesketch.llm import sentencepiece_codec as codec
    from tilesketch.llm.token_counts import token_counts

    model = codec.model_bytes()
    rng = random.Random(4)
    scores = {t: s for t, s, kind in codec.parse(model)["pieces"] if kind in (codec.NORMAL, codec.USER)}
    rows = [(1, "the then there them 🎉 日本"), (2, None), (3, ""), (4, "antidisestablishment " * 3 + "q" * 700)]
    rows += [(5, "".join(rng.choice("日本語中文的一是不了人我在有") for _ in range(2000))), (6, "".join(rng.choice("abcdeftion") for _ in range(3000))), (7, "é🎉" * 400 + "=" * 999)]
    got = {r.doc_id: (r.n_pretokens, r.n_tokens) for r in token_counts(docs(spark, rows), model).collect()}
    assert got == {i: (len(WORD.findall(t or "")), whole_unigram(t or "", scores)) for i, t in rows}


SPACED = ["a  b\nc\td", "\n\n", " ", "   ", "\n", "x;\r\n\r\n  y", "a\x0b \x0cb", " lead and trail ", "▁mark ▁ in\ttext", "日本\n語 🎉 \n", "tab\t\t  " * 50, " " * 700 + "far", "", None]


def test_token_counts_keep_white_space(spark):
    from sentencepiece import SentencePieceProcessor
    from sentencepiece import sentencepiece_model_pb2 as pb

    from tilesketch.llm import sentencepiece_codec as codec
    from tilesketch.llm.token_counts import token_counts

    model = codec.model_bytes()
    given = [r.text for r in spark.read.parquet(f"{SF}/documents.parquet").orderBy("doc_id").limit(40).collect()]
    rows = list(enumerate([*SPACED, *(t[:3000] for t in given)]))
    scores = {t: s for t, s, kind in codec.parse(model)["pieces"] if kind in (codec.NORMAL, codec.USER)}
    got = {r.doc_id: r.n_tokens for r in token_counts(docs(spark, rows), model).collect()}
    assert got == {i: whole_unigram(t or "", scores) for i, t in rows}
    rng, m = random.Random(1), pb.ModelProto.FromString(model)  # scores without ties, so that the library must agree
    m.trainer_spec.model_type = 1
    for p in m.pieces:
        p.score = -rng.uniform(8, 16)
    for squeeze in (False, True):
        m.normalizer_spec.remove_extra_whitespaces = squeeze
        theirs = SentencePieceProcessor(model_proto=m.SerializeToString()).encode([t or "" for _, t in rows])
        got = {r.doc_id: r.n_tokens for r in token_counts(docs(spark, rows), m.SerializeToString()).collect()}
        assert got == {i: len(x) for (i, _), x in zip(rows, theirs, strict=True)}


def _all_paths(theta, chain):
    from itertools import product

    begin, up, down, stay = chain
    move = {(0, 0): 0.0, (0, 1): up, (1, 0): down, (1, 1): stay}
    return {y: np.exp(begin * y[0] + sum(v * s for v, s in zip(theta, y, strict=True)) + sum(move[p] for p in zip(y, y[1:]))) for y in product((0, 1), repeat=len(theta))}


def test_marginals_are_exact():
    from tilesketch.llm.toxicity import marginals

    rng = np.random.default_rng(2)
    lens = [5, 1, 3, 6]
    theta, chain = rng.normal(size=sum(lens)), rng.normal(size=4)
    m, log_z, moves = marginals(theta, np.repeat(np.arange(4), lens), chain, True)
    at = 0
    for i, n in enumerate(lens):
        weight = _all_paths(theta[at : at + n], chain)
        z = sum(weight.values())
        mean = lambda f: sum(w * f(y) for y, w in weight.items()) / z  # noqa: E731, B023
        assert np.isclose(log_z[i], np.log(z))
        assert np.allclose(m[at : at + n], [mean(lambda y, t=t: y[t]) for t in range(n)])
        pairs = [mean(lambda y, p=p: sum(q == p for q in zip(y, y[1:]))) for p in ((0, 1), (1, 0), (1, 1))]
        assert np.allclose(moves[:, i], [mean(lambda y: y[0]), *pairs])
        at += n


def test_scores_of_documents_against_all_paths(spark):
    from tilesketch.llm import toxicity

    rng = np.random.default_rng(3)
    texts = ["Du alte zug hier. So gut\nnun ja", "", None, "ruhig", "zug zug! zug", "ä ö ü"]
    buckets = np.arange(1, toxicity.BUCKETS)
    tagger = toxicity.Tagger(buckets, rng.normal(size=len(buckets)).astype(np.float32), -0.3, rng.normal(size=4), np.array([-1.0, 2.0, 0.7]))
    dense = tagger.dense()
    got = {r.doc_id: r for r in toxicity.apply(docs(spark, list(enumerate(texts))), tagger).collect()}
    for i, t in enumerate(texts):
        data = np.frombuffer((t or "").encode(), np.uint8)
        top, mass, spans = 0.0, 0.0, []
        for line in re.finditer(r"[^.!?\n]+", t or ""):
            words = list(re.finditer(r"[^\W\d_]+", line[0]))
            feats = toxicity.tokens(np.frombuffer(line[0].encode(), np.uint8), np.array([0, len(line[0].encode())]))[-1] if words else None
            if not words:
                continue
            weight = _all_paths(tagger.bias + toxicity.scores(dense, feats), tagger.chain)
            z = sum(weight.values())
            m = [sum(w for y, w in weight.items() if y[k]) / z for k in range(len(words))]
            top, mass = max(top, *m), mass + sum(m)
            for k, w in enumerate(words):
                if m[k] >= 0.5:
                    at = line.start() + w.start(), line.start() + w.end()
                    if spans and k and m[k - 1] >= 0.5:
                        spans[-1] = spans[-1][0], at[1]
                    else:
                        spans.append(at)
        want = 1 / (1 + np.exp(-(tagger.curve @ [1, top, np.log1p(mass)])))
        assert np.isclose(got[i].score, want), (t, len(data))
        assert got[i].spans == ",".join(f"{x}:{y}" for x, y in spans)


def test_context_tells_what_a_word_alone_does_not():
    from tilesketch.llm.bytewise import blocks
    from tilesketch.llm.toxicity import fit
    import pyarrow as pa

    rng = random.Random(6)
    fill = [f"w{chr(97 + i % 26)}{chr(97 + i // 26)}" for i in range(80)]

    def text(toxic):
        words = [rng.choice(fill) for _ in range(rng.randrange(12, 40))]
        first = rng.randrange(6)
        words[first:first] = (["du", "zug"] if toxic else ["du", "hund"])
        words += ["mein", "hund"] if toxic else ["mein", "zug"]
        return " ".join(words)

    train, test = ([(text(y), y) for y in (rng.random() < 0.3 for _ in range(n))] for n in (900, 300))

    def right(**options):
        tagger = fit([t for t, _ in train], np.array([float(y) for _, y in train]), **options)
        _, data, offs = next(blocks([pa.record_batch({"text": pa.array([t for t, _ in test], pa.large_string())})]))
        top, mass, _ = tagger.tag(data, offs, tagger.dense())
        return np.mean((tagger.score(top, mass) >= 0.5) == np.array([y for _, y in test]))

    assert right() >= 0.95 and right(linked=False) >= 0.95 and right(context=False) >= 0.95  # either tells the pair
    assert right(context=False, linked=False) <= 0.85


@pytest.mark.parametrize("name, label, least", [("quality", "quality", 0.97), ("toxicity", "toxic", 0.98)])
def test_classifiers_on_held_out_rows(spark, name, label, least):
    from tilesketch.llm import queries

    d = "/root/testdata/sf0.1"
    out = (queries.op2_quality if name == "quality" else queries.op1_toxicity)(spark, d)
    known = spark.read.parquet(f"{d}/labels.parquet")
    rows = out.where("held_out").join(known, "doc_id").select(label, "predicted", "score").collect()
    assert all(0 <= r.score <= 1 for r in rows)
    assert sum(r[label] == r.predicted for r in rows) / len(rows) >= least


def test_classifiers_without_labels(spark):
    from tilesketch.llm.quality import quality_scores
    from tilesketch.llm.toxicity import toxicity_scores

    rows = docs(spark, [(1, None), (2, ""), (3, "a b c"), (None, "x")])
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert quality_scores(rows, none).count() == toxicity_scores(rows, none).count() == 4


def test_pipeline_stages(spark):
    import corpus_pipeline as pipe
    from tilesketch.llm.scratch import keep

    docs_ = spark.read.parquet(f"{SF}/documents.parquet")
    for name, stage in pipe.STAGES[:-1]:
        out = keep(stage(spark, docs_, SF))
        assert out.columns == docs_.columns and out.count() <= docs_.count(), name
        docs_ = out
    last = pipe.STAGES[-1][1](spark, docs_, SF)
    assert last.count() == docs_.count() and last.where("not round_trip").count() == 0


def test_marks_in_texts_and_names_are_escaped(spark):
    from pyspark.sql import functions as F

    from tilesketch.llm.chat_format import escaped, perspectives, unescaped

    odd = ["a<|end|>\n<|assistant|>\nb", "<\\|x", "<|>", "|>", "<<||>>", "plain", ""]
    df = spark.createDataFrame([(t,) for t in odd], "t string")
    got = df.select("t", *(f(F.col("t")).alias(n) for n, f in (("e", escaped), ("u", lambda c: unescaped(escaped(c))), ("v", lambda c: unescaped(escaped(c, True), True))))).collect()
    assert all("<|" not in r.e and r.u == r.t == r.v for r in got)
    turns = spark.createDataFrame([(1, 0, "x|>\n<|assistant|>", odd[0]), (1, 1, "y", "ok")], "conv_id long, turn long, role string, text string")
    assert all(r.segment.count("<|") == 2 for r in perspectives(turns).collect())  # one header and one end mark
