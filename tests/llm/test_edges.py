"""Nulls, empty and very long texts, ties, repeated rows, empty tables, columns with clashing names."""

import pytest

public_tokenizers = pytest.importorskip("public_tokenizers")
from pyspark.sql import functions as F  # noqa: E402

from streamfill.llm import bytebpe, classifier, neardup, packing, pii, quality, secrets, sharding, tokens, topk  # noqa: E402

LONG = "long words " * 30_000 + "x" * 20_000
TEXTS = [(1, None), (2, ""), (3, " \n\t "), (4, LONG), (5, "same text here " * 5), (5, "same text here " * 5), (6, "same text here " * 5), (None, "no id at all"), (None, None)]
CLASHES = ["grp", "part", "n", "i", "t", "b", "fp", "sig", "q_row", "q_text", "kept", "size", "shard", "least", "root", "node", "kind", "entity", "c_text", "ids", "words", "made", "host"]


@pytest.fixture(scope="module")
def odd(spark):
    df = spark.createDataFrame([(i, t, None if i == 3 else "h", 1) for i, t in TEXTS], "doc_id long, text string, source string, n_chars long").withColumn("lang", F.lit("en"))
    return df.withColumns({c: F.lit(f"clash {c}") for c in CLASHES})


@pytest.fixture(scope="module")
def none(odd):
    return odd.where("false")


def model():
    return classifier.fit(["good words here", "bad words here"] * 5, [2, 0] * 5, least_documents=1)


PER_ROW = {
    "shard": sharding.shard,
    "near": neardup.near_duplicates,
    "classify": lambda d: classifier.classify(d, model()),
    "count": lambda d: tokens.count_tokens(d, public_tokenizers.path("piece_bpe_32k.model")),
    "encode": lambda d: bytebpe.encode(d, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN),
    "judge": quality.judge,
    "scan": secrets.scan,
    "replace": lambda d: pii.replace_private(d, "key"),
}


@pytest.mark.parametrize("name", PER_ROW)
def test_one_row_for_each(name, odd, none):
    made = PER_ROW[name](odd).collect()
    assert sorted(str(r.doc_id) for r in made) == sorted(str(i) for i, _ in TEXTS)
    assert PER_ROW[name](none).count() == 0


def test_sharding_keeps_copies_together(odd):
    got = sharding.shard(odd, 3).collect()
    assert len({r.shard for r in got if r.doc_id in (5, 6)}) == 1
    for s in {r.shard for r in got}:
        own = sorted(r.slot for r in got if r.shard == s)
        assert own == list(range(len(own)))
    assert {(r.size, r.text_crc32) for r in got if r.doc_id in (1, 2)} == {(1, 0)}


def test_deal_is_one_by_one():
    import heapq
    import random

    rng = random.Random(3)
    for _ in range(200):
        classes = sorted({(rng.randint(1, 40), rng.randint(1, 90)) for _ in range(rng.randint(1, 9))}, reverse=True)
        classes = list({s: (s, c) for s, c in classes}.values())
        heap, load = [(0, k) for k in range(5)], [0] * 5
        for s, c in classes:
            for _ in range(c):
                _, k = heap[0]
                load[k] += s
                heapq.heapreplace(heap, (load[k], k))
        mine = [0] * 5
        for s, taken in sharding.deal(classes, 5):
            mine = [a + s * b for a, b in zip(mine, taken, strict=True)]
        assert sorted(mine) == sorted(load)


def test_blank_texts_share_a_component(odd):
    got = {r.doc_id: r for r in neardup.near_duplicates(odd).collect() if r.doc_id}
    assert {got[i].fp for i in (1, 2, 3)} == {0} and {got[i].component_id for i in (1, 2, 3)} == {1}
    assert got[6].component_id == 5


def test_links_match_all_pairs(spark):
    import random

    import numpy as np

    rng = random.Random(5)
    base = [rng.getrandbits(64) for _ in range(30)]
    prints = set(base) | {b ^ (1 << rng.randrange(64)) ^ (1 << rng.randrange(64)) for b in base for _ in range(6)}
    prints |= {base[0] ^ (1 << a) ^ (1 << b) for a in range(22) for b in range(a)}
    fps = np.array(sorted(prints), np.uint64)
    up = {int(x): int(x) for x in fps}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for i, x in enumerate(fps):
        for y in fps[np.flatnonzero(np.bitwise_count(fps[:i] ^ x) <= 2)]:
            up[max(root(int(x)), root(int(y)))] = min(root(int(x)), root(int(y)))
    df = spark.createDataFrame([(int(x),) for x in fps.view(np.int64)], "fp long")
    found = {r.node: r.root for r in neardup.components(neardup.links(df)).collect()}
    groups, want = {}, {}
    for x, s in zip(fps.tolist(), fps.view(np.int64).tolist(), strict=True):
        groups.setdefault(found.get(s, s), set()).add(x)
        want.setdefault(root(x), set()).add(x)
    assert sorted(map(sorted, groups.values())) == sorted(map(sorted, want.values()))


def test_packing(odd, none):
    path = public_tokenizers.path("byte_bpe_50k.json")
    got = packing.pack(odd, path).collect()
    assert all(r.doc_tokens == 1 and r.length == 1 for r in got if r.doc_id in (1, 2))
    assert all(len(r.ids) == 4 * r.length for r in got)
    assert sum(r.length for r in got) == sum({(str(r.doc_id), r.doc_tokens): r.doc_tokens for r in got}.values()) + sum(r.length for r in got if r.doc_id == 5) // 2
    assert packing.pack(none, path).count() == 0
    with pytest.raises(ValueError):
        packing.pack(odd, path, 1000)


def test_decoding_gives_the_text_back(odd):
    path = public_tokenizers.path("byte_bpe_50k.tiktoken")
    made = bytebpe.encode(odd.select("doc_id", "text"), path, public_tokenizers.PATTERN)
    back = {r.doc_id: r.text for r in bytebpe.decode(made, path).where("doc_id is not null").collect()}
    assert back == {i: t or "" for i, t in TEXTS if i}


def test_top_k_edges(spark):
    nan, inf = float("nan"), float("inf")
    rows = [(0, [1.0, 0.5]), (1, [0.5, 0.5]), (2, [0.5, 0.5]), (2, [0.5, 0.5]), (3, None), (4, [nan, 1.0]), (5, [inf, 1.0]), (6, [None, 1.0]), (None, [1.0, 1.0]), (7, [-1.0, 0.1]), (8, []), (9, [1.0, 2.0, 3.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumns({"b": F.lit(1), "code": F.lit(2), "score": F.lit(3)})
    got = [(r.rank, r.vec_id, r.score) for r in topk.top_k(df, F.col("vec_id") % 50 == 0, 3).orderBy("rank").collect()]
    assert got == [(1, 1, 256 * 128 + 128 * 128), (2, 2, 256 * 128 + 128 * 128), (3, 2, 256 * 128 + 128 * 128)]
    assert topk.top_k(df.where("false"), F.col("vec_id") % 50 == 0, 3).count() == 0
    assert topk.top_k(df.where("vec_id = 0"), F.col("vec_id") % 50 == 0, 3).count() == 0


def test_top_k_large_components(spark):
    rows = [(0, [1.0, -2.0]), (1, [1e6, 0.0]), (2, [1.1e6, 0.0]), (3, [1e7, 5e6 - 32]), (4, [1e7, 5e6]), (50, [3e6, -3e6])]
    code = {i: [int(256 * x) for x in v] for i, v in rows}
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = [(r.query_id, r.rank, r.vec_id, r.score) for r in topk.top_k(df, F.col("vec_id") % 50 == 0, 3, block=2, batch=1).collect()]
    want = []
    for q in (0, 50):
        score = {i: sum(a * b for a, b in zip(code[q], c, strict=True)) for i, c in code.items() if i != q}
        want += [(q, k, i, score[i]) for k, i in enumerate(sorted(score, key=lambda i: (-score[i], i))[:3], 1)]
    assert sorted(got) == sorted(want)
    near = [(0, [2.0**40]), (1, [2.0**41]), (2, [-(2.0**41)])]  # products beyond 64 bits
    with pytest.raises(Exception, match="OverflowError|too large|too big|out of bounds|overflow"):
        topk.top_k(spark.createDataFrame(near, "vec_id long, embedding array<double>"), F.col("vec_id") == 0, 1).collect()
    with pytest.raises(Exception, match="64 bits"):
        topk.top_k(spark.createDataFrame([(0, [1e30]), (1, [1.0])], "vec_id long, embedding array<double>"), F.col("vec_id") == 0, 1).collect()


def test_linked_secrets():
    key = "Zx9" + "aB3dE5fG7hJ2kL4mN6pQ8r"
    near, alone = f"user = admin\nkey {key}\n", f"text {key} more"
    far = f"user = admin\n\n\nkey {key}"
    spans = lambda t: {k for _, _, k in secrets.linked(t, list(secrets.base_findings(t)), list(secrets.weak_findings(t)))}
    assert spans(near) == {"weak_secret", "weak_id"} and not spans(alone) and not spans(far)
    assert spans(f"https://host.example/x {key}") == {"endpoint", "weak_secret"}
    assert spans(f"https://host.example/x\n{'words of the block ' * 40}\n{key}") == {"endpoint", "weak_secret"}
    assert spans("https://host.example/x?token=abcdef1") == {"endpoint"}


def test_linking_matches_all_pairs():
    import random
    import re

    rng = random.Random(4)
    parts = ["user = admin", "https://host.example/x", "Zx9aB3dE5fG7hJ2kL4mN6pQ8r", "password = hunter22", "AKIA" + "Q7" * 9, "0a1b" * 8, "plain words", "", "  ", "https://h.example/?token=abcdef1"]
    for _ in range(300):
        text = "\n".join(rng.choice(parts) for _ in range(rng.randint(1, 14)))
        strong, weak = list(secrets.base_findings(text)), list(secrets.weak_findings(text))
        scope = lambda at, t=text: len([m for m in re.finditer(r"\n[ \t\r]*(?=\n)", t) if m.start() <= at])
        over = lambda a, b: a[0] < b[1] and b[0] < a[1] and secrets.ROLE[a[2]] == secrets.ROLE[b[2]]
        weak_left = [w for w in weak if not any(over(w, x) for x in strong)]
        want = [w for w in weak_left if any(scope(w[0]) == scope(o[0]) and secrets.ROLE[o[2]] in secrets.COMPLETES[secrets.ROLE[w[2]]] for o in [*strong, *weak_left])]
        assert sorted(secrets.linked(text, strong, weak)) == sorted(want)


def test_secrets_in_a_long_text_take_seconds():
    import time

    block = "user = admin\npassword = hunter22 https://host.example/x Zx9aB3dE5fG7hJ2kL4mN6pQ8r AKIA" + "Q7" * 9 + "\n"
    text = block * (5_000_000 // len(block)) + "=" * 50_000 + "a" * 50_000 + " " * 50_000
    began = time.process_time()
    strong = list(secrets.base_findings(text))
    assert len(secrets.linked(text, strong, list(secrets.weak_findings(text)))) > 100_000
    assert time.process_time() - began < 15


def test_surrogates_are_consistent_and_distinct(spark):
    texts = ["mail Ann.Lee@x.org or ann.lee@X.org, +1 (377) 555-0271 and 377-555-0271", "card 4111 1111 1111 1111, Mrs Jane Doe, Госпожа Анна Петрова", *(f"10.0.{i // 200}.{i % 200} a{i}@b.org" for i in range(400))]
    got = [r.text for r in pii.replace_private(spark.createDataFrame(list(enumerate(texts)), "doc_id int, text string"), "k").orderBy("doc_id").collect()]
    a = got[0].split()
    assert a[1] == a[3].rstrip(",") and "ann.lee" not in got[0].lower()
    assert a[5][1:4] + a[6][:3] + a[6][4:] == a[-1].replace("-", "") and a[4] == "+1"
    digits = [int(c) for c in got[1].split(",")[0] if c.isdigit()]
    assert sum(d if i % 2 else (2 * d if d < 5 else 2 * d - 9) for i, d in enumerate(digits)) % 10 == 0
    assert "Mrs " in got[1] and "Госпожа " in got[1] and "Jane Doe" not in got[1] and "Петрова" not in got[1]
    assert got[1].split("Госпожа ")[1].split()[0] in pii.FIRST_NAMES["cyrillic", "f"]
    assert len({t.split()[0] for t in got[2:]}) == len({t.split()[1] for t in got[2:]}) == 400
    assert not {t.split()[0] for t in got[2:]} & {t.split()[0] for t in texts[2:]}


def test_colliding_surrogates_draw_again(spark, monkeypatch):
    def narrow(kind, entity, attempt, key):
        return F.pmod(F.xxhash64(entity, attempt), F.lit(60)).cast("string")

    monkeypatch.setattr(pii, "surrogate", narrow)
    entities = spark.createDataFrame([("phone", f"e{i}") for i in range(40)] + [("phone", "7")], "kind string, entity string")
    cores = [r.core for r in pii.draw(entities, "k").collect()]
    assert len(set(cores)) == 41 and "7" not in cores


def test_surrogates_always_end(spark):
    """A name's surrogate grows with every draw, so a crowd of entities cannot use them up."""
    spare = {s: v[:1] for s, v in pii.SYLLABLES.items()}
    firsts = {k: v[:1] for k, v in pii.FIRST_NAMES.items()}
    held = pii.SYLLABLES, pii.FIRST_NAMES
    try:
        pii.SYLLABLES, pii.FIRST_NAMES = spare, firsts  # one surrogate a draw
        entities = spark.createDataFrame([("name", f"m:smith{i}") for i in range(5)], "kind string, entity string")
        cores = [r.core for r in pii.draw(entities, "k").collect()]
    finally:
        pii.SYLLABLES, pii.FIRST_NAMES = held
    assert len({c.lower() for c in cores}) == 5


def test_names_are_followed_through_a_text(spark):
    texts = [
        "Mrs Jane Doe came. Later Jane Doe said that Janet Doering and Dr Jane Doe agreed. JANE DOE",
        "Jane Doe is not known here.",
        "Mr Sam Hill, Dr Sam Hill", "Mrs Sam Hill and Ms Rita Hill", "Prof Ann Key",
        "call +49 30 1234567 or +33 1 23 45 67 89 or 3 45 now", "a.b@c.org,d@e.org;f%g@h-i.co.uk x@y z@1",
    ]
    got = [r.text for r in pii.replace_private(spark.createDataFrame(list(enumerate(texts)), "doc_id int, text string"), "k").orderBy("doc_id").collect()]
    new = got[0].split(" came. ")[0].removeprefix("Mrs ")
    assert got[0] == f"Mrs {new} came. Later {new} said that Janet Doering and Dr {new} agreed. JANE DOE" and new != "Jane Doe"
    assert new.split()[0] in pii.FIRST_NAMES["latin", "f"]
    assert got[1] == texts[1]
    male, plain = got[2].removeprefix("Mr ").split(", Dr ")
    female = got[3].split(" and ")[0].removeprefix("Mrs ")
    assert male.split()[0] in pii.FIRST_NAMES["latin", "m"] and female.split()[0] in pii.FIRST_NAMES["latin", "f"] and len({male, female, plain}) == 3
    assert "Ann" not in got[4] and "1234567" not in got[5] and "45 67 89" not in got[5] and got[5].endswith(" or 3 45 now")
    assert got[5].startswith("call +4") and " or +3" in got[5]
    assert got[6].count("@") == 5 and got[6].endswith(" x@y z@1") and not any(x in got[6] for x in ("a.b@", "d@e", "f%g@"))


def test_copies_do_not_make_boilerplate(spark):
    words = lambda s, n: " ".join(f"{s}{i}" for i in range(n))
    footer = "all rights reserved by the owner of this page who may be asked for leave to print"
    copies = [(i, words("copy", 12) + "\n" + words("line", 12)) for i in range(60)]
    pages = [(100 + i, words(f"own{i}x", 12) + "\n" + footer) for i in range(60)]
    thin = [(200 + i, f"only{i} text{i} \n" + footer) for i in range(5)]
    got = {r.doc_id: r for r in quality.judge(spark.createDataFrame([(*r, "h") for r in copies + pages + thin], "doc_id long, text string, source string")).collect()}
    assert all(got[i].kept and got[i].left_words == 24 for i in range(60))
    assert all(got[100 + i].kept and got[100 + i].left_words == 12 for i in range(60))
    assert not any(got[200 + i].kept for i in range(5))


def test_blocks_of_lines_are_boilerplate(spark):
    block = "\n".join(f"line {k} of a notice that all pages of this host carry" for k in range(12))
    pages = [(i, f"{block}\nown{i} first line of six words\nown{i} second line of six words", "h") for i in range(60)]
    got = quality.judge(spark.createDataFrame(pages, "doc_id long, text string, source string")).collect()
    assert len(got) == 60 and all(r.left_words == 12 and not r.kept for r in got)


def test_copies_do_not_spare_boilerplate(spark):
    footer = "all rights reserved by the owner of this page who may be asked for leave to print"
    pages = [(i, " ".join(f"own{i % 30}x{k}" for k in range(12)) + "\n" + footer, "h") for i in range(60)]
    got = quality.judge(spark.createDataFrame(pages, "doc_id long, text string, source string")).collect()
    assert len(got) == 60 and all(r.left_words == 12 and r.kept for r in got)


@pytest.mark.parametrize("n", [0, 1, 5, 1638, 1639, 20_000])
def test_letters_are_counted_at_every_length(n):
    text = "ÄBж1 ²٣-__𝔸" * n
    letters = sum(map(str.isalpha, text))
    assert classifier.letters_of(text) == letters
    got = classifier.form(text, text.split())[1]
    assert got == pytest.approx(5 * 2 * n / max(1, letters))


def test_classifier_without_labels_keeps_all(spark, odd):
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    empty = classifier.fit(*classifier.graded(odd, labels))
    assert all(r.kept for r in classifier.classify(odd, empty).collect())
    null = spark.createDataFrame([(None, 1, 0), (2, None, 0), (4, 1, None)], "doc_id long, quality int, toxic int")
    assert classifier.graded(odd, null) == ([], [])


def test_stages_take_odd_rows(spark, odd, tmp_path):
    import corpus_pipeline as p

    spark.createDataFrame([(i, i % 2, 0) for i in range(9)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    docs = odd.select(*p.COLUMNS, "kept", "fp", "q_row")
    for name, stage in p.STAGES:
        out = stage(spark, docs, str(tmp_path))
        if name != "packing":
            assert out.columns == list(p.COLUMNS), name
        assert stage(spark, docs.where("false"), str(tmp_path)).count() == 0, name
        assert out.count() >= (0 if name.startswith("quality") else 1), name


def test_near_dedup_goes_by_text_not_by_id(spark, tmp_path):
    import corpus_pipeline as p

    words = lambda s: " ".join(f"{s}{i}" for i in range(40))
    rows = [(None, words("a")), (None, words("b")), (None, words("b")), (7, words("c")), (7, words("d")), (7, words("d")), (9, words("c")), (1, words("e")), (None, words("e")), (2, None), (3, "")]
    docs = spark.createDataFrame([(i, t, "en", None, 1) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    got = sorted(((r.doc_id, (r.text or "")[:1]) for r in p.near_dedup(spark, docs, str(tmp_path)).collect()), key=str)
    assert got == sorted([(None, "a"), (None, "b"), (7, "c"), (7, "d"), (1, "e"), (2, "")], key=str)


def test_long_words_are_folded_like_the_library(spark):
    import base64
    import random

    import tiktoken

    path = public_tokenizers.path("byte_bpe_50k.tiktoken")
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(path, "rb"))}
    library = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    rng = random.Random(11)
    letters = lambda n, of: "".join(rng.choice(of) for _ in range(n))
    texts = [letters(n, of) for n in (47, 48, 49, 300, 1500) for of in ("abcdefgh", "aab", "日本語文字", "éßñabc")]
    texts += ["x" * bytebpe.FOLDED, "y" * (bytebpe.FOLDED + 1), letters(bytebpe.FOLDED + 900, "abc"), "ab" * 10_000, " " + letters(700, "0123") + " " + letters(90, "#$%") + "\n\n  " + letters(60, "α ")]
    got = bytebpe.encode(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), path, public_tokenizers.PATTERN).collect()
    assert {r.doc_id: r.ids for r in got} == {i: library.encode_ordinary(t) for i, t in enumerate(texts)}
    assert all(r.n_tokens == len(r.ids) for r in got)


def test_tasks_give_back_what_they_freed():
    from streamfill.llm.common import light

    held = lambda: int(open("/proc/self/statm").read().split()[1]) * 4096 / 1e6
    pins = []

    def step(batches):
        for batch in batches:
            many = [bytes(600) for _ in range(300_000)]
            pins.append(many[-1])  # lies above what is freed
            yield batch
            del many

    before = held()
    assert list(light(step)(iter([1, 2]))) == [1, 2]
    assert held() - before < 60
    run = light(step)(iter([3, 4]))
    assert next(run) == 3
    run.close()  # a task that is ended early
    assert held() - before < 60


def test_packing_holds_small_chunks_and_packs_the_same(spark, monkeypatch):
    import public_tokenizers

    from streamfill.llm import packing, pieces

    assert 3 * packing.CHUNK <= pieces.CHUNK
    docs = spark.createDataFrame([(k, "one two  three <|endoftext|> four\n" * k) for k in range(9)] + [(9, None)], "doc_id long, text string")
    path, made = public_tokenizers.path("byte_bpe_50k.json"), []
    for size in (packing.CHUNK, 40):
        monkeypatch.setattr(packing, "CHUNK", size)
        made.append(sorted(packing.pack(docs, path, 16).select("doc_id", "start", "length", "ids_crc32", "doc_tokens").collect()))
    assert made[0] == made[1] and {r.doc_id for r in made[0]} == set(range(10))


def test_packing_encodes_a_word_once_in_a_task():
    import numpy as np
    import public_tokenizers
    import pyarrow as pa
    from tokenizers import Tokenizer

    from streamfill.llm import packing
    from streamfill.llm.pieces import chunks

    path = public_tokenizers.path("byte_bpe_50k.json")
    with open(path, encoding="utf-8") as f:
        encoder = packing.Encoder(f.read())
    plain = Tokenizer.from_file(path)
    texts = ["It's one. One, two&&& three.\nFour don't\n five  six \u4e2d\u6587. \u0391\u03b2. x\u00d7y <|endoftext|> a<|endoftext|>. 7th ", "two. two, two! three?  two\n", "", "\u00e9t\u00e9. \u0455\u043b\u043e\u0432\u043e\u0301, e\u0301. a\u0300. _b"]
    batch = lambda: iter([pa.RecordBatch.from_pydict({"i": list(range(len(texts))), "t": texts})])
    seen = []
    for most in (packing.HELD, packing.HELD, 1):
        packing.HELD, before = most, packing.HELD
        for chunk in chunks(batch(), 10):
            flat, starts, sizes = encoder.encoded(chunk)
            got = [[x for p in places for x in flat[starts[p] : starts[p] + sizes[p]]] for places in np.split(chunk.places, np.cumsum(chunk.lengths)[:-1])]
            assert got == [plain.encode(texts[i], add_special_tokens=False).ids for i in chunk.ids]
        packing.HELD = before
        seen.append((encoder.words.made, encoder.tails.made))
    assert seen[0] == seen[1], "held from chunk to chunk"
