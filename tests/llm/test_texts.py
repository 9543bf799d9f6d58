import hashlib
import re
import tarfile
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from eqdict.llm import language, media, near_dedup, pii, setsketch, substring_dedup
from eqdict.llm.common import LOWER, components, window_hashes, word_hashes

WORD = re.compile(r"[^\x20\x09-\x0D]+")


# --- shared pieces ---------------------------------------------------------------------------------------------------------------


def test_word_hashes_depend_on_the_word_only():
    texts = ["a b a", "  a\tb", "", " ", "é a é", "x" * 3_000_000 + " a", "  a\x1c b", "ab ba aab aba"]
    known = {}
    for t in texts:
        words = WORD.findall(t)
        h = word_hashes(t.encode())
        assert len(h) == len(words)
        for w, x in zip(words, h.tolist()):
            assert known.setdefault(w, x) == x
    assert len(set(known.values())) == len(known)


def test_window_hashes_depend_on_the_words_only():
    r = np.random.default_rng(0)
    w = word_hashes(" ".join(map(str, r.integers(0, 3, 3000))).encode())
    for n in (1, 2, 3, 5, 8, 13, 35):
        known = {}
        for i, h in enumerate(window_hashes(w, n).tolist()):
            assert known.setdefault(w[i : i + n].tobytes(), h) == h
        assert len(set(known.values())) == len(known)
    assert len(window_hashes(w, 4000)) == 0


def test_components(spark, tmp_path):
    r = np.random.default_rng(1)
    for k, edges in enumerate([[], [(1, 2)], [(i, i + 1) for i in range(70)], [(0, i) for i in range(1, 200)], [tuple(map(int, r.integers(0, 400, 2))) for _ in range(250)], [(5, 5), (None, 3)]]):
        root = {}

        def find(x, root=root):
            while root.setdefault(x, x) != x:
                x = root[x]
            return x

        for a, b in edges:
            if a is not None:
                x, y = sorted((find(a), find(b)))
                root[y] = x
        got = components(spark.createDataFrame(edges, "a long, b long"), f"file://{tmp_path}/c{k}").collect()
        assert {x.node: x.root for x in got} == {x: find(x) for x in list(root)}
        assert len(got) == len(root)


# --- personal data ---------------------------------------------------------------------------------------------------------------

EMAIL, IP, CARD, PHONE = (re.compile(p) for p in (r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", r"[0-9]([\x20-]?[0-9])+", r"\+[0-9][\x20().0-9-]+[0-9]"))


def plain_spans(t):
    digits = lambda s: re.sub("[^0-9]", "", s)
    luhn = lambda d: sum(int(c) if i % 2 == 0 else sum(divmod(2 * int(c), 10)) for i, c in enumerate(reversed(d))) % 10 == 0
    return {
        "email": [m.span() for m in EMAIL.finditer(t)],
        "ip": [m.span() for m in IP.finditer(t) if all(int(p) <= 255 for p in m.group().split("."))],
        "card": [m.span() for m in CARD.finditer(t) if 16 <= len(digits(m.group())) <= 19 and luhn(digits(m.group()))],
        "phone": [m.span() for m in PHONE.finditer(t) if 8 <= len(digits(m.group())) <= 15],
    }


def test_base_spans(small):
    r = np.random.default_rng(5)
    texts = [*small[1].values(), "a@b.c@d.e.f", "a@b.c+d@e.f", "@x.y a@@b.c", "a@b. c@d", "4111 1111 1111 1111-4111111111111111", "4111-1111-1111-1111", "+1 (2) 3.4-5 6 7 8)", "+1+2 34567890", "1.2.3.4.5.6.7.8", "01.002.0003.255 256.1.1.1"]
    texts += ["".join(r.choice(list("ab01.@+- ()9"), 40)) for _ in range(4000)]
    for t in texts:
        assert pii.base_spans(t) == plain_spans(t), t[:200]


def test_field_learns_and_decodes_exactly():
    f = pii.default_field()
    lines = defaultdict(list)
    for s, _, w, t in pii.labelled_words(seed=1234, sentences=300):
        lines[s].append((w, t))
    right, found, true = 0, 0, 0
    for line in lines.values():
        ids = np.concatenate([[0], f.ids([pii.shapes(w.encode())[0] for w, _ in line]), [0]])
        at, tags = f.decode(ids)
        got = np.zeros(len(line), int)
        got[at - 1] = tags
        assert (pii.viterbi(f.scores(ids, np.arange(1, len(line) + 1))[None], f.moves)[0] == got).all()  # without leaving anything out
        gold = np.array([pii.TAGS.index(t) for _, t in line])
        right, found, true = right + ((got == gold) & (gold > 0)).sum(), found + (got > 0).sum(), true + (gold > 0).sum()
    assert right / found > 0.9 and right / true > 0.9


def test_viterbi_against_all_paths():
    import itertools

    r = np.random.default_rng(0)
    moves = r.normal(size=(4, 4))
    scores = r.normal(size=(5, 4, 4))
    got = pii.viterbi(scores, moves)
    for run in range(5):
        value = lambda p: sum(scores[run, i, t] for i, t in enumerate(p)) + sum(moves[a, b] for a, b in zip((0, *p), (*p, 0)))  # noqa: E731, B023
        assert max(itertools.product(range(4), repeat=4), key=value) == tuple(got[run])


def test_gradient_of_the_likelihood():
    """Against differences, and the value against the sum over all paths."""
    import itertools

    r = np.random.default_rng(4)
    x, w, moves = r.integers(0, 2, (3, 4, 5)).astype(float), r.normal(size=(5, 3)), r.normal(size=(3, 3))
    gold = r.integers(0, 3, (3, 4))
    want, want_moves = np.eye(3)[gold], np.zeros((3, 3))
    for g in gold:
        for a, b in zip((0, *g), (*g, 0)):
            want_moves[a, b] += 1
    value, gw, gm = pii.objective(x, want, want_moves, w, moves, 0.1)
    path = lambda s, p: sum(x[s, i] @ w[:, t] for i, t in enumerate(p)) + sum(moves[a, b] for a, b in zip((0, *p), (*p, 0)))
    plain = sum(path(s, gold[s]) - np.log(sum(np.exp(path(s, p)) for p in itertools.product(range(3), repeat=4))) for s in range(3))
    assert abs(value - (plain - 0.05 * ((w**2).sum() + (moves**2).sum()))) < 1e-9
    for theta, grad in ((w, gw), (moves, gm)):
        for i in np.ndindex(theta.shape):
            step = np.zeros_like(theta)
            step[i] = 1e-6
            up, down = (pii.objective(x, want, want_moves, *((w + k * step, moves) if theta is w else (w, moves + k * step)), 0.1)[0] for k in (1, -1))
            assert abs((up - down) / 2e-6 - grad[i]) < 1e-5


def test_spans_apart():
    r = np.random.default_rng(6)
    for _ in range(300):
        spans = lambda n: [(int(a), int(a) + int(r.integers(1, 9))) for a in r.integers(0, 60, n)]
        taken, added = spans(int(r.integers(0, 8))), [("x", a, b) for a, b in spans(6)]
        assert pii.apart(added, taken) == [x for x in added if not any(a < x[2] and x[1] < b for a, b in taken)]


def test_thousands_of_entities_in_a_text(spark):
    one = lambda i: f'é token = "{hashlib.sha1(str(i).encode()).hexdigest()}" a{i}@b.cd und 10.0.{i % 200}.1 '
    n = 20_000
    text = "".join(map(one, range(n)))
    (got,) = pii.personal_data(spark.createDataFrame([(1, text)], "doc_id long, text string")).collect()
    assert (got.n_email, got.n_ip) == (n, n) and got.n_field == n - got.n_card  # a card number by chance is a base span, which stays
    _, a, b = got.spans.split(",")[-1].split(":")
    assert hashlib.sha1(str(n - 1).encode()).hexdigest() == text[int(a) : int(b)]


def test_personal_data(edge, empty, small):
    df, texts = small
    for r in pii.personal_data(df).collect():
        base = plain_spans(texts[r.doc_id])
        assert (r.n_email, r.n_ip, r.n_card, r.n_phone) == tuple(map(len, base.values()))
        joined = ",".join(f"{k}:{a}:{b}" for k, v in base.items() for a, b in v)
        assert r.base_sha256 == hashlib.sha256(joined.encode()).hexdigest() and r.spans.startswith(joined)
        for s in filter(None, r.spans.split(",")[sum(map(len, base.values())) :]):
            kind, a, b = s.split(":")
            assert kind in pii.FIELD_KINDS and 0 <= int(a) < int(b) <= len(texts[r.doc_id])
    assert pii.personal_data(edge).count() == edge.count() and pii.personal_data(empty).count() == 0


def test_field_finds_secrets_and_leaves_prose(spark):
    key = hashlib.sha1(b"x").hexdigest()
    docs = spark.createDataFrame([(1, f'und é wh token = "{key}" an the.'), (2, "Le chat était là. 1999, 12:30 and 2024-01-02 on 3.14 it | was = fine; see (5) 100% ok"), (3, f"a@b.cd {key} 10.0.0.1")], "doc_id long, text string")
    got = {r.doc_id: r.spans for r in pii.personal_data(docs).collect()}
    at = f'und é wh token = "{key}'.index(key)
    assert got[1] == f"secret:{at}:{at + 40}" and got[2] == "" and got[3] == "email:0:6,ip:48:56,secret:7:47"


def test_bound_of_the_shape_table_changes_nothing():
    """Numbers of shapes hold for all texts of a group, however many shapes it has."""
    f = pii.default_field()
    tight, wide = (pii.Field(f.names, f.weights, f.moves) for _ in range(2))
    tight.most_shapes = 5
    r = np.random.default_rng(3)
    odd = lambda: "".join(r.choice(list("aA1-/"), int(r.integers(1, 30))))
    texts = [" ".join(w for i in range(12) for w in (odd(), "token", "=", f'"{hashlib.sha1(bytes([t, i])).hexdigest()}"', odd(), "123-45-6789")) for t in range(30)]
    groups = [texts[i : i + 6] for i in range(0, 30, 6)]
    found = [pii.found_in(g, tight) for g in groups]
    assert found == [pii.found_in(g, wide) for g in groups] and sum(len(added) for g in found for _, added in g) > 300
    assert len(tight.at) < len(wide.at)  # made anew between groups


# --- language --------------------------------------------------------------------------------------------------------------------


def plain_ngrams(text):
    out = Counter()
    for word in re.findall(r"[^\W\d_]+", text.lower()):
        padded = f"_{word}_"
        for c in word:
            out[c] += 1
        for n in (2, 3):
            for i in range(len(padded) - n + 1):
                if n == 2 or padded[i + 1] != "_":
                    out[padded[i : i + n]] += 1
    return out


def plain_order(g):
    """Shorter n-grams first, then by letters: word ends, FIRST, the rest by code point."""
    return len(g), [(0, 0) if c == "_" else (1, language.FIRST.index(c)) if c in language.FIRST else (2, ord(c)) for c in g]


def plain_list(counts, top):
    return sorted(counts, key=lambda g: (-counts[g], plain_order(g)))[:top]


def test_ngrams_are_those_of_padded_words():
    for t in ("Hello, wörld! a", "aaa bb c-d'e", "", "123 !", "éé", "Привет мир", "日本語 のテキスト a", "ab " * 60_000):
        codes, n = language.ngrams(t)
        want = plain_ngrams(t)
        assert (np.diff(codes) > 0).all() and len(codes) == len(want)
        assert [(len(g), c) for g, c in sorted(want.items(), key=lambda x: plain_order(x[0]))] == [(language.gram(c)[0], k) for c, k in zip(codes.tolist(), n.tolist())]


def test_out_of_place_distance():
    both = {"fr": "le chat est sur le tapis", "en": "the cat sat on the mat", "el": "η γάτα κάθισε στο χαλί"}
    p = language.Profiles(list(both), [language.ranked(*language.ngrams(t), 50) for t in both.values()], 50)
    lists = {k: plain_list(plain_ngrams(t), 50) for k, t in sorted(both.items())}
    assert p.names == sorted(both)
    for text in ("the cat", "le chat", "zzz", "γάτα"):
        mine = plain_list(plain_ngrams(text), 50)
        far = {k: sum(abs(x.index(g) - i) if g in x else 50 for i, g in enumerate(mine)) for k, x in lists.items()}
        want = min(far, key=lambda k: (far[k], k))
        lang, score = p.judge(text)
        assert lang == want and abs(score - (1 - far[want] / (50 * len(mine)))) < 1e-12


def test_languages_against_plain_profiles(small):
    """The whole query, its sample being all labelled documents, against lists of strings."""
    df, texts = small
    lang = {r.doc_id: r.lang for r in df.select("doc_id", "lang").collect()}
    total = defaultdict(Counter)
    for d, t in texts.items():
        if zlib.crc32(str(d).encode()) % 4 != 2 and lang[d] is not None:
            total[lang[d]].update(plain_ngrams(t))
    lists = {k: {g: i for i, g in enumerate(plain_list(c, 300))} for k, c in sorted(total.items())}
    for r in language.languages(df, sample=10**9).collect():
        mine = plain_list(plain_ngrams(texts[r.doc_id]), 300)
        if not mine:
            assert (r.lang_pred, r.score) == ("und", 0.0)
            continue
        far = {k: sum(abs(x[g] - i) if g in x else 300 for i, g in enumerate(mine)) for k, x in lists.items()}
        want = min(far, key=lambda k: (far[k], k))
        assert r.lang_pred == want and abs(r.score - (1 - far[want] / (300 * len(mine)))) < 1e-9


SCRIPTS = {
    "ru": ["Вчера мы долго гуляли по старому городу и говорили о книгах, которые она читала", "Сегодня утром шёл дождь, и мы остались дома; все были рады, что никуда не нужно ехать", "Она сказала, что вернётся завтра вечером"],
    "uk": ["Вчора ми довго гуляли старим містом і говорили про книжки, які вона читала", "Сьогодні вранці йшов дощ, і ми залишилися вдома; всі були раді, що нікуди не треба їхати", "Вона сказала, що повернеться завтра ввечері"],
    "el": ["Χθες περπατήσαμε πολλή ώρα στην παλιά πόλη", "Σήμερα το πρωί έβρεχε και μείναμε στο σπίτι", "Είπε ότι θα γυρίσει αύριο το βράδυ"],
    "ar": ["مشينا أمس طويلا في المدينة القديمة وتحدثنا عن الكتب", "كان المطر يهطل هذا الصباح فبقينا في البيت", "قالت إنها ستعود غدا في المساء"],
    "fa": ["دیروز مدت زیادی در شهر قدیمی قدم زدیم و درباره کتاب‌ها گفتگو کردیم", "امروز صبح باران می‌آمد و ما در خانه ماندیم", "او گفت که فردا شب برمی‌گردد"],
    "zh": ["昨天我们在老城里走了很久，谈了很多书", "今天早上下雨，我们留在家里", "她说她明天晚上回来"],
    "ja": ["昨日は古い町を長く歩いて、本の話をしました", "今朝は雨が降っていたので、家にいました", "彼女は明日の夜に帰ると言いました"],
}


def test_letters_of_other_scripts_keep_their_identity(spark):
    ids = [i for i in range(1, 200) if zlib.crc32(str(i).encode()) % 4 != 2]
    asked = [i for i in range(1, 200) if zlib.crc32(str(i).encode()) % 4 == 2]
    rows = [(ids.pop(), t, k) for k, (a, b, _) in SCRIPTS.items() for t in (a, b)] + [(asked.pop(), c, k) for k, (_, _, c) in SCRIPTS.items()]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    want = {d: k for d, _, k in rows}
    got = language.languages(df).where("held_out").collect()
    assert len(got) == 7 and {r.doc_id: r.lang_pred for r in got} == {r.doc_id: want[r.doc_id] for r in got}
    bare = df.withColumn("lang", F.lit(None).cast("string")).unionByName(spark.createDataFrame([(900, "12 !", None), (901, None, None)], df.schema))
    assert language.of_known_language(bare).count() == len(rows)  # nothing to judge by: all with a letter
    many = spark.range(300).select("id", F.lit("abc").alias("_text"), F.concat(F.lit("l"), "id").alias("_lang")).withColumnRenamed("id", "_id")
    assert len(language.fit(many).names) == 300


def test_held_out_accuracy(small, edge, empty):
    df, texts = small
    lang = {r.doc_id: r.lang for r in df.select("doc_id", "lang").collect()}
    got = language.languages(df).collect()
    held = [r for r in got if r.held_out]
    assert len(got) == len(texts) and all((zlib.crc32(str(r.doc_id).encode()) % 4 == 2) == r.held_out and 0 <= r.score <= 1 for r in got)
    assert sum(r.lang_pred == lang[r.doc_id] for r in held) / len(held) > 0.95
    odd = {r.doc_id: r for r in language.languages(edge).collect()}
    assert odd[3].lang_pred == odd[4].lang_pred == odd[9].lang_pred == "und" and odd[10].lang_pred != "und"
    assert language.languages(empty).count() == 0
    assert {r.lang_pred for r in language.languages(edge.withColumn("lang", F.lit(None).cast("string"))).collect()} == {"und"}
    kept = language.of_known_language(edge)
    assert kept.columns == edge.columns and sorted(r.doc_id or 0 for r in kept.collect()) == [0, 1, 2, 6, 7, 8, 8, 10, 11]


def test_labels_of_held_out_rows_do_not_matter(small):
    df, _ = small
    wrong = df.withColumn("lang", F.when(language.held_out("doc_id"), F.lit("zz")).otherwise(F.col("lang")))
    assert sorted(map(tuple, language.languages(df).collect())) == sorted(map(tuple, language.languages(wrong).collect()))


# --- media -----------------------------------------------------------------------------------------------------------------------


def test_png_round_trip():
    for data in (b"", b"a", b"x" * 64, bytes(range(256)) * 9):
        payload = media.padded(data)
        assert len(payload) % 64 == 0 and payload[: len(data)] == data and not payload[len(data) :].strip(b"\0")
        image = media.to_png(payload)
        assert media.from_png(image) == payload and media.png_header(image[: media.HEADER_BYTES]) == (64, len(payload) // 64, 8)
    with pytest.raises(ValueError):
        media.png_header(b"\x89PNG" + bytes(40))


def test_media_columns(spark, edge, empty, small, tmp_path):
    folder = f"file://{tmp_path}/m"
    df = edge.unionByName(small[0].limit(30), allowMissingColumns=True)
    rows = media.media_columns(df, folder).collect()
    want = Counter((r.doc_id, r.text or "") for r in df.collect())
    assert len(rows) == sum(want.values())
    by_text = {}
    texts = defaultdict(set)
    for d, t in want:
        texts[d].add(hashlib.sha256(media.padded(t.encode())).hexdigest())
    for r in rows:
        assert r.payload_sha256 in texts[r.doc_id]
        same = tuple(r[c] for c in r.__fields__ if c != "doc_id")
        assert by_text.setdefault(r.payload_sha256, same) == same
        with tarfile.open(f"{tmp_path}/m/shards/{r.shard}") as tar:
            stored = tar.extractfile(f"{r.payload_sha256}.png").read()
        assert hashlib.sha256(stored).hexdigest() == r.media_sha256 and len(stored) == r.media_bytes
        with open(f"{tmp_path}/m/shards/{r.shard}", "rb") as f:
            f.seek(r.at)
            assert f.read(r.media_bytes) == stored
        payload = media.from_png(stored)
        assert r.tail_crc32 == zlib.crc32(payload[-64:]) and r.payload_bytes == len(payload) and r.feature == media.feature(payload)
    places = media.places(spark.read.parquet(f"{folder}/places"))
    heads = media.headers(places, folder).collect()
    assert {(h.width, h.height, h.bits) for h in heads} == {(64, r.payload_bytes // 64, 8) for r in rows}
    assert media.media_columns(empty).count() == 0


def test_metadata_columns_come_from_headers(spark, tmp_path, monkeypatch):
    """The query reads each header by itself before the whole range."""
    asked, own = [], media.headers
    monkeypatch.setattr(media, "headers", lambda at, folder: asked.append(folder) or own(at, folder))
    docs = spark.createDataFrame([(1, "some text " * 30), (2, None)], "doc_id long, text string")
    got = {(r.doc_id, r.width, r.height, r.bits) for r in media.media_columns(docs, f"file://{tmp_path}/q").collect()}
    assert asked and got == {(1, 64, 5, 8), (2, 64, 1, 8)}


def test_damage_is_noticed(spark, tmp_path):
    folder = f"file://{tmp_path}/d"
    docs = spark.createDataFrame([(1, "some text " * 30)], "doc_id long, text string")
    at = media.places(media.stored(docs, folder))
    (shard,) = (tmp_path / "d" / "shards").iterdir()
    data = bytearray(shard.read_bytes())
    data[512 + 60] ^= 1
    shard.write_bytes(data)
    for crc in shard.parent.glob(".*.crc"):
        crc.unlink()
    with pytest.raises(Exception, match="damaged|zlib|incorrect|invalid|Error"):
        media.facts(at, folder).collect()


# --- repeated windows ------------------------------------------------------------------------------------------------------------


def plain_repeats(docs, n):
    words = [WORD.findall(t or "") for _, t in docs]
    seen = Counter(tuple(w[i : i + n]) for w in words for i in range(len(w) - n + 1))
    out = []
    for (d, _), w in zip(docs, words):
        gone = [False] * len(w)
        for i in range(len(w) - n + 1):
            if seen[tuple(w[i : i + n])] > 1:
                gone[i : i + n] = [True] * n
        left = " ".join(x for x, g in zip(w, gone) if not g)
        out.append((d, len(w), sum(gone), hashlib.sha256(left.encode()).hexdigest(), left))
    return sorted(out, key=repr)


@pytest.mark.parametrize(("window", "start", "block", "part"), [(35, 9, 16 << 20, 4_000_000), (35, 35, 20_000, 50), (4, 1, 5_000, 1000), (1, 9, 5_000, 10**6), (5, 2, 1, 300)])
def test_windows(small, window, start, block, part):
    df, texts = small
    docs = list(texts.items())[:60]
    got = substring_dedup.without_repeats(df.where(F.col("doc_id").isin([d for d, _ in docs])), window, start, with_text=True, block_bytes=block, part_hashes=part)
    assert sorted(map(tuple, got.collect()), key=repr) == plain_repeats(docs, window)


def test_windows_of_odd_rows(spark, edge, empty):
    docs = [(r.doc_id, r.text) for r in edge.collect()]
    assert sorted(map(tuple, substring_dedup.without_repeats(edge, with_text=True).collect()), key=repr) == plain_repeats(docs, 35)
    assert substring_dedup.without_repeats(empty).count() == 0
    same = [(1, "a " * 100), (2, "b " * 34), (3, "c " * 35), (4, " ".join(map(str, range(200))) + " " + " ".join(map(str, range(40))))]
    df = spark.createDataFrame(same, "doc_id long, text string")
    assert sorted(map(tuple, substring_dedup.without_repeats(df, with_text=True).collect()), key=repr) == plain_repeats(same, 35)


def test_blocks_of_few_words(spark):
    """Blocks of 1 to 40 words, one document each, of which some repeat."""
    docs = [(n, " ".join(f"w{i}" for i in range(n))) for n in range(1, 41)]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    assert sorted(map(tuple, substring_dedup.without_repeats(df, with_text=True, block_bytes=1).collect()), key=repr) == plain_repeats(docs, 35)


def test_levels():
    assert substring_dedup.levels(35, 9) == [9, 18, 35] and substring_dedup.levels(35, 50) == [35] and substring_dedup.levels(8, 1) == [1, 2, 4, 8]


# --- near copies -----------------------------------------------------------------------------------------------------------------


def plain_groups(docs, k, percent):
    sets = []
    for _, t in docs:
        w = WORD.findall((t or "").encode().translate(LOWER).decode())
        sets.append(frozenset(tuple(w[i : i + k]) for i in range(len(w) - k + 1)) if len(w) >= k else frozenset([tuple(w)] if w else []))
    root = {d: d for d, _ in docs}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, (a, _) in enumerate(docs):
        for j in range(i):
            b, s, t = docs[j][0], sets[i], sets[j]
            if a is not None and b is not None and s and t and 100 * len(s & t) >= percent * len(s | t):
                x, y = sorted((find(a), find(b)))
                root[y] = x
    return sorted(((d, len(s), None if d is None else find(d), d is None or find(d) == d) for (d, _), s in zip(docs, sets)), key=repr)


@pytest.mark.parametrize(("k", "percent"), [(3, 85), (5, 80)])
def test_near_groups(small, k, percent):
    df, texts = small
    assert sorted(map(tuple, near_dedup.near_groups(df, k, percent).collect()), key=repr) == plain_groups(list(texts.items()), k, percent)


def test_chains_and_odd_rows(spark, edge, empty):
    r = np.random.default_rng(0)
    base, docs = [f"w{i}" for i in range(120)], []
    for i in range(150):  # each near its neighbours only, and one family of scattered copies
        docs.append((1000 - i, " ".join(base)))
        base[int(r.integers(0, 120))] = f"n{i}"
    for i in range(200):
        copy = [f"q{j}" for j in range(90)]
        for _ in range(int(r.integers(0, 5))):
            copy[int(r.integers(0, 90))] = f"z{i}"
        docs.append((2000 + i, " ".join(copy)))
    docs += [(7, "A b c d"), (7, "x y z w"), (6, "a B c d"), (5, "x y z w"), (None, "a b c d")]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    assert sorted(map(tuple, near_dedup.near_groups(df, 3, 85).collect()), key=repr) == plain_groups(docs, 3, 85)
    odd = [(x.doc_id, x.text) for x in edge.collect()]
    got = sorted(map(tuple, near_dedup.near_groups(edge, 3, 85).collect()), key=repr)
    assert got == plain_groups(odd, 3, 85)
    assert near_dedup.near_groups(empty).count() == 0
    kept = near_dedup.near_distinct(edge, 3, 85)
    assert kept.columns == edge.columns and kept.count() == sum(1 for x in got if x[3])


@pytest.mark.parametrize(("block", "size"), [(7, near_dedup.SLICE), (256, 50), (5, 20)])
def test_blocks_and_slices(spark, block, size):
    """Families with members of several sizes, in small units and sets in slices."""
    r = np.random.default_rng(4)
    docs = []
    for i in range(160):
        copy = [f"q{i % 3}x{j}" for j in range(60 + 8 * int(r.integers(0, 3)))]
        for _ in range(int(r.integers(0, 5))):
            copy[int(r.integers(0, 60))] = f"z{i}"
        docs.append((i, " ".join(copy)))
    docs += [(200, docs[0][1]), (200, docs[0][1]), (200, docs[1][1]), (201, docs[1][1] + " end")]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    got = sorted(map(tuple, near_dedup.near_groups(df, 3, 85, block=block, size=size).collect()), key=repr)
    want = plain_groups(docs, 3, 85)
    assert got == want and len({x[2] for x in want}) > 20


def test_levels_of_slices(spark):
    ns = [1, 9, 10, 11, 20, 21, 39, 40, 41, 80, 81, 10**9]
    got = [r[0] for r in spark.createDataFrame([(n,) for n in ns], "n long").coalesce(1).select(near_dedup.level_col(F.col("n"), 10)).collect()]
    assert got == [near_dedup.slice_level(n, 10) for n in ns] and got[:9] == [0, 0, 0, 1, 1, 2, 2, 2, 3]


def test_estimates_rule_out_almost_no_link():
    """Pairs at a threshold: share of those whose estimate falls below what the second stage asks for."""
    r = np.random.default_rng(8)
    for percent in (50, 80, 85, 90):
        n, low = 400, 0
        both = -(-2 * n * percent // (100 + percent))
        for _ in range(300):
            a, b, c = (r.integers(0, 1 << 63, m, dtype=np.uint64) for m in (both, n - both, n - both))
            u, v = (np.frombuffer(s, "<u2")[None] for s in setsketch.sketches([np.unique(np.concatenate([a, b])), np.unique(np.concatenate([a, c]))]))
            low += setsketch.joint_estimate(u, v, np.array([n]), np.array([n]))[0] < setsketch.surely(percent / 100)
        assert low == 0


def doubling(n):
    """Two words of 2^n characters, made of the same two letters by doubling."""
    a, b = "a", "b"
    for _ in range(n):
        a, b = a + b, b + a
    return a, b


def test_words_of_doubling_sequences_differ(spark):
    """Sums over a word's bytes, modulo a power of two, cannot tell these words apart."""
    words = [w for n in range(3, 14) for w in doubling(n)]
    for seed in (0, 1):
        assert len(set(word_hashes(" ".join(words).encode(), seed).tolist())) == len(words)
    for n in (10, 11, 12, 13):
        a, b = doubling(n)
        docs = spark.createDataFrame([(1, " ".join([a, *(f"w{i}" for i in range(34))])), (2, " ".join([b, *(f"w{i}" for i in range(34))])), (3, f"{a} {a} {b}"), (4, f"{b} {b} {a}")], "doc_id long, text string")
        assert {r.doc_id: r.n_removed for r in substring_dedup.without_repeats(docs).collect()} == {1: 0, 2: 0, 3: 0, 4: 0}
        assert all(r.kept for r in near_dedup.near_groups(docs.where("doc_id > 2"), 3, 85).collect())


def test_sketches():
    r = np.random.default_rng(2)
    for n in (1, 3, 40, 3000):
        a, b, c = (r.integers(0, 1 << 63, n, dtype=np.uint64) for _ in range(3))
        x, y = np.unique(np.concatenate([a, b])), np.unique(np.concatenate([b, c]))
        sx, sy, su, none = setsketch.sketches([x, y, np.unique(np.concatenate([a, b, c])), np.zeros(0, np.uint64)])
        assert setsketch.merged(sx, sy) == su and none is None
        assert setsketch.sketches([y, x])[1] == sx  # whatever else is in the batch
    errors = []
    for i in range(60):
        both, own = int(r.integers(0, 500)), 300
        a, b, c = (r.integers(0, 1 << 63, m, dtype=np.uint64) for m in (both, own, own))
        x, y = np.unique(np.concatenate([a, b])), np.unique(np.concatenate([a, c]))
        u, v = (np.frombuffer(s, "<u2")[None] for s in setsketch.sketches([x, y]))
        errors.append(setsketch.joint_estimate(u, v, np.array([len(x)]), np.array([len(y)]))[0] - both / (both + 2 * own))
    assert abs(np.mean(errors)) < 0.015 and np.std(errors) < 0.05
    assert abs(setsketch.equal_chance(1.0) - 1) < 1e-9 and setsketch.equal_chance(0.85) > 0.84


def test_bands_miss_almost_nothing():
    for percent in (20, 30, 40, 50, 60, 70, 80, 85, 90, 95):
        rows, bands = near_dedup.band_rows(percent)
        assert rows * bands <= setsketch.REGISTERS
        assert (1 - setsketch.equal_chance(percent / 100) ** rows) ** bands < 1e-6


def test_distinct_pairs():
    r = np.random.default_rng(0)
    for more in (None, np.zeros(500, np.uint32), r.integers(0, 3, 500).astype(np.uint32)):
        code = r.integers(0, 40, 500, dtype=np.uint64)
        order, starts, group = substring_dedup.distinct(code, more)
        pairs = list(zip(code.tolist(), (more if more is not None else code).tolist()))
        assert len(starts) == len(set(pairs)) and len({(p, g) for p, g in zip(pairs, group.tolist())}) == len(starts)
        assert (group[order] == np.sort(group)).all() and (code[order] == np.sort(code)).all()
