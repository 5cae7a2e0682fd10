"""The ten operators against brute force, on whole small tables."""

import dataclasses
import hashlib
import itertools
import math
import re
import time
import zlib
from collections import Counter

import duckdb
import numpy as np
import pandas as pd
import pytest
import xxhash
from hypothesis import given, settings
from hypothesis import strategies as st

from tests.llm.hand_pages import PAGES
from tests.twins import assert_twin, rows_of
from vecroute.llm import boosting, collisions, fertility, labeller, licences, mixing, packing, page_maker, sharding, simhash, templates, words
from vecroute.llm.components import Forest, components
from vecroute.llm.queries import HOSTILE, ORACLES, QUERIES
from vecroute.runtime import Workspace, table


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_twin(spark, sf, name):
    assert_twin(spark, sf, QUERIES[name], ORACLES[name])


# 1 ---------------------------------------------------------------------------------------------


def slow_base(text):
    w = re.findall(r"[^\x20\x09-\x0D]+", text or "")
    grams = [tuple(w[i : i + 3]) for i in range(len(w) - 2)]
    n = Counter(grams)
    hit = {i + j for i, g in enumerate(grams) if n[g] > 1 for j in range(3)}
    lines = (text or "").split("\n")
    dup = sum(1 for i, x in enumerate(lines) if re.search(r"[^\x20\x09-\x0D]", x) and x in lines[:i])
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", text or "")), dup, len(hit)


@settings(max_examples=200, deadline=None)
@given(st.text(alphabet="ab \n\t \u0085é#", max_size=60))
def test_base_statistics(text):
    w = words.words_of(text)
    got = len(w), len(text) - sum(map(text.count, " \t\n\v\f\r")), words.symbol_count(text), words.duplicate_lines(text), words.repeated_window_words(w)
    assert got == slow_base(text)


def test_op1_whole_table(spark, sf):
    from tokenizers import Tokenizer

    got = QUERIES["op1_fertility_rules"](spark, sf).toPandas().set_index("doc_id")
    docs = table(spark, sf, "documents").toPandas()
    bpe = Tokenizer.from_file(fertility.vocabulary_path("byte_bpe_50k.json"))
    bpe.encode_special_tokens = True
    for r in docs.itertuples():
        g, base = got.loc[r.doc_id], slow_base(r.text)
        assert (g.n_words, g.word_chars, g.n_symbols, g.n_dup_lines, g.n_repeat_words) == base
        assert g.base_failed == (base[0] < 50 or 100 * base[4] > 50 * base[0])
        assert not (g.kept and g.base_failed)
        assert g.n_tokens == len(bpe.encode(r.text, add_special_tokens=False).ids)
    labels = table(spark, sf, "labels").toPandas().set_index("doc_id").join(got)
    clean = labels[(labels.quality == 1) & ~labels.base_failed]
    assert clean.kept.all()
    assert not labels[labels.quality == 0].kept.any()


#: Ordinary prose, written for this test: a story and an official notice in each listed language.
PROSE = [
    ('en', 'The morning train was late again, so we stood on the platform and talked about the weather, the price of bread and the new bridge that the council had promised for years. An old man with a brown dog told us that he remembered the first bridge, which had been washed away by a flood when he was a boy. Nobody quite believed him, but it was a good story, and it made the waiting easier. When the train finally came, we found seats near the window and watched the fields go by until the city appeared behind the hills.'),
    ('fr', "Ce matin, le train était encore en retard, alors nous avons attendu sur le quai en parlant du temps, du prix du pain et du nouveau pont que la mairie promet depuis des années. Un vieil homme avec un chien brun nous a raconté qu'il se souvenait du premier pont, emporté par une crue quand il était enfant. Personne ne le croyait vraiment, mais c'était une belle histoire, et l'attente nous a paru moins longue. Quand le train est enfin arrivé, nous avons trouvé des places près de la fenêtre."),
    ('de', 'Heute Morgen hatte der Zug wieder Verspätung, also standen wir auf dem Bahnsteig und sprachen über das Wetter, den Brotpreis und die neue Brücke, die der Gemeinderat seit Jahren verspricht. Ein alter Mann mit einem braunen Hund erzählte uns, dass er sich noch an die erste Brücke erinnern könne, die ein Hochwasser fortgerissen habe, als er ein kleiner Junge war. Niemand glaubte ihm so recht, aber es war eine gute Geschichte, und das Warten fiel uns leichter. Als der Zug endlich kam, fanden wir Plätze am Fenster.'),
    ('es', 'Esta mañana el tren llegó tarde otra vez, así que esperamos en el andén hablando del tiempo, del precio del pan y del puente nuevo que el ayuntamiento promete desde hace años. Un hombre mayor con un perro marrón nos contó que todavía recordaba el primer puente, que una inundación se llevó cuando él era niño. Nadie le creyó del todo, pero era una buena historia y la espera se hizo más corta. Cuando por fin llegó el tren, encontramos asientos junto a la ventana y miramos los campos.'),
    ('en', 'Applicants must submit the completed form, together with a copy of their passport and two recent photographs, to the regional office no later than the last working day of March. Incomplete applications will be returned without examination. The fee is not refundable; it covers the cost of processing and cannot be waived except in cases of documented hardship. Successful candidates will be informed in writing within six weeks, and the decision may be appealed once.'),
    ('fr', "Les candidats doivent remettre le formulaire rempli, accompagné d'une copie du passeport et de deux photographies récentes, au bureau régional au plus tard le dernier jour ouvrable de mars. Les dossiers incomplets seront renvoyés sans examen. Les frais ne sont pas remboursables ; ils couvrent le traitement de la demande et ne peuvent être supprimés qu'en cas de difficulté établie. Les personnes retenues seront informées par écrit dans un délai de six semaines."),
    ('de', 'Bewerberinnen und Bewerber müssen das ausgefüllte Formular zusammen mit einer Kopie des Reisepasses und zwei neueren Lichtbildern spätestens am letzten Werktag im März bei der Bezirksverwaltung einreichen. Unvollständige Unterlagen werden ohne Prüfung zurückgesandt. Die Bearbeitungsgebühr ist nicht erstattungsfähig; sie deckt die Verwaltungskosten und kann nur in nachgewiesenen Härtefällen erlassen werden. Erfolgreiche Personen werden innerhalb von sechs Wochen schriftlich benachrichtigt und können einmal Widerspruch gegen die Entscheidung einlegen.'),
    ('es', 'Las personas interesadas deben presentar el formulario completo, junto con una copia del pasaporte y dos fotografías recientes, en la oficina regional a más tardar el último día hábil de marzo. Las solicitudes incompletas serán devueltas sin examen. La tasa no es reembolsable; cubre los gastos de tramitación y solo puede suprimirse en casos de dificultad acreditada. Las personas seleccionadas recibirán una notificación por escrito en un plazo de seis semanas.'),
]


#: The same story in other scripts and in languages without a band of their own; words are set apart by spaces, as the base rules count them.
OTHER_PROSE = [
    ('ar', 'في الصباح وصل القطار متأخرا مرة أخرى فوقفنا على الرصيف نتحدث عن الطقس وثمن الخبز والجسر الجديد الذي وعدت به البلدية منذ سنوات طويلة. أخبرنا رجل عجوز معه كلب بني أنه ما زال يتذكر الجسر الأول الذي جرفه الفيضان عندما كان طفلا صغيرا. لم يصدقه أحد تماما لكنها كانت قصة جميلة وجعلت الانتظار أسهل علينا. وعندما وصل القطار أخيرا وجدنا مقاعد قرب النافذة ونظرنا إلى الحقول حتى ظهرت المدينة خلف التلال البعيدة.'),
    ('zh', '今天 早上 火车 又 晚点 了 , 我们 站 在 月台 上 谈论 天气 、 面包 的 价格 和 市政府 多年 来 承诺 修建 的 新 桥 。 一位 带着 棕色 小狗 的 老人 告诉 我们 , 他 还 记得 第一座 桥 , 那座 桥 在 他 小时候 被 洪水 冲走 了 。 没有 人 完全 相信 他 , 但 这 是 一个 好 故事 , 让 等待 变得 轻松 。 火车 终于 来 了 , 我们 在 窗边 找到 座位 , 看着 田野 , 直到 城市 出现 在 山 后面 。'),
    ('ru', 'Сегодня утром поезд снова опоздал, поэтому мы стояли на платформе и говорили о погоде, о ценах на хлеб и о новом мосте, который город обещает построить уже много лет. Старик с коричневой собакой рассказал нам, что помнит первый мост, который унесло наводнением, когда он был мальчиком. Никто ему особенно не поверил, но история была хорошая, и ждать стало легче. Когда поезд наконец пришёл, мы нашли места у окна и смотрели на поля, пока за холмами не показался город.'),
    ('ja', '今朝 も 電車 は 遅れ 、 私たち は ホーム に 立って 天気 や パン の 値段 、 そして 町 が 何年 も 前 から 約束 して いる 新しい 橋 に ついて 話し ました 。 茶色 の 犬 を 連れた 老人 が 、 子ども の ころ に 洪水 で 流された 最初 の 橋 を 覚えて いる と 言い ました 。 誰 も 本気 に は しません でした が 、 いい 話 で 、 待つ 時間 が 短く 感じ られ ました 。 やっと 電車 が 来て 、 窓 の そば に 座り ました 。'),
    ('ko', '오늘 아침에도 기차가 늦어서 우리는 승강장에 서서 날씨와 빵 값, 그리고 시에서 몇 년 동안 약속한 새 다리에 대해 이야기했다. 갈색 개를 데리고 온 한 노인이 자기가 어렸을 때 홍수에 떠내려간 첫 번째 다리를 아직도 기억한다고 말했다. 아무도 그 말을 다 믿지는 않았지만 좋은 이야기였고 기다리는 시간이 한결 짧게 느껴졌다. 마침내 기차가 들어왔고 우리는 창가에 자리를 잡고 앉아 언덕 너머로 도시가 나타날 때까지 들판을 바라보았다. 집에 도착하니 이미 밤이 깊었다.'),
    ('hi', 'आज सुबह रेलगाड़ी फिर देर से आई, इसलिए हम प्लेटफ़ॉर्म पर खड़े होकर मौसम, रोटी के दाम और उस नए पुल के बारे में बातें करते रहे जिसका वादा नगरपालिका कई सालों से कर रही है। भूरे कुत्ते के साथ आए एक बूढ़े आदमी ने बताया कि उसे पहला पुल अब भी याद है, जो उसके बचपन में बाढ़ में बह गया था। किसी ने उस पर पूरा विश्वास नहीं किया, पर कहानी अच्छी थी और इंतज़ार आसान हो गया।'),
    ('el', 'Σήμερα το πρωί το τρένο άργησε πάλι, έτσι σταθήκαμε στην αποβάθρα και μιλούσαμε για τον καιρό, την τιμή του ψωμιού και την καινούργια γέφυρα που υπόσχεται ο δήμος εδώ και χρόνια. Ένας γέρος με έναν καφέ σκύλο μάς είπε ότι θυμάται ακόμα την πρώτη γέφυρα, που την παρέσυρε η πλημμύρα όταν ήταν παιδί. Κανείς δεν τον πίστεψε εντελώς, αλλά ήταν ωραία ιστορία και η αναμονή έγινε πιο εύκολη.'),
    ('it', "Stamattina il treno era di nuovo in ritardo, così abbiamo aspettato sul marciapiede parlando del tempo, del prezzo del pane e del nuovo ponte che il comune promette da anni. Un vecchio con un cane marrone ci ha raccontato che ricordava ancora il primo ponte, portato via da una piena quando era bambino. Nessuno gli ha creduto davvero, ma era una bella storia e l'attesa è sembrata più breve. Quando finalmente il treno è arrivato abbiamo trovato posto vicino al finestrino."),
    ('pl', 'Dziś rano pociąg znowu się spóźnił, więc staliśmy na peronie i rozmawialiśmy o pogodzie, cenach chleba i nowym moście, który miasto obiecuje od lat. Stary człowiek z brązowym psem opowiedział nam, że pamięta jeszcze pierwszy most, który zabrała powódź, kiedy był chłopcem. Nikt mu do końca nie uwierzył, ale była to dobra historia i czekanie stało się łatwiejsze. Kiedy pociąg wreszcie przyjechał, znaleźliśmy miejsca przy oknie i patrzyliśmy na pola.'),
    ('vi', 'Sáng nay tàu lại đến muộn nên chúng tôi đứng trên sân ga nói chuyện về thời tiết, giá bánh mì và cây cầu mới mà thành phố đã hứa từ nhiều năm nay. Một ông già dắt con chó nâu kể rằng ông vẫn còn nhớ cây cầu đầu tiên bị lũ cuốn trôi khi ông còn nhỏ. Không ai hoàn toàn tin ông nhưng đó là một câu chuyện hay và việc chờ đợi trở nên dễ dàng hơn.'),
]


@pytest.mark.parametrize("lang, text", OTHER_PROSE)
def test_prose_of_other_scripts_is_kept(lang, text):
    for known in (lang, None):
        assert fertility.measure_one(text, known)[6]


def test_junk_of_any_script_is_rejected():
    rng = np.random.default_rng(0)
    noise = " ".join(bytes(rng.integers(0, 256, 8).tolist()).decode("latin-1") for _ in range(80))
    code = " ".join("".join(rng.choice(list("abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789+/"), 60)) for _ in range(60))
    marked = " ".join(w + m for w, m in zip(PROSE[0][1].split(" "), itertools.cycle(["###", "$$$", "%%%", "***"])))
    for text, lang in ((noise, "en"), (noise, None), (code, "en"), (marked, "en"), ("ха ха " * 60, None)):
        assert not fertility.measure_one(text, lang)[6]


@pytest.mark.parametrize("lang, text", PROSE)
def test_natural_prose_is_kept(lang, text):
    words_in = text.split(" ")
    for n in (50, 60, len(words_in)):
        for known in (lang, None):
            assert fertility.measure_one(" ".join(words_in[:n]), known)[6]


def test_byte_share_is_that_of_the_vocabulary():
    import sentencepiece

    path = fertility.vocabulary_path("piece_bpe_32k.model")
    sp, plain = sentencepiece.SentencePieceProcessor(model_file=path), fertility.piece_characters(path)
    for text in ("plain", "été größe", "日本語テキスト", "🙂🙂 ok", "ñandú", "ක්ර", "∮∯ x", "abc☃def"):
        ids = sp.encode(text)
        fallback = sum(sp.is_byte(i) for i in ids)
        assert fertility.byte_share(text, plain) == pytest.approx(fallback / len(text.encode()))


def test_entropy_and_top_share():
    for ids in ([], [5], [1, 1, 2, 3], list(range(100)), [7] * 50 + [8]):
        n = Counter(ids)
        want = -sum(c / len(ids) * math.log2(c / len(ids)) for c in n.values()) if ids else 0.0
        assert fertility.token_entropy(np.array(ids, int)) == pytest.approx((want, max(n.values(), default=0) / max(1, len(ids))))


def test_op1_verdict_by_hand(spark, sf):
    """``kept`` of every row from its own measures and the bands, checked one by one."""
    rules, lang = fertility.DEFAULT, table(spark, sf, "documents").select("doc_id", "lang").toPandas().set_index("doc_id").lang
    bands = dict(rules.languages) | dict(rules.scripts)
    for r in QUERIES["op1_fertility_rules"](spark, sf).toPandas().itertuples():
        b, slack = bands.get(r.band, rules.other), fertility.NOISE / max(1, r.n_tokens) ** 0.5
        assert r.band == lang[r.doc_id] or lang[r.doc_id] not in dict(rules.languages)
        inside = [b.main[0] - slack < r.chars_per_token < b.main[1] + slack, b.multi[0] - slack < r.chars_per_token_multi < b.multi[1] + slack, r.token_entropy > b.entropy_low - slack, r.byte_share < b.byte_share_high, r.top_share < b.top_share_high + slack / 4]
        assert r.kept == (not r.base_failed and (r.n_tokens < fertility.MIN_TOKENS or all(inside)))


def test_fit_bands(spark, sf):
    clean = table(spark, sf, "documents").join(table(spark, sf, "labels").where("quality = 1"), "doc_id")
    bands = fertility.fit_bands(clean).toPandas()
    assert (bands.main_low < bands.main_high).all() and set(bands.band) <= {"en", "de", "fr", "es"}


# 2 ---------------------------------------------------------------------------------------------


def check_pieces(pieces, ids_of):
    for doc, want in ids_of.items():
        mine = pieces[pieces.doc_id == doc].sort_values("start")
        got = b"".join(bytes(b) for b in mine.token_ids)
        assert np.array_equal(np.frombuffer(got, "<u4"), want)
        assert (mine.start.to_numpy() == np.r_[0, np.cumsum(mine.length)[:-1]]).all()
        assert (mine.doc_tokens == len(want)).all()
    for _, s in pieces.groupby("sequence_id"):
        s = s.sort_values("offset")
        assert (s.offset.to_numpy() == np.r_[0, np.cumsum(s.length)[:-1]]).all()
        used = s.length.sum()
        assert used <= 2048 and used & (used - 1) == 0 and (s.sequence_tokens == used).all()


def test_op2_whole_table(spark, sf):
    from tokenizers import Tokenizer

    docs = table(spark, sf, "documents")
    pieces = packing.pack(docs, round_tokens=5000).toPandas()
    bpe = Tokenizer.from_file(fertility.vocabulary_path("byte_bpe_50k.json"))
    ids = {r.doc_id: np.array([*bpe.encode(r.text, add_special_tokens=False).ids, 1]) for r in docs.toPandas().itertuples()}
    check_pieces(pieces, ids)
    digest = QUERIES["op2_tiered_packing"](spark, sf).toPandas()
    assert digest.length.sum() == sum(map(len, ids.values()))
    for r in digest.head(200).itertuples():
        assert r.ids_crc32 == zlib.crc32(ids[r.doc_id][r.start : r.start + r.length].astype("<u4").tobytes())
    assert set(packing.packing_measures(pieces_frame(spark, pieces)).toPandas().padding) == {0.0}


def test_op2_added_tokens(spark):
    from tokenizers import Tokenizer

    bpe = Tokenizer.from_file(fertility.vocabulary_path("byte_bpe_50k.json"))
    texts = ["a <|endoftext|> b", "<|endoftext|>", "one  <|endoftext|>\n two<|endoftext|><|endoftext|>x", "<|endoftext| >", "plain"]
    ids = {i: np.array([*bpe.encode(t, add_special_tokens=False).ids, 1]) for i, t in enumerate(texts)}
    assert 50256 in ids[0]
    check_pieces(packing.pack(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").coalesce(1)).toPandas(), ids)


def pieces_frame(spark, pieces):
    return spark.createDataFrame(pieces[["sequence_id", "tier", "step_group", "sequence_tokens", "length"]])


def test_step_groups_are_even():
    windows = [(2048, [(0, 0, 2048)]) if i % 3 else (2048, [(0, 0, 512)] * 4) for i in range(64)]
    groups = packing.step_groups(windows, 1 << 15)
    cost = Counter()
    for (_, p), g in zip(windows, groups, strict=True):
        cost[g] += sum(x[2] ** 2 for x in p)
    assert len(cost) == 4 and max(cost.values()) < 1.05 * sum(cost.values()) / 4


# 3 ---------------------------------------------------------------------------------------------


def test_op3_mixture(spark, sf01):
    placed = sharding.interleave(table(spark, sf01, "documents")).toPandas()
    counts = placed.groupby("shard").size()
    assert counts.max() - counts.min() <= 1
    for s, g in placed.groupby("shard"):
        assert sorted(g.slot) == list(range(len(g)))
    per = placed.groupby(["source", "shard"]).size().unstack(fill_value=0)
    assert (per.max(axis=1) - per.min(axis=1) <= 2).all()


def test_many_sources(spark):
    """Cost grows with the rows, and with the sources of a schedule by a second for a thousand."""
    docs = spark.range(30_000).selectExpr("id doc_id", "cast(id % 10000 as string) source", "'t' text")
    got = sharding.interleave(docs).groupBy("shard").count().toPandas()
    assert got["count"].tolist() == [3750] * 8
    clock = time.perf_counter()
    mixed = mixing.mix(docs.where("cast(source as int) < 1000")).toPandas()
    assert time.perf_counter() - clock < 20
    assert sorted(mixed.position) == list(range(3000)) and (mixed.release <= mixed.slot).all() and (mixed.slot < mixed.deadline).all()


# 4 ---------------------------------------------------------------------------------------------


def test_op4_held_out(spark, sf01):
    got = QUERIES["op4_boosted_quality"](spark, sf01).toPandas().set_index("doc_id")
    labels = table(spark, sf01, "labels").toPandas().set_index("doc_id").join(got)
    assert (got.held_out == [zlib.crc32(str(i).encode()) % 5 == 0 for i in got.index]).all()
    assert (got.predicted == (got.score >= 0.3)).all() and got.score.between(0, 1).all()
    h = labels[labels.held_out]
    assert boosting.auc(h.score.to_numpy(), h.quality.to_numpy()) > 0.97


def test_flat_traversal_equals_node_by_node():
    rng = np.random.default_rng(0)
    x = rng.standard_normal((400, 5))
    y = (x[:, 0] + x[:, 1] * x[:, 2] > 0).astype(float)
    m = boosting.fit(x, y, trees=12)

    def walk(row):
        total = m.base
        for node in m.roots:
            while m.left[node] != node:
                node = m.left[node] if row[m.feature[node]] <= m.threshold[node] else m.right[node]
            total += m.value[node]
        return total

    assert np.allclose(m.raw(x), [walk(r) for r in x])
    assert boosting.auc(m.score(x), y) > 0.97


def plain_tree(x, y, margin, depth, rate, leaf_rows, ridge):
    """One tree by trying every split at every value; the score it adds to each row."""
    prob = 1 / (1 + np.exp(-margin))
    grad, hess = prob - y, prob * (1 - prob)
    out = np.zeros(len(y))

    def grow(rows, level):
        g, h = grad[rows].sum(), hess[rows].sum()
        best = (1e-9, None)
        for f in range(x.shape[1] if level < depth else 0):
            for v in np.unique(x[:, f])[:-1]:
                a, b = rows[x[rows, f] <= v], rows[x[rows, f] > v]
                if len(a) >= leaf_rows and len(b) >= leaf_rows:
                    gain = grad[a].sum() ** 2 / (hess[a].sum() + ridge) + grad[b].sum() ** 2 / (hess[b].sum() + ridge) - g**2 / (h + ridge)
                    if gain > best[0] + 1e-9:
                        best = (gain, (a, b))
        if best[1] is None:
            out[rows] = -g / (h + ridge) * rate
        else:
            grow(best[1][0], level + 1)
            grow(best[1][1], level + 1)

    grow(np.arange(len(y)), 0)
    return out


def test_fit_equals_a_plain_split_search():
    """With a bin for each value, histograms find the splits that trying all of them finds."""
    rng = np.random.default_rng(7)
    x = np.round(rng.random((300, 4)) * 12) / 12
    y = (x[:, 0] + 0.5 * x[:, 2] + 0.2 * rng.standard_normal(300) > 0.8).astype(float)
    got = boosting.fit(x, y, trees=4, depth=3, rate=0.3, bins=300, leaf_rows=5, ridge=1.0)
    margin = np.full(300, np.log(y.mean() / (1 - y.mean())))
    for _ in range(4):
        margin = margin + plain_tree(x, y, margin, 3, 0.3, 5, 1.0)
    assert np.allclose(got.raw(x), margin)


def test_statistics_of_a_text():
    s = dict(zip(boosting.FEATURES, boosting.statistics("Ab c1 c1!\nAb c1 c1!\n| x, é."), strict=True))
    raw = "Ab c1 c1!\nAb c1 c1!\n| x, é.".encode()
    p = np.array(list(Counter(raw).values())) / len(raw)
    assert s["log_words"] == np.log1p(9) and s["distinct_share"] == 6 / 9 and s["top_word_share"] == 2 / 9 and s["exclaim_per_word"] == 2 / 9
    assert s["upper_share"] == 2 / 9 and s["duplicate_line_share"] == 1 / 3 and s["repeat_word_share"] == 6 / 9 and s["byte_entropy"] == pytest.approx(-(p * np.log2(p)).sum())


def test_fit_without_labels():
    assert boosting.fit(np.zeros((0, 20)), np.zeros(0)).score(np.zeros((2, 20))).tolist() == [0.5, 0.5]
    assert boosting.fit(np.zeros((3, 20)), np.ones(3)).score(np.zeros((1, 20)))[0] > 0.99


# 5 ---------------------------------------------------------------------------------------------


def test_op5_articles(spark, sf01):
    got = QUERIES["op5_recurrent_extraction"](spark, sf01).toPandas().set_index("page_id")
    pages = table(spark, sf01, "pages").toPandas()
    right = 0
    for r in pages.itertuples():
        want = "\n\n".join(b.text for b in labeller.blocks_of(r.html) if any(p.startswith("article") for p in b.path))
        right += got.loc[r.page_id].text == want
        assert got.loc[r.page_id].n_chars == len(got.loc[r.page_id].text)
    assert right / len(pages) >= 0.98


def test_labeller_on_unseen_pages():
    rng, hit, total = np.random.default_rng(1234), 0, 0
    for _ in range(120):
        blocks, y = labeller.labelled_blocks(page_maker.make_page(rng))
        if blocks:
            p = labeller.trained().probabilities([labeller.vectors(blocks)])[0] >= 0.5
            hit, total = hit + (p == y).sum(), total + len(y)
    assert hit / total > 0.97


def test_labeller_on_hand_made_pages():
    """The truth was written by hand, so it depends on neither the generator nor the tag reader."""
    missed = extra = whole = 0
    for (_, _, want), got in zip(PAGES, labeller.main_texts([p for _, p, _ in PAGES], labeller.trained()), strict=True):
        left = Counter(want) - Counter(got.split("\n\n") if got else [])
        more = Counter(got.split("\n\n") if got else []) - Counter(want)
        missed, extra, whole = missed + left.total(), extra + more.total(), whole + len(want)
    assert len(PAGES) == 10 and missed <= 3 and extra <= 2 and whole > 45


def slow_forward(p, x):
    """One direction over one page, number by number."""
    n = p["h"].shape[0]
    h, c, out = [0.0] * n, [0.0] * n, []
    sig = lambda v: 1 / (1 + math.exp(-v))
    for row in x:
        z = [float(p["b"][j]) + sum(float(v) * float(p["x"][i, j]) for i, v in enumerate(row) if v) + sum(h[i] * float(p["h"][i, j]) for i in range(n)) for j in range(4 * n)]
        c = [sig(z[n + k]) * c[k] + sig(z[k]) * math.tanh(z[3 * n + k]) for k in range(n)]
        h = [sig(z[2 * n + k]) * math.tanh(c[k]) for k in range(n)]
        out.append(h)
    return np.array(out)


def test_network_equals_a_slow_one():
    model = labeller.trained()
    pages = [labeller.vectors(labeller.blocks_of(p)) for _, p, _ in PAGES[:4]]
    for x, got in zip(pages, model.probabilities(pages), strict=True):
        hidden = np.concatenate([slow_forward(model.forward, x), slow_forward(model.backward, x[::-1])[::-1]], axis=1)
        assert np.allclose(got, 1 / (1 + np.exp(-(hidden @ model.read_out["w"] + model.read_out["b"]))), atol=1e-4)


@pytest.mark.parametrize("piece", ["<a ", "<a \"'>", "<svg>", "<svg", "<iframe><p>t</p>", "<!--", "<a x='", "<div>", "<b>", "</x>", "<p class=\""])
def test_tags_are_read_in_linear_time(piece):
    clock = time.perf_counter()
    labeller.blocks_of(piece * 100_000 + ">")
    assert time.perf_counter() - clock < 10


def test_text_is_not_lost_to_open_tags():
    for tag in ("svg", "iframe", "object", "template", "noscript", "textarea", "b x='1"):
        got = " ".join(b.text for b in labeller.blocks_of(f"<p>one</p><{tag}><p>two</p><p>three</p>"))
        assert got.endswith("two three") or (tag.startswith("b") and "three" in got), tag
    assert [b.text for b in labeller.blocks_of("<object data=x><p>instead</p></object><p>after</p><svg><text>no</text></svg>")] == ["instead", "after"]
    assert labeller.blocks_of('<div data-id="footer" class="a1"><p>t')[0].path == ("div a", "p")


def test_gradients():
    rng = np.random.default_rng(3)
    p = labeller.Lstm.init(rng, 4, 3)
    x, mask = rng.standard_normal((5, 2, 4)), np.array([[1, 1], [1, 1], [1, 1], [1, 0], [1, 0]], bool)
    d = rng.standard_normal((5, 2, 3))
    _, saved = labeller.Lstm.forward(p, x, mask, True)
    g = labeller.Lstm.backward(p, x, mask, saved, d)
    for k in p:
        at = tuple(0 for _ in p[k].shape)
        e = 1e-6
        p[k][at] += e
        up = (labeller.Lstm.forward(p, x, mask)[0] * d).sum()
        p[k][at] -= 2 * e
        down = (labeller.Lstm.forward(p, x, mask)[0] * d).sum()
        p[k][at] += e
        assert g[k][at] == pytest.approx((up - down) / (2 * e), rel=1e-4, abs=1e-7)


def test_blocks():
    page = "<p>a &amp;&eacute;<br>b<b>c</b> d<p>e <li>f<li>g<script>x='</p>'</script><!-- <p>no</p> --><div>h<div>i</div>j"
    assert [b.text for b in labeller.blocks_of(page)] == ["a &é bc d", "e", "f", "g", "h", "i", "j"]
    assert labeller.blocks_of(None) == [] and labeller.blocks_of("<div class='unclosed") is not None


# 6 ---------------------------------------------------------------------------------------------


def test_licence_texts(spark):
    def text(*ids):
        return "Words before it\n" + "".join(f"{licences.SENTENCES[i][0]}.\n" for i in ids) + "words after it."

    wrapped = text("MitGrant", "MitNotice").replace(" to deal", "\nto deal").replace(" of the", "\n of the")
    rows = [(1, text("ApacheUnder2", "ApacheCompliance", "ApacheObtain", "ApacheAsIs", "ApacheSee")), (2, wrapped), (3, text("BsdGrant", "BsdSource", "BsdBinary")), (4, text("BsdGrant", "BsdSource", "BsdBinary", "BsdName")), (5, text("Cc-BY-SA-4.0", "GplUnder3")), (6, None), (7, ""), (8, text("AllRights")), (9, "# SPDX-License-Identifier: MIT\n")]
    got = {r.doc_id: r for r in licences.scan(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert [got[i].licences for i in range(1, 10)] == ["Apache-2.0", "MIT", "BSD-2-Clause", "BSD-3-Clause", "GPL-3.0-only,CC-BY-SA-4.0", "", "", "", "MIT"]
    assert got[8].unmatched == "AllRights" and got[1].unmatched == ""


def test_every_sentence_is_found(spark):
    rows, want = [], []
    for name, texts in licences.SENTENCES.items():
        for one in texts:
            spaces = [i for i, c in enumerate(one) if c == " "]
            cuts = [one[:i] + "\n" + one[i + 1 :] for i in spaces if one[i - 2 : i] != "1."]
            above = "All rights reserved\n"
            for form in (one, one + ".\n", "Words\n" + one + "\nmore words", above + one, *cuts, *(above + "# " + c.replace("\n", "\n# ") + "\nx = 1" for c in cuts)):
                rows.append((len(rows), form))
                want.append(["AllRights"] * form.startswith(above) + [name])
    got = {r.doc_id: r.sentence_ids for r in licences.scan(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert [(rows[i][1], got[i]) for i in got if got[i] != ",".join(want[i])] == []


def test_licence_twin_on_wrapped_texts(spark, tmp_path):
    """The twin cuts and looks up as the scan does, also versions, wrapped lines and neighbours."""
    rows = [None, "", "v. 2.0", "Public License, v.\n\n2.0 copyright"]
    for texts in licences.SENTENCES.values():
        one = texts[0]
        at = one.find(" ", len(one) // 2)
        rows += [one, f"x v. 2 {one}. More\n{one}", f"All rights reserved\n# {one[:at]}\n# {one[at + 1 :]}\ny"]
    df = spark.createDataFrame(list(enumerate(rows)), "doc_id long, text string")
    df.coalesce(1).write.parquet(f"{tmp_path}/documents.parquet")
    c = duckdb.connect()
    c.sql(f"CREATE VIEW documents AS SELECT * FROM '{tmp_path}/documents.parquet/*.parquet'")
    assert rows_of(licences.scan(df).toPandas()) == rows_of(c.sql(licences.oracle_sql()).df())


@pytest.mark.parametrize("text", ["license\n" + "\n".join(f"row {i} of b{i % 7}" for i in range(60_000)), "redistributions of source code must retain the above\n" * 20_000, "license " + "a 1 b 2 " * 130_000, "license" + " \n " * 300_000])
def test_long_texts_are_scanned_in_linear_time(spark, text):
    df = spark.createDataFrame([(1, text)], "doc_id long, text string")
    clock = time.perf_counter()
    assert licences.scan(df).first().licences == ""
    assert time.perf_counter() - clock < 15  # 57 s at 8 000 lines before


def test_licence_plan_is_native(spark, sf):
    plan = QUERIES["op6_licence_sentences"](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Pandas|Arrow|Exchange", plan)


# 7 ---------------------------------------------------------------------------------------------


def slow_links(x, cosine=0.95):
    ok = np.array([v is not None and len(v) > 0 and None not in v and np.isfinite(v).all() and any(v) for v in x])
    u = [np.array(v, float) / np.linalg.norm(v) if o else None for v, o in zip(x, ok, strict=True)]
    n, f = np.zeros(len(x), int), Forest(len(x))
    for i, j in itertools.combinations(np.flatnonzero(ok), 2):
        if len(u[i]) == len(u[j]) and u[i] @ u[j] >= cosine:
            n[i] += 1
            n[j] += 1
            f.link(np.array([i]), np.array([j]))
    return n, f.roots()


def test_op7_planted(spark):
    rng = np.random.default_rng(5)
    x = [v.tolist() for v in rng.standard_normal((150, 64))]
    for i in range(40):
        x.append((np.array(x[i]) + rng.standard_normal(64) * (0.05 + 0.01 * i)).tolist())
    hub = rng.standard_normal(64)
    x += [(hub + rng.standard_normal(64) * 0.12).tolist() for _ in range(60)] + [x[0]] * 20 + [(np.array(x[1]) * 7).tolist()]
    x += [None, [], [0.0] * 64, [float("nan")] * 64, [1.0, None] * 32, [1.0, 0.0], [2.0, 0.0]]
    order = rng.permutation(len(x))
    df = spark.createDataFrame([(int(k), x[i], "extra") for k, i in enumerate(order)], "vec_id long, embedding array<double>, pool string").repartition(5)
    got = collisions.near_vectors(df, block=16, pool_rows=8).toPandas().sort_values("vec_id")
    n, root = slow_links([x[i] for i in order])
    want = pd.Series(range(len(x))).groupby(root).transform("min")
    assert (got.n_links.to_numpy() == n).mean() >= 0.99
    assert (got.component_id.to_numpy() == want.to_numpy()).mean() >= 0.99
    assert (got.n_links.to_numpy() <= n).all()
    assert (got.kept == (got.vec_id == got.component_id)).all()


def brute_links(x, cosine=0.95):
    """Links and components of unit rows by blocked products."""
    n, f = np.zeros(len(x), int), Forest(len(x))
    for at in range(0, len(x), 2000):
        a, b = np.nonzero(x[at : at + 2000] @ x.T >= cosine)
        a = a + at
        f.link(a[a < b], b[a < b])
        np.add.at(n, a[a != b], 1)
    return n, pd.Series(range(len(x))).groupby(f.roots()).transform("min").to_numpy()


@pytest.mark.parametrize("offset", [0.0, 2.0, 4.0])
def test_op7_recall_off_centre(spark, offset):
    """A common offset (mean cosine 0, 0.8, 0.94) costs neither recall nor even pools."""
    rng = np.random.default_rng(int(offset))
    n, d = 6000, 32
    x = rng.standard_normal((n, d)) / d**0.5
    x[:, 0] += offset
    copies = x[rng.integers(0, n, 1500)] + rng.standard_normal((1500, d)) * 0.2 * rng.random((1500, 1)) * (1 + offset) / d**0.5
    x = np.vstack([x, copies]).astype(np.float32)
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<float>").repartition(8)
    got = collisions.near_vectors(df).toPandas().sort_values("vec_id")
    u = x.astype(float)
    n_links, component = brute_links(u / np.linalg.norm(u, axis=1, keepdims=True))
    assert n_links.sum() > 1000 and (got.n_links.to_numpy() <= n_links).all()
    assert got.n_links.sum() / n_links.sum() >= 0.999
    if offset < 4:  # there all but a few are one component
        assert (got.component_id.to_numpy() == component).mean() >= 0.999


def test_op7_pools_are_even_off_centre(spark):
    rng = np.random.default_rng(1)
    x = rng.standard_normal((20_000, 64)) / 8
    x[:, 0] += 2
    df = spark.createDataFrame(pd.DataFrame({"raw": [v.astype("<f4").tobytes() for v in x], "class_id": range(len(x)), "copies": 1}))
    means = collisions._mean_vectors(df, "<f4")
    centred = df.selectExpr("*", "octet_length(raw) size").join(means, "size").select("raw", "mean", "class_id", "copies")
    spread = collisions._spread(centred, "<f4")
    assert 0.1 < spread < 0.2
    plan = dataclasses.replace(collisions.calibrate(len(x), spread=spread), cuts=6, tables=12)
    sizes = centred.mapInArrow(collisions._pools(plan, "<f4", False), "pool_table int, size int, pool long").groupBy("pool_table", "pool").count().toPandas()
    assert sizes["count"].max() < 4 * len(x) / 2**6 and sizes["count"].min() > len(x) / 2**6 / 4


def test_op7_lengths(spark):
    """Vectors of other lengths are never compared, whatever the lengths are."""
    rng = np.random.default_rng(2)
    long, short = rng.standard_normal((40, 1035)), rng.standard_normal((40, 4))
    rows = [(i, v.tolist()) for i, v in enumerate([*short, *long, *long, *(short * 3)])]
    got = collisions.near_vectors(spark.createDataFrame(rows, "vec_id long, embedding array<double>")).toPandas().sort_values("vec_id")
    n, root = slow_links([v for _, v in rows])
    assert got.n_links.tolist() == n.tolist()
    assert got.component_id.tolist() == pd.Series(range(len(rows))).groupby(root).transform("min").tolist()


def test_calibration():
    for n in (10, 10_000, 10**9):
        for spread in (1.0, 0.2, 0.06, 0.0):
            p = collisions.calibrate(n, spread=spread)
            assert p.expected_recall >= collisions.RECALL - 1e-9
    assert collisions.calibrate(10**9).cuts > collisions.calibrate(10**5).cuts > collisions.calibrate(10**5, spread=0.06).cuts


def test_counts_are_window_collisions():
    p = np.random.default_rng(0).standard_normal((30, 5))
    got = collisions.count_collisions(p, np.arange(30), np.arange(30), 0.4)
    assert (got == (np.abs(p[:, None] - p[None]) <= 0.4).sum(axis=2)).all()


# 8 ---------------------------------------------------------------------------------------------

pieces = st.sampled_from(["<", "[", "\\", "|", "/s>", "s>", "INST]", "/INST]", "<|turn|>", "<|end|>", "\n", "a", "<SYS>>", "n", "é"])


@settings(max_examples=300, deadline=None)
@given(st.lists(st.tuples(st.lists(pieces, max_size=6).map("".join), st.lists(pieces, max_size=8).map("".join)), max_size=4))
def test_round_trip(turns):
    text, spans = templates.Template(templates.CHAT).render(messages=[{"role": r, "text": t} for r, t in turns])
    assert templates.read_back(text) == turns
    assert "".join(templates.unescape(text[a:b]) for a, b in spans) == "".join(t for r, t in turns if r == "assistant")
    for control in ("</s>", "[INST]", "[/INST]"):
        assert control not in text


def test_op8_hostile(spark, sf):
    got = QUERIES["op8_template_chat"](spark, sf).where("conv_id = -1").first()
    assert got.n_turns == 2 and got.loss_chars == len(HOSTILE)
    assert got.turns_sha256 == hashlib.sha256(f"user\n{HOSTILE}\nassistant\n{HOSTILE}\n".encode()).hexdigest()
    assert got.loss_sha256 == hashlib.sha256(HOSTILE.encode()).hexdigest()


@pytest.mark.parametrize(
    ("source", "context", "want"),
    [
        ("{{ 1 + 2 * 3 }}", {}, "7"), ("{{ 'a' ~ x ~ 'b' }}", {"x": 1}, "a1b"), ("{% for x in [1, 2, 3] %}{{ x }}{% if not loop.last %},{% endif %}{% endfor %}", {}, "1,2,3"),
        ("{% set y = x | upper %}{{ y if y else 'none' }}", {"x": "q"}, "Q"), ("a {#- note -#} b", {}, "ab"), ("{% if x is defined and x in [1, 2] %}yes{% elif x == 3 %}three{% else %}no{% endif %}", {"x": 3}, "three"),
        ("{{ m.a[0].b }}{{ m.nothing }}", {"m": {"a": [{"b": 5}]}}, "5"), ("{{ not false }}{{ none }}{{ -2 }}", {}, "true-2"), ("{{ x | default('d') | trim }}", {}, "d"),
    ],
)
def test_templates(source, context, want):
    assert templates.Template(source).render(**context)[0] == want


def test_folding():
    assert templates.Template("{{ 'a' ~ 'b' }}{% if 1 == 2 %}x{% else %}c{% endif %}d").tree == templates.Node("text", value="abcd")


@pytest.mark.parametrize("source", ["{{ x.__class__ }}", "{{ _x }}", "{{ open('f') }}", "{% import os %}", "{{ x | system }}", "{% for x in y %}", "{{ 1 + }}", "{{ (1 }}"])
def test_sandbox(source):
    with pytest.raises(templates.TemplateError):
        templates.Template(source)


def test_sandbox_at_run_time():
    assert templates.Template("{{ x.upper }}{{ x.real }}").render(x="s")[0] == ""
    with pytest.raises(templates.TemplateError):
        templates.Template("{{ stop('no') }}").render()


# 9 ---------------------------------------------------------------------------------------------


def check_mix(got, slots, block):
    """Less than one block off the target after every slot, until a source runs out."""
    sizes = got.groupby("source").size()
    laps = min(int(sizes[s] // (block * slots[s])) for s in sizes.index)
    period = sum(slots.values())
    order = got.sort_values("position")
    horizon = laps * period
    seen = Counter()
    for t, s in enumerate(order[order.in_block == 0].source[:horizon]):
        seen[s] += 1
        for k, a in slots.items():
            assert abs(seen[k] - (t + 1) * a / period) < 1
    return horizon


def test_op9_deviation(spark):
    rows = [(i, s, "t") for i, s in enumerate(["a"] * 3000 + ["b"] * 900 + ["c"] * 500 + ["d"] * 100)]
    df = spark.createDataFrame(rows, "doc_id long, source string, text string")
    got = mixing.mix(df, {"a": 0.5, "b": 0.25}, block_rows=2, period=64).toPandas()
    assert sorted(got.position) == list(range(len(rows))) and got.doc_id.nunique() == len(rows)
    first = got[got.slot < 64].groupby("source").block.nunique().to_dict()
    assert sum(first.values()) == 64 and abs(first["a"] - 32) <= 2
    assert check_mix(got, first, 2) >= 64
    assert (got.release <= got.slot).all() and (got.slot < got.deadline).all()


def test_mixed_order(spark, sf):
    docs = table(spark, sf, "documents")
    want = mixing.mix(docs).orderBy("position").toPandas().doc_id.tolist()
    got = mixing.mixed_order(docs)
    assert got.columns == docs.columns
    at = f"{Workspace(spark, 'mixed').base}/m"
    got.write.parquet(at)
    assert [r.doc_id for r in got.collect()] == want


def test_mix_plan_is_native(spark, sf):
    plan = QUERIES["op9_pfair_mixing"](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Pandas|InArrow", plan)


# 10 --------------------------------------------------------------------------------------------


def slow_fingerprint(text):
    low = "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "")
    w = re.findall(r"[^\x20\x09-\x0D]+", low)
    grams = [" ".join(w[i : i + 3]) for i in range(len(w) - 2)] if len(w) > 2 else [" ".join(w)] if w else []
    h = [xxhash.xxh64_intdigest(g.encode(), 42) for g in grams]
    return sum(1 << b for b in range(64) if sum(x >> b & 1 for x in h) * 2 > len(h))


def test_op10_whole_table(spark, sf):
    got = QUERIES["op10_simhash_groups"](spark, sf).toPandas().sort_values("doc_id")
    docs = table(spark, sf, "documents").toPandas().sort_values("doc_id")
    fp = np.array([slow_fingerprint(t) for t in docs.text], np.uint64)
    assert got.fingerprint.tolist() == [f"{int(f):016x}" for f in fp]
    f = Forest(len(fp))
    a, b = np.nonzero(np.bitwise_count(fp[:, None] ^ fp[None]) <= 3)
    f.link(a, b)
    assert got.component_id.tolist() == pd.Series(docs.doc_id.to_numpy()).groupby(f.roots()).transform("min").tolist()


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(0, 2**64 - 1), min_size=1, max_size=40, unique=True), st.lists(st.integers(0, 63), max_size=60))
def test_bk_tree(values, flips):
    v = list(dict.fromkeys([*values, *(x ^ 1 << b for x, b in zip(itertools.cycle(values), flips, strict=False))]))
    v = np.array(v, np.uint64)
    q, x = simhash.BKTree(v).within(v, 3)
    a, b = np.nonzero(np.bitwise_count(v[:, None] ^ v[None]) <= 3)
    assert set(zip(q.tolist(), x.tolist(), strict=True)) == set(zip(a.tolist(), b.tolist(), strict=True))


@pytest.mark.parametrize("bands", [4, 5, 6])
def test_bands_lose_no_pair(bands):
    rng = np.random.default_rng(0)
    masks = simhash.band_masks(bands, 3)
    for _ in range(300):
        x = int(rng.integers(0, 2**63))
        y = x
        for b in rng.choice(64, 3, replace=False):
            y ^= 1 << int(b)
        assert any(x & m == y & m for m in masks)


def test_split_shards(spark):
    """A shard larger than a block is compared as pairs of blocks and loses nothing."""
    from pyspark.sql import functions as F

    base = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon"
    rows = [(i, " ".join(f"{w}{i % 3 if k == i % 20 else ''}" for k, w in enumerate(base.split() * 4))) for i in range(150)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    a = simhash.near_duplicates(df, block=4).orderBy("doc_id").toPandas()
    b = simhash.near_duplicates(df).orderBy("doc_id").toPandas()
    assert a.equals(b) and a.component_id.nunique() < 150
    assert df.select(simhash.fingerprint(F.col("text"))).count() == 150


def test_keep_one_goes_by_row(spark, sf):
    """Repeated ids, null ids and repeated rows, against every pair of rows compared."""
    docs = table(spark, sf, "documents").limit(120).toPandas()
    texts = docs.text.tolist()
    a, b = texts[0], texts[1]
    rows = [(1, a, "x"), (1, b, "x"), (2, b + " word", "x"), (1, a, "x"), (1, a, "y"), (None, b, "z"), (None, "alone and unlike all others here", "z"), (3, None, "z"), (3, "", "z")]
    rows += [(10 + i % 50, t, "s") for i, t in enumerate(texts)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(4)
    fp = np.array([slow_fingerprint(t) for _, t, _ in rows], np.uint64)
    f = Forest(len(rows))
    f.link(*np.nonzero(np.bitwise_count(fp[:, None] ^ fp[None]) <= 3))
    key = lambda r: (r[0] is None, r[0] or 0, "" if r[1] is None else hashlib.md5(r[1].encode()).hexdigest())
    best = {}
    for r, root in zip(rows, f.roots(), strict=True):
        best[root] = min(best.get(root, r), r, key=key)
    got = [(r.doc_id, r.text) for r in simhash.keep_one(df).collect()]
    assert sorted(got, key=str) == sorted(((r[0], r[1]) for r in best.values()), key=str)
    assert (1, a) in got and any(t == b for _, t in got)
    pair = spark.createDataFrame([(1, a), (1, b), (2, b + " word")], "doc_id long, text string")
    assert {r.text for r in simhash.keep_one(pair).collect()} == {a, b}


def test_components_of_a_long_path(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(0, 200)] + [(500, 501), (501, 501), (502, 500)], "a long, b long")
    got = {r.node: r.component for r in components(edges, Workspace(spark, "test")).collect()}
    assert {got[i] for i in range(201)} == {0} and got[501] == got[502] == 500
