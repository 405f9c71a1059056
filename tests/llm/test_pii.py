import hashlib
import re

import pyarrow as pa
import pyarrow.compute
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from edgemill.llm import pii

PLAIN = {
    "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+",
    "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
    "card": r"[0-9]([\x20-]?[0-9])+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}


def brute(text):
    out = []
    for kind, pattern in PLAIN.items():
        for m in re.finditer(pattern, text):
            digits = re.sub("[^0-9]", "", m[0])
            if kind == "ip" and any(int(p) > 255 for p in m[0].split(".")):
                continue
            if kind == "card" and not (13 <= len(digits) <= 19 and sum(sum(divmod(int(d) * (1 + i % 2), 10)) for i, d in enumerate(digits[::-1])) % 10 == 0):
                continue
            if kind == "phone" and not 9 <= len(digits) <= 15:
                continue
            out.append((kind, *m.span()))
    return out


@settings(max_examples=600, deadline=None)
@given(st.text(alphabet="ab1234567890.@-+ ()_%", max_size=60))
def test_base_spans_equal_the_plain_patterns(text):
    (_, base, every), = pii.findings(pa.array([text]))
    assert base == brute(text)
    assert set(base) <= set(every)


@pytest.mark.parametrize("text,kind,source", [
    ("write to jane.doe [at] example [dot] com now", "email", "jane.doe [at] example [dot] com"),
    ("jane(at)example(dot)co(dot)uk", "email", "jane(at)example(dot)co(dot)uk"),
    ("mail: jane dot doe at example dot com.", "email", "jane dot doe at example dot com"),
    ("j\u0430ne@ex\u0430mple.com", "email", "j\u0430ne@ex\u0430mple.com"),
    ("ｊａｎｅ＠example.com", "email", "ｊａｎｅ＠example.com"),
    ("jane\u200b@example.com", "email", "jane\u200b@example.com"),
    ("at 192 dot 168 dot 0 dot 17 they", "ip", "192 dot 168 dot 0 dot 17"),
    ("one nine two dot one six eight dot zero dot one", "ip", "one nine two dot one six eight dot zero dot one"),
    ("card four one one one one one one one one one one one one one one one ok", "card", "four one one one one one one one one one one one one one one one"),
    ("call plus four four two zero seven nine four six zero nine five eight", "phone", "plus four four two zero seven nine four six zero nine five eight"),
])
def test_disguises(text, kind, source):
    (_, _, every), = pii.findings(pa.array([text]))
    a = text.index(source)
    assert (kind, a, a + len(source)) in every


@pytest.mark.parametrize("text", ["look at example.com for more", "they met at noon. dot com boom", "one two three and four", "the point at hand", "a dot b"])
def test_clean_prose_stays_clean(text):
    (_, base, every), = pii.findings(pa.array([text]))
    assert base == every == []


def test_long_runs_are_linear():
    for text in ("1" * 200_000, "a." * 100_000, "@" * 100_000, "+1" * 100_000, "1." * 100_000, "a@b" * 60_000):
        list(pii.findings(pa.array([text])))


def test_report_and_mask(spark):
    rows = [(1, None, 0, "a"), (2, "", 0, "b"), (3, "x@y.zz and x [at] y [dot] zz, 1.2.3.4", 5, "c"), (3, "x@y.zz and x [at] y [dot] zz, 1.2.3.4", 5, "c"), (4, "long " * 50_000 + "+12 345 678 90", 9, None)]
    df = spark.createDataFrame(rows, "doc_id long, text string, n_chars long, spans string")
    got = sorted(pii.report(df).collect(), key=lambda r: r.doc_id)
    assert [r.n_email for r in got] == [0, 0, 1, 1, 0] and [r.n_phone for r in got] == [0, 0, 0, 0, 1]
    assert got[0].base_sha256 == hashlib.sha256(b"").hexdigest() and got[0].spans == ""
    assert got[2].base_sha256 == hashlib.sha256(b"email:0:6,ip:30:37").hexdigest()
    assert got[2].spans == "email:0:6,email:11:28,ip:30:37"
    out = {r.doc_id: r for r in pii.mask(df).collect()}
    assert out[3].text == "<EMAIL> and <EMAIL>, <IP>" and out[3].n_chars == len(out[3].text)
    assert out[1].text is None and out[2].text == "" and out[4].text.endswith("<PHONE>")
    assert pii.mask(df).columns == df.columns and pii.report(df.limit(0)).count() == 0


@pytest.mark.parametrize("text,kind,source", [
    ("call plus 44 20 7946 0958 now", "phone", "plus 44 20 7946 0958"),
    ("call +44 20 seven nine four 0 nine five 8 now", "phone", "+44 20 seven nine four 0 nine five 8"),
    ("card 4111 1111 1111 one one one 1 ok", "card", "4111 1111 1111 one one one 1"),
    ("host 192.168.zero.one up", "ip", "192.168.zero.one"),
    ("jane [\u00a0at\u00a0] example.com", "email", "jane [\u00a0at\u00a0] example.com"),
    ("host 192.168.\u017fIX.s\u0131x up", "ip", "192.168.\u017fIX.s\u0131x"),
])
def test_partly_disguised(text, kind, source):
    (_, _, every), = pii.findings(pa.array([text]))
    a = text.index(source)
    assert (kind, a, a + len(source)) in every


PARTS = [*pii.DIGIT_WORDS, "plus", "Plus", "+", "at", "dot", "AT", "@", ".", "-", " ", " ", "_", "\t", "\n", "\xa0", "\x0b", "[", "]", "(", ")", "a", "com", "jane", "4111", "192", "168", "0", "7", "44", "\u200b", "\u0131", "\u017f", "\u0430"]


@settings(max_examples=3000, deadline=None)
@given(st.lists(st.sampled_from(PARTS), max_size=24).map("".join))
def test_texts_that_the_gate_passes_over_hide_nothing(text):
    gate = pa.compute.match_substring_regex(pa.array([text]), pii.MAY_HIDE, ignore_case=True)[0].as_py()
    assert gate or not any(pii.hidden(text).values())


def test_spans_do_not_hang_on_other_triggers():
    for text in ("call +44 20 7946 0958 at 10 today", "call plus 44 20 7946 0958", "192.168.zero.one", "4111 1111 at 1111 1111"):
        (_, _, alone), (_, _, beside) = pii.findings(pa.array([text, text + " \u0430"]))
        assert alone == beside
    (_, base, every), = pii.findings(pa.array(["call +44 20 7946 0958 at 10, zero"]))
    assert base == every == [("phone", 5, 21)]


@pytest.mark.parametrize("text,kind,source", [
    ("ruf an: +49 eins sieben null 1234567 heute", "phone", "+49 eins sieben null 1234567"),
    ("appelez +33 SEPT huit neuf zéro un deux 345", "phone", "+33 SEPT huit neuf zéro un deux 345"),
    ("al +34 seis siete ocho nueve cero uno dos tres", "phone", "+34 seis siete ocho nueve cero uno dos tres"),
    ("host 192.168.fünf.neun up", "ip", "192.168.fünf.neun"),
])
def test_digits_of_the_corpus_languages(text, kind, source):
    (_, _, every), = pii.findings(pa.array([text]))
    assert [(k, text[a:b]) for k, a, b in every] == [(kind, source)]
    assert every == pii.find(text)[1]


def test_words_that_only_hold_a_digit_word_stay():
    for text in ("+49 einsam 1234567", "10.0.0.dosé", "la +34 unos 12345678", "10.0.0.neunzig"):
        (_, base, every), = pii.findings(pa.array([text]))
        assert every == base
