import hashlib
import re

from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import types as T

from wsig.llm import pii

SCHEMA = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("text", T.StringType()), T.StructField("spans", T.StringType()), T.StructField("n_chars", T.LongType())])


def brute(text):
    """The contract's patterns, taken literally."""
    digits = lambda s: re.sub("[^0-9]", "", s)
    out = [(m.start(), m.end(), "email") for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", text)]
    out += [(m.start(), m.end(), "ip") for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", text) if all(int(x) <= 255 for x in m.group().split("."))]
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", text):
        d = [int(c) for c in digits(m.group())][::-1]
        if 12 <= len(d) <= 19 and sum(sum(divmod(2 * x, 10)) if i % 2 else x for i, x in enumerate(d)) % 10 == 0:
            out.append((m.start(), m.end(), "card"))
    out += [(m.start(), m.end(), "phone") for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", text) if 9 <= len(digits(m.group())) <= 15]
    return sorted(out, key=lambda s: (s[0], ["email", "ip", "card", "phone"].index(s[2])))


@settings(max_examples=1500, deadline=None)
@given(st.text(alphabet="ab@.-+ 0127()%é\n", max_size=60))
def test_plain_spans_equal_the_patterns(text):
    assert pii.plain(text) == brute(text)


def test_numbers():
    for t in ("+1 (017) 555-7713", "97.51.17.173", "97.51.17.1731.2.3.4.5", "4845168114407329 x", "4845-1681 1440-7329", "a@b@c.de.f@g.h", "0000.1.2.3", "1" * 3000 + ".1.1.1", "0" * 3000 + "1.1.1.256"):
        assert pii.plain(t) == brute(t)


def spans(text):
    return [(text[a:b], kind) for a, b, kind in pii.find(text)[1]]


def test_disguises_map_back_to_source():
    assert spans("write to jane.doe (at) mail dot example [dot] org now") == [("jane.doe (at) mail dot example [dot] org", "email")]
    assert spans("é jane at example dot com.") == [("jane at example dot com", "email")]
    assert spans("jаne＠exаmple．com") == [("jаne＠exаmple．com", "email")]
    assert spans("ring plus one five five five one two three four five six seven, thanks") == [("plus one five five five one two three four five six seven", "phone")]
    assert spans("host one nine two dot one six eight dot one dot two up") == [("one nine two dot one six eight dot one dot two", "ip")]
    assert spans("card ４８４５ １６８１ １４４０ ７３２９.") == [("４８４５ １６８１ １４４０ ７３２９", "card")]
    assert spans("4845​1681​1440​7329") == [("4845​1681​1440​7329", "card")]
    assert spans("a@b.cd and x (at) y dot zz") == [("a@b.cd", "email"), ("x (at) y dot zz", "email")]


def test_disguise_that_widens_a_plain_span():
    text = "mail jаne@example.com now"  # a Cyrillic letter
    base, every = pii.find(text)
    assert base == [(7, 21, "email")] and every == [(5, 21, "email"), (7, 21, "email")] and pii.mask(text, every) == "mail <EMAIL> now"
    assert spans("ask jane at example.com or j.roe at mail.example.org.") == [("jane at example.com", "email"), ("j.roe at mail.example.org", "email")]


#: Ways to write a mailbox, an address and a number: what is shown for what is meant.
_AT_FORMS, _DOT_FORMS = (" (at) ", "[at]", " {at} ", "(@)", " arroba "), (" (dot) ", "[.]", " dot ", " [punkt] ")
_LOOKS = str.maketrans("aeopcx", "аеорсх")
_WIDE = {ord(c): ord(c) + 0xFEE0 for c in "0123456789@"}
_SPELT = "zero one two three four five six seven eight nine".split()


@settings(max_examples=300, deadline=None)
@given(st.lists(st.tuples(st.integers(0, 5), st.integers(0, 10**9), st.sampled_from(_AT_FORMS), st.sampled_from(_DOT_FORMS)), min_size=1, max_size=6))
def test_planted_disguises_are_found_whole(plan):
    """Each planted form is found at its own place, and nothing else is."""
    text, want = "Of stones, ", []
    for form, n, at, dot in plan:
        digits = f"{n % 10**9 + 10**9:010d}"
        shown, kind = {
            0: (f"mona{n}{at}post{dot}com", "email"),
            1: (f"mona{n}＠post．com", "email"),
            2: ("hаrpo" + f"{n}@post.com".translate(_WIDE | {ord("@"): ord("@")}), "email"),
            3: ("plus " + " ".join(_SPELT[int(c)] for c in digits), "phone"),
            4: ("+" + digits.translate(_WIDE), "phone"),
            5: (" dot ".join(" ".join(_SPELT[int(c)] for c in str(n // 7**k % 200)) for k in range(4)), "ip"),
        }[form]
        want.append((len(text), len(text) + len(shown), kind))
        text += shown + ", rivers: "
    base, every = pii.find(text)
    assert [s for s in every if s not in base] == want


def test_many_spans_take_linear_time():
    import time

    text = "a@b.cd x (at) y dot zz 10.0.0.1 " * 8000
    start = time.process_time()
    base, every = pii.find(text)
    assert len(base) == 16000 and len(every) == 24000 and time.process_time() - start < 8


def test_prose_stays_clean():
    for t in ("He looked at the dot on the wall at one.", "We met at noon. Two dots, three lines at four.", "Look at example.com for six seven eight", "Привет, мир. αβγ δεζ", "one two three go", "at dot at dot", "More information at example.com, or look at www.example.org.", ""):
        assert spans(t) == []


def test_query_and_mask(spark):
    rows = [(1, "mail a.b@c.de or 10.0.0.1", "clash", 0), (2, None, None, None), (3, "", "clash", 0), (None, "x (at) y dot zz", None, 5), (4, "w " * 200000 + "+1 (017) 555-7713", None, 1), (1, "mail a.b@c.de or 10.0.0.1", "clash", 0)]
    df = spark.createDataFrame(rows, SCHEMA)
    got = pii.find_pii(df).collect()
    assert len(got) == 6
    by = {r.doc_id: r for r in got}
    assert (by[1].n_email, by[1].n_ip, by[1].n_card, by[1].n_phone) == (1, 1, 0, 0)
    assert by[1].base_sha256 == hashlib.sha256(b"email:5:13,ip:17:25").hexdigest()
    assert by[None].spans == "email:0:15" and by[None].base_sha256 == hashlib.sha256(b"").hexdigest()
    assert by[4].n_phone == 1 and by[2].spans == by[3].spans == ""
    masked = {r.doc_id: r for r in pii.mask_pii(df).collect()}
    assert masked[1].text == "mail <EMAIL> or <IP>" and masked[1].n_chars == 20 and masked[1].spans == "clash"
    assert masked[2].text is None and masked[None].text == "<EMAIL>"
    assert pii.find_pii(df.limit(0)).count() == 0
