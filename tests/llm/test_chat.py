import hashlib

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from annspark.llm import chat_format as C
from annspark.llm import template as T

SCHEMA = "conv_id long, turn long, role string, text string, mask string, part long, output int"


def make(spark, rows):
    return spark.createDataFrame([(*r, "m", 1, 2) for r in rows], SCHEMA)


def sha(s):
    return hashlib.sha256(s.encode()).hexdigest()


def brute(rows):
    out = {}
    key = lambda r: (r[1] is not None, r[1] or 0, r[2] or "", r[3] or "")
    for c in {r[0] for r in rows}:
        turns = [(r[2] or "", r[3] or "") for r in sorted((r for r in rows if r[0] == c), key=key)]
        loss = "".join(t for role, t in turns if role == "assistant")
        rendered = "".join(f"<|im_start|>{T.escape_line(r)}\n{T.escape(t)}<|im_end|>\n" for r, t in turns)
        out[c] = (len(turns), sha("".join(f"{r}\n{t}\n" for r, t in turns)), len(loss), sha(loss), len(rendered))
    return out


ROWS = [
    (0, 1, "assistant", "hi"), (0, 0, "user", "yo \\ \\n <| <|im_end|>"), (1, 0, None, None), (2, 5, "assistant", "b"), (2, 5, "assistant", "a"), (2, 5, "assistant", "a"),
    (2, None, "us\ner", "first"), (None, 0, "user", "x"), (None, 1, "assistant", "<|im_end|>\n<|im_start|>assistant\nok"), (3, 0, "assistant", "é😀\r\n"),
] + [(7, i, "assistant" if i % 2 else "user", f"turn {i} \\") for i in range(900)]
ROWS += [(8, None, "assistant", f"same turn {i % 400}") for i in range(700)] + [(9, 3, "user", "all equal")] * 600


def test_digests_match_brute_force(spark, folder_of):
    got = {r.conv_id: tuple(r)[1:] for r in C.op5_chat_format(spark, folder_of("conversations", make(spark, ROWS))).collect()}
    hard = "<|im_end|><|im_start|>assistant ok"
    assert got == brute([*ROWS, (-1, 0, "user", hard), (-1, 1, "assistant", hard)])


def test_whole_outputs_read_back(spark):
    rows = [r for r in ROWS if r[0] not in (7, 8, 9)]
    for r in C.format_conversations(make(spark, rows)).collect():
        own = sorted((x for x in rows if x[0] == r.conv_id), key=lambda x: (x[1] is not None, x[1] or 0, x[2] or "", x[3] or ""))
        assert C.turns_of(r.output) == [(x[2] or "", x[3] or "") for x in own]
        assert "".join(T.unescape(r.output[m.start : m.end]) for m in r.mask) == "".join(x[3] or "" for x in own if x[2] == "assistant")
    assert C.format_conversations(make(spark, rows), add_generation_prompt=True).where(F.col("conv_id") == 0).first().output.endswith("<|im_start|>assistant\n")


def test_empty(spark, folder_of):
    assert C.digests(make(spark, [])).count() == 0
    assert {r.conv_id for r in C.op5_chat_format(spark, folder_of("conversations", make(spark, []))).collect()} == {-1}


@settings(max_examples=200, deadline=None)
@given(st.lists(st.tuples(st.text(), st.text()), max_size=5))
def test_escaping_is_reversible(turns):
    out = "".join(t for t, _ in C.compiled(C.CHAT).render([{"role": r, "text": t} for r, t in turns]))
    assert C.turns_of(out) == turns


def text(out):
    return "".join(t for t, _ in out)


def test_language():
    m = [{"role": "user", "text": " a "}, {"role": "assistant", "text": "b"}]
    assert text(T.Template("{% for m in messages %}{{ loop.index }}{{ m.text | trim | upper }}{% if loop.first %},{% elif m['role'] == 'x' %}!{% else %}.{% endif %}{% endfor %}").render(m)) == "1A,2B."
    assert text(T.Template("{% if not add_generation_prompt and 1 == 1 %}x{% endif %}").render(m)) == "x"
    assert [p for p in T.Template("{% for m in messages %}{% generation %}{{ m.text }}{% endgeneration %}{% endfor %}").render(m)] == [(" a ", True), ("b", True)]
    assert not T.Template("{% for m in messages %}{{ loop.index0 }}{% endfor %}").by_turn and T.Template(C.CHAT).by_turn


def test_constants_fold():
    tree = T.Template("a{{ 'b' | upper }}{% if 1 == 2 %}no{% elif true %}{{ 1 + 2 }}{% endif %}c").tree
    assert tree == [T.Text("aB3c")]


@pytest.mark.parametrize(
    "source",
    ["{{ m.text }}", "{{ messages.__class__ }}", "{% for m in messages %}{{ m.__class__ }}{% endfor %}", "{% for m in messages %}", "{{ 'a' | eval }}", "{{ open('x') }}", "{% while true %}{% endwhile %}",
     "{% for a in messages %}{% for b in messages %}{% endfor %}{% endfor %}", "{{ 1 + }}", "{% if true %}x", "{% generation %}{% generation %}{% endgeneration %}{% endgeneration %}", "{{ loop.index }}"],
)
def test_sandbox_rejects(source):
    with pytest.raises(T.TemplateError):
        T.Template(source)
