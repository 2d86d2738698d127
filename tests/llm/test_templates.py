from __future__ import annotations

import pytest

from utilmine.llm.templates import Node, Template, TemplateError, fold, parse


def render(source, **context):
    return Template(source).render(context)[0]


@pytest.mark.parametrize("source,want", [
    ("a{{ 1 + 2 }}b", "a3b"),
    ("{% for x in xs %}{{ x.n }}{% if not loop.last %},{% endif %}{% endfor %}", "1,2"),
    ("{% if xs | length > 1 and 'a' in name %}y{% elif name %}m{% else %}n{% endif %}", "m"),
    ("{% set t = name ~ '!' %}{{ t | upper }}", "BOB!"),
    ("a  {%- if true -%}  b  {%- endif -%}  c", "abc"),
    ("{{ xs[0]['n'] }}{{ xs[9] }}{{ nothing.at.all }}", "1"),
    ("{{ 'q\\n' ~ \"w\" }}", "q\nw"),
    ("{{ not (1 == 2) }}", "true"),
])
def test_render(source, want):
    assert render(source, xs=[{"n": 1}, {"n": 2}], name="bob") == want


def test_folding():
    tree = fold(parse("a{{ 'b' ~ 1 }}{% if 1 == 1 %}c{% else %}{{ x }}{% endif %}{% if false %}z{% endif %}d"), {})
    assert tree == Node("text", ("ab1cd",))


def test_generation_spans_are_code_points():
    text, spans = Template("é{% generation %}{{ x }}{% endgeneration %}{% generation %}{% endgeneration %}z").render({"x": "🙂b"})
    assert text == "é🙂bz" and spans == [(1, 3)]


@pytest.mark.parametrize("source", ["{{ x.__class__.__mro__ }}", "{{ ''.join }}", "{{ x['__init__'] }}"])
def test_sandbox_has_no_attributes(source):
    assert render(source, x="s") == ""


@pytest.mark.parametrize("source", ["{{ f(x) }}", "{% import os %}", "{{ x | eval }}", "{% for x in y %}", "{{ 1 + }}", "{% if %}{% endif %}"])
def test_errors(source):
    with pytest.raises(TemplateError):
        Template(source)
