"""The two passes of the block rules against a plain reference, other languages and markups that mislead."""

import random

import pytest

from layout_ie.llm import html_text as H

SENTENCES = {
    "en": "The river runs to the sea and it is wide at the mouth, as all of the boats that come in know well. ",
    "de": "Der Fluss fließt in das Meer und ist an der Mündung breit, wie es die Boote wissen, die von dort kommen. ",
    "ru": "Река течёт к морю и широка у самого устья, и это знают все лодки, которые приходят сюда каждую весну. ",
    "zh": "河流流向大海，在入海口处非常宽阔，每年春天来到这里的所有船只都知道这一点，渔民们也都知道。",
    "pl": "Rzeka płynie do morza i przy samym ujściu jest szeroka, o czym wiedzą wszystkie łodzie, które tu wpływają. ",
    "fi": "Joki virtaa mereen ja on suulla leveä, minkä kaikki tänne keväisin saapuvat veneet hyvin tietävät aina. ",
}
MENU = "<ul><li><a href=1>Home</a><li><a href=2>News</a><li><a href=3>About us</a></ul>"


def reference(blocks):
    """Labels by the rules as the module's docstring has them, with nearest neighbours found by looking at all pairs."""
    dense = lambda b: b.link_chars / max(1, len(b.text))
    size = lambda b: len(b.text) + 2 * sum("⺀" <= c <= "힣" for c in b.text)
    words = lambda b: [w.strip(".,;:!?\"'()") for w in b.text.lower().split()]
    longs = [b for b in blocks if size(b) >= 70 and dense(b) <= 0.34]
    listed = sum(w in H.STOP_WORDS for b in longs for w in words(b)) >= 0.1 * max(1, sum(len(words(b)) for b in longs))
    inside = sum(size(b) for b in blocks if b.region == "main")
    prose = sum(size(b) for b in blocks if b.region == "page" and size(b) >= 200 and dense(b) <= 0.34)
    article = inside > 0 and (inside >= 70 or prose < 600)
    first = []
    for i, b in enumerate(blocks):
        stop = sum(w in H.STOP_WORDS for w in words(b)) / max(1, len(words(b))) if listed else 1
        links = [dense(x) > 0.9 and x.region == b.region for x in blocks]
        lo = next((j for j in range(i, -1, -1) if not links[j]), -1)
        hi = next((j for j in range(i, len(blocks)) if not links[j]), len(blocks))
        if b.region in ("aside", "marked") or (links[i] and hi - lo - 1 >= 3) or (article and b.region == "page"):
            first.append("bad")
        elif article and b.region == "main":
            first.append("bad" if dense(b) > 0.9 and size(b) > 70 else "good" if size(b) >= 70 and stop >= 0.2 else "")
        elif dense(b) > 0.34 or (size(b) >= 70 and stop < 0.2):
            first.append("bad")
        else:
            first.append("good" if size(b) >= 200 and stop >= 0.3 else "")
    out = list(first)
    for i, b in enumerate(blocks):
        if not first[i]:
            near = [(abs(i - j), first[j] != "good") for j in range(len(blocks)) if first[j] and blocks[j].region == b.region]
            out[i] = ("bad" if min(near)[1] else "good") if near else "good" if b.region == "main" else "bad"
    return out


@pytest.mark.parametrize("seed", range(6))
def test_labels_equal_the_reference(seed):
    r = random.Random(seed)
    for _ in range(150):
        found = []
        for _ in range(r.randrange(1, 14)):
            text = (r.choice(list(SENTENCES.values())) * 3)[: r.choice((5, 30, 69, 70, 120, 199, 230))].strip()
            found.append(H.Block(text, r.choice((0, 0, 0, len(text) // 2, len(text))), r.choice(("main", "page", "page", "aside", "marked"))))
        want = reference(found)
        H.first_labels(found)
        H.second_labels(found)
        assert [b.label for b in found] == want


@pytest.mark.parametrize("lang", SENTENCES)
@pytest.mark.parametrize("tagged", [True, False])
def test_articles_in_any_language(lang, tagged):
    body = "".join(f"<p>{SENTENCES[lang] * n}</p>" for n in (4, 3, 5))
    article = f"<article>{body}</article>" if tagged else f"<div>{body}</div>"
    got = H.main_text(f"<html><body>{MENU}{article}<footer>Imprint</footer></body></html>")
    assert got == "\n".join((SENTENCES[lang] * n).strip() for n in (4, 3, 5))


def test_each_pass_changes_the_result():
    long, short = SENTENCES["en"] * 3, "A short line."
    page = f"<div>{long}</div><p>{short}</p><div>{long}</div>{MENU}<p>Read more here</p><div><a>{'link ' * 30}</a></div>"
    found = H.blocks(page)
    H.first_labels(found)
    assert [b.label for b in found] == ["good", "", "good", "bad", "bad", "bad", "", "bad"]  # links and menus by density, long text by stop words
    H.second_labels(found)
    assert [b.label for b in found][1] == "good" and [b.label for b in found][6] == "bad"  # short ones by their neighbours
    # In a listed language a block without stop words is no prose.
    odd = "Widget gadget sprocket flange gasket bearing. " * 6
    assert H.main_text(f"<div>{long}</div><div>{odd}</div><div>{long}</div>").count("sprocket") == 0
    # A menu inside the article goes, a lone link stays.
    assert "About us" not in H.main_text(f"<article><p>{long}</p>{MENU}<p>{long}</p></article>")
    assert "one link" in H.main_text(f"<article><p>{long}</p><p><a>one link</a></p><p>{long}</p></article>")


@pytest.mark.parametrize("wrapper", ["content with-sidebar", "has-ads", "post-share-enabled", "sidebar", "widget", "comments"])
def test_a_wrapper_does_not_take_the_article(wrapper):
    text = SENTENCES["en"] * 4
    assert H.main_text(f"<div class='{wrapper}'><article><p>{text}</p></article></div>") == text.strip()
    assert H.main_text(f"<div class='{wrapper}'><p>{text}</p></div>") == text.strip()
    assert H.main_text(f"<article><p>{text}</p></article><div class='sidebar'>{SENTENCES['de'] * 4}</div>") == text.strip()


def test_an_empty_teaser_is_not_the_article():
    text = SENTENCES["en"] * 8
    assert H.main_text(f"<article>Top story</article><div>{text}</div>").endswith(text.strip())


def test_very_long_pages():
    text = SENTENCES["en"].strip()
    assert H.main_text("<article>" + f"<p>{text}</p>" * 20_000 + "</article>") == "\n".join([text] * 20_000)
