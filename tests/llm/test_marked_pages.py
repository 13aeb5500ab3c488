"""A page's mark of its article is a prior for the block rules, not a verdict."""

from temporal_rules.llm import html_blocks

PROSE = "This is the text of a story that was told in the town, and it is long enough to be the main part of what a page says to us. "
LINKS = '<div><a href="/1">One more story</a> <a href="/2">Another story of the town</a></div>'


def test_link_block_inside_the_article():
    page = f"""<body><article><h1>Head</h1><div><a href="/by">By A. Writer</a></div><p>{PROSE * 2}</p>{LINKS}<p>{PROSE}</p>
    {LINKS}<p>Short.</p>{LINKS}<p>{PROSE * 2}</p><p>A <a href="/x">link</a> in it.</p><h2>More</h2>{LINKS}<p>© 2020 A town</p></article></body>"""
    long = (PROSE * 2).strip()
    assert html_blocks.main_text(page) == "\n\n".join(["Head", long, PROSE.strip(), long, "A link in it."])


def test_stop_words_inside_the_article():
    tags = "<p><a href='/t'>Economy</a>, trade, budget, market, industry, business, finance, company, shares, growth, prices, export, import</p>"
    assert html_blocks.main_text(f"<article><p>{PROSE * 2}</p>{tags}</article>") == (PROSE * 2).strip()
    foreign = "Kaupungissa kerrottiin tarina, joka oli niin pitkä, että siitä tuli <a href='/t'>sivun</a> tärkein teksti kaikille lukijoille."
    assert html_blocks.main_text(f"<article><p>{foreign}</p><p>{foreign}</p></article>").count("Kaupungissa") == 2


def test_teasers_marked_as_articles():
    teaser = '<article><h3><a href="/s">A story of elsewhere</a></h3><p>Short teaser.</p></article>'
    page = f"<body><div><h1>Head</h1><p>{PROSE * 2}</p><p>Yes.</p><p>{PROSE * 2}</p></div>{teaser * 3}</body>"
    long = (PROSE * 2).strip()
    assert html_blocks.main_text(page) == "\n\n".join(["Head", long, "Yes.", long])


def test_clear_text_outside_the_mark():
    page = f"<body><div>Site name</div><p>{PROSE * 2}</p><article><p>Short one.</p><p>{PROSE}</p></article>{LINKS}<div>{PROSE}</div><nav>{PROSE * 2}</nav></body>"
    assert html_blocks.main_text(page) == "\n\n".join([(PROSE * 2).strip(), "Short one.", PROSE.strip()])
