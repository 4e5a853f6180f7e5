"""Furniture amid the text of a page without a marked main part."""

import pytest

from rangebound.llm import html_extract

AD = "<div class='ad-box'>buy this now or you will be sorry my friend</div>"
FIRST, SECOND = " ".join(f"a{i}" for i in range(12)), " ".join(f"b{i}" for i in range(30))


@pytest.mark.parametrize("page", [f"<body><p>{FIRST}</p>{AD}<p>{SECOND}</p></body>", f"<body><div><p>{FIRST}</p></div>{AD}<div><p>{SECOND}</p></div></body>", f"<p>{FIRST}</p>{AD}<p>{SECOND}</p>"])
def test_text_on_both_sides_of_an_advert(page):
    assert html_extract.extract(page, html_extract.Weights()) == f"{FIRST} {SECOND}"


def test_furniture_at_the_edges_is_left_out():
    page = f"<body><nav>home about us</nav>{AD}<p>{FIRST}</p>{AD}<p>{SECOND}</p><footer>all rights</footer></body>"
    assert html_extract.extract(page, html_extract.Weights()) == f"{FIRST} {SECOND}"
