import random

import pytest

from densegrid.llm import html_extract
from tests.llm.test_operators import page, prose


@pytest.mark.parametrize("mark", ["style='overflow:hidden'", "class='overflow-hidden'", "class='has-sidebar'", "class='with-header'", "id='legal-article'", "class='search-results'", "data-hidden='no'", "hidden='until-found'", "title='hidden'"])
def test_wrappers_named_after_furniture_keep_their_article(mark):
    paras = [prose(40, random.Random(i)) for i in range(4)]
    inner = "".join(f"<p>{p}</p>" for p in paras)
    assert html_extract.main_text(page(f"<div {mark}>{inner}</div>"), html_extract.Weights()) == "\n".join(paras)


@pytest.mark.parametrize("mark", ["hidden", "hidden=''", "aria-hidden=true", "style='color:red; display : none'", "class='wide ad'", "id=cookie-notice", "role='search'"])
def test_hidden_and_furniture_elements_go(mark):
    paras = [prose(40, random.Random(i)) for i in range(4)]
    inner = "".join(f"<p>{p}</p>" for p in paras[:2]) + f"<div {mark}>gone words</div>" + "".join(f"<p>{p}</p>" for p in paras[2:])
    assert html_extract.main_text(page(f"<div>{inner}</div>"), html_extract.Weights()) == "\n".join(paras)
