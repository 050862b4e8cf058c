from carrierpath.llm import html_extract


def test_features_read_the_whole_block():
    word = "word " * 600
    pages = [f"<html><body><p>{word}{end}</p></body></html>" for end in ("end", "One. Two! Three?", "© 2020")]
    plain, stops, sign = (set(html_extract.features(html_extract.leaf_blocks(p))[0]) for p in pages)
    assert "stops=0" in plain and "copyright" not in plain
    assert "stops=3" in stops and "copyright" in sign


def test_unclosed_elements_do_not_swallow_the_page():
    for tag in ("svg", "object", "select", "video", "noscript", "canvas"):
        page = f"<html><body><article><p>First paragraph.</p><{tag} class=x><p>Second paragraph.</p><{tag}><p>Third one.</p></article></body></html>"
        assert [b.text for b in html_extract.leaf_blocks(page)] == ["First paragraph.", "Second paragraph.", "Third one."]
        closed = f"<article><p>First.</p><{tag}>inside</{tag}><p>Second.</p></article>"
        assert [b.text for b in html_extract.leaf_blocks(closed)] == ["First.", "Second."]
    assert [b.text for b in html_extract.leaf_blocks("<p>Text.</p><script>if (a < b) <p>no</p>")] == ["Text."]
    assert html_extract.leaf_blocks("<select>" * 50_000 + "end")[-1].text == "end"
