"""Short sources written for this library: (slice, text, spans as (kind, covered text))."""

CODE_SAMPLES = [
    ("python", "def add(a, b):\n    # sum, TODO tidy\n    return a + b  # '#'\n", [("comment", "# sum, TODO tidy"), ("comment", "# '#'")]),
    ("python", 'url = "http://x#y"\nname = r\'raw\'\n', [("literal", '"http://x#y"'), ("literal", "r'raw'")]),
    ("python", 'def f():\n    """Doc # no comment."""\n    return 1\n', [("literal", '"""Doc # no comment."""')]),
    ("java", 'class A { String u = "http://a/*b*/"; // end\n /* block\n two */ char c = \'"\'; }', [("literal", '"http://a/*b*/"'), ("comment", "// end"), ("comment", "/* block\n two */"), ("literal", "'\"'")]),
    ("go", "s := `raw // not\n comment`\n// yes\nr := 'x'\n", [("literal", "`raw // not\n comment`"), ("comment", "// yes"), ("literal", "'x'")]),
    ("ruby", "=begin\nblock\n=end\nputs 'a#b' # tail\n", [("comment", "=begin\nblock\n=end"), ("literal", "'a#b'"), ("comment", "# tail")]),
    ("rust", "fn f<'a>(x: &'a str) { let c = 'y'; /* n */ let r = r#\"raw \"q\" \"#; } // t", [("literal", "'y'"), ("comment", "/* n */"), ("literal", 'r#"raw "q" "#'), ("comment", "// t")]),
    ("html", '<!-- ad 3 --><p class="x">a &amp; b</p><script>var s = "</p>";</script>', [("comment", "<!-- ad 3 -->"), ("literal", '"x"'), ("literal", '"</p>"')]),
    ("prose", 'He said "well, no" and\nleft "open', [("literal", '"well, no"')]),
]
