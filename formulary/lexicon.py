"""Word lists, patterns and cuts of the corpus methods. Lists that aren't published are version 1 of our own."""

# The ten literals of the keyword gate, case-sensitive.
MATH_KEYWORDS = ("MathJax", "mathjax", "<math", "math-container", "katex.min.css", "latex.php", "codecogs", "tex.cgi", 'class="tex"', "class='tex'")

# Cuts.
PREFILTER_CUT = 0.8
CUT_WITH_TEX = 0.17
CUT_WITHOUT_TEX = 0.8
RARELY_USEFUL = 0.2
MAX_PERPLEXITY = 15_000.0
SIMILARITY = 0.7
CLUSTERS, MEMBERS, VOTES = 128, 5, 16

COMMANDS = tuple(
    "frac sqrt sum int prod lim infty alpha beta gamma delta epsilon varepsilon theta lambda mu nu pi rho sigma tau phi varphi psi omega eta zeta xi chi kappa "
    "Gamma Delta Theta Lambda Sigma Phi Psi Omega Pi partial nabla cdot cdots ldots dots times div pm mp leq le geq ge neq ne approx equiv sim "
    "in notin subset subseteq cup cap setminus emptyset forall exists to rightarrow leftarrow Rightarrow Leftrightarrow implies mathbb "
    "mathbf mathcal mathrm text left right begin end overline sin cos tan log ln exp max min sup hat bar vec tilde dot binom quad".split()
)
COMMAND_PATTERN = r"\\[A-Za-z]+"

PHRASES = ("all rights reserved", "cookie", "privacy policy", "terms of use", "log in", "sign up", "subscribe", "share this", "powered by", "previous post", "next post", "reply", "report", "posted by", "license", "copyright")
BLOCKED = ("ad", "ads", "advert", "sidebar", "comments", "cookie-banner", "footer", "share", "related", "breadcrumb")
MATH_WORDS = ("theorem", "proof", "equation", "integral", "polynomial", "matrix", "algebra", "derivative", "function", "lemma", "vector", "probability", "root", "field", "prove")
STOP_WORDS = {
    "en": ("the", "of", "and", "to", "in", "is", "that", "for", "it", "as", "with", "was", "on", "by", "this"),
    "fr": ("le", "la", "les", "et", "des", "un", "une", "est", "pas", "que", "de", "du", "aux", "il"),
    "de": ("der", "die", "das", "und", "ein", "zu", "den", "von", "nicht", "sich", "mit", "des", "auf"),
    "es": ("el", "los", "las", "y", "que", "por", "una", "con", "del", "se", "de", "como", "su"),
}
SPAM_HOSTS = ("cheap-pills", "casino-win", "free-bets", "adult-x", "spam-farm", "ads-track")
TRACKING = ("utm_source", "utm_medium", "utm_campaign", "ref", "fbclid")

# Encodings of mathematics that one pattern finds: name -> (pattern, group). Used by Spark and by the SQL twins alike.
ENCODINGS = {
    "display": (r"(?s)\$\$([^$]+)\$\$", 1),
    "bracket": (r"(?s)\\[(\[](.+?)\\[)\]]", 1),
    "image_url": (r"<img[^>]*src=\"[^\"]*codecogs\.com[^\"?]*\?([^\"]+)\"", 1),
    "image_alt": (r"<img[^>]*alt=\"([^\"]*\\[A-Za-z][^\"]*)\"", 1),
    "container": (r"(?s)<span class=\"math-container\">(.*?)</span>", 1),
    "annotation": (r"(?s)<annotation encoding=\"application/x-tex\">(.*?)</annotation>", 1),
    "tag": (r"(?s)<mathjax>(.*?)</mathjax>", 1),
    "align": (r"(?s)\\begin\{align\*?\}(.*?)\\end\{align\*?\}", 1),
    "equation": (r"(?s)\\begin\{equation\*?\}(.*?)\\end\{equation\*?\}", 1),
    "script": (r"(?s)<script type=\"math/[^\"]*\">(.*?)</script>", 1),
    "alttext": (r"<math[^>]*alttext=\"([^\"]*)\"", 1),
    "tex_class": (r"(?s)<span class=\"tex\">(.*?)</span>", 1),
    "plugin_image": (r"latex\.php\?latex=([^\"&]+)", 1),
    "plugin_code": (r"\$latex ([^$]+)\$", 1),
    "mathml": (r"(?s)(<math>.*?</math>)", 1),
}
INLINE_PATTERN = r"\$([^$\n]+)\$"
DISPLAY_STRIP = r"(?s)\$\$[^$]+\$\$"


def sql_quote(text: str) -> str:
    return "'" + text.replace("'", "''") + "'"
