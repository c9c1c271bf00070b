"""MathML to LaTeX by a rule for each element."""

from __future__ import annotations

# Operators and letters that have a command.
COMMANDS = {
    "×": r"\times ", "÷": r"\div ", "±": r"\pm ", "∓": r"\mp ", "≤": r"\leq ", "≥": r"\geq ", "≠": r"\neq ", "≈": r"\approx ", "≡": r"\equiv ", "∞": r"\infty ", "∑": r"\sum ", "∏": r"\prod ", "∫": r"\int ", "√": r"\sqrt ",
    "→": r"\rightarrow ", "⇒": r"\Rightarrow ", "∂": r"\partial ", "∇": r"\nabla ", "∈": r"\in ", "∉": r"\notin ", "∪": r"\cup ", "∩": r"\cap ", "⊂": r"\subset ", "⊆": r"\subseteq ", "∀": r"\forall ", "∃": r"\exists ", "·": r"\cdot ", "⋅": r"\cdot ",
    "α": r"\alpha ", "β": r"\beta ", "γ": r"\gamma ", "δ": r"\delta ", "ε": r"\epsilon ", "θ": r"\theta ", "λ": r"\lambda ", "μ": r"\mu ", "π": r"\pi ", "ρ": r"\rho ", "σ": r"\sigma ", "τ": r"\tau ", "φ": r"\phi ", "ψ": r"\psi ", "ω": r"\omega ", "Γ": r"\Gamma ", "Δ": r"\Delta ", "Σ": r"\Sigma ", "Ω": r"\Omega ",
}
ACCENTS = {"^": r"\hat", "¯": r"\bar", "‾": r"\overline", "→": r"\vec", "~": r"\tilde", "˙": r"\dot", "_": r"\underline"}


def _text(node) -> str:
    return "".join(c if isinstance(c, str) else _text(c) for c in node.children).strip()


def _mapped(s: str) -> str:
    return "".join(COMMANDS.get(c, c) for c in s)


def convert(node) -> str:
    """LaTeX of an element tree (objects with tag, attrs and children). Unknown elements give their children."""
    kids = [c for c in node.children if not isinstance(c, str)]
    part = [convert(k) for k in kids]
    at = lambda i: part[i] if i < len(part) else ""
    tag = node.tag
    if tag == "mi":
        t = _text(node)
        return _mapped(t) if len(t) <= 1 else rf"\mathrm{{{t}}}"
    if tag in ("mo", "mn"):
        return _mapped(_text(node))
    if tag == "mtext":
        return rf"\text{{{_text(node)}}}"
    if tag == "ms":
        return rf"\text{{``{_text(node)}''}}"
    if tag == "mspace":
        return r"\ "
    if tag == "mfrac":
        return rf"\frac{{{at(0)}}}{{{at(1)}}}"
    if tag == "msup":
        return f"{{{at(0)}}}^{{{at(1)}}}"
    if tag == "msub":
        return f"{{{at(0)}}}_{{{at(1)}}}"
    if tag in ("msubsup", "munderover"):
        return f"{{{at(0)}}}_{{{at(1)}}}^{{{at(2)}}}" if tag == "msubsup" else f"{at(0).strip()}_{{{at(1)}}}^{{{at(2)}}}"
    if tag == "msqrt":
        return rf"\sqrt{{{''.join(part)}}}"
    if tag == "mroot":
        return rf"\sqrt[{at(1)}]{{{at(0)}}}"
    if tag in ("mover", "munder"):
        mark = _text(kids[1]) if len(kids) > 1 else ""
        if mark in ACCENTS:
            return f"{ACCENTS[mark]}{{{at(0)}}}"
        return f"{at(0).strip()}{'^' if tag == 'mover' else '_'}{{{at(1)}}}"
    if tag == "mfenced":
        marks = (node.attrs.get("separators") or ",").strip() or ","
        inner = part[0] if part else ""
        for i, p in enumerate(part[1:]):
            inner += marks[min(i, len(marks) - 1)] + p
        return rf"\left{node.attrs.get('open') or '('}{inner}\right{node.attrs.get('close') or ')'}"
    if tag == "mtable":
        return r"\begin{matrix} " + r" \\ ".join(part) + r" \end{matrix}"
    if tag == "mtr":
        return " & ".join(part)
    if tag in ("annotation", "annotation-xml"):
        return ""
    return "".join(part) if kids else _mapped(_text(node))
