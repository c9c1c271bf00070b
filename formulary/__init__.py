"""Methods for building a web corpus of mathematical text, as DataFrame plans."""
