"""wordlid: word-level language tagging of code-mixed text, as DataFrame plans."""
