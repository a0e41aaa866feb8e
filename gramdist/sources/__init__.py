"""Where strings, grammars and repositories come from and go to."""
