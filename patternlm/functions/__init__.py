"""Driver-side and in-task building blocks: regular expressions, automata, tokenizers, numbers."""
