"""Training-data operators (toxicity to language ID). Nothing outside this subpackage imports it."""
