"""The corpus operators are a leaf: the rest of the library stands without them."""

import ast
from pathlib import Path

import sqltutor

ROOT = Path(sqltutor.__file__).parent


def test_nothing_imports_the_corpus_operators():
    for file in ROOT.rglob("*.py"):
        if "llm" in file.relative_to(ROOT).parts:
            continue
        for node in ast.walk(ast.parse(file.read_text())):
            names = [a.name for a in node.names] if isinstance(node, ast.Import) else [node.module or "", *[a.name for a in node.names]] if isinstance(node, ast.ImportFrom) else []
            assert not any("llm" in n.split(".") for n in names), (file, names)
