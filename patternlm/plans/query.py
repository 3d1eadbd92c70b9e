"""The query object."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from patternlm.functions import automata as fa
from patternlm.functions.regex import ALPHABET


@dataclass(frozen=True)
class Rules:
    """Decision rules on body tokens; ranks are over the whole vocabulary at the context, ties by token id."""

    top_k: int | None = None
    top_p: float | None = None
    temperature: float = 1.0


@dataclass(frozen=True)
class Preprocessor:
    """edits(d, scope), exclude(words), erase(words), synonyms(classes), transducer(arcs, finals). deferred exclude filters results."""

    kind: str
    args: dict = field(default_factory=dict)
    deferred: bool = False


def edits(d: int = 1, alphabet: str = ALPHABET, scope: str = "both") -> Preprocessor:
    return Preprocessor("edits", {"d": d, "alphabet": alphabet, "scope": scope})


def exclude(words, deferred: bool = False) -> Preprocessor:
    return Preprocessor("exclude", {"words": tuple(words)}, deferred)


def erase(words) -> Preprocessor:
    return Preprocessor("erase", {"words": tuple(words)})


def synonyms(classes: dict[str, list[str]], alphabet: str = ALPHABET) -> Preprocessor:
    return Preprocessor("synonyms", {"classes": classes, "alphabet": alphabet})


def transducer(arcs, finals) -> Preprocessor:
    return Preprocessor("transducer", {"arcs": tuple(arcs), "finals": frozenset(finals)})


@dataclass(frozen=True)
class PatternQuery:
    """A pattern (regular prefix and body), decision rules, a traversal and preprocessors, applied in order."""

    body: str
    prefix: str = ""
    encoding: str = "canonical"  # or "all"
    rules: Rules = Rules()
    traversal: str = "best"  # or "sample"
    preprocessors: tuple[Preprocessor, ...] = ()
    require_eos: bool = False
    max_tokens: int = 64
    prefix_order: str = "model"  # or "zero"
    seal_boundary: bool = False
    seed: int = 42
    alphabet: str = ALPHABET

    def but(self, **changes) -> PatternQuery:
        return replace(self, **changes)

    def automaton(self, lazy: bool = False) -> fa.Dfa | fa.LazyDfa:
        """The character automaton after all preprocessors that are not deferred. lazy: its states may be made as they are read, where the last step is edits."""
        dfa = fa.compile_regex(self.body, self.prefix, self.alphabet)
        for p in self.preprocessors:
            if p.kind == "edits":
                dfa = fa.edited(dfa, **p.args, lazy=lazy and p is self.preprocessors[-1])
            elif p.kind == "exclude" and not p.deferred:
                dfa = fa.difference(dfa, fa.words_dfa(p.args["words"]))
            elif p.kind == "erase":
                dfa = fa.erased(dfa, p.args["words"])
            elif p.kind == "synonyms":
                dfa = fa.transduced(dfa, *fa.synonym_arcs(p.args["classes"], p.args["alphabet"]))
            elif p.kind == "transducer":
                dfa = fa.transduced(dfa, list(p.args["arcs"]), set(p.args["finals"]))
        return dfa

    @property
    def deferred_words(self) -> frozenset[str]:
        return frozenset(w for p in self.preprocessors if p.kind == "exclude" and p.deferred for w in p.args["words"])
