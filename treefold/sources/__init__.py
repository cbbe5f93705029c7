"""Tables, tree builders, readers and writers."""

from .files import read_tree, write
from .generator import generate, register_generator
from .trees import BUILDERS, load, tree

__all__ = ["BUILDERS", "generate", "load", "read_tree", "register_generator", "tree", "write"]
