"""Reading documents and matrices."""

from .read import load_table, read_coo, read_docs, read_libsvm, register_coo_source
from .write import load_fit, load_matrix, save_fit, save_matrix

__all__ = ["load_fit", "load_matrix", "load_table", "read_coo", "read_docs", "read_libsvm", "register_coo_source", "save_fit", "save_matrix"]
