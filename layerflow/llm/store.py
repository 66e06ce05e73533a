"""The engine's tables between steps, for the operators here."""

from layerflow.store import delete, discard, names, new_path, read_text, release, text_batches, until_exit, write_text, written

__all__ = ["delete", "discard", "names", "new_path", "read_text", "release", "text_batches", "until_exit", "write_text", "written"]
