"""Reading and writing grammars."""
