"""Training-data operators: ten corpus operations on the `documents`-like tables. Nothing outside imports this subpackage."""
