"""Operations on training text. Nothing else in the library imports this subpackage."""
