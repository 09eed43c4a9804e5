"""Operations on training text: ten operators, each in a module of its own."""
