"""Training-data operators over a `documents(doc_id, text, ...)` table.

Nothing outside this subpackage imports it. Conventions shared by every operator:
a null text counts as the empty text unless the docstring says otherwise, only the
named columns are read (so extra columns with any name are harmless), repeated rows
are processed row by row, and an empty table gives an empty result of the same schema.
"""
