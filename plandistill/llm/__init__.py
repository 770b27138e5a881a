"""Operations of a training-data pipeline over documents, pages, vectors and chats.

Nothing outside this subpackage imports it; ``__spark_entry__`` adds its
queries only when the folder is present.
"""
