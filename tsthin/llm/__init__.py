"""Training-data operators: near-duplicate search, tokenising, decontamination, secrets, chat, language, URLs.

Nothing else in the package imports this subpackage; ``__spark_entry__`` adds its queries when it can be imported.
"""
