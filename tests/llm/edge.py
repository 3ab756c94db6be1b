"""Small tables with the awkward rows that every operator must take."""

TEXTS = [None, "", " ", "same text here again and again", "same text here again and again", "x" * 70_000, "line one\nline two\nline one\n" * 40, "Ünïcödé 日本 ١٢٣ 😀", "a b c d e f g h i j k l m n o p"]


def documents(spark, texts=TEXTS):
    rows = [(i, t, "en" if i % 2 else None, None if i == 3 else f"src{i % 3}", None, i, "clash") for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, n_tokens long, chunk string")


def tables(spark, folder, texts=TEXTS):
    documents(spark, texts).coalesce(2).write.mode("overwrite").parquet(f"{folder}/documents.parquet")
    return str(folder)
