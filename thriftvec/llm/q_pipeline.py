"""The five-stage pipeline of corpus_pipeline.py."""

NAME = "pipeline"


def query(spark, sf_dir):
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)
