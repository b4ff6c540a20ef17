"""corpusmill: turn raw web pages and crawl text into curated training corpora with Spark."""
