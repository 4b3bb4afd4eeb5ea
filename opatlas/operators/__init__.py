"""The methods: statements, vectors, embeddings, clusters, pairs, frequent sets, labels, votes, scores, serving."""
