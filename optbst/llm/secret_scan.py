"""Secret scans with two character Markov models (DataFrame functions only).

Three base patterns are always applied. Beside them, long runs of token characters are scored with
the log-likelihood ratio of two first-order character models, one of random strings and one of
ordinary identifiers, both trained from labelled samples with a Spark aggregation. Runs that look
random enough become spans of kind ``markov``.

Scale: a single pass, nothing shuffled: positions come from the pieces between matches, and the model
(a square of the alphabet, 66 x 66 numbers, whatever the data) travels as an array literal. Each row
works with arrays of its own matches; places and overlaps come from running sums and maxima in
logarithmically many steps, so a text with n matches takes n log n, besides its length.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import two_columns

# The base patterns, the kinds in their order, the least lengths.
ASSIGN = r"""(?i)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]+"
HEX = r"[0-9a-f]{16,}"
KINDS = ("assign", "access", "hex", "markov")
LEAST = {"assign": 12, "access": 18, "hex": 16}
#: Characters of candidate runs for the Markov models, and how long a run is at least.
CANDIDATE, LEAST_RUN = r"[A-Za-z0-9+/_-]", 16
ALPHABET = "abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789+/_-"
#: Mean log-likelihood ratio for a character from which a run counts as random.
THRESHOLD = 0.2

#: Ordinary identifiers, label 0 of the training table.
IDENTIFIERS = """
accountBalance add_user_to_group allocation_count apply_transformation array_index authenticationManager average_response_time
background_color batch_size_limit buildConfiguration calculate_total_price callback_function categoryName check_permission
client_request_handler column_definition compareVersions computeChecksum connection_pool_size content_type_header convert_to_string
create_temporary_table currentTimestamp customer_address data-source-name database_connection default_configuration deleteRecursively
dependency-injection destination_directory display_name documentElement download_progress element_at_position emailAddress
enable_feature_flag environment_variable error_message_text event_listener execute_statement expected_result export_to_file
fetchAllResults file_system_watcher findByIdentifier formatDateTime generate_report getElementById global_settings handle_exception
hash_partitioning horizontal_alignment http_request_timeout identifier_list image-processing import_from_module initialize_session
input_validation insertBefore integration_tests intermediate_result invalidArgumentException iterate_over_items javascript_engine
keyboard_shortcuts language_model_training last_modified_date library/collections/ordered load_environment logging_configuration
machine_learning_pipeline maximum_connections measure_elapsed_time memory_allocation message_queue_consumer metadata_repository
network_interface notification_service number_of_partitions object_serialization onConfigurationChanged operating_system
optimization_level original_document output_directory parallel_execution parse_arguments performance_counter permission_denied
persistent_storage previous_iteration process_incoming_messages product_description query_optimizer random_number_generator
read_from_parquet recommended_settings redirect_to_login refresh_interval register_handler relational_algebra remove_duplicates
request_parameters resource_manager response_status_code retry_with_backoff return_value schedule_next_run search_results_page
security-policy-document select_all_columns serialize_to_json server_certificate setDefaultLocale shared_library shopping_cart_total
software_engineering source/main/resources standard_deviation start_transaction statistics_collector string_representation
structured_streaming_query subscription_plan summary_statistics synchronization_point table_of_contents temperature_sensor
template_renderer text_classification the_quick_brown_fox_jumps thread_pool_executor timestamp_with_timezone tokenizer_vocabulary
transaction_isolation_level transformation_matrix translation_service unexpected_end_of_input update_or_create user_interface_component
validateCredentials vertical_scrollbar virtual_machine_image visibility_timeout weighted_average_price window_functions
""".split()


def labelled_samples(spark: SparkSession, random_rows: int = 800, number_rows: int = 150) -> DataFrame:
    """The training table (sample, random): identifiers above, also in capitals, plain numbers, and random strings made by rule from digests."""
    digest = lambda name: F.unhex(F.sha2(F.concat(F.lit(name), F.col("id").cast("string")), 256))
    rule, coded = F.col("id") % 4, F.base64(digest("sample-"))
    plain = F.regexp_replace(coded, "[^A-Za-z0-9]", "")
    rand = F.when(rule == 0, F.substring(F.lower(F.hex(digest("sample-"))), 1, 40)).when(rule == 1, F.substring(coded, 1, 40)).when(rule == 2, F.substring(F.lower(plain), 1, 36)).otherwise(F.substring(F.upper(plain), 1, 36))
    rand = spark.range(random_rows).select(rand.alias("sample"), F.lit(True).alias("random"))
    numbers = spark.range(number_rows).select(F.substring(F.regexp_replace(F.hex(digest("number-")), "[A-F]", ""), 1, 20).alias("sample"), F.lit(False).alias("random"))
    names = [*IDENTIFIERS, *(w.upper() for w in IDENTIFIERS if "_" in w)]
    return spark.createDataFrame([(w, False) for w in names], "sample string, random boolean").unionByName(numbers).unionByName(rand)


def train_markov(samples: DataFrame, smoothing: float = 0.5) -> list[float]:
    """Log-likelihood ratios log P(next | char, random) - log P(next | char, identifier), row by row of the alphabet.

    Characters outside the alphabet break a sample. The result has len(ALPHABET)^2 numbers.
    """
    size = len(ALPHABET)
    chars = samples.where("sample IS NOT NULL AND random IS NOT NULL").select("random", F.split("sample", "").alias("c"))
    pairs = chars.select("random", F.explode(F.expr("transform(sequence(1, greatest(size(c) - 1, 1)), i -> struct(get(c, i - 1) AS a, get(c, i) AS b))")).alias("p"))
    place = lambda c: F.instr(F.lit(ALPHABET), c) - 1
    counts = pairs.where("p.a <> '' AND p.b <> ''").groupBy("random", place(F.col("p.a")).alias("a"), place(F.col("p.b")).alias("b")).agg(F.count(F.lit(1)).alias("n")).where("a >= 0 AND b >= 0").collect()
    seen = {label: [[0.0] * size for _ in range(size)] for label in (True, False)}
    for r in counts:
        seen[r["random"]][r["a"]][r["b"]] += r["n"]

    def model(label: bool) -> list[list[float]]:
        # A character without much history leans on how often the next one stands at all.
        single = [sum(row[b] for row in seen[label]) + 0.5 for b in range(size)]
        lean = [smoothing * size * x / sum(single) for x in single]
        return [[(row[b] + lean[b]) / (sum(row) + smoothing * size) for b in range(size)] for row in seen[label]]

    rand, plain = model(True), model(False)
    return [math.log(rand[a][b]) - math.log(plain[a][b]) for a in range(size) for b in range(size)]


def _running(values: str, merge: str) -> str:
    """SQL: running sums, maxima ... of the integer array in column ``values``, by SQL ``merge`` over ``x`` and an earlier place ``acc[..]``, written ``Y``.

    Each step merges places twice as far apart, so an array of n takes n log n; a fold that appended would copy what it has at every place.
    """
    merged = merge.replace("Y", "get(acc, i - shiftleft(1, s))")
    steps = f"sequence(0, cast(ceil(log2(size({values}))) AS int))"
    return f"IF(size({values}) < 2, {values}, aggregate({steps}, {values}, (acc, s) -> transform(acc, (x, i) -> IF(i >= shiftleft(1, s), {merged}, x))))"


def _with_spans(rows: DataFrame, patterns: dict[str, tuple[str, int, int]], text: str = "text") -> DataFrame:
    """``rows`` with a column of spans struct(start, kind, end, value) for each of ``patterns`` (pattern, group of the value, its least length).

    Spans are the leftmost matches that do not overlap; their places follow from the pieces between them.
    """
    columns = rows.columns
    found = []
    for name, (pattern, group, _) in patterns.items():
        found.append(F.regexp_extract_all(text, F.lit(pattern), F.lit(0)).alias(f"m_{name}"))
        if group:
            found.append(F.regexp_extract_all(text, F.lit(pattern), F.lit(group)).alias(f"v_{name}"))
        found.append(F.transform(F.split(text, pattern, -1), F.char_length).alias(f"g_{name}"))
    rows = rows.select(*columns, *found)
    rows = rows.select("*", *[F.expr(f"transform(m_{k}, (x, i) -> char_length(x) + get(g_{k}, i))").alias(f"step_{k}") for k in patterns])
    rows = rows.select("*", *[F.expr(_running(f"step_{k}", "x + Y")).alias(f"at_{k}") for k in patterns])
    spans = []
    for name, (_, group, least) in patterns.items():
        value = f"get(v_{name}, i)" if group else "x"
        one = f"struct(get(at_{name}, i) - char_length(x) AS start, {KINDS.index(name)} AS kind, get(at_{name}, i) AS `end`, {value} AS value)"
        spans.append(F.expr(f"filter(transform(m_{name}, (x, i) -> {one}), s -> char_length(s.value) >= {least})").alias(name))
    return rows.select(*columns, *spans)


def _without_overlap(rows: DataFrame, spans: str, others: str) -> DataFrame:
    """``rows`` with ``spans`` only where no span of ``others`` has a character in common with it, from one sort of both."""
    both = f"concat(transform({others}, b -> struct(b.start AS start, b.`end` AS `end`, -1 AS n)), transform({spans}, (r, i) -> struct(r.start AS start, r.`end` AS `end`, i AS n)))"
    columns = rows.columns
    rows = rows.select("*", F.expr(f"IF(size({others}) = 0 OR size({spans}) = 0, cast(array() AS array<struct<start: int, `end`: int, n: int>>), array_sort({both}))").alias("both_"))
    rows = rows.select("*", F.expr("transform(both_, x -> IF(x.n < 0, x.`end`, -1))").alias("ends_"), F.expr("reverse(transform(both_, x -> IF(x.n < 0, x.start, 2147483647)))").alias("starts_"))
    # The latest end of another span so far, and the first start of one from here on.
    rows = rows.select("*", F.expr(_running("ends_", "greatest(x, Y)")).alias("before_"), F.expr(_running("starts_", "least(x, Y)")).alias("after_"))
    free = f"transform(filter(transform(both_, (x, i) -> IF(x.n >= 0 AND get(before_, i) <= x.start AND get(after_, size(after_) - 1 - i) >= x.`end`, x.n, -1)), n -> n >= 0), n -> get({spans}, n))"
    own = F.expr(f"IF(size(both_) = 0, {spans}, {free})").alias(spans)
    return rows.select(*[c for c in columns if c != spans], own)


def _spelled(spans: Column) -> Column:
    names = F.array(*[F.lit(k) for k in KINDS])
    one = lambda s: F.concat_ws(":", F.get(names, s["kind"]), s["start"].cast("string"), s["end"].cast("string"))
    return F.concat_ws(",", F.transform(F.array_sort(spans), one))


def mean_ratio(token: Column, ratios: list[float]) -> Column:
    """Mean log-likelihood ratio over neighbouring characters of a token of the alphabet."""
    table = F.expr("array(" + ",".join(f"{x!r}D" for x in ratios) + ")")
    size = len(ALPHABET)
    codes = F.transform(F.split(token, ""), lambda c: F.instr(F.lit(ALPHABET), c) - 1)
    total = F.aggregate(
        codes,
        F.struct(F.lit(-1).alias("prev"), F.lit(0.0).alias("sum")),
        lambda acc, c: F.when(c < 0, acc).otherwise(F.struct(c.alias("prev"), F.when(acc["prev"] < 0, acc["sum"]).otherwise(acc["sum"] + F.get(table, acc["prev"] * size + c)).alias("sum"))),
        lambda acc: acc["sum"],
    )
    return total / F.greatest(F.char_length(token) - 1, F.lit(1))


def secret_scan(docs: DataFrame, key: str = "doc_id", text: str = "text", ratios: list[float] | None = None, threshold: float = THRESHOLD, least_run: int = LEAST_RUN) -> DataFrame:
    """One row per input row: doc_id, n_assign, n_access, n_hex, n_markov, base_sha256, spans, secrets.

    Spans are ``kind:start:end`` in code points, by start and then kind. ``base_sha256`` digests the
    base spans only. A Markov span is a run of at least ``least_run`` token characters whose mean ratio is
    at least ``threshold`` and that has no character in common with a base span. ``secrets`` holds the matched values with their
    spans. Null and empty texts have no span. Repeated rows are scanned alike, empty tables give none.
    """
    spark = docs.sparkSession
    ratios = train_markov(labelled_samples(spark)) if ratios is None else ratios
    base = two_columns(docs, key, text)
    rows = _with_spans(base, {"assign": (ASSIGN, 2, LEAST["assign"]), "access": (ACCESS, 0, LEAST["access"]), "hex": (HEX, 0, LEAST["hex"]), "markov": (f"{CANDIDATE}{{{least_run},}}", 0, least_run)})
    rows = _without_overlap(rows.drop("text").select("*", F.concat("assign", "access", "hex").alias("base")), "markov", "base")
    rows = rows.select(*[c for c in rows.columns if c != "markov"], F.filter("markov", lambda s: mean_ratio(s["value"], ratios) >= threshold).alias("markov"))
    every = F.concat("base", "markov")
    return rows.select(
        "doc_id",
        F.size("assign").cast("long").alias("n_assign"),
        F.size("access").cast("long").alias("n_access"),
        F.size("hex").cast("long").alias("n_hex"),
        F.size("markov").cast("long").alias("n_markov"),
        F.sha2(_spelled(F.col("base")).cast("binary"), 256).alias("base_sha256"),
        _spelled(every).alias("spans"),
        F.array_sort(every).alias("secrets"),
    )
